"""Every operator on small tables: brute force where SQL has no form, and nulls, empty texts, repeats, empty tables and clashing columns."""

import io
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathq.llm import coder, html, language, licenses, mixing, near_dedup, packing, search, shingles, tokens, vectors, warc
from pathq.llm.graph import components, forest
from pathq.llm.common import Workspace, prefilter

DOCS = "doc_id long, text string, lang string, source string, n_chars long, block string, bucket string"


def docs_of(spark, rows):
    """(id, text) rows as documents, with columns whose names clash with those that operators add."""
    return spark.createDataFrame([(i, t, "en", f"s{(i or 0) % 3}", len(t or ""), "x", "y") for i, t in rows], DOCS)


ODD = [(1, "a b c d e f"), (2, None), (3, ""), (4, "   \n"), (5, "a b c d e f"), (5, "a b c d e f"), (None, "null id here with words"), (6, "w " * 30_000), (7, "!!! ???")]


# --- packing -------------------------------------------------------------------------------------------------------


def best_padding(bins, k):
    """Least padding by trying every set of boundaries."""
    from itertools import combinations

    lens = [b.longest for b in bins]
    best = math.inf
    for r in range(min(k, len(bins))):
        for cuts in combinations(lens[:-1], r):
            best = min(best, packing.padding_of(bins, [*cuts, lens[-1]]))
    return best


@pytest.mark.parametrize("seed", range(25))
def test_boundaries_are_optimal(seed):
    rng = random.Random(seed)
    bins = [packing.Bin(n, c := rng.randint(1, 9), n * c) for n in sorted(rng.sample(range(0, 60), rng.randint(1, 9)))]
    for k in (1, 2, 3, 4, 20):
        assert packing.padding_of(bins, packing.boundaries(bins, k)) == best_padding(bins, k)


def test_packing(spark):
    rng = random.Random(3)
    rows = [(i, "w " * rng.choice([1, 2, 3, 30, 31, 200])) for i in range(400)] + ODD
    out = packing.pack(docs_of(spark, rows), n_buckets=4, token_budget=100, rows_a_chunk=50).collect()
    assert Counter(r["doc_id"] for r in out) == Counter(i for i, _ in rows)
    batches = {}
    for r in out:
        assert r["n_tokens"] <= r["bucket_len"] and r["padding"] == r["bucket_len"] - r["n_tokens"]
        batches.setdefault((r["bucket"], r["batch"]), []).append(r)
    for own in batches.values():
        assert sorted(r["slot"] for r in own) == list(range(len(own)))
        assert len(own) == 1 or sum(r["bucket_len"] for r in own) <= 100
    for b in {r["bucket"] for r in out}:  # only the last batch of a bucket may be short
        sizes = [len(batches[b, k]) for k in sorted(k for x, k in batches if x == b)]
        assert all(s == sizes[0] for s in sizes[:-1])
    assert packing.pack(docs_of(spark, [])).count() == 0


# --- mixing --------------------------------------------------------------------------------------------------------


def test_exponent_and_weights(spark):
    totals = spark.createDataFrame([("a", 900, 9), ("b", 90, 5), ("c", 10, 1), (None, 0, 2)], "source string, tokens long, docs long")
    for share in (0.5, 0.8, 0.97):
        alpha = mixing.exponent(totals, 1000.0, target_entropy=share)
        w = [r["weight"] for r in mixing.weights(totals, alpha).collect() if r["weight"] > 0]
        assert abs(sum(w) - 1) < 1e-9
        assert abs(-sum(x * math.log(x) for x in w) / math.log(3) - share) < 1e-6
    alpha = mixing.exponent(totals, 1000.0, max_repeats=5.0)
    assert abs(max(r["weight"] * 1000 / r["tokens"] for r in mixing.weights(totals, alpha).collect() if r["tokens"]) - 5) < 1e-6
    assert mixing.exponent(totals.filter("source = 'a'"), 1000.0, 0.5) == 1.0


def test_mixing_meets_budget(spark):
    rng = random.Random(4)
    rows = [(i, "w " * rng.randint(1, 40), "en", "big" if i % 10 else f"small{i % 3}", 0, "x", "y") for i in range(1500)]
    df = spark.createDataFrame(rows, DOCS)
    out = mixing.mix(df, target_entropy=0.9, max_repeats=4.0, block_tokens=300).collect()
    total = sum(t.count("w") for _, t, *_ in rows)
    by, weight = Counter(), {}
    for r in out:
        by[r["source"]] += r["n_tokens"]
        weight[r["source"]] = r["weight"]
    for s, w in weight.items():
        assert w * total - 40 <= by[s] <= w * total + 1e-6  # one document at the edge may not fit
    own = Counter(t[3] for t in rows)
    times = Counter((r["source"], r["doc_id"]) for r in out)
    for s in weight:
        counts = [n for (x, _), n in times.items() if x == s] + [0] * (own[s] - sum(x == s for x, _ in times))
        assert max(counts) - min(counts) <= 1  # whole epochs, then part of one
        assert max(counts) <= 4
    assert mixing.mix(docs_of(spark, [])).count() == 0
    odd = mixing.mix(docs_of(spark, ODD), target_entropy=None)
    assert odd.count() == len(ODD) and set(docs_of(spark, []).columns) <= set(odd.columns)


# --- licenses ------------------------------------------------------------------------------------------------------


def test_licenses(spark):
    mit = licenses.LICENSES[0].text
    words = mit.split()
    rows = [
        (1, "x CC-BY y cc by"), (2, f"start {mit.upper()} end"), (3, " ".join([*words[:8], "oddly", *words[8:]])), (4, "all rights  Reserved, all rights reserved"),
        (5, "General Public\nLicense"), (6, "permission is hereby granted"), (8, "cc é by"), (9, None), (9, "cc by"), (10, "İ cc by K"),
    ]
    got = {(r["doc_id"], r["n_words"]): r for r in licenses.scan(spark, docs_of(spark, rows)).collect()}
    assert (got[1, 6]["n_base"], got[1, 6]["first_word"], got[1, 6]["last_word"], got[1, 6]["base_labels"]) == (2, 1, 4, "cc-by")
    assert got[2, len(words) + 2]["labels"] == "mit" and got[2, len(words) + 2]["score"] == 1.0
    assert got[3, len(words) + 1]["labels"] == "mit"  # an inserted word splits the diagonal; neighbours merge
    assert got[4, 6]["n_base"] == 2 and got[5, 3]["base_labels"] == "gpl" and got[6, 4]["labels"] == ""
    assert got[8, 3]["n_base"] == 0 and got[9, 0]["first_word"] is None and got[9, 2]["n_base"] == 1 and got[10, 4]["n_base"] == 1
    out = licenses.scan(spark, docs_of(spark, ODD)).collect()
    assert len(out) == len(ODD) and licenses.scan(spark, docs_of(spark, [])).count() == 0
    plan = licenses.scan(spark, docs_of(spark, rows))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


# --- html ----------------------------------------------------------------------------------------------------------

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p><p>no</p>";</script></head><body class="page">
<header><a href="/">Site</a></header><nav><ul><li><a href=x>Home</a></li></ul></nav><div class="cookie-notice">We use cookies to improve this site.</div>
<main><article><h1>Title &amp; more</h1><p>First <b>bold
   text</b> here.<p>Second &lt;one&gt;.<br>line</p><ul><li>item</ul><!-- hidden <p>x</p> --><section id="comments"><p>I do not agree at all with this.</p></section></article></main>
<aside><p>Another sidebar story with quite a few words in it.</p></aside><div class="ad">Buy now</div><form><p>Your name</p></form><footer>&copy; Site</footer></body></html>"""


def test_html(spark):
    assert html.main_text(PAGE) == "Title & more\n\nFirst bold text here.\n\nSecond <one>. line\n\nitem"
    assert html.main_text(None) == html.main_text("") == html.main_text("<nav>x</nav><script>never closed <p>") == ""
    assert html.main_text("plain text, no tags at all.") == "plain text, no tags at all."
    rows = [(1, "u", PAGE), (1, "u", PAGE), (None, None, None), (2, None, "<p>" + "long words " * 50_000)]
    out = html.extract(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit(1))).collect()
    assert len(out) == 4 and out[0]["text"] == out[1]["text"] and out[2]["n_chars"] == 0 and all(r["n_chars"] == len(r["text"]) for r in out)


@pytest.mark.parametrize("seed", range(40))
def test_cut_is_minimal(seed):
    rng = random.Random(seed)
    n = rng.randint(1, 9)
    terminal = [rng.uniform(-2, 2) for _ in range(n)]
    edges = [(rng.randrange(n), rng.randrange(n), rng.uniform(0, 1.5)) for _ in range(rng.randint(0, 14))]

    def cost(side):
        out = sum(max(t, 0) if not s else max(-t, 0) for t, s in zip(terminal, side, strict=True))
        return out + sum(c for a, b, c in edges if side[a] != side[b])

    best = min(cost([bool(m >> i & 1) for i in range(n)]) for m in range(1 << n))
    assert abs(cost(html.cut(terminal, edges)) - best) < 1e-9


# --- token ids -----------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("n,block,vocabulary", [(0, 8, 100), (1, 8, 2), (100, 16, 50_257), (5000, 256, 1 << 20), (3000, 4096, 300)])
def test_coder_round_trip(n, block, vocabulary):
    rng = np.random.default_rng(n)
    ids = np.minimum(rng.zipf(1.4, n), vocabulary - 1).astype(np.int64)
    parts = coder.encode_blocks(ids, block, vocabulary)
    lengths = [min(block, n - i * block) for i in range(len(parts))]
    back = coder.decode_blocks(parts, lengths, vocabulary)
    assert (np.concatenate(back) if back else np.empty(0)).tolist() == ids.tolist()
    if len(parts) > 1:  # a block is decoded alone
        assert coder.decode_blocks([parts[1]], [lengths[1]], vocabulary)[0].tolist() == back[1].tolist()


def test_repeats_compress():
    ids = np.tile(np.random.default_rng(0).integers(0, 50_000, 40), 100)
    assert sum(map(len, coder.encode_blocks(ids, 4096, 50_257))) < len(ids) * 0.25


def test_damage_is_found():
    out = io.BytesIO()
    out.close, w = lambda: None, None
    w = tokens.FileWriter(out, 50_257, 64, 4)
    w.add(1, np.arange(500, dtype=np.uint32))
    w.close()
    data = bytearray(out.getvalue())
    assert [(d, x.tolist()) for d, x in tokens.read_file(io.BytesIO(bytes(data)))] == [(1, list(range(500)))]
    data[60] ^= 255
    with pytest.raises(ValueError):
        list(tokens.read_file(io.BytesIO(bytes(data))))


def test_token_files(spark):
    from tokenizers import Tokenizer

    path = tokens.default_tokenizer()
    t = Tokenizer.from_file(path)
    rows = [*ODD, (8, "naïve  café 😀\r\n\ttab"), (9, "a <|endoftext|> x"), (-3, "negative id"), (10, "b<|endoftext|>"), (1 << 62, "far"), (-(1 << 62), "far below")]
    manifest, folder = tokens.write(docs_of(spark, rows), path, block=64, lanes=4, range_bytes=40)
    got = sorted(tokens.read(manifest, folder, lanes=3).collect(), key=lambda r: r["start"])
    key = lambda i: (i is not None, i)
    assert [key(r["doc_id"]) for r in got] == sorted(key(i) for i, _ in rows)
    start, expected = 0, {}
    for i, text in rows:
        expected[i] = t.encode(text or "", add_special_tokens=False).ids + [0]
    for r in got:
        assert r["start"] == start and list(r["ids"]) == expected[r["doc_id"]] and r["n_tokens"] == len(r["ids"])
        start += r["n_tokens"]
    digest = {r["doc_id"]: r["ids_crc32"] for r in tokens.read(manifest, folder, digest=True).collect()}
    assert digest[8] == zlib.crc32(np.array(expected[8], "<u4").tobytes())
    manifest, folder = tokens.write(docs_of(spark, []), path)
    assert tokens.read(manifest, folder).count() == 0


def test_pieces_give_the_ids_of_whole_texts():
    """Cuts are only where the library's pre-tokenizer parts texts, whatever stands beside them, and the memo may be small."""
    from tokenizers import Tokenizer

    path, rng = tokens.default_tokenizer(), random.Random(5)
    library = Tokenizer.from_file(path)
    signs = ["a", "the", "é", "ß", "×", "3", "²", "'", "'s", "’", "…", ".", ",", "!", ":", " ", " ", " ", "\n", "\n", "\r", "\t", "\x1c", "\x85", "\xa0", "\u180e", "\u2003", "\u200b", "\u3000", "\ufeff", "ж", "日", "😀", "\u0301", "<|endoftext|>", "_", "\x00"]
    for most in (10, 600_000):
        own = tokens.Tokens(path, most=most)
        for _ in range(6):
            texts = ["".join(rng.choices(signs, k=rng.randint(0, 30))) for _ in range(300)] + [None, "", "x" * 200 + " y"]
            for text, ids in zip(texts, own.batch(texts), strict=True):
                assert ids.tolist() == library.encode(text or "", add_special_tokens=False).ids, text
    data = "Così disse.\nThe end, the end.".encode()
    at = tokens.cuts(data := np.frombuffer(data, np.uint8), np.array([0, len(data)])).tolist()
    pieces = [data[i:j].tobytes().decode() for i, j in zip(at[:-1], at[1:], strict=True)]
    assert pieces == ["Così", " disse", ".", "\n", "The", " end", ",", " the", " end", "."]  # " end" is encoded once


@pytest.mark.parametrize("top", [300, 1 << 20])
def test_pairs_of_ids(top):
    """Frequent pairs are one symbol, so that the coder makes about half as many steps; rare ones are spelled."""
    rng = np.random.default_rng(top)
    for n in (0, 1, 2, 7, 4001):
        ids = np.minimum(rng.zipf(1.5, n), top - 1)
        for most in (1 << 19, 3):
            symbols, alphabet = coder.paired(ids, most)
            assert coder.unpaired(symbols, alphabet).tolist() == ids.tolist() and np.all(np.diff(np.bincount(symbols, minlength=len(alphabet))) <= 0)
    ids = np.tile(rng.integers(0, top, 40), 100)
    symbols, alphabet = coder.paired(ids)
    assert len(symbols) == 2000 and len(alphabet) == 20 and sum(map(len, coder.encode_blocks(symbols, 4096, 20))) < 300


def test_damaged_alphabet_is_found():
    out = io.BytesIO()
    out.close = lambda: None
    w = tokens.FileWriter(out, 50_257, 64, 4)
    w.add(1, np.arange(2000, dtype=np.uint32))
    w.close()
    data = out.getvalue()
    assert [x.tolist() for _, x in tokens.read_file(io.BytesIO(data), lanes=3)] == [list(range(2000))]
    for at in range(tokens.HEAD.size + tokens.GROUP.size, tokens.HEAD.size + tokens.GROUP.size + 40):
        broken = bytearray(data)
        broken[at] ^= 255
        with pytest.raises(ValueError):
            list(tokens.read_file(io.BytesIO(bytes(broken))))


def test_rows_keep_their_ranges():
    """Texts are grouped across Arrow batches; each row keeps its own range and id."""
    import pyarrow as pa

    batches = [pa.RecordBatch.from_pydict({"range": pa.array([i, i], pa.int32()), "doc_id": [10 * i, 10 * i + 1], "text": ["a b", None if i % 2 else "c" * 9]}) for i in range(7)]
    for most in (1, 12, 1 << 20):
        got = list(tokens._encoded(iter(batches), tokens.tokens(tokens.default_tokenizer()), most))
        assert [(r, d) for r, d, _ in got] == [(i, 10 * i + k) for i in range(7) for k in (0, 1)] and all(len(x) == 2 for _, d, x in got if d % 10 == 0)


# --- WARC ----------------------------------------------------------------------------------------------------------


def test_warc(spark):
    big = "<p>é" + "same payload " * 200
    rows = [(i, f"http://x/{i}\r\nbad", big) for i in (3, 7, 5)] + [(7, "http://x/7", big), (None, None, big), (8, None, None), (9, "u", "short"), (10, "u", "short")]
    rows += [(100 + i, f"http://y/{i}", f"<html><body><p>page number {i}</p>{'common footer ' * 9}</body></html>") for i in range(400)]
    manifest, folder = warc.write(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit(0)).coalesce(1), train_bytes=40_000)
    out = warc.read(manifest, folder).collect()
    assert len(out) == len(rows)
    by = {r["page_id"]: r for r in out}
    assert {i: by[i]["refers_to"] for i in (3, 5, 7, None)} == {3: 7, 5: 7, 7: None, None: 7}
    assert by[3]["record_type"] == "revisit" and by[3]["payload_bytes"] == len(big.encode()) and by[3]["payload_digest"] == by[7]["payload_digest"]
    assert by[8]["payload_bytes"] == 0 and by[9]["record_type"] == by[10]["record_type"] == "response"
    assert by[130]["payload"] == rows[8 + 30][2] and "\r" not in by[3]["url"]
    fs, _ = warc.filesystem(folder)
    with fs.open_input_stream(manifest.first()["file"]) as f:
        assert f.read(4) == warc.DICTIONARY_MAGIC
    empty, folder = warc.write(spark.createDataFrame([], "page_id long, url string, html string"))
    assert warc.read(empty, folder).count() == 0


# --- language ------------------------------------------------------------------------------------------------------


def test_language(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = language.op8_language_id(spark, sf).join(docs.select("doc_id", "lang"), "doc_id").collect()
    known = [r for r in out if r["held_out"] and r["lang"] is not None and r["lang_pred"] != "und"]
    assert sum(r["lang"] == r["lang_pred"] for r in known) >= 0.95 * len(known) and len(known) > 20
    ready = language.Profiles(language.fit(docs))
    assert ready.predict(None) == ready.predict("") == ready.predict("123 !!") == ("und", 0.0)
    assert language.fit(docs.limit(0)) == {} and language.Profiles({}).predict("words") == ("und", 0.0)
    out = language.identify(docs_of(spark, ODD).withColumn("score", F.lit("x")), language.fit(docs)).collect()
    assert len(out) == len(ODD) and {r["lang_pred"] for r in out if not (r["text"] or "").strip(" \n!?")} == {"und"}


def test_slabs_count_alike(monkeypatch):
    text = "".join(random.Random(1).choice("abc é1") for _ in range(5000))
    whole = language.count_grams(text)
    monkeypatch.setattr(language, "SLAB", 97)
    parts = language.count_grams(text)
    assert whole[0].tolist() == parts[0].tolist() and whole[1].tolist() == parts[1].tolist()


# --- near duplicates -----------------------------------------------------------------------------------------------


def shingle_set(text, k):
    words = (text or "").encode().translate(bytes(i + 32 if 65 <= i <= 90 else i for i in range(256))).split()
    return frozenset(tuple(words[i : i + k]) for i in range(len(words) - k + 1)) if len(words) >= k else frozenset([tuple(words)]) if words else frozenset()


def brute_components(rows, k):
    sets = [(i, shingle_set(t, k)) for i, t in rows if i is not None]
    comp = {i: i for i, _ in sets}

    def root(x):
        while comp[x] != x:
            x = comp[x]
        return x

    for n, (i, a) in enumerate(sets):
        for j, b in sets[:n]:
            if a and b and 100 * len(a & b) >= 80 * len(a | b):
                x, y = root(i), root(j)
                comp[max(x, y)] = min(x, y)
    return {i: root(i) for i in comp}


def copies(rng, n):
    base = [rng.choice("abcdefghijklmnop") + str(rng.randrange(500)) for _ in range(rng.randint(20, 120))]
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(9999)}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize("small", [2048, 8])
def test_near_duplicates(spark, small):
    """With ``small=8`` nodes count as large early, so that pivots and further branching are used too."""
    rng = random.Random(small)
    texts = [t for n in (60, 25, 9, 3, 1, 1, 2) for t in copies(rng, n)]
    rows = list(enumerate(texts)) + [(1000 + i, t) for i, t in ODD if i is not None] + [(None, texts[0]), (2000, "SHORT Text"), (2001, "short text")]
    out = near_dedup.near_duplicates(docs_of(spark, rows), k=4, small=small).collect()
    assert len(out) == len(rows)
    expected = brute_components(rows, 4)
    for r in out:
        if r["doc_id"] is None:
            assert r["component_id"] is None and not r["kept"]
        else:
            assert r["component_id"] == expected[r["doc_id"]] and r["kept"] == (r["doc_id"] == expected[r["doc_id"]])
    sizes = {i: len(shingle_set(t, 4)) for i, t in rows if i is not None}
    assert all(r["n_shingles"] == sizes[r["doc_id"]] for r in out if r["doc_id"] is not None)
    assert near_dedup.near_duplicates(docs_of(spark, [])).count() == 0


def test_trees_follow_the_depth(spark):
    """Classes whose nodes stay large for many steps get the trees that their depth asks for."""
    assert [near_dedup.trees_for(d, 0.8, 0.9995) for d in (3, 4, 8, 14)] == [9, 12, 28, 93]
    rng = random.Random(6)
    rows = list(enumerate(copies(rng, 4) + copies(rng, 1)))
    join = near_dedup.Join(docs_of(spark, rows), 4, 80, 0.9995, 2048)
    grow, grown = join.grow, []

    def seen(classes, trees, nodes, links):
        grown.append((trees, classes.count()))
        grow(classes, trees, nodes, links)
        deep = [(r["rep"], 8) for r in classes.select("rep").sort("rep").limit(3).collect()]  # as if they had gone so far
        return spark.createDataFrame(deep, "rep long, depth int")

    join.grow = seen
    join.run()
    assert grown == [(9, len(set(t for _, t in rows))), (9, 3), (10, 3)]


def test_long_texts_shingle_alike(monkeypatch):
    import pyarrow as pa

    text = " ".join(f"w{i % 700}" for i in range(4000))
    whole = list(shingles.document_sets(pa.array([text, "x y"]), 4))
    monkeypatch.setattr(shingles, "SEGMENT", 64)
    shingles._POWERS[:] = []
    assert [x.tolist() for x in shingles.document_sets(pa.array([text, "x y"]), 4)] == [x.tolist() for x in whole]
    shingles._POWERS[:] = []


def test_components(spark):
    rng = random.Random(2)
    e = [(rng.randrange(80), rng.randrange(80)) for _ in range(60)] + [(100 + i, 101 + i) for i in range(40)] + [(200, 300 + i) for i in range(50)]
    got = {r["id"]: r["component"] for r in components(spark.createDataFrame(e, "a long, b long"), Workspace(spark, "test")).collect()}
    v, root = forest(*(np.array(x) for x in zip(*e, strict=True)))
    expected = dict(zip(v.tolist(), root.tolist(), strict=True)) | {r: r for r in root.tolist()}
    assert {k: c for k, c in got.items()} == {k: c for k, c in expected.items() if k in got} and set(expected) <= set(got)
    assert components(spark.createDataFrame([], "a long, b long"), Workspace(spark, "test")).count() == 0


def test_prefilter(spark):
    df, ids = spark.range(1000).withColumnRenamed("id", "doc_id"), spark.range(0, 1000, 7).withColumnRenamed("id", "doc_id")
    held, out = prefilter(df, ids, "doc_id"), prefilter(df, ids, "doc_id", out=True)
    assert held.count() + out.count() == 1000 and held.join(ids, "doc_id").count() == ids.count() and held.count() < 200
    assert prefilter(df, ids.limit(0), "doc_id").count() == 0


# --- vectors -------------------------------------------------------------------------------------------------------


def vector_rows(seed=0, n=300, dim=16):
    rng = np.random.default_rng(seed)
    base = rng.standard_normal((n, dim))
    near = np.repeat(base[:6], 20, axis=0) + rng.standard_normal((120, dim)) * 0.12
    x = np.concatenate((base, near, base[:5], base[:1] * 3)).astype(np.float32)
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    return rows + [(5000, None), (5001, [0.0] * dim), (5002, [float("nan")] * dim), (5003, [1.0, None]), (5004, []), (5005, [1.0, 0.0]), (5006, [1.0, 0.01]), (None, x[0].tolist()), (7, x[7].tolist())]


def usable(v):
    return bool(v) and all(a is not None and math.isfinite(a) for a in v) and any(v)


def test_near_vectors(spark):
    rows = vector_rows()
    out = vectors.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("n_links", F.lit("x")), tile=16).collect()
    assert len(out) == len(rows)
    good = [(i, np.array(v, np.float32).astype(float)) for i, v in rows if i is not None and usable(v)]
    links, pairs = Counter(), []
    for n, (i, a) in enumerate(good):
        for j, b in good[:n]:
            if len(a) == len(b) and a @ b / (np.linalg.norm(a) * np.linalg.norm(b)) >= 0.9:
                links[i] += 1
                links[j] += 1
                if i != j:
                    pairs.append((i, j))
    v, root = forest(*(np.array(x) for x in zip(*pairs, strict=True)))
    comp = dict(zip(v.tolist(), root.tolist(), strict=True))
    for r in out:
        i = r["vec_id"]
        if i is None:
            assert r["n_links"] == 0 and not r["kept"]
        elif i == 7:
            assert r["n_links"] * 2 == links[7]  # two rows of one id count each other once
        else:
            assert r["n_links"] == links[i] and r["component_id"] == comp.get(i, i) and r["kept"] == (comp.get(i, i) == i)
    assert vectors.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_nearest(spark):
    rows = vector_rows(1, 900)
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit("x"))
    out = search.nearest(df, F.col("vec_id") % 20 == 0, k=20).collect()
    good = {i: np.array(v, np.float32).astype(float) for i, v in rows if i is not None and usable(v)}
    by = {}
    for r in out:
        by.setdefault(r["query_id"], []).append(r)
    hit = total = 0
    for q, own in by.items():
        own.sort(key=lambda r: r["rank"])
        assert [r["rank"] for r in own] == list(range(1, len(own) + 1)) and q not in [r["vec_id"] for r in own]
        others = sorted(((-(v @ good[q]), i) for i, v in good.items() if i != q and len(v) == len(good[q])))[:20]
        assert len(own) == min(20, len(others))
        assert all(abs(r["score"] - good[q] @ good[r["vec_id"]]) < 1e-9 for r in own)
        assert all((-a["score"], a["vec_id"]) < (-b["score"], b["vec_id"]) for a, b in zip(own[:-1], own[1:], strict=True))
        hit += len({i for _, i in others} & {r["vec_id"] for r in own})
        total += len(others)
    assert hit >= 0.9 * total and set(by) == {i for i in good if i % 20 == 0}
    assert search.nearest(df.limit(0), F.lit(True)).count() == 0
    assert search.nearest(df.filter("vec_id < 3"), F.lit(True)).count() == 6


def test_nearest_in_groups_of_copies(spark):
    """Large groups of exact and of tight near copies, against brute force by id: ties go to the smallest ids of the whole group."""
    rng = np.random.default_rng(5)
    base = rng.standard_normal((800, 16))
    same = np.repeat(base[:1], 700, axis=0)
    tight = base[1] + rng.standard_normal((700, 16)) * 1e-4
    x = np.concatenate((base, same, tight)).astype(np.float32)[rng.permutation(2200)]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    exact = x.astype(float)
    got = {}
    for r in search.nearest(df, F.col("vec_id") % 20 == 0, k=20, recall=1.0).collect():
        got.setdefault(r["query_id"], set()).add(r["vec_id"])
    hit = total = 0
    for i in range(0, 2200, 20):
        score = (exact * exact[i]).sum(axis=1)
        order = np.lexsort((np.arange(2200), -score))
        best = [int(j) for j in order[order != i][:20]]
        hit, total = hit + len(got[i] & set(best)), total + 20
    assert len(got) == 110 and hit >= 0.97 * total
