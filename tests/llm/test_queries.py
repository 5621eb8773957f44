"""The registered queries on the smallest tables: against SQL where there is some, else against plain versions of their own."""

import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from pathq.llm import queries
from pathq.llm.language import TOP, fit, held_out, identify
from pathq.llm.mixing import exponent, source_totals, weights
from pathq.llm.packing import boundaries, histogram, padding_of

WORD = r"[^\x20\x09-\x0D]+"


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_against_sql(spark, duck, sf, name):
    df = queries.QUERIES[name](spark, sf)
    cursor = duck.execute(queries.ORACLES[name])
    names = [d[0] for d in cursor.description]
    columns = sorted(df.columns)
    assert sorted(names) == columns
    order = [names.index(c) for c in columns]
    key = lambda r: tuple((x is None, str(x)) for x in r)
    assert sorted((tuple(r) for r in df.select(columns).collect()), key=key) == sorted((tuple(r[i] for i in order) for r in cursor.fetchall()), key=key)


def lengths_of(duck):
    return dict(duck.execute(f"SELECT doc_id, len(regexp_extract_all(coalesce(text, ''), '{WORD}')) FROM documents").fetchall())


def test_packing_against_plain(spark, duck, sf):
    """Every row once; the plan's padding is that of an exhaustive program; batches keep to the budget."""
    rows, n = queries.QUERIES["op1_packing"](spark, sf).collect(), lengths_of(duck)
    assert sorted((r["doc_id"], r["n_tokens"]) for r in rows) == sorted(n.items())
    own = sorted(Counter(n.values()).items())
    sizes, count = [x for x, _ in own], np.cumsum([0] + [c for _, c in own])
    total = np.cumsum([0] + [x * c for x, c in own])
    best = [0.0] + [math.inf] * len(own)
    for _ in range(16):
        best = [0.0] + [min(best[i] + sizes[j - 1] * (count[j] - count[i]) - (total[j] - total[i]) for i in range(j)) for j in range(1, len(own) + 1)]
    assert sum(r["padding"] for r in rows) == best[-1]
    batches = Counter((r["bucket"], r["batch"]) for r in rows)
    length = {r["bucket"]: r["bucket_len"] for r in rows}
    assert all(k == 1 or k * length[b] <= 65536 for (b, _), k in batches.items())
    assert len({(r["bucket"], r["batch"], r["slot"]) for r in rows}) == len(rows)
    bins = histogram(spark.createDataFrame([(x,) for x in n.values()], "n_tokens long"))
    assert padding_of(bins, boundaries(bins, 16)) == best[-1]


def test_mixing_against_plain(spark, duck, sf):
    """Weights are those of a plain bisection; each source gets its budget up to a document of the block at the edge."""
    rows, n = queries.QUERIES["op4_mixing"](spark, sf).collect(), lengths_of(duck)
    source = dict(duck.execute("SELECT doc_id, source FROM documents").fetchall())
    tokens = Counter()
    for i, k in n.items():
        tokens[source[i]] += k
    budget, live = sum(tokens.values()), {s: t for s, t in tokens.items() if t}

    def at(alpha):
        w = {s: t**alpha for s, t in live.items()}
        z = sum(w.values())
        w = {s: x / z for s, x in w.items()}
        return w, -sum(x * math.log(x) for x in w.values()), max(budget * x / live[s] for s, x in w.items())

    low, high = 0.0, 1.0
    met = lambda a: at(a)[1] <= 0.97 * math.log(len(live)) and at(a)[2] <= 4.0 + 1e-12
    if met(0.0):
        high = 0.0
    elif met(1.0):
        for _ in range(60):
            mid = (low + high) / 2
            low, high = (low, mid) if met(mid) else (mid, high)
    expected = at(high)[0]
    assert all(abs(r["weight"] - expected[r["source"]]) < 1e-6 for r in rows if tokens[r["source"]])
    taken = Counter()
    for r in rows:
        taken[r["source"]] += r["n_tokens"]
    for s, w in expected.items():
        longest = max(n[i] for i in n if source[i] == s)
        assert w * budget - longest - 1 <= taken[s] <= w * budget + 1e-6 * budget
    assert len({(r["doc_id"], r["epoch"]) for r in rows}) == len(rows)
    epochs = Counter(r["doc_id"] for r in rows)
    for s in live:  # every document is taken as often as any other of its source, or once more
        times = [epochs[i] for i in n if source[i] == s and n[i]]
        assert max(times) - min(times) <= 1


def plain_rank(text):
    """Most frequent 1- to 3-grams of folded text, by counting."""
    folded = "".join(c.lower() if c.isalpha() and len(c.lower()) == 1 else c if c.isalpha() else " " for c in text)
    s = " " + " ".join(folded.split()) + " "
    grams = Counter(s[i : i + k] for k in (1, 2, 3) for i in range(len(s) - k + 1))
    del grams[" "]
    key = lambda g: sum(ord(c) << (21 * j) for j, c in enumerate(g))
    return [g for g, _ in sorted(grams.items(), key=lambda x: (-x[1], key(x[0])))[:TOP]]


def test_language_against_plain(spark, duck, sf):
    """Predictions equal a plain rank-order distance to profiles that are counted plainly."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    learned = docs.filter(~held_out(F.col("doc_id"))).filter("lang is not null and text is not null").select("text", "lang").collect()
    totals: dict[str, Counter] = {}
    for r in learned:
        folded = "".join(c.lower() if c.isalpha() and len(c.lower()) == 1 else c if c.isalpha() else " " for c in r["text"])
        s = " " + " ".join(folded.split()) + " "
        own = totals.setdefault(r["lang"], Counter())
        own.update(s[i : i + k] for k in (1, 2, 3) for i in range(len(s) - k + 1))
    key = lambda g: sum(ord(c) << (21 * j) for j, c in enumerate(g))
    profiles = {}
    for lang, grams in totals.items():
        del grams[" "]
        profiles[lang] = {g: i for i, (g, _) in enumerate(sorted(grams.items(), key=lambda x: (-x[1], key(x[0])))[:TOP])}
    said = {r["doc_id"]: r for r in queries.QUERIES["op8_language_id"](spark, sf).collect()}
    right = checked = 0
    for r in docs.collect():
        text = r["text"]
        if not text or not any(c.isalpha() for c in text):
            assert said[r["doc_id"]]["lang_pred"] == "und" and said[r["doc_id"]]["score"] == 0.0
            continue
        order = plain_rank(text)
        far = {lang: sum(min(abs(p[g] - i), TOP) if g in p else TOP for i, g in enumerate(order)) for lang, p in profiles.items()}
        best = min(sorted(far), key=far.get)
        assert said[r["doc_id"]]["lang_pred"] == best and abs(said[r["doc_id"]]["score"] - (1 - far[best] / (TOP * len(order)))) < 1e-9
        if said[r["doc_id"]]["held_out"] and r["lang"]:
            checked, right = checked + 1, right + (best == r["lang"])
    assert right >= 0.9 * checked


def test_ties_and_repeats_in_language(spark):
    rows = [(1, "aba aba", "x"), (5, "aba aba", "y"), (5, "aba aba", "y"), (9, None, "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    out = identify(docs, fit(docs)).collect()
    assert {r["lang_pred"] for r in out if r["text"]} == {"x"}  # equal profiles: the smaller name


def test_nearest_against_brute_force(spark, sf):
    rows = [(r["vec_id"], r["embedding"]) for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect() if r["embedding"]]
    ids, x = np.array([i for i, _ in rows]), np.array([v for _, v in rows], np.float64)
    found: dict[int, list] = {}
    for r in queries.QUERIES["op2_nearest"](spark, sf).collect():
        found.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    asked = [i for i in ids.tolist() if i % 20 == 0]
    assert sorted(found) == asked
    hits = wanted = 0
    for i in asked:
        q = x[ids == i][0]
        score = (x * q).sum(axis=1)
        best = [j for j in np.lexsort((ids, -score)) if ids[j] != i][:20]
        own = sorted(found[i])
        assert [r for r, _, _ in own] == list(range(1, len(own) + 1)) and len(own) == len(best)
        assert all(abs(s - score[ids == v][0]) < 1e-12 for _, v, s in own)
        hits += len({v for _, v, _ in own} & set(ids[best].tolist()))
        wanted += len(best)
    assert hits >= 0.9 * wanted


def test_pages_and_tokens_return_every_row(spark, sf):
    pages, docs = spark.read.parquet(f"{sf}/pages.parquet").count(), spark.read.parquet(f"{sf}/documents.parquet").count()
    told = queries.QUERIES["op5_html_text"](spark, sf).collect()
    assert len(told) == pages and all(r["n_chars"] == len(r["text"]) and r["n_turned"] <= r["n_blocks"] for r in told)
    ids = queries.QUERIES["op6_token_ids"](spark, sf).orderBy("start").collect()
    assert len(ids) == docs and all(a["start"] + a["n_tokens"] == b["start"] and a["doc_id"] <= b["doc_id"] for a, b in zip(ids, ids[1:], strict=False))


def test_stages_on_odd_tables(spark, sf):
    """Nulls in every column, empty texts, repeats, columns that clash with added ones, and no rows at all."""
    words = "the quick brown fox jumps over the lazy dog and runs away from it all "
    rows = [(None, None, None, None, None), (1, "", "en", "a", 0), (2, words * 3, "en", None, 9), (2, words * 3, "en", None, 9), (3, "a wholly different text about ships and the open sea in another season", None, "b", 1), (4, "123 456", "en", "b", 1)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    docs = spark.createDataFrame(rows, schema).withColumn("bucket", F.lit("x")).withColumn("score", F.lit(1)).withColumn("weight", F.lit("w"))
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        got = out.collect()
        assert len(stage(spark, docs.limit(0), sf).collect()) == 0
        ids = [r["doc_id"] for r in got]
        assert 2 in ids and 3 in ids, name
        if name == "near_dedup":
            assert ids.count(2) == 1
        if name == "language":
            assert 4 not in ids and 1 not in ids and ids.count(2) == 2
        if name == "packing":
            assert len(got) == len(rows)
    totals = source_totals(spark.createDataFrame([(None, 5), ("a", 0)], "source string, n_tokens long"))
    assert exponent(totals, 5.0, 0.9) == 1.0 and {r["source"]: r["weight"] for r in weights(totals, 1.0).collect()} == {None: 1.0, "a": 0.0}
