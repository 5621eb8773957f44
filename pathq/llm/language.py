"""Language identification by rank-order profiles.

A profile is the list of a language's most frequent character n-grams, by rank. A document's own most frequent
n-grams are ranked the same way, and its distance to a profile is the sum of how far each n-gram is out of
place; an n-gram that the profile lacks counts the most. The nearest profile wins.

N-grams run over the lower-cased text, where every run of characters that are not letters becomes one space.
They are packed exactly into 63 bits (three code points of 21 bits). Whole texts count; long ones are counted
in slabs, so memory is bounded by the slab and by the text's distinct n-grams.

Profiles are fitted on a bounded sample of labelled rows (``max_train_docs`` of each language, drawn by a hash of the
id; all rows of a language that has fewer); prediction covers every row.

Edge cases: null texts and texts without a letter give ``und`` and score 0. Ties go to the smaller name. Repeated
rows are predicted alike. Without any training row all predictions are ``und``. Extra columns are ignored; a
null ``doc_id`` counts as not held out.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.llm.common import Workspace

TOP = 400
SLAB = 1 << 19
GROUP_CHARS = 1 << 20
UNKNOWN = "und"

_FOLD: np.ndarray | None = None


def _fold_table() -> np.ndarray:
    """Code point -> lower-case code point if it is a letter, else 32. Built from the Unicode data of the interpreter."""
    global _FOLD
    if _FOLD is None:
        table = np.full(0x110000, 32, dtype=np.uint32)
        for start, stop in ((0, 0xD800), (0xE000, 0x323B0)):  # letters live below
            for c in range(start, stop):
                ch = chr(c)
                if ch.isalpha():
                    low = ch.lower()
                    table[c] = ord(low) if len(low) == 1 else c
                elif unicodedata.category(ch)[0] == "M":
                    table[c] = c  # marks stay with their letters
        _FOLD = table
    return _FOLD


def _letters(text: str) -> np.ndarray:
    """Folded code points with one space between words and around the text."""
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    folded = _fold_table()[points]
    keep = np.empty(len(folded) + 2, dtype=np.uint64)
    keep[0] = keep[-1] = 32
    keep[1:-1] = folded
    blank = keep == 32
    return keep[~(blank & np.concatenate(([False], blank[:-1])))]


def _grams(s: np.ndarray) -> np.ndarray:
    """All 1- to 3-grams of folded text but lone spaces, as packed keys."""
    one = s[s != 32]
    two = s[:-1] | (s[1:] << np.uint64(21))
    three = s[:-2] | (s[1:-1] << np.uint64(21)) | (s[2:] << np.uint64(42)) if len(s) > 2 else s[:0]
    return np.concatenate((one, two, three))


def count_grams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """(keys, counts) of the whole text, keys rising; slab by slab, two characters of overlap."""
    s = _letters(text)
    if len(s) <= SLAB:
        return np.unique(_grams(s), return_counts=True)
    keys, counts = np.empty(0, np.uint64), np.empty(0, np.int64)
    for at in range(0, len(s), SLAB):
        part = s[at : at + SLAB]
        grams = [part[part != 32]]
        ahead = s[at : at + SLAB + 2]
        n = len(part)
        a, b = ahead[: min(n, len(ahead) - 1)], ahead[1 : n + 1]
        grams.append(a[: len(b)] | (b << np.uint64(21)))
        c = ahead[2 : n + 2]
        grams.append(ahead[: len(c)] | (ahead[1 : len(c) + 1] << np.uint64(21)) | (c << np.uint64(42)))
        k, v = np.unique(np.concatenate(grams), return_counts=True)
        both, where = np.unique(np.concatenate((keys, k)), return_inverse=True)
        counts = np.bincount(where, weights=np.concatenate((counts, v)), minlength=len(both)).astype(np.int64)
        keys = both
    return keys, counts


def ranked(keys: np.ndarray, counts: np.ndarray, top: int = TOP) -> np.ndarray:
    """The most frequent keys, most frequent first, ties to the smaller key."""
    if len(keys) > 4 * top:
        floor = np.partition(counts, len(counts) - top)[len(counts) - top]
        near = counts >= floor
        keys, counts = keys[near], counts[near]
    return keys[np.lexsort((keys, -counts))][:top]


def _sample_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    totals: dict[str, dict[int, int]] = {}
    for batch in batches:
        for text, lang in zip(batch["text"], batch["lang"], strict=True):
            if (t := text.as_py()) is None:
                continue
            keys, counts = count_grams(t)
            own = totals.setdefault(lang.as_py(), {})
            for k, c in zip(keys.tolist(), counts.tolist(), strict=True):
                own[k] = own.get(k, 0) + c
    for lang, own in totals.items():
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(own), pa.string()), pa.array(list(own), pa.int64()), pa.array(list(own.values()), pa.int64())], names=["lang", "gram", "n"])


def fit(labelled: DataFrame, max_train_docs: int = 2000, top: int = TOP) -> dict[str, np.ndarray]:
    """Profiles by language, from about ``max_train_docs`` rows of each language, or all it has, out of (doc_id, text, lang)."""
    spark = labelled.sparkSession
    usable = labelled.filter(F.col("lang").isNotNull() & F.col("text").isNotNull())
    rows = usable.groupBy("lang").count().collect()  # names of languages: a closed set
    if not rows:
        return {}
    most = 1 << 20
    shares = F.create_map(*[F.lit(x) for r in rows for x in (r["lang"], min(most, max_train_docs * most // r["count"]))])
    drawn = usable.filter(F.pmod(F.xxhash64("doc_id"), F.lit(most)) < F.element_at(shares, F.col("lang")))
    counts = drawn.select("text", "lang").mapInArrow(_sample_counts, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    work = Workspace(spark, "language")
    counts = work.table(counts, "grams")
    langs = [r[0] for r in counts.select("lang").distinct().collect()]  # names of languages: a closed set
    profiles = {}
    for lang in sorted(langs):
        best = counts.filter(F.col("lang") == lang).orderBy(F.desc("n"), "gram").limit(top).select("gram").collect()
        profiles[lang] = np.array([r[0] for r in best], dtype=np.uint64)
    work.close()
    return profiles


class Profiles:
    """Profiles made ready for lookup: sorted keys and the rank of each key in every language."""

    def __init__(self, profiles: dict[str, np.ndarray], top: int = TOP):
        self.langs, self.top = sorted(profiles), top
        self.keys = np.unique(np.concatenate(list(profiles.values()))) if profiles else np.empty(0, np.uint64)
        self.ranks = np.full((len(self.langs), len(self.keys)), -1, dtype=np.int32)
        for i, lang in enumerate(self.langs):
            self.ranks[i, np.searchsorted(self.keys, profiles[lang])] = np.arange(len(profiles[lang]))

    def predict(self, text: str | None) -> tuple[str, float]:
        if text is None or not self.langs:
            return UNKNOWN, 0.0
        keys, counts = count_grams(text)
        if not len(keys):
            return UNKNOWN, 0.0
        if not any(_is_letter(int(k)) for k in keys[keys < (1 << 21)]):
            return UNKNOWN, 0.0
        return self.nearest(ranked(keys, counts, self.top))

    def nearest(self, order: np.ndarray) -> tuple[str, float]:
        """The language with the smallest out-of-place distance; score 1 is distance 0, score 0 nothing in common."""
        at = np.minimum(np.searchsorted(self.keys, order), len(self.keys) - 1)
        known = self.keys[at] == order
        place = np.arange(len(order), dtype=np.int32)
        ranks = self.ranks[:, at]
        out = np.where(known & (ranks >= 0), np.minimum(np.abs(ranks - place), self.top), self.top).sum(axis=1)
        best = int(np.argmin(out))
        return self.langs[best], float(1.0 - out[best] / (self.top * len(order)))


def _is_letter(c: int) -> bool:
    return chr(c).isalpha()


def identify(docs: DataFrame, profiles: dict[str, np.ndarray], top: int = TOP) -> DataFrame:
    """``docs`` with lang_pred and score for every row; only ``text`` is looked at."""
    kept = docs.drop("lang_pred", "score")
    schema = kept.withColumn("lang_pred", F.lit("").cast("string")).withColumn("score", F.lit(0.0)).schema
    ready = Profiles(profiles, top)
    where = kept.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [ready.predict(t.as_py()) for t in batch.column(where)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([x[0] for x in found], pa.string()), pa.array([x[1] for x in found], pa.float64())], names=[*batch.schema.names, "lang_pred", "score"])

    return kept.mapInArrow(run, schema)


def held_out(doc_id) -> F.Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string")), F.lit(4)) == 2, F.lit(False))


def op8_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    profiles = fit(docs.filter(~held_out(F.col("doc_id"))))
    # only the id and the verdict leave the task
    ready = Profiles(profiles)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [ready.predict(t.as_py()) for t in batch["text"]]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array([x[0] for x in found], pa.string()), pa.array([x[1] for x in found], pa.float64())], names=["doc_id", "lang_pred", "score"])

    said = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double")
    return said.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
