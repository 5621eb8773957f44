"""Packing by optimal length buckets.

A global histogram of lengths (every document counts) feeds a dynamic program that places the bucket
boundaries with the least total padding; inside each bucket, documents fill batches of a token budget.

The histogram is the only thing the driver sees. Lengths up to ``exact_up_to`` keep a row each; longer ones
share geometric bins of ``1/1024`` of their size, so its rows are bounded by
``exact_up_to + 1024 * log2(longest / exact_up_to)`` whatever the corpus. A bin's boundary is its longest
length, and padding is computed from exact sums, so the plan is optimal over these boundaries.

Edge cases: null and empty texts have length 0 and lie in the first bucket. A document longer than the budget
gets a batch alone. Ties in length share a bucket. Repeated rows are packed as rows of their own. An empty
table gives an empty result. Columns that clash with the added ones are replaced.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathq.llm.common import Workspace

ADDED = ("n_tokens", "bucket", "bucket_len", "batch", "slot", "padding")


def word_length(text: Column) -> Column:
    """Words between ASCII white space, of the whole text."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


@dataclass(frozen=True)
class Bin:
    longest: int
    count: int
    total: int


def histogram(lengths: DataFrame, exact_up_to: int = 65536) -> list[Bin]:
    """Bins of the column ``n_tokens``, by rising length."""
    n = F.col("n_tokens")
    step = F.greatest(F.lit(1).cast("long"), F.pow(F.lit(2.0), F.floor(F.log2(F.greatest(n, F.lit(1).cast("long")).cast("double"))) - 10).cast("long"))
    key = F.when(n <= exact_up_to, n).otherwise(F.floor(n / step).cast("long") * step)
    rows = lengths.groupBy(key.alias("k")).agg(F.max(n).alias("longest"), F.count(F.lit(1)).alias("count"), F.sum(n).alias("total")).collect()
    return sorted((Bin(r["longest"], r["count"], r["total"]) for r in rows), key=lambda b: b.longest)


def boundaries(bins: list[Bin], n_buckets: int) -> list[int]:
    """The at most ``n_buckets`` boundaries with the least padding; the last is the longest length.

    Padding of a bucket that holds bins i+1..j is ``longest_j * (C_j - C_i) - (T_j - T_i)`` with running counts C
    and totals T. For a fixed j it is a line in ``longest_j``, with slope ``-C_i``; as slopes fall and queries rise,
    a monotone hull answers a layer in time linear in the bins.
    """
    m = len(bins)
    if not m:
        return []
    counts, totals = [0], [0]
    for b in bins:
        counts.append(counts[-1] + b.count)
        totals.append(totals[-1] + b.total)
    best: list[float] = [0.0] + [float("inf")] * m
    back: list[list[int]] = []
    for _ in range(min(n_buckets, m)):
        hull: list[tuple[int, float]] = []  # (split, intercept)
        head, layer, frm = 0, [float("inf")] * (m + 1), [0] * (m + 1)
        layer[0] = 0.0
        for j in range(1, m + 1):
            i = j - 1
            if best[i] < float("inf"):
                line = (i, best[i] + totals[i])
                while len(hull) - head >= 2:
                    (i1, b1), (i2, b2) = hull[-2], hull[-1]
                    # the middle line is never lowest
                    if (line[1] - b1) * (counts[i2] - counts[i1]) <= (b2 - b1) * (counts[line[0]] - counts[i1]):
                        hull.pop()
                    else:
                        break
                hull.append(line)
            x = bins[j - 1].longest
            while len(hull) - head >= 2 and hull[head + 1][1] - x * counts[hull[head + 1][0]] <= hull[head][1] - x * counts[hull[head][0]]:
                head += 1
            split, intercept = hull[head]
            layer[j], frm[j] = intercept - x * counts[split] + x * counts[j] - totals[j], split
        best = layer
        back.append(frm)
    cuts, j = [], m
    for frm in reversed(back):
        if j == 0:
            break
        cuts.append(bins[j - 1].longest)
        j = frm[j]
    return cuts[::-1]


def padding_of(bins: list[Bin], cuts: list[int]) -> int:
    out, k = 0, 0
    for b in bins:
        while b.longest > cuts[k]:
            k += 1
        out += cuts[k] * b.count - b.total
    return out


def pack(docs: DataFrame, length: Column | None = None, n_buckets: int = 16, token_budget: int = 65536, seed: int = 7, rows_a_chunk: int = 50_000) -> DataFrame:
    """``docs`` with n_tokens, bucket, bucket_len, batch, slot and padding (of the row).

    A batch holds ``max(1, token_budget // bucket_len)`` documents of one bucket. Ranks within a bucket are
    exact but come from two levels: chunks of about ``rows_a_chunk`` rows by a hash of the row are ranked on
    their own, and a running sum over chunk counts shifts them, so no task gathers a whole bucket.
    """
    spark = docs.sparkSession
    kept = docs.drop(*ADDED)
    length = word_length(F.col("text")) if length is None else length
    measured = kept.withColumn("n_tokens", length)
    bins = histogram(measured.select("n_tokens"))
    cuts = boundaries(bins, n_buckets) or [0]
    n_rows = sum(b.count for b in bins)
    n_chunks = max(1, -(-n_rows // rows_a_chunk))
    bucket = F.lit(len(cuts) - 1)
    for k in reversed(range(len(cuts) - 1)):
        bucket = F.when(F.col("n_tokens") <= cuts[k], k).otherwise(bucket)
    ids = [c for c in ("doc_id",) if c in kept.columns] or kept.columns[:1]
    placed = measured.withColumn("bucket", bucket.cast("int")).withColumn("__tie", F.xxhash64(F.lit(seed), *[F.col(c) for c in ids]))
    placed = placed.withColumn("__chunk", F.pmod(F.col("__tie"), F.lit(n_chunks)).cast("int"))
    sizes = placed.groupBy("bucket", "__chunk").agg(F.count(F.lit(1)).alias("__n"))
    before = Window.partitionBy("bucket").orderBy("__chunk").rowsBetween(Window.unboundedPreceding, -1)
    shifts = sizes.select("bucket", "__chunk", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__shift"))
    inside = Window.partitionBy("bucket", "__chunk").orderBy("__tie", *ids)
    lens = F.element_at(F.array(*[F.lit(c).cast("long") for c in cuts]), F.col("bucket") + 1)
    room = F.greatest(F.lit(1).cast("long"), F.floor(F.lit(token_budget) / F.greatest(F.col("bucket_len"), F.lit(1).cast("long"))).cast("long"))
    ranked = placed.withColumn("__r", F.row_number().over(inside)).join(shifts, ["bucket", "__chunk"])
    if n_rows == 0:
        return spark.createDataFrame([], ranked.select(*kept.columns).schema).select("*", *[F.lit(None).cast(t).alias(c) for c, t in zip(ADDED, ("long", "int", "long", "long", "long", "long"), strict=True)])
    rank = F.col("__shift") + F.col("__r") - 1
    return (
        ranked.withColumn("bucket_len", lens)
        .withColumn("batch", F.floor(rank / room).cast("long"))
        .withColumn("slot", F.pmod(rank, room).cast("long"))
        .withColumn("padding", F.col("bucket_len") - F.col("n_tokens"))
        .select(*kept.columns, *ADDED)
    )


def op1_packing(spark, sf_dir: str) -> DataFrame:
    """Packs every row of documents; the texts themselves are not carried along."""
    work = Workspace(spark, "packing")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", word_length(F.col("text")).alias("__len"))
    docs = work.table(docs, "lengths")  # texts are read once; the plan and the ranks need lengths alone
    return work.finish(pack(docs, length=F.col("__len")).drop("__len"))
