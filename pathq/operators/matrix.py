"""Boolean matrices in blocks of bits: the baseline by matrix product."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.store import Store

#: A block: its place, its bits as a list of places in row order or, where many are set, as a bitmap, and how many are set.
FORM = "bi long, bj long, at array<int>, bits binary, ones long"
BITS = 1 << 20  # bits, and ways over two bits, that a product of strips holds as numbers at once
STRIP = 2048  # blocks of a strip that it holds so


def number(ids: DataFrame, store: Store) -> DataFrame:
    """(id, i): dense numbers 0..n-1 of a column ``id``, by ranges, so that no task sees all."""
    spark = ids.sparkSession
    ranged = store.table(ids.distinct().repartitionByRange("id").withColumn("part", F.spark_partition_id()), "ranged")
    sizes = sorted((r["part"], r["count"]) for r in ranged.groupBy("part").count().collect())  # a row per partition
    start, offsets = 0, []
    for p, n in sizes:
        offsets.append((p, start))
        start += n
    from pyspark.sql import Window

    place = F.row_number().over(Window.partitionBy("part").orderBy("id")) - 1
    starts = spark.createDataFrame(offsets or [(0, 0)], "part int, start long")
    return ranged.withColumn("k", place).join(F.broadcast(starts), "part").select("id", (F.col("start") + F.col("k")).alias("i"))


def _thin(block: int) -> int:
    """Bits from which on a block is a bitmap; with fewer it is the list of their places, which takes no more bytes."""
    return block * block // 32


def to_blocks(pairs: DataFrame, block: int) -> DataFrame:
    """Blocks (``FORM``) of (i, j): ``block`` x ``block`` bits in row order."""
    keyed = pairs.select((F.col("i") / block).cast("long").alias("bi"), (F.col("j") / block).cast("long").alias("bj"), (F.col("i") % block * block + F.col("j") % block).cast("int").alias("at"))
    return unite(keyed.select("bi", "bj", F.array("at").alias("at"), F.lit(None).cast("binary").alias("bits")), block)


def _unpack(data: bytes, block: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(data, np.uint8), count=block * block).reshape(block, block)


def _places(at: pa.Array, bits: pa.Array, block: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, place) of every bit set in some blocks, rows ascending."""
    n = np.asarray(at.value_lengths().fill_null(0), np.int64)
    row, place = np.repeat(np.arange(len(at)), n), at.flatten().to_numpy().astype(np.int64)
    full = np.flatnonzero(np.asarray(bits.is_valid()))
    if len(full):
        found = [np.flatnonzero(_unpack(bits[int(r)].as_py(), block)) for r in full]
        row, place = np.concatenate((row, np.repeat(full, list(map(len, found))))), np.concatenate((place, *found))
        order = np.argsort(row, kind="stable")
        row, place = row[order], place[order]
    return row, place


def _listed(code: np.ndarray, block: int) -> tuple[np.ndarray, pa.ListArray]:
    """Sorted codes (block number * places of a block + place) -> the numbers that occur, the places of each."""
    number = code // (block * block)
    first = np.flatnonzero(np.concatenate(([True], number[1:] != number[:-1]))) if len(code) else np.zeros(0, np.int64)
    ends = pa.array(np.append(first, len(code)), pa.int32())
    return number[first], pa.ListArray.from_arrays(ends, pa.array((code - number * (block * block)).astype(np.int32)))


def _batch(bi: np.ndarray, bj: np.ndarray, at: pa.Array, bits: pa.Array, *more: tuple[str, np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(bi, pa.int64()), pa.array(bj, pa.int64()), at, bits, *(pa.array(c) for _, c in more)], names=["bi", "bj", "at", "bits", *(c for c, _ in more)])


def _keyed(batches: Iterator[pa.RecordBatch], *keys: str) -> Iterator[pa.Table]:
    """Sorted rows as tables of whole groups: all that is known to be complete, each time a batch came."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        now = [batch[k].to_numpy() for k in keys]
        if held:
            same = np.logical_and.reduce([c == held[-1][k][-1].as_py() for c, k in zip(now, keys, strict=True)])
            if same.all():
                held.append(batch)
                continue
            to = int(np.argmin(same))
            yield pa.Table.from_batches([*held, batch.slice(0, to)])
            batch, now = batch.slice(to), [c[to:] for c in now]
        last = int(np.argmax(np.logical_and.reduce([c == c[-1] for c in now])))
        if last:
            yield pa.Table.from_batches([batch.slice(0, last)])
        held = [batch.slice(last)]
    if held:
        yield pa.Table.from_batches(held)


def _chunks(ones: np.ndarray) -> Iterator[slice]:
    """Blocks of one strip, some at a time, by the bits that they have set."""
    lo, sums = 0, np.concatenate(([0], np.cumsum(ones)))
    while lo < len(ones):
        hi = max(lo + 1, min(lo + STRIP, int(np.searchsorted(sums, sums[lo] + BITS, "right")) - 1))
        yield slice(lo, hi)
        lo = hi


def _met(a: pa.Table, b: pa.Table, block: int) -> Iterator[pa.RecordBatch]:
    """Products of the blocks ``a`` of one column of blocks with the blocks ``b`` of the row of that number, not united."""
    size = block * block
    bi, bj = a["bi"].to_numpy(), b["bj"].to_numpy()
    (ra, p), (rb, q) = (_places(x["at"].combine_chunks(), x["bits"].combine_chunks(), block) for x in (a, b))
    i, t = p // block, p % block
    order = np.argsort(q // block, kind="stable")
    rb, u, j = rb[order], (q // block)[order], (q % block)[order]

    def expand(ra: np.ndarray, i: np.ndarray, t: np.ndarray, rb: np.ndarray, u: np.ndarray, j: np.ndarray) -> Iterator[pa.RecordBatch]:
        begin = np.searchsorted(u, np.arange(block + 1))
        n = np.diff(begin)[t]
        sums, lo = np.concatenate(([0], np.cumsum(n))), 0
        while lo < len(t):
            hi = max(lo + 1, int(np.searchsorted(sums, sums[lo] + BITS, "right")) - 1)
            k = n[lo:hi]
            spots = np.repeat(begin[t[lo:hi]] - sums[lo:hi] + sums[lo], k) + np.arange(sums[hi] - sums[lo])
            code = np.unique((np.repeat(ra[lo:hi], k) * len(bj) + rb[spots]) * size + np.repeat(i[lo:hi], k) * block + j[spots])
            if len(code):
                number, at = _listed(code, block)
                yield _batch(bi[number // len(bj)], bj[number % len(bj)], at, pa.nulls(len(number), pa.binary()))
            lo = hi

    ways = np.bincount(t, minlength=block) @ np.bincount(u, minlength=block)
    if ways <= size:
        if ways:
            yield from expand(ra, i, t, rb, u, j)
        return
    counts = lambda row, at, n: np.bincount(row * block + at, minlength=n * block).reshape(n, block).astype(np.float32)
    many = counts(ra, t, len(bi)) @ counts(rb, u, len(bj)).T > size  # two blocks that meet more often are multiplied as bits
    plain = ~many.any(1)
    own = plain[ra]
    yield from expand(ra[own], i[own], t[own], rb, u, j)
    for r in np.flatnonzero(~plain):
        own, other = ra == r, ~many[r][rb]
        yield from expand(ra[own], i[own], t[own], rb[other], u[other], j[other])
        x = np.zeros((block, block), np.float32)
        x[i[own], t[own]] = 1
        for c in np.flatnonzero(many[r]):
            y = np.zeros((block, block), np.float32)
            y[u[rb == c], j[rb == c]] = 1
            bits = np.packbits(x @ y > 0, axis=None).tobytes()
            yield _batch(bi[[r]], bj[[c]], pa.nulls(1, pa.list_(pa.int32())), pa.array([bits], pa.binary()))


def multiply(a: DataFrame, b: DataFrame, block: int) -> DataFrame:
    """Boolean product of block matrices: products of one place are united."""
    return unite(_products(a, b, block), block)


def _products(a: DataFrame, b: DataFrame, block: int) -> DataFrame:
    """The blocks of one column of ``a`` meet those of one row of ``b`` in a task, which goes from bit to bit where few are set and
    multiplies bitmaps where many are."""

    def product(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _keyed(batches, "k"):
            k, side = table["k"].to_numpy(), table["side"].to_numpy()
            edges = [0, *(np.flatnonzero((np.diff(k) != 0) | (np.diff(side) != 0)) + 1).tolist(), len(k)]
            parts = [table.slice(lo, hi - lo) for lo, hi in zip(edges[:-1], edges[1:], strict=True)]
            for p, q in zip(parts[:-1], parts[1:], strict=True):
                if p["k"][0] == q["k"][0]:
                    for x in _chunks(p["ones"].to_numpy()):
                        for y in _chunks(q["ones"].to_numpy()):
                            yield from _met(p.slice(x.start, x.stop - x.start), q.slice(y.start, y.stop - y.start), block)

    side = lambda df, k, n: df.select(F.col(k).alias("k"), F.lit(n).alias("side"), "bi", "bj", "at", "bits", "ones")
    met = side(a, "bj", 0).unionByName(side(b, "bi", 1)).repartition("k").sortWithinPartitions("k", "side")
    return met.mapInArrow(product, "bi long, bj long, at array<int>, bits binary")


def unite(blocks: DataFrame, block: int) -> DataFrame:
    """Blocks of one place as one, in ``FORM``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = block * block
        for table in _keyed(batches, "bi", "bj"):
            bi, bj, at, bits = table["bi"].to_numpy(), table["bj"].to_numpy(), table["at"].combine_chunks(), table["bits"].combine_chunks()
            new = np.concatenate(([True], (bi[1:] != bi[:-1]) | (bj[1:] != bj[:-1])))
            number, first = np.cumsum(new) - 1, np.flatnonzero(new)
            n = np.asarray(at.value_lengths().fill_null(0), np.int64)
            code = np.unique(np.repeat(number, n) * size + at.flatten().to_numpy())
            ones = np.bincount(code // size, minlength=len(first))
            packed: dict[int, np.ndarray] = {b: np.zeros((size + 7) // 8, np.uint8) for b in np.flatnonzero(ones >= _thin(block)).tolist()}
            for r in np.flatnonzero(np.asarray(bits.is_valid())).tolist():
                own = packed.setdefault(int(number[r]), np.zeros((size + 7) // 8, np.uint8))
                own |= np.frombuffer(bits[r].as_py(), np.uint8)
            for b, own in packed.items():
                place = code[slice(*np.searchsorted(code, (b * size, (b + 1) * size)))] - b * size
                m = np.zeros(size, bool)
                m[place] = True
                own |= np.packbits(m)
                ones[b] = int(np.bitwise_count(own).sum())
            full = np.isin(np.arange(len(first)), list(packed))
            thin = np.flatnonzero(~full)
            if len(thin):
                _, lists = _listed(code[~full[code // size]], block)
                yield _batch(bi[first[thin]], bj[first[thin]], lists, pa.nulls(len(thin), pa.binary()), ("ones", ones[thin]))
            for b, own in packed.items():
                yield _batch(bi[first[[b]]], bj[first[[b]]], pa.nulls(1, pa.list_(pa.int32())), pa.array([own.tobytes()], pa.binary()), ("ones", ones[[b]]))

    return blocks.repartition("bi", "bj").sortWithinPartitions("bi", "bj").mapInArrow(run, FORM)


def to_pairs(blocks: DataFrame, block: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _chunks(batch["ones"].to_numpy()):
                some = batch.slice(part.start, part.stop - part.start)
                row, place = _places(some["at"], some["bits"], block)
                i, j = some["bi"].to_numpy()[row] * block + place // block, some["bj"].to_numpy()[row] * block + place % block
                yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j)], names=["i", "j"])

    return blocks.mapInArrow(run, "i long, j long")


def _named(pairs: DataFrame, names: DataFrame) -> DataFrame:
    a, b = names.select(F.col("id").alias("src"), "i"), names.select(F.col("id").alias("dst"), F.col("i").alias("j"))
    return pairs.join(a, "i").join(b, "j").select("src", "dst")


def matrix_word(parts: list[DataFrame], store: Store, block: int = 512) -> DataFrame:
    """Distinct (src, dst) of a chain of relations (p, q), by Boolean matrix products."""
    ids = parts[0].select(F.col("p").alias("id"))
    for r in parts:
        ids = ids.union(r.select("p")).union(r.select("q"))
    names = store.table(number(ids, store), "numbers")
    numbered = lambda r: r.join(names.select(F.col("id").alias("p"), "i"), "p").join(names.select(F.col("id").alias("q"), F.col("i").alias("j")), "q").select("i", "j")
    out = to_blocks(numbered(parts[0]), block)
    for r in parts[1:]:
        out = multiply(out, to_blocks(numbered(r), block), block)
    return _named(to_pairs(out, block), names)


def matrix_closure(edges: DataFrame, store: Store, block: int = 512) -> DataFrame:
    """Distinct (src, dst) joined by one edge or more, by repeated squaring of the block matrix until no bit is added."""
    names = store.table(number(edges.select(F.col("src").alias("id")).union(edges.select("dst")), store), "numbers")
    pairs = edges.join(names.select(F.col("id").alias("src"), "i"), "src").join(names.select(F.col("id").alias("dst"), F.col("i").alias("j")), "dst").select("i", "j")
    blocks, ones = store.table(to_blocks(pairs, block), "blocks"), -1
    while True:
        blocks = store.table(unite(blocks.drop("ones").unionByName(_products(blocks, blocks, block)), block), "blocks")
        now = blocks.agg(F.sum("ones")).first()[0] or 0
        if now == ones:
            return _named(to_pairs(blocks, block), names)
        ones = now
