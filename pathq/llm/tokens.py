"""Token ids in files of our own: whole texts through a tokenizer, ids through the range coder, in document order.

A file holds consecutive documents in ascending id order, each with its end id. It begins with a fixed head; groups of
coded blocks follow. A group begins with its alphabet, the pairs and single ids that its symbols stand for, and a checksum of
it; each block has its length, its numbers of symbols and ids and a checksum of the ids. The foot lists every document's id
and number of ids. Blocks of a group are independent, so a damaged one is found by its checksum and loses only itself; a
damaged alphabet is found too and loses its group.

Documents are ranged by id, so that ranges hold about equally many bytes of text: cut points are quantiles of the ids,
drawn in proportion to the length of their texts. Each range is a task's, which sorts its texts and writes them. Files are written by tasks under names of their own; the committed manifest says which count and gives
each one's number of ids, from which the starts of all files follow.

Tokenising goes piece by piece through a bounded memo: texts are cut where the pre-tokenizer never joins (see ``cuts``), over
the bytes of many texts at once; distinct pieces are encoded once by the library and looked up after. A text that holds the
string of an added token goes to the library whole.

Edge cases: null and empty texts give the end id alone. Documents with a null id come first, as do their ids. Rows
that repeat an id are documents of their own, one after the other. Very long texts are encoded whole; their ids may
span many blocks. An empty table gives no files. Extra columns are ignored.
"""

from __future__ import annotations

import os
import re
import struct
import uuid
import zlib
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.llm.coder import checksum, decode_blocks, encode_blocks, paired, unpaired
from pathq.llm.common import Workspace, filesystem

MAGIC = b"IDSTREAM\x02"
HEAD = struct.Struct("<9sII")  # magic, vocabulary, block
GROUP = struct.Struct("<IIII")  # blocks, symbols of the alphabet, bytes of the alphabet, its checksum
BLOCK = struct.Struct("<IIII")  # coded bytes, symbols, ids, checksum
FOOT = struct.Struct("<QQQ8s")  # place of the foot, documents, ids, end mark
END = b"IDSTREAM"
MANIFEST = "range int, file string, n_docs long, n_ids long, n_bytes long"

# white space of any kind, and characters that engines of regular expressions class differently
_BARE = re.compile(r"[^\s\u180e\u200b\ufeff]+")
_SPACED = re.compile(r" [^\s\u180e\u200b\ufeff]+")


def _table(*spans: tuple[int, int]) -> np.ndarray:
    found = np.zeros(256, bool)
    for a, b in spans:
        found[a : b + 1] = True
    return found


_VISIBLE = _table((33, 126))
_ALNUM = _table((48, 57), (65, 90), (97, 122))
_STOP = _table(*((ord(c), ord(c)) for c in ".,;:!?"))
_TRAIL = _table((0x80, 0xBF))
# first bytes of characters of two, three and four bytes none of which is white space; C2, E1 to E3 and EF lead to some that are
_LEAD = (_table((0xC3, 0xDF)), _table((0xE0, 0xE0), (0xE4, 0xEE)), _table((0xF0, 0xF4)))
_FIRST = _VISIBLE | _LEAD[0] | _LEAD[1] | _LEAD[2]


def _visible_before(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Whether the character that ends before each place is surely visible."""
    last = data.take(at - 1, mode="clip")
    found = _VISIBLE[last]
    odd = np.flatnonzero(~found & _TRAIL[last])
    if len(odd):
        seen = np.zeros(len(odd), bool)
        trail = np.ones(len(odd), bool)
        for k, lead in enumerate(_LEAD):
            x = data.take(at[odd] - 2 - k, mode="clip")
            seen |= trail & lead[x]
            trail &= _TRAIL[x]
        found[odd] = seen
    return found


def cuts(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Places in UTF-8 ``data`` at which the pre-tokenizer parts texts, the bounds of texts (``offsets``) among them.

    Cut is before a single space between two visible characters, on both sides of a single line feed between two, and between
    an ASCII or Latin letter or a digit and a stop or comma. Where it is not sure that a character is visible nothing is cut.
    """
    mark = np.zeros(len(data) + 1, bool)
    mark[offsets] = True
    for sign in (32, 10):
        at = np.flatnonzero(data == sign)
        at = at[_FIRST[data.take(at + 1, mode="clip")]]
        at = at[_visible_before(data, at)]
        mark[at] = True
        if sign == 10:
            mark[at + 1] = True
    at = np.flatnonzero(_STOP[data])
    last, first = data.take(at - 1, mode="clip"), data.take(at - 2, mode="clip")
    latin = (first == 0xC3) & _TRAIL[last] & (last != 0x97) & (last != 0xB7)
    mark[at[_ALNUM[last] | latin]] = True
    return np.flatnonzero(mark)


class Tokens:
    """Ids of whole texts, the library's own, through a memo of at most ``most`` pieces (and those of one batch of texts).

    Pieces that are new to a batch of texts are encoded in runs. In a run every piece begins with the only token that begins with
    a space, or is parted from the next by the only line feed, which is how the run's ids are dealt back to the pieces.
    """

    longest = 64  # bytes of a piece that is remembered

    def __init__(self, path: str, most: int = 600_000):
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks are the parallel units
        self.tokenizer = Tokenizer.from_file(path)
        self.added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.vocabulary = self.tokenizer.get_vocab_size()
        self.spaced = np.zeros(self.vocabulary, bool)
        for token, i in self.tokenizer.get_vocab().items():
            self.spaced[i] = token.startswith("\u0120")  # how byte-level vocabularies write a space
        feed = self._run("\n")
        self.feed = int(feed[0]) if len(feed) == 1 else -1
        self.most = most
        self.memo: dict[bytes, int] = {}  # a piece's number, in order
        self.first, self.size, self.flat, self.hits = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.uint32), np.empty(0, np.int32)

    def _forget(self) -> None:
        """Keep at most half of ``most`` pieces: those that came again after they were learned, the most frequent first."""
        keep = np.flatnonzero(self.hits)
        if len(keep) > self.most // 2:
            keep = np.sort(keep[np.argsort(-self.hits[keep], kind="stable")[: self.most // 2]])
        keys = list(self.memo)
        self.memo = {keys[i]: n for n, i in enumerate(keep.tolist())}
        self.flat, self.size = _dealt(self.flat, self.first[keep], self.size[keep]), self.size[keep]
        self.first, self.hits = np.cumsum(self.size) - self.size, self.hits[keep] >> 1

    def _run(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32)

    def _learned(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The number of ids of each piece, and all ids one after the other."""
        texts = [x.decode() for x in pieces]
        kinds: tuple[list[int], list[int], list[int]] = [], [], []
        for i, x in enumerate(texts):
            kinds[0 if _SPACED.fullmatch(x) else 1 if _BARE.fullmatch(x) else 2].append(i)
        size, runs, order = np.zeros(len(pieces), np.int64), [], []
        alone = kinds[2]
        for kind, glue in ((kinds[0], ""), (kinds[1], "\n")):
            for at in range(0, len(kind), 8000):
                part = kind[at : at + 8000]
                ids = self._run(glue.join([texts[i] for i in part]))
                if glue:
                    cut = np.flatnonzero(ids == self.feed)
                    n = np.diff(np.concatenate(([-1], cut, [len(ids)]))) - 1
                    ids = np.delete(ids, cut)
                else:
                    cut = np.flatnonzero(self.spaced[ids])
                    n = np.diff(np.append(cut, len(ids))) if len(cut) and cut[0] == 0 else []
                if len(n) == len(part):
                    size[part] = n
                    runs.append(ids)
                    order += part
                else:
                    alone = alone + part
        for i in alone:
            ids = self._run(texts[i])
            size[i] = len(ids)
            runs.append(ids)
            order.append(i)
        flat, place = np.concatenate(runs), np.array(order)
        first = np.empty(len(pieces), np.int64)
        first[place] = np.cumsum(size[place]) - size[place]
        return size, _dealt(flat, first, size)

    def _ids(self, pieces: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(first, size, flat): where the ids of each of the distinct ``pieces`` lie in flat."""
        keys = pieces.to_numpy(zero_copy_only=False).tolist()
        if len(self.memo) > self.most:
            self._forget()
        at = np.fromiter(map(self.memo.get, keys, repeat(-1)), np.int64, len(keys))
        new = np.flatnonzero(at < 0)
        self.hits[at[at >= 0]] += 1
        if not len(new):
            return self.first[at], self.size[at], self.flat
        fresh = keys if len(new) == len(keys) else [keys[i] for i in new.tolist()]
        size, ids = self._learned(fresh)
        known, first = len(self.first), len(self.flat) + np.cumsum(size) - size
        at[new] = known + np.arange(len(new))
        firsts, sizes, flat = np.concatenate((self.first, first)), np.concatenate((self.size, size)), np.concatenate((self.flat, ids))
        kept = np.flatnonzero(pc.binary_length(pieces).to_numpy()[new] <= self.longest)
        self.memo.update(zip([fresh[i] for i in kept.tolist()], range(known, known + len(kept)), strict=True))
        self.hits = np.concatenate((self.hits, np.zeros(len(kept), np.int32)))
        if len(kept) == len(fresh):
            self.first, self.size, self.flat = firsts, sizes, flat
        else:
            n = size[kept]
            self.first = np.concatenate((self.first, len(self.flat) + np.cumsum(n) - n))
            self.size, self.flat = np.concatenate((self.size, n)), np.concatenate((self.flat, _dealt(flat, first[kept], n)))
        return firsts[at], sizes[at], flat

    def batch(self, texts: list[str | None] | pa.Array) -> list[np.ndarray]:
        column = texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string())
        column = pc.fill_null(column.cast(pa.string()), "")
        whole: dict[int, np.ndarray] = {}
        for mark in self.added:
            has = pc.match_substring(column, mark)
            if pc.any(has).as_py():
                whole |= {int(i): self._run(column[int(i)].as_py()) for i in np.flatnonzero(has.to_numpy(zero_copy_only=False))}
                column = pc.if_else(has, "", column)
        _, place, buffer = column.buffers()
        bounds = np.frombuffer(place, np.int32)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int32)
        lo, hi = int(bounds[0]), int(bounds[-1])
        if hi == lo:
            return [whole.get(i, np.empty(0, np.uint32)) for i in range(len(column))]
        data = np.frombuffer(buffer, np.uint8)[lo:hi]
        bounds = bounds - lo
        at = cuts(data, bounds)
        pieces = pa.Array.from_buffers(pa.binary(), len(at) - 1, [None, pa.py_buffer(at.astype(np.int32)), pa.py_buffer(data)]).dictionary_encode()
        first, size, flat = self._ids(pieces.dictionary)
        code = pieces.indices.to_numpy()
        size = size[code]
        ends = np.concatenate(([0], np.cumsum(size)))
        ids = _dealt(flat, first[code], size)
        edge = ends[np.searchsorted(at, bounds)].tolist()
        return [whole[i] if i in whole else ids[a:b] for i, (a, b) in enumerate(zip(edge[:-1], edge[1:], strict=True))]

    def ids(self, text: str | None) -> np.ndarray:
        return self.batch([text])[0]


def _dealt(flat: np.ndarray, first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The runs of ``flat`` that begin at ``first`` and are ``size`` long, one after the other."""
    ends = np.cumsum(size)
    place = np.repeat(first - (ends - size), size)
    place += np.arange(len(place))
    return flat.take(place)


_TOKENS: dict[str, Tokens] = {}


def tokens(path: str) -> Tokens:
    """One per worker process, kept between tasks."""
    if path not in _TOKENS:
        _TOKENS[path] = Tokens(path)
    return _TOKENS[path]


class FileWriter:
    """Collects ids and codes them in groups of about ``lanes`` blocks, two ids to a symbol."""

    def __init__(self, stream, vocabulary: int, block: int, lanes: int):
        self.stream, self.vocabulary, self.block, self.group = stream, vocabulary, block, 2 * block * lanes
        self.kind = np.uint16 if vocabulary <= 1 << 16 else np.uint32
        self.parts: list[np.ndarray] = []
        self.waiting = self.n_bytes = self.n_ids = 0
        self.docs: list[tuple[int, int]] = []
        self._put(HEAD.pack(MAGIC, vocabulary, block))

    def _put(self, data: bytes) -> None:
        self.stream.write(data)
        self.n_bytes += len(data)

    def add(self, doc_id: int, ids: np.ndarray) -> None:
        self.docs.append((doc_id, len(ids)))
        self.parts.append(ids.astype(self.kind))
        self.waiting += len(ids)
        self.n_ids += len(ids)
        if self.waiting >= self.group:
            self._code(False)

    def _code(self, last: bool) -> None:
        ids = np.concatenate(self.parts) if self.parts else np.empty(0, self.kind)
        whole = len(ids) if last else len(ids) // self.group * self.group
        self.parts = [ids[whole:].copy()] if whole < len(ids) else []
        self.waiting = len(ids) - whole
        for at in range(0, whole, self.group):
            self._group(ids[at : min(at + self.group, whole)])

    def _group(self, ids: np.ndarray) -> None:
        symbols, alphabet = paired(ids)
        blocks = encode_blocks(symbols, self.block, len(alphabet))
        table = alphabet.astype("<u4").tobytes()
        packed = zlib.compress(table, 6)
        self._put(GROUP.pack(len(blocks), len(alphabet), len(packed), zlib.crc32(table)) + packed)
        for i, coded in enumerate(blocks):
            part = symbols[i * self.block : (i + 1) * self.block]
            own = unpaired(part, alphabet)
            self._put(BLOCK.pack(len(coded), len(part), len(own), checksum(own)) + coded)

    def close(self) -> None:
        self._code(True)
        at = self.n_bytes
        table = np.array(self.docs, np.int64).reshape(-1, 2)
        self._put(zlib.compress(table.tobytes(), 6))
        self._put(FOOT.pack(at, len(self.docs), self.n_ids, END))
        self.stream.close()


def _alphabet(packed: bytes, n: int, crc: int) -> np.ndarray:
    try:
        table = zlib.decompress(packed)
    except zlib.error as e:
        raise ValueError("an alphabet is damaged") from e
    if zlib.crc32(table) != crc or len(table) != 8 * n:
        raise ValueError("an alphabet is damaged")
    return np.frombuffer(table, "<u4").reshape(n, 2)


def read_file(data, lanes: int = 2048) -> Iterator[tuple[int, np.ndarray]]:
    """(doc_id, ids) of a file's documents in order. ``data``: a seekable binary stream. Holds ``lanes`` blocks at a time."""
    data.seek(0, 2)
    size = data.tell()
    data.seek(size - FOOT.size)
    foot, n_docs, n_ids, end = FOOT.unpack(data.read(FOOT.size))
    if end != END:
        raise ValueError("not a file of token ids, or cut short")
    data.seek(foot)
    docs = np.frombuffer(zlib.decompress(data.read(size - FOOT.size - foot)), np.int64).reshape(n_docs, 2)
    data.seek(0)
    magic, vocabulary, _ = HEAD.unpack(data.read(HEAD.size))
    if magic != MAGIC:
        raise ValueError("not a file of token ids")
    at, held, have, left, alphabet = HEAD.size, [], 0, 0, None
    turn = iter(docs.tolist())
    wanted = next(turn, None)
    while wanted is not None:
        while have < wanted[1]:
            if not left and at < foot:
                left, n_symbols, n, crc = GROUP.unpack(data.read(GROUP.size))
                alphabet = _alphabet(data.read(n), n_symbols, crc)
                at += GROUP.size + n
            parts, lengths, sums = [], [], []
            while at < foot and left and len(parts) < lanes:
                n, count, n_own, crc = BLOCK.unpack(data.read(BLOCK.size))
                parts.append(data.read(n))
                lengths.append(count)
                sums.append((n_own, crc))
                at += BLOCK.size + n
                left -= 1
            if not parts:
                raise ValueError("the file holds fewer ids than it says")
            for symbols, told in zip(decode_blocks(parts, lengths, len(alphabet)), sums, strict=True):
                ids = unpaired(symbols, alphabet)
                if (len(ids), checksum(ids)) != told:
                    raise ValueError("a block is damaged")
                held.append(ids)
                have += len(ids)
        run = np.concatenate(held) if len(held) > 1 else held[0] if held else np.empty(0, np.int64)
        used = 0
        while wanted is not None and have - used >= wanted[1]:
            yield wanted[0], run[used : used + wanted[1]]
            used += wanted[1]
            wanted = next(turn, None)
        held, have = [run[used:]], have - used


NULL_ID = -(1 << 63)  # stands for a null document id in a file


def _encoded(batches: Iterator[pa.RecordBatch], own: Tokens, most_bytes: int = 1 << 23) -> Iterator[tuple[int, int | None, np.ndarray]]:
    """(range, doc_id, ids) of rows in order; texts go to the tokenizer in groups of about ``most_bytes``."""
    held: list[pa.RecordBatch] = []
    size = 0

    def told() -> Iterator[tuple[int, int | None, np.ndarray]]:
        texts = pa.concat_arrays([x["text"] for x in held])
        ranges, ids = ([v for x in held for v in x[c].to_pylist()] for c in ("range", "doc_id"))
        yield from zip(ranges, ids, own.batch(texts), strict=True)

    for batch in batches:
        reach = np.cumsum(pc.fill_null(pc.binary_length(batch["text"]), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            done = int(reach[at - 1]) if at else 0
            to = max(at + 1, int(np.searchsorted(reach, done + most_bytes - size, "right")))
            held.append(batch.slice(at, to - at))
            size += int(reach[to - 1]) - done
            at = to
            if size >= most_bytes or at < batch.num_rows:
                yield from told()
                held, size = [], 0
    if held:
        yield from told()


def _write(folder: str, path: str, end_id: int, block: int, lanes: int, file_ids: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = filesystem(folder)
        fs.create_dir(base, recursive=True)
        own, end = tokens(path), np.array([end_id], np.uint32)
        out, name, current, done = None, "", None, []

        def close() -> None:
            out.close()
            done.append((current, name, len(out.docs), out.n_ids, out.n_bytes))

        for r, doc_id, ids in _encoded(batches, own):
            if out is not None and (r != current or out.n_ids >= file_ids):
                close()
                out = None
            if out is None:
                current, name = r, f"{base}/ids-{r:08d}-{len(done):05d}-{uuid.uuid4().hex}.bin"
                out = FileWriter(fs.open_output_stream(name), own.vocabulary, block, lanes)
            out.add(NULL_ID if doc_id is None else doc_id, np.concatenate((ids, end)))
        if out is not None:
            close()
        if done:
            columns = list(zip(*done, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int32()), *map(pa.array, columns[1:])], names=["range", "file", "n_docs", "n_ids", "n_bytes"])

    return run


def cut_points(lengths: DataFrame, n: int, total: int) -> list[int]:
    """At most n - 1 ids that part (doc_id, n_bytes) into ranges of about equally many bytes.

    Each id is drawn as often as its bytes hold units of 1/64 of a range, the rest by a hash of the id; so quantiles of some
    64 n draws are taken, whatever the corpus. An id that fills ranges of its own is one cut point.
    """
    if n < 2:
        return []
    unit = max(1.0, total / (64 * n))
    chance = F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(1 << 20)) / float(1 << 20)
    times = F.floor(F.col("n_bytes") / unit + chance).cast("int")
    drawn = lengths.filter("doc_id is not null").withColumn("times", times).filter("times > 0")
    drawn = drawn.select("doc_id", F.explode(F.sequence(F.lit(1), F.least("times", F.lit(64 * n)))).alias("k"))
    return sorted(set(drawn.agg(F.percentile_approx("doc_id", [i / n for i in range(1, n)], max(10_000, 32 * n)).alias("c")).first()["c"] or []))


def ranged(rows: DataFrame, cuts: list[int]) -> DataFrame:
    """``rows`` with ``range``, the number of cut points below doc_id; null ids are in range 0.

    The ids between two cut points are parted into cells of a grid, and the small table of (cell, range) is broadcast: as
    many rows as there are cells and cut points. So a row looks at the cut points of its own cell only.
    """
    if not cuts:
        return rows.withColumn("range", F.lit(0))
    lo, cells = cuts[0], 2 * len(cuts)
    width = max(1, -(-(cuts[-1] - lo) // cells))
    cell_of = lambda c: max(0, min(cells, (c - lo) // width + 1))
    bounds = [None, *cuts, None]  # range i holds ids above bounds[i], up to bounds[i + 1]
    table = []
    for i, (a, b) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)):
        table += [(c, i, a, b) for c in range(0 if a is None else cell_of(a), (cells if b is None else cell_of(b)) + 1)]
    small = rows.sparkSession.createDataFrame(table, "__cell long, range int, __above long, __upto long")
    id_ = F.col("doc_id")
    step = F.expr(f"(cast(doc_id as decimal(20,0)) - cast('{lo}' as decimal(20,0))) div cast('{width}' as decimal(20,0))")
    cell = F.when(id_.isNull(), -1).when(id_ < lo, 0).when(id_ >= cuts[-1], cell_of(cuts[-1])).otherwise(F.least(step + 1, F.lit(cells).cast("long")))
    placed = rows.withColumn("__cell", cell.cast("long")).join(F.broadcast(small), "__cell", "left")
    fits = (F.col("__above").isNull() | (id_ > F.col("__above"))) & (F.col("__upto").isNull() | (id_ <= F.col("__upto")))
    return placed.filter(id_.isNull() | fits).withColumn("range", F.coalesce("range", F.lit(0))).select(*rows.columns, "range")


def write(docs: DataFrame, tokenizer: str, folder: str | None = None, end_id: int = 0, block: int = 4096, lanes: int = 2048, range_bytes: int = 32 << 20, most_ranges: int = 65_536, file_ids: int = 1 << 26) -> tuple[DataFrame, str]:
    """Writes the ids of ``docs`` (doc_id, text). Returns the manifest, with the start of every file, and the folder.

    A group of coded blocks holds up to 2 * ``block`` * ``lanes`` ids, as a symbol is mostly two of them. ``range_bytes`` of text make a range; above ``most_ranges`` of them ranges grow. A task holds one batch of texts and its
    coder, and sorts its range with Spark, which spills; so a large range costs time only. A range ends a file at ``file_ids``.
    """
    work = Workspace(docs.sparkSession, "tokens")
    folder = folder or work.path("ids")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    lengths = work.table(rows.select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes")), "lengths")
    total = lengths.agg(F.coalesce(F.sum("n_bytes"), F.lit(0)).alias("n")).first()["n"]
    cuts = cut_points(lengths, max(1, min(most_ranges, -(-total // range_bytes))), total)
    # a range is a partition, by number
    sorted_ = ranged(rows, cuts).repartitionById(len(cuts) + 1, F.col("range")).sortWithinPartitions("range", F.asc_nulls_first("doc_id"))
    done = work.table(sorted_.select("range", "doc_id", "text").mapInArrow(_write(folder, tokenizer, end_id, block, lanes, file_ids), MANIFEST), "manifest")
    # a row per file; names are in order of writing
    starts, total = [], 0
    for r in sorted(done.collect(), key=lambda r: (r["range"], r["file"].rsplit("/", 1)[1])):
        starts.append((r["file"], total, r["n_docs"], r["n_ids"], r["n_bytes"]))
        total += r["n_ids"]
    return docs.sparkSession.createDataFrame(starts, "file string, start long, n_docs long, n_ids long, n_bytes long"), folder


def _read(folder: str, lanes: int, digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = filesystem(folder)
        for batch in batches:
            for name, start in zip(batch["file"].to_pylist(), batch["start"].to_pylist(), strict=True):
                rows, held = [], 0
                with fs.open_input_file(name) as data:
                    for doc_id, ids in read_file(data, lanes):
                        rows.append((None if doc_id == NULL_ID else doc_id, start, len(ids), checksum(ids) if digest else ids.tolist()))
                        start += len(ids)
                        held += len(ids)
                        if len(rows) >= 10_000 or not digest and held > 1 << 20:
                            yield _batch(rows, digest)
                            rows, held = [], 0
                if rows:
                    yield _batch(rows, digest)

    return run


def _batch(rows: list, digest: bool) -> pa.RecordBatch:
    c = list(zip(*rows, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.int64()), pa.array(c[3], pa.int64() if digest else pa.list_(pa.int64()))], names=["doc_id", "start", "n_tokens", "ids_crc32" if digest else "ids"])


def read(manifest: DataFrame, folder: str, lanes: int = 2048, digest: bool = False) -> DataFrame:
    """doc_id, start, n_tokens and the ids (or with ``digest`` their unsigned crc32) of every document in the files."""
    last = "ids_crc32 long" if digest else "ids array<long>"
    return manifest.select("file", "start").repartition(max(1, manifest.count())).mapInArrow(_read(folder, lanes, digest), f"doc_id long, start long, n_tokens long, {last}")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op6_token_ids(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    manifest, folder = write(docs, default_tokenizer())
    return read(manifest, folder, digest=True)
