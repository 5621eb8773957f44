"""An adaptive context-mixing range coder for token ids, run over many blocks in lock step.

Ids are cut into blocks. Each block starts from a fresh model and carries a checksum, so it can be decoded alone. The
model predicts an id in three ways: order 2 and order 1 remember, per hashed context, the id that came last and how
often it held; order 0 is an adaptive distribution over intervals of ids. Two adaptive tables, one keyed by the
confidence of the remembered ids, one by recent outcomes, say how likely each of them is right; their predictions are
mixed with a weight that follows whichever did better, and the mixture drives the range coder.

All blocks of a batch take the same step at the same time, as lanes of arrays, so the cost of a step is shared. Every
number that steers the coder comes from element-wise integer or IEEE arithmetic, so the decoder repeats it exactly. The
coder's own numbers are whole ones below 2**53 in doubles: those are exact, and dividing them is cheap for arrays.

What is coded need not be single ids: ``paired`` turns a run of ids into symbols of an alphabet of its own, where frequent
pairs of ids are one symbol, so that about half as many steps are made.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa

TOTAL = 4096  # of the first decision and of the order-0 intervals
# what is remembered of a last id lies in one line of LINE places: 4 for it alone, 8 for it and the one before, by their hashes
LINES, LINE = 256, 16
INTERVALS = 256
REBUILD = 512  # most steps between rebuilds of the order-0 tables; the first ones come after 16, 32, 64 and so on
SHARE = 1.0 / TOTAL
WORD, LEAST, TOP = 65536.0, 2.0**36, 2.0**32  # a range below LEAST takes in a word; low gives out what is above TOP
MOST = 2.0**48  # the first range: three words
# Pairs of probabilities, of the order-1 and of the order-2 id, lie in the low and the high half of one long; FULL stands for 1
FULL, HIGH, LOW = 4080 << 4, 32, (1 << 32) - 1
WEIGHTS = 6  # bits of a mixing weight


def intervals(vocabulary: int) -> np.ndarray:
    """Edges of the order-0 intervals: single ids at first, then wider by a constant ratio."""
    ratio = (vocabulary / 64 + 1) ** (1 / INTERVALS)
    edges = np.floor(64 * (ratio ** np.arange(INTERVALS + 1) - 1)).astype(np.int64)
    edges = np.maximum.accumulate(np.maximum(edges, np.minimum(np.arange(INTERVALS + 1), vocabulary)))
    edges[-1] = vocabulary
    return np.minimum(edges, vocabulary)


# both halves without the bits that a shift brings from the high to the low one; what the outcomes neither, order 1 and order 2 give back
_FIELDS = {rate: ((1 << HIGH - rate) - 1) << HIGH | (1 << HIGH - rate) - 1 for rate in (3, 5)}
_TOLD = {rate: np.array([0, FULL >> rate, (FULL >> rate) << HIGH]) for rate in (3, 5)}


class Model:
    """The state of all lanes."""

    def __init__(self, lanes: int, vocabulary: int):
        if vocabulary > 1 << 20:
            raise ValueError("ids have to be below 2**20")
        self.n, self.lane = lanes, np.arange(lanes)
        self.edges = intervals(vocabulary)
        width = np.diff(self.edges)
        self.wide = int(width.max()) > 2048  # then the range is filled up before the place in an interval is coded
        self.live = (width > 0).astype(np.int64)
        self.before_live = np.concatenate(([0], np.cumsum(self.live))).astype(np.float32)
        self.where = np.repeat(np.arange(INTERVALS, dtype=np.uint8), width)
        self.width, self.edge = np.maximum(width, 1).astype(np.float64), self.edges[:-1].astype(np.float64)
        # the remembered id, and in the two low bits how often it held
        self.kept = np.zeros(lanes * LINES * LINE, np.int32)
        self.base = self.lane * LINES * LINE
        self.at = np.stack((self.base + 4, self.base))  # order 2, then order 1
        self.base_c, self.base_t = self.lane * (INTERVALS + 1), self.lane * TOTAL
        # probabilities by how sure the remembered ids are (32 contexts a lane), then by the last two outcomes (16)
        self.tally = np.full(lanes * 48, (FULL >> 3) << HIGH | FULL >> 3, np.int64)
        self.row, self.base_a, self.base_b = np.empty((2, lanes), np.int64), self.lane * 32, self.lane * 16 + lanes * 32
        self.weight = np.full(lanes, 1 << WEIGHTS - 1)
        self.past = np.zeros(lanes, np.int64)
        self.counts = np.tile((self.live * 2).astype(np.float32), lanes)
        self.tag = np.zeros(lanes, np.uint32)  # of the last id
        self.seen: list[np.ndarray] = []
        self.step, self.due = 0, 16
        self._rebuild()

    def look(self) -> None:
        """Predictions of the next id: f1, f2 out of TOTAL of the order-1 and the order-2 id, the rest of neither."""
        if self.step == self.due:
            self._rebuild()
            self.due += min(self.due, REBUILD)
        self.m = m = self.kept.take(self.at)
        self.sure, self.c = m & 3, m >> 2
        row = (self.sure[0] << 3) + (self.sure[1] << 1)
        row += self.c[0] == self.c[1]
        np.add(self.base_a, row, out=self.row[0])
        np.add(self.base_b, self.past, out=self.row[1])
        self.p = self.tally.take(self.row)
        a, b = self.p
        self.gap = a - b
        f = (b << WEIGHTS) + self.weight * self.gap
        self.f1, self.f2 = (f.astype("<i8", copy=False).view("<u4") >> WEIGHTS + 4).reshape(-1, 2).T.astype(np.float64, order="C") + 1.0
        self.f12 = self.f1 + self.f2

    def _rebuild(self) -> None:
        """Order-0 frequencies, as running sums up to TOTAL, and for decoding the interval at every point of it."""
        counts = self.counts.reshape(self.n, INTERVALS)
        if self.seen:
            k = self.where.take(np.stack(self.seen)) + self.lane * INTERVALS
            self.counts += np.bincount(k.ravel(), minlength=len(self.counts)).astype(np.float32) * np.float32(24)
            self.seen = []
        sums = np.zeros((self.n, INTERVALS + 1), np.float32)
        np.cumsum(counts, axis=1, out=sums[:, 1:])
        total = sums[:, -1:].copy()
        sums *= (TOTAL - self.before_live[-1]) / total
        np.floor(sums, out=sums)
        sums += self.before_live
        sums[:, -1] = TOTAL
        self.sums, self.inverse = sums.astype(np.int16), None
        heavy = np.flatnonzero(total.ravel() > 6000)
        if len(heavy):
            counts[heavy] = np.ceil(counts[heavy] * np.float32(0.5))

    def interval_at(self, point: np.ndarray) -> np.ndarray:
        if self.inverse is None:
            self.inverse = np.repeat(np.tile(np.arange(INTERVALS, dtype=np.uint8), self.n), np.diff(self.sums, axis=1).ravel())
        return self.inverse.take(self.base_t + point)

    def learn(self, ids: np.ndarray) -> None:
        right = self.c == ids
        said = right.view(np.int8)
        outcome = np.maximum(said[0] << 1, said[1]).astype(np.int64)
        if self.step % 4 == 0:
            halves = self.gap.view("<i4").reshape(-1, 2)
            one, two = halves[:, 0], halves[:, 1]
            gain = np.where(right[0], two, np.where(right[1], one, -(one + two)))
            self.weight = np.minimum(np.maximum(self.weight + np.where(gain > 0, 2, -2), 2), 62)
        rate = 3 if self.step < 64 else 5
        # both probabilities lose 1 / 2**rate of themselves, and the right one gets that of FULL
        self.tally[self.row] = self.p - ((self.p >> rate) & _FIELDS[rate]) + _TOLD[rate].take(outcome)
        m = self.m
        self.kept[self.at] = np.where(right, m + (self.sure < 3), np.where(self.sure > 0, m - 1, ids << 2))
        self.past = (self.past << 2 | outcome) & 15
        self.seen.append(ids)
        fresh = ids.astype(np.uint32) * np.uint32(2654435761)
        line = ((fresh >> np.uint32(24)) << np.uint32(4)) + self.base
        tag = fresh >> np.uint32(13)
        self.at = np.stack((line + (((self.tag + (fresh >> np.uint32(10))) & np.uint32(7)) + np.uint32(4)), line + (tag & np.uint32(3))))
        self.tag = tag
        self.step += 1


class Encoder:
    """Words are given out with what carries into the word before them, which is settled at the end."""

    def __init__(self, lanes: int, steps: int):
        self.low, self.range = np.zeros(lanes), np.full(lanes, MOST)
        self.lanes = lanes
        self.out = np.zeros((3 * steps + 8) * lanes, np.uint32)  # by place, then lane: lanes move on at about the same pace
        self.n = np.arange(lanes)

    def _give(self, go: np.ndarray) -> None:
        low = self.low[go]
        word = np.floor(low * (1.0 / TOP))
        at = self.n[go]
        self.out[at] = word
        self.n[go] = at + self.lanes
        self.low[go] = (low - word * TOP) * WORD

    def shift(self) -> None:
        """Move words out until every lane has room for the next step."""
        while len(go := np.flatnonzero(self.range < LEAST)):
            self._give(go)
            self.range[go] *= WORD

    def finish(self) -> list[bytes]:
        for _ in range(3):
            self._give(np.arange(len(self.n)))
        n = self.n // self.lanes
        words = self.out[: int(n.max()) * self.lanes].reshape(-1, self.lanes)
        while (carry := words >> 16).any():
            words &= 65535
            words[:-1] += carry[1:]
        words = np.ascontiguousarray(words.astype("<u2").T)
        return [words[i, :k].tobytes() for i, k in enumerate(n.tolist())]


class Decoder:
    def __init__(self, parts: list[bytes]):
        lanes = len(parts)
        words = [np.frombuffer(p, "<u2") for p in parts]
        self.lanes = lanes
        data = np.zeros((lanes, max(map(len, words)) + 8), np.uint16)
        for i, w in enumerate(words):
            data[i, : len(w)] = w
        data = np.ascontiguousarray(data.T)
        self.data = data.ravel()
        self.range, self.away = np.full(lanes, MOST), np.zeros(lanes)  # away: how far the code is above low
        for k in range(3):
            self.away = self.away * WORD + data[k]
        self.n = np.arange(lanes) + 3 * lanes

    def shift(self) -> None:
        while len(go := np.flatnonzero(self.range < LEAST)):
            at = self.n[go]
            self.away[go] = self.away[go] * WORD + self.data.take(at, mode="clip")
            self.n[go] = at + self.lanes
            self.range[go] *= WORD


def encode_blocks(ids: np.ndarray, block: int, vocabulary: int) -> list[bytes]:
    """Coded blocks of a run of ids. The last one may be short; the steps it lacks are coded as id 0."""
    if not len(ids):
        return []
    lanes = -(-len(ids) // block)
    steps = block if lanes > 1 else len(ids)
    grid = np.zeros((lanes, steps), np.int32)
    grid.ravel()[: len(ids)] = ids
    model, coder = Model(lanes, vocabulary), Encoder(lanes, steps)
    for tile in range(0, steps, 64):
        for x in np.ascontiguousarray(grid[:, tile : tile + 64].T):
            model.look()
            right2, right1 = x == model.c[0], x == model.c[1]
            known = right2 | right1
            # [0, TOTAL) is dealt to order 2, order 1 and neither
            unit = np.floor(coder.range * SHARE)
            coder.low += unit * np.where(right2, 0.0, np.where(right1, model.f2, model.f12))
            coder.range = unit * np.where(right2, model.f2, np.where(right1, model.f1, TOTAL - model.f12))
            if model.wide:
                coder.shift()
            k = model.where.take(x)
            at = model.base_c + k
            unit = np.floor(coder.range * SHARE)
            below = model.sums.take(at)
            part = np.floor(unit * (model.sums.take(at + 1) - below) / model.width.take(k))
            skip = unit * below + part * (x - model.edge.take(k))
            skip[known] = 0.0
            coder.low += skip
            coder.range = np.where(known, coder.range, part)
            coder.shift()
            model.learn(x)
    return coder.finish()


def decode_blocks(parts: list[bytes], lengths: list[int], vocabulary: int) -> list[np.ndarray]:
    """Ids of coded blocks; blocks coded together need not be decoded together."""
    if not parts:
        return []
    n = max(lengths)
    model, coder = Model(len(parts), vocabulary), Decoder(parts)
    grid = np.zeros((n, len(parts)), np.int32)
    # of a damaged block any number may come out, but no place outside the tables
    for i in range(n):
        model.look()
        unit = np.floor(coder.range * SHARE)
        point = np.floor(coder.away / unit)
        right2, known = point < model.f2, point < model.f12
        coder.away -= unit * np.where(right2, 0.0, np.where(known, model.f2, model.f12))
        coder.range = unit * np.where(right2, model.f2, np.where(known, model.f1, TOTAL - model.f12))
        if model.wide:
            coder.shift()
        x = np.where(right2, model.c[0], model.c[1])
        unit = np.floor(coder.range * SHARE)
        k = model.interval_at(np.minimum(np.floor(coder.away / unit), TOTAL - 1.0).astype(np.int64))
        at = model.base_c + k
        below, width = model.sums.take(at), model.width.take(k)
        part = np.maximum(np.floor(unit * (model.sums.take(at + 1) - below) / width), 1.0)
        rest = coder.away - unit * below
        off = np.minimum(np.floor(rest / part), width - 1.0)
        x = np.where(known, x, (model.edge.take(k) + off).astype(np.int32))
        coder.away = np.where(known, coder.away, rest - part * off)
        coder.range = np.where(known, coder.range, part)
        coder.shift()
        grid[i] = x
        model.learn(x)
    return [grid[: lengths[j], j] for j in range(len(parts))]


NONE = (1 << 32) - 1  # the second id of a symbol that stands for one only


def paired(ids: np.ndarray, most: int = 1 << 19) -> tuple[np.ndarray, np.ndarray]:
    """(symbols, alphabet): ids two by two. The alphabet's rows are a symbol's two ids, the most frequent symbol first.

    At most ``most`` pairs, those that come twice or more, are symbols; other pairs are spelled by two symbols of one id each,
    as is an odd id at the end. ``unpaired`` is the way back.
    """
    ids = np.asarray(ids).astype(np.uint32)
    even = len(ids) // 2 * 2
    kind, bits = (np.uint32, 16) if int(ids.max(initial=0)) < 1 << 16 else (np.uint64, 32)
    coded = pa.array(ids[0:even:2].astype(kind) << kind(bits) | ids[1:even:2]).dictionary_encode()
    code, keys = coded.indices.to_numpy(), coded.dictionary.to_numpy()
    del coded
    count = np.bincount(code, minlength=len(keys))
    twice = np.flatnonzero(count > 1)
    if len(twice) > most:
        twice = twice[np.argsort(-count[twice], kind="stable")[:most]]
    place = np.full(len(keys), -1, np.int64)
    place[twice] = np.arange(len(twice))
    symbol = place[code]
    spelled = np.flatnonzero(symbol < 0)
    single, which = np.unique(np.concatenate((ids[0:even:2][spelled], ids[1:even:2][spelled], ids[even:])), return_inverse=True)
    alone = np.bincount(which, minlength=len(single))
    order = np.argsort(-np.concatenate((count[twice], alone)), kind="stable")
    rank = np.empty(len(order), np.int32)
    rank[order] = np.arange(len(order), dtype=np.int32)
    size = np.ones(len(symbol), np.int64)
    size[spelled] = 2
    ends = np.cumsum(size)
    out = np.empty((int(ends[-1]) if len(ends) else 0) + len(ids) - even, np.int32)
    out[ends - 1] = rank[symbol]  # what is spelled comes below
    which = rank[which + len(twice)]
    out[ends[spelled] - 2], out[ends[spelled] - 1] = which[: len(spelled)], which[len(spelled) : 2 * len(spelled)]
    out[len(out) - (len(ids) - even) :] = which[2 * len(spelled) :]
    first = np.concatenate(((keys[twice] >> kind(bits)).astype(np.uint32), single))
    second = np.concatenate(((keys[twice] & kind((1 << bits) - 1)).astype(np.uint32), np.full(len(single), NONE, np.uint32)))
    return out, np.stack((first, second), axis=1)[order]


def unpaired(symbols: np.ndarray, alphabet: np.ndarray) -> np.ndarray:
    ids = np.ascontiguousarray(alphabet, np.uint32).view(np.uint64).ravel().take(symbols).view(np.uint32)
    return ids[ids != NONE]


def checksum(ids: np.ndarray) -> int:
    return zlib.crc32(np.asarray(ids).astype("<u4").tobytes())
