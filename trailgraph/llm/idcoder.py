"""Context-mixing range coder for token ids: many blocks at a time, one numpy lane per block.

A block is coded from a fresh model and checked by its own CRC, so any block can be read alone. For
each id the model has an order-2 and an order-1 prediction (what followed the same two ids, or the
same id, last time in this block) and an order-0 list of the block's ids by how often they were coded from it. One of
16 events is coded - order-2 right, order-1 right, a new id, or the class (bit length) of the id's
place in the order-0 list - followed by the bits that are left.

Three adaptive distributions predict the event: by how far both contexts have proved right, by how far
the order-1 context has, and by the block alone. They are mixed by weights that each lane learns from
what the events cost: a weight is multiplied by the probability that its distribution gave the event, and a
small share of all weight is dealt out evenly, so that a distribution that was wrong can come back. All
arithmetic is on integers, so writer and reader agree on every machine.

Arithmetic coding: carry-less range coder with 64-bit low and range, 32-bit words, totals of 2^16.
``LANES`` blocks at most are coded side by side, which bounds the memory of a group of any size.
"""

from __future__ import annotations

import zlib

import numpy as np

BLOCK, EVENTS, SLOTS, LANES = 4096, 16, 4096, 1536
NONE = 0xFFFF
_U = np.uint64
_W, _LOW = _U(32), _U(0xFFFFFFFF)
_RATE = 6
_STEP = (1 << 16) // EVENTS
_LENGTH = np.array([int(x).bit_length() for x in range(1 << 16)], np.uint8)


def _targets() -> np.ndarray:
    """Cumulative distributions that an event pulls towards: nearly all on it, and a share for each other."""
    out = np.zeros((EVENTS, EVENTS + 1), np.int32)
    for s in range(EVENTS):
        f = np.full(EVENTS, 64)
        f[s] = (1 << 16) - 64 * (EVENTS - 1)
        out[s, 1:] = np.cumsum(f)
    return out[:, :EVENTS].copy()


_PULL = _targets()


_SHARED, _LEARNED = 1 << 9, (1 << 16) - 3 * (1 << 9)


class Model:
    """State of ``n`` lanes; reset by making a new one. The lanes in use are always the first ``m``."""

    def __init__(self, n: int):
        self.n = n
        self.t2, self.t1 = np.full(n * SLOTS, NONE, np.uint16), np.full(n * SLOTS, NONE, np.uint16)
        self.k2, self.k1 = np.zeros(n * SLOTS, np.uint8), np.zeros(n * SLOTS, np.uint8)
        start = np.arange(EVENTS, dtype=np.int32) * _STEP
        self.by_both, self.by_one, self.by_lane = (np.tile(start, (n * k, 1)) for k in (9, 3, 1))
        self.w = np.full((3, n), (1 << 16) // 3, np.int64)
        self.p1, self.p2 = np.zeros(n, np.int64), np.zeros(n, np.int64)
        self.base, self.nine, self.three, self.row = np.arange(n) * SLOTS, np.arange(n) * 9, np.arange(n) * 3, np.arange(n) * EVENTS

    def look(self, m: int) -> tuple:
        """Slots, predictions, states and the three distributions (cumulative) of the next id in the first ``m`` lanes, and their weights."""
        p1, p2 = self.p1[:m], self.p2[:m]
        s2 = self.base[:m] + (((p2 * 40503 + p1 * 10007) * 2654435761 >> 16) & (SLOTS - 1))
        s1 = self.base[:m] + ((p1 * 2654435761 >> 16) & (SLOTS - 1))
        one = self.k1[s1]
        both = self.nine[:m] + 3 * self.k2[s2] + one
        one = self.three[:m] + one
        w = self.w[:, :m] >> 8
        w[2] = 256 - w[0] - w[1]
        return s2, s1, self.t2[s2], self.t1[s1], both, one, (self.by_both[both], self.by_one[one], self.by_lane[:m]), w

    def mixed(self, seen: tuple) -> np.ndarray:
        """The cumulative distribution of the next event in every lane."""
        (a, b, c), w = seen[6], seen[7].astype(np.int32)[:, :, None]
        return (a * w[0] + b * w[1] + c * w[2]) >> 8

    def share(self, seen: tuple, event: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        """Start and width of ``event`` in the mixture, and its width in each distribution."""
        at, last = self.row[: len(event)] + event, event == EVENTS - 1
        after = at + ~last
        starts, ends = [], []
        for cum in seen[6]:
            flat = cum.reshape(-1)
            starts.append(flat[at].astype(np.int64))
            ends.append(np.where(last, 1 << 16, flat[after]).astype(np.int64))
        w = seen[7]
        start = (starts[0] * w[0] + starts[1] * w[1] + starts[2] * w[2]) >> 8
        end = (ends[0] * w[0] + ends[1] * w[1] + ends[2] * w[2]) >> 8
        return start, end - start, [e - s for s, e in zip(starts, ends)]

    def learn(self, seen: tuple, event: np.ndarray, widths: list[np.ndarray], code: np.ndarray) -> None:
        s2, s1, c2, c1, both, one, (a, b, c), _ = seen
        m = len(code)
        proved = self.w[:, :m] * np.stack(widths)
        self.w[:, :m] = proved * _LEARNED // proved.sum(0) + _SHARED
        pull = _PULL[event]
        self.by_both[both] = a + ((pull - a) >> _RATE)
        self.by_one[one] = b + ((pull - b) >> _RATE)
        c += (pull - c) >> _RATE
        self.k2[s2] = 1 + (c2 == code)
        self.k1[s1] = 1 + (c1 == code)
        self.t2[s2] = code
        self.t1[s1] = code
        self.p2[:m] = self.p1[:m]
        self.p1[:m] = code


class Ranks:
    """Order-0 lists of ``n`` lanes: codes by falling count, so that a code's place follows its frequency.

    ``above[c]`` is how many codes of the lane have a count over c, hence also where the codes of count c begin; one more
    of a code changes places with the first of its count and moves that border by one.
    """

    def __init__(self, n: int):
        self.codes, self.counts, self.above = (np.zeros((n, BLOCK + 1), np.uint16) for _ in range(3))

    def count(self, lane: np.ndarray, code: np.ndarray, d: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """One more of ``code``, which is at place ``d`` (None: new). Gives its place now, and which code is at its old place."""
        c = np.zeros(len(lane), np.int64) if d is None else self.counts[lane, d].astype(np.int64)
        to = self.above[lane, c].astype(np.int64)
        d = to if d is None else d
        other = self.codes[lane, to]
        self.codes[lane, d] = other
        self.codes[lane, to] = code
        self.counts[lane, to] = c + 1
        self.above[lane, c] = to + 1
        return to, other, d


def _settle(low: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Lanes whose upper word is fixed, after cutting ranges that got too small."""
    same = ((low ^ (low + size)) >> _W) == 0
    cut = ~same & (size <= _LOW)
    if cut.any():
        size[cut] = (_U(0) - low[cut]) & _LOW
    return same | cut


class Writer:
    def __init__(self, n: int, room: int):
        self.low, self.size = np.zeros(n, _U), np.full(n, 0xFFFFFFFFFFFFFFFF, _U)
        self.out, self.at = np.zeros((n, room), np.uint32), np.zeros(n, np.int64)

    def put(self, lane: np.ndarray, start: np.ndarray, width: np.ndarray) -> None:
        low, size = self.low[lane], self.size[lane]
        r = size >> _U(16)
        low = low + start.astype(_U) * r
        size = width.astype(_U) * r
        while (ready := _settle(low, size)).any():
            who = lane[ready]
            self.out[who, self.at[who]] = (low[ready] >> _W).astype(np.uint32)
            self.at[who] += 1
            low[ready] <<= _W
            size[ready] <<= _W
        self.low[lane], self.size[lane] = low, size

    def finish(self) -> list[bytes]:
        every = np.arange(len(self.at))
        for shift in (_W, _U(0)):
            self.out[every, self.at] = ((self.low >> shift) & _LOW).astype(np.uint32)
            self.at += 1
        return [self.out[i, :k].tobytes() for i, k in enumerate(self.at)]


class Reader:
    def __init__(self, blocks: list[bytes]):
        n = len(blocks)
        size = np.array([len(b) // 4 for b in blocks])
        self.data = np.zeros((n, int(size.max()) + 2), np.uint32)
        for i, b in enumerate(blocks):
            self.data[i, : size[i]] = np.frombuffer(b, np.uint32)
        self.low, self.size = np.zeros(n, _U), np.full(n, 0xFFFFFFFFFFFFFFFF, _U)
        self.code = (self.data[:, 0].astype(_U) << _W) | self.data[:, 1].astype(_U)
        self.at = np.full(n, 2)

    def value(self, lane: np.ndarray) -> np.ndarray:
        return np.minimum((self.code[lane] - self.low[lane]) // (self.size[lane] >> _U(16)), _U(65535)).astype(np.int32)

    def skip(self, lane: np.ndarray, start: np.ndarray, width: np.ndarray) -> None:
        low, size, code = self.low[lane], self.size[lane], self.code[lane]
        r = size >> _U(16)
        low = low + start.astype(_U) * r
        size = width.astype(_U) * r
        while (ready := _settle(low, size)).any():
            who = lane[ready]
            code[ready] = (code[ready] << _W) | self.data[who, np.minimum(self.at[who], self.data.shape[1] - 1)].astype(_U)
            self.at[who] += 1
            low[ready] <<= _W
            size[ready] <<= _W
        self.low[lane], self.size[lane], self.code[lane] = low, size, code


def _crcs(ids: np.ndarray) -> np.ndarray:
    return np.array([zlib.crc32(ids[i : i + BLOCK].tobytes()) for i in range(0, len(ids), BLOCK)], np.uint32)


def encode(ids: np.ndarray) -> tuple[np.ndarray, list[bytes], np.ndarray]:
    """uint32 ids -> (dictionary, coded blocks of ``BLOCK`` ids, CRC of each block's ids). At most 65,534 distinct ids."""
    known, codes = np.unique(ids, return_inverse=True)
    if len(known) > NONE - 1:
        raise ValueError("more than 65,534 distinct ids in a group")
    step = LANES * BLOCK
    return known, [b for i in range(0, len(ids), step) for b in _encode_lanes(codes[i : i + step], len(known))], _crcs(ids)


def _new_bits(kinds: int) -> int:
    return max(1, int(kinds - 1).bit_length())


def _encode_lanes(codes: np.ndarray, kinds: int) -> list[bytes]:
    n, bits = -(-len(codes) // BLOCK), _new_bits(kinds)
    final = len(codes) - BLOCK * (n - 1)
    x = np.zeros(n * BLOCK, np.int64)
    x[: len(codes)] = codes
    x = np.ascontiguousarray(x.reshape(n, BLOCK).T)
    model, writer = Model(n), Writer(n, BLOCK * 2 + 8)
    place, ranks = np.full(n * kinds, NONE, np.uint16), Ranks(n)
    every, first = np.arange(n), np.arange(n) * kinds
    for t in range(BLOCK if n > 1 else final):
        m = n if t < final else n - 1
        lane, code = every[:m], x[t, :m]
        seen = model.look(m)
        spot = first[:m] + code
        d = place[spot].astype(np.int64)
        new = d == NONE
        event = np.where(seen[2] == code, 0, np.where(seen[3] == code, 1, np.where(new, 2, 3 + _LENGTH[d]))).astype(np.int64)
        start, width, widths = model.share(seen, event)
        writer.put(lane, start, width)
        extra = np.where(event == 2, bits, np.maximum(event - 4, 0))
        more = np.flatnonzero(extra)
        if len(more):
            rest = np.where(new[more], code[more], d[more] - (1 << extra[more]))
            left = 16 - extra[more]
            writer.put(more, rest << left, np.int64(1) << left)
        if len(who := np.flatnonzero(event >= 3)):
            to, other, old = ranks.count(who, code[who], d[who])
            place[first[who] + other] = old
            place[spot[who]] = to
        if len(who := np.flatnonzero(new)):
            place[spot[who]] = ranks.count(who, code[who])[0]
        model.learn(seen, event, widths, code)
    return writer.finish()


def decode(known: np.ndarray, blocks: list[bytes], total: int, crcs: np.ndarray) -> np.ndarray:
    """The ids again; raises ValueError where a block's CRC doesn't fit."""
    if not blocks:
        return np.zeros(0, np.uint32)
    step = LANES * BLOCK
    parts = [_decode_lanes(blocks[i : i + LANES], min(step, total - i * BLOCK), len(known)) for i in range(0, len(blocks), LANES)]
    ids = known[np.minimum(np.concatenate(parts), len(known) - 1)].astype(np.uint32)
    if ((found := _crcs(ids)) != crcs).any():
        raise ValueError(f"checksum of block {int(np.flatnonzero(found != crcs)[0])} does not fit")
    return ids


def _decode_lanes(blocks: list[bytes], total: int, kinds: int) -> np.ndarray:
    n, bits = len(blocks), _new_bits(kinds)
    final = total - BLOCK * (n - 1)
    model, reader = Model(n), Reader(blocks)
    ranks, every = Ranks(n), np.arange(n)
    x = np.zeros((BLOCK, n), np.int64)
    for t in range(BLOCK if n > 1 else final):
        m = n if t < final else n - 1
        lane = every[:m]
        seen = model.look(m)
        value = reader.value(lane)
        event = (model.mixed(seen) <= value[:, None]).sum(1) - 1
        start, width, widths = model.share(seen, event)
        reader.skip(lane, start, width)
        extra = np.where(event == 2, bits, np.maximum(event - 4, 0))
        rest = np.zeros(m, np.int64)
        more = np.flatnonzero(extra)
        if len(more):
            left = 16 - extra[more]
            got = reader.value(more).astype(np.int64) >> left
            reader.skip(more, got << left, np.int64(1) << left)
            rest[more] = got
        d = np.where(event <= 3, 0, np.minimum(rest + (1 << extra), BLOCK - 1))
        code = np.where(event == 0, seen[2], np.where(event == 1, seen[3], np.where(event == 2, rest, ranks.codes[lane, d]))).astype(np.int64)
        if len(who := np.flatnonzero(event >= 3)):
            ranks.count(who, code[who], d[who])
        if len(who := np.flatnonzero(event == 2)):
            ranks.count(who, code[who])
        model.learn(seen, event, widths, code)
        x[t, :m] = code
    return x.T.ravel()[:total]
