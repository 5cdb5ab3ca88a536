"""Adaptive context-mixing range coder for token ids, many blocks at a time.

Ids are cut into blocks of ``BLOCK``; each block starts from a fresh model and a
fresh coder and carries a CRC-32 of its ids, so any block can be decoded, or found
broken, on its own. All blocks of a segment advance in lockstep, one id a step, as
the lanes of numpy arrays, which is what makes an adaptive coder affordable here.

Model of a block. Order 2 (hash of the last two ids) and order 1 (hash of the last id)
each predict one id, with a confidence of 0 to 7 by how often they were right. Adaptive
chances, one for each confidence, go through the logistic domain into two mixers whose
weights learn from every id: the first gives the chance that order 2's id comes, the
second that order 1's comes if that fails. Any other id is coded by order 0: how often each single id
was coded so in this block, on top of a fixed share that falls with the id's number, as vocabularies
are numbered by frequency. Counts stand in a tree of partial sums per lane.

Coder. Carry-less range coder with 64-bit low and range and 16-bit output words. The
model is made of integers alone, so every machine decodes what another one wrote.
"""

from __future__ import annotations

import math
import struct
import zlib

import numpy as np

#: Ids of a block; slots of order 1 and 2 as powers of two.
BLOCK, SLOTS1, SLOTS2 = 4096, 11, 12
#: What a coded id adds to its order-0 count, beside its fixed share.
GAIN = 64
_IDS = 1 << 16
#: Fixed shares of order 0: one each, and the more the lower the id; cumulated. With ``GAIN`` they stay below 2**20 in a block.
_SHARE = np.concatenate([[0], np.cumsum(1 + 12_000 // (np.arange(_IDS, dtype=np.int64) + 300))])
_STEPS = {k: np.arange(17) << k for k in (12, 8, 4, 0)}
_LATER = (np.arange(17) > np.arange(16)[:, None]).astype(np.uint16)
#: Chances of 12 bits to the logistic domain in steps of 1/256, and back.
_STRETCH = np.array([round(256 * math.log((k + 0.5) / (4095.5 - k))) for k in range(4096)], np.int32)
_SQUASH = np.array([min(4095, max(1, round(4096 / (1 + math.exp(-d / 256))))) for d in range(-2047, 2048)], np.int32)
_TOP, _BOT, _LOW = np.uint64(1 << 48), np.uint64(1 << 32), np.uint64((1 << 32) - 1)
_16, _48, _ONE, _12 = np.uint64(16), np.uint64(48), np.uint64(1), np.uint64(12)
_MAGIC = b"IDRC3" + struct.pack("<I", zlib.crc32(_STRETCH.tobytes() + _SQUASH.tobytes() + _SHARE.tobytes()))
_HEAD = len(_MAGIC)


class _Mixer:
    """Chances of 12 bits from two inputs, by weights of each lane and context that learn."""

    def __init__(self, lanes: int, contexts: int):
        self.w = np.full((2, lanes * contexts), 1 << 15, np.int32)

    def mix(self, at: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        self.at, self.x, self.wa, self.wb = at, (_STRETCH[a >> 4], _STRETCH[b >> 4]), self.w[0][at], self.w[1][at]
        self.p = _SQUASH[np.minimum(np.maximum((self.wa * self.x[0] >> 16) + (self.wb * self.x[1] >> 16), -2047), 2047) + 2047]
        return self.p

    def learn(self, came: np.ndarray, asked: np.ndarray) -> None:
        error = ((came << 12) - self.p) * asked
        for w, old, x in zip(self.w, (self.wa, self.wb), self.x, strict=True):
            w[self.at] = np.minimum(np.maximum(old + (x * error >> 9), -(1 << 19)), 1 << 19)


class _Order0:
    """How often each id was coded, in a tree of sixteen children a node per lane; nodes hold sums of the children before each child."""

    def __init__(self, lanes: int):
        self.levels = [(k, np.zeros((lanes << 12 - k, 17), np.uint16)) for k in (12, 8, 4, 0)]
        self.seen = np.zeros(lanes, np.int64)

    def total(self, lanes: np.ndarray) -> np.ndarray:
        return _SHARE[-1] + GAIN * self.seen[lanes]

    def span(self, lanes: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Begin and size of ids."""
        begin = np.zeros(len(x), np.int64)
        for k, sums in self.levels:
            at = ((lanes << 12 - k) + (x >> k + 4)) * 17 + (x >> k & 15)
            own = sums.reshape(-1)[at]
            begin += own
        return _SHARE[x] + GAIN * begin, _SHARE[x + 1] - _SHARE[x] + GAIN * (sums.reshape(-1)[at + 1] - own).astype(np.int64)

    def find(self, lanes: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The ids whose spans hold ``u``, and their begins and sizes."""
        x, before = np.zeros(len(u), np.int64), np.zeros(len(u), np.int64)
        pick = np.arange(len(u))
        for k, sums in self.levels:
            row = sums[(lanes << 12 - k) + (x >> k + 4)]
            ends = _SHARE[x[:, None] + _STEPS[k]] + GAIN * (before[:, None] + row)
            d = (ends[:, 1:16] <= u[:, None]).sum(1)
            before += row[pick, d]
            x += d << k
        return x, ends[pick, d], ends[pick, d + 1] - ends[pick, d]

    def learn(self, lanes: np.ndarray, x: np.ndarray) -> None:
        self.seen[lanes] += 1
        for k, sums in self.levels:
            sums[(lanes << 12 - k) + (x >> k + 4)] += _LATER[x >> k & 15]


class _Model:
    def __init__(self, lanes: int):
        self.lane = np.arange(lanes)
        self.base1, self.base2 = self.lane << SLOTS1, self.lane << SLOTS2
        self.id1, self.id2 = np.zeros(lanes << SLOTS1, np.uint16), np.zeros(lanes << SLOTS2, np.uint16)
        self.sure1, self.sure2 = np.zeros(lanes << SLOTS1, np.uint8), np.zeros(lanes << SLOTS2, np.uint8)
        # chances of 16 bits that a prediction is right: confidence, whether both agree, lane
        self.right2, self.right1, self.next1 = (np.full(16 * lanes, 1 << 14, np.int32) for _ in range(3))
        self.first, self.second = _Mixer(lanes, 2), _Mixer(lanes, 1)
        self.order0 = _Order0(lanes)
        self.last1 = self.last2 = np.zeros(lanes, np.int64)

    def predict(self):
        """Predicted ids of order 2 and 1, and of 4096 the shares of order 2's, and of both."""
        n, h = len(self.lane), self.last1 * 40503
        self.slot1 = self.base1 + (h >> 3 & ((1 << SLOTS1) - 1))
        self.slot2 = self.base2 + ((h ^ (self.last2 * 30011)) >> 2 & ((1 << SLOTS2) - 1))
        self.p2, self.p1 = self.id2[self.slot2], self.id1[self.slot1]
        self.s2, self.s1 = self.sure2[self.slot2], self.sure1[self.slot1]
        self.agree = (self.p2 == self.p1).astype(np.int64)
        self.at2 = (self.s2.astype(np.int64) * 2 + self.agree) * n + self.lane
        self.at1 = (self.s1.astype(np.int64) * 2 + self.agree) * n + self.lane
        a = self.first.mix(self.agree * n + self.lane, self.right2[self.at2], self.right1[self.at1])
        b = self.second.mix(self.lane, self.next1[self.at1], self.next1[self.at2])
        f0 = np.minimum(a, 4094)
        f1 = np.where(self.agree, 0, np.minimum(np.maximum((4096 - f0) * b >> 12, 1), 4095 - f0))
        return self.p2, self.p1, f0.astype(np.int64), (f0 + f1).astype(np.int64)

    def learn(self, ids: np.ndarray, outcome: np.ndarray) -> None:
        hit2, hit1 = (ids == self.p2).astype(np.int32), (ids == self.p1).astype(np.int32)
        asked = ((outcome > 0) & (self.agree == 0)).astype(np.int32)
        self.first.learn(hit2, np.int32(1))
        self.second.learn(hit1, asked)
        for chance, at, hit in ((self.right2, self.at2, hit2), (self.right1, self.at1, hit1)):
            old = chance[at]
            chance[at] = old + (((hit << 16) - hit - old) >> 5)
        old = self.next1[self.at1]
        self.next1[self.at1] = old + ((((hit1 << 16) - hit1 - old) * asked) >> 5)
        for held, sure, slot, p, s, hit in ((self.id2, self.sure2, self.slot2, self.p2, self.s2, hit2), (self.id1, self.sure1, self.slot1, self.p1, self.s1, hit1)):
            held[slot] = np.where((hit > 0) | (s > 1), p, ids)
            sure[slot] = np.where(hit > 0, np.minimum(s + 1, 7), s >> 1)
        self.last2, self.last1 = self.last1, ids.astype(np.int64)


def _unsettled(low: np.ndarray, wide: np.ndarray) -> np.ndarray:
    """Lanes that must put out a word: the first word is settled, or the range has become too narrow."""
    return np.flatnonzero(((low ^ (low + wide)) < _TOP) | (wide < _BOT))


def _narrowed(low: np.ndarray, wide: np.ndarray) -> np.ndarray:
    return np.where((low ^ (low + wide)) < _TOP, wide, (~low + _ONE) & _LOW) << _16


def encode(ids: np.ndarray) -> bytes:
    """A segment: header, block lengths and checksums, then each block's words."""
    n = len(ids)
    lanes = -(-n // BLOCK)
    padded = np.zeros((lanes, BLOCK), np.uint16)
    padded.reshape(-1)[:n] = ids
    sums = np.array([zlib.crc32(row) for row in padded], np.uint32)
    if not lanes:
        return _MAGIC + struct.pack("<QII", 0, 0, BLOCK)
    columns = np.ascontiguousarray(padded.T)
    m = _Model(lanes)
    low, wide = np.zeros(lanes, np.uint64), np.full(lanes, (1 << 64) - 1, np.uint64)
    words, used = np.zeros((lanes, BLOCK * 3 + 8), np.uint16), np.zeros(lanes, np.int64)
    for k in range(min(n, BLOCK)):
        x = columns[k]
        p2, p1, c0, c1 = m.predict()
        outcome = np.where(x == p2, 0, np.where(x == p1, 1, 2))
        begin = np.where(outcome == 0, 0, np.where(outcome == 1, c0, c1))
        size = np.where(outcome == 0, c0, np.where(outcome == 1, c1, 4096)) - begin
        step = wide >> _12
        low = low + step * begin.astype(np.uint64)
        wide = step * size.astype(np.uint64)
        new = np.flatnonzero(outcome == 2)
        if len(new):
            xs = x[new].astype(np.int64)
            begin, size = m.order0.span(new, xs)
            part = wide[new] // m.order0.total(new).astype(np.uint64)
            low[new] += part * begin.astype(np.uint64)
            wide[new] = part * size.astype(np.uint64)
            m.order0.learn(new, xs)
        m.learn(x, outcome)
        while len(out := _unsettled(low, wide)):
            lo = low[out]
            words[out, used[out]] = (lo >> _48).astype(np.uint16)
            used[out] += 1
            wide[out] = _narrowed(lo, wide[out])
            low[out] = lo << _16
    for _ in range(4):
        words[m.lane, used] = (low >> _48).astype(np.uint16)
        used += 1
        low = low << _16
    body = b"".join(w[:u].tobytes() for w, u in zip(words, used.tolist(), strict=True))
    return _MAGIC + struct.pack("<QII", n, lanes, BLOCK) + used.astype("<u4").tobytes() + sums.astype("<u4").tobytes() + body


def decode(data: bytes) -> np.ndarray:
    """The ids of a segment; raises if a block's checksum doesn't hold."""
    if data[:_HEAD] != _MAGIC:
        raise ValueError("not an id segment")
    n, lanes, block = struct.unpack_from("<QII", data, _HEAD)
    if not lanes:
        return np.zeros(0, np.uint16)
    used = np.frombuffer(data, "<u4", lanes, _HEAD + 16).astype(np.int64)
    sums = np.frombuffer(data, "<u4", lanes, _HEAD + 16 + 4 * lanes)
    body = np.frombuffer(data, np.uint8, offset=_HEAD + 16 + 8 * lanes).view("<u2").astype(np.uint64)
    body = np.concatenate([body, np.zeros(8, np.uint64)])
    at = np.cumsum(used) - used
    code = np.zeros(lanes, np.uint64)
    for _ in range(4):
        code = (code << _16) | body[at]
        at += 1
    m = _Model(lanes)
    low, wide = np.zeros(lanes, np.uint64), np.full(lanes, (1 << 64) - 1, np.uint64)
    columns = np.zeros((block, lanes), np.uint16)
    for k in range(min(n, block)):
        p2, p1, c0, c1 = m.predict()
        step = wide >> _12
        v = ((code - low) // step).astype(np.int64)
        outcome = (v >= c0).astype(np.int64) + (v >= c1)
        x = np.where(outcome == 0, p2, p1)
        begin = np.where(outcome == 0, 0, np.where(outcome == 1, c0, c1))
        size = np.where(outcome == 0, c0, np.where(outcome == 1, c1, 4096)) - begin
        low = low + step * begin.astype(np.uint64)
        wide = step * size.astype(np.uint64)
        new = np.flatnonzero(outcome == 2)
        if len(new):
            total = m.order0.total(new)
            part = wide[new] // total.astype(np.uint64)
            xs, begin, size = m.order0.find(new, np.minimum(((code[new] - low[new]) // part).astype(np.int64), total - 1))
            x[new] = xs
            low[new] += part * begin.astype(np.uint64)
            wide[new] = part * size.astype(np.uint64)
            m.order0.learn(new, xs)
        columns[k] = x
        m.learn(x, outcome)
        while len(out := _unsettled(low, wide)):
            lo = low[out]
            code[out] = (code[out] << _16) | body[np.minimum(at[out], len(body) - 1)]
            at[out] += 1
            wide[out] = _narrowed(lo, wide[out])
            low[out] = lo << _16
    rows = np.ascontiguousarray(columns.T)
    flat = rows.reshape(-1)
    flat[n:] = 0
    bad = [i for i, row in enumerate(rows) if zlib.crc32(row) != sums[i]]
    if bad:
        raise ValueError(f"checksum of block {bad[0]} does not hold")
    return flat[:n]
