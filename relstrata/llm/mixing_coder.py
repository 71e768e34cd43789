"""Adaptive context-mixing range coder for token ids, many blocks at a time.

Per id, the orders 2, 1 and 0 each predict the id that last held out under their context, with
a confidence. One symbol says which prediction holds (order 2, 1, 0, none); its counts are
mixed from three tables, one under the confidence of each order. An id that no order
predicts is coded by order 0 as hex digits under adaptive counts. All counts
and predictions start afresh in every block, so any block can be read alone; its
checksum is verified when read. Blocks advance together, one id each a step, so that every
step is a few array operations. Integers only: any machine decodes what another wrote.

A block: magic, ids, 16-bit code words (both uint32), crc32 of the ids as little-endian uint32,
hex digits of an id (uint32), code words.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

MAGIC = b"IDCN"
HEAD = "<4sIIII"
HEAD_SIZE = struct.calcsize(HEAD)
#: Contexts kept a block for order 2 and order 1.
SLOTS2, SLOTS1 = 4096, 2048
#: Rows of digit counts: the first digit, the second by the first, the third by both, each later one by 8 folded bits.
LEAD_ROWS, FOLD_ROWS = 273, 256
INC, LIMIT = 24, 8000
NONE = np.uint32(0xFFFFFFFF)
U = np.uint64
_LOW48, _MIN = U((1 << 48) - 1), U(1 << 32)
#: Four counts of 16 bits in one word; ones everywhere; a count's step and its place by symbol.
_ONES = U(0x0001000100010001)
_PLACE = np.arange(4, dtype=U) * U(16)
_STEP = U(INC) << _PLACE
_HALF = U(0x7FFF7FFF7FFF7FFF)


class Model:
    """Predictions and counts of ``lanes`` blocks. A prediction is a word of an id and its confidence."""

    def __init__(self, lanes: int, digits: int):
        self.lanes, self.digits = lanes, digits
        self.rows = LEAD_ROWS + FOLD_ROWS * max(0, digits - 3)
        self.each = np.arange(lanes)
        empty = U(NONE) << U(8)
        self.guess = [np.full(lanes * n, empty, U) for n in (SLOTS2, SLOTS1, 1)]
        self.flag = [np.full(lanes * 16, _ONES, U) for _ in range(3)]
        self.digit = np.ones((lanes * self.rows, 16), np.uint16)
        self.p1 = np.zeros(lanes, np.int64)
        self.p2 = np.zeros(lanes, np.int64)

    def narrow(self, keep: int) -> Model:
        """The first ``keep`` blocks (the others have ended)."""
        new = Model.__new__(Model)
        new.lanes, new.digits, new.rows, new.each = keep, self.digits, self.rows, self.each[:keep]
        new.guess = [g[: keep * n] for g, n in zip(self.guess, (SLOTS2, SLOTS1, 1), strict=True)]
        new.flag = [f[: keep * 16] for f in self.flag]
        new.digit, new.p1, new.p2 = self.digit[: keep * self.rows], self.p1[:keep], self.p2[:keep]
        return new

    def look(self) -> None:
        """Predictions for the next id of every block, and the mixed counts."""
        h2 = ((self.p1 * 40503 + self.p2 * 60493 + (self.p2 >> 5)) & 0xFFFFFFF) >> 4
        self.slot = [self.each * SLOTS2 + h2 % SLOTS2, self.each * SLOTS1 + ((self.p1 * 40503) >> 5) % SLOTS1, self.each]
        word = [g[s] for g, s in zip(self.guess, self.slot, strict=True)]
        self.sure = [(w & U(255)).astype(np.int64) for w in word]
        self.id = [(w >> U(8)).astype(np.uint32) for w in word]
        agree = self.id[0] == self.id[1]
        self.row = [self.each * 16 + np.minimum(c, 7) * 2 + agree for c in self.sure]
        self.held = [f[r] for f, r in zip(self.flag, self.row, strict=True)]
        self.counts = self.held[0] + self.held[1] + self.held[2]  # below 2**16 each: no carry
        a, b, c, d = ((self.counts >> p) & U(0xFFFF) for p in _PLACE)
        self.edges = [a, a + b, a + b + c]
        self.total = self.edges[2] + d

    def span(self, flag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the symbol's part of the total begins, and its size."""
        low = np.where(flag > 0, np.where(flag > 1, np.where(flag > 2, self.edges[2], self.edges[1]), self.edges[0]), U(0))
        return low, (self.counts >> _PLACE[flag]) & U(0xFFFF)

    def learn_flag(self, flag: np.ndarray) -> None:
        place = _PLACE[flag]
        step = _STEP[flag]
        for table, rows, held in zip(self.flag, self.row, self.held, strict=True):
            new = held + step
            full = (new >> place) & U(0xFFFF) > LIMIT
            if full.any():
                new[full] = ((new[full] >> U(1)) & _HALF) | _ONES
            table[rows] = new

    def digit_row(self, lanes: np.ndarray, k: int, before: np.ndarray) -> np.ndarray:
        """Row of counts for digit k, given the digits before it as one number."""
        if k < 3:
            return lanes * self.rows + (0, 1, 17)[k] + before
        fold = ((before >> 8) * 7 + ((before >> 4) & 15) * 3 & 15) << 4 | (before & 15)
        return lanes * self.rows + LEAD_ROWS + FOLD_ROWS * (k - 3) + fold

    def learn_digit(self, rows: np.ndarray, d: np.ndarray) -> None:
        self.digit[rows, d] += INC
        full = rows[self.digit[rows, d] > LIMIT // 4]
        if len(full):
            self.digit[full] = (self.digit[full] >> 1) | 1

    def learn(self, ids: np.ndarray) -> None:
        now = ids.astype(U) << U(8)
        for table, slot, sure, guess in zip(self.guess, self.slot, self.sure, self.id, strict=True):
            right = guess == ids
            stay = right | (sure > 1)
            c = np.where(right, np.minimum(sure + 1, 255), np.where(sure > 1, sure >> 1, 1))
            table[slot] = np.where(stay, guess.astype(U) << U(8), now) | c.astype(U)
        self.p2, self.p1 = self.p1, ids.astype(np.int64)


class Writer:
    """Range encoders of all blocks: 48-bit low end, carries go back into written words."""

    def __init__(self, lanes: int, words: int):
        self.low, self.range = np.zeros(lanes, U), np.full(lanes, _LOW48, U)
        self.out, self.at = np.zeros((lanes, words + 8), np.uint16), np.zeros(lanes, np.int64)

    def _carry(self, lanes: np.ndarray) -> None:
        back = self.at[lanes] - 1
        while len(lanes):
            self.out[lanes, back] += 1
            more = self.out[lanes, back] == 0
            lanes, back = lanes[more], back[more] - 1

    def put(self, lanes: np.ndarray | slice, low: np.ndarray, count: np.ndarray, total: np.ndarray) -> None:
        r = self.range[lanes] // total
        lo = self.low[lanes] + r * low
        rng = r * count
        over = lo > _LOW48
        if over.any():
            self._carry(np.flatnonzero(over) if isinstance(lanes, slice) else lanes[over])
            lo &= _LOW48
        small = np.flatnonzero(rng < _MIN)
        if len(small):
            k = small if isinstance(lanes, slice) else lanes[small]
            need = int(self.at[k].max()) + 4
            if need > self.out.shape[1]:
                self.out = np.pad(self.out, ((0, 0), (0, self.out.shape[1])))
            self.out[k, self.at[k]] = (lo[small] >> U(32)).astype(np.uint16)
            self.at[k] += 1
            lo[small] = (lo[small] << U(16)) & _LOW48
            rng[small] <<= U(16)
        self.low[lanes], self.range[lanes] = lo, rng

    def close(self, lane: int) -> bytes:
        tail = int(self.low[lane])
        words = [(tail >> s) & 0xFFFF for s in (32, 16, 0)]
        return self.out[lane, : self.at[lane]].astype("<u2").tobytes() + np.array(words, "<u2").tobytes()


class Reader:
    def __init__(self, codes: list[np.ndarray]):
        width = max(map(len, codes)) + 4
        self.code = np.zeros((len(codes), width), np.uint16)
        for k, c in enumerate(codes):
            self.code[k, : len(c)] = c
        c = self.code[:, :3].astype(U)
        self.value = (c[:, 0] << U(32)) | (c[:, 1] << U(16)) | c[:, 2]
        self.range, self.at = np.full(len(codes), _LOW48, U), np.full(len(codes), 3, np.int64)

    def peek(self, lanes: np.ndarray | slice, total: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        r = self.range[lanes] // total
        return np.minimum(self.value[lanes] // r, total - U(1)), r

    def take(self, lanes: np.ndarray | slice, r: np.ndarray, low: np.ndarray, count: np.ndarray) -> None:
        v = self.value[lanes] - r * low
        rng = r * count
        small = np.flatnonzero(rng < _MIN)
        if len(small):
            k = small if isinstance(lanes, slice) else lanes[small]
            at = np.minimum(self.at[k], self.code.shape[1] - 1)
            v[small] = (v[small] << U(16)) | self.code[k, at]
            self.at[k] += 1
            rng[small] <<= U(16)
        self.value[lanes], self.range[lanes] = v, rng


def encode(blocks: list[np.ndarray]) -> list[bytes]:
    """Each block's ids (below 2**32 - 1) as bytes; the longest blocks come first inside, order is kept outside."""
    order = sorted(range(len(blocks)), key=lambda k: -len(blocks[k]))
    sizes = np.array([len(blocks[k]) for k in order])
    steps = int(sizes.max(initial=0))
    largest = max((int(b.max()) for b in blocks if len(b)), default=0)
    digits = max(4, -(-largest.bit_length() // 4))
    ids = np.zeros((steps, len(order)), np.uint32)
    for lane, k in enumerate(order):
        ids[: len(blocks[k]), lane] = blocks[k]
    writer, model = Writer(len(order), steps), Model(len(order), digits)
    every = slice(0, len(order))
    for t in range(steps):
        live = int(np.searchsorted(-sizes, -t, side="left"))
        if live < model.lanes:
            model, every = model.narrow(live), slice(0, live)
        now = ids[t, :live]
        model.look()
        flag = np.where(now == model.id[0], 0, np.where(now == model.id[1], 1, np.where(now == model.id[2], 2, 3)))
        writer.put(every, *model.span(flag), model.total)
        model.learn_flag(flag)
        miss = np.flatnonzero(flag == 3)
        if len(miss):
            value = now[miss].astype(np.int64)
            place = np.arange(len(miss))
            for k in range(digits):
                rest = 4 * (digits - 1 - k)
                d = (value >> rest) & 15
                rows = model.digit_row(miss, k, value >> (rest + 4))
                counts = model.digit[rows]
                cum = np.cumsum(counts, axis=1, dtype=np.uint32)
                n = counts[place, d].astype(U)
                writer.put(miss, cum[place, d].astype(U) - n, n, cum[:, 15].astype(U))
                model.learn_digit(rows, d)
        model.learn(now)
    out: list[bytes] = [b""] * len(blocks)
    for lane, k in enumerate(order):
        code = writer.close(lane)
        crc = zlib.crc32(np.asarray(blocks[k]).astype("<u4").tobytes())
        out[k] = struct.pack(HEAD, MAGIC, len(blocks[k]), len(code) // 2, crc, digits) + code
    return out


def decode(blobs: list[bytes]) -> list[np.ndarray]:
    """The ids of each block, as uint32; raises ValueError where a checksum or head is wrong."""
    heads = []
    for b in blobs:
        if len(b) < HEAD_SIZE:
            raise ValueError("not a token block, or cut off")
        magic, n, words, crc, digits = struct.unpack_from(HEAD, b)
        if magic != MAGIC or len(b) != HEAD_SIZE + 2 * words or not 4 <= digits <= 8:
            raise ValueError("not a token block, or cut off")
        heads.append((n, crc, digits))
    out = [np.zeros(0, np.uint32)] * len(blobs)
    for digits in sorted({h[2] for h in heads}):
        of = [k for k, h in enumerate(heads) if h[2] == digits]
        for k, got in zip(of, _decode([blobs[k] for k in of], [heads[k][0] for k in of], digits), strict=True):
            if zlib.crc32(got.astype("<u4").tobytes()) != heads[k][1]:
                raise ValueError("a token block fails its checksum")
            out[k] = got
    return out


def _decode(blobs: list[bytes], n: list[int], digits: int) -> list[np.ndarray]:
    order = sorted(range(len(blobs)), key=lambda k: -n[k])
    sizes = np.array([n[k] for k in order])
    steps = int(sizes.max(initial=0))
    ids = np.zeros((steps, len(order)), np.uint32)
    if steps:
        reader, model = Reader([np.frombuffer(blobs[k], "<u2", offset=HEAD_SIZE) for k in order]), Model(len(order), digits)
    every = slice(0, len(order))
    for t in range(steps):
        live = int(np.searchsorted(-sizes, -t, side="left"))
        if live < model.lanes:
            model, every = model.narrow(live), slice(0, live)
        model.look()
        at, r = reader.peek(every, model.total)
        flag = (at >= model.edges[0]).astype(np.int64) + (at >= model.edges[1]) + (at >= model.edges[2])
        reader.take(every, r, *model.span(flag))
        model.learn_flag(flag)
        now = np.where(flag == 0, model.id[0], np.where(flag == 1, model.id[1], model.id[2]))
        miss = np.flatnonzero(flag == 3)
        if len(miss):
            value = np.zeros(len(miss), np.int64)
            place = np.arange(len(miss))
            for k in range(digits):
                rows = model.digit_row(miss, k, value)
                counts = model.digit[rows]
                cum = np.cumsum(counts, axis=1, dtype=np.uint32)
                at, r = reader.peek(miss, cum[:, 15].astype(U))
                d = (cum <= at[:, None]).sum(1)
                c = counts[place, d].astype(U)
                reader.take(miss, r, cum[place, d].astype(U) - c, c)
                model.learn_digit(rows, d)
                value = (value << 4) | d
            now[miss] = value
        ids[t, :live] = now
        model.learn(now)
    out = [np.zeros(0, np.uint32)] * len(blobs)
    for lane, k in enumerate(order):
        out[k] = ids[: sizes[lane], lane].copy()
    return out
