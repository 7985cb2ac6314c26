"""Adaptive context-mixing range coder for token ids, run in lock step over many independent blocks.

A block of ids is coded alone: its models start empty, and its bytes carry a checksum of the ids. An id is first offered
the guess of the order-2 context (or, where that has none yet, of the order-1 context). The chance that the guess is right
is mixed, in the logistic domain and with weights learnt as coding goes on, from three predictions of it: how well
order-2 guesses of this kind have done lately, how well order-1 guesses have, and how often the block's ids so far were
the guessed one (order 0, counted id by id). After a wrong guess the id follows under order-0 frequencies, taken anew from
the block's ids so far at 64, 256, 1024, ... ids; an id not among them follows an escape as plain bits.
All steps go through one range coder: a range of at most 48 bits, 16-bit digits, carries settled when a block ends.

Every numpy call works on all blocks of a group at once ("lanes"), so Python's cost is one call for each place in the
block, not for each id. All of it is integer arithmetic, or division that is exact in doubles, so any machine decodes
what another has encoded.
"""

from __future__ import annotations

import struct
import zlib
from itertools import pairwise

import numpy as np

BLOCK, MOST_LANES, MOST_ID = 1024, 2048, 0xFFFFFFFF
SLOTS, SCALE = 1024, 11
LEAST, WIDEST = 1 << 32, 1 << 48
_HASH1, _HASH2 = np.uint32(0x9E3779B1), np.uint32(0x85EBCA6B)
#: Ids of a block after which order-0 frequencies are taken anew.
LOOK_BACK = {4**i for i in range(3, 16)}
#: Bounds of a weight; three of them times a logit stay below 2**31.
HEAVY = 1 << 18

_x = np.arange(4096)
_logit = np.log((_x + 0.5) / (4095.5 - _x))
#: Logit in 1/256ths of a 12-bit chance, and back.
STRETCH = np.clip(np.round(_logit * 256), -2047, 2047).astype(np.int32)
SQUASH = np.clip(np.round(4096 / (1 + np.exp(-(np.arange(4096) - 2048) / 256))), 32, 4064).astype(np.int64)


def frequencies(lane: np.ndarray, times: np.ndarray, k: int, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first slot, slots) of each id seen, of 2**SCALE a lane, and the first slot of each lane's escape. Ids come by lane, then value."""
    kinds = np.bincount(lane, minlength=k)
    escape = np.clip((kinds << SCALE) // (2 * n), 32, 1024)
    slots = 1 + times * ((1 << SCALE) - kinds - escape)[lane] // n
    upto = np.cumsum(slots)
    ends = np.bincount(lane, slots, k).astype(np.int64)
    return upto - slots - (np.cumsum(ends) - ends)[lane], slots, ends


class _Lanes:
    """Models and coder state of k blocks. The first `live` lanes still have ids; callers sort blocks by falling length.

    A slot of a context holds, from the lowest bits on: how sure the guess is (2 bits, 0: nothing yet), the id that last
    followed, and, for order 1, how often the context's own id has come (so far as 12 bits hold it).
    """

    ready = False

    def __init__(self, k: int, plain: int) -> None:
        self.plain, self.whole = plain, np.int32 if plain == 1 else np.int64
        self.lane = np.arange(k)
        self.base, self.base_p = self.lane * SLOTS, self.lane * 16
        self.two, self.one = np.zeros(k * SLOTS, self.whole), np.zeros(k * SLOTS, self.whole)
        self.top, self.slot = 16 * plain + 2, (1 << 16 * plain + 2) - 1
        self.chance = np.full(k * 16, 1 << 14, np.int32)
        self.w = np.full((3, k), 1 << 15, np.int32)
        self.w[2] = 1 << 13
        self.logits = np.zeros((3, k), np.int32)
        self.hash, self.hash2 = np.zeros(k, np.uint32), np.zeros(k, np.uint32)
        self.range = np.full(k, WIDEST)

    def guess(self, t: int, n: int) -> None:
        """Guess of each live lane's next id, the t-th, and the mixed chance, of 4096, that it is right."""
        base = self.base[:n]
        self.at2 = ((self.hash[:n] + self.hash2[:n]) >> 11 & (SLOTS - 1)) + base
        self.at1 = (self.hash[:n] >> 13 & (SLOTS - 1)) + base
        self.e2, held = self.two.take(self.at2), self.one.take(self.at1)
        self.e1 = held & self.slot
        self.came = held - self.e1
        self.f2, self.f1 = self.e2 & 3, self.e1 & 3
        known = self.f2 > 0
        self.candidate = np.where(known, self.e2, self.e1) >> 2
        times = (self.one.take((self.candidate.astype(np.uint32) * _HASH1 >> 13 & (SLOTS - 1)) + base) >> self.top).astype(np.int32)
        at = self.at_p = np.empty((2, n), np.int64)
        np.add(self.base_p[:n], 2 * self.f2 + (self.e1 ^ self.e2 < 4), out=at[0])
        np.add(self.base_p[:n], self.f1 + 4 * known + 8, out=at[1])
        self.p = self.chance.take(at)
        s = self.s = self.logits[:, :n]
        s[:2] = STRETCH.take(self.p >> 4)
        s[2] = STRETCH.take(np.minimum((times << 12) // max(t, 1), 4095))
        mixed = self.w[:, :n] * s
        mixed = (mixed[0] + mixed[1] + mixed[2] >> 16) + 2048
        self.mixed = SQUASH.take(mixed, mode="clip")

    def learn(self, n: int, ids: np.ndarray, right: np.ndarray) -> None:
        right = right.astype(np.int32)
        w = self.w[:, :n]
        w += self.s * ((right << 12) - self.mixed.astype(np.int32)) >> 9
        np.minimum(np.maximum(w, -HEAVY, out=w), HEAVY, out=w)
        self.chance[self.at_p] = self.p + (right * 65535 - self.p >> 5)
        fresh = ids * 4 + 1
        for e, f in ((self.e2, self.f2), (self.e1, self.f1)):
            now = np.where(f > 1, e - 1, fresh)
            np.copyto(now, e + (f < 3), where=e ^ fresh < 4)
            if e is self.e2:
                self.two[self.at2] = now
        now += self.came
        now += (self.came < 4095 << self.top).astype(self.whole) << self.top
        self.one[self.at1] = now
        np.multiply(self.hash[:n], _HASH2, out=self.hash2[:n])
        np.multiply(ids.astype(np.uint32), _HASH1, out=self.hash[:n])


def _by_lane(ids: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order of each lane's ids by value, which of them, so ordered, come within its length); a row a lane."""
    most = np.uint16 if ids.max(initial=0) < 1 << 16 else np.uint32
    order = np.argsort(ids.astype(most), axis=1, kind="stable")
    return order, order < lengths[:, None]


class _Encoder(_Lanes):
    def __init__(self, ids: np.ndarray, lengths: np.ndarray, plain: int) -> None:
        """ids: a column a lane, each as long as its length says. plain: digits of an id that follows an escape."""
        k = ids.shape[1]
        super().__init__(k, plain)
        self.ids, self.low = ids.astype(self.whole, copy=False), np.zeros(k, np.int64)
        room = (plain + 2) * len(ids) + 8
        self.out, self.first = np.zeros(k * room, np.uint32), self.lane * room
        self.next = self.first.copy()
        # number of each id among all that come in its lane; some lanes at a time, to hold less at once
        self.kind, self.seen_len, kinds, known = np.empty(ids.shape, np.int32), lengths, [], 0
        self.known = [0]  # kinds before each group of lanes
        for a in range(0, k, 256):
            rows = np.ascontiguousarray(ids[:, a : a + 256].T)
            order, _ = _by_lane(rows, lengths[a : a + 256])
            value = np.take_along_axis(rows, order, 1)
            new = np.ones(rows.shape, bool)
            new[:, 1:] = value[:, 1:] != value[:, :-1]
            number = (np.cumsum(new.ravel(), dtype=np.int32) + (known - 1)).reshape(rows.shape)
            kind = np.empty(rows.shape, np.int32)
            np.put_along_axis(kind, order, number, 1)
            self.kind[:, a : a + 256] = kind.T
            kinds.append(new.sum(1))
            known += int(kinds[-1].sum())
            self.known.append(known)
        self.kind_lane = np.repeat(self.lane.astype(np.int32), np.concatenate(kinds))

    def look_back(self, t: int) -> None:
        """Order-0 frequencies from the first t ids."""
        times, place = np.zeros(len(self.kind_lane), np.int32), np.arange(t)[:, None]
        for a, (lo, hi) in zip(range(0, len(self.lane), 256), pairwise(self.known), strict=True):
            kind = self.kind[:t, a : a + 256][place < self.seen_len[a : a + 256]]
            times[lo:hi] = np.bincount(kind - lo, minlength=hi - lo)
        seen = np.flatnonzero(times)
        lo, n, self.escape = frequencies(self.kind_lane[seen], times[seen].astype(np.int64), len(self.lane), t)
        self.slots = np.full(len(times), -1, np.int32)  # first slot and slots of a kind together
        self.slots[seen] = lo << 13 | n
        self.ready = True

    def put_out(self, lanes: np.ndarray) -> None:
        """Digits of those lanes whose range has grown small."""
        while len(lanes := lanes[self.range.take(lanes) < LEAST]):
            low = self.low.take(lanes)
            self.out[self.next[lanes]] = low >> 32
            self.next[lanes] += 1
            self.low[lanes] = (low & 0xFFFFFFFF) << 16
            self.range[lanes] <<= 16

    def step(self, t: int, n: int) -> None:
        ids = self.ids[t, :n]
        if t in LOOK_BACK:
            self.look_back(t)
        self.guess(t, n)
        right = ids == self.candidate
        wide = self.range[:n]
        cut = (wide >> 12) * self.mixed
        self.low[:n] += cut * ~right
        self.range[:n] = np.where(right, cut, wide - cut)
        wrong = np.flatnonzero(~right)
        if self.ready:
            slots = self.slots.take(self.kind[t, :n].take(wrong))
            new = np.flatnonzero(slots < 0)
            lo = self.escape[wrong[new]]
            slots[new] = lo << 13 | (1 << SCALE) - lo
            unit = self.range.take(wrong) >> SCALE
            self.low[wrong] += unit * (slots >> 13)
            self.range[wrong] = unit * (slots & 0x1FFF)
            wrong = wrong[new]
        if len(wrong):
            for shift in range(16 * (self.plain - 1), -1, -16):
                self.put_out(wrong)
                unit = self.range.take(wrong) >> 16
                self.low[wrong] += unit * (ids[wrong] >> shift & 0xFFFF)
                self.range[wrong] = unit
        # one digit of every lane that is due one; a lane that isn't writes where its next digit will go
        wide, low = self.range[:n], self.low[:n]
        due = wide < LEAST
        self.out[self.next[:n]] = low >> 32
        self.next[:n] += due
        np.copyto(low, (low & 0xFFFFFFFF) << 16, where=due)
        wide <<= due * 16
        if wide.min() < LEAST:
            self.put_out(self.lane[:n])
        self.learn(n, ids, right)

    def streams(self) -> list[bytes]:
        for shift, keep in ((32, 0x1FFFF), (16, 0xFFFF), (0, 0xFFFF)):
            self.out[self.next] = self.low >> shift & keep
            self.next += 1
        digits = np.concatenate([self.out[a:b] for a, b in zip(self.first.tolist(), self.next.tolist(), strict=True)])
        # a digit above 16 bits carries into the one before it; the first of a lane never does
        while len(over := np.flatnonzero(digits >> 16)):
            digits[over] &= 0xFFFF
            digits[over - 1] += 1
        digits, ends = digits.astype("<u2"), np.cumsum(self.next - self.first).tolist()
        return [digits[a:b].tobytes() for a, b in zip([0, *ends], ends, strict=False)]


class _Decoder(_Lanes):
    def __init__(self, streams: list[bytes], ids: np.ndarray, sizes: np.ndarray, plain: int) -> None:
        """ids: where decoded ids go, a column a lane."""
        super().__init__(len(streams), plain)
        self.ids, self.sizes = ids, sizes
        lengths = np.array([len(s) // 2 for s in streams])
        self.words = np.frombuffer(b"".join([*streams, bytes(16)]), "<u2")
        self.next = np.cumsum(lengths) - lengths
        self.code = np.zeros(len(streams), np.int64)
        for _ in range(3):
            self.code = self.code << 16 | self.words[self.next]
            self.next += 1

    def take_in(self, lanes: np.ndarray) -> None:
        while len(lanes := lanes[self.range.take(lanes) < LEAST]):
            at = self.next.take(lanes)
            self.code[lanes] = self.code.take(lanes) << 16 | self.words.take(at, mode="clip")
            self.next[lanes] = at + 1
            self.range[lanes] <<= 16

    def look_back(self, t: int) -> None:
        lanes, values, counts = [], [], []
        for a in range(0, len(self.lane), 256):  # some lanes at a time, to hold less at once
            rows = np.ascontiguousarray(self.ids[:t, a : a + 256].T)
            order, held = _by_lane(rows, self.sizes[a : a + 256])
            value, lane = np.take_along_axis(rows, order, 1)[held], np.nonzero(held)[0] + a
            new = np.ones(len(value), bool)
            new[1:] = (value[1:] != value[:-1]) | (lane[1:] != lane[:-1])
            first = np.flatnonzero(new)
            lanes.append(lane[first])
            values.append(value[first].astype(self.whole))
            counts.append(np.diff(np.append(first, len(new))))
        lane, value = np.concatenate(lanes), np.concatenate(values)
        lo, n, self.escape = frequencies(lane, np.concatenate(counts), len(self.lane), t)
        self.kinds, self.kind_slots = value, lo << 13 | n
        self.slots = np.full(len(self.lane) << SCALE, -1, np.int32)
        place = np.arange(n.sum()) + np.repeat((lane << SCALE) + lo - (np.cumsum(n) - n), n)
        self.slots[place] = np.repeat(np.arange(len(value), dtype=np.int32), n)
        self.ready = True

    def step(self, t: int, n: int) -> np.ndarray:
        if t in LOOK_BACK:
            self.look_back(t)
        self.guess(t, n)
        wide, code = self.range[:n], self.code[:n]
        cut = (wide >> 12) * self.mixed
        right = code < cut
        code -= cut * ~right
        self.range[:n] = np.where(right, cut, wide - cut)
        ids = self.candidate
        wrong = np.flatnonzero(~right)
        if self.ready:
            unit, code = self.range.take(wrong) >> SCALE, self.code.take(wrong)
            slot = np.minimum(code / unit, (1 << SCALE) - 1).astype(np.int64)
            kind = self.slots.take((wrong << SCALE) + slot)
            slots = self.kind_slots.take(kind, mode="wrap")
            ids[wrong] = self.kinds.take(kind, mode="wrap")
            new = np.flatnonzero(kind < 0)
            lo = self.escape[wrong[new]]
            slots[new] = lo << 13 | (1 << SCALE) - lo
            self.code[wrong] = code - unit * (slots >> 13)
            self.range[wrong] = unit * (slots & 0x1FFF)
            wrong = wrong[new]
        if len(wrong):
            value = np.zeros(len(wrong), np.int64)
            for _ in range(self.plain):
                self.take_in(wrong)
                unit, code = self.range.take(wrong) >> 16, self.code.take(wrong)
                digit = np.minimum(code / unit, 0xFFFF).astype(np.int64)
                self.code[wrong] = code - unit * digit
                self.range[wrong] = unit
                value = value << 16 | digit
            ids[wrong] = value
        wide, code, at = self.range[:n], self.code[:n], self.next[:n]
        due = wide < LEAST
        np.copyto(code, code << 16 | self.words.take(at, mode="clip"), where=due)
        at += due
        wide <<= due * 16
        if wide.min() < LEAST:
            self.take_in(self.lane[:n])
        self.learn(n, ids, right)
        return ids


def _groups(order: list[int]) -> list[list[int]]:
    """Blocks to be coded together, in groups of about one size."""
    some = -(-len(order) // max(1, -(-len(order) // MOST_LANES))) or 1
    return [order[i : i + some] for i in range(0, len(order), some)]


def encode_blocks(blocks: list[np.ndarray], plain: int = 1) -> list[bytes]:
    """Coded bytes of each block of ids (0 to 65535; with plain = 2, 16-bit digits of an unforeseen id, to 2**32 - 1)."""
    out: list[bytes] = [b""] * len(blocks)
    order = sorted(range(len(blocks)), key=lambda i: -len(blocks[i]))
    for mine in _groups(order):
        lengths = np.array([len(blocks[i]) for i in mine])
        ids = np.zeros((lengths.max(initial=0), len(mine)), np.int32 if plain == 1 else np.int64)
        for lane, i in enumerate(mine):
            ids[: lengths[lane], lane] = blocks[i]
        coder = _Encoder(ids, lengths, plain)
        for t, n in enumerate(np.searchsorted(-lengths, -np.arange(len(ids)), "left")):
            coder.step(t, n)
        for i, s in zip(mine, coder.streams(), strict=True):
            out[i] = s
        del coder, ids  # before the next group's are made
    return out


def decode_blocks(streams: list[bytes], lengths: list[int], plain: int = 1) -> list[np.ndarray]:
    out: list[np.ndarray] = [np.zeros(0, np.uint32)] * len(streams)
    order = sorted(range(len(streams)), key=lambda i: -lengths[i])
    for mine in _groups(order):
        sizes = np.array([lengths[i] for i in mine])
        ids = np.zeros((sizes.max(initial=0), len(mine)), np.uint32)
        coder = _Decoder([streams[i] for i in mine], ids, sizes, plain)
        with np.errstate(divide="ignore", invalid="ignore"):  # broken bytes
            for t, n in enumerate(np.searchsorted(-sizes, -np.arange(len(ids)), "left")):
                ids[t, :n] = coder.step(t, n)
        del coder
        rows = np.ascontiguousarray(ids.T)
        for lane, i in enumerate(mine):
            out[i] = rows[lane, : sizes[lane]]
    return out


MAGIC = b"CMID2\0"
_HEAD, _BLOCK = struct.Struct("<6sBQI"), struct.Struct("<III")  # magic, digits of a plain id, ids, blocks; then ids, bytes, crc32 of each block


class CorruptBlock(ValueError):
    """Bytes that don't decode to the ids they were made from."""


def pack(ids: np.ndarray, block: int | None = None) -> bytes:
    """File bytes of a run of ids: a header, an entry for each block, the coded blocks.

    Short runs are cut into shorter blocks (a 128th of the run, from 512 ids on), so that there are lanes to fill a step.
    """
    block = block or min(BLOCK, max(512, len(ids) // 128))
    plain = 2 if len(ids) and int(ids.max()) > 0xFFFF else 1
    if len(ids) and (int(ids.min()) < 0 or int(ids.max()) > MOST_ID):
        raise ValueError(f"ids must lie between 0 and {MOST_ID}")
    blocks = [ids[i : i + block] for i in range(0, len(ids), block)]
    coded = encode_blocks(blocks, plain)
    entries = [_BLOCK.pack(len(b), len(c), zlib.crc32(b.astype("<u4").tobytes())) for b, c in zip(blocks, coded, strict=True)]
    return b"".join([_HEAD.pack(MAGIC, plain, len(ids), len(blocks)), *entries, *coded])


def unpack(data: bytes) -> np.ndarray:
    """The ids; CorruptBlock if the header or any block's checksum is wrong."""
    try:
        magic, plain, n, k = _HEAD.unpack_from(data)
        entries = [_BLOCK.unpack_from(data, _HEAD.size + i * _BLOCK.size) for i in range(k)] if magic == MAGIC and plain in (1, 2) else None
    except struct.error as e:
        raise CorruptBlock("bytes are missing") from e
    if entries is None or sum(x[0] for x in entries) != n or _HEAD.size + k * _BLOCK.size + sum(x[1] for x in entries) != len(data):
        raise CorruptBlock("header doesn't fit the bytes")
    at, streams = _HEAD.size + k * _BLOCK.size, []
    for _, size, _ in entries:
        streams.append(data[at : at + size])
        at += size
    if any(len(s) < 6 or len(s) % 2 for s in streams):
        raise CorruptBlock("a block is too short")
    found = decode_blocks(streams, [x[0] for x in entries], plain)
    for i, (ids, (_, _, crc)) in enumerate(zip(found, entries, strict=True)):
        if zlib.crc32(ids.astype("<u4").tobytes()) != crc:
            raise CorruptBlock(f"block {i}: checksum differs")
    return np.concatenate(found) if found else np.zeros(0, np.uint32)
