"""Numpy kernels that run inside Arrow tasks: alignment tables, tracebacks, guide trees, merges.

Moves of a path are named d (both advance), u (the first string advances over a gap) and l (the second does).
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np

from ..functions.scoring import Scoring

GAP = "_"
LOW = -(1 << 40)
#: Cells of a table up to which it is held whole; larger ones go through their rows in a band.
CELLS = 4_000_000


# ---- pairwise alignment ----------------------------------------------------


def coded(strings: Sequence[Sequence[str]], extra: str = "") -> tuple[list[str], list[np.ndarray]]:
    """(symbols in order, each string as numbers of them)."""
    symbols = sorted({c for s in strings for c in s} | set(extra))
    at = {c: i for i, c in enumerate(symbols)}
    return symbols, [np.fromiter((at[c] for c in s), np.int64, len(s)) for s in strings]


def substitution(a: Sequence[str], b: Sequence[str], scoring: Scoring) -> np.ndarray:
    symbols, (x, y) = coded([a, b])
    if not len(x) or not len(y):
        return np.zeros((len(x), len(y)), np.int64)
    return scoring.table(symbols)[x[:, None], y[None, :]]


def next_row(prev: np.ndarray, sub: np.ndarray, gap: float, first: float) -> np.ndarray:
    """Row after prev: the better of diagonal and up, then all left moves at once by a running maximum."""
    row = np.empty_like(prev)
    row[0] = first
    np.maximum(prev[:-1] + sub, prev[1:] + gap, out=row[1:])
    steps = np.arange(len(row)) * np.asarray(gap, row.dtype)
    return np.maximum.accumulate(row - steps) + steps


def table(sub: np.ndarray, gap: float) -> np.ndarray:
    """The whole score table of a substitution matrix."""
    n, m = sub.shape
    kind = np.int64 if sub.dtype.kind == "i" and float(gap).is_integer() else float
    h = np.empty((n + 1, m + 1), kind)
    h[0] = np.arange(m + 1) * gap
    for i in range(n):
        h[i + 1] = next_row(h[i], sub[i], gap, (i + 1) * gap)
    return h


def _like(pairs: Sequence[tuple[str, str]], scoring: Scoring, most_cells: int) -> Iterator[tuple[list[int], np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Pairs of like length together: (their places, lengths of both, symbol numbers of both, scores of symbols)."""
    order = sorted(range(len(pairs)), key=lambda i: (len(pairs[i][1]), len(pairs[i][0])))
    symbols, strings = coded([s for p in pairs for s in p])
    t = scoring.table(symbols) if symbols else np.zeros((1, 1), np.int64 if scoring.is_whole else float)
    at = 0
    while at < len(order):
        upto = at + 1
        while upto < len(order) and (upto + 1 - at) * (1 + len(pairs[order[upto]][1])) <= most_cells and upto - at < 4096:
            upto += 1
        mine = order[at:upto]
        at = upto
        a, b = [strings[2 * i] for i in mine], [strings[2 * i + 1] for i in mine]
        la, lb = np.array([len(x) for x in a]), np.array([len(x) for x in b])
        first, second = np.zeros((len(mine), max(int(la.max()), 1)), np.int64), np.zeros((len(mine), int(lb.max())), np.int64)
        for k, (x, y) in enumerate(zip(a, b)):
            first[k, : len(x)], second[k, : len(y)] = x, y
        yield mine, la, lb, first, second, t


def scores(pairs: Sequence[tuple[str, str]], scoring: Scoring, most_cells: int = 1 << 18) -> np.ndarray:
    """Optimal scores of many pairs: pairs of like length go through the rows of their tables together."""
    out = np.zeros(len(pairs), np.int64 if scoring.is_whole else float)
    for mine, la, lb, first, second, t in _like(pairs, scoring, most_cells):
        steps = np.arange(second.shape[1] + 1) * np.asarray(scoring.gap, t.dtype)
        row, lane = np.tile(steps, (len(mine), 1)), np.arange(len(mine))
        done = np.where(la == 0, row[lane, lb], 0)
        for i in range(int(la.max())):
            new = np.empty_like(row)
            new[:, 0] = (i + 1) * scoring.gap
            np.maximum(row[:, :-1] + t[first[:, i][:, None], second], row[:, 1:] + scoring.gap, out=new[:, 1:])
            row = np.maximum.accumulate(new - steps, axis=1) + steps
            ends = la == i + 1
            if ends.any():
                done[ends] = row[lane[ends], lb[ends]]
        out[mine] = done
    return out


def path_counts(pairs: Sequence[tuple[str, str]], scoring: Scoring, tie: str = "dul", most_cells: int = 1 << 18) -> np.ndarray:
    """(matches, mismatches, letter-gap columns) of the path that traceback() takes, for many pairs, without a traceback.

    A cell's path goes on from one cell before it, which the tie order fixes, so its counts are that cell's and one step
    more; cells reached from the left take theirs from the nearest cell to the left that isn't.
    """
    out = np.zeros((len(pairs), 3), np.int64)
    rest = []
    for k, (a, b) in enumerate(pairs):
        moves = None
        if min(len(a), len(b)) >= 256 or len(a) * len(b) > CELLS:
            symbols, (x, y) = coded([a, b])
            t = scoring.table(symbols)
            moves = near_moves(x, y, t, scoring.gap, tie) or (moves_of(x, y, t, scoring.gap, tie) if len(a) * len(b) > CELLS else None)
        if moves is None:
            rest.append(k)
            continue
        moves = np.frombuffer(moves.encode(), np.uint8)
        d = moves == ord("d")
        same = int((x[np.cumsum(moves != ord("l"))[d] - 1] == y[np.cumsum(moves != ord("u"))[d] - 1]).sum())
        out[k] = same, int(d.sum()) - same, len(moves) - int(d.sum())
    if len(rest) < len(pairs):
        out[rest] = path_counts([pairs[k] for k in rest], scoring, tie, most_cells) if rest else 0
        return out
    for mine, la, lb, first, second, t in _like(pairs, scoring, most_cells):
        n, width, g = len(mine), second.shape[1] + 1, scoring.gap
        steps = np.arange(width) * np.asarray(g, t.dtype)
        row, lane = np.tile(steps, (n, 1)), np.arange(n)
        same, both, place = np.zeros((n, width), np.int32), np.zeros((n, width), np.int32), np.arange(width)
        for i in range(int(la.max())):
            sub, letter = t[first[:, i][:, None], second], first[:, i][:, None] == second
            diagonal, up = row[:, :-1] + sub, row[:, 1:] + g
            new = np.empty_like(row)
            new[:, 0] = (i + 1) * g
            np.maximum(diagonal, up, out=new[:, 1:])
            new = np.maximum.accumulate(new - steps, axis=1) + steps
            here = new[:, 1:]
            open_ = {"d": diagonal == here, "u": up == here, "l": new[:, :-1] + g == here} if t.dtype.kind == "i" else {"d": np.abs(diagonal - here) < 1e-9, "u": np.abs(up - here) < 1e-9, "l": np.abs(new[:, :-1] + g - here) < 1e-9}
            move = np.full(here.shape, 3, np.int8)
            for k, m in reversed(list(enumerate(tie))):
                move[open_[m]] = k
            d, left = move == tie.index("d"), move == tie.index("l")
            next_same, next_both = same.copy(), both.copy()  # up keeps the cell above
            np.copyto(next_same[:, 1:], same[:, :-1] + letter, where=d)
            np.copyto(next_both[:, 1:], both[:, :-1] + 1, where=d)
            next_same[:, 0] = next_both[:, 0] = 0
            if left.any():
                from_ = np.zeros((n, width), np.int64)
                np.copyto(from_[:, 1:], np.broadcast_to(place[1:], left.shape), where=~left)
                from_ = np.maximum.accumulate(from_, axis=1)
                next_same, next_both = np.take_along_axis(next_same, from_, 1), np.take_along_axis(next_both, from_, 1)
            done = la <= i  # shorter first strings keep their last row
            if done.any():
                next_same[done], next_both[done], new[done] = same[done], both[done], row[done]
            same, both, row = next_same, next_both, new
        s, d = same[lane, lb], both[lane, lb]
        out[mine] = np.stack([s, d - s, la + lb - 2 * d], 1)
    return out


def traceback(h: np.ndarray, sub: np.ndarray, gap: float, tie: str = "dul") -> str:
    """Moves of one optimal path; where several moves are optimal, the first of `tie` (seen from the end) is taken."""
    i, j, moves = h.shape[0] - 1, h.shape[1] - 1, []
    near = (lambda x, y: x == y) if h.dtype.kind == "i" else (lambda x, y: abs(x - y) < 1e-9)
    while i or j:
        for move in tie:
            if move == "d" and i and j and near(h[i, j], h[i - 1, j - 1] + sub[i - 1, j - 1]):
                i, j = i - 1, j - 1
                break
            if move == "u" and i and near(h[i, j], h[i - 1, j] + gap):
                i -= 1
                break
            if move == "l" and j and near(h[i, j], h[i, j - 1] + gap):
                j -= 1
                break
        moves.append(move)
    return "".join(reversed(moves))


def moves_in_linear_memory(sub_rows, n: int, m: int, gap: float) -> str:
    """Moves of one optimal path by divide and conquer; sub_rows(i, j0, j1, reverse) gives parts of substitution rows."""

    def last_row(i0: int, i1: int, j0: int, j1: int, back: bool) -> np.ndarray:
        row = np.arange(j1 - j0 + 1) * float(gap)
        for k, i in enumerate(range(i1 - 1, i0 - 1, -1) if back else range(i0, i1)):
            s = sub_rows(i, j0, j1)
            row = next_row(row, s[::-1] if back else s, gap, (k + 1) * gap)
        return row

    def solve(i0: int, i1: int, j0: int, j1: int) -> str:
        if i0 == i1:
            return "l" * (j1 - j0)
        if j0 == j1:
            return "u" * (i1 - i0)
        if i1 - i0 == 1:
            sub = sub_rows(i0, j0, j1)[None, :]
            return traceback(table(sub.astype(float), gap), sub.astype(float), gap)
        mid = (i0 + i1) // 2
        cut = j0 + int(np.argmax(last_row(i0, mid, j0, j1, False) + last_row(mid, i1, j0, j1, True)[::-1]))
        return solve(i0, mid, j0, cut) + solve(mid, i1, cut, j1)

    return solve(0, n, 0, m)


def moves_in_band(sub_row, n: int, m: int, gap: float, best: float, tie: str = "dul", whole: bool = True, start: int = 64) -> str:
    """Moves of the path that traceback() takes, without the whole table; sub_row(i, j0, j1) gives part of a substitution row.

    best: no substitution is above it. The band of diagonals doubles until no path that leaves it can be as good as the
    best one inside, so that all optimal paths lie inside and ties go as in the whole table. Every so many rows one is
    kept, and the moves of the rows between two kept ones are taken anew from the end.
    """
    kind = np.int64 if whole and float(gap).is_integer() else float
    near = (lambda x, y: x == y) if kind is np.int64 else (lambda x, y: np.abs(x - y) < 1e-9)
    band = start if gap < best / 2 else n + m
    while True:
        lo, hi = max(min(0, m - n) - band, -n), min(max(0, m - n) + band, m)
        width = hi - lo + 1
        steps, place = np.arange(width) * np.asarray(gap, kind), np.arange(width)

        def after(prev: np.ndarray, i: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            """(row i, its cells if reached by d, by u); place k of a row is column i + lo + k."""
            at = i + lo
            k0, k1 = max(0, -at), min(width, m - at + 1)
            d, u = np.full(width, LOW, kind), np.full(width, LOW, kind)
            a = max(k0, 1 - at)
            d[a:k1] = prev[a:k1] + sub_row(i - 1, at + a - 1, at + k1 - 1)
            up = min(k1, width - 1)
            u[k0:up] = prev[k0 + 1 : up + 1] + gap
            row = np.full(width, LOW, kind)
            row[k0:k1] = np.maximum.accumulate(np.maximum(d[k0:k1], u[k0:k1]) - steps[k0:k1]) + steps[k0:k1]
            return row, d, u

        row = np.where((place + lo >= 0) & (place + lo <= m), (place + lo) * np.asarray(gap, kind), LOW)
        each = int((8 * n) ** 0.5) + 1
        kept = [row]
        for i in range(1, n + 1):
            row = after(row, i)[0]
            if i % each == 0:
                kept.append(row)
        gaps = abs(n - m) + 2 * (band + 1)
        if lo == -n and hi == m or row[m - n - lo] > best * max(n + m - gaps, 0) / 2 + gap * gaps + 1e-6:
            break
        band *= 2
    i, j, moves = n, m, []
    while i:
        base = (i - 1) // each * each
        row, rows = kept[base // each], np.full((i - base, width), 3, np.int8)
        for r in range(base + 1, i + 1):
            row, d, u = after(row, r)
            left = np.zeros(width, bool)
            left[1:] = near(row[:-1] + gap, row[1:])
            open_ = {"d": near(d, row), "u": near(u, row), "l": left}
            for k, move in reversed(list(enumerate(tie))):
                rows[r - base - 1][open_[move]] = k
        while i > base:
            move = tie[rows[i - base - 1, j - i - lo]]
            moves.append(move)
            i, j = i - (move != "l"), j - (move != "u")
    return "".join(reversed(moves + ["l"] * j))


def _kinds(t: np.ndarray) -> tuple[int, int, int | None, int, int] | None:
    """(match, mismatch, symbol apart from the others or None, its score with others, with itself), if whole scores t are so simple."""
    if t.dtype.kind != "i" or len(t) > 200:
        return None
    for g in (None, *range(len(t))):
        rest = [i for i in range(len(t)) if i != g]
        if not rest:
            continue
        own = t[np.ix_(rest, rest)]
        same, other = np.unique(np.diag(own)), np.unique(own[~np.eye(len(rest), dtype=bool)])
        edge = np.unique(np.append(t[g, rest], t[rest, g])) if g is not None else np.zeros(1, int)
        if len(same) == 1 and len(other) < 2 and len(edge) == 1:
            return int(same[0]), int(other[0] if len(other) else same[0]), g, int(edge[0]), int(t[g, g]) if g is not None else 0
    return None


def moves_by_diagonals(x: np.ndarray, y: np.ndarray, kinds: tuple[int, int, int | None, int, int], gap: int, tie: str = "dul", start: int = 64) -> str:
    """Moves of the path that traceback() takes between x and y, numbers of symbols with scores kinds (see _kinds).

    With -gap added to every step gaps are free, and neighbours in the table differ by small whole numbers; these differences
    fit a byte and go through the table by its diagonals, all cells of one at once. The band of j - i is as wide as needed:
    the score in a narrow one says how far a path as good can lead away. Every so many diagonals the differences are kept,
    and between two that are the moves are taken anew from the end, in the triangle that the path can come from.
    """
    n, m = len(x), len(y)
    same, other, g, edge, both = (s if k == 2 else max(s - 2 * gap, -1) for k, s in enumerate(kinds))
    best = max(kinds[0], kinds[1], *(kinds[3:] if g is not None else ()))
    x, y = x.astype(np.uint8), y[::-1].astype(np.uint8)  # place r of y, and of across, is column m - r
    odd_x, odd_y = x == (255 if g is None else g), y == (255 if g is None else g)
    odd = bool(odd_x.any() or odd_y.any())
    y[odd_y] = 255
    down, across = np.zeros(n + 1, np.int8), np.zeros(m + 1, np.int8)  # differences to the cell above, to the left
    equal_, w_, z_, t_ = np.empty(n + 1, bool), *(np.empty(n + 1, np.int8) for _ in range(3))
    each, low, high = math.isqrt(n + m) + 1, -n, m

    def step(d: int, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        """Differences on rows a to b of diagonal d; (scores of symbols, of the step to each cell). -1: not in the band."""
        k, r = b - a + 1, m - d + a
        if d - 2 * a == high and a > 1:
            across[r] = -1
        if d - 2 * b == low and d - b > 1:
            down[b] = -1
        v, h = down[a : b + 1], across[r : r + k]
        w = np.multiply(np.equal(x[a - 1 : b], y[r : r + k], out=equal_[:k]).view(np.int8), same - other, out=w_[:k])
        w += other
        if odd:
            w += (odd_x[a - 1 : b] ^ odd_y[r : r + k]).view(np.int8) * (edge - other)
            if both != other:
                w += (odd_x[a - 1 : b] & odd_y[r : r + k]).view(np.int8) * (both - other)
        z = np.maximum(w, v, out=z_[:k])
        np.maximum(z, h, out=z)
        t = np.subtract(z, v, out=t_[:k])
        np.subtract(z, h, out=v)
        h[:] = t
        return w, z

    band = start if gap < best / 2 else n + m
    while True:
        low, high = max(min(0, m - n) - band, -n), min(max(0, m - n) + band, m)
        down[:], across[:] = 0, 0
        kept, total, at = {0: (1, down[:0], across[:0])}, 0, 0
        for d in range(1, n + m + 1):
            a, b = max(1, d - m, -((high - d) // 2)), min(n, d - 1, (d - low) // 2)
            if a <= b:
                step(d, a, b)
            to = d * n // (n + m)  # a staircase of cells, along which differences add up to the score
            if to and to < d:
                total += int(down[to] if to > at else across[m - d + to])
            at = to
            if d % each == 0:
                kept[d] = a, down[a : b + 1].copy(), across[m - d + a : m - d + b + 1].copy()
        gaps, score = abs(n - m) + 2 * (band + 1), total + gap * (n + m)
        if low == -n and high == m or score > best * max(n + m - gaps, 0) / 2 + gap * gaps + 1e-6:
            break
        need = int((best * (n + m) / 2 - score) / (best / 2 - gap)) + 2
        band = max(band + 1, (need - abs(n - m) + 1) // 2)

    i, j, moves = n, m, []
    while i and j:
        d = i + j
        c = (d - 1) // each * each
        first, v, h = kept[c]
        top, left = max(1, i - (d - c)), max(1, j - (d - c))
        down[top : i + 1], across[m - j : m - left + 1] = 0, 0
        lo, hi = max(top, first), min(i + 1, first + len(v))
        if lo < hi:
            down[lo:hi] = v[lo - first : hi - first]
        begin = m - c + first
        lo, hi = max(m - j, begin), min(m - left + 1, begin + len(h))
        if lo < hi:
            across[lo:hi] = h[lo - begin : hi - begin]
        rows = np.full((d - c, i - top + 1), 3, np.int8)
        for e in range(c + 1, d + 1):
            a, b = max(top, e - j, -((high - e) // 2)), min(i, e - 1, (e - low) // 2)
            if a > b:
                continue
            w, z = step(e, a, b)
            row, r = rows[e - c - 1, a - top : b - top + 1], m - e + a
            open_ = {"d": z == w, "u": down[a : b + 1] == 0, "l": across[r : r + b - a + 1] == 0}
            for k, move in reversed(list(enumerate(tie))):
                row[open_[move]] = k
        while i and j and i + j > c:
            move = tie[rows[i + j - c - 1, i - top]]
            moves.append(move)
            i, j = i - (move != "l"), j - (move != "u")
    return "l" * j + "u" * i + "".join(reversed(moves))


def alike(x: bytes, y: bytes, grams: int = 16, least: int = 4) -> bool:
    """Whether some of a few stretches of x are in y: then moves_by_waves() is likely to be fast."""
    step = len(x) // grams
    return step >= 16 and sum(x[k * step : k * step + 16] in y for k in range(grams)) >= least


def moves_by_waves(x: np.ndarray, y: np.ndarray, kinds: tuple[int, int, int | None, int, int], gap: int, tie: str = "dul", most: float = 20.0) -> str | None:
    """Moves of the path that traceback() takes between sequences that differ little; None if they differ too much for it.

    A path's score is match * (n + m) / 2 less what its mismatches and gaps cost. Costs never fall along a diagonal, so for
    each cost it is enough to know how far cells of no higher cost go on each diagonal; equal symbols are passed at once,
    and moving over them along the diagonal is never worse. The same reaches say which moves lead to a cell.
    """
    same, other, g, edge, both = kinds
    n, m, price = len(x), len(y), [2 * (same - v) for v in ((other,) if g is None else (other, edge, both))]
    shift = same - 2 * gap
    if tie[0] != "d" or min(*price, shift) <= 0:
        return None
    unit = math.gcd(shift, *price)
    shift, price, odd = shift // unit, [v // unit for v in price], g is not None
    if odd:  # such a symbol equals none, itself neither
        odd_x, odd_y, paid_ = (x == g).astype(np.int8), (y == g).astype(np.int8), np.array(price)
        x, y = np.where(x == g, 254, x), np.where(y == g, 255, y)
    x, y = x.astype(np.uint8), y.astype(np.uint8)
    # eight symbols from each place on, none alike beyond the ends
    next_x, next_y = (np.ndarray(len(z) + 1, "<u8", z.tobytes() + bytes([pad] * 8), 0, (1,)).copy() for z, pad in ((x, 252), (y, 253)))
    reach, cost, end = [], 0, m - n  # by cost: (first diagonal, how far cells go on this one and the next)
    low, now, old = 0, np.zeros(1, np.int32), np.full(1, -1, np.int32)
    while True:
        k = np.arange(low, low + len(now), dtype=np.int32)
        np.minimum(now, np.minimum(n, m - k), out=now)
        going = np.flatnonzero(now > old)
        while len(going):  # over equal symbols
            i = now[going]
            other_ = next_x[i] ^ next_y[i + k[going]]
            now[going] = i + np.where(other_ == 0, 8, np.bitwise_count((other_ & (~other_ + np.uint64(1))) - np.uint64(1)) >> 3)
            going = going[other_ == 0]
        reach.append((low, now))
        if low <= end < low + len(now) and now[end - low] >= n:
            break
        cost += 1
        if cost > most * math.sqrt(n + m) * shift / 5:
            return None
        was, last = low, low + len(now)
        if cost >= shift:
            first, far = reach[cost - shift]
            low, last = min(low, max(first - 1, -n)), max(last, min(first + len(far), m) + 1)
        old = np.full(last - low, -1, np.int32)
        old[was - low : was - low + len(now)] = now
        now = old.copy()
        if cost >= shift:
            skip = first - 1 < low  # off the table
            to = now[first - 1 + skip - low : first - 1 + len(far) - low]
            np.maximum(to, far[skip:] + 1, out=to)
            to = now[first + 1 - low : first + 1 + len(far) - low]
            np.maximum(to, far[: len(to)], out=to)
        for v in {v for v in price if v <= cost}:
            first, far = reach[cost - v]
            to, step = now[first - low : first - low + len(far)], 1
            if odd:
                on = np.arange(first, first + len(far), dtype=np.int32)
                inside = far < np.minimum(n, m - on)
                i = np.where(inside, far, 0)
                step = inside & (paid_[odd_x[i] + odd_y[np.where(inside, far + on, 0)]] <= v)
            np.maximum(to, far + step, out=to)

    unlike: dict[int, np.ndarray] = {}  # places of different symbols by diagonal

    def places(k: int) -> np.ndarray:
        if k not in unlike:
            a, b = max(0, -k), min(n, m - k)
            unlike[k] = np.flatnonzero(x[a:b] != y[a + k : b + k]) + a
        return unlike[k]

    def reached(c: int, k: int, i: int) -> bool:
        return c >= 0 and 0 <= k - reach[c][0] < len(reach[c][1]) and reach[c][1][k - reach[c][0]] >= i

    i, j, moves = n, m, []
    while i and j:
        r = places(j - i)
        at = int(np.searchsorted(r, i)) - 1
        if run := i - (int(r[at]) + 1 if at >= 0 else max(0, i - j)):
            moves.append("d" * run)
            i, j = i - run, j - run
            continue
        paid = price[odd_x[i - 1] + odd_y[j - 1]] if odd else price[0]
        for move in tie:
            if reached(cost - (paid if move == "d" else shift), j - i + (move == "u") - (move == "l"), i - (move != "l")):
                break
        cost -= paid if move == "d" else shift
        moves.append(move)
        i, j = i - (move != "l"), j - (move != "u")
    return "l" * j + "u" * i + "".join(reversed(moves))


@lru_cache(maxsize=64)
def _near(x: bytes, y: bytes, kinds: tuple[int, int, int | None, int, int], gap: int, tie: str) -> str | None:
    if not alike(x, y):
        return None
    return moves_by_waves(np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8), kinds, gap, tie)


def near_moves(x: np.ndarray, y: np.ndarray, t: np.ndarray, gap: float, tie: str = "dul") -> str | None:
    """Moves of the path that traceback() takes, if the sequences are long and differ little; x, y: numbers of symbols, t: their scores."""
    if min(len(x), len(y)) < 256 or not float(gap).is_integer() or not (kinds := _kinds(t)):
        return None
    if kinds[2] is not None and not (x == kinds[2]).any() and not (y == kinds[2]).any():
        kinds = (*kinds[:2], None, 0, 0)
    return _near(x.astype(np.uint8).tobytes(), y.astype(np.uint8).tobytes(), kinds, int(gap), tie)


@lru_cache(maxsize=64)
def _remembered(x: bytes, y: bytes, kinds: tuple[int, int, int | None, int, int], gap: int, tie: str) -> str:
    """Two sequences of a family meet for their distance and again in the merges of each tree and seed."""
    return moves_by_diagonals(np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8), kinds, gap, tie)


def moves_of(x: np.ndarray, y: np.ndarray, t: np.ndarray, gap: float, tie: str = "dul") -> str:
    """Moves of the path that traceback() takes, for tables too large to hold; x, y: numbers of symbols, t: their scores."""
    kinds = _kinds(t) if float(gap).is_integer() and gap <= 0 else None
    if kinds and max(kinds[0], kinds[1], *kinds[3:]) - 2 * gap <= 100:
        if kinds[2] is not None and not (x == kinds[2]).any() and not (y == kinds[2]).any():
            kinds = (*kinds[:2], None, 0, 0)
        return _remembered(x.astype(np.uint8).tobytes(), y.astype(np.uint8).tobytes(), kinds, int(gap), tie)
    rows = t[:, y]
    return moves_in_band(lambda i, j0, j1: rows[x[i], j0:j1], len(x), len(y), gap, t.max(), tie, t.dtype.kind == "i")


def align_moves(a: Sequence[str], b: Sequence[str], scoring: Scoring, tie: str = "dul", limit: int = 4_000_000) -> tuple[str, float]:
    """(moves, score); above `limit` cells memory stays linear, and ties may go another way than `tie`."""
    symbols, (x, y) = coded([a, b])
    t = scoring.table(symbols) if symbols else np.zeros((1, 1), np.int64)
    if len(x) * len(y) <= limit:
        sub = t[x[:, None], y[None, :]] if len(x) and len(y) else np.zeros((len(x), len(y)), t.dtype)
        h = table(sub, scoring.gap)
        return traceback(h, sub, scoring.gap, tie), h[-1, -1].item()
    moves = moves_in_linear_memory(lambda i, j0, j1: t[x[i], y[j0:j1]].astype(float), len(x), len(y), scoring.gap)
    return moves, scores([(a, b)], scoring)[0].item()


def spell(a: Sequence[str], b: Sequence[str], moves: str) -> tuple[str, str]:
    i = j = 0
    left, right = [], []
    for m in moves:
        left.append(GAP if m == "l" else a[i])
        right.append(GAP if m == "u" else b[j])
        i, j = i + (m != "l"), j + (m != "u")
    return "".join(left), "".join(right)


def count_optimal(a: str, b: str, scoring: Scoring) -> int:
    """Number of different optimal paths."""
    sub = substitution(a, b, scoring)
    h = table(sub, scoring.gap)
    n, m = len(a), len(b)
    ways = [[0] * (m + 1) for _ in range(n + 1)]
    ways[0][0] = 1
    for i in range(n + 1):
        for j in range(m + 1):
            if i and j and h[i, j] == h[i - 1, j - 1] + sub[i - 1, j - 1]:
                ways[i][j] += ways[i - 1][j - 1]
            if i and h[i, j] == h[i - 1, j] + scoring.gap:
                ways[i][j] += ways[i - 1][j]
            if j and h[i, j] == h[i, j - 1] + scoring.gap:
                ways[i][j] += ways[i][j - 1]
    return ways[n][m]


def all_optimal(a: str, b: str, scoring: Scoring, limit: int) -> Iterator[tuple[str, str]]:
    """Up to `limit` optimal alignments, in order of d, u, l from the end."""
    sub = substitution(a, b, scoring)
    h = table(sub, scoring.gap)
    stack, found = [(len(a), len(b), "")], 0
    while stack and found < limit:
        i, j, moves = stack.pop()
        if not i and not j:
            found += 1
            yield spell(a, b, moves)
            continue
        nexts = []
        if i and j and h[i, j] == h[i - 1, j - 1] + sub[i - 1, j - 1]:
            nexts.append((i - 1, j - 1, "d" + moves))
        if i and h[i, j] == h[i - 1, j] + scoring.gap:
            nexts.append((i - 1, j, "u" + moves))
        if j and h[i, j] == h[i, j - 1] + scoring.gap:
            nexts.append((i, j - 1, "l" + moves))
        stack.extend(reversed(nexts))


def banded_score(a: str, b: str, scoring: Scoring, start: int = 8) -> tuple[float, int]:
    """(optimal score, band): the band doubles until no path that leaves it could score higher.

    A path that leaves the band of `band` diagonals beside the corners' has that many gaps more than the lengths ask for.
    """
    symbols, (x, y) = coded([a, b])
    t = scoring.table(symbols) if symbols else np.zeros((1, 1), np.int64)
    n, m, band = len(a), len(b), start
    best = max(scoring.match, float(t.max()))
    while True:
        lo, hi = min(0, m - n) - band, max(0, m - n) + band
        row, new = np.full((2, m + 1), LOW, float)  # only the band and its rim are touched from row to row
        row[: min(m, hi) + 1] = np.arange(min(m, hi) + 1) * scoring.gap
        for i in range(1, n + 1):
            j0, j1 = max(0, i + lo), min(m, i + hi)
            k0 = max(j0, 1)
            if j0 > 0:
                new[j0 - 1] = LOW
            if j1 < m:
                new[j1 + 1] = LOW
            if k0 <= j1:
                new[k0 : j1 + 1] = np.maximum(row[k0 - 1 : j1] + t[x[i - 1], y[k0 - 1 : j1]], row[k0 : j1 + 1] + scoring.gap)
            if j0 == 0:
                new[0] = i * scoring.gap
            steps = np.arange(j0, j1 + 1) * scoring.gap
            new[j0 : j1 + 1] = np.maximum.accumulate(new[j0 : j1 + 1] - steps) + steps
            row, new = new, row
        gaps = abs(n - m) + 2 * (band + 1)
        if row[m] >= best * max(n + m - gaps, 0) / 2 + scoring.gap * gaps or band > n + m:
            return row[m].item(), band
        band *= 2


def pair_counts(a: str, b: str) -> tuple[int, int, int]:
    """(matches, mismatches, letter-gap columns) of two aligned rows; gap-gap columns count nothing."""
    same = sum(x == y != GAP for x, y in zip(a, b))
    gaps = sum((x == GAP) != (y == GAP) for x, y in zip(a, b))
    return same, sum(x != y and GAP not in (x, y) for x, y in zip(a, b)), gaps


METRICS = ("mismatch_gap", "p_distance", "edit", "score_normalised", "kmer", "jc_corrected")


def kmer_distance(a: str, b: str, k: int = 3) -> float:
    from collections import Counter

    x, y = (Counter(s[i : i + k] for i in range(len(s) - k + 1)) for s in (a, b))
    short = min(sum(x.values()), sum(y.values()))
    return 1 - sum((x & y).values()) / short if short else float(a != b)


def from_counts(counts: np.ndarray, metric: str) -> np.ndarray:
    """Distances of a metric that only needs (matches, mismatches, gaps)."""
    same, other, gaps = counts.T.astype(float)
    if metric == "mismatch_gap":
        return np.divide(other + gaps, same + other + gaps, out=np.zeros(len(same)), where=same + other + gaps > 0)
    p = np.divide(other, same + other, out=np.zeros(len(same)), where=same + other > 0)
    return p if metric == "p_distance" else -0.75 * np.log(np.maximum(1 - 4 * p / 3, 1e-6))


def distances(pairs: Sequence[tuple[str, str]], metric: str, scoring: Scoring, tie: str = "dul") -> np.ndarray:
    if metric == "edit":
        return -scores(pairs, Scoring.unit_edit()).astype(float)
    if metric == "kmer":
        return np.array([kmer_distance(a, b) for a, b in pairs], float)
    if metric == "score_normalised":
        own = scores([(s, s) for p in pairs for s in p], scoring).reshape(-1, 2).min(1)
        return np.array([1 - v / o if o else float(a != b) for v, o, (a, b) in zip(scores(pairs, scoring), own, pairs)], float)
    if metric in ("mismatch_gap", "p_distance", "jc_corrected"):
        return from_counts(path_counts(pairs, scoring, tie), metric)
    raise ValueError(f"unknown metric {metric}")


def distance(a: str, b: str, metric: str, scoring: Scoring, tie: str = "dul") -> float:
    return float(distances([(a, b)], metric, scoring, tie)[0])


def distance_matrix(seqs: Sequence[str], metric: str, scoring: Scoring, tie: str = "dul") -> np.ndarray:
    n = len(seqs)
    d = np.zeros((n, n))
    at = [(i, j) for i in range(n) for j in range(i + 1, n)]
    if at:
        every = [(seqs[i], seqs[j]) for i, j in at]
        pairs = list(dict.fromkeys(every))  # copies of a sequence
        if metric == "score_gap":
            v = scores(pairs, scoring)
            v = v.max() - v
        else:
            v = distances(pairs, metric, scoring, tie)
        of = dict(zip(pairs, range(len(pairs))))
        d[tuple(zip(*at))] = v[[of[p] for p in every]]
    return d + d.T


# ---- guide trees -----------------------------------------------------------


@dataclass
class Tree:
    """Joins in order: (left, right, node, left_len, right_len, height); leaves are 0..n-1, joins n, n+1, ..."""

    n: int
    joins: list[tuple[int, int, int, float, float, float]] = field(default_factory=list)

    def children(self) -> dict[int, tuple[int, int]]:
        return {k: (a, b) for a, b, k, *_ in self.joins}

    def leaves(self) -> dict[int, list[int]]:
        out = {i: [i] for i in range(self.n)}
        for a, b, k, *_ in self.joins:
            out[k] = sorted(out[a] + out[b])
        return out

    def splits(self) -> set[frozenset[int]]:
        """Bipartitions of the unrooted tree, each as the side without leaf 0; the trivial ones are left out."""
        every = frozenset(range(self.n))
        sides = (frozenset(v) for v in self.leaves().values())
        return {s for x in sides if 1 < len(s := every - x if 0 in x else x) < self.n - 1}

    def edges(self) -> list[tuple[int, int, float]]:
        """Edges of the unrooted tree: the root of a joined tree is taken out."""
        out = [(a, k, x) for a, _, k, x, _, _ in self.joins[:-1]] + [(b, k, y) for _, b, k, _, y, _ in self.joins[:-1]]
        if self.joins:
            a, b, _, x, y, _ = self.joins[-1]
            out.append((a, b, x + y))
        return out

    def cophenetic(self) -> np.ndarray:
        """Path lengths between leaves."""
        near: dict[int, list[tuple[int, float]]] = {i: [] for i in range(self.n)}
        for a, b, w in self.edges():
            near.setdefault(a, []).append((b, w))
            near.setdefault(b, []).append((a, w))
        d = np.zeros((self.n, self.n))
        for i in range(self.n):
            stack = [(i, -1, 0.0)]
            while stack:
                at, came, far = stack.pop()
                if at < self.n:
                    d[i, at] = far
                stack += [(b, at, far + w) for b, w in near[at] if b != came]
        return d

    def levels(self) -> dict[int, int]:
        """Joins of one level don't depend on each other."""
        level = dict.fromkeys(range(self.n), 0)
        for a, b, k, *_ in self.joins:
            level[k] = 1 + max(level[a], level[b])
        return {k: v for k, v in level.items() if k >= self.n}

    def newick(self, names: Sequence[str] | None = None, digits: int = 6) -> str:
        text = {i: str(names[i] if names is not None else i) for i in range(self.n)}
        for a, b, k, x, y, _ in self.joins:
            text[k] = f"({text[a]}:{round(x, digits):g},{text[b]}:{round(y, digits):g})"
        return (text[self.joins[-1][2]] if self.joins else text.get(0, "")) + ";"

    def leaf_order(self) -> list[int]:
        kids, out, stack = self.children(), [], [self.joins[-1][2] if self.joins else 0]
        while stack:
            k = stack.pop()
            stack += reversed(kids[k]) if k in kids else []
            out += [] if k in kids else [k]
        return out

    def depth(self) -> int:
        return max(self.levels().values(), default=0)


def parse_newick(text: str) -> tuple[Tree, list[str]]:
    """(tree, leaf names) of a binary Newick text with or without lengths."""
    names: list[str] = []
    inner: list[tuple] = []
    at = 0

    def read() -> tuple:
        nonlocal at
        if text[at] == "(":
            at += 1
            kids = [read()]
            while text[at] == ",":
                at += 1
                kids.append(read())
            at += 1
            here: tuple = ("join", kids)
        else:
            end = at
            while text[end] not in ",():;":
                end += 1
            names.append(text[at:end])
            here, at = ("leaf", len(names) - 1), end
        size = 0.0
        if text[at] == ":":
            end = at + 1
            while text[end] not in ",();":
                end += 1
            size, at = float(text[at + 1 : end]), end
        return here, size

    top, _ = read()

    def number(node: tuple) -> int:
        if node[0] == "leaf":
            return node[1]
        (a, x), (b, y) = node[1]
        left, right = number(a), number(b)
        inner.append((left, right, len(names) + len(inner), x, y, 0.0))
        return inner[-1][2]

    number(top)
    return Tree(len(names), inner), names


def _least(values: np.ndarray, ids: np.ndarray) -> tuple[int, int]:
    """(row, column) of the least value, ties by the smaller then the larger node id; ids grow with the position."""
    v = np.round(values, 9)
    v[np.tril_indices(len(v))] = np.inf
    return divmod(int(np.argmin(v)), len(v))


def neighbor_joining(d: np.ndarray, root: str = "midpoint", negative: str = "keep", search: str = "scan") -> Tree:
    """Neighbor-Joining over a distance matrix: divergences, the best pair, its stems, the reduced distances, again.

    search="pruned" skips rows whose least distance can't beat the best criterion so far; the tree is the same.
    """
    n = len(d)
    d, ids, tree = np.array(d, float), np.arange(n), Tree(n)
    clamp = (lambda x: max(x, 0.0)) if negative == "clamp" else float
    while len(ids) > 2:
        k = len(ids)
        r = d.sum(1) / (k - 2)
        if search == "pruned":
            best, pick = np.inf, (0, 1)
            off = d + np.where(np.eye(k, dtype=bool), np.inf, 0)
            bound = off.min(1) - r - r.max()
            for p in np.argsort(bound, kind="stable"):
                if bound[p] > best + 1e-8:
                    break
                q = np.round(d[p] - r[p] - r, 9)
                q[p] = np.inf
                for j in np.flatnonzero(q == q.min()):
                    pair = (min(p, j), max(p, j))
                    if (q[j], pair) < (best, pick):
                        best, pick = q[j], pair
            p, q = map(int, pick)
        else:
            p, q = _least(d - r[:, None] - r[None, :], ids)
        x = 0.5 * (d[p, q] + r[p] - r[q])
        tree.joins.append((int(ids[p]), int(ids[q]), n + len(tree.joins), clamp(x), clamp(d[p, q] - x), 0.0))
        new = 0.5 * (d[p] + d[q] - d[p, q])
        keep = np.array([i for i in range(k) if i not in (p, q)])
        bigger = np.zeros((k - 1, k - 1))
        bigger[:-1, :-1] = d[np.ix_(keep, keep)]
        bigger[-1, :-1] = bigger[:-1, -1] = new[keep]
        d, ids = bigger, np.append(ids[keep], n + len(tree.joins) - 1)
    if len(ids) == 2:
        tree.joins.append((int(ids[0]), int(ids[1]), n + len(tree.joins), clamp(d[0, 1]) / 2, clamp(d[0, 1]) / 2, 0.0))
    return midpoint(tree) if root == "midpoint" else tree


def midpoint(tree: Tree) -> Tree:
    """The same unrooted tree with its root in the middle of the longest path between leaves."""
    if tree.n < 3:
        return tree
    near: dict[int, list[tuple[int, float]]] = {}
    for a, b, w in tree.edges():
        near.setdefault(a, []).append((b, w))
        near.setdefault(b, []).append((a, w))

    def far(start: int) -> dict[int, tuple[float, int]]:
        out, stack = {start: (0.0, -1)}, [start]
        while stack:
            at = stack.pop()
            for b, w in near[at]:
                if b != out[at][1]:
                    out[b] = (out[at][0] + w, at)
                    stack.append(b)
        return out

    best = max(((round(far(i)[j][0], 9), -i, -j) for i in range(tree.n) for j in range(i + 1, tree.n)))
    i, j = -best[1], -best[2]
    reach, at = far(i), j
    while reach[at][1] != i and reach[reach[at][1]][0] >= best[0] / 2:
        at = reach[at][1]
    above = reach[at][1]  # the root lies on the edge from above to at
    split = min(max(best[0] / 2 - reach[above][0], 0.0), max(reach[at][0] - reach[above][0], 0.0))
    out, size = Tree(tree.n), reach[at][0] - reach[above][0]
    joins: list[tuple[float, int, int, float, float, int]] = []

    def down(node: int, came: int) -> tuple[int, float]:
        """(number, height) of the subtree that hangs at node; joins are numbered in the order they can be made."""
        kids = [(b, w) for b, w in near[node] if b != came]
        if not kids:
            return node, 0.0
        (a, x), (b, y) = [(down(b, node), w) for b, w in kids]
        height = max(a[1] + x, b[1] + y)
        joins.append((height, a[0], b[0], x, y, -1 - len(joins)))
        return joins[-1][5], height

    import sys

    sys.setrecursionlimit(max(sys.getrecursionlimit(), 4 * tree.n + 1000))
    (a, ha), (b, hb) = down(above, at), down(at, above)
    joins.append((max(ha + split, hb + size - split), a, b, split, size - split, -1 - len(joins)))
    number = {i: i for i in range(tree.n)}
    # nearest first, children before parents
    waiting = sorted(joins, key=lambda x: (round(x[0], 9), -x[5]))
    while waiting:
        ready = next(x for x in waiting if x[1] in number and x[2] in number)
        waiting.remove(ready)
        k = tree.n + len(out.joins)
        left, right = sorted([(number[ready[1]], ready[3]), (number[ready[2]], ready[4])])
        out.joins.append((left[0], right[0], k, left[1], right[1], ready[0]))
        number[ready[5]] = k
    return out


LINKAGES = ("average", "weighted", "single", "complete")


def _update(linkage: str, a: np.ndarray, b: np.ndarray, na: int, nb: int) -> np.ndarray:
    if linkage == "average":
        return (na * a + nb * b) / (na + nb)
    if linkage == "weighted":
        return (a + b) / 2
    if linkage == "single":
        return np.minimum(a, b)
    if linkage == "complete":
        return np.maximum(a, b)
    raise ValueError(f"unknown linkage {linkage}")


def agglomerative(d: np.ndarray, linkage: str = "average", search: str = "scan") -> Tree:
    """Fuse the closest live pair again and again; a fusion's height is half its distance. search: scan, or chain (quadratic)."""
    n = len(d)
    if search == "chain" and (tree := _chain(np.array(d, float), linkage)) is not None:
        return tree
    d, ids, sizes, heights, tree = np.array(d, float), np.arange(n), np.ones(n), np.zeros(n), Tree(n)
    while len(ids) > 1:
        p, q = _least(d.copy(), ids)
        h = d[p, q] / 2
        tree.joins.append((int(ids[p]), int(ids[q]), n + len(tree.joins), h - heights[p], h - heights[q], h))
        new = _update(linkage, d[p], d[q], sizes[p], sizes[q])
        keep = np.array([i for i in range(len(ids)) if i not in (p, q)], int)
        bigger = np.zeros((len(ids) - 1, len(ids) - 1))
        bigger[:-1, :-1] = d[np.ix_(keep, keep)]
        bigger[-1, :-1] = bigger[:-1, -1] = new[keep]
        sizes, heights = np.append(sizes[keep], sizes[p] + sizes[q]), np.append(heights[keep], h)
        d, ids = bigger, np.append(ids[keep], n + len(tree.joins) - 1)
    return tree


def _chain(d: np.ndarray, linkage: str) -> Tree | None:
    """Nearest-neighbour chains; fusions are put in order of height at the end. None where distances tie (to 9 places): the
    chain would settle ties in the order it comes upon them, and only a scan by the order of ids."""
    n = len(d)
    np.fill_diagonal(d, np.inf)
    live, sizes, found, chain = np.ones(n, bool), np.ones(n), [], []
    for _ in range(n - 1):
        if not chain:
            chain.append(int(np.flatnonzero(live)[0]))
        while True:
            a = chain[-1]
            row = np.where(live, d[a], np.inf)
            b = int(np.argmin(row))
            if len(chain) > 1 and row[chain[-2]] <= row[b]:
                b = chain[-2]
                break
            chain.append(b)
        chain = chain[:-2]
        found.append((d[a, b], min(a, b), max(a, b)))
        a, b = min(a, b), max(a, b)
        if any((np.round(np.where(live, d[k], np.inf), 9) <= round(d[a, b], 9)).sum() > 1 for k in (a, b)):
            return None
        new = _update(linkage, d[a], d[b], sizes[a], sizes[b])
        d[a], d[:, a], d[a, a] = new, new, np.inf
        live[b] = False
        sizes[a] += sizes[b]
    if len({round(v, 9) for v, _, _ in found}) < len(found):
        return None
    tree, node, height = Tree(n), list(range(n)), dict.fromkeys(range(n), 0.0)
    for v, a, b in sorted(found, key=lambda x: round(x[0], 9)):
        k = n + len(tree.joins)
        left, right = sorted((node[a], node[b]))
        tree.joins.append((left, right, k, v / 2 - height[left], v / 2 - height[right], v / 2))
        node[a], height[k] = k, v / 2
        for i in range(n):
            if node[i] in (left, right):
                node[i] = k
    return tree


def caterpillar(n: int) -> Tree:
    """Sequences one after the other, in input order."""
    return Tree(n, [(0 if k == 0 else n + k - 1, k + 1, n + k, 0.0, 0.0, float(k + 1)) for k in range(n - 1)])


def random_tree(n: int, seed: int = 0) -> Tree:
    live, tree = list(range(n)), Tree(n)
    for k in range(n - 1):
        a = live.pop(draw(seed, "tree", k, 0, len(live)))
        b = live.pop(draw(seed, "tree", k, 1, len(live)))
        tree.joins.append((min(a, b), max(a, b), n + k, 0.0, 0.0, float(k + 1)))
        live.append(n + k)
    return tree


def star(d: np.ndarray) -> Tree:
    """The most central sequence first, then the others by distance from it."""
    n = len(d)
    if n < 2:
        return Tree(n)
    order = np.argsort(d[int(np.argmin(d.sum(1)))], kind="stable")
    centre = int(np.argmin(d.sum(1)))
    rest, tree, at = [int(i) for i in order if i != centre], Tree(n), centre
    for k, i in enumerate(rest):
        tree.joins.append((min(at, i), max(at, i), n + k, 0.0, 0.0, float(k + 1)))
        at = n + k
    return tree


# ---- profiles and merges ---------------------------------------------------

#: A minimal-standard generator, the same in numpy, Spark SQL and DuckDB as nothing overflows 64 bits.
DRAW_MOD, DRAW_MUL = 2147483647, 48271


def draw(seed: int, family: str, node: int, pos: int, k: int) -> int:
    """A number below k from seed, family, node and position: the same on every retry and partitioning."""
    x = (seed + 1) % DRAW_MOD
    for v in (zlib.crc32(family.encode()), node, pos, 0, 0):
        x = (x * DRAW_MUL + v) % DRAW_MOD
    return x % k


def consensus(counts: np.ndarray, symbols: list[str], tie: str, seed: int, family: str, node: int, partner: Sequence[int] | None = None, gap_policy: str = "include") -> np.ndarray:
    """Number of the winning symbol of each position.

    tie: first or last symbol among the equal ones, or partner: the partner's symbol there if it is one of them, else a draw.
    """
    counts = counts.copy()
    if gap_policy == "exclude" and GAP in symbols:
        g = symbols.index(GAP)
        others = np.delete(counts, g, 1).sum(1) > 0
        counts[others, g] = -1
    top = counts == counts.max(1, keepdims=True)
    won = np.argmax(top, 1)
    if tie == "last":
        return counts.shape[1] - 1 - np.argmax(top[:, ::-1], 1)
    if tie == "partner":
        for pos in np.flatnonzero(top.sum(1) > 1):
            tied = np.flatnonzero(top[pos])
            if partner is not None and pos < len(partner) and partner[pos] in tied:
                won[pos] = partner[pos]
            else:
                won[pos] = tied[draw(seed, family, node, int(pos), len(tied))]
    return won


@dataclass
class Options:
    scoring: Scoring = field(default_factory=Scoring.experiment)
    tie: str = "partner"
    traceback: str = "dul"
    gap_policy: str = "include"
    gap_symbol: str = "neutral"
    mode: str = "consensus"
    seed: int = 0


def merge_columns(a: np.ndarray, b: np.ndarray, symbols: list[str], o: Options, family: str, node: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(columns of a in the merge, columns of b, counts of the merge) of two sides given as counts by position and symbol."""
    na, nb = int(a[0].sum()) if len(a) else 0, int(b[0].sum()) if len(b) else 0
    t = o.scoring.table(symbols)
    g = symbols.index(GAP)
    if o.gap_symbol == "symbol":
        t = t.copy()
        t[g, :] = t[:, g] = o.scoring.mismatch
        t[g, g] = o.scoring.match
    if o.mode == "expected":
        left, right = (a / max(na, 1)) @ t.astype(float), (b / max(nb, 1)).T
        of = lambda i, j0, j1: left[i] @ right[:, j0:j1]
        sub = left @ right if len(a) * len(b) <= CELLS else None
    else:
        right = consensus(b, symbols, o.tie, o.seed, family, 2 * node + 1, None, o.gap_policy) if len(b) else np.zeros(0, int)
        left = consensus(a, symbols, o.tie, o.seed, family, 2 * node, right, o.gap_policy) if len(a) else np.zeros(0, int)
        right = consensus(b, symbols, o.tie, o.seed, family, 2 * node + 1, left, o.gap_policy) if len(b) else right
        path = near_moves(left, right, t, o.scoring.gap, o.traceback)
        sub = None if path or len(a) * len(b) > CELLS else t[left[:, None], right[None, :]] if len(a) and len(b) else np.zeros((len(a), len(b)), t.dtype)
    if o.mode != "expected" and path:
        pass
    elif sub is None and o.mode == "expected":
        path = moves_in_band(of, len(a), len(b), o.scoring.gap, t.max(), o.traceback, False)
    elif sub is None:
        path = moves_of(left, right, t, o.scoring.gap, o.traceback)
    else:
        path = traceback(table(sub, o.scoring.gap), sub, o.scoring.gap, o.traceback)
    moves = np.frombuffer(path.encode(), np.uint8)
    at_a, at_b = np.flatnonzero(moves != ord("l")), np.flatnonzero(moves != ord("u"))
    counts = np.zeros((len(moves), len(symbols)), np.int64)
    counts[at_a] += a
    counts[at_b] += b
    counts[moves == ord("l"), g] += na
    counts[moves == ord("u"), g] += nb
    return at_a, at_b, counts


def progressive(seqs: Sequence[str], tree: Tree, o: Options, family: str = "") -> tuple[list[str], int]:
    """(aligned rows, cells filled): profiles merged in tree order; a gap once placed stays."""
    n = len(seqs)
    symbols, coded_ = coded(seqs, GAP)
    if n == 1:
        return [seqs[0]], 0
    g, counts, own = symbols.index(GAP), {}, {}
    for i, x in enumerate(coded_):
        counts[i] = np.zeros((len(x), len(symbols)), np.int64)
        counts[i][np.arange(len(x)), x] = 1
    members = {i: 1 for i in range(n)}
    leaves, cells = tree.leaves(), 0
    for a, b, k, *_ in tree.joins:
        a, b = sorted((a, b), key=lambda x: leaves[x][0])  # the smaller leaf is on the left
        left, right = counts.pop(a), counts.pop(b)
        cells += (len(left) + 1) * (len(right) + 1)
        if not len(left) or not len(right):  # a side of empty sequences is all gaps
            at_a, at_b = np.arange(len(left)), np.arange(len(right))
            both = left.copy() if len(left) else right.copy()
            both[:, g] += members[b] if len(left) else members[a]
        else:
            at_a, at_b, both = merge_columns(left, right, symbols, o, family, k)
        counts[k], own[k], members[k] = both, ((a, at_a), (b, at_b)), members[a] + members[b]
    top = tree.joins[-1][2]
    width = len(counts[top])
    place = {top: np.arange(width)}
    for *_, k in [(0, j[2]) for j in reversed(tree.joins)]:
        for child, at in own[k]:
            place[child] = place[k][at]
    out = []
    for i, x in enumerate(coded_):
        row = np.full(width, g)
        row[place[i][: len(x)]] = x
        out.append("".join(symbols[c] for c in row))
    return out, cells


def sum_of_pairs(rows: Sequence[str], s: Scoring) -> tuple[int, int, int]:
    """(matches, mismatches, letter-gap pairs) over all row pairs and columns, from counts by column."""
    if not rows or not rows[0]:
        return 0, 0, 0
    a = np.array([list(r) for r in rows])
    same = other = gaps = 0
    letters = [c for c in np.unique(a) if c != GAP]
    c = np.stack([(a == x).sum(0) for x in letters]) if letters else np.zeros((1, a.shape[1]), int)
    full = c.sum(0)
    same = int((c * (c - 1) // 2).sum())
    other = int((full * (full - 1) // 2).sum()) - same
    gaps = int((full * (len(rows) - full)).sum())
    return same, other, gaps


def exact_three(a: str, b: str, c: str, s: Scoring, limit: int = 60) -> float:
    """Best sum-of-pairs score of three strings, by dynamic programming over a cube."""
    if max(len(a), len(b), len(c)) > limit:
        raise ValueError(f"exact alignment of three is for strings of at most {limit} symbols")
    symbols, (x, y, z) = coded([a, b, c], GAP)
    t = s.table(symbols)
    g = symbols.index(GAP)
    h = np.full((len(x) + 1, len(y) + 1, len(z) + 1), LOW, float)
    h[0, 0, 0] = 0
    for i in range(len(x) + 1):
        for j in range(len(y) + 1):
            for k in range(len(z) + 1):
                for di, dj, dk in ((1, 1, 1), (1, 1, 0), (1, 0, 1), (0, 1, 1), (1, 0, 0), (0, 1, 0), (0, 0, 1)):
                    if i >= di and j >= dj and k >= dk:
                        p, q, r = (x[i - 1] if di else g), (y[j - 1] if dj else g), (z[k - 1] if dk else g)
                        v = h[i - di, j - dj, k - dk] + t[p, q] + t[p, r] + t[q, r]
                        h[i, j, k] = max(h[i, j, k], v)
    return h[-1, -1, -1].item()


def exact_many(seqs: Sequence[str], s: Scoring) -> float:
    raise NotImplementedError("exact alignment under sum-of-pairs is NP-hard and offered for at most three sequences; use progressive.align")


def add_sequence(rows: Sequence[str], seq: str, o: Options, family: str = "") -> list[str]:
    """rows and seq aligned: one sequence-profile merge; the rows keep their gaps."""
    symbols, coded_ = coded([*rows, seq], GAP)
    a = np.zeros((len(rows[0]) if rows else 0, len(symbols)), np.int64)
    for r in coded_[:-1]:
        a[np.arange(len(r)), r] += 1
    b = np.zeros((len(seq), len(symbols)), np.int64)
    b[np.arange(len(seq)), coded_[-1]] = 1
    at_a, at_b, counts = merge_columns(a, b, symbols, o, family, len(rows))
    out = []
    for text, at in [*((r, at_a) for r in rows), (seq, at_b)]:
        row = [GAP] * len(counts)
        for c, k in zip(text, at):
            row[k] = c
        out.append("".join(row))
    return out
