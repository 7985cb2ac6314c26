"""Removal of repeated byte strings across documents, by the interval tree of an enhanced suffix array.

A document loses every byte that a string of LENGTH bytes covers which also starts in a document with a smaller doc_id.

1. Each document is cut into runs: consecutive places at which the least hash of the K-byte strings inside the
   LENGTH-byte string that starts there is the same. That least hash is the run's key; equal strings have equal keys, so
   only runs of one key can share a string. About one run starts in every 16 bytes.
2. The texts of the runs whose key several documents have go through the tree: an enhanced suffix array over the places
   that can start a maximal repeat, and a stack scan of its common-prefix intervals, which gives each maximal repeat
   (LENGTH or longer, with different bytes before its occurrences) with all its occurrences at once. Those in documents
   after its first go. Runs of equal text enter once for their first and once for their second document; what the tree
   says of the second holds for all later ones.
3. The tree is asked twice. First in each stretch of input (GATHER bytes), whose runs then go on only if some place of
   them is still without an earlier copy; so a key sends about one document's runs from each stretch, however frequent it
   is. Then by key over all stretches: first the keys that more than one document has are found, then the texts of
   these are fetched, one for each different text, and put through the tree.
4. Each document's spans are merged and its other bytes hashed.

What goes from task to task is packed: one row for each stretch and bucket of keys, and for each bucket and drawer of
documents, that have something to say to each other. Buckets and drawers come from the input's bytes, not from the
session's partitions, and rows never outnumber the runs in them. A key so frequent that its runs with different
surroundings would fill one task (HOT_DOCS or more of about SAMPLE documents taken by hash of doc_id) is dealt further:
places of it that are left after step 2 travel one by one under the hash of their own LENGTH bytes. Which keys those are
decides on the spread alone, never on the result.

Edge cases: a null text is empty; texts shorter than LENGTH lose nothing; a null doc_id is in no order, so that row
neither loses bytes nor costs others any; rows with one doc_id don't cost each other anything, each is cut for
itself; texts of any length are cut whole; an empty table gives an empty result; extra columns are ignored, whatever
their names.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, mix64, tidy

LENGTH, K = 50, 20
#: Bytes hashed at once, bytes whose runs are gathered before they are sent, bytes of text that go through one tree.
STEP, GATHER, TREE = 1 << 20, 12 << 20, 1 << 21
#: Bytes of input for each bucket of keys and each drawer of documents.
BUCKET, DRAWER = 4 << 20, 16 << 20
#: Documents looked at for frequent keys, and how many of them make a key frequent.
SAMPLE, HOT_DOCS = 4000, 16
#: Suffixes up to this many bytes are sorted as strings, longer ones by doubling.
WIDE = 256
BASE = 0x9E3779B97F4A7C15 | 1
_BYTE = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(BASE))
PACKED = "at int, kind byte, data binary"
RUNS, GONE, ASKED, MEMBERS = 0, 1, 2, 3


_ENTRY = struct.Struct("<cBQ")  # kind and bytes of an array's items, number of items


def pack(*columns: np.ndarray) -> bytes:
    """Arrays as compressed bytes; integers that grow should come as differences."""
    head = b"".join(_ENTRY.pack(c.dtype.kind.encode(), c.dtype.itemsize, len(c)) for c in columns)
    return zstandard.compress(b"".join([bytes([len(columns)]), head, *(np.ascontiguousarray(c).tobytes() for c in columns)]), 1)


def unpack(data: bytes) -> list[np.ndarray]:
    data = zstandard.decompress(data)
    at, out = 1 + data[0] * _ENTRY.size, []
    for k in range(data[0]):
        kind, width, n = _ENTRY.unpack_from(data, 1 + k * _ENTRY.size)
        out.append(np.frombuffer(data, f"<{kind.decode()}{width}", n, at))
        at += n * width
    return out


def _pack_rows(doc: np.ndarray, row: np.ndarray, *more: np.ndarray) -> bytes:
    return pack(np.diff(doc, prepend=0), row, *more)


def _unpack_rows(data: bytes) -> list[np.ndarray]:
    doc, *more = unpack(data)
    return [np.cumsum(doc), *more]


def _rolled(x: np.ndarray, base: int, width: int = K) -> np.ndarray:
    """Hash of the `width` bytes that start at each place."""
    parts, step, h, at, out = width, 1, x, 0, None
    while parts:
        if parts & 1:
            here = h[at:] if out is None else h[at : at + len(out)]
            out = here if out is None else out[: len(here)] * np.uint64(pow(base, step, 1 << 64)) + here
            at += step
        parts >>= 1
        if parts:
            h = h[: len(h) - step] * np.uint64(pow(base, step, 1 << 64)) + h[step:]
            step *= 2
    return mix64(out)


def runs_of(texts: list[bytes], length: int = LENGTH) -> tuple[np.ndarray, ...]:
    """(text number, first place, places, key, hash of the run's bytes) of each run of each text."""
    sizes = np.array([len(t) for t in texts], np.int64)
    data = np.frombuffer(b"".join(texts), np.uint8)
    if len(data) < length:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.uint64, np.uint64))
    with np.errstate(over="ignore"):
        x = _BYTE[data]
        h = _rolled(x, BASE)
        wide, step = length - K + 1, 1
        while 2 * step <= wide:
            h = np.minimum(h[:-step], h[step:])
            step *= 2
        if wide > step:
            h = np.minimum(h[: len(h) - (wide - step)], h[wide - step :])
        ends = np.cumsum(sizes)
        starts = ends - sizes
        long = np.flatnonzero(sizes >= length)
        new = np.empty(len(h), bool)
        new[0] = True
        np.not_equal(h[1:], h[:-1], out=new[1:])
        new[starts[long]] = True
        first = np.flatnonzero(new)
        of = np.searchsorted(ends, first, "right")
        last = np.minimum(np.append(first[1:], len(h)) - 1, ends[of] - length)
        ok = last >= first
        first, last, of = first[ok], last[ok], of[ok]
        power = np.empty(len(data), np.uint64)
        power[0] = 1
        power[1:] = BASE
        np.multiply.accumulate(power, out=power)
        total = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(x * power, out=total[1:])
        inverse = np.full(len(data), pow(BASE, -1, 1 << 64), np.uint64)
        inverse[0] = 1
        np.multiply.accumulate(inverse, out=inverse)
        whole = mix64((total[last + length] - total[first]) * inverse[first] + (last - first).astype(np.uint64))
    return of, first - starts[of], last - first + 1, h[first], whole


def _shared(key: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """The runs whose key more than one document has."""
    if not len(key):
        return np.zeros(0, np.int64)
    order = np.argsort(key, kind="stable")
    new = _news(key[order])
    starts, d = np.flatnonzero(new), doc[order]
    return order[(np.maximum.reduceat(d, starts) > np.minimum.reduceat(d, starts))[np.cumsum(new) - 1]]


def _news(*sorted_columns: np.ndarray) -> np.ndarray:
    """Where a value comes that differs from the one before it."""
    new = np.ones(len(sorted_columns[0]), bool)
    new[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in sorted_columns])
    return new


def _classes(key: np.ndarray, whole: np.ndarray, doc: np.ndarray, row: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order by key and text, number of each run's text, whether another document had it before), all in that order."""
    order = np.lexsort((place, row, doc, whole, key))
    new = _news(key[order], whole[order])
    of, d = np.cumsum(new) - 1, doc[order]
    return order, of, d > d[np.flatnonzero(new)][of]


def _by(number: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(value, places of it, in the order given) for each value."""
    order = np.argsort(number, kind="stable")
    cuts = np.flatnonzero(np.diff(number[order])) + 1
    for at in np.split(order, cuts) if len(order) else []:
        yield int(number[at[0]]), at


def _batch(at: list[int], kind: list[int], data: list[bytes]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(kind, pa.int8()), pa.array(data, pa.binary())], names=["at", "kind", "data"])


def _gone(doc: np.ndarray, row: np.ndarray, place: np.ndarray, size: np.ndarray, drawers: int) -> Iterator[tuple[int, bytes]]:
    """Spans to remove, packed by the drawer of their document."""
    order = np.lexsort((place, row, doc))
    doc, row, place, size = doc[order], row[order], place[order], size[order]
    for d, at in _by(doc % drawers):
        yield d, _pack_rows(doc[at], row[at], place[at].astype(np.uint32), size[at].astype(np.uint32))


def _tree_batches(size: np.ndarray, key: np.ndarray) -> Iterator[slice]:
    """Texts in order of key, taken together up to TREE bytes, never with a key torn apart."""
    last = np.flatnonzero(np.append(key[1:] != key[:-1], True)) if len(key) else np.zeros(0, np.int64)
    upto, first = np.cumsum(size), 0
    while first < len(size):
        fit = np.searchsorted(upto[last], (upto[first - 1] if first else 0) + TREE, "right") - 1
        end = int(last[max(fit, np.searchsorted(last, first))]) + 1
        yield slice(first, end)
        first = end


def _decide(of: np.ndarray, later: np.ndarray, doc: np.ndarray, key: np.ndarray, text: Callable[[int], np.ndarray], size: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """Members of texts by the tree: (member, offset in its text, length) of each span to remove, and for each member
    where its places lie in the last array, which says of each place whether a span holds all LENGTH bytes from it.

    of, later: the text of each member and whether another document had that text before, ordered by text, then document;
    key, size, text: of each text, ordered by key.
    """
    # a text enters the tree for its first document, and once more for its second
    enter = np.flatnonzero(_news(of, later))
    entry = np.cumsum(_news(of, later)) - 1
    e_text, e_doc = of[enter], doc[enter]
    e_size = size[e_text]
    spans = [np.zeros((0, 3), np.int64)]
    for some in _tree_batches(e_size, key[e_text]):
        found = repeated_spans(np.concatenate([text(t) for t in e_text[some].tolist()]), e_size[some], e_doc[some], length)
        found[:, 0] += some.start
        spans.append(found)
    spans = np.concatenate(spans)
    spans = spans[np.argsort(spans[:, 0], kind="stable")]
    room = e_size - length + 2  # a place more than there are, where spans may end
    base = np.cumsum(room) - room
    edge = np.bincount(base[spans[:, 0]] + spans[:, 1], minlength=int(room.sum())) - np.bincount(base[spans[:, 0]] + spans[:, 1] + spans[:, 2] - length + 1, minlength=int(room.sum()))
    covered = np.cumsum(edge) > 0
    times = np.bincount(spans[:, 0], minlength=len(enter))
    start, n = (np.cumsum(times) - times)[entry], times[entry]
    member = np.repeat(np.arange(len(of)), n)
    pick = np.arange(len(member)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(start, n)
    return member, spans[pick, 1], spans[pick, 2], base[entry], covered


def _ranges(start: np.ndarray, n: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of each range, n of them."""
    return np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n - start, n)


def _settle(data: np.ndarray, at: np.ndarray, doc: np.ndarray, row: np.ndarray, place: np.ndarray, n: np.ndarray, key: np.ndarray, whole: np.ndarray, hot: np.ndarray, length: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """(spans to remove, runs that go on) of one stretch: doc, row, place, bytes; doc, row, place, places, key, text's hash."""
    mine = _shared(key, doc)
    goes_on = np.ones(len(doc), bool)
    frequent = np.isin(key, hot) if len(hot) else np.zeros(len(doc), bool)
    gone, single = [np.zeros(0, np.int64)] * 4, []
    if len(mine):
        order, of, later = _classes(key[mine], whole[mine], doc[mine], row[mine], place[mine])
        mine = mine[order]
        first = np.flatnonzero(_news(of))
        where, size = at[mine[first]], n[mine[first]] + length - 1
        text = lambda t: data[where[t] : where[t] + size[t]]
        member, offset, span, base, covered = _decide(of, later, doc[mine], key[mine[first]], text, size, length)
        gone = [doc[mine[member]], row[mine[member]], place[mine[member]] + offset, span]
        places = _ranges(base, n[mine])
        whose = np.repeat(np.arange(len(mine)), n[mine])
        left = ~covered[places]
        goes_on[mine] = np.bincount(whose[left], minlength=len(mine)) > 0
        deal = left & frequent[mine][whose]
        single.append((mine[whose[deal]], (places - base[whose])[deal]))
        alone = frequent.copy()
        alone[mine] = False
    else:
        alone = frequent
    if len(hot):
        whose = np.repeat(np.flatnonzero(alone), n[alone])
        single.append((whose, _ranges(np.zeros(int(alone.sum()), np.int64), n[alone])))
        goes_on &= ~frequent
    on = np.flatnonzero(goes_on)
    runs = [doc[on], row[on], place[on], n[on], key[on], whole[on]]
    if single and sum(len(x) for x, _ in single):
        whose, offset = (np.concatenate(x) for x in zip(*single, strict=True))
        with np.errstate(over="ignore"):
            own = _hash_at(data, at[whose] + offset, length)
        runs = [np.concatenate(x) for x in zip(runs, [doc[whose], row[whose], place[whose] + offset, np.ones(len(whose), np.int64), mix64(own), own], strict=True)]
    return gone, runs


def _hash_at(data: np.ndarray, at: np.ndarray, length: int, some: int = 1 << 16) -> np.ndarray:
    """Hash of the `length` bytes at each of these places."""
    powers = np.array([pow(BASE, length - 1 - i, 1 << 64) for i in range(length)], np.uint64)
    windows = np.lib.stride_tricks.sliding_window_view(data, length)
    return np.concatenate([np.zeros(0, np.uint64)] + [mix64((_BYTE[windows[at[i : i + some]]] * powers).sum(1, dtype=np.uint64)) for i in range(0, len(at), some)])


def _stretches(batches: Iterator[pa.RecordBatch], length: int, gather: int) -> Iterator[tuple[list[bytes], list[int], list[int]]]:
    """(texts, doc_ids, rows) of about `gather` bytes at a time; texts too short to hold a string are left out."""
    texts, docs, rows, size = [], [], [], 0
    for batch in (whole.slice(i, 500) for whole in batches for i in range(0, whole.num_rows, 500)):
        for doc, row, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            data = text.encode("utf-8", "replace")
            if len(data) < length:
                continue
            texts.append(data)
            docs.append(doc)
            rows.append(row)
            size += len(data)
            if size >= gather:
                yield texts, docs, rows
                texts, docs, rows, size = [], [], [], 0
    if texts:
        yield texts, docs, rows


def _runs_of_stretch(texts: list[bytes], length: int) -> tuple[np.ndarray, ...]:
    """Like runs_of, STEP bytes at a time."""
    parts, first, size = [], 0, 0
    for i, t in enumerate(texts):
        size += len(t)
        if size >= STEP or i == len(texts) - 1:
            of, *more = runs_of(texts[first : i + 1], length)
            parts.append((of + first, *more))
            first, size = i + 1, 0
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _find_runs(batches: Iterator[pa.RecordBatch], buckets: int, drawers: int, hot: np.ndarray, length: int, gather: int) -> Iterator[pa.RecordBatch]:
    for texts, docs, rows in _stretches(batches, length, gather):
        of, place, n, key, whole = _runs_of_stretch(texts, length)
        sizes = np.array([len(t) for t in texts], np.int64)
        at = (np.cumsum(sizes) - sizes)[of] + place
        doc, row = np.array(docs, np.int64)[of], np.array(rows, np.int64)[of]
        gone, (doc, row, place, n, key, whole) = _settle(np.frombuffer(b"".join(texts), np.uint8), at, doc, row, place, n, key, whole, hot, length)
        to, kind, data = [], [], []
        if len(gone[0]):
            order = np.lexsort((gone[2], gone[1], gone[0]))
            to.append(int(docs[0] % buckets))
            kind.append(GONE)
            data.append(_pack_rows(gone[0][order], gone[1][order], gone[2][order].astype(np.uint32), gone[3][order].astype(np.uint32)))
        order = np.lexsort((place, row, doc))
        high = (key >> np.uint64(32)).astype(np.uint32)
        for b, mine in _by((high[order] % np.uint32(buckets)).astype(np.int64)):
            i = order[mine]
            to.append(b)
            kind.append(RUNS)
            data.append(_pack_rows(doc[i], row[i], place[i].astype(np.uint32), n[i].astype(np.uint32), high[i], whole[i]))
        yield _batch(to, kind, data)


def _compare_runs(table: pa.Table, drawers: int, length: int) -> pa.Table:
    """Of one bucket: the runs whose key several documents have (one row), and the texts to fetch, one of each that differs."""
    kinds, data = table.column("kind").to_pylist(), table.column("data").to_pylist()
    out: list[tuple[int, int, bytes]] = []
    gone = [_unpack_rows(x) for k, x in zip(kinds, data, strict=True) if k == GONE]
    runs = [_unpack_rows(x) for k, x in zip(kinds, data, strict=True) if k == RUNS]
    del data
    if runs:
        doc, row, place, n, key, whole = (np.concatenate(x) for x in zip(*runs, strict=True))
        mine = _shared(key, doc)
        if len(mine):
            order, of, later = _classes(key[mine], whole[mine], doc[mine], row[mine], place[mine])
            mine = mine[order]
            first = mine[np.flatnonzero(_news(of))]
            out.append((int(table.column("at")[0].as_py()), MEMBERS, pack(np.diff(of, prepend=0).astype(np.uint8), later, doc[mine], row[mine], place[mine], key[first], n[first])))
            ask = np.lexsort((place[first], row[first], doc[first]))
            for dr, i in _by(doc[first][ask] % drawers):
                i = ask[i]
                out.append((dr, ASKED, _pack_rows(doc[first[i]], row[first[i]], place[first[i]], n[first[i]], key[first[i]], i.astype(np.uint32))))
    if gone:
        out += [(dr, GONE, x) for dr, x in _gone(*(np.concatenate(x).astype(np.int64) for x in zip(*gone, strict=True)), drawers)]
    return pa.table(_columns(out))


def _columns(out: list[tuple[int, int, bytes]]) -> dict[str, pa.Array]:
    return {"at": pa.array([x[0] for x in out], pa.int32()), "kind": pa.array([x[1] for x in out], pa.int8()), "data": pa.array([x[2] for x in out], pa.binary())}


def _fetch(docs: pa.Table, asked: pa.Table, buckets: int, length: int) -> pa.Table:
    """Texts asked for, by bucket of their key."""
    out: list[tuple[int, int, bytes]] = []
    asks = [_unpack_rows(x) for x in asked.column("data").to_pylist()]
    if asks:
        doc, row, place, n, key, number = (np.concatenate(x) for x in zip(*asks, strict=True))
        text = {(d, r): t.encode("utf-8", "replace") for d, r, t in zip(*(docs.column(c).to_pylist() for c in ("doc_id", "row", "text")), strict=True)}
        for b, i in _by((key % np.uint32(buckets)).astype(np.int64)):
            parts = [text[d, r][p : p + m + length - 1] for d, r, p, m in zip(doc[i].tolist(), row[i].tolist(), place[i].tolist(), n[i].tolist(), strict=True)]
            out.append((b, RUNS, pack(number[i], np.frombuffer(b"".join(parts), np.uint8), n[i])))
    return pa.table(_columns(out))


def suffix_array(codes: np.ndarray, longest: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffix array, common prefix of each suffix and the one before it), by doubling; prefixes count up to `longest` codes."""
    ranks, step = [np.unique(codes, return_inverse=True)[1].astype(np.int32)], 1
    while True:
        r, n = ranks[-1], len(codes)
        if step > longest or r.max(initial=0) == n - 1:
            break
        pair = r.astype(np.int64) * (n + 1)
        pair[: n - step] += r[step:] + 1
        ranks.append(np.unique(pair, return_inverse=True)[1].astype(np.int32))
        step *= 2
    order = np.argsort(ranks[-1], kind="stable")
    a, b, common = order[:-1].copy(), order[1:].copy(), np.zeros(max(len(order) - 1, 0), np.int64)
    for level in range(len(ranks) - 1, -1, -1):
        r = np.append(ranks[level], -1)
        same = r[np.minimum(a, len(codes))] == r[np.minimum(b, len(codes))]
        same &= (a < len(codes)) & (b < len(codes))
        common[same] += 1 << level
        a[same] += 1 << level
        b[same] += 1 << level
    return order, np.concatenate([[0], common])[: len(order)]


def maximal_repeats(common: list[int], before: list[int], doc: list[int], least: int) -> Iterator[tuple[int, int, int, int]]:
    """(length, first suffix, last suffix, least document) of each maximal repeat of at least `least`, by one stack scan.

    common[i]: common prefix of suffixes i-1 and i; before[i]: code of what stands before suffix i, where equal codes mean
    that the repeat goes on to the left.
    """
    stack: list[list[int]] = []  # length, first suffix, least document, code before it or -1 if codes differ
    for i in range(1, len(common) + 1):
        here = common[i] if i < len(common) else 0
        start, low, code = i - 1, doc[i - 1], before[i - 1]
        while stack and stack[-1][0] > here:
            length, first, least_doc, one = stack.pop()
            low, code, start = min(least_doc, low), one if one == code else -1, first
            if code == -1:
                yield length, first, i - 1, low
        if stack and stack[-1][0] == here:
            top = stack[-1]
            top[2], top[3] = min(top[2], low), top[3] if top[3] == code else -1
        elif here >= least:
            stack.append([here, start, low, code])


def longest_with_earlier(repeats: list[tuple[int, int, int, int]], doc: np.ndarray) -> np.ndarray:
    """For each suffix the length of the longest of the repeats that holds it and a suffix of a smaller document; 0 if none.

    Repeats nest and come inner ones first. Each suffix is given to its innermost repeat, and each repeat a link to the
    nearest one around it with a smaller least document: work stays in proportion even where a text repeats itself.
    """
    around, inner, open_ = [-1] * len(repeats), np.full(len(doc), -1), []
    for k, (_, i, j, _) in enumerate(repeats):
        kids = []
        while open_ and open_[-1][0] >= i:
            kids.append(open_.pop())
        at = i
        for start, end, kid in reversed(kids):
            around[kid] = k
            inner[at:start] = k
            at = end + 1
        inner[at : j + 1] = k
        open_.append((i, j, k))
    length, _, _, low = (np.array(x) for x in zip(*repeats, strict=True))
    earlier = [-1] * len(repeats)
    for k in range(len(repeats) - 1, -1, -1):
        p = around[k]
        earlier[k] = -1 if p < 0 else p if low[p] < low[k] else earlier[p]
    pick = np.where(inner < 0, -1, np.where(low[inner] < doc, inner, np.array(earlier)[inner]))
    return np.where(pick < 0, 0, length[pick])


def _order_short(data: np.ndarray, place: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, common prefix with the one before) of the suffixes at these places, with so many bytes left to them."""
    wide = int(left.max())
    rows = np.lib.stride_tricks.sliding_window_view(np.append(data, np.zeros(wide, np.uint8)), wide)[place]
    rows[np.arange(wide) >= left[:, None]] = 0
    order = np.lexsort((left, rows.view(f"S{wide}").ravel()))
    rows, left = rows[order], left[order]
    differ = rows[1:] != rows[:-1]
    same = np.where(differ.any(1), differ.argmax(1), wide)
    return order, np.append(0, np.minimum(same, np.minimum(left[1:], left[:-1])))


def _order_long(data: np.ndarray, starts: np.ndarray, size: np.ndarray, of: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same by the suffix array of the texts that hold these places."""
    texts, mine = np.unique(of, return_inverse=True)
    # each text gets a mark of its own after it, which ends all common prefixes
    codes = np.concatenate([x for k, t in enumerate(texts.tolist()) for x in (data[starts[t] : starts[t] + size[t]].astype(np.int32), np.array([256 + k], np.int32))])
    begin = np.cumsum(size[texts] + 1) - size[texts] - 1
    number = np.full(len(codes), -1)
    number[begin[mine] + at] = np.arange(len(at))
    order, common = suffix_array(codes, int(size[texts].max()))
    found = np.flatnonzero(number[order] >= 0)
    # the common prefix of two of these is the least of all between them
    common = np.minimum.reduceat(common[: found[-1] + 1], np.append(0, found[:-1] + 1))
    common[0] = 0
    return number[order[found]], common


def repeated_spans(data: np.ndarray, size: np.ndarray, doc: np.ndarray, length: int = LENGTH) -> np.ndarray:
    """text, place, bytes of each occurrence of a maximal repeat that an earlier document has, too.

    data holds the texts one after the other, each of `length` bytes at least. Only places whose next `length` bytes
    stand in several documents, and not always after the same byte, can start one; only those are sorted. What stands
    before a text's first byte is unlike anything else.
    """
    none = np.zeros((0, 3), np.int64)
    if not len(size):
        return none
    starts, windows = np.cumsum(size) - size, size - length + 1
    of = np.repeat(np.arange(len(size)), windows)
    place = _ranges(starts, windows)
    with np.errstate(over="ignore"):
        h = _rolled(_BYTE[data], BASE, length)[place]
    order = np.argsort(h, kind="stable")
    new = _news(h[order])
    first = np.flatnonzero(new)
    often = np.diff(np.append(first, len(order))) > 1
    order = order[often[np.cumsum(new) - 1]]
    if not len(order):
        return none
    new = _news(h[order])
    first, d = np.flatnonzero(new), doc[of[order]]
    before = np.where(place[order] > starts[of[order]], data[place[order] - 1].astype(np.int64), 256 + of[order])
    can = (np.maximum.reduceat(d, first) > np.minimum.reduceat(d, first)) & (np.maximum.reduceat(before, first) > np.minimum.reduceat(before, first))
    group = np.cumsum(new) - 1
    left = (starts + size)[of[order]] - place[order]
    long = np.maximum.reduceat(left, first) > WIDE
    found = []
    for which in (can & ~long, can & long):
        pick = which[group]
        mine, one = order[pick], group[pick]
        if not len(mine):
            continue
        n, code, whose = left[pick], before[pick], d[pick]
        if long[one[0]]:
            turns = [(slice(0, len(mine)), *_order_long(data, starts, size, of[mine], place[mine] - starts[of[mine]]))]
        else:
            cuts = [0, *(np.flatnonzero(np.diff(one // max(1, int(one[-1]) * len(mine) // (1 << 18)))) + 1).tolist()] if len(mine) > 1 << 18 else [0]
            turns = [(slice(x, y), *_order_short(data, place[mine[x:y]], n[x:y])) for x, y in zip(cuts, [*cuts[1:], len(mine)], strict=True)]
        for some, ranked, common in turns:
            m, w = mine[some][ranked], whose[some][ranked]
            repeats = list(maximal_repeats(common.tolist(), code[some][ranked].tolist(), w.tolist(), length))
            if repeats:
                bytes_ = longest_with_earlier(repeats, w)
                late = np.flatnonzero(bytes_)
                found.append(np.stack([of[m[late]], place[m[late]] - starts[of[m[late]]], bytes_[late]], 1))
    return np.concatenate([none, *found])


def _repeats(members: pa.Table, texts: pa.Table, drawers: int, length: int) -> pa.Table:
    """Spans to remove from the runs of one bucket, by the tree over its texts."""
    out: list[tuple[int, int, bytes]] = []
    for packed in members.column("data").to_pylist():  # one row
        step, later, doc, row, place, key, n = unpack(packed)
        number, data, places = (np.concatenate(x) for x in zip(*(unpack(x) for x in texts.column("data").to_pylist()), strict=True))
        size = places.astype(np.int64) + length - 1
        where = np.empty(len(key), np.int64)
        where[number] = np.cumsum(size) - size
        size = n.astype(np.int64) + length - 1
        text = lambda t, where=where, size=size, data=data: data[where[t] : where[t] + size[t]]
        member, offset, span, *_ = _decide(np.cumsum(step, dtype=np.int64), later, doc, key, text, size, length)
        out += [(dr, GONE, x) for dr, x in _gone(doc[member], row[member], place[member] + offset, span, drawers)]
    return pa.table(_columns(out))


def merged(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of the union of spans; spans that touch are one."""
    order = np.argsort(start, kind="stable")
    start, upto = start[order], np.maximum.accumulate(end[order])
    new = np.ones(len(start), bool)
    new[1:] = start[1:] > upto[:-1]
    first = np.flatnonzero(new)
    return start[first], upto[np.append(first[1:], len(start)) - 1]


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def _finish(docs: pa.Table, gone: pa.Table) -> pa.Table:
    spans = [_unpack_rows(x) for x in gone.column("data").to_pylist()]
    cols = [np.concatenate(x).astype(np.int64) for x in zip(*spans, strict=True)] if spans else [np.zeros(0, np.int64)] * 4
    order = np.lexsort((cols[1], cols[0]))
    doc, row, start, size = (c[order] for c in cols)
    new = np.flatnonzero(np.append(True, (doc[1:] != doc[:-1]) | (row[1:] != row[:-1]))) if len(doc) else np.zeros(0, np.int64)
    where = {(d, r): (a, b) for d, r, a, b in zip(doc[new].tolist(), row[new].tolist(), new.tolist(), np.append(new[1:], len(doc))[: len(new)].tolist(), strict=True)}
    out = []
    for d, r, text in zip(*(docs.column(c).to_pylist() for c in ("doc_id", "row", "text")), strict=True):
        data = (text or "").encode("utf-8", "replace")
        a, b = where.get((d, r), (0, 0))
        first, last = merged(start[a:b], start[a:b] + size[a:b]) if b > a else (start[:0], start[:0])
        digest, upto = hashlib.sha256(), 0
        for x, y in zip(first.tolist(), last.tolist(), strict=True):
            digest.update(data[upto:x])
            upto = y
        digest.update(data[upto:])
        out.append((d, len(data), int((last - first).sum()), len(first), digest.hexdigest()))
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
    return pa.table({c: pa.array([x[i] for x in out], pa.string() if i == 4 else pa.int64()) for i, c in enumerate(names)})


def _with_row(docs: DataFrame) -> DataFrame:
    """doc_id, row, text: row tells rows of one doc_id apart (0 where there is one)."""
    slim = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    again = slim.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 AND doc_id IS NOT NULL").select(F.col("doc_id").alias("twice"))
    if again.limit(1).count() == 0:
        return slim.withColumn("row", F.lit(0).cast("long")).select("doc_id", "row", "text")
    again = cut(again, "twice")
    return slim.join(again, F.col("doc_id") == F.col("twice"), "left").select("doc_id", F.when(F.col("twice").isNotNull(), F.xxhash64("text")).otherwise(0).alias("row"), "text")


def _hot_keys(rows: DataFrame, n_docs: int, length: int) -> np.ndarray:
    """Keys of HOT_DOCS or more of about SAMPLE documents."""

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for texts, docs, _ in _stretches(batches, length, STEP):
            of, _, _, key, _ = runs_of(texts, length)
            doc = np.array(docs, np.int64)[of]
            order = np.lexsort((doc, key))
            yield pa.RecordBatch.from_arrays([pa.array(key[order][_news(key[order], doc[order])].view(np.int64))], names=["key"])

    some = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(max(1, n_docs // SAMPLE))) == 0)
    often = some.mapInArrow(tidy(keys), "key long").groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") >= HOT_DOCS)
    return np.sort(np.array([r["key"] for r in often.select("key").collect()], np.int64).view(np.uint64))


def _prime(n: int) -> int:
    """The least prime from n on, so that doc_ids that come in steps still spread."""
    return next(p for p in range(max(2, n), 2 * max(2, n) + 1) if all(p % d for d in range(2, int(p**0.5) + 1)))


def remove_repeats(docs: DataFrame, length: int = LENGTH, buckets: int | None = None, gather: int = GATHER) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of each row of docs.

    buckets: buckets of keys, by default as many as the input's bytes ask for. gather: bytes of a stretch.
    """
    rows = _with_row(docs)
    told = rows.agg(F.count("*").alias("docs"), F.sum(F.octet_length("text")).alias("bytes")).first()
    buckets = _prime(buckets or (told["bytes"] or 0) // BUCKET)
    drawers = _prime((told["bytes"] or 0) // DRAWER)
    rows = rows.withColumn("at", F.coalesce(F.pmod("doc_id", F.lit(drawers)), F.lit(0)).cast("int"))
    known = rows.where("doc_id IS NOT NULL").select("doc_id", "row", "text")
    hot = _hot_keys(known, told["docs"], length)
    runs = known.mapInArrow(tidy(lambda b: _find_runs(b, buckets, drawers, hot, length, gather)), PACKED)
    found = cut(runs.groupBy("at").applyInArrow(lambda t: _compare_runs(t, drawers, length), PACKED), "runs")
    kind = lambda k: found.where(F.col("kind") == k).groupBy("at")
    texts = rows.groupBy("at").cogroup(kind(ASKED)).applyInArrow(lambda d, a: _fetch(d, a, buckets, length), PACKED)
    compared = kind(MEMBERS).cogroup(texts.groupBy("at")).applyInArrow(lambda m, t: _repeats(m, t, drawers, length), PACKED)
    gone = found.where(F.col("kind") == GONE).unionByName(compared)
    return rows.groupBy("at").cogroup(gone.groupBy("at")).applyInArrow(_finish, RESULT)
