"""Operator 7: removing repeated passages with an enhanced suffix array.

Every byte covered by a ``SPAN`` = 50-byte string that also starts in a document with a smaller doc_id is removed.  The
suffixes of 100 TB are not sorted together; they are dealt so that equal strings always meet:

1. *Anchors.*  Of the 35 16-grams in a 50-byte string the one with the smallest hash is its anchor, so equal strings
   have equal anchors at equal places.  About one position in twenty is an anchor.
2. *Shared anchors.*  Documents stand in groups by hashed id.  A group sends the distinct hashes of its anchors
   (delta-coded, a few bytes each) to hash-range buckets; a bucket answers with those that several documents have.
3. *Suffix arrays.*  Around each shared anchor a group sends the 34 bytes before it and the 50 bytes from it on, once for
   all its documents with the same bytes (the smallest id stands for them).  A bucket sorts the right contexts
   (a suffix array over anchors) and the reversed left contexts, with the common-prefix lengths of neighbours.  A scan
   with a stack gives the intervals of the common-prefix tree of the right contexts; the entries of each are split by a
   scan over their left extensions, down to where these differ.  What is left are the maximal repeat groups with all
   their occurrences, and all but those with the smallest id are marked.
4. *Cutting.*  The marked byte ranges return to their group, which removes them.

A hot anchor (a line that a third of all documents hold) is found in step 2 from its counts; its contexts are sent as
single 50-byte strings, dealt by their own hash, so that no bucket receives all of its occurrences.  Each group of
copies is reduced before anything is sent.  Comparisons are on bytes; hashes only deal work out.

Defined results: null text is empty; texts under 50 bytes stay whole; rows that repeat a doc_id don't remove each other;
a null doc_id counts as larger than any id; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.sources.tables import read_table

SPAN, GRAM = 50, 16
WIDTH = SPAN - GRAM + 1
LEFT = SPAN - GRAM
#: Bytes of text in a group (a worker needs about 40 times that; raise it with the executors, to 256 MB for 100 TB, as the
#: number of messages is groups times buckets), fewest groups, and occurrences that make an anchor hot.
GROUP_BYTES, LEAST_GROUPS, HOT = 4 << 20, 24, 20_000
#: Entries of common-prefix intervals that are split by their left extensions at once.
LOT = 1 << 18
NO_ID = np.iinfo(np.int64).max
MESSAGE = "dest int, kind int, sender int, blob binary"
REPEATS = "repeat string, doc_id long, start long, stop long"
CLEANED = "doc_id long, n_bytes long, kept binary, spans array<struct<start: long, stop: long>>"


# ---- coding -----------------------------------------------------------------------------------------------


def _planes(values: np.ndarray) -> bytes:
    """Integers, byte plane by byte plane, which compresses small and sorted values well."""
    raw = np.ascontiguousarray(values).view(np.uint8).reshape(len(values), values.itemsize)
    return raw.T.tobytes()


def _unplanes(data: bytes, dtype: str) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(size, -1).T).view(dtype).ravel()


def _zip(*parts: bytes) -> bytes:
    head = np.array([len(parts), *map(len, parts)], dtype="<u4").tobytes()
    return zstandard.compress(head + b"".join(parts), 1)


def _unzip(blob: bytes) -> list[bytes]:
    data = zstandard.decompress(blob)
    n = int.from_bytes(data[:4], "little")
    sizes, at, out = np.frombuffer(data, "<u4", n, 4).tolist(), 4 + 4 * n, []
    for s in sizes:
        out.append(data[at : at + s])
        at += s
    return out


# ---- anchors ----------------------------------------------------------------------------------------------


def _slide(x: np.ndarray, width: int, best) -> np.ndarray:
    """``best`` over every ``width`` neighbours."""
    size = 1
    while 2 * size <= width:
        x = best(x[:-size], x[size:])
        size *= 2
    return best(x[: len(x) - (width - size)], x[width - size :]) if size < width else x


def _grams(bytes_: np.ndarray) -> np.ndarray:
    """Hashes of the grams along the last axis."""
    x, size = bytes_.astype(np.uint64), 1
    with np.errstate(over="ignore"):
        while size < GRAM:
            x = (x[..., :-size] * np.uint64(0x9E3779B97F4A7C15) + x[..., size:] + np.uint64(1)) * np.uint64(0xBF58476D1CE4E5B9)
            x ^= x >> np.uint64(31)
            size *= 2
    return x


def anchors(buf: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places and 48-bit hashes (never 0) of the anchors of the documents in ``buf``, which end at ``ends``."""
    n = len(buf)
    if n < SPAN:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    x = _grams(buf)
    low = _slide(x, WIDTH, np.minimum)
    # a string that would cross the end of its document is none
    starts = np.append(0, ends[:-1])
    valid = np.zeros(n + 1, np.int32)
    np.add.at(valid, starts, 1)
    np.add.at(valid, np.maximum(ends - SPAN + 1, starts), -1)
    low[np.cumsum(valid)[: len(low)] <= 0] = 0
    # the largest minimum among the strings around a place: its own hash if and only if it is an anchor
    around = _slide(np.concatenate([np.zeros(WIDTH - 1, np.uint64), low, np.zeros(WIDTH - 1, np.uint64)]), WIDTH, np.maximum)
    at = np.flatnonzero((around == x) & (x > 0))
    return at, x[at] >> np.uint64(16) | np.uint64(1)


class Group:
    """The documents of one group in a fixed order, whatever order they were fetched in."""

    def __init__(self, table: pa.Table) -> None:
        ids = table.column("doc_id").to_pylist()
        texts = [(t or "").encode() for t in table.column("text").to_pylist()]
        order = sorted(range(len(ids)), key=lambda i: (NO_ID if ids[i] is None else ids[i], texts[i]))
        self.ids = [ids[i] for i in order]
        self.texts = [texts[i] for i in order]
        self.key = np.array([NO_ID if i is None else i for i in self.ids], dtype=np.int64)
        self.ends = np.cumsum([len(t) for t in self.texts], dtype=np.int64)
        self.starts = np.append(0, self.ends[:-1])
        self.buf = np.frombuffer(b"".join(self.texts), np.uint8)

    def anchors(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places, hashes and document numbers; documents are taken in runs of a few MB, for the cache's sake."""
        places, hashes, lo = [], [], 0
        while lo < len(self.ends):
            hi = max(lo + 1, int(np.searchsorted(self.ends, self.starts[lo] + (1 << 20))))
            a, b = int(self.starts[lo]), int(self.ends[hi - 1])
            at, h = anchors(self.buf[a:b], self.ends[lo:hi] - a)
            places.append(at + a)
            hashes.append(h)
            lo = hi
        at = np.concatenate(places) if places else np.empty(0, np.int64)
        return at, (np.concatenate(hashes) if hashes else np.empty(0, np.uint64)), np.searchsorted(self.ends, at, side="right")


def _bucket(hashes: np.ndarray, buckets: int) -> np.ndarray:
    # anchors are minima, so their hashes crowd at the low end: mix before dealing
    with np.errstate(over="ignore"):
        mixed = hashes * np.uint64(0x9E3779B97F4A7C15)
    mixed ^= mixed >> np.uint64(29)
    with np.errstate(over="ignore"):
        mixed *= np.uint64(0xBF58476D1CE4E5B9)
    return ((mixed >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def _messages(rows: list[tuple]) -> pa.Table:
    cols = list(zip(*rows, strict=True)) if rows else [[], [], [], []]
    return pa.table({"dest": pa.array(cols[0], pa.int32()), "kind": pa.array(cols[1], pa.int32()), "sender": pa.array(cols[2], pa.int32()), "blob": pa.array(cols[3], pa.binary())})


# ---- the four steps ---------------------------------------------------------------------------------------


def _offer(group: Group, sender: int, buckets: int) -> pa.Table:
    """Step 1: distinct anchor hashes with the number of documents (1 or 2) and of occurrences."""
    _, h, doc = group.anchors()
    order = np.lexsort((doc, h))
    h, doc = h[order], doc[order]
    first = np.flatnonzero(np.append(True, h[1:] != h[:-1])) if len(h) else np.empty(0, np.int64)
    last = np.append(first[1:], len(h)) - 1 if len(h) else first
    distinct, several = h[first], (group.key[doc[first]] != group.key[doc[last]]).astype(np.uint8)
    count = np.minimum(last - first + 1, 65535).astype(np.uint16)
    rows, dest = [], _bucket(distinct, buckets)
    order = np.lexsort((distinct, dest))
    dest, distinct, several, count = dest[order], distinct[order], several[order], count[order]
    for b, part in _runs(dest):
        rows.append((b, 0, sender, _zip(_planes(np.diff(distinct[part], prepend=np.uint64(0))), several[part].tobytes(), _planes(count[part]))))
    return _messages(rows)


def _runs(sorted_: np.ndarray) -> Iterator[tuple[int, slice]]:
    """Value and place of each run of equal values."""
    if len(sorted_):
        edges = np.flatnonzero(np.append(True, sorted_[1:] != sorted_[:-1]))
        for a, b in zip(edges.tolist(), np.append(edges[1:], len(sorted_)).tolist(), strict=True):
            yield int(sorted_[a]), slice(a, b)


def _answer(table: pa.Table, hot: int) -> pa.Table:
    """Step 2: to each sender those of its hashes that several documents have, and which are hot."""
    parts = [(s, _unzip(b)) for s, b in zip(table.column("sender").to_pylist(), table.column("blob").to_pylist(), strict=True)]
    sent = [(s, np.cumsum(_unplanes(p[0], "<u8"), dtype=np.uint64), np.frombuffer(p[1], np.uint8), _unplanes(p[2], "<u2")) for s, p in parts]
    h = np.concatenate([x[1] for x in sent])
    order = np.argsort(h, kind="stable")
    h = h[order]
    several, count = np.concatenate([x[2] for x in sent])[order], np.concatenate([x[3] for x in sent])[order].astype(np.int64)
    first = np.flatnonzero(np.append(True, h[1:] != h[:-1]))
    size = np.diff(np.append(first, len(h)))
    shared = (size > 1) | (np.maximum.reduceat(several, first) > 0)
    known, is_hot = h[first][shared], (np.add.reduceat(count, first) > hot)[shared]
    rows = []
    for s, own, _, _ in sent:
        at = np.searchsorted(known, own)
        hit = at < len(known)
        hit[hit] = known[at[hit]] == own[hit]
        if hit.any():
            rows.append((s, 1, -1, _zip(_planes(np.diff(own[hit], prepend=np.uint64(0))), is_hot[at[hit]].astype(np.uint8).tobytes())))
    return _messages(rows)


def _contexts(group: Group, replies: pa.Table, sender: int, buckets: int, copies: bool = False) -> pa.Table:
    """Step 3a: contexts of shared anchors, one for all documents of the group that have the same bytes; with ``copies``, also which places it stands for."""
    if not replies.num_rows:
        return _messages([])
    got = [_unzip(b) for b in replies.column("blob").to_pylist()]
    known = np.concatenate([np.cumsum(_unplanes(g[0], "<u8"), dtype=np.uint64) for g in got])
    hot = np.concatenate([np.frombuffer(g[1], np.uint8) for g in got])
    order = np.argsort(known)
    known, hot = known[order], hot[order]
    at, h, doc = group.anchors()
    where = np.minimum(np.searchsorted(known, h), len(known) - 1)
    mine = known[where] == h
    at, h, doc, hot = at[mine], h[mine], doc[mine], hot[where[mine]]
    left = np.minimum(at - group.starts[doc], LEFT)
    right = np.minimum(group.ends[doc] - at, SPAN)
    # single strings around hot anchors: a context without left side, at the string's own start
    strings = []
    for i in np.flatnonzero(hot).tolist():
        a = np.arange(at[i] - left[i], min(at[i], group.ends[doc[i]] - SPAN) + 1)
        strings.append(np.column_stack([a, np.full(len(a), doc[i])]))
    if strings:
        extra = np.unique(np.concatenate(strings), axis=0)
        # only those whose own anchor is hot: the others are found under theirs
        views, busy = np.lib.stride_tricks.sliding_window_view(group.buf, SPAN), np.unique(h[hot == 1])
        own = [np.isin(_grams(views[extra[i : i + LOT // 8, 0]]).min(axis=1) >> np.uint64(16) | np.uint64(1), busy) for i in range(0, len(extra), LOT // 8)]
        extra = extra[np.concatenate(own)]
        keep = hot == 0
        at, h, doc = np.append(at[keep], extra[:, 0]), np.append(h[keep], np.zeros(len(extra), np.uint64)), np.append(doc[keep], extra[:, 1])
        left, right = np.append(left[keep], np.zeros(len(extra), np.int64)), np.append(right[keep], np.full(len(extra), SPAN))
    hot = h == 0
    padded = np.concatenate([np.zeros(LEFT, np.uint8), group.buf, np.zeros(SPAN, np.uint8)])
    bytes_ = np.lib.stride_tricks.sliding_window_view(padded, LEFT + SPAN)[at].copy()
    reach = np.arange(LEFT + SPAN)[None, :]
    bytes_[(reach < LEFT - left[:, None]) | (reach >= LEFT + right[:, None])] = 0
    data, size = bytes_.tobytes(), LEFT + SPAN
    side = (left * 64 + right).tolist()
    order = np.argsort(doc, kind="stable").tolist()  # documents ascend by id: the first of equal contexts has the smallest
    seen: dict[tuple[bytes, int], int] = {}
    send, own, of = [], [], []
    key, docs = group.key, doc.tolist()
    for i in order:
        k = (data[size * i : size * i + size], side[i])
        j = seen.setdefault(k, i)
        if key[docs[j]] == key[docs[i]]:
            send.append(i)
        else:
            own.append(i)
            of.append(j)
    rows = []
    if own:  # an earlier document of this group has all of it
        o = np.array(own)
        rows.append((sender % buckets, 3, sender, _ranges(doc[o], at[o] - left[o] - group.starts[doc[o]], at[o] + right[o] - group.starts[doc[o]])))
        if copies:
            places = [_planes(x) for i in (np.array(of), o) for x in (doc[i].astype(np.uint32), (at[i] - group.starts[doc[i]]).astype(np.uint32))]
            rows.append((sender % buckets, 4, sender, _zip(*places)))
    several = np.zeros(len(at), np.uint8)
    several[of] = 1
    several[hot] |= 2
    s = np.array(send, dtype=np.int64)
    if len(s):
        # a hot string is dealt by a hash of its bytes
        deal = h[s].copy()
        if (loose := np.flatnonzero(hot[s])).size:
            deal[loose] = [int.from_bytes(hashlib.blake2b(data[size * i + LEFT : size * i + size], digest_size=8).digest(), "little") for i in s[loose].tolist()]
        dest = _bucket(deal, buckets)
        order = np.lexsort((deal, dest))
        s, dest = s[order], dest[order]
        for b, part in _runs(dest):
            i = s[part]
            rows.append((b, 2, sender, _zip(bytes_[i].tobytes(), _planes(group.key[doc[i]]), _planes(doc[i].astype(np.uint32)), _planes((at[i] - group.starts[doc[i]]).astype(np.uint32)), left[i].astype(np.uint8).tobytes(), right[i].astype(np.uint8).tobytes(), *[several[i].tobytes()] * copies)))
    return _messages(rows)


def _ranges(doc: np.ndarray, start: np.ndarray, end: np.ndarray) -> bytes:
    """Byte ranges by document, with overlaps merged."""
    order = np.lexsort((start, doc))
    doc, start, end = doc[order].astype(np.int64), start[order].astype(np.int64), end[order].astype(np.int64)
    far = doc << 33  # documents apart from each other on one line
    reach = np.maximum.accumulate(far + end)
    first = np.append(True, far[1:] + start[1:] > reach[:-1])
    last = np.append(np.flatnonzero(first)[1:], len(doc)) - 1
    return _zip(_planes(doc[first].astype(np.uint32)), _planes(start[first].astype(np.uint32)), _planes((reach[last] - far[last]).astype(np.uint32)))


def _prefix_ranks(rows: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted order of byte rows, of which the first ``size`` bytes count, and the common-prefix length of each with the one before (0 for the first)."""
    words = -(-rows.shape[1] // 8)
    wide = np.zeros((len(rows), 8 * words), np.uint8)
    wide[:, : rows.shape[1]] = rows
    order = np.lexsort((size, *wide.view(">u8").astype(np.uint64).T[::-1]))
    differs = rows[order[1:]] != rows[order[:-1]]
    lcp = np.where(differs.any(axis=1), differs.argmax(axis=1), rows.shape[1])
    return order, np.append(0, np.minimum(lcp, np.minimum(size[order[1:]], size[order[:-1]]))).astype(np.int8)


def lcp_intervals(lcp: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Depth, begin and end of every interval of the common-prefix tree that is ``least`` deep or more, by one scan with a stack."""
    found, stack = [], []
    for i, depth in enumerate(np.append(np.where(lcp[1:] < least, -1, lcp[1:]), -1).tolist()):
        begin = i
        while stack and stack[-1][0] > depth:
            d, begin = stack.pop()
            found.append((d, begin, i + 1))
        if depth >= 0 and (not stack or stack[-1][0] < depth):
            stack.append((depth, begin))
    return tuple(np.array(found, dtype=np.int64).reshape(-1, 3).T)


class _RangeMin:
    """Least value between two places, from the least values of all runs of a power of two."""

    def __init__(self, values: np.ndarray) -> None:
        self.runs, size = [values], 1
        while 2 * size <= len(values):
            self.runs.append(np.minimum(self.runs[-1][:-size], self.runs[-1][size:]))
            size *= 2

    def __call__(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        out = np.empty(len(begin), self.runs[0].dtype)
        level = np.frexp(end - begin)[1] - 1
        for k in np.unique(level).tolist():
            at = np.flatnonzero(level == k)
            out[at] = np.minimum(self.runs[k][begin[at]], self.runs[k][end[at] - (1 << k)])
        return out


def _within(size: np.ndarray) -> np.ndarray:
    """0, 1, 2 and so on for each run of ``size``, run after run."""
    return np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)


def maximal_repeats(context: np.ndarray, left: np.ndarray, right: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Groups of entries with one repeat of ``SPAN`` bytes or more around their anchors: entries, sizes of groups, bytes before and from the anchor.

    Entry i has ``left`` bytes before its anchor and ``right`` from it on.  A group holds all entries with its bytes, and
    can be made longer on neither side without losing one of them, as far as the contexts reach.  To the right these are
    the intervals of the common-prefix tree; the entries of an interval are split by a second scan over their left
    extensions, whose intervals end where the bytes before differ; what still has one right extension is left to the
    deeper interval.  Groups come in lots of intervals with some ``LOT`` entries.
    """
    right_order, right_lcp = _prefix_ranks(context[:, LEFT:], right)
    left_order, left_lcp = _prefix_ranks(context[:, :LEFT][:, ::-1], left)
    right_rank, left_rank = np.argsort(right_order), np.argsort(left_order)
    right_least, left_least = _RangeMin(right_lcp), _RangeMin(left_lcp)
    depth, begin, end = lcp_intervals(right_lcp, SPAN - LEFT)
    lot = (np.cumsum(end - begin) - 1) // LOT
    for _, part in _runs(lot):
        size = (end - begin)[part]
        node = np.repeat(np.arange(part.start, part.stop), size)
        entry = right_order[np.repeat(begin[part], size) + _within(size)]
        entry = entry[np.lexsort((left_rank[entry], node))]
        rank = left_rank[entry]
        same = np.flatnonzero(node[1:] == node[:-1])
        shared = np.full(len(entry), -1, np.int8)
        shared[same + 1] = left_least(rank[same] + 1, rank[same + 1] + 1)
        shared[shared < SPAN - depth[node]] = -1
        before, first, stop = lcp_intervals(shared, 0)
        if not len(first):
            continue
        place, edges = np.append(right_rank[entry], 0), np.column_stack([first, stop]).ravel()
        ends = np.minimum.reduceat(place, edges)[::2], np.maximum.reduceat(place, edges)[::2]
        diverse = right_least(ends[0] + 1, ends[1] + 1) == depth[node[first]]
        before, first, stop = before[diverse], first[diverse], stop[diverse]
        count = stop - first
        yield entry[np.repeat(first, count) + _within(count)], count, before, depth[node[first]]


def later_shifts(context: np.ndarray, key: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Smallest and largest shift t at which an entry's string also stands under a smaller key (-1 where none does).

    At shift t an entry's string starts t bytes before its anchor.
    """
    low, high = np.full(len(key), SPAN, np.int16), np.full(len(key), -1, np.int16)
    for entry, count, before, after in maximal_repeats(context, left, right):
        if not len(count):
            continue
        least = np.minimum.reduceat(key[entry], np.cumsum(count) - count)
        late = key[entry] > np.repeat(least, count)
        np.minimum.at(low, entry[late], np.repeat(np.maximum(SPAN - after, 0), count)[late].astype(np.int16))
        np.maximum.at(high, entry[late], np.repeat(before, count)[late].astype(np.int16))
    return np.where(high < 0, -1, low), high


def _mark(table: pa.Table) -> pa.Table:
    """Step 3b: byte ranges to remove, to each sender."""
    rows, entries = [], []
    for kind, sender, blob in zip(*(table.column(c).to_pylist() for c in ("kind", "sender", "blob")), strict=True):
        if kind == 3:
            rows.append((sender, 3, -1, blob))
        else:
            p = _unzip(blob)
            entries.append((sender, np.frombuffer(p[0], np.uint8).reshape(-1, LEFT + SPAN), _unplanes(p[1], "<i8"), _unplanes(p[2], "<u4"), _unplanes(p[3], "<u4"), np.frombuffer(p[4], np.uint8), np.frombuffer(p[5], np.uint8)))
    if entries:
        key, doc, at, left, right = (np.concatenate([e[c] for e in entries]) for c in range(2, 7))
        low, high = later_shifts(np.concatenate([e[1] for e in entries]), key, left, right)
        a = 0
        for e in entries:
            part = np.arange(a, a + len(e[2]))
            a += len(e[2])
            part = part[low[part] >= 0]
            if len(part):
                place = at[part].astype(np.int64)
                rows.append((e[0], 3, -1, _ranges(doc[part], place - high[part], place - low[part] + SPAN)))
    return _messages(rows)


def _name(table: pa.Table) -> pa.Table:
    """Step 3b for ``repeats``: to each sender its entries of every maximal repeat group, under a hash of the group's bytes."""
    rows, entries = [], []
    for kind, sender, blob in zip(*(table.column(c).to_pylist() for c in ("kind", "sender", "blob")), strict=True):
        if kind == 4:
            rows.append((sender, 4, -1, blob))
        elif kind == 2:
            p = _unzip(blob)
            n = len(p[5])
            entries.append((np.full(n, sender), np.frombuffer(p[0], np.uint8).reshape(-1, LEFT + SPAN), _unplanes(p[2], "<u4"), _unplanes(p[3], "<u4"), *(np.frombuffer(x, np.uint8) for x in p[4:7])))
    if not entries:
        return _messages(rows)
    sender, context, doc, at, left, right, several = (np.concatenate(x) for x in zip(*entries, strict=True))
    # an entry that stands for several places is its own repeat, too
    whole = np.repeat(np.arange(len(at)), 1 + (several & 1).astype(np.int64))
    for entry, count, before, after in maximal_repeats(context[whole], left[whole], right[whole]):
        group = np.repeat(np.arange(len(count)), count)
        group, entry = np.unique(np.column_stack([group, whole[entry]]), axis=0).T
        first = np.flatnonzero(np.append(True, group[1:] != group[:-1])) if len(group) else group
        names, complete = [], np.zeros(len(count), bool)
        np.logical_or.at(complete, group, several[entry] > 1)
        for g, (i, a, b) in enumerate(zip(entry[first].tolist(), before.tolist(), after.tolist(), strict=True)):
            bytes_ = context[i, LEFT - a : LEFT + b]
            names.append(hashlib.blake2b(bytes_.tobytes(), digest_size=16).digest())
            # other places of these bytes are sure to have this anchor if it is one within the bytes
            complete[g] |= a in anchors(bytes_, np.array([a + b]))[0]
        named = np.frombuffer(b"".join(names), np.uint8).reshape(-1, 16)
        group, entry = group[complete[group]], entry[complete[group]]
        order = np.argsort(sender[entry], kind="stable")
        group, entry = group[order], entry[order]
        for to, part in _runs(sender[entry]):
            g, e = group[part], entry[part]
            start = (at[e].astype(np.int64) - before[g]).astype(np.uint32)
            rows.append((to, 5, -1, _zip(named[g].tobytes(), _planes(doc[e]), _planes(at[e]), _planes(start), _planes((before + after)[g].astype(np.uint32)))))
    return _messages(rows)


def _occurrences(group: Group, messages: pa.Table) -> pa.Table:
    """Step 4 for ``repeats``: the places of all entries of the group, and of the copies that they stand for."""
    copies: dict[tuple[int, int], list[tuple[int, int]]] = {}
    named, out = [], []
    for kind, blob in zip(messages.column("kind").to_pylist(), messages.column("blob").to_pylist(), strict=True):
        p = _unzip(blob)
        if kind == 5:
            named.append(p)
            continue
        for d, a, e, b in zip(*(_unplanes(x, "<u4").tolist() for x in p), strict=True):
            copies.setdefault((d, a), []).append((e, b))
    for p in named:
        for i, (d, a, start, size) in enumerate(zip(*(_unplanes(x, "<u4").tolist() for x in p[1:]), strict=True)):
            for e, b in [(d, a), *copies.get((d, a), ())]:
                out.append((p[0][16 * i : 16 * i + 16].hex(), group.ids[e], b - a + start, b - a + start + size))
    cols = zip(*out, strict=True) if out else [[]] * 4
    return pa.table({n: pa.array(c, t) for n, c, t in zip(("repeat", "doc_id", "start", "stop"), cols, (pa.string(), *[pa.int64()] * 3), strict=True)})


def _cut(group: Group, marks: pa.Table) -> pa.Table:
    """Step 4: the kept bytes of every document of the group, and the spans taken out."""
    ranges: dict[int, list[tuple[int, int]]] = {}
    for blob in marks.column("blob").to_pylist():
        d, a, b = (_unplanes(x, "<u4").tolist() for x in _unzip(blob))
        for i, lo, hi in zip(d, a, b, strict=True):
            ranges.setdefault(i, []).append((lo, hi))
    out = []
    for i, (doc, text) in enumerate(zip(group.ids, group.texts, strict=True)):
        kept, done, spans = [], 0, []
        for lo, hi in sorted(ranges.get(i, ())):
            if lo > done or not spans:  # a new run; touching ranges are one
                kept.append(text[done:lo])
                spans.append({"start": lo, "stop": hi})
                done = hi
            elif hi > done:
                spans[-1]["stop"] = done = hi
        kept.append(text[done:])
        out.append((doc, len(text), b"".join(kept), spans))
    cols = zip(*out, strict=True) if out else [[]] * 4
    kinds = (pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())])))
    return pa.table({n.split(" ")[0]: pa.array(c, t) for n, c, t in zip(("doc_id", "n_bytes", "kept", "spans"), cols, kinds, strict=True)})


def _dealt(docs: DataFrame, doc_id: str, text: str, group_bytes: int, hot: int, middle, last, schema: str, copies: bool = False) -> DataFrame:
    """The four steps, with ``middle`` in the buckets and ``last`` on a group and what the buckets sent it.

    The documents' exchange is the same in the three steps that read it, so it runs once.
    """
    total = docs.agg(F.sum(F.octet_length(docs[text]))).first()[0] or 0
    groups = max(LEAST_GROUPS, -(-total // group_bytes))
    # a message should hold a few hashes
    buckets = int(max(1, min(groups, group_bytes // 20 // 4)))
    rows = docs.select(docs[doc_id].cast("long").alias("doc_id"), docs[text].alias("text"))
    dealt = rows.withColumn("dest", F.pmod(F.xxhash64("doc_id"), F.lit(groups)).cast("int"))
    by_group = dealt.groupBy("dest")

    def offer(key, table):  # Spark reads the type hints of these functions, and takes none as Arrow tables
        return _offer(Group(table), key[0].as_py(), buckets)

    def contexts(key, table, replies):
        return _contexts(Group(table), replies, key[0].as_py(), buckets, copies) if table.num_rows else _messages([])

    def finish(key, table, messages):
        return last(Group(table), messages)

    replies = by_group.applyInArrow(offer, MESSAGE).groupBy("dest").applyInArrow(lambda t: _answer(t, hot), MESSAGE)
    sent = by_group.cogroup(replies.groupBy("dest")).applyInArrow(contexts, MESSAGE)
    back = sent.groupBy("dest").applyInArrow(lambda t: middle(t), MESSAGE)
    return by_group.cogroup(back.groupBy("dest")).applyInArrow(finish, schema)


def cleaned(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", group_bytes: int = GROUP_BYTES, hot: int = HOT) -> DataFrame:
    """doc_id, n_bytes, kept, spans for every row of ``docs``: the bytes that stay, and the byte ranges taken out.

    ``kept`` is binary, since a range may begin or end inside a character.
    """
    return _dealt(docs, doc_id, text, group_bytes, hot, _mark, _cut, CLEANED)


def repeats(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", group_bytes: int = GROUP_BYTES, hot: int = HOT) -> DataFrame:
    """repeat, doc_id, start, stop: the maximal repeat groups with all their occurrences, as byte ranges.

    ``repeat`` is a hash of the group's bytes.  Groups are maximal within the window around their anchor, 34 bytes before
    and 50 from it on; a longer passage is a chain of them, one for each of its anchors.  Strings around hot anchors are
    groups of 50 bytes.  Anchors that a single document holds are not looked at.
    """
    return _dealt(docs, doc_id, text, group_bytes, hot, _name, _occurrences, REPEATS, copies=True).distinct()


def remove_repeats(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row of ``docs``: the digest of ``cleaned``."""
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s["stop"] - s["start"])
    return cleaned(docs, **options).select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(read_table(spark, sf_dir, "documents", "doc_id", "text"))
