"""Operator 9: hierarchical multi-length packing of tokenised documents.

Each task packs the documents of its own input partition in one pass, so nothing is shuffled:

* routing: full windows are cut off a document first; what is left goes to the shortest context tier that holds it
  (256, 512, 1024, 2048 by default);
* packing: each tier, the longest first, is packed into windows of its own size: its longest waiting piece opens one,
  and the gap is filled from the waiting pieces, largest fitting one first, so from shorter tiers where its own has
  none; a gap of ``MIN_CUT`` ids or more (of a window of 2048, in proportion below) is closed by cutting the next piece;
* the last, partly filled window of a task is cut into sequences whose lengths are powers of two, which need no padding;
* step groups: the sequences of each packed lot are dealt to groups in snake order of their length, so that groups
  carry nearly the same number of ids.

Tokenising: white space always separates the tokenizer's words, so a text is split there, distinct words are encoded
apart, and a document is the concatenation of their ids.  A bounded cache in two generations holds the words: those that
the newer one has not met again go with the older one, so that words of a single text do not fill the worker's memory.

The order of rows within a partition must not change when a lost task runs again: the operator is to be applied to a
scan of stored files (the pipeline's stages are).  Defined results: a null or empty text is the end id alone; repeated
rows are packed each on its own; an empty table gives no pieces; null ids pass through.
"""

from __future__ import annotations

import ctypes
import gc
import re
import zlib
from bisect import bisect_right, insort
from collections.abc import Iterator
from contextlib import suppress
from itertools import accumulate

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from evenpart.sources.tables import read_table

WINDOW, TIERS, END_ID = 2048, (256, 512, 1024, 2048), 1
#: Gaps below this many ids are padded rather than closed by cutting a document.
MIN_CUT = 16
LOT, STEP_SEQUENCES = 4096, 64
#: Words of a generation of the cache, beyond those of the texts at hand; texts encoded at once.
CACHE_WORDS, TEXTS = 120_000, 512
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier int, step_group long"
#: What ``pack`` gives: the digest's columns and the ids themselves.
PIECES = f"{SCHEMA}, ids array<int>"

#: A full stop or comma that may belong to a run of punctuation.
_UNSAFE = re.compile(rb"(?<![A-Za-z0-9])(?<!\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])[.,](?=[ \n])")


class WordEncoder:
    """Ids of whole texts as little-endian 32-bit bytes."""

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        # only texts without the tokenizer's special strings may be cut into words
        self.special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.known: dict[bytes, bytes] = {}
        self.older: dict[bytes, bytes] = {}

    def words(self, text: str) -> list[bytes]:
        raw = text.encode().lower()  # the tokenizer lower-cases anyway; here only A-Z
        if _UNSAFE.search(raw) is None:
            for sign in (b".", b","):
                for blank in (b" ", b"\n"):
                    raw = raw.replace(sign + blank, b" " + sign + b" ")
        return raw.split()

    def _learn(self, words: list[bytes]) -> None:
        import numpy as np

        for lo in range(0, len(words), 1000):
            part = [w.decode() for w in words[lo : lo + 1000]]
            whole = self.tokenizer.encode(" ".join(part), add_special_tokens=False)
            ends = np.cumsum([len(w) + 1 for w in part])
            ids = np.array(whole.ids, dtype="<u4")
            first = np.fromiter((o[0] for o in whole.offsets), dtype=np.int64, count=len(ids))
            cuts = np.searchsorted(first, ends, side="left")
            data, a = ids.tobytes(), 0
            for w, b in zip(words[lo : lo + 1000], cuts.tolist(), strict=True):
                self.known[w] = data[4 * a : 4 * b]
                a = b

    def __call__(self, texts: list[str | None]) -> list[bytes]:
        import numpy as np

        split: list[list[bytes] | None] = []
        new: set[bytes] = set()
        for t in texts:
            ws = self.words(t or "")
            whole = "<|" in (t or "") and any(s in w for s in self.special for w in ws)
            split.append(None if whole else ws)
            if not whole:
                new.update(ws)
        if len(self.known) > CACHE_WORDS:
            self.known, self.older = {}, self.known
        missing = []
        for w in new.difference(self.known):
            ids = self.older.pop(w, None)
            if ids is None:
                missing.append(w)
            else:
                self.known[w] = ids
        self._learn(missing)
        get = self.known.__getitem__
        return [b"".join(map(get, ws)) if ws is not None else np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, dtype="<u4").tobytes() for ws, t in zip(split, texts, strict=True)]


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


class Packer:
    """Packs pieces (doc, start, ids) into sequences; ``rows`` gathers the output."""

    def __init__(self, base: int, window: int = WINDOW, tiers: tuple[int, ...] = TIERS, lot: int = LOT) -> None:
        self.window, self.tiers, self.lot, self.base = window, tiers, lot, base
        self.sequences = self.groups = self.waiting = 0
        self.queues: dict[int, list] = {t: [] for t in tiers}
        self.made: list[list] = []
        self.open: list = []
        self.tail: list = []
        self.tail_room = window
        self.rows: list[tuple] = []
        self.n = 0

    def add(self, doc, ids: bytes) -> None:
        """One document: its ids, 4 bytes each."""
        total = len(ids) // 4
        full = total - total % self.window
        for s in range(0, full, self.window):
            self.made.append([(doc, s, ids[4 * s : 4 * (s + self.window)], total)])
        if total > full:
            self._wait((total - full, self.n, (doc, full, ids[4 * full :], total)))
            self.n += 1
        if self.waiting >= self.lot:
            self.flush(False)

    def _wait(self, item) -> None:
        tier = next(t for t in self.tiers if item[0] <= t)
        insort(self.queues[tier], item, key=lambda x: x[:2])
        self.waiting += 1

    def _take(self, most: int):
        """The longest waiting piece of at most ``most`` ids."""
        for t in reversed(self.tiers):
            q = self.queues[t]
            if q and q[0][0] <= most:
                at = bisect_right(q, most, key=lambda x: x[0]) - 1
                self.waiting -= 1
                return q.pop(at)
        return None

    def flush(self, last: bool) -> None:
        """Pack what waits, a window of its own size for each tier; unless ``last``, a window that nothing fills goes on waiting."""
        while self.waiting:
            room = self.tail_room if self.tail else next(t for t in reversed(self.tiers) if self.queues[t])
            seq, gap, least = self.tail, room - sum(len(p[2]) // 4 for p in self.tail), max(1, MIN_CUT * room // self.window)
            self.tail = []
            while gap:
                got = self._take(gap)
                if got is None:
                    if not self.waiting or gap < least:
                        break
                    got = self._take(self.window)  # longer than the gap: cut it
                    doc, start, ids, total = got[2]
                    rest = (doc, start + gap, ids[4 * gap :], total)
                    self._wait((got[0] - gap, self.n, rest))
                    self.n += 1
                    got = (gap, 0, (doc, start, ids[: 4 * gap], total))
                seq.append(got[2])
                gap -= got[0]
            if gap >= least:
                self.tail, self.tail_room = seq, room  # nothing waits any more
            else:
                self.made.append(seq)
        if last and self.tail:
            self._powers(self.tail)
            self.tail = []
        self._emit()

    def _powers(self, pieces: list) -> None:
        """Cut ``pieces`` into sequences whose lengths are the powers of two in their sum."""
        left = sum(len(p[2]) // 4 for p in pieces)
        queue = list(reversed(pieces))
        while left:
            room = 1 << (left.bit_length() - 1)
            left -= room
            seq = []
            while room:
                doc, start, ids, total = queue.pop()
                size = len(ids) // 4
                if size > room:
                    queue.append((doc, start + room, ids[4 * room :], total))
                    ids, size = ids[: 4 * room], room
                seq.append((doc, start, ids, total))
                room -= size
            self.made.append(seq)

    def _emit(self) -> None:
        lengths = [sum(len(p[2]) // 4 for p in s) for s in self.made]
        groups = max(1, -(-len(self.made) // STEP_SEQUENCES))
        order = sorted(range(len(self.made)), key=lambda i: (-lengths[i], i))
        group = {}
        for rank, i in enumerate(order):
            turn, at = divmod(rank, groups)
            group[i] = at if turn % 2 == 0 else groups - 1 - at
        for i, seq in enumerate(self.made):
            offset, size = 0, lengths[i]
            tier = next(t for t in self.tiers if size <= t)
            for doc, start, ids, total in seq:
                n = len(ids) // 4
                self.rows.append((doc, start, n, zlib.crc32(ids), total, self.base + self.sequences, offset, tier, self.base + self.groups + group[i], ids))
                offset += n
            self.sequences += 1
        self.groups += groups if self.made else 0
        self.made = []

    def drain(self) -> list[tuple]:
        out, self.rows = self.rows, []
        return out


def trim() -> None:
    """Give back what earlier tasks of this worker have freed, their Arrow buffers included."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


def pack(docs: DataFrame, tokenizer_path: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per piece, with its ids."""
    end = END_ID.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trim()
        encode = encoder(tokenizer_path)
        schema = pa.schema([(n, pa.int32() if t == "int" else pa.int64()) for n, t in (c.split(" ") for c in SCHEMA.split(", "))] + [("ids", pa.list_(pa.int32()))])
        packer = Packer(TaskContext.get().partitionId() << 32)

        def out(rows: list[tuple]) -> pa.RecordBatch:
            *columns, ids = zip(*rows, strict=True)
            edges = pa.array(list(accumulate((len(x) // 4 for x in ids), initial=0)), pa.int32())
            flat = pa.Array.from_buffers(pa.int32(), edges[-1].as_py(), [None, pa.py_buffer(b"".join(ids))])
            return pa.RecordBatch.from_arrays([*[pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=False)], pa.ListArray.from_arrays(edges, flat)], schema=schema)

        for batch in batches:
            for lo in range(0, batch.num_rows, TEXTS):
                part = batch.slice(lo, TEXTS)
                for doc, ids in zip(part.column(0).to_pylist(), encode(part.column(1).to_pylist()), strict=True):
                    packer.add(doc, ids + end)
                if packer.rows:
                    yield out(packer.drain())
        packer.flush(True)
        if packer.rows:
            yield out(packer.drain())

    return docs.select(docs[doc_id].alias("doc_id"), docs[text].alias("text")).mapInArrow(run, PIECES)


def vocabulary_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op9_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(read_table(spark, sf_dir, "documents", "doc_id", "text"), vocabulary_path()).drop("ids")
