"""Repeated passages by bucket-pointer refinement over byte suffixes.

A suffix's bucket at depth ``2q`` is the pair of its bucket at depth ``q`` and the
bucket, at depth ``q``, of the suffix ``q`` bytes later.  The bucket identifiers
are 64-bit numbers made of the two earlier identifiers by a mixing function, so
each refinement reuses the last one's identifiers and no text is compared twice.

Refining every suffix of a corpus would shuffle all its bytes.  Three exact facts
keep the refinement to where it can matter:

* Of a 100-byte window only the 32-byte bucket with the smallest identifier (its
  *anchor*) starts the refinement: equal windows have equal anchors.  A bucket
  with one member is final and is dropped: its windows occur once.
* An anchor's full context (68 bytes on both sides) is one identifier.  Of the
  anchors with equal context all but the first are repeats with all their windows.
* Only the first members of buckets with several contexts go on, with their 168
  bytes: the 69 windows around each are refined to depth 100, bucket by bucket, and
  the first of each kind is kept.  A bucket of more than ``MAX_TOGETHER`` members
  is not brought together; its windows are counted as rows of their own.

Identifiers are not compared with the bytes: a bucket and a context hold 128 bits together,
a window 64 among those of its bucket's task.

Hot buckets (a passage in a third of all documents) meet a partial aggregate
before each shuffle, and the joins back to their members are skew-split.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settle

LENGTH, Q = 100, 32
REACH = LENGTH - Q
CONTEXT = LENGTH + REACH
BLOCK = 1 << 17
#: Members of a bucket that one task refines together, and rows it refines at once.
MAX_TOGETHER, CHUNK = 1 << 16, 1 << 14
_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def _byte_ids() -> np.ndarray:
    x = (np.arange(1, 257, dtype=np.uint64)) * _M1
    for shift, mul in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(mul)
    return x ^ (x >> np.uint64(31))


_BYTE = _byte_ids()


def _pair(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The bucket of two buckets."""
    x = a * _M1
    x += b * _M2
    x ^= x >> np.uint64(29)
    return x


def refine(data: np.ndarray, depth: int) -> dict[int, np.ndarray]:
    """Bucket identifiers of all suffixes of ``data`` (along its last axis) at depths 1, 2, 4, .. ``depth``."""
    ids, q = {1: _BYTE[data]}, 1
    while q < depth and data.shape[-1] >= 2 * q:
        ids[2 * q] = _pair(ids[q][..., :-q], ids[q][..., q:])
        q *= 2
    return ids


def _slide(x: np.ndarray, width: int, pick: Callable) -> np.ndarray:
    """``pick`` (minimum or maximum) over windows of ``width``."""
    span = 1
    while 2 * span <= width:
        x = pick(x[:-span], x[span:])
        span *= 2
    return pick(x[: len(x) - (width - span)], x[width - span:]) if span < width else x


class _Block:
    """Pieces of documents, concatenated: ``(row, first byte, core start, core end, whole length)``."""

    def __init__(self, pieces: list[tuple[int, bytes, int, int, int, int]]):
        self.rows = np.array([p[0] for p in pieces])
        self.lens = np.array([len(p[1]) for p in pieces])
        self.at = np.concatenate([[0], np.cumsum(self.lens)[:-1]])
        self.first, self.lo, self.hi, self.whole = (np.array([p[k] for p in pieces]) for k in (2, 3, 4, 5))
        data = np.frombuffer(b"".join(p[1] for p in pieces), np.uint8)
        self.ids = refine(data, Q)
        h = (self.ids.get(Q, np.zeros(0, np.uint64)) >> np.uint64(32)).astype(np.uint32)
        n = len(data)
        if n < LENGTH:
            self.anchors = np.zeros(0, np.int64)
            return
        low = _slide(h, REACH + 1, np.minimum)  # one per window of 100 bytes
        real = np.ones(len(low), bool)
        for end in (self.at + self.lens).tolist():  # windows that pass an end are none
            real[max(end - LENGTH + 1, 0): end] = False
        low[~real] = 0
        padded = np.concatenate([np.zeros(REACH, np.uint32), low, np.zeros(REACH, np.uint32)])
        best = _slide(padded, REACH + 1, np.maximum)
        j = np.flatnonzero(best[: len(h)] == h)
        # 0 is the best where no window is, too: an identifier of 0 counts where one is
        nil = np.flatnonzero(h[j] == 0)
        if len(nil):
            upto = np.concatenate([[0], np.cumsum(real)])
            some = upto[np.minimum(j[nil] + 1, len(real))] > upto[np.clip(j[nil] - REACH, 0, len(real))]
            j = np.delete(j, nil[~some])
        piece = np.searchsorted(self.at, j, "right") - 1
        pos = self.first[piece] + j - self.at[piece]
        core = (pos >= self.lo[piece]) & (pos < self.hi[piece])
        self.anchors, self.piece, self.pos = j[core], piece[core], pos[core]

    def contexts(self, salt: np.ndarray) -> np.ndarray:
        """The bucket of each anchor's full context; anchors near an end of their
        document have one of their own (``salt``: unlike for all rows)."""
        j, ids = self.anchors, self.ids
        full = (self.pos >= REACH) & (self.pos + LENGTH <= self.whole[self.piece])
        out = _pair(salt[self.rows[self.piece]], self.pos.astype(np.uint64))
        k = j[full]
        if len(k):
            h = ids[Q]
            left, right = _pair(_pair(h[k - 68], h[k - 36]), _pair(h[k - 4], h[k + 28])), _pair(h[k + 60], ids[8][k + 92])
            out[full] = _pair(left, right)
        return out


def _blocks(texts: list[bytes | None], reach: int = LENGTH) -> Iterator[_Block]:
    """Whole texts in blocks of bounded size; a longer text comes in overlapping pieces."""
    pieces, size = [], 0
    for row, text in enumerate(texts):
        n = len(text or b"")
        if n < LENGTH:
            continue
        for lo in range(0, n, BLOCK):
            hi = min(n, lo + BLOCK)
            first = max(0, lo - 2 * reach)
            part = text[first: hi + 2 * reach]
            pieces.append((row, part, first, lo, hi, n))
            size += len(part)
            if size >= BLOCK:
                yield _Block(pieces)
                pieces, size = [], 0
    if pieces:
        yield _Block(pieces)


def _bytes(column: pa.Array) -> list[bytes | None]:
    return column.cast(pa.binary()).to_pylist()


def _salts(ids: pa.Array) -> np.ndarray:
    x = np.asarray(ids.fill_null(-1), dtype=np.int64).astype(np.uint64)
    return _pair(x, x ^ _M2)


def _table(**columns: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({k: pa.array(v.view(np.int64) if v.dtype == np.uint64 else v) for k, v in columns.items()})


def _find_anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = np.asarray(batch.column("doc_id"), dtype=np.int64)
        salt = _salts(batch.column("doc_id"))
        for block in _blocks(_bytes(batch.column("text"))):
            if len(block.anchors):
                yield _table(bucket=block.ids[Q][block.anchors], context=block.contexts(salt),
                             doc_id=ids[block.rows[block.piece]], pos=block.pos.astype(np.int32))


def _find_buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for block in _blocks(_bytes(batch.column("text"))):
            if len(block.anchors):
                yield _table(bucket=block.ids[Q][block.anchors])


def _cut_contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The bytes around each listed anchor, as far as its document goes."""
    for batch in batches:
        ids, buckets, docs, places, out = batch.column("doc_id").to_pylist(), [], [], [], []
        for i, (text, anchors) in enumerate(zip(_bytes(batch.column("text")), batch.column("anchors").to_pylist())):
            for a in anchors:
                buckets.append(a["bucket"])
                docs.append(ids[i])
                places.append(a["pos"])
                out.append(text[max(a["pos"] - REACH, 0): a["pos"] + LENGTH])
        for lo in range(0, len(out), 50_000):
            part = slice(lo, lo + 50_000)
            yield pa.RecordBatch.from_arrays([pa.array(buckets[part], pa.int64()), pa.array(docs[part], pa.int64()), pa.array(places[part], pa.int32()), pa.array(out[part], pa.binary())],
                                             ["bucket", "doc_id", "pos", "around"])


def _window_ids(bucket: np.ndarray, pos: np.ndarray, around: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """For each row the bucket at depth 100 of its 69 windows, and which of them its document has."""
    n = len(around)
    data, left = np.zeros((n, CONTEXT), np.uint8), np.minimum(pos, REACH)
    whole = np.array([len(x) == CONTEXT for x in around])
    if whole.any():
        data[whole] = np.frombuffer(b"".join(x for x in around if len(x) == CONTEXT), np.uint8).reshape(-1, CONTEXT)
    for i in np.flatnonzero(~whole).tolist():
        at = REACH - int(left[i])
        data[i, at: at + len(around[i])] = np.frombuffer(around[i], np.uint8)
    ids = refine(data, Q)
    k = REACH + 1
    h = ids[Q]
    w = _pair(_pair(_pair(h[:, :k], h[:, 32: 32 + k]), _pair(h[:, 64: 64 + k], ids[4][:, 96: 96 + k])), bucket.view(np.uint64)[:, None])
    starts = np.arange(k)[None, :]
    right = np.array([len(x) for x in around]) - left - Q
    return w, (starts >= (REACH - left)[:, None]) & (starts <= right[:, None])


def _runs(repeats: np.ndarray, doc: np.ndarray, pos: np.ndarray) -> pa.RecordBatch:
    """Runs of repeated windows as byte intervals."""
    edge = np.diff(np.pad(repeats, ((0, 0), (1, 1))).astype(np.int8), axis=1)
    row, first = np.nonzero(edge == 1)
    _, last = np.nonzero(edge == -1)
    start = pos[row] - REACH + first
    return _table(doc_id=doc[row], start=start.astype(np.int32), end=(pos[row] - REACH + last - 1 + LENGTH).astype(np.int32))


def _refine_buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Whole buckets, sorted by bucket, document and place: all windows but the first of their kind."""
    held: list[tuple] = []
    size = 0

    def done(parts: list[tuple]) -> pa.RecordBatch:
        bucket, doc, pos = (np.concatenate([p[k] for p in parts]) for k in range(3))
        around = [x for p in parts for x in p[3]]
        ids, fits = np.empty((len(doc), REACH + 1), np.uint64), np.empty((len(doc), REACH + 1), bool)
        for lo in range(0, len(doc), 2048):
            part = slice(lo, lo + 2048)
            ids[part], fits[part] = _window_ids(bucket[part], pos[part], around[part])
        flat = np.flatnonzero(fits)
        keys = ids.ravel()[flat]
        order = np.argsort(keys, kind="stable")
        keys, flat = keys[order], flat[order]
        again = np.zeros(ids.size, bool)
        if len(flat):
            # the first place of each kind; one window may be here under two anchors
            heads = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
            kind = np.repeat(np.arange(len(heads)), np.diff(np.append(heads, len(keys))))
            row = flat // (REACH + 1)
            start, own = pos[row] + flat % (REACH + 1), doc[row] == doc[row[heads]][kind]
            first = np.minimum.reduceat(np.where(own, start, np.iinfo(np.int64).max), heads)
            again[flat] = ~(own & (start == first[kind]))
        return _runs(again.reshape(ids.shape), doc, pos)

    for batch in batches:
        rows = (np.asarray(batch.column("bucket")), np.asarray(batch.column("doc_id")), np.asarray(batch.column("pos")).astype(np.int64), batch.column("around").to_pylist())
        cuts = [0, *(np.flatnonzero(np.diff(rows[0])) + 1).tolist(), len(rows[0])]
        for lo, hi in zip(cuts, cuts[1:]):
            if lo == hi:
                continue
            if size >= CHUNK and held[-1][0][-1] != rows[0][lo]:
                yield done(held)
                held, size = [], 0
            held.append(tuple(x[lo:hi] for x in rows))
            size += hi - lo
    if held:
        yield done(held)


def _spread_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The windows of hot buckets, one row each."""
    for batch in batches:
        bucket, doc, pos = np.asarray(batch.column("bucket")), np.asarray(batch.column("doc_id")), np.asarray(batch.column("pos")).astype(np.int64)
        around = batch.column("around").to_pylist()
        for lo in range(0, len(doc), 2048):
            part = slice(lo, lo + 2048)
            ids, fits = _window_ids(bucket[part], pos[part], around[part])
            row, at = np.nonzero(fits)
            yield _table(bucket=bucket[part][row], window=ids[row, at], doc_id=doc[part][row], pos=(pos[part][row] - REACH + at).astype(np.int32))


def cut(text: bytes, starts: list[int], ends: list[int]) -> tuple[int, int, list[tuple[int, int]], bytes]:
    """Bytes and maximal runs removed, the runs, and what is left."""
    n, runs = len(text), []
    for a, b in sorted(zip(starts, ends)):
        a, b = max(a, 0), min(b, n)
        if runs and a <= runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], b)
        else:
            runs.append([a, b])
    kept, last = [], 0
    for a, b in runs:
        kept.append(text[last:a])
        last = b
    kept.append(text[last:])
    left = b"".join(kept)
    return n - len(left), len(runs), [tuple(r) for r in runs], left


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for text, starts, ends in zip(_bytes(batch.column("text")), batch.column("starts").to_pylist(), batch.column("ends").to_pylist()):
            text = text or b""
            removed, spans, _, left = cut(text, starts or [], ends or [])
            rows.append((len(text), removed, spans, hashlib.sha256(left).hexdigest()))
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), *(pa.array([r[k] for r in rows], pa.int64()) for k in range(3)), pa.array([r[3] for r in rows], pa.string())],
            ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def repeated_intervals(docs: DataFrame, max_together: int = MAX_TOGETHER) -> DataFrame:
    """Byte intervals ``(doc_id, start, end)`` of ``docs`` (doc_id, text) that also start
    earlier, as lists per document; they overlap and may pass the ends of a text."""
    texts = docs.select("doc_id", "text").where("octet_length(text) >= 100 AND doc_id IS NOT NULL")
    buckets = texts.select("doc_id", "text").mapInArrow(_find_buckets, "bucket long")
    shared = settle(buckets.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("bucket"), "buckets")
    anchors = texts.mapInArrow(_find_anchors, "bucket long, context long, doc_id long, pos int")
    anchors = settle(anchors.join(shared.hint("shuffle_hash"), "bucket", "left_semi"), "anchors")

    place = F.struct("doc_id", "pos")
    first = anchors.groupBy("bucket", "context").agg(F.min(place).alias("first"))
    first = settle(first, "contexts")
    later = anchors.join(first.hint("shuffle_hash"), ["bucket", "context"]).where(place != F.col("first"))
    whole = later.select("doc_id", (F.col("pos") - REACH).alias("start"), (F.col("pos") + LENGTH).alias("end"))
    mixed = first.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    open_ = first.join(mixed.hint("shuffle_hash"), "bucket").select("bucket", "n", "first.doc_id", "first.pos")
    open_ = settle(open_, "open")

    def contexts(anchors_of: DataFrame) -> DataFrame:
        listed = anchors_of.groupBy("doc_id").agg(F.collect_list(F.struct("bucket", "pos")).alias("anchors"))
        return texts.join(listed.hint("shuffle_hash"), "doc_id").select("doc_id", "text", "anchors").mapInArrow(
            _cut_contexts, "bucket long, doc_id long, pos int, around binary")

    together = contexts(open_.where(F.col("n") <= max_together)).repartition("bucket").sortWithinPartitions("bucket", "doc_id", "pos")
    spans = settle(together.mapInArrow(_refine_buckets, "doc_id long, start int, end int"), "spans")
    hot = open_.where(F.col("n") > max_together)
    if not hot.isEmpty():
        windows = settle(contexts(hot).mapInArrow(_spread_windows, "bucket long, window long, doc_id long, pos int"), "windows")
        firsts = windows.groupBy("bucket", "window").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
        again = windows.join(firsts.hint("merge"), ["bucket", "window"]).where(place != F.col("first"))
        spans = spans.union(again.select("doc_id", F.col("pos").alias("start"), (F.col("pos") + LENGTH).alias("end")))
    spans = whole.unionByName(spans).groupBy("doc_id").agg(F.collect_set(F.struct("start", "end")).alias("spans"))
    return settle(spans.select("doc_id", F.col("spans.start").alias("starts"), F.col("spans.end").alias("ends")), "intervals")


def remove_repeats(docs: DataFrame) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, n_bytes, n_removed, n_spans, kept_sha256.

    A byte goes if a 100-byte string that covers it starts earlier as well, in a
    smaller doc_id or earlier in the same document.  Null texts are empty and
    texts under 100 bytes keep all; long texts are read in overlapping pieces;
    rows that repeat a doc_id are one document and get the same intervals; rows
    without an id neither lose nor remove anything."""
    joined = docs.select("doc_id", "text").join(repeated_intervals(docs).hint("merge"), "doc_id", "left")
    return joined.select("doc_id", "text", "starts", "ends").mapInArrow(
        _digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
