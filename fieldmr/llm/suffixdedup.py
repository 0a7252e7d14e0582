"""Removal of byte strings that repeat across documents, by column-wise transforms of anchored pieces.

Every run of ``SPAN`` bytes has an anchor, its gram of least hash, the leftmost of equal ones; equal runs have equal anchors at the same place.
Consecutive runs with one anchor make a piece of text.  Anchors that only one document has
need no further look.  Pieces of the others are dealt into buckets by anchor, and in each bucket a column-wise
construction (``colwise``) sorts all suffixes of its distinct pieces with their common prefixes, in files that are read and
rewritten front to back.  Neighbours that share ``SPAN`` bytes form a group; the least document of a group keeps the
run, all others lose it.

Documents travel in packs of a few MB.  A pack sends each distinct anchor or piece once, however many of its
documents hold it, so what a bucket gathers from a text that a third of all documents share is one piece per pack.
An anchor that very many documents have, each in a text of its own, does not go to one bucket: its runs are dealt one by one, by
a hash of all their bytes.  A pack is one compressed row of a written table, so no step sorts or deals out single documents.
"""

from __future__ import annotations

import hashlib
import os
import tempfile
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textbytes as tb
from .colwise import shared_least
from .runtime import broadcast_if_small, drop_table, materialise

SPAN = 50
GRAM = 28
#: Runs that one piece holds at most, as a gram at one place is in no more; it bounds the rounds of a construction.
RUNS = SPAN - GRAM + 1
#: Bytes of text per pack and per bucket, about.
PACK, BUCKET = 4 << 20, 4 << 20
#: Documents from which on the runs of an anchor are dealt one by one.
HOT = 20_000
#: Compression of texts, which are written once and moved several times.
TEXT_LEVEL = 3
#: Runs that are hashed together, and pieces that are; few enough for a processor's cache.
STRETCH, BATCH = 1 << 15, 1 << 12

_BASE = 0x9E3779B97F4A7C15


def _powers(base: int, n: int) -> np.ndarray:
    return np.array([pow(base, k, 1 << 64) for k in range(n)], dtype=np.uint64)


_UP, _DOWN = _powers(_BASE, STRETCH + SPAN), _powers(pow(_BASE, -1, 1 << 64), STRETCH + SPAN)
#: The low bits of a gram's hash, which hold its place in a stretch while anchors are sought: of equal grams the leftmost is the anchor.
_PLACE = np.uint64(0xFFFF)


def _hashed(sums: np.ndarray) -> np.ndarray:
    return tb.mix64(sums) | _PLACE


def anchored(data: np.ndarray, offsets: np.ndarray, span: int = SPAN, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, number of runs, distance of the anchor from the first run) of the pieces of all documents.

    The pieces of a document lie one after another, from its first run to its last.
    """
    found: list[tuple[np.ndarray, ...]] = []
    width = span - gram + 1
    ends = offsets[1:] - span  # a document's last run
    for a in range(0, len(data) - span + 1, STRETCH):
        raw = data[a : a + STRETCH + span - 1]
        sums = np.zeros(len(raw) + 1, dtype=np.uint64)
        np.cumsum(_UP[: len(raw)] * (raw.astype(np.uint64) + np.uint64(1)), out=sums[1:])
        grams = _hashed((sums[gram:] - sums[:-gram]) * _DOWN[: len(raw) - gram + 1])
        grams -= _PLACE - np.arange(len(grams), dtype=np.uint64)
        least = tb.sliding_min(grams, width)
        edge = np.empty(len(least), dtype=bool)
        edge[0] = True
        np.not_equal(least[1:], least[:-1], out=edge[1:])
        # documents begin new pieces, and runs end with them
        d, e = np.searchsorted(offsets, (a, a + len(least)))
        edge[offsets[d:e] - a] = True
        first = np.flatnonzero(edge)
        doc = np.searchsorted(offsets, a + first, side="right") - 1
        until = np.minimum(np.append(first[1:], len(least)), ends[doc] + 1 - a)
        runs = until - first
        real = runs > 0
        first, doc, runs = first[real], doc[real], runs[real]
        found.append((doc, runs.astype(np.uint8), ((least[first] & _PLACE).astype(np.int64) - first).astype(np.uint8)))
    if not found:
        return np.empty(0, np.int64), np.empty(0, np.uint8), np.empty(0, np.uint8)
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def _anchor_hashes(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Hashes of the grams at some places, the same as those that anchors are chosen by."""
    out = np.empty(len(at), dtype=np.uint64)
    if len(at):
        grams = np.lib.stride_tricks.sliding_window_view(data, GRAM)
        for a in range(0, len(at), BATCH):
            out[a : a + BATCH] = _hashed(((grams[at[a : a + BATCH]].astype(np.uint64) + np.uint64(1)) * _UP[:GRAM]).sum(axis=1, dtype=np.uint64))
    return out


def _spread(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """All places of some strings, one string after another."""
    return np.repeat(starts - (np.cumsum(lengths) - lengths), lengths) + np.arange(int(lengths.sum()))


def _string_hashes(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    out = np.empty(len(starts), dtype=np.uint64)
    for a in range(0, len(starts), BATCH):
        n = lengths[a : a + BATCH]
        begin = np.cumsum(n) - n
        terms = (data[_spread(starts[a : a + BATCH], n)].astype(np.uint64) + np.uint64(1)) * _UP[_spread(np.zeros_like(n), n)]
        out[a : a + BATCH] = tb.mix64(np.add.reduceat(terms, begin) + n.astype(np.uint64))
    return out


def _alike(data: np.ndarray, starts: np.ndarray, to: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Which strings equal byte for byte those of the same length that start at ``to``."""
    out = np.ones(len(starts), dtype=bool)
    look = np.flatnonzero(starts != to)
    for a in range(0, len(look), BATCH):
        own = look[a : a + BATCH]
        n = lengths[own]
        same = data[_spread(starts[own], n)] == data[_spread(to[own], n)]
        out[own] = np.logical_and.reduceat(same, np.cumsum(n) - n)
    return out


def distinct(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(number of its distinct string for each string, one string of each number); strings are of one byte or more.

    Equal hashes only propose; bytes decide.
    """
    if not len(starts):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    _, first, of = np.unique(_string_hashes(data, starts, lengths), return_index=True, return_inverse=True)
    same = lengths[first[of]] == lengths
    same[same] = _alike(data, starts[same], starts[first[of]][same], lengths[same])
    other = np.flatnonzero(~same)
    of[other] = len(first) + np.arange(len(other))
    return of, np.append(first, other)


_PACK = pa.schema([("pack", pa.int64()), ("body", pa.binary())])


def _packs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Documents and their pieces as rows of about ``PACK`` bytes of text, numbered apart from those of all other tasks."""
    task, number = TaskContext.get().partitionId(), 0
    ids: list[np.ndarray] = []
    texts: list[tuple[np.ndarray, np.ndarray]] = []
    held = 0

    def row() -> pa.RecordBatch:
        data, sizes = np.concatenate([t[0] for t in texts]), np.concatenate([t[1] for t in texts])
        doc, runs, distance = anchored(data, np.concatenate(([0], np.cumsum(sizes))))
        body = _pack_z(np.concatenate(ids), sizes, data, np.bincount(doc, minlength=len(sizes)), runs, distance, level=TEXT_LEVEL)
        return pa.RecordBatch.from_arrays([pa.array([(task << 32) | number]), pa.array([body], pa.binary())], schema=_PACK)

    for batch in batches:
        own = batch.column(batch.schema.get_field_index("doc_id"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch), PACK):
            ids.append(own.slice(i, j - i).to_numpy(zero_copy_only=False).astype(np.int64))
            texts.append((data.copy(), np.diff(offsets)))
            held += len(data)
            if held >= PACK:
                yield row()
                ids, texts, held, number = [], [], 0, number + 1
    if ids:
        yield row()


class Pack:
    """Documents of one pack and their pieces."""

    def __init__(self, number: int, body: bytes, pieces: bool = True):
        self.number = number
        self.ids, sizes, self.data, counts, runs, distance = _unpack_z(body, np.int64, np.int64, np.uint8, np.int64, np.uint8, np.uint8)
        self.offsets = np.concatenate(([0], np.cumsum(sizes)))
        if not pieces:
            return
        self.doc = np.repeat(np.arange(len(self.ids)), counts)
        self.runs = runs.astype(np.int64)
        before = np.cumsum(self.runs) - self.runs
        lead = np.cumsum(counts) - counts
        own = counts > 0
        self.start = before + np.repeat(self.offsets[:-1][own] - before[lead[own]], counts[own])
        self.anchor = self.start + distance

    @staticmethod
    def of(table: pa.Table, pieces: bool = True) -> Pack:
        return Pack(*(table.column(c)[0].as_py() for c in ("pack", "body")), pieces)

    def raw(self, d: int) -> np.ndarray:
        return self.data[self.offsets[d] : self.offsets[d + 1]]

    def keys(self, bits: int) -> np.ndarray:
        return _keys(_anchor_hashes(self.data, self.anchor), bits)


def _keys(anchor: np.ndarray, bits: int) -> np.ndarray:
    """Bucket (the first bits) and the next 32 bits of a second hash, as least hashes are small ones; collisions only cost a needless look."""
    anchor = tb.mix64(anchor + np.uint64(_BASE))
    return ((anchor >> np.uint64(64 - bits)) << np.uint64(32)) | (anchor >> np.uint64(32 - bits)) & np.uint64(0xFFFFFFFF)


def _cut(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Begin and end of the runs of equal values."""
    begin = np.flatnonzero(np.concatenate(([True], values[1:] != values[:-1]))) if len(values) else np.empty(0, np.int64)
    return begin, np.append(begin[1:], len(values))[: len(begin)]


_PACKED = "bucket int, pack long, body binary"


def _pack_z(*arrays: np.ndarray, level: int = 1) -> bytes:
    head = np.array([a.nbytes for a in arrays], dtype=np.int64).tobytes()
    return zstandard.ZstdCompressor(level=level).compress(head + b"".join(a.tobytes() for a in arrays))


def _unpack_z(body: bytes, *kinds) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(body)
    sizes, at, out = np.frombuffer(raw, np.int64, len(kinds)), 8 * len(kinds), []
    for size, kind in zip(sizes.tolist(), kinds, strict=True):
        out.append(np.frombuffer(raw, dtype=kind, offset=at, count=size // np.dtype(kind).itemsize))
        at += size
    return out


def _rows(rows: list[tuple[int, int, bytes]]) -> pa.Table:
    return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int32()), "pack": pa.array([r[1] for r in rows], pa.int64()), "body": pa.array([r[2] for r in rows], pa.binary())})


def _offer(batches: Iterator[pa.RecordBatch], bits: int) -> Iterator[pa.RecordBatch]:
    """A pack's distinct anchors by bucket, and how many of its documents have each (65535: that or more)."""
    for batch in batches:
        for row in batch.to_pylist():
            pack = Pack(row["pack"], row["body"])
            key, doc = pack.keys(bits), pack.doc
            order = np.argsort(key, kind="stable")  # documents stay ascending
            key, doc = key[order], doc[order]
            begin, _ = _cut(key)
            fresh = np.concatenate(([True], (doc[1:] != doc[:-1]) | (key[1:] != key[:-1]))) if len(key) else np.empty(0, bool)
            many = np.minimum(np.add.reduceat(fresh, begin, dtype=np.int64), 65535).astype(np.uint16) if len(key) else np.empty(0, np.uint16)
            bucket, short = (key[begin] >> np.uint64(32)).astype(np.int64), key[begin].astype(np.uint32)
            yield from _rows([(int(bucket[a]), pack.number, _pack_z(short[a:b], many[a:b])) for a, b in zip(*_cut(bucket), strict=True)]).to_batches()


def _answer(table: pa.Table, hot: int = HOT) -> pa.Table:
    """Of one bucket: to each pack those of its anchors that more than one document has, and which very many have."""
    packs = table.column("pack").to_pylist()
    bodies = [_unpack_z(b, np.uint32, np.uint16) for b in table.column("body").to_pylist()]
    key, of = np.unique(np.concatenate([b[0] for b in bodies]), return_inverse=True)
    total = np.bincount(of, weights=np.concatenate([b[1] for b in bodies]))
    bucket, rows = table.column("bucket")[0].as_py(), []
    for pack, (short, _) in zip(packs, bodies, strict=True):
        n = total[np.searchsorted(key, short)]
        again = n > 1
        if again.any():
            rows.append((bucket, pack, _pack_z(short[again], n[again] > hot)))
    return _rows(rows)


class Sent:
    """The distinct strings that a pack asks about, bucket after bucket; the answers come in this order."""

    def __init__(self, table: pa.Table, replies: pa.Table, bits: int):
        self.pack = pack = Pack.of(table)
        key, known, hot = pack.keys(bits), [], []
        for bucket, body in zip(replies.column("bucket").to_pylist(), replies.column("body").to_pylist(), strict=True):
            short, often = _unpack_z(body, np.uint32, np.bool_)
            known.append((np.uint64(bucket) << np.uint64(32)) | short.astype(np.uint64)), hot.append(often)
        known, hot = (np.concatenate(x) for x in (known, hot))
        order = np.argsort(known)
        known, hot = known[order], hot[order]
        to = np.minimum(np.searchsorted(known, key), len(known) - 1)
        shared = known[to] == key
        often = shared & hot[to]
        at, one = np.flatnonzero(shared & ~often), np.flatnonzero(often)
        # pieces as they are; of hot anchors each run by itself, by a hash of its own
        runs = pack.runs[one]
        run = _spread(pack.start[one], runs)
        self.start = np.concatenate([pack.start[at], run])
        self.runs = np.concatenate([pack.runs[at], np.ones(len(run), dtype=np.int64)])
        self.doc = np.concatenate([pack.doc[at], np.repeat(pack.doc[one], runs)])
        own = _string_hashes(pack.data, run, np.full(len(run), SPAN, dtype=np.int64))
        key = np.concatenate([key[at], _keys(own, bits)])
        of, first = distinct(pack.data, self.start, self.runs + SPAN - 1)
        order = np.argsort(key[first], kind="stable")
        number = np.empty(len(first), dtype=np.int64)
        number[order] = np.arange(len(first))
        self.of, self.first, self.key = number[of], first[order], key[first[order]]

    def buckets(self) -> Iterator[tuple[int, slice]]:
        bucket = (self.key >> np.uint64(32)).astype(np.int64)
        for a, b in zip(*_cut(bucket), strict=True):
            yield int(bucket[a]), slice(a, b)


def _send(table: pa.Table, replies: pa.Table, bits: int) -> pa.Table:
    if not len(table) or not len(replies):
        return _rows([])
    sent = Sent(table, replies, bits)
    least = np.full(len(sent.first), np.iinfo(np.int64).max)
    np.minimum.at(least, sent.of, sent.pack.ids[sent.doc])
    # to itself a pack sends where its strings stand, under a negative bucket of its own
    steps = np.diff(sent.start, prepend=0)
    rows = [(-1 - (sent.pack.number * _BASE % (1 << 64) >> 33), sent.pack.number, _pack_z(steps, sent.runs.astype(np.uint8), sent.of.astype(np.int32), sent.runs[sent.first].astype(np.uint8)))]
    for bucket, own in sent.buckets():
        first = sent.first[own]
        lengths = sent.runs[first] + SPAN - 1
        text = sent.pack.data[_spread(sent.start[first], lengths)]
        rows.append((bucket, sent.pack.number, _pack_z(least[own], lengths.astype(np.uint8), text, level=TEXT_LEVEL)))
    return _rows(rows)


def _scratch() -> Path:
    """A folder for the files of one task: where this executor's block manager keeps its own spills, gone with the task."""
    return Path(os.environ["SPARK_LOCAL_DIRS"].split(",")[0])


def _judge(table: pa.Table) -> pa.Table:
    """Of one bucket: for each string that a pack sent, runs of equal least documents over its windows; what packs send to themselves goes on."""
    if table.column("bucket")[0].as_py() < 0:
        return table
    packs, parts = table.column("pack").to_pylist(), [_unpack_z(b, np.int64, np.uint8, np.uint8) for b in table.column("body").to_pylist()]
    docs, lengths, data = (np.concatenate([p[k] for p in parts]) for k in range(3))
    counts = [len(p[0]) for p in parts]
    del parts
    lengths = lengths.astype(np.int64)
    starts = np.cumsum(lengths) - lengths
    of, first = distinct(data, starts, lengths)
    least = np.full(len(first), np.iinfo(np.int64).max)
    np.minimum.at(least, of, docs)
    windows = lengths[first] - SPAN + 1
    base = np.cumsum(windows) - windows
    with tempfile.TemporaryDirectory(dir=_scratch()) as folder:
        limit = shared_least(data, starts[first], lengths[first], least, SPAN, Path(folder))
    bucket, rows, done = table.column("bucket")[0].as_py(), [], 0
    for pack, n in zip(packs, counts, strict=True):
        mine = of[done : done + n]
        values, string = limit[_spread(base[mine], windows[mine])], np.repeat(np.arange(n), windows[mine])
        begin = np.flatnonzero(np.concatenate(([True], (values[1:] != values[:-1]) | (string[1:] != string[:-1]))))
        rows.append((bucket, pack, _pack_z(values[begin], np.diff(np.append(begin, len(values))).astype(np.uint8))))
        done += n
    return _rows(rows)


_VERDICT = pa.schema([("doc_id", pa.int64()), ("text_key", pa.string()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("spans", pa.list_(pa.int64()))])


def _apply(table: pa.Table, told: pa.Table) -> pa.Table:
    """Mark the windows whose least document is a smaller one, and cut their bytes out."""
    if not len(table):
        return _VERDICT.empty_table()
    pack, place = Pack.of(table, pieces=False), np.empty(0, np.int64)
    if len(told):
        said = sorted(zip(told.column("bucket").to_pylist(), told.column("body").to_pylist(), strict=True))
        steps, runs, of, size = _unpack_z(said[0][1], np.int64, np.uint8, np.int32, np.uint8)
        limits = []
        for _, body in said[1:]:
            values, n = _unpack_z(body, np.int64, np.uint8)
            limits.append(np.repeat(values, n.astype(np.int64)))
        limit, start = np.concatenate(limits), np.cumsum(steps)
        runs, size = runs.astype(np.int64), size.astype(np.int64)
        doc = np.searchsorted(pack.offsets, start, side="right") - 1
        lost = limit[_spread((np.cumsum(size) - size)[of], runs)] < np.repeat(pack.ids[doc], runs)
        place = _spread(start, runs)[lost]
    # a byte goes if one of the last runs that begin before its end does
    begun = np.zeros(len(pack.data) + SPAN, dtype=np.int32)
    begun[place + SPAN] = 1
    np.cumsum(begun, out=begun)
    gone = begun[SPAN:] > begun[: len(pack.data)]
    out: list[tuple] = []
    for d, doc in enumerate(pack.ids.tolist()):
        raw, lose = pack.raw(d), gone[pack.offsets[d] : pack.offsets[d + 1]]
        edge = np.flatnonzero(np.diff(np.concatenate(([0], lose.view(np.int8), [0]))))
        whole = raw.tobytes()
        kept = raw[~lose].tobytes() if len(edge) else whole
        out.append((doc, hashlib.sha256(whole).hexdigest(), int(lose.sum()), len(edge) // 2, hashlib.sha256(kept).hexdigest(), edge.tolist()))
    return pa.Table.from_arrays([pa.array([r[k] for r in out], f.type) for k, f in enumerate(_VERDICT)], schema=_VERDICT)


def repeated_spans(docs: DataFrame, hot: int = HOT) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans) for each row of ``docs`` (doc_id, text, ...).

    A byte goes when a run of ``SPAN`` bytes over it also starts in a document with a smaller doc_id; ``spans``
    has begin and end of each maximal removed run, flat.  Texts that are the same byte for byte are judged once: the row
    with the least doc_id stands for them, the others lose all they have if it is ``SPAN`` bytes or more.
    Null text counts as empty.  A null doc_id is neither smaller nor larger than any: such rows lose nothing and
    cost nobody anything.  Rows that repeat a doc_id are judged each by its own text; extra columns are
    not read; no documents give no rows.  ``hot``: from how many documents on the runs of an anchor are dealt one by one; it changes no row.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    keys = materialise(docs.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.sha2("text", 256).alias("text_key")), "keys")
    firsts = keys.where("doc_id is not null").groupBy("text_key").agg(F.min("doc_id").alias("first"))
    placed = materialise(keys.join(firsts, "text_key", "left"), "placed")
    own = placed.where(f"doc_id = first and n_bytes >= {SPAN}")
    total = own.agg(F.coalesce(F.sum("n_bytes"), F.lit(0))).first()[0]
    bits = max(4, int(total // BUCKET + 1).bit_length())
    heads = materialise(own.select("doc_id").distinct(), "heads")
    texts = docs.where(F.octet_length("text") >= SPAN).join(broadcast_if_small(heads), "doc_id", "left_semi")
    packs = materialise(texts.mapInArrow(_packs, "pack long, body binary"), "packs", compression="none")
    offers = packs.mapInArrow(lambda it: _offer(it, bits), _PACKED)
    # a bucket's work outweighs its bytes, so its exchange has a number of partitions of its own
    tasks = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1 << (bits - 1))
    replies = materialise(offers.groupBy("bucket").applyInArrow(lambda t: _answer(t, hot), _PACKED), "replies")
    by_pack = packs.groupBy("pack")
    sent = by_pack.cogroup(replies.groupBy("pack")).applyInArrow(lambda t, r: _send(t, r, bits), _PACKED)
    judged = materialise(sent.repartition(tasks, "bucket").groupBy("bucket").applyInArrow(_judge, _PACKED), "judged")
    told = by_pack.cogroup(judged.groupBy("pack")).applyInArrow(_apply, "doc_id long, text_key string, n_removed long, n_spans long, kept_sha256 string, spans array<long>")
    found = materialise(told.dropDuplicates(["doc_id", "text_key"]), "found")
    for done in (packs, replies, judged, heads, keys):
        drop_table(done)
    out = placed.join(found, ["doc_id", "text_key"], "left")
    copy = F.col("doc_id").isNotNull() & (F.col("doc_id") > F.col("first")) & (F.col("n_bytes") >= SPAN)
    pick = lambda whole, name, none: F.when(copy, whole).otherwise(F.coalesce(name, none)).alias(name)
    return out.select(
        "doc_id", "n_bytes", pick(F.col("n_bytes"), "n_removed", F.lit(0).cast("long")), pick(F.lit(1).cast("long"), "n_spans", F.lit(0).cast("long")),
        pick(F.sha2(F.lit(""), 256), "kept_sha256", F.col("text_key")), pick(F.array(F.lit(0).cast("long"), F.col("n_bytes")), "spans", F.array().cast("array<long>")),
    )


def without_spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, spans) to (doc_id, text) with the spans' bytes cut out; a character cut in two is dropped whole."""
    for batch in batches:
        texts = []
        for text, spans in zip(batch.column("text").to_pylist(), batch.column("spans").to_pylist(), strict=True):
            raw, at, left = (text or "").encode(), 0, []
            for a, b in zip(spans[::2], spans[1::2], strict=True):
                left.append(raw[at:a])
                at = b
            texts.append(b"".join([*left, raw[at:]]).decode(errors="ignore"))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])
