"""Benchmark decontamination by winnowing.

A window of ``n`` words has a fingerprint: the least hash of its runs of ``k`` words.  Equal windows have
equal fingerprints, so a join of the fingerprints of training and test windows misses no shared
span of ``n`` words or more.  A joined window is then extended to all its words: its hash over all ``n``
words and at last the words themselves must agree, so no hash decides a hit alone.

Test items go out in blocks of bounded size.  One block is the usual case; with more, documents are written with
a key per row, read once per block, and hits of all blocks meet per row.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textbytes as tb
from .runtime import materialise

N_WORDS = 10
GRAM = 5
#: Characters of item texts that are sent to executors at a time.
BLOCK_CHARS = 4 << 20

HITS = "row long, doc_id long, n_words long, spans array<struct<first:long,last:long>>, items array<string>"


class Index:
    """Windows of test items by length, as sorted arrays: fingerprints, window hashes and where in the items each window begins."""

    def __init__(self, items: list[tuple[str | None, str]], n: int, k: int):
        self.k, self.ids = k, [item_id for item_id, _ in items]
        raws = [text.encode() for _, text in items]
        offsets = np.concatenate(([0], np.cumsum([len(r) for r in raws], dtype=np.int64)))
        self.words = tb.Words(np.frombuffer(b"".join(raws), dtype=np.uint8), offsets, tb.ALNUM)
        sizes = np.minimum(n, self.words.per_doc)
        self.by_size: dict[int, tuple] = {}
        for size in np.unique(sizes[sizes > 0]).tolist():
            at, least, full = _windows(self.words, size, k)
            own = sizes[self.words.doc[at]] == size
            order = np.argsort(full[own], kind="stable")
            self.by_size[size] = (_sieve(least[own]), full[own][order], at[own][order])

    def found(self, text: bytes, places: np.ndarray, size: int) -> set:
        """Ids of the items that have these words at one of some places."""
        return {self.ids[self.words.doc[p]] for p in places.tolist() if self.words.text(p, p + size) == text}


def _sieve(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted fingerprints and a bit table that rules most others out."""
    least = np.unique(prints)
    table = np.zeros(1 << 20, dtype=bool)
    table[(least & np.uint64(0xFFFFF)).astype(np.int64)] = True
    return least, table


def _windows(words: tb.Words, size: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First word, fingerprint and full hash of all windows of ``size`` words inside one document."""
    inside = words.doc[: max(0, len(words) - size + 1)] == words.doc[size - 1 :]
    grams, _ = words.grams(min(k, size))
    least = tb.sliding_min(grams, size - min(k, size) + 1)
    full, _ = words.grams(size)
    at = np.flatnonzero(inside)
    return at, least[at], full[at]


def _member(x: np.ndarray, ordered: np.ndarray) -> np.ndarray:
    at = np.searchsorted(ordered, x)
    at[at == len(ordered)] = 0
    return ordered[at] == x


def _hits(words: tb.Words, index: Index) -> tuple[np.ndarray, dict[int, set]]:
    """Which words are hit, and the items found in each document."""
    hit = np.zeros(len(words) + 1, dtype=np.int32)
    items: dict[int, set] = defaultdict(set)
    for size, ((least, table), full, places) in index.by_size.items():
        k = min(index.k, size)
        if len(words) < size:
            continue
        prints = tb.sliding_min(words.grams(k)[0], size - k + 1)
        at = np.flatnonzero(table[(prints & np.uint64(0xFFFFF)).astype(np.int64)])
        at = at[_member(prints[at], least)] if len(at) else at
        at = at[words.doc[at] == words.doc[at + size - 1]]
        if not len(at):
            continue
        # the joined windows, extended: the hash of all words, then the words
        h = np.zeros(len(at), dtype=np.uint64)
        for t in range(size):
            h += words.hashes[at + t] * tb.gram_power(t)
        h = tb.mix64(h)
        low, high = np.searchsorted(full, h, side="left"), np.searchsorted(full, h, side="right")
        ok = high > low
        for i, a, b in zip(at[ok].tolist(), low[ok].tolist(), high[ok].tolist(), strict=True):
            ids = index.found(words.text(i, i + size), places[a:b], size)
            if ids:
                hit[i] += 1
                hit[i + size] -= 1
                items[int(words.doc[i])].update(ids)
    return np.cumsum(hit[:-1]) > 0, items


def _scan(batches: Iterator[pa.RecordBatch], shared: Broadcast) -> Iterator[pa.RecordBatch]:
    index: Index = shared.value
    span = pa.struct([("first", pa.int64()), ("last", pa.int64())])
    schema = pa.schema([("row", pa.int64()), ("doc_id", pa.int64()), ("n_words", pa.int64()), ("spans", pa.list_(span)), ("items", pa.list_(pa.string()))])
    for batch in batches:
        rows, ids = (batch.column(batch.schema.get_field_index(c)) for c in ("row", "doc_id"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            words = tb.Words(data, offsets, tb.ALNUM)
            hit, items = _hits(words, index)
            spans: list[list[dict]] = [[] for _ in range(j - i)]
            marked = np.flatnonzero(hit)
            for d in np.unique(words.doc[marked]).tolist():
                a, b = int(words.bounds[d]), int(words.bounds[d + 1])
                edge = np.flatnonzero(np.diff(np.concatenate(([0], hit[a:b].view(np.int8), [0]))))
                spans[d] = [{"first": int(x), "last": int(y) - 1} for x, y in zip(edge[::2], edge[1::2], strict=True)]
            found = [sorted(x for x in items.get(d, ()) if x is not None) for d in range(j - i)]
            yield pa.RecordBatch.from_arrays([rows.slice(i, j - i), ids.slice(i, j - i), pa.array(words.per_doc, pa.int64()), pa.array(spans, pa.list_(span)), pa.array(found, pa.list_(pa.string()))], schema=schema)


def _blocks(bench: DataFrame, chars: int) -> Iterator[list[tuple[str | None, str]]]:
    block, size = [], 0
    for item_id, text in bench.where("text is not null").toLocalIterator():
        block.append((item_id, text))
        size += len(text)
        if size >= chars:
            yield block
            block, size = [], 0
    yield block


def contamination(docs: DataFrame, bench: DataFrame, n: int = N_WORDS, k: int = GRAM, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """(doc_id, n_words, spans, items): runs of hit words (by position) and the ids of items that occur.

    ``docs``: (doc_id, text), ``bench``: (item_id, text); extra columns are not read.  Null and blank texts have no words, items
    without words no window.  A window of an item without an id is hit but not listed.  Repeated items count
    once, repeated documents give a row each.  With no items nothing is hit; no documents give no rows.
    Texts of any length are read whole.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    context = docs.sparkSession.sparkContext
    blocks = _blocks(bench.select(F.col("item_id").cast("string"), F.col("text").cast("string")), block_chars)
    block, following = next(blocks), next(blocks, None)
    if following is None:
        shared = context.broadcast(Index(block, n, k))
        return docs.select(F.lit(0).cast("long").alias("row"), "*").mapInArrow(lambda it: _scan(it, shared), HITS).drop("row")
    # ids may be null or repeat, so rows meet by a key that is written once and read by every scan
    docs = materialise(docs.select(F.monotonically_increasing_id().alias("row"), "*"), "rows")
    every = None
    while block is not None:
        shared = context.broadcast(Index(block, n, k))
        part = docs.mapInArrow(lambda it, shared=shared: _scan(it, shared), HITS)
        every = part if every is None else every.unionByName(part)
        block, following = following, next(blocks, None)
    met = every.groupBy("row", "doc_id", "n_words").agg(F.flatten(F.collect_list("spans")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    return met.select("doc_id", "n_words", merged("spans").alias("spans"), "items")


def merged(spans: str) -> Column:
    """Overlapping or touching runs as one, in order."""
    empty = F.lit(None).cast("array<struct<first:bigint,last:bigint>>")
    joined = lambda acc, s: F.when(
        (F.size(acc) > 0) & (F.element_at(acc, -1)["last"] + 1 >= s["first"]),
        F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.struct(F.element_at(acc, -1)["first"].alias("first"), F.greatest(F.element_at(acc, -1)["last"], s["last"]).alias("last")))),
    ).otherwise(F.concat(acc, F.array(s)))
    return F.aggregate(F.array_sort(spans), F.coalesce(empty, F.array().cast("array<struct<first:bigint,last:bigint>>")), joined)


def digest(hits: DataFrame) -> DataFrame:
    """The query's columns from the operator's spans and items."""
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda acc, s: acc + s["last"] - s["first"] + 1)
    return hits.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", F.array_sort("items")), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def _unhit(batches: Iterator[pa.RecordBatch], shared: Broadcast) -> Iterator[pa.RecordBatch]:
    index: Index = shared.value
    for batch in batches:
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            words = tb.Words(data, offsets, tb.ALNUM)
            hit, _ = _hits(words, index)
            keep = np.ones(j - i, dtype=bool)
            keep[words.doc[hit]] = False
            yield batch.slice(i, j - i).filter(pa.array(keep))


def clean(docs: DataFrame, bench: DataFrame, n: int = N_WORDS, k: int = GRAM, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows of ``docs``, with all their columns, in which no window of a test item occurs; no shuffle."""
    context = docs.sparkSession.sparkContext
    for block in _blocks(bench.select(F.col("item_id").cast("string"), F.col("text").cast("string")), block_chars):
        shared = context.broadcast(Index(block, n, k))
        docs = docs.mapInArrow(lambda it, shared=shared: _unhit(it, shared), docs.schema)
    return docs
