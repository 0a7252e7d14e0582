"""Near-duplicate documents: banded minwise candidates, sequential Bayesian verification, exact confirmation.

Copies (documents with one and the same shingle set) fold into a class first, so a
group of any number of copies costs one signature in what follows.  Among class representatives:

1. every band of a signature is a bucket; each bucket's members are compared with one leader,
   chosen by a hash per band, and not with each other;
2. a pair's signatures are read in batches; after each batch it is dropped when the posterior
   probability that its similarity reaches the threshold falls below ``miss``;
3. survivors are confirmed on full shingle sets, and confirmed links give components;
4. members of a bucket that are still in different components are compared across components, as queries
   against blocks of bounded size with exact counts, which loses no link and emits no pairs but links.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from math import lgamma

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textbytes as tb
from .components import connected_components
from .runtime import broadcast_if_small, materialise

K = 5
PERCENT = 75
HASHES, ROWS = 128, 4
BANDS = HASHES // ROWS
#: Similarities below the threshold are given up when the chance that they reach it is under this.
MISS = 1e-6
#: Shingles of the documents in one chunk of a crowded bucket, about.
CHUNK_SHINGLES = 200_000
#: Hash functions compared between two looks at the posterior.
BATCH = 16

_SEEDS = np.random.default_rng(20240501)
_A = (_SEEDS.integers(0, 1 << 32, HASHES, dtype=np.uint64) | np.uint64(1)).astype(np.uint32)
_B = _SEEDS.integers(0, 1 << 32, HASHES, dtype=np.uint64).astype(np.uint32)
#: Shingles mapped at a time, so that the maps of one piece stay in cache.
_PIECE = 1 << 11


def signature(shingles: np.ndarray) -> np.ndarray:
    """Minima of ``HASHES`` affine maps of the folded 64-bit shingle hashes."""
    h = (shingles >> np.uint64(32)).astype(np.uint32) ^ shingles.astype(np.uint32)
    out = np.full(HASHES, 0xFFFFFFFF, dtype=np.uint32)
    for at in range(0, len(h), _PIECE):
        maps = h[None, at : at + _PIECE] * _A[:, None]
        maps += _B[:, None]
        np.minimum(out, maps.min(axis=1), out=out)
    return out


def band_keys(sig: np.ndarray) -> np.ndarray:
    rows = sig.reshape(BANDS, ROWS).astype(np.uint64)
    key = np.arange(1, BANDS + 1, dtype=np.uint64) << np.uint64(40)
    for r in range(ROWS):
        key = tb.mix64(key + rows[:, r])
    return key.view(np.int64)


_SKETCH = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("set_key", pa.string()), ("bands", pa.list_(pa.int64())), ("sig", pa.binary())])


def _sketch(batches: Iterator[pa.RecordBatch], with_signature: bool) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column(batch.schema.get_field_index("doc_id"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            sets = tb.shingle_sets(tb.Words(data, offsets, tb.NON_SPACE), K)
            keys, bands, sigs = [], [], []
            for s in sets:
                if not len(s):
                    keys.append(None), bands.append(None), sigs.append(None)
                    continue
                x, y = tb.mix64(s).sum(), tb.mix64(s ^ np.uint64(0x5851F42D4C957F2D)).sum()
                keys.append(f"{int(x):016x}{int(y):016x}")
                if with_signature:
                    sig = signature(s)
                    bands.append(band_keys(sig)), sigs.append(sig.tobytes())
                else:
                    bands.append(None), sigs.append(None)
            yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array([len(s) for s in sets], pa.int64()), pa.array(keys, pa.string()), pa.array(bands, pa.list_(pa.int64())), pa.array(sigs, pa.binary())], schema=_SKETCH)


def sketches(docs: DataFrame, signatures: bool = True) -> DataFrame:
    """(doc_id, n_shingles, set_key, bands, sig) of each document; the last three null for an empty set."""
    return docs.select("doc_id", "text").mapInArrow(lambda it: _sketch(it, signatures), "doc_id long, n_shingles long, set_key string, bands array<long>, sig binary")


@lru_cache(maxsize=None)
def least_matches(threshold: float, miss: float, hashes: int = HASHES, batch: int = BATCH) -> tuple[tuple[int, int], ...]:
    """(n, m): after n compared hashes a pair with under m matches is given up.

    With a uniform prior the posterior after m of n matches is Beta(m + 1, n - m + 1);
    its tail above the threshold is integrated numerically.
    """
    grid = np.linspace(threshold, 1, 4001)
    mid = (grid[1:] + grid[:-1]) / 2
    width = grid[1] - grid[0]
    table = []
    for n in range(batch, hashes + 1, batch):
        for m in range(n + 1):
            norm = lgamma(n + 2) - lgamma(m + 1) - lgamma(n - m + 1)
            tail = float(np.exp(norm + m * np.log(mid) + (n - m) * np.log1p(-mid)).sum() * width)
            if tail >= miss:
                table.append((n, m))
                break
    return tuple(table)


def _plausible(batches: Iterator[pa.RecordBatch], threshold: float, miss: float) -> Iterator[pa.RecordBatch]:
    """Pairs (a, b, sig_a, sig_b) that no look at the posterior gives up, as (a, b, matches)."""
    looks = least_matches(threshold, miss)
    for batch in batches:
        col = {f.name: batch.column(i) for i, f in enumerate(batch.schema)}
        x = np.frombuffer(b"".join(col["sig_a"].to_pylist()), dtype=np.uint32).reshape(-1, HASHES)
        y = np.frombuffer(b"".join(col["sig_b"].to_pylist()), dtype=np.uint32).reshape(-1, HASHES)
        alive, matches, done = np.arange(len(x)), np.zeros(len(x), dtype=np.int64), 0
        for n, m in looks:
            matches[alive] += (x[alive, done:n] == y[alive, done:n]).sum(axis=1)
            alive = alive[matches[alive] >= m]
            done = n
        take = pa.array(alive)
        yield pa.RecordBatch.from_arrays([col["a"].take(take), col["b"].take(take), pa.array(matches[alive])], names=["a", "b", "matches"])


def plausible(pairs: DataFrame, sigs: DataFrame, threshold: float, miss: float) -> DataFrame:
    left, right = (sigs.select(F.col("rep").alias(k), F.col("sig").alias(f"sig_{k}")) for k in "ab")
    return pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "sig_a", "sig_b").mapInArrow(lambda it: _plausible(it, threshold, miss), "a long, b long, matches long")


def _full_sets(batches: Iterator[pa.RecordBatch], packed: bool) -> Iterator[pa.RecordBatch]:
    """(rep, members): whole shingle sets, packed as bytes or as an array."""
    for batch in batches:
        ids = batch.column(batch.schema.get_field_index("rep"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            sets = tb.shingle_sets(tb.Words(data, offsets, tb.NON_SPACE), K)
            yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array([s.tobytes() for s in sets], pa.binary()) if packed else pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], names=["rep", "members"])


def _confirm(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        col = {f.name: batch.column(i) for i, f in enumerate(batch.schema)}
        keep = []
        for p, q in zip(col["set_a"], col["set_b"], strict=True):
            x, y = np.frombuffer(p.as_buffer(), dtype=np.uint64), np.frombuffer(q.as_buffer(), dtype=np.uint64)
            small, big = (x, y) if len(x) <= len(y) else (y, x)
            at = np.searchsorted(big, small)
            at[at == len(big)] = 0
            both = int((big[at] == small).sum()) if len(big) else 0
            keep.append(both > 0 and 100 * both >= percent * (len(x) + len(y) - both))
        mask = pa.array(keep, pa.bool_())
        yield pa.RecordBatch.from_arrays([col["a"].filter(mask), col["b"].filter(mask)], names=["a", "b"])


def confirmed(pairs: DataFrame, docs: DataFrame, percent: int) -> DataFrame:
    """The pairs whose full shingle sets are similar enough; only documents in a pair are shingled a second time."""
    ends = materialise(pairs.select(F.col("a").alias("rep")).union(pairs.select("b")).distinct(), "ends")
    texts = docs.select(F.col("doc_id").alias("rep"), "text")
    sets = texts.join(broadcast_if_small(ends), "rep", "left_semi").mapInArrow(lambda it: _full_sets(it, True), "rep long, members binary")
    left, right = (sets.select(F.col("rep").alias(k), F.col("members").alias(f"set_{k}")) for k in "ab")
    return pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "set_a", "set_b").mapInArrow(lambda it: _confirm(it, percent), "a long, b long")


def _met(table: pa.Table, percent: int) -> pa.Table:
    """Of one block: links between its query documents and its members, as few as join their components."""
    role = np.array(table.column("query").to_pylist(), dtype=bool)
    reps, components = table.column("rep").to_numpy(), table.column("component").to_numpy()
    sets = [np.frombuffer(m.as_buffer(), dtype=np.uint64) for m in table.column("members")]
    sizes = np.array([len(m) for m in sets], dtype=np.int64)
    members = np.flatnonzero(~role)
    links: list[tuple[int, int]] = []
    if len(members) and role.any():
        # postings of the members, then one pass over them per query document
        keys = np.concatenate([sets[i] for i in members])
        order = np.argsort(keys, kind="stable")
        keys, owner = keys[order], np.repeat(np.arange(len(members)), sizes[members])[order]
        root: dict[int, int] = {}

        def find(x: int) -> int:
            while root.setdefault(x, x) != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        for i in np.flatnonzero(role).tolist():
            low, high = np.searchsorted(keys, sets[i], side="left"), np.searchsorted(keys, sets[i], side="right")
            n = high - low
            at = np.repeat(low - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            both = np.bincount(owner[at], minlength=len(members))
            alike = (100 * both >= percent * (sizes[i] + sizes[members] - both)) & (both > 0)
            for k in members[np.flatnonzero(alike)].tolist():
                x, y = find(int(components[i])), find(int(components[k]))
                if x != y:
                    root[x] = y
                    links.append((min(int(reps[i]), int(reps[k])), max(int(reps[i]), int(reps[k]))))
    return pa.table({"a": pa.array([x for x, _ in links], pa.int64()), "b": pa.array([y for _, y in links], pa.int64())})


def _across(docs: DataFrame, open_: DataFrame, percent: int) -> DataFrame:
    """Links between components that share a bucket; ``open_``: (main, rep, component, apart).

    The documents ``apart`` from the main component of a bucket are queries against all documents of buckets with that
    main component.  Both sides are cut into chunks of bounded size, a block is one chunk of each, and a
    block counts shared shingles exactly.  Only links that join components leave it.
    """
    reps = materialise(open_.select("rep").distinct(), "open")
    texts = docs.select(F.col("doc_id").alias("rep"), "text").join(broadcast_if_small(reps), "rep", "left_semi")
    sets = materialise(texts.mapInArrow(lambda it: _full_sets(it, True), "rep long, members binary"), "sets")
    crowd = materialise(open_.join(sets, "rep"), "crowd")
    parts = crowd.groupBy("main").agg(F.ceil(F.sum(F.octet_length("members")) / F.lit(8 * CHUNK_SHINGLES)).cast("int").alias("parts"))
    # blocks of a crowd that a third of all documents belong to must not follow its single key
    dealt = crowd.join(broadcast_if_small(materialise(parts, "parts")), "main").withColumn("own", F.pmod(F.xxhash64("rep"), "parts").cast("int"))
    others = F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("other")
    member = dealt.select("main", "rep", "component", "members", F.lit(False).alias("query"), F.col("own").alias("j"), others).withColumnRenamed("other", "i")
    query = dealt.where("apart").select("main", "rep", "component", "members", F.lit(True).alias("query"), F.col("own").alias("i"), others).withColumnRenamed("other", "j")
    return member.unionByName(query).repartition("main", "i", "j").groupBy("main", "i", "j").applyInArrow(lambda t: _met(t, percent), "a long, b long")


def near_duplicates(docs: DataFrame, percent: int = PERCENT, miss: float = MISS) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of ``docs`` (doc_id, text, ...).

    Null or blank text: an empty set, linked with nothing, its own component.  Null doc_id: counted and
    linked, but never a representative; component_id is its group's, null if the group has no id, and kept is false.
    Rows that repeat a doc_id follow their own text, and are kept or dropped alike; classes with the same smallest id are one.
    Very long texts are shingled whole.  Extra columns are not read.  No rows give no rows.
    """
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    table = materialise(sketches(docs), "sketches")
    # bands and signature are functions of the set, so any member's will do
    reps = table.where("set_key is not null and doc_id is not null").groupBy("set_key").agg(F.min("doc_id").alias("rep"))
    reps = materialise(reps, "classes")
    own = (table["set_key"] == reps["set_key"]) & (table["doc_id"] == reps["rep"])
    sigs = table.join(reps, own, "left_semi").dropDuplicates(["doc_id", "set_key"]).select(F.col("doc_id").alias("rep"), "n_shingles", "bands", "sig")
    sigs = materialise(sigs, "signatures")

    band = sigs.select("rep", F.explode("bands").alias("bucket"))
    # the leader of a bucket differs from band to band
    chosen = F.min_by("rep", F.xxhash64("bucket", "rep")).alias("leader")
    buckets = materialise(band.groupBy("bucket").agg(F.count("*").alias("n"), chosen).where("n > 1"), "buckets")
    stars = band.join(buckets, "bucket").where("rep <> leader").select(F.least("rep", "leader").alias("a"), F.greatest("rep", "leader").alias("b")).distinct()
    links = materialise(confirmed(materialise(plausible(stars, sigs, percent / 100, miss), "plausible"), docs, percent), "links")
    components = connected_components(links)

    # buckets that still hold more than one component: compare across components
    crowd = buckets.where("n > 2")
    placed = band.join(crowd, "bucket").join(components.withColumnRenamed("node", "rep"), "rep", "left").select("bucket", "rep", F.coalesce("component", "rep").alias("component"))
    placed = materialise(placed, "placed")
    sizes = placed.groupBy("bucket", "component").agg(F.count("*").alias("size"))
    main = sizes.groupBy("bucket").agg(F.max_by("component", F.struct("size", "component")).alias("main"), F.count("*").alias("parts")).where("parts > 1").select("bucket", "main")
    open_ = placed.join(main, "bucket").select("main", "rep", "component", (F.col("component") != F.col("main")).alias("apart")).distinct()
    more = materialise(_across(docs, materialise(open_, "open"), percent), "links")
    if more.limit(1).count():
        components = connected_components(links.unionByName(more))
    of = reps.join(components.withColumnRenamed("node", "rep"), "rep", "left").select("set_key", F.coalesce("component", "rep").alias("component"))
    # documents of a class are its own rows; blank ones stand alone
    linked = table.where("set_key is not null").select("doc_id", "n_shingles", "set_key").join(of, "set_key", "left").select("doc_id", "n_shingles", "component")
    blank = table.where("set_key is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component"))
    out = linked.unionByName(blank).withColumnRenamed("component", "component_id")
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)))
