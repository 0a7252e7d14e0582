import hashlib
import random
import time
from itertools import combinations

import numpy as np
import pytest
from conftest_llm import EDGE, words

from fieldmr.llm import colwise, neardup
from fieldmr.llm import suffixdedup as sd
from fieldmr.llm.components import connected_components


def components_of(nodes, links):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    return {n: find(n) for n in nodes}


def brute_near(rows):
    sets = []
    for i, t in rows:
        w = words(t)
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    links = [(a, b) for a, b in combinations(range(len(rows)), 2) if sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    comp = components_of(range(len(rows)), links)
    least = {}
    for k, (i, _) in enumerate(rows):
        if i is not None:
            least[comp[k]] = min(i, least.get(comp[k], i))
    return sorted(((i, len(sets[k]), least.get(comp[k]) if sets[k] or i is not None else i) for k, (i, _) in enumerate(rows)), key=repr)


def test_near_duplicates_edge(edge):
    got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in neardup.near_duplicates(edge).collect()), key=repr)
    assert got == brute_near(EDGE)


def test_near_duplicates_empty(none):
    assert neardup.near_duplicates(none).count() == 0


def test_crowded_group(spark):
    """Many near copies of one text, changed more or less, some linked to nothing: blocks certify what stars leave open."""
    rng = random.Random(3)
    base = [f"t{i}" for i in range(120)]
    rows = []
    for i in range(160):
        w = list(base)
        for _ in range(rng.choice((0, 1, 1, 2, 3, 5, 8))):
            w[rng.randrange(len(w))] = f"n{rng.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=repr)
    assert got == brute_near(rows)


def test_blocks_split_a_crowd(spark, monkeypatch):
    monkeypatch.setattr(neardup, "CHUNK_SHINGLES", 300)
    test_crowded_group(spark)


def test_posterior_bounds_are_monotone():
    table = neardup.least_matches(0.75, 1e-6)
    assert [n for n, _ in table] == list(range(16, 129, 16)) and all(a[1] <= b[1] for a, b in zip(table, table[1:]))
    assert table[-1][1] < 0.75 * 128


def test_components(spark):
    rng = np.random.default_rng(5)
    links = [(int(a), int(b)) for a, b in rng.integers(0, 200, (150, 2))] + [(i, i + 1) for i in range(300, 360)] + [(None, 5)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    real = [(a, b) for a, b in links if a is not None and a != b]
    assert got == components_of({n for p in real for n in p}, real)


@pytest.mark.parametrize("block", [1, 5, 1 << 16])
def test_transform_and_prefixes(tmp_path, block):
    """Whatever the blocks that the files are read in, they hold the sorted suffixes of all strings."""
    rng = np.random.default_rng(block)
    for _ in range(20):
        n = int(rng.integers(1, 12))
        lengths = rng.integers(1, 14, n)
        starts = np.cumsum(lengths) - lengths
        data = rng.integers(97, 97 + int(rng.integers(1, 4)), lengths.sum()).astype(np.uint8)
        files = colwise.build(data, starts, lengths, tmp_path, block)
        bwt, lcp = (np.concatenate(x) for x in zip(*files.read(block), strict=True))
        texts = [bytes(data[a : a + k]) for a, k in zip(starts, lengths, strict=True)]
        want = sorted(([*texts[i][o:], i - 1000], i, o) for i in range(n) for o in range(len(texts[i]) + 1))
        code = {c: k + 1 for k, c in enumerate(sorted(set(data.tolist())))}
        assert bwt.tolist() == [code[texts[i][o - 1]] if o else 0 for _, i, o in want]
        for p in range(1, len(want)):
            a, b = want[p - 1][0][:-1], want[p][0][:-1]
            k = 0
            while k < min(len(a), len(b)) and a[k] == b[k]:
                k += 1
            assert lcp[p] == k
        owner, least = rng.integers(0, 100, n), {}
        for t, o in zip(texts, owner.tolist(), strict=True):
            for k in range(len(t) - 2):
                least[t[k : k + 3]] = min(o, least.get(t[k : k + 3], o))
        got = colwise.shared_least(data, starts, lengths, owner, 3, tmp_path, block)
        assert got.tolist() == [least[t[k : k + 3]] for t in texts for k in range(len(t) - 2)]


def test_ranks_of_a_block():
    rng = np.random.default_rng(2)
    for n in (1, 2, 300):
        bwt, lcp = rng.integers(0, 5, n).astype(np.uint8), rng.integers(0, 9, n).astype(np.uint8)
        ranks = colwise.Ranks(bwt)
        for c in range(256):
            assert ranks.order[ranks.begin[c] : ranks.stop[c]].tolist() == np.flatnonzero(bwt == c).tolist()
        assert ranks.here.tolist() == sorted(set(bwt.tolist())) and ranks.count.sum() == n
        after = ranks.order[ranks.stop[ranks.here] - 1] + 1
        assert colwise._least_after(lcp, after).tolist() == [min(lcp[a:].tolist(), default=255) for a in after]


def test_construction_time(tmp_path):
    """A round takes few times what it takes to sort its blocks by symbol (F1: CPU seconds of op9_suffix_dedup)."""
    rng = np.random.default_rng(3)
    words = [bytes(rng.integers(97, 123, k).astype(np.uint8)) + b" " for k in rng.integers(2, 10, 2000)]
    data = np.frombuffer(b"".join(words[k] for k in (2000 * rng.random(60_000) ** 2).astype(int)), np.uint8)
    n, size = 12_000, 60
    starts, lengths = rng.integers(0, len(data) - size, n), np.full(n, size)
    built, sorted_ = [], []
    for _ in range(6):
        begun = time.process_time()
        files = colwise.build(data, starts, lengths, tmp_path)
        built.append(time.process_time() - begun)
        bwt = np.concatenate([b for b, _ in files.read()])
        files.close()
        begun = time.process_time()
        for upto in range(n, n * size + 1, n):
            for a in range(0, upto, colwise.BLOCK):
                np.argsort(bwt[a : min(upto, a + colwise.BLOCK)], kind="stable")
        sorted_.append(time.process_time() - begun)
    assert min(built) < 4.5 * min(sorted_)


def brute_spans(rows, span=50):
    first = {}
    for i, t in rows:
        raw = (t or "").encode()
        for k in range(len(raw) - span + 1 if i is not None else 0):
            g = raw[k : k + span]
            first[g] = min(i, first.get(g, i))
    out = []
    for i, t in rows:
        raw = (t or "").encode()
        lose = np.zeros(len(raw) + 2, dtype=bool)
        for k in range(len(raw) - span + 1 if i is not None else 0):
            if first[raw[k : k + span]] < i:
                lose[k + 1 : k + span + 1] = True
        runs = int((lose[1:] & ~lose[:-1]).sum())
        kept = bytes(b for b, x in zip(raw, lose[1:], strict=False) if not x)
        out.append((i, len(raw), int(lose.sum()), runs, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=repr)


def test_repeated_spans_edge(edge):
    got = sorted(((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.repeated_spans(edge).collect()), key=repr)
    assert got == brute_spans(EDGE)


def test_repeated_spans_tables(spark, docs, none):
    assert sd.repeated_spans(none).count() == 0
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    got = sorted(((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.repeated_spans(docs).collect()), key=repr)
    assert got == brute_spans(rows)


def test_spans_can_be_cut_out(spark):
    passage = "this passage of text is long enough to be found again in another document, word by word"
    d = spark.createDataFrame([(1, passage), (2, f"before {passage} after")], "doc_id long, text string")
    spans = sd.repeated_spans(d).select("doc_id", "spans")
    got = {r.doc_id: r.text for r in d.join(spans, "doc_id").mapInArrow(sd.without_spans, "doc_id long, text string").collect()}
    assert got == {1: passage, 2: "before  after"}


def test_hot_anchors(spark):
    """One boilerplate line in very many texts of their own: its runs are dealt one by one, with the same rows."""
    rng = random.Random(7)
    line = "all rights reserved; see the terms of use for what may be done with this text, "
    rows = [(i, f"{rng.random()} {line * (1 + i % 2)}{rng.random()} " * (1 + i % 3)) for i in range(120)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for hot in (2, sd.HOT):
        got = sorted(((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.repeated_spans(docs, hot=hot).collect()), key=repr)
        assert got == brute_spans(rows)


def test_distinct_strings():
    data = np.frombuffer(b"abcabcabdab", np.uint8)
    starts, lengths = np.array([0, 3, 6, 0, 9]), np.array([3, 3, 3, 2, 2])
    of, first = sd.distinct(data, starts, lengths)
    texts = [bytes(data[a : a + n]) for a, n in zip(starts, lengths, strict=True)]
    assert [texts[first[k]] for k in of] == texts and len(first) == 3


@pytest.mark.parametrize("raws", [[], [b""], [b"a" * 49], [b"a" * 50], [b"ab" * 400, b"", b"b" * 50, b"ba" * 99], [bytes(range(256)) * 4] * 3, [b"xy" * 40000, b"y" * 60]])
def test_pieces_hold_every_run_once(raws):
    data, sizes = np.frombuffer(b"".join(raws), np.uint8), np.array([len(r) for r in raws], dtype=np.int64)
    offsets = np.concatenate(([0], np.cumsum(sizes)))
    doc, runs, distance = sd.anchored(data, offsets)
    counts = np.bincount(doc, minlength=len(raws))
    pack = sd.Pack(0, sd._pack_z(np.arange(len(raws)), sizes, data, counts, runs, distance))
    covered = [k for f, n in zip(pack.start.tolist(), pack.runs.tolist(), strict=True) for k in range(f, f + n)]
    assert covered == [offsets[d] + k for d, r in enumerate(raws) for k in range(len(r) - 49)] and (pack.runs <= sd.RUNS).all()
    assert all(f <= a <= f + sd.SPAN - sd.GRAM for f, a in zip(pack.start.tolist(), pack.anchor.tolist(), strict=True))
    # equal runs have equal anchors
    keys = {}
    for f, n, key in zip(pack.start.tolist(), pack.runs.tolist(), pack.keys(8).tolist(), strict=True):
        for k in range(f, f + n):
            assert keys.setdefault(bytes(data[k : k + sd.SPAN]), key) == key


def test_periodic_texts(spark):
    """Runs that hold their anchor's gram more than once, and texts of two letters, are matched wherever they stand."""
    rng = random.Random(11)
    bits = ["".join(rng.choice("ab") for _ in range(300)) for _ in range(3)]
    rows = [(i, rng.choice(bits)[k : k + 90] + rng.choice(["", "x", "yz"]) + "ab" * rng.randrange(60) + "abc" * rng.randrange(30)) for i, k in enumerate(rng.randrange(200) for _ in range(60))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.repeated_spans(docs).collect()), key=repr)
    assert got == brute_spans(rows)
