import hashlib
import re
import zlib

import numpy as np
from conftest_llm import EDGE, LOWER, words

from fieldmr.llm import decontam, langid, linefreq, mixing, toxicity

ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def brute_hits(rows, items):
    wins = {}
    for item, text in items:
        w = ALNUM.findall((text or "").translate(LOWER))
        n = min(10, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            wins.setdefault(tuple(w[i : i + n]), set()).add(item)
    out = []
    for i, text in rows:
        w, hit, ids = ALNUM.findall((text or "").translate(LOWER)), set(), set()
        for n in {len(k) for k in wins}:
            for k in range(len(w) - n + 1):
                found = wins.get(tuple(w[k : k + n]))
                if found:
                    hit.update(range(k, k + n))
                    ids |= found
        names = sorted(str(x) for x in ids if x is not None)
        out.append((i, len(w), len(hit), len(names), hashlib.sha256(",".join(names).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=repr)


ITEMS = [(1, "quick brown fox jumps over the lazy dog again and again until"), (2, "one"), (3, None), (4, "..."), (5, "a b c d e f g h i j"), (None, "four"), (6, "lazy dog"), (2, "one")]


def test_decontamination(spark, edge, none):
    bench = spark.createDataFrame([(i, t, "x") for i, t in ITEMS], "item_id long, text string, lang string")
    want = brute_hits(EDGE, ITEMS)
    for chars in (decontam.BLOCK_CHARS, 20):
        got = decontam.digest(decontam.contamination(edge, bench, block_chars=chars)).collect()
        distinct = sorted({tuple(r) for r in got}, key=repr)
        assert distinct == sorted(set(want), key=repr)
    kept = decontam.clean(edge, bench)
    assert kept.columns == edge.columns
    assert sorted((r.doc_id or -1 for r in kept.collect())) == sorted((w[0] or -1 for w in want if not w[5]))
    assert decontam.contamination(none, bench).count() == 0
    assert decontam.contamination(edge, bench.limit(0)).where("size(spans) > 0").count() == 0


def test_decontamination_in_blocks_keeps_a_row_each(spark, edge):
    """Repeated rows, and documents without an id that have as many words, stay apart whatever the size of a block."""
    bench = spark.createDataFrame(ITEMS, "item_id long, text string")
    more = spark.createDataFrame([(None, "four"), (None, "one"), (30, "one lazy dog"), (30, "two lazy dog"), (30, "one lazy dog")], "doc_id long, text string")
    rows = edge.select("doc_id", "text").unionByName(more)
    want = brute_hits([tuple(r) for r in rows.collect()], ITEMS)
    for chars in (decontam.BLOCK_CHARS, 20, 1):
        got = decontam.contamination(rows, bench, block_chars=chars)
        assert got.columns == ["doc_id", "n_words", "spans", "items"]
        assert sorted((tuple(r) for r in decontam.digest(got).collect()), key=repr) == want


def brute_measures(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    many = {p for i, g in enumerate(grams) if grams.count(g) > 1 for p in (i, i + 1, i + 2)}
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(many)


def test_line_measures(spark, edge, none):
    odd = [(20, "a\na\n b\n\n \na"), (21, "x y z x y z"), (22, "x x x x"), (23, "\x0b#| *\x0c"), (24, "p q r s p q r"), (25, " \x85 word\xa0joined  ")]
    rows = [(i, t) for i, t in EDGE if len(t or "") < 6000] + odd
    d = spark.createDataFrame([(i, t, "h") for i, t in rows], "doc_id long, text string, source string")
    got = sorted(((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in linefreq.line_frequency(d).collect()), key=repr)
    assert got == sorted(((i, *brute_measures(t)) for i, t in rows), key=repr)
    assert linefreq.line_frequency(edge).count() == len(EDGE)
    assert linefreq.line_frequency(none).count() == 0


def test_frequent_lines_deplete(spark):
    name = lambda n: "".join(chr(97 + int(c)) for c in str(n))
    body = lambda i: "\n".join(" ".join(f"u{name(i)}v{name(k)}w{name(j)}" for j in range(10)) for k in range(8))
    banner = "Same Banner 123 of this   host " + " ".join(f"b{name(i)}" for i in range(60))
    rows = [(i, body(i), "h") for i in range(60)] + [(100 + i, f"{banner}\nown words {name(i)} only", "h") for i in range(40)] + [(200, banner, "other")]
    got = {r.doc_id: (r.kept, r.n_removed_words) for r in linefreq.line_frequency(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert all(got[i] == (True, 0) for i in range(60))
    assert all(got[100 + i] == (False, 66) for i in range(40))
    assert got[200] == (True, 0)


def test_frequent_lines_of_large_hosts(spark):
    """Beyond a fixed number of texts a line is frequent whatever its share; joined rows give what compared ones give."""
    name = lambda n: "".join(chr(97 + int(c)) for c in str(n))
    own = lambda i: " ".join(f"o{name(i)}w{name(j)}" for j in range(70))
    rows = [(i, f"{own(i)}\nshared by few of very many" if i % 20 == 0 else own(i), "big") for i in range(700)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    for most, removed in ((linefreq.MOST_TEXTS, 0), (30, 35 * 6)):
        got = [sorted(tuple(r) for r in linefreq.line_frequency(docs, most=most, host_lines=n).collect()) for n in (linefreq.HOST_LINES, 0)]
        assert got[0] == got[1] and sum(r[8] for r in got[0]) == removed and all(r[7] for r in got[0])


def test_frequent_lines_are_removed_from_the_text(spark):
    """Documents with few words in frequent lines are kept without these; other lines, blank ones too, stay as they were and in order."""
    name = lambda n: "".join(chr(97 + int(c)) for c in str(n))
    own = lambda i: " ".join(f"U{name(i)}v{name(k)}" for k in range(60))
    banner, foot = "Page 7 of  this HOST", "\tall rights reserved "
    text = lambda i: f"{banner.replace('7', str(i))}\n{own(i)} \n\n  {foot}\nlast  line {name(i)}\n"
    rows = [(i, text(i), "h") for i in range(30)] + [(0, text(0), "h"), (None, text(1), "h"), (50, text(50), "other"), (51, None, "h"), (52, banner, "h"), (53, banner, None)]
    got = linefreq.line_frequency(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    want = [(i, f"{own(i)} \n\nlast  line {name(i)}\n", True, 8) for i in [*range(30), 0]]
    want += [(None, f"{own(1)} \n\nlast  line {name(1)}\n", True, 8), (50, text(50), True, 0), (51, "", False, 0), (52, "", False, 5), (53, banner, False, 0)]
    assert sorted(((r.doc_id, r.text, r.kept, r.n_removed_words) for r in got), key=repr) == sorted(want, key=repr)


def test_language(spark, docs, edge, none):
    rows = langid.identify_languages(docs).collect()
    truth = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    held = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    assert np.mean([r.lang_pred == truth[r.doc_id] for r in held]) > 0.9
    assert all(0 <= r.score <= 1 for r in rows)
    said = langid.identify_languages(edge).collect()
    assert len(said) == len(EDGE) and {r.lang_pred for r in said if r.doc_id in (4, 5, 6)} == {"und"}
    assert langid.identify_languages(none).count() == 0


def test_ordinal_fit_recovers_order():
    rng = np.random.default_rng(2)
    x = rng.random((2000, 3)) < 0.3
    score = x @ np.array([3.0, 1.0, 0.0]) + rng.logistic(size=2000)
    grade = (score > 1.5).astype(int) + (score > 3.5)
    row, col = np.nonzero(x)
    w, cuts = toxicity.fit_ordinal(row, col, 3, grade, np.ones(2000), 3)
    assert abs(w[0] - 3) < 0.4 and abs(w[1] - 1) < 0.4 and abs(w[2]) < 0.4
    assert abs(cuts[0] - 1.5) < 0.3 and abs(cuts[1] - 3.5) < 0.4


def test_toxicity(spark, edge, none):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    rated = {r.doc_id: r for r in toxicity.rate_toxicity(docs, labels).collect()}
    truth = {r.doc_id: r.toxic for r in labels.collect()}
    good = [rated[i].severity for i, t in truth.items() if t == 0]
    bad = [rated[i].severity for i, t in truth.items() if t == 1]
    assert np.mean(bad) > np.mean(good) + 0.5
    assert sum(rated[i].toxic for i, t in truth.items() if t == 0) <= 0.01 * len(good)
    assert all(abs(r.severity - (r.p_mild + 2 * r.p_severe)) < 1e-9 for r in rated.values())
    kept = toxicity.without_toxic(docs, labels)
    assert kept.columns == docs.columns and kept.count() == sum(not r.toxic for r in rated.values())
    assert toxicity.rate_toxicity(edge, labels.limit(0)).where("toxic").count() == 0
    assert toxicity.rate_toxicity(none, labels).count() == 0


def test_mixing_meets_targets(spark, edge, none):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    rows = mixing.mix_rates(docs, labels).collect()
    p, n, r = (np.array([getattr(x, k) for x in rows]) for k in ("posterior", "n_tokens", "rate"))
    assert (r >= 0).all() and np.allclose(p.sum(axis=1), 1)
    total = (p * (n * r)[:, None]).sum(axis=0)
    assert abs(total[1] / total.sum() - 0.95) < 1e-3
    assert abs(total[1] / (p * n[:, None]).sum(axis=0)[1] - 1) < 1e-3
    free = mixing.mix_rates(docs, labels, targets={"0": 0.5, "1": 0.5}, anchor=None).collect()
    r2 = np.array([x.rate for x in free])
    share = (p * (n * r2)[:, None]).sum(axis=0) / n.sum()
    assert np.allclose(share, 0.5, atol=1e-3)
    out = mixing.mixed(docs, labels)
    assert out.columns == docs.columns
    assert out.count() == sum(x.copies for x in rows)
    assert mixing.mix_rates(edge, labels.limit(0)).where("rate <> 1").count() == 0
    assert mixing.mix_rates(none, labels).count() == 0


def test_native_operators_run_no_python(spark, docs):
    labels = spark.read.parquet("/root/testdata/sf0.001/labels.parquet")
    for df in (linefreq.line_frequency(docs), mixing.mix_rates(docs, labels), mixing.mixed(docs, labels)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Arrow|Pandas", plan)
