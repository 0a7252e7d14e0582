"""What pages show, and plain versions of the learned operators: the same model applied row by row in Python."""

from math import exp, log, pi

import numpy as np
import pytest
import zstandard
from conftest_llm import EDGE

from fieldmr.llm import htmltext, langid, mixing, toxicity
from fieldmr.llm import textbytes as tb
from fieldmr.llm.runtime import read_table

SF = "/root/testdata/sf0.001"


def test_forms_drawings_and_formulas_show():
    show = lambda html: htmltext.render(html)[0]
    assert show("<p>Pick <select><option>red<option selected>blue</select> now</p>") == "Pick blue now"
    assert show("<p>Pick <select><optgroup label=x><option>red<option>blue</optgroup></select> now</p>") == "Pick red now"
    assert show("<select multiple><option>red</option><option>blue</option></select>") == "red\nblue"
    assert show("<p>a <svg><title>t</title><defs><text>no</text></defs><text>one</text><text>two</text></svg> b</p>") == "a one two b"
    assert show("<p><math><mi>x</mi><mo>=</mo><mn>2</mn><annotation>tex</annotation></math></p>") == "x=2"
    assert show("<p>a<script>no</script><noscript>no</noscript><p hidden>no<p style='display: none'>no<p>b") == "a\n\nb"


@pytest.mark.parametrize("depth", [10, 160, 3000])
def test_any_depth_keeps_rules(depth):
    text = htmltext.render("<div>" * depth + "<p hidden>secret</p><ul><li>a<li>b</ul><table><tr><td>c<td>d</table>")[0]
    assert text == "- a\n- b\n\nc  d"
    assert htmltext.render("<table><tr><td>" * depth + "x")[0] == "x"
    assert htmltext.render("<b><i>" * depth + "x" + "</i></b>" * depth + "<p>y")[0] == "x\n\ny"


def test_spans_of_cells():
    html = "<table><tr><td rowspan=2>a<td colspan=300>b<td>c</tr><tr><td>d</table>"
    first, second = htmltext.render(html)[0].split("\n")
    assert first.startswith("a  b") and first.endswith("c") and second.strip() == "d" and second.index("d") == first.index("b")


def test_no_pages(spark):
    none = spark.createDataFrame([], "page_id long, url string, html string, text string")
    assert htmltext.page_text(none).count() == 0
    rows = [(1, "u", None, "x"), (None, None, "", "x"), (2, "u", "<p>a", "x"), (2, "u", "<p>a", "x")]
    got = htmltext.page_text(spark.createDataFrame(rows, "page_id long, url string, html string, text string")).collect()
    assert sorted(((r.page_id, r.text, r.n_lines) for r in got), key=repr) == sorted([(1, "", 0), (None, "", 0), (2, "a", 1), (2, "a", 1)], key=repr)


def test_languages_row_by_row(spark, docs):
    samples = langid.dictionaries(docs.select("doc_id", "text", "lang"))
    want = {}
    for r in docs.collect():
        raw, best = (r.text or "").lower().encode(), []
        for k, (lang, sample) in enumerate(samples.items()):
            one = zstandard.ZstdCompressor(level=langid.LEVEL, dict_data=zstandard.ZstdCompressionDict(sample, dict_type=zstandard.DICT_TYPE_RAWCONTENT), write_checksum=False, write_content_size=False)
            best.append((sum(len(one.compress(raw[i : i + langid.CHUNK])) for i in range(0, len(raw), langid.CHUNK)), k, lang))
        want[r.doc_id] = min(best)[2] if any(c.isalpha() for c in r.text or "") else "und"
    got = {r.doc_id: r.lang_pred for r in langid.identify_languages(docs).collect()}
    # precomputed dictionaries may parse a chunk another way, by a few bytes
    assert np.mean([got[i] == lang for i, lang in want.items()]) >= 0.99


def test_toxicity_row_by_row(spark, edge):
    docs, labels = (read_table(spark, "/root/testdata/sf0.01", t) for t in ("documents", "labels"))
    both = docs.select("doc_id", "text").unionByName(edge.selectExpr("doc_id + 1000000 AS doc_id", "text"))
    model, rows = toxicity.fit_model(both, labels), both.collect()
    weight = dict(zip(model.words.tolist(), model.weights.tolist(), strict=True))
    got = toxicity.rate_toxicity(both, labels).collect()
    want = []
    for r in rows:
        raw = np.frombuffer((r.text or "").encode(), np.uint8)
        score = sum(weight.get(h, 0.0) for h in set(tb.Words(raw, np.array([0, len(raw)]), tb.ALNUM).hashes.tolist()))
        upto = [1 / (1 + exp(score - c)) for c in model.thresholds]
        want.append((r.doc_id, round(upto[1] - upto[0], 6), round(1 - upto[1], 6), 1 - upto[0] >= toxicity.REJECT))
    assert sorted(((r.doc_id, round(r.p_mild, 6), round(r.p_severe, 6), r.toxic) for r in got), key=repr) == sorted(want, key=repr)
    assert len([r for r in got if r.doc_id == 1000012]) == 2  # repeated rows


def test_mixing_row_by_row(spark, edge):
    docs, labels = (read_table(spark, SF, t) for t in ("documents", "labels"))
    table = mixing.feature_table(docs)
    mix = mixing.fit_mix(table, labels)
    seen = {r.doc_id: r for r in mixing.mix_rates(docs, labels).collect()}
    for r in table.collect():
        score = [log(p) + sum(-0.5 * log(2 * pi * v) - (x - m) ** 2 / (2 * v) for x, m, v in zip(r.x, mean, var, strict=True)) for p, mean, var in zip(mix.prior, mix.mean, mix.variance, strict=True)]
        part = [exp(s - max(score)) for s in score]
        p = [x / sum(part) for x in part]
        rate = 1.0
        for step in mix.history:
            rate = max(0.0, rate - sum(a * b for a, b in zip(p, step, strict=True)))
        assert seen[r.doc_id].posterior == pytest.approx(p, abs=1e-9) and seen[r.doc_id].rate == pytest.approx(rate, abs=1e-9)
    again = mixing.mix_rates(edge, labels).collect()
    assert len(again) == len(EDGE)
    twice = [(r.n_tokens, r.rate, r.copies) for r in again if r.doc_id == 12]
    assert len(twice) == 2 and twice[0] == twice[1]


def test_pipeline_keeps_one_row_of_each_group(spark, tmp_path):
    """Repeated rows, rows without an id and one id with two texts: rows are told apart, the least id of a group stays."""
    import corpus_pipeline as cp

    own = lambda k: " ".join(f"w{k}x{j}" for j in range(80))
    rows = [(1, own(1)), (1, own(1)), (2, own(1) + " end"), (None, own(1)), (3, own(3)), (3, own(2)), (4, own(3)), (None, own(5)), (None, own(5)), (6, None), (6, None), (7, ""), (8, own(8))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or ""), "z") for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, key string")
    got = cp.near_dedup(spark, docs, SF)
    assert got.columns == docs.columns
    assert sorted(((r.doc_id, r.text) for r in got.collect()), key=repr) == sorted([(1, own(1)), (3, own(3)), (3, own(2)), (None, own(5)), (6, None), (6, None), (7, ""), (8, own(8))], key=repr)
    none = docs.limit(0)
    for _, stage in cp.STAGES:
        assert stage(spark, none, SF).count() == 0
