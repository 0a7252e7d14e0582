import random
import zlib

import numpy as np
import pytest
from conftest_llm import EDGE

from fieldmr.llm import htmltext, rans, tokencount, tokenfile


@pytest.mark.parametrize("n", [0, 1, 511, 512, 513, rans.BLOCK, rans.BLOCK + 1, 300_000])
def test_segments_round_trip(n):
    ids = (np.random.default_rng(n).zipf(1.3, n) % 49_000).astype(np.uint32)
    raw = rans.encode(ids, np.array([7]), np.array([n]))
    seg = rans.Segment(raw)
    assert np.array_equal(seg.tokens(), ids)
    for k in reversed(range(seg.n_blocks)):
        assert np.array_equal(seg.read(k), ids[k * rans.BLOCK : (k + 1) * rans.BLOCK])


def test_damage_is_noticed():
    ids = np.arange(5000, dtype=np.uint32) % 700
    raw = bytearray(rans.encode(ids, np.array([7]), np.array([5000])))
    raw[-3] ^= 1
    with pytest.raises(ValueError):
        rans.Segment(bytes(raw)).tokens()
    raw[20] ^= 1
    with pytest.raises(ValueError):
        rans.Segment(bytes(raw))


def test_frequencies_add_up():
    rng = np.random.default_rng(1)
    for n in (1, 2, 100, 4000):
        counts = rng.zipf(1.2, n).clip(1, 10**9)
        f = rans.frequencies(counts, 13)
        assert f.sum() == 1 << 13 and (f > 0).all()


def expected(rows):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenfile.vocabulary())
    order = sorted(range(len(rows)), key=lambda k: (rows[k][0] is not None, rows[k][0] or 0))
    out, start = [], 0
    for k in order:
        ids = [*t.encode(rows[k][1] or "", add_special_tokens=False).ids, 2]
        out.append((rows[k][0], start, len(ids), zlib.crc32(np.array(ids, dtype="<u4").tobytes())))
        start += len(ids)
    return out


def test_token_table(spark, docs, none):
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    assert sorted(tuple(r) for r in tokenfile.token_table(docs).collect()) == sorted(expected(rows))
    assert tokenfile.token_table(none).count() == 0


def test_token_table_edge(spark):
    rows = [(i, t) for i, t in EDGE if i is not None] + [(-3, "Don't stop, it's \t odd. İstanbul ΣΑΣ. éa, á. <|endoftext|>x, <|startoftext|>. a\x1cb c!., 1,2. x1."), (40, "<|STARTOFTEXT|> É,. ÉCOLE. ß. éa"), (41, "...a. a.b,c a."), (None, None)]
    d = spark.createDataFrame([(i, t, "k") for i, t in rows], "doc_id long, text string, start string").repartition(3)
    assert sorted(map(tuple, tokenfile.token_table(d).collect()), key=repr) == sorted(expected(rows), key=repr)


def test_ids_come_back(spark, tmp_path):
    d = spark.createDataFrame([(2, "hello there"), (1, "general")], "doc_id long, text string")
    tokenfile.write_tokens(d, f"file://{tmp_path}/t", close_at=1)
    got = {r.doc_id: r for r in tokenfile.read_tokens(spark, f"file://{tmp_path}/t", with_ids=True).collect()}
    assert got[1].start == 0 and got[2].start == got[1].n_tokens and got[2].ids[-1] == 2 and len(got[2].ids) == got[2].n_tokens


def greedy(word, initial, rest):
    n = i = 0
    while i < len(word):
        pieces = initial if i == 0 else rest
        j = next((j for j in range(len(word), i, -1) if word[i:j] in pieces), None)
        if j is None:
            return 1
        i, n = j, n + 1
    return n


def test_automaton_counts_greedy_pieces():
    rng = random.Random(1)
    for t in range(150):
        make = lambda: {bytes(rng.choice(b"abab") if rng.random() < 0.95 else 99 for _ in range(rng.randint(1, 5))) for _ in range(rng.randint(1, 8))}
        initial, rest = make(), make() if t % 2 else None
        words = [bytes(rng.choice(b"ab") if rng.random() < 0.95 else rng.choice(b"cd") for _ in range(rng.randint(1, 10))) for _ in range(50)]
        ends = np.cumsum([len(w) for w in words])
        got = tokencount.Automaton(initial, rest).counts(np.frombuffer(b"".join(words), np.uint8), ends - [len(w) for w in words], ends)
        assert got.tolist() == [greedy(w, initial, initial if rest is None else rest) for w in words]


def test_counts_of_documents(spark, edge, none):
    pieces = tokencount.pieces_of(tokenfile.vocabulary())
    low = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
    want = [(i, len(w := (t or "").encode().translate(low).split()), sum(greedy(x, pieces, pieces) for x in w)) for i, t in EDGE]
    assert sorted(map(tuple, tokencount.count_tokens(edge).collect()), key=repr) == sorted(want, key=repr)
    assert tokencount.count_tokens(none).count() == 0


PAGES = [
    ("<p>One<p>Two <b>bold<i>x</b> y</i><div>three</div>", "One\n\nTwo boldx y\n\nthree"),
    ("<ul><li>a<li>b<ol start=3><li>c<li>d</ol><li>e</ul>tail", "- a\n- b\n  3. c\n  4. d\n- e\n\ntail"),
    ("<table><tr><th>Name<th>Qty<tr><td>apple pie<td>3<tr><td colspan=2>total &amp; more<td>x</table>", "Name          Qty\napple pie     3\ntotal & more       x"),
    ("<title>t</title><style>.h{display:none}</style><p class=h>no<p hidden>no<p style='visibility: hidden'>no<p>yes<script>var t='</p>'</script><!-- c -->", "yes"),
    ("a<br>b  c\n d<pre> x\n  y</pre>&lt;z&gt;", "a\nb c d\n\n x\n  y\n\n<z>"),
    ("<dl><dt>T<dd>D</dl><blockquote>q</blockquote>", "T\n    D\n\n> q"),
    ("plain text only", "plain text only"), ("", ""), ("<", "<"), ("<div", ""), ("</p>x", "x"), ("<table><td>1<td>2", "1  2"),
]


@pytest.mark.parametrize("html,text", PAGES)
def test_rendering(html, text):
    assert htmltext.render(html)[0] == text


def test_hostile_pages_end():
    for html in ("<div>" * 20_000 + "x", "<" * 20_000, "<a " * 20_000, "<!--" * 20_000, "<p>" * 20_000, "<table><tr><td>" * 300 + "deep", "<ul><li>" * 500 + "z", "<a '>" * 20_000):
        htmltext.render(html)


def test_page_table(spark):
    rows = [(1, "<p>a</p><p>b</p>", "x"), (1, "<p>a</p><p>b</p>", "x"), (None, None, "x"), (2, "", "x")]
    got = sorted(map(tuple, htmltext.page_text(spark.createDataFrame(rows, "page_id long, html string, text string")).collect()), key=repr)
    assert got == sorted([(1, "a\n\nb", 4, 3, 0, 0)] * 2 + [(None, "", 0, 0, 0, 0), (2, "", 0, 0, 0, 0)], key=repr)


def test_hashing_and_encoding_need_little_memory():
    """Arrays of eight bytes a byte of text live for a block of words, not for a whole slice."""
    import tracemalloc

    from fieldmr.llm import textbytes as tb

    text = np.frombuffer(b"some words of several lengths stand here again and again " * 70_000, np.uint8)
    offsets = np.array([0, len(text)])
    words = tb.Words(text, offsets, tb.NON_SPACE)
    tracemalloc.start()
    try:
        whole = words.hashes
        assert tracemalloc.get_traced_memory()[1] < 12 * len(text)
    finally:
        tracemalloc.stop()
    assert len(whole) == len(words)
    # blocks change no hash: a word's is the same wherever it stands, and so is that of a word longer than a block
    assert np.array_equal(whole[:10], whole[-10:]) and len(np.unique(whole)) == 9
    long = np.frombuffer(b"ab " + b"x" * (tb.HASH_BYTES + 5) + b" ab", np.uint8)
    three = tb.Words(long, np.array([0, len(long)]), tb.NON_SPACE).hashes
    alone = tb.Words(long[3:-3], np.array([0, len(long) - 6]), tb.NON_SPACE).hashes
    assert three[0] == three[2] and three[1] == alone[0]
