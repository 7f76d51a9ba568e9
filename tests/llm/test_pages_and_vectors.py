"""Pages and embeddings."""

import os
import re
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from diversify.llm import vectors, wrappers

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var a="</p>";</script></head><body><nav><a href="/x">Home</a></nav><!-- c --><div class="ad">Buy</div>
<article><h1>Title %s</h1><p><b>Some&nbsp;text %s &amp; more.<br><p>Second   block
of it</p><form><input>Name</form><aside>Side</aside><div class="comments"><p>Nice!</p></div></article><footer>&copy; x</footer></body></html>"""
BARE = """<html><body><div class="top"><a href=x>Home</a> <a href=y>News</a></div><div id="wrap"><div class="c1"><h2>T %s</h2><p>Body %s goes on.</p></div>
<div class="box"><p>About this site.</p></div></div><div class="bottom"><p>All rights reserved.</p></div></body></html>"""


def test_articles_and_slots(spark, tables):
    pages = [(i, f"http://A.example/{i}", PAGE % (i, i)) for i in range(4)] + [(10 + i, f"https://b.example:80/p?{i}", BARE % (i, i)) for i in range(4)]
    pages += [(20, None, None), (21, "", ""), (22, "http://c.example/", "<p>Alone &#233;</p>"), (23, "nonsense", "<div>" * 3000 + "deep" + "</div>"), (20, None, None), (24, "http://c.example/", "no tags < here & there"), (25, "http://d.example", "<script>var x = 1;")]
    got = sorted((r.page_id, r.text, r.n_chars) for r in wrappers.pages_text(spark, tables(pages=pages)).collect())
    text = {i: t for i, t, _ in got}
    assert len(got) == len(pages) and all(len(t) == n for _, t, n in got)
    for i in range(4):
        assert text[i] == f"Title {i}\nSome text {i} & more.\nSecond block of it"
        assert text[10 + i] == f"T {i}\nBody {i} goes on."
    assert text[20] == text[21] == text[25] == "" and text[22] == "Alone é" and text[23] == "deep" and text[24] == "no tags < here & there"


def test_equal_pages_keep_their_text(spark, tables):
    got = wrappers.pages_text(spark, tables(pages=[(i, "http://a.example/", PAGE % (1, 1)) for i in range(5)])).collect()
    assert {r.text for r in got} == {"Title 1\nSome text 1 & more.\nSecond block of it"}


def texts(spark, tables, pages):
    return {r.page_id: r.text for r in wrappers.pages_text(spark, tables(pages=pages)).collect()}


def test_template_blocks_need_support_among_all_pages(spark, tables):
    copy = '<html><body><div class="t"><h2>Title %s</h2></div><div class="c"><p>The shared story.</p></div><div class="box"><p>About us.</p></div></body></html>'
    other = '<html><body><div class="t"><h2>Title %s</h2></div><div class="c"><p>Story %s.</p></div><div class="box"><p>About us.</p></div></body></html>'
    pages = [(i, "http://two.example/", copy % i) for i in range(2)]  # near copies alone on a host
    pages += [(10 + i, "http://some.example/", copy % i) for i in range(4)] + [(20 + i, "http://some.example/", other % (20 + i, i)) for i in range(6)]
    layouts = ["alpha", "beta", "gamma", "delta", "omega"]
    pages += [(100 + 10 * k + i, "http://many.example/", f'<body><div class="{x}"><div class="u"><p>Own {x} {i}.</p></div><div class="v"><p>Constant of {x}.</p></div></div></body>') for k, x in enumerate(layouts) for i in range(4)]
    got = texts(spark, tables, pages)
    assert all("The shared story." in got[i] for i in (0, 1))
    assert all(got[10 + i] == f"Title {i}\nThe shared story." for i in range(4)) and all(got[20 + i] == f"Title {20 + i}\nStory {i}." for i in range(6))
    assert all(got[100 + 10 * k + i] == f"Own {x} {i}." for k, x in enumerate(layouts) for i in range(4))


def test_marks_of_articles_are_only_hints(spark, tables):
    teaser = '<div class="u"><article><h3><a href="/%s">Read %s</a></h3><p>Short.</p></article><article><h3><a href="/b">Read b %s</a></h3><p>Brief.</p></article></div>'
    outside = '<body><div class="c"><h1>Title %s</h1><p>The long story number %s is told here in a plain container.</p></div>' + teaser + "</body>"
    within = '<body><article><h1>Title %s</h1><p>Story %s is here.</p><div class="x"><p>Support our paper today and tomorrow.</p></div><p>End of %s.</p></article></body>'
    beside = "<body>" + teaser + "<article><h1>Title %s</h1><p>Story %s is here.</p></article></body>"
    pages = [(i, "http://out.example/", outside % ((i,) * 5)) for i in range(5)] + [(10 + i, "http://in.example/", within % ((i,) * 3)) for i in range(5)]
    pages += [(20 + i, "http://beside.example/", beside % ((i,) * 5)) for i in range(2)]
    got = texts(spark, tables, pages)
    assert all(got[i] == f"Title {i}\nThe long story number {i} is told here in a plain container." for i in range(5))
    assert all(got[10 + i] == f"Title {i}\nStory {i} is here.\nEnd of {i}." for i in range(5))
    assert all(got[20 + i] == f"Title {i}\nStory {i} is here." for i in range(2))


def test_text_after_a_deep_nest(spark, tables):
    nest = lambda n: "<div>" * n + "deep" + "</div>" * n
    pages = [(i, f"http://h{i}.example/", f"<body><div><article><p>before</p>{nest(n)}<p>after</p></article></div><footer>foot</footer></body>") for i, n in enumerate((300, 30_000))]
    pages += [(2, "http://b.example/", "<body><article><p>text" + "<font><b>" * 300 + "<nav>menu</nav><aside>side</aside></p> end</article></body>")]
    got = texts(spark, tables, pages)
    assert got[0] == got[1] == "before\ndeep\nafter" and got[2] == "text\nend"


def brute_size(a, b):
    """Simple tree matching by its definition, over all ways to skip children."""
    if a[0] != b[0]:
        return 0

    def best(i, j):
        if i == len(a[1]) or j == len(b[1]):
            return 0
        return max(best(i + 1, j), best(i, j + 1), brute_size(a[1][i], b[1][j]) + best(i + 1, j + 1))

    return 1 + best(0, 0)


def random_tree(rng, depth):
    return [str(rng.choice(list("xy"))), [random_tree(rng, depth - 1) for _ in range(rng.integers(0, 4))] if depth else [], []]


def test_tree_matching_against_its_definition():
    rng = np.random.default_rng(1)
    for _ in range(150):
        a, b = random_tree(rng, 3), random_tree(rng, 3)
        a[0] = b[0] = "r"
        known = wrappers.Aligner(b)
        of = known.shaped(a)
        assert known.size(of[id(a)], known.own[id(b)]) == brute_size(a, b)
        paired = [(x, y) for x, y in known.pairing(a) if y is not None]
        assert len(paired) == brute_size(a, b) and all(x[0] == y[0] for x, y in paired) and len({id(y) for _, y in paired}) == len(paired)


def test_tree_matching_of_long_lists():
    leaf = lambda k: [f"h2.s{k}", [], []]
    a = ["r", [leaf(k) for k in range(3000)], []]
    b = ["r", [leaf(k) for k in (*range(1, 3000), 0)], []]  # the first label stands last
    paired = [y for _, y in wrappers.Aligner(b).pairing(a) if y is not None]
    assert len(paired) == 3001  # all but one in order, and that one by its name


def bare(html):
    """A page without any mark: elements with a meaning are plain ones, names and roles are gone."""
    html = re.sub(r"<(/?)(?:article|main|nav|header|footer|aside|form)\b[^>]*>", r"<\1div>", html)
    return re.sub(r'\s(?:class|id|role)="[^"]*"', "", html)


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.01"), reason="no test tables here")
def test_alignment_finds_the_articles_of_pages_without_marks(spark, tables):
    given = [(r.page_id, r.url, r.html) for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").collect()]
    want = {i: wrappers.main_text(re.search(r"<article>.*</article>", h, re.S)[0]) for i, _, h in given}
    d = f"{tables(pages=given)}/bare"
    assert {r.page_id: r.text for r in wrappers.pages_text(spark, d[:-5]).collect()} == want
    spark.createDataFrame([(i, u, bare(h)) for i, u, h in given], "page_id long, url string, html string").write.parquet(f"{d}/pages.parquet")
    got = {r.page_id: r.text for r in wrappers.pages_text(spark, d).collect()}
    alone = {i: wrappers.main_text(bare(h)) for i, _, h in given}
    found, without = (sum(x[i] == want[i] for i in want) for x in (got, alone))
    short = [i for i in want if len(want[i]) < 250]
    assert found >= 0.98 * len(want) and without < found
    assert all(got[i] == want[i] for i in short) and sum(alone[i] == want[i] for i in short) < 0.7 * len(short)


def test_pages_take_linear_time():
    n = 1 << 18
    odd = ["<a ", '<a b="', "<a b='x>", "<p '", "<", "<!--", "<p><table><b><div></div>", "<div>", "</div>", "<li>", "a=" * 50, "<a " + "x" * 90, "&amp", '<a b="x>"', "<b><p>"]
    for piece in odd:
        for end in ("", ">", '">', "\">'>"):
            began = time.perf_counter()
            wrappers.main_text("<p>First.</p>" + piece * (n // len(piece)) + end)
            assert time.perf_counter() - began < 10, piece
    assert wrappers.main_text("<p>It's <a title=don't href='x'>here</a>.</p>") == "It's here."


def test_no_pages_and_clashing_columns(spark, tables):
    d = tables()
    assert wrappers.pages_text(spark, d).collect() == []
    rows = [(i, f"http://a.example/{i}", PAGE % (i, i)) for i in range(4)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for name in ("host", "tree", "known", "text", "n_chars", "h", "b", "p", "slot", "parts"):
        pages = pages.withColumn(name, F.lit("x"))
    assert {r.text for r in wrappers.extract(pages).collect()} == {f"Title {i}\nSome text {i} & more.\nSecond block of it" for i in range(4)}


def brute(vecs):
    ids = sorted({i for i, v in vecs if v})
    x = {i: np.array(v, float) for i, v in vecs}
    ok = [i for i in ids if np.isfinite(x[i]).all() and np.abs(x[i]).sum() > 0]
    near = {i: {j for j in ok if j != i and len(x[i]) == len(x[j]) and x[i] @ x[j] / np.linalg.norm(x[i]) / np.linalg.norm(x[j]) >= 0.9} for i in ok}
    of = {}
    for i in ok:
        todo = [] if i in of else [i]
        while todo:
            y = todo.pop()
            if y not in of:
                of[y] = i
                todo += near[y]
    return {i: (len(near.get(i, ())), of.get(i, i)) for i, _ in vecs}


def clustered(n, seed=0, dims=32):
    rng = np.random.default_rng(seed)
    centers = rng.standard_normal((n // 6 + 1, dims))
    v = centers[rng.integers(0, len(centers), n)] + 0.25 * rng.standard_normal((n, dims))
    v[::9] = v[0]
    return [(i, v[i].astype(np.float32).tolist()) for i in range(n)]


@pytest.mark.parametrize("leaf,block", [(400, 2000), (40, 2000), (40, 25)])
def test_links_match_brute_force(spark, tables, monkeypatch, leaf, block):
    monkeypatch.setattr(vectors, "LEAF", leaf)
    monkeypatch.setattr(vectors, "BLOCK", block)
    vecs = clustered(400)
    got = {r.vec_id: (r.n_links, r.component_id) for r in vectors.embeddings(spark, tables(embeddings=[(i, v, 0) for i, v in vecs])).collect()}
    want = brute(vecs)
    found, true = sum(n for n, _ in got.values()), sum(n for n, _ in want.values())
    assert all(got[i][0] <= want[i][0] for i in want) and found >= 0.97 * true
    if leaf == 400:
        assert got == want


def test_odd_vectors(spark, tables):
    nan, inf = float("nan"), float("inf")
    rows = [(1, None, 0), (2, [], 0), (3, [0.0, 0.0], 1), (4, [nan, 1.0], None), (5, [inf, 1.0], 0), (6, [1.0, 0.0], 0), (7, [2.0, 0.0], 3), (8, [2.0, -0.0], 3), (9, [1.0, 0.0, 0.0], 0), (10, [None, 1.0], 0), (None, [1.0, 0.0], 0), (6, [1.0, 0.0], 0)]
    got = [(r.vec_id, r.n_links, r.component_id, r.kept) for r in vectors.embeddings(spark, tables(embeddings=rows)).collect()]
    assert len(got) == len(rows)
    by = {i: (n, c, k) for i, n, c, k in got}
    assert by[6] == (2, 6, True) and by[7] == (2, 6, False) and by[8] == (2, 6, False) and by[9] == (0, 9, True)
    assert all(by[i] == (0, i, True) for i in (1, 2, 3, 4, 5, 10)) and by[None] == (0, None, False)


def test_no_vector_that_can_be_compared(spark, tables):
    got = vectors.embeddings(spark, tables(embeddings=[(1, None, 0), (1, None, 0), (2, [0.0, 0.0], 1), (None, None, None)])).collect()
    assert sorted((r.vec_id or 0, r.n_links, r.component_id, r.kept) for r in got) == [(0, 0, None, False), (1, 0, 1, True), (1, 0, 1, True), (2, 0, 2, True)]


def test_no_vectors_and_clashing_columns(spark, tables):
    d = tables()
    assert vectors.embeddings(spark, d).collect() == []
    e = spark.read.parquet(f"{d}/embeddings.parquet").withColumn("rep", F.lit(1)).withColumn("n", F.lit(1))
    assert vectors.near_vectors(e).collect() == []
