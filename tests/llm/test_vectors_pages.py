"""The vector searches and HTML extraction, against brute force."""

import numpy as np
import pytest

from farfield.llm import ann, html, topk, vectors

SCHEMA = "vec_id long, embedding array<float>, label int, norm double, block int"


def table(spark, rows):
    return spark.createDataFrame([(i, v, 0, 1.0, 3) for i, v in rows], SCHEMA)


def clustered(n, d, seed=1, copies=0):
    r = np.random.default_rng(seed)
    centres = r.normal(size=(12, d))
    x = centres[r.integers(0, 12, n)] + 0.3 * r.normal(size=(n, d))
    x *= r.uniform(0.2, 3, (n, 1))
    x[:copies] = x[0]
    return x.astype(np.float32)


def brute_near(x, q, k):
    d = np.sqrt(((x.astype(np.float64) - x[q].astype(np.float64)) ** 2).sum(1))
    order = [i for i in np.lexsort((np.arange(len(x)), d)) if i != q][:k]
    return order, d[order]


def test_multi_index_recall_and_scores(spark, monkeypatch):
    x = clustered(1500, 16, copies=40)
    rows = ann.op4_multi_index(table(spark, list(enumerate(x.tolist())))).collect()
    hit = 0
    for q in range(0, 1500, 100):
        mine = sorted((r["rank"], r["vec_id"], r["score"]) for r in rows if r["query_id"] == q)
        order, d = brute_near(x, q, 10)
        assert [r for r, _, _ in mine] == list(range(1, 11))
        assert all(abs(s - np.sqrt(((x[v].astype(float) - x[q].astype(float)) ** 2).sum())) < 1e-12 for _, v, s in mine)
        assert [(s, v) for _, v, s in mine] == sorted((s, v) for _, v, s in mine)
        hit += len({v for _, v, _ in mine} & set(order))
    assert hit >= 0.9 * 150


def test_cells_come_in_order():
    a, b = np.array([3.0, 1.0, 2.0]), np.array([0.5, 0.1])
    got = list(ann.by_distance(a, b))
    assert len(got) == len(set(got)) == 6
    sums = [a[i] + b[j] for i, j in got]
    assert sums == sorted(sums)


@pytest.mark.parametrize("scale", [1.0, 30.0])
def test_norm_buckets_are_exact(spark, scale, monkeypatch):
    monkeypatch.setattr(vectors, "CHUNK", 100)
    monkeypatch.setattr(vectors, "STRIP", 7)
    monkeypatch.setattr(topk, "SEEDS", 30)
    x = clustered(700, 8, 2, copies=30) * np.float32(scale)
    rows = topk.op7_norm_buckets(table(spark, list(enumerate(x.tolist())))).collect()
    v = np.floor(x.astype(np.float64) * 256).astype(np.int64)
    for q in range(0, 700, 50):
        s = v @ v[q]
        order = [i for i in np.lexsort((np.arange(700), -s)) if i != q][:5]
        assert sorted((r["rank"], r["vec_id"], r["score"]) for r in rows if r["query_id"] == q) == [(k + 1, i, s[i]) for k, i in enumerate(order)]


@pytest.mark.parametrize("op,zero", [(ann.op4_multi_index, False), (topk.op7_norm_buckets, True)])
def test_odd_vectors(spark, op, zero):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 2.0]), (100, [1.0, 2.5]), (1, [0.0, 0.0]), (2, None), (3, [nan, 1.0]), (4, [inf, 1.0]), (5, [None, 1.0]), (6, [1.0]), (None, [1.0, 1.0]), (7, [-1.0, 0.5]), (7, [-1.0, 0.5]), (8, [])]
    got = op(table(spark, rows)).collect()
    seen = {r["vec_id"] for r in got}
    assert {r["query_id"] for r in got} == {0, 100} and seen == {0, 100, 7} | ({1} if zero else set())
    assert all(r["vec_id"] != r["query_id"] for r in got)
    assert op(table(spark, [])).collect() == [] == op(table(spark, [(3, [1.0, 2.0])])).collect()
    assert op(table(spark, [(0, [1.0, 2.0])])).collect() == []


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var a="<p>no</p>";</script></head><body class="home">
<header><h1>Site</h1></header><nav><ul><li><a href="/a">Home</a></li></ul></nav><div class="cookie-notice"><p>We use cookies here.</p></div>
<article><header><h1>Title &amp; more</h1></header><p>First  <b>bold</b>&nbsp;text<br>goes on.<p>Second.</p><div class="ad">Buy now this thing</div>
<ul><li>One</li><li>Two &lt;3</li></ul><aside>Side</aside><form><p>Name</p><input name="x"></form><p>5 < 6 and <i>so</i> on</p>
<section class="comments"><article class="comment"><p>Nice one</p></article></section></article>
<div id="sidebar"><p>Other things to read that are long enough to look like text</p></div><footer>&copy; us</footer></body></html>"""


def test_article():
    assert html.main_text(PAGE) == "Title & more\nFirst bold text goes on.\nSecond.\nOne\nTwo <3\n5 < 6 and so on"


def test_page_without_article():
    p = "<body><ul><li><a href=x>Home</a><li><a href=y>About us</a></ul><div><p>" + "word " * 60 + "<p>" + "more " * 45 + "</div><p><a href=z>next</a></body>"
    assert html.main_text(p) == ("word " * 60).strip() + "\n" + ("more " * 45).strip()


def _given(n, ad=9, last=True):
    """A page as the given table has them, without any mark of structure, and its article."""
    r = np.random.default_rng(n)
    words = lambda k: " ".join(f"w{x}" for x in r.integers(0, 99, k))
    article = [words(8), *(words(int(k)) for k in r.integers(35, 90, 6))]
    blocks = [f'<li><a href="/{k}">link</a></li>' for k in range(6)] + [f"<div>{words(ad)}</div>"] + [f"<p>{x}</p>" for x in article] + ([f"<div>{words(10)}</div>"] if last else [])
    return "".join(blocks), article


def test_words_and_links_decide():
    # no element, class or article says anything: menu, advert and footer go by the words and links of blocks and neighbours
    for n in range(8):
        page, article = _given(n)
        assert html.main_text(page) == "\n".join(article)
    root = html.trained()
    assert root.feature == html.FEATURES.index("links") and root.low.feature == html.FEATURES.index("links_before")
    x = html.features(html.blocks_of(PAGE))
    changed = x.copy()
    changed[:, : html.SHALLOW] = x[::-1, : html.SHALLOW]
    assert (root.predict(changed) != root.predict(x)).any()


def test_tree_brute_force():
    """Each row of the labelled table falls to a leaf whose value is the mean of the rows that fall there."""
    pages = [np.array(p, float).T for p in html.LABELLED]
    x, y = np.concatenate([html.with_neighbours(*p[:4]) for p in pages]), np.concatenate([p[4] for p in pages])

    def leaf(node, row, path=""):
        while node.feature >= 0:
            side = row[node.feature] <= node.cut
            node, path = (node.low, path + "l") if side else (node.high, path + "h")
        return path, node.value

    leaves = [leaf(html.trained(), row) for row in x]
    for at in {p for p, _ in leaves}:
        own = [y[k] for k, (p, _) in enumerate(leaves) if p == at]
        assert {v for p, v in leaves if p == at} == {float(np.mean(own))}
    assert np.array_equal(html.trained().predict(x), [v for _, v in leaves])
    assert ((html.trained().predict(x) >= 0.5) == y).mean() > 0.98


def test_odd_pages(spark):
    rows = [(1, "u", None), (2, None, ""), (3, "u", "<p>unclosed <b"), (4, "u", "<!-- only"), (5, "u", "<article><p>x</article>" * 3), (6, "u", "<div>" * 5000 + "deep"), (7, "u", "<" * 5000), (8, "u", '<article><a href="x>y</a> tail</article>'), (None, "u", "<article>n</article>"), (5, "u", "<article><p>x</article>" * 3)]
    df = spark.createDataFrame([(*r, "extra") for r in rows], "page_id long, url string, html string, text string")
    got = html.op10_html(df).collect()
    assert len(got) == len(rows) and all(r["n_chars"] == len(r["text"]) for r in got)
    by = {r["page_id"]: r["text"] for r in got}
    assert by[1] == by[2] == by[4] == "" and by[5] == "x\nx\nx" and by[None] == "n"
    assert html.op10_html(df.limit(0)).collect() == []
