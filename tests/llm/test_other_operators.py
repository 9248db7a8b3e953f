"""Neighbour search, URL lists, exact top-k, HTML extraction."""

import datetime as dt
import html as entities
import re

import numpy as np
import pytest
from conftest import compare
from pyspark.sql import functions as F

from shardwise.llm import ann, html, queries, topk, urlfilter

NAN = float("nan")


@pytest.fixture(scope="module")
def vectors(spark):
    """Some groups of near vectors, one vector many times, and rows that take no part; a clashing extra column."""
    rng = np.random.default_rng(1)
    centres = rng.normal(size=(6, 8))
    rows = [(i, (centres[i % 6] + 0.4 * rng.normal(size=8)).tolist(), 0) for i in range(300)]
    rows += [(i, [1.0] * 8, 0) for i in range(300, 360)]
    rows += [(1000, None, 0), (1020, [0.0] * 8, 0), (1040, [NAN] + [1.0] * 7, 0), (1060, [None] + [1.0] * 7, 0), (1080, [float("inf")] * 8, 0), (1100, [], 0)]
    return spark.createDataFrame(rows, "vec_id long, embedding array<double>, score int").cache()


def test_walk_with_full_lists_equals_a_plain_walk(vectors):
    """Lists of 40 are full from the second hop on, so scores below their last stay behind; the walk goes as one that brings all of them."""
    params = ann.Params(neighbours=10, target=60, chunk=64, block=64, home=100, query_block=4, width=40, beam=5)
    index = ann.Index(ann.prepared(vectors, "vec_id", "embedding"), params).build()
    near, v = {}, {}
    table = index.adjacency().toArrow()
    for i, x, others in zip(table.column("id").to_pylist(), ann._half(table.column("v")), table.column("near").to_pylist()):
        near[i], v[i] = others, x
    asked = index.members.where("vec_id % 20 = 0").select(F.col("vec_id").alias("query_id"), "x", F.col("id").alias("entry"))
    got = {}
    for r in index.search(asked, 5).collect():
        got.setdefault(r.query_id, set()).add(r.id)
    width, hops = params.wide(index.n)
    for r in asked.collect():
        q = (np.array(r.x) / index.scale).astype(np.float32)
        kept, opened, ask = {}, set(), [r.entry]
        for hop in range(hops):
            for c in {o for a in ask for o in near[a]} | (set(ask) if hop == 0 else set()):
                kept[c] = float(v[c] @ q)
            best = sorted(kept, key=lambda c: (-kept[c], c))[:width]
            kept = {c: kept[c] for c in best}
            opened &= set(best)
            ask = [c for c in best if c not in opened][: params.beam]
            opened |= set(ask)
            if not ask:
                break
        assert got[r.query_id] == set(best[:20])


def test_neighbours(vectors):
    got = {}
    for r in ann.nearest(vectors, F.col("vec_id") % 20 == 0, k=20, params=ann.Params(neighbours=15, target=60, chunk=64, block=64, query_block=4)).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    data = {r.vec_id: np.array(r.embedding) for r in vectors.where("vec_id < 1000").collect()}
    ids = np.array(sorted(data))
    m = np.stack([data[i] for i in ids])
    assert set(got) == {i for i in data if i % 20 == 0}
    hits = []
    for q, rows in got.items():
        rows.sort()
        s = m @ data[q]
        order = [i for i in np.lexsort((ids, -s)) if ids[i] != q][:20]
        assert [r for r, _, _ in rows] == list(range(1, 21)) and q not in {v for _, v, _ in rows}
        assert all(x == pytest.approx(float(data[v] @ data[q])) for _, v, x in rows)
        assert rows == sorted(rows, key=lambda r: (-r[2], r[1]))
        hits.append(len({v for _, v, _ in rows} & set(ids[order])) / 20)
    assert np.mean(hits) >= 0.9


def test_neighbours_with_an_outlier_and_lengths_that_differ(spark):
    """One vector of another magnitude takes no recall from the rest; short vectors are filled up with zeros; default parameters."""
    rng = np.random.default_rng(2)
    m = rng.normal(size=(1500, 16))
    m[3] *= 1e8
    m[7, 9:] = 0
    rows = [(i, (x[:9] if i == 7 else x).tolist()) for i, x in enumerate(m)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {}
    for r in ann.nearest(df, F.col("vec_id") % 50 == 0, k=20).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    hits = []
    for q, found in got.items():
        s = m @ m[q]
        hits.append(len(found & set([i for i in np.argsort(-s, kind="stable") if i != q][:20])) / 20)
    assert len(got) == 30 and np.mean(hits) >= 0.95


def test_neighbours_of_few_and_none(vectors):
    few = ann.nearest(vectors.where("vec_id < 5 or vec_id >= 1000"), F.col("vec_id") % 2 == 0, k=20).collect()
    assert {(r.query_id, r.rank) for r in few} == {(q, r) for q in (0, 2, 4) for r in range(1, 5)}
    assert ann.nearest(vectors.where("false"), F.col("vec_id") % 2 == 0).count() == 0


def test_topk_equals_brute_force(spark, vectors):
    index = topk.quantised(vectors)
    got = {}
    for r in topk.top_k(index, index.where("id % 10 = 0"), 5, rows=50, block=7).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    data = {r.vec_id: np.floor(256 * np.array(r.embedding)).astype(np.int64) for r in vectors.where("vec_id < 1000 or vec_id = 1020").collect()}
    data[1100] = np.zeros(8, np.int64)  # an empty vector counts as zeros
    ids = np.array(sorted(data))
    m = np.stack([data[i] for i in ids])
    assert set(got) == {i for i in data if i % 10 == 0}
    for q, rows in got.items():
        s = m @ data[q]
        order = [i for i in np.lexsort((ids, -s)) if ids[i] != q][:5]
        assert sorted(rows) == [(n + 1, ids[i], s[i]) for n, i in enumerate(order)]


def test_topk_prunes_and_stays_exact():
    rng = np.random.default_rng(3)
    sparse = np.floor(rng.exponential(20, size=(6000, 32)) ** 1.5 * (rng.random((6000, 32)) < 0.2)).astype(np.int64)
    signed = np.floor(256 * rng.normal(size=(6000, 32)) * np.exp(-np.arange(32) / 6)).astype(np.int64)
    for rows in (sparse, signed):
        shard = topk.Shard(np.arange(6000), rows)
        assert all(np.array_equal(at, np.flatnonzero(rows[:, t])) for t, (at, _) in enumerate(shard.lists))
        held = sum(len(at) for at, _ in shard.lists)
        for query in (7, 100, 2500):
            q = rows[query]
            s = rows @ q
            order = [i for i in np.lexsort((np.arange(6000), -s)) if i != query][:5]
            for floor in (None, int(s[order[-1]]) - 3, int(s[order[-1]])):
                before = shard.touched + shard.probed
                ids, scores = shard.search(query, q, 5, floor)
                assert ids.tolist() == order and scores.tolist() == s[order].tolist()
                assert shard.touched + shard.probed - before < 0.9 * held
        ids, scores = shard.search(7, -rows[7] * 0, 5)
        assert scores.tolist() == [0] * 5 and ids.tolist() == [0, 1, 2, 3, 4]
    big = topk.Shard(np.arange(3), np.full((3, 2), 1 << 30, np.int64))
    assert not big.exact and big.search(0, np.full(2, 1 << 30, np.int64), 5)[1].tolist() == [2 << 60] * 2


@pytest.mark.parametrize("large", [False, True])
def test_topk_of_dense_lists_traverses_them_for_many_queries_at_once(large):
    """A block of queries against dense lists: the rows of single searches, with pruning, ties, zeros and floors, and no list walked query by query."""
    rng = np.random.default_rng(5)
    rows = np.floor(256 * rng.normal(size=(5000, 24)) * np.exp(-np.arange(24) / 4)).astype(np.int64) * ((1 << 20) if large else 1)
    rows[100:110] = rows[4000:4010]  # ties
    shard = topk.Shard(np.arange(5000), rows)
    asked = np.r_[np.arange(0, 5000, 50), 104]
    queries = rows[asked].copy()
    queries[3] = 0
    want = []
    for i, q in zip(asked, queries):
        s = rows @ q
        order = np.array([x for x in np.lexsort((np.arange(5000), -s)) if x != i][:5])
        want.append((order.tolist(), s[order].tolist()))
    floors = [None if i % 3 else w[1][-1] for i, w in enumerate(want)]
    shard.search = None
    for given in (floors, [None] * len(asked)):
        before = shard.touched + shard.probed
        got = shard.search_all(asked, queries, 5, given)
        assert [(ids.tolist(), scores.tolist()) for ids, scores in got] == want
        assert shard.touched + shard.probed - before < 0.9 * len(asked) * rows.size
    assert shard.exact is not large


def test_topk_all_scores_below_zero():
    rows = -np.arange(1, 3001, dtype=np.int64)[:, None] * np.ones(4, np.int64)
    ids, scores = topk.Shard(np.arange(3000), rows).search(0, np.array([1, 2, 0, 1]), 3)
    assert ids.tolist() == [1, 2, 3] and scores.tolist() == [-8, -12, -16]


def test_topk_and_urls_equal_sql(spark, sf):
    for name, text in (("op5_maxscore", queries.OP5_SQL), ("op4_url_filter", queries.OP4_SQL), ("op6_jaccard_join", queries.OP6_SQL)):
        got, want = compare(spark, sf, queries.queries()[name], text)
        assert got == want


def test_topk_empty(vectors):
    index = topk.quantised(vectors)
    assert topk.top_k(index.where("false"), index.where("false")).count() == 0
    assert topk.top_k(index.where("id < 2"), index.where("id = 0")).count() == 1


def day(n):
    return dt.datetime(2024, 1, 1) + dt.timedelta(days=n)


def test_url_lists(spark):
    changes = spark.createDataFrame([
        ("bad", "spam.example", "add", day(10)), ("bad", "spam.example", "add", day(12)), ("bad", "spam.example", "remove", day(50)),
        ("bad", "spam.example", "remove", day(60)), ("bad", "spam.example", "add", day(200)), ("worse", "a.spam.example/x", "add", day(20)),
        ("bad", "b.example", "remove", day(5)), ("bad", None, "add", day(5)), ("bad", "c.example", "add", day(7)), ("bad", "c.example", "remove", day(7)),
    ], "list string, key string, action string, at timestamp")
    urls = ["https://u:p@A.Spam.example:8080/x/y?q", "http://spam.example", "http://notspam.example/", "mailto:x", None, "http://c.example/"]
    rows = [(100 * u + n, url, day(d), "k") for u, url in enumerate(urls) for n, d in enumerate((9, 10, 25, 50, 230))] + [(9999, urls[1], None, "k")]
    caps = spark.createDataFrame(rows, "id long, url string, at timestamp, key string")
    got = {r.id: (r.n_active, r.list, r.key) for r in urlfilter.temporal_list_join(caps, changes).collect()}
    assert len(got) == len(rows)
    assert [got[i][0] for i in range(5)] == [0, 1, 2, 1, 2] and got[2][1:] == ("worse", "a.spam.example/x")
    assert [got[100 + i][0] for i in range(5)] == [0, 1, 1, 0, 1]
    assert all(got[i][0] == 0 for i in got if 200 <= i < 500) and got[9999][0] == 0
    assert [got[500 + i][0] for i in range(5)] == [1, 1, 1, 1, 1]  # the removal of that moment came first
    assert urlfilter.temporal_list_join(caps.where("false"), changes).count() == 0
    assert urlfilter.temporal_list_join(caps, changes.where("false")).where("n_active > 0").count() == 0


def test_url_lists_of_any_depth(spark):
    deep = ".".join(f"l{i}" for i in range(13)) + ".example.com"
    far = "/".join("abcdefgh")
    keys = ["example.com", "l12.example.com", deep, f"h.example/{far[:11]}", f"h.example/{far}", f"{deep}/a/b/c/d/e", "local", "h.example//a"]
    changes = spark.createDataFrame([("bad", k, "add", day(1)) for k in keys], "list string, key string, action string, at timestamp")
    urls = [f"http://{deep}/", f"http://x.{deep}/{far}", f"http://h.example/{far}/i", f"http://h.example//{far[:11]}", f"http://h.example/{far[:9]}", f"http://{deep}/{far}", "http://local/", "http://not.local/", "http://notexample.com"]
    caps = spark.createDataFrame([(i, u, day(2)) for i, u in enumerate(urls)], "id long, url string, at timestamp")
    got = {r.id: (r.n_active, r.key) for r in urlfilter.temporal_list_join(caps, changes).collect()}
    assert got == {0: (3, deep), 1: (3, deep), 2: (2, keys[4]), 3: (1, keys[3]), 4: (0, None), 5: (4, keys[5]), 6: (1, "local"), 7: (0, None), 8: (0, None)}


def test_url_captures_that_repeat(spark):
    """Rows that repeat an id, or whole rows, are rows of their own."""
    changes = spark.createDataFrame([("bad", "spam.example", "add", day(10)), ("bad", "spam.example", "remove", day(50))], "list string, key string, action string, at timestamp")
    rows = [(3, "http://spam.example/", day(20)), (3, "http://spam.example/", day(20)), (3, "http://spam.example/", day(60)), (3, "http://ok.example/", day(20)), (None, "http://spam.example/x", day(20))]
    caps = spark.createDataFrame(rows, "id long, url string, at timestamp")
    got = sorted(((r.id, r.n_active) for r in urlfilter.temporal_list_join(caps, changes).collect()), key=str)
    assert got == sorted([(3, 1), (3, 1), (3, 0), (3, 0), (None, 1)], key=str)


def article(source):
    m = re.search(r"<article>(.*?)(</article>|<footer|$)", source, re.S)
    parts = [" ".join(entities.unescape(re.sub("<[^>]*>", "", b.replace("<br>", " "))).split()) for b in re.split(r"</?p>|</?h1>", m[1])]
    return "\n\n".join(p for p in parts if p)


def test_pages(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    want = {r.page_id: article(r.html) for r in pages.collect()}
    assert {r.page_id: r.text for r in html.extract(pages).collect()} == want


def page(i, form="div class=story"):
    return (
        f"<html><body><header>Site</header><div id=sidebar><a href=x>link {i}</a></div><div class=page><div class=wrap><{form}><h2>Title {i}</h2>"
        f"<p>Text &eacute; {i}  one<br>two<ul><li>first {i}<li>second</ul><form><input>send</form><div class='comment-list'>reader {i}</div>"
        f"<p>Same closing words.</div></div><div class=cookie-notice>We use cookies {i}</div></div><footer>&copy; {i}</footer><script>var a='<p>no</p>'</script></body></html>"
    )


def test_wrapper_without_article_elements(spark):
    rows = [(i, f"http://h.example/{i}", page(i)) for i in range(6)] + [(50, None, None), (51, "http://h.example/e", ""), (52, "http://h.example/t", "plain <b>text</b>"), (53, "x", "<p>a<p>b</p></p>&lt; 1 < 2")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit("zzz"))
    got = {r.page_id: r.text for r in html.extract(df).collect()}
    for i in range(6):
        # the last line is the same on all pages: template; so is the second item of the list
        assert got[i] == f"Title {i}\n\nText é {i} one two\n\nfirst {i}"
    assert got[50] == "" and got[51] == "" and got[52] == "plain text" and got[53] == "a\n\nb\n\n< 1 < 2"
    assert html.extract(df.where("false")).count() == 0


@pytest.mark.parametrize("odd", [None, "", "plain text", "<html><body><h1>404</h1><p>Not found</p></body></html>", "<html><body>" + "<ul><li><a href=x>entry</a></li></ul>" * 60 + "</body></html>"])
def test_wrapper_when_the_first_page_is_of_another_kind(spark, odd):
    page_of = lambda i: page(i).replace("class=cookie-notice", "class=zz9").replace("We use cookies", "Buy this")
    rows = [(-1, "http://h.example/0", odd)] + [(i, f"http://h.example/{i}", page_of(i)) for i in range(6)]
    got = {r.page_id: r.text for r in html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for i in range(6):
        assert got[i] == f"Title {i}\n\nText é {i} one two\n\nfirst {i}"


def extracted(spark, sources, host="h.example"):
    rows = [(i, f"http://{host}/{i}", s) for i, s in enumerate(sources)]
    return {r.page_id: r.text for r in html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}


def unnamed(i):
    """No article element, no name that tells anything."""
    menu = "".join(f"<li><a href=/{x}>{x}</a></li>" for x in ("Home", "World", "Sport"))
    text = "".join(f"<p>Sentence {k} of story {i}, which differs from page to page.</p>" for k in range(2 + i % 3))
    return f"<html><body><div class=x1><ul>{menu}</ul></div><div class=x2><div class=x3><h2>Story {i}</h2>{text}<p>A passage that some repeat.</p><p>Share this story with friends</p></div></div><div class=x4>Offer {i % 2}: buy now</div><div class=x5>All rights reserved</div></body></html>"


def test_template_is_told_from_slots_by_the_pages_alone(spark):
    pages = [unnamed(i).replace("<p>A passage that some repeat.</p>", "" if i % 2 else "<p>A passage that some repeat.</p>") for i in range(9)]
    got = extracted(spark, pages)
    for i in range(9):
        lines = [f"Story {i}", *[f"Sentence {k} of story {i}, which differs from page to page." for k in range(2 + i % 3)], *([] if i % 2 else ["A passage that some repeat."])]
        assert got[i] == "\n\n".join(lines)
        # without the wrapper menus and notices would be in the text
        assert {"Home", "Share this story with friends", "All rights reserved"} <= set(html.main_text(pages[i], None).split("\n\n"))
    # too few pages to call the line constant
    assert extracted(spark, pages[:3])[0].endswith("Share this story with friends")


def test_constant_lines_inside_an_article_element(spark):
    page = lambda i: f"<body><article><h1>News {i}</h1><p>Body {i} text, long enough to be most of it all.</p><div>Read more of our news</div><p>End {i}</p></article></body>"
    got = extracted(spark, [page(i) for i in range(7)])
    assert got == {i: f"News {i}\n\nBody {i} text, long enough to be most of it all.\n\nEnd {i}" for i in range(7)}
    # copies of one article are not a template
    copies = extracted(spark, [page(1).replace("News 1", f"News {i}").replace("End 1", "End") for i in range(7)])
    assert all(t.endswith("Read more of our news\n\nEnd") for t in copies.values())


def test_names_are_overruled_by_the_slots(spark):
    page = lambda i: f"<body><div class=menu>Home {i % 2}</div><div class='layout sidebar-left'><h1>Title {i}</h1><p>Words of page {i} that no other page has, many of them.</p><div class=comments>reader {i}</div></div></body>"
    got = extracted(spark, [page(i) for i in range(6)])
    assert got == {i: f"Title {i}\n\nWords of page {i} that no other page has, many of them." for i in range(6)}


def test_deep_and_wide_pages(spark):
    import time

    deep = lambda n, x: "<html><body>" + "<div>" * n + f"<p>deep {x}</p><i>{x}" + "<b>" * (x % 3) + "</div>" * n + "</span>" * n
    tag = lambda k, x: "p" if (k * 7 + x * k * k) % 3 else "div"
    wide = lambda n, x: "<html><body>" + "".join(f"<{tag(k, x)}><b>w{k} {x}</b>{'<i>y</i>' * ((k * x) % 4)}</{tag(k, x)}>" for k in range(n))
    began = time.time()
    a, b = html.parse(deep(10_000, 1)), html.parse(deep(10_000, 2))
    assert len(html.matched(a, b)) >= 10_000
    a, b = html.parse(wide(20_000, 1)), html.parse(wide(20_000, 2))
    pairs = html.matched(a, b)
    assert len(pairs) > 10_000 and all(x.tag == y.tag for x, y in pairs)
    assert time.time() - began < 60
    got = extracted(spark, [deep(3000, 1), deep(3000, 2), None])
    assert got == {0: "deep 1\n\n1", 1: "deep 2\n\n2", 2: ""}
    got = extracted(spark, [wide(3000, 1), wide(3000, 2)])
    assert all(got[i].startswith(f"w0 {i + 1}") and got[i].count("\n\n") == 2999 for i in range(2))


def test_tree_matching_is_largest():
    a, b = html.parse("<body><div><p>1</p><ul><li>x</li></ul></div><p>2</p></body>"), html.parse("<body><p>0</p><div><h1>t</h1><p>1</p><ul><li>x</li><li>y</li></ul></div></body>")
    tags = [(x.tag, y.tag) for x, y in html.matched(a, b)]
    assert all(x == y for x, y in tags) and [x for x, _ in tags] == ["html", "body", "div", "p", "ul", "li"]
