from collections import Counter
from html.parser import HTMLParser

import numpy as np
import pytest

from dagframe.llm import embeddings, html
from dagframe.llm import queries as llm
from dagframe.llm.components import components


def test_components(spark):
    r = np.random.default_rng(3)
    pairs = [(int(a), int(b)) for a, b in r.integers(0, 400, (260, 2))] + [(i, i + 1) for i in range(500, 560)] + [(7, 7)]
    parent = list(range(600))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in pairs:
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    want = {i: find(i) for p in pairs for i in p if p[0] != p[1]}
    got = components(spark.createDataFrame([*pairs, (None, 1)], "a long, b long")).collect()
    assert {r["id"]: r["component"] for r in got} == want and len(got) == len(want)
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_embeddings_against_brute_force(spark):
    r = np.random.default_rng(1)
    base = r.standard_normal((300, 16))
    near = base[:120] + 0.05 * r.standard_normal((120, 16))
    x = np.concatenate([base, near, near[:40], np.repeat(base[:1], 60, 0) + 0.02 * r.standard_normal((60, 16))]).astype(np.float32)
    odd = [None, [], [0.0] * 16, [float("nan")] + [1.0] * 15, [None] + [1.0] * 15, [float("inf")] + [1.0] * 15, [1.0, 2.0]]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(1000 + i, v) for i, v in enumerate(odd)] + [(None, base[5].astype(np.float32).tolist())]
    for options in ({}, {"leaf": 32}, {"cell": 50}, {"leaf": 64, "cell": 20}):
        got = embeddings.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), **options).toPandas()
        u = embeddings.unit(np.concatenate([x, base[5:6].astype(np.float32)]))
        close = u @ u.T >= 0.95
        np.fill_diagonal(close, False)
        one = got[got.vec_id < 1000].set_index("vec_id").sort_index()
        assert one.n_links.sum() >= 0.98 * close[:-1].sum() and (one.n_links.to_numpy() <= close[:-1].sum(1)).all()
        assert (got[got.vec_id >= 1000].n_links == 0).all() and got[got.vec_id >= 1000].kept.all() and len(got) == len(rows)
        assert (one.kept == (one.index == one.component_id)).all()
    assert embeddings.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_embeddings_of_the_given_table_with_near_copies(spark):
    table = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    rows = [(r["vec_id"], r["embedding"]) for r in table.collect() if r["embedding"]]
    r = np.random.default_rng(6)
    near = [(10_000 + i, (np.array(v) * (1 + 0.2 * r.standard_normal(len(v)))).astype(np.float32).tolist()) for i, (_, v) in enumerate(rows[:200])]
    both = spark.createDataFrame([(i, v, 1, 2) for i, v in rows + near], "vec_id long, embedding array<float>, n int, node int")
    u = embeddings.unit(np.array([v for _, v in rows + near], dtype=np.float32))
    close = u @ u.T >= 0.95
    np.fill_diagonal(close, False)
    assert close.sum() >= 200
    for options in ({}, {"leaf": 64}):
        got = embeddings.near_duplicates(both, **options).toPandas().set_index("vec_id").loc[[i for i, _ in rows + near]]
        assert (got.n_links.to_numpy() <= close.sum(1)).all() and got.n_links.sum() >= 0.9 * close.sum()


PAGE = """<html><head><title>t</title><style>p{}</style></head><body><header>Site</header><nav><a href=x>menu</a></nav><div class="cookie-notice">We use cookies</div>
<div id="content"><div class="post"><h1>Title &amp; more</h1><p>First paragraph, long enough to be prose, with a <a href=y>link</a>.<p>Second   one
with <b>bold</b> text&hellip;<ul><li>one<li>two</ul><form><input>name</form><script>var a = "<p>no</p>";</script></div>
<div class="comments"><p>Great post, I liked every bit of it very much indeed, thanks for sharing.</p></div></div><aside>side text</aside><footer>&copy; foot</footer></body></html>"""


def test_html():
    want = "Title & more First paragraph, long enough to be prose, with a link. Second one with bold text… one two"
    assert html.extract(PAGE, []) == want
    assert html.votes(PAGE)[0][0] == "/html/body/div/div.post"
    assert html.extract(PAGE, ["/nowhere", "/html/body/div/div.post"]) == want
    assert html.extract("", []) == "" and html.extract("plain &lt;b&gt;\n text", []) == "plain <b> text"
    assert html.extract("<div><p>a<p>b<br>c</div", []) == "a b c"
    assert html.extract("<!-- <p>x</p> --><p>kept</p><script>never ends <p>x", []) == "kept"
    assert html.extract("<header>Site</header><article><header><h1>Head</h1></header><p>Text of it.</p><footer>by x</footer></article>", []) == "Head Text of it."
    assert html.extract("<div class='main no-sidebar'><p>Text beside nothing.</p></div><div class='left sidebar'><p>Text of the side, which is longer.</p></div>", []) == "Text beside nothing."
    deep = "<div>" * 3000 + "deep" + "</div>" * 3000
    assert html.extract(deep, []) == "deep"


class _Slow(HTMLParser):
    """Text of the article element of a page, by the standard library's parser: blocks joined by one space."""

    def __init__(self):
        super().__init__()
        self.depth, self.raw, self.parts = 0, 0, []

    def handle_starttag(self, tag, attributes):
        self.depth += tag == "article"
        self.raw += tag in ("script", "style")
        if tag in html.BLOCKS:
            self.parts.append("\n")

    def handle_endtag(self, tag):
        self.depth -= tag == "article"
        self.raw -= tag in ("script", "style")
        if tag in html.BLOCKS:
            self.parts.append("\n")

    def handle_data(self, data):
        if self.depth and not self.raw:
            self.parts.append(" ".join(data.replace("\n", " ").split(" ")))

    def text(self):
        return " ".join(x for x in (" ".join(p.split()) for p in "".join(self.parts).split("\n")) if x)


def test_html_against_the_article_element(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    want = {}
    for r in pages.collect():
        slow = _Slow()
        slow.feed(r["html"] or "")
        want[r["page_id"]] = slow.text()
    for most_bytes in (html.BROADCAST_BYTES, 0):
        got = {r["page_id"]: r["text"] for r in html.main_text(pages, most_bytes=most_bytes).collect()}
        assert len(got) == len(want)
        assert sum(got[i].split() == want[i].split() for i in want) / len(want) >= 0.99, [(got[i][:200], want[i][:200]) for i in want if got[i] != want[i]][:2]


def test_html_whole_article_and_odd_pages(spark):
    body = "<article><header><h1>Head</h1><p>Lead.</p></header><div class=body>" + "<p>Long text of the body, sentence after sentence.</p>" * 30 + "</div><section class=more><p>More of it.</p></section></article><div class=x><p>Other.</p></div>"
    got = html.extract(body, ["/article/div.body"])
    assert got.startswith("Head Lead. Long text") and got.endswith("More of it.") and "Other" not in got
    assert html.extract(body, []) == got and html.extract("<article><div class=a>x</div><div class=a>y</div></article>", ["/article/div.a"]) == "x y"
    long_ = "<p>word word word</p>" * 100_000
    rows = [(i, "http://hot.example/", body, "p", "h", 1) for i in range(40)] + [(50, "http://hot.example/", long_, "p", "h", 1), (51, None, "", None, None, None)]
    table = spark.createDataFrame(rows, "page_id long, url string, html string, paths string, host string, salt int")
    for most_bytes in (html.BROADCAST_BYTES, 0):
        by = {r["page_id"]: r["text"] for r in html.main_text(table, most_bytes=most_bytes).collect()}
        assert by[0] == got and len(by[50].split()) == 300_000 and by[51] == "" and len(by) == 42


def test_html_consensus(spark):
    other = "<html><body><div class='promo-box'>x</div><div id=a class=story><p>Short.</p></div><div class=extra><p>A much longer piece of text that stands beside the story on this page only, and wins alone.</p></div></body></html>"
    usual = "<html><body><div class=story><p>The usual story of this host is found in this place on nearly all of its pages.</p></div></body></html>"
    rows = [(i, "http://h.example/%d" % i, usual) for i in range(8)] + [(8, "http://h.example/8", other), (9, None, None), (10, "not a url", usual), (10, "not a url", usual)]
    got = html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    by = {r["page_id"]: r["text"] for r in got}
    assert len(got) == len(rows) and by[8] == "Short." and by[9] == "" and by[10].startswith("The usual")
    assert html.main_text(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_pipeline_against_its_parts(spark, sf):
    import corpus_pipeline as pipeline
    from dagframe.llm import lines, quality, simhash

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = pipeline.run(spark, sf)
    model = quality.learnt(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    good = [r for r in docs.collect() if model.score(r["text"] or "") >= quality.THRESHOLD]
    good_table = spark.createDataFrame(good, docs.schema)
    kept = {r["row"]["doc_id"]: r["kept"] for r in lines.LineIndex.of(good_table).apply(good_table, most_bytes=0).collect()}
    fp = {i: simhash.fingerprint_bytes(t.encode(), 5) for i, t in kept.items()}
    parent = {i: i for i in fp}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a in sorted(fp):
        for b in sorted(fp):
            if a < b and (fp[a] ^ fp[b]).bit_count() <= 5:
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    assert {r["doc_id"] for r in got.select("doc_id").distinct().collect()} == {i for i in fp if find(i) == i}
    for _, stage in pipeline.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == docs.columns


@pytest.mark.parametrize("name", ["op3_chat_format", "op10_line_dedup"])
def test_sql_twins(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "conversations"):
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    a, b = llm.queries()[name](spark, sf).toPandas(), con.sql(llm.oracle_sql()[name]).df()
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)
    assert Counter(map(tuple, a[cols].astype(str).to_numpy())) == Counter(map(tuple, b[cols].astype(str).to_numpy()))
