"""Pages, archives, vectors, chats and shards."""

import html.parser
import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsewire.llm import chat_format, hash_forest, html_wrapper, shard_store, warc
from sparsewire.llm.common import fresh_dir
from sparsewire.llm.queries import ORACLE_SQL, QUERIES

TABLES = ("documents", "pages", "conversations", "embeddings", "benchmark", "labels")


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got, want = QUERIES[name](spark, sf).toPandas(), con.execute(ORACLE_SQL[name]).df()
    cols = sorted(want.columns)
    got, want = (x[cols].sort_values(cols, ignore_index=True) for x in (got, want))
    assert len(got) == len(want)
    for c in cols:
        assert ((got[c] == want[c]) | (got[c].isna() & want[c].isna())).all(), c


def test_all_ten_are_registered():
    assert sorted(int(n[2:].split("_")[0]) for n in QUERIES) == list(range(1, 11))


# ---- pages (4)

PAGE = """<html><head><title>T</title></head><body><header class=top><h2>Site</h2></header><nav>menu</nav><div id="content"><div class="cookie-notice">We use</div>
<h1>Hello &amp; bye {n}</h1><p>First  para {n} with some more words<p>Second <i>it</i>alic<script>x<p></script> &lt;b&gt; {n}</p><ul><li>one {n}<li>two</ul><form><p>f</p></form></div>
<aside>side</aside><section class="comments"><p>Reader says a long thing {n}</p></section><p>Same on all pages of the site</p><footer>f</footer></body>"""


def test_unmarked_pages_use_the_template(spark):
    rows = [(i, "http://h.example/x", PAGE.replace("{n}", str(i))) for i in range(9)] + [(20, "http://alone.example/", "<article><p>a&nbsp;b<br>c</article>"), (21, None, None), (22, "bad url", "")]
    d = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("host", F.lit("mine")).withColumn("template", F.lit("mine"))
    got = {r.page_id: r for r in html_wrapper.extract(d).collect()}
    assert got[3].text == "Hello & bye 3\n\nFirst para 3 with some more words\n\nSecond italic <b> 3\n\none 3\n\ntwo"
    assert "Same on all" not in got[3].text and "Reader" not in got[3].text and "We use" not in got[3].text
    assert got[20].text == "a b c" and got[21].text == "" and got[22].n_chars == 0 and len(got) == 12
    assert html_wrapper.extract(d.limit(0)).count() == 0


def test_articles_keep_every_block(spark, sf):
    for r in html_wrapper.op4_html_wrapper(spark, sf).join(spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "html"), "page_id").collect():
        import re
        from html import unescape

        art = r.html[r.html.index("<article>") : r.html.index("</article>")]
        want = [" ".join(unescape(x).split()) for x in re.split(r"</?(?:p|h1)>", re.sub(r"</?b>|<article>", "", art).replace("<br>", " "))]
        assert r.text == "\n\n".join(x for x in want if x) and r.n_chars == len(r.text)


def test_names_of_furniture():
    page = '<body class="has-sidebar"><div class="layout with-sidebar"><div class="nav-wrap"><article class="no-comments"><div class="post-header"><h1>T</h1></div><p>text</p><div class="share-buttons">Share</div><div id="comments">c</div></article></div></div><div class="ad-banner">buy</div></body>'
    assert html_wrapper.main_text(page, "") == "T\n\ntext"


def test_tree_matching():
    a, b = (html_wrapper.shape(html_wrapper.parse(f"<div><p>x{k}</p><ul><li>1</ul>{'<b>z</b>' * k}</div>")) for k in (0, 2))
    size, _ = html_wrapper.match(a, b)
    assert size >= 5 and html_wrapper.main_text("<div>" * 3000 + "deep", "") == "deep"


def test_depth_names_quotes_and_formulas():
    deep = "<div>" * 160 + "<article><p>body</p><nav>menu</nav></article>"
    assert html_wrapper.main_text(deep, "") == "body"
    assert html_wrapper.main_text("<i><div class=x>" * 60_000 + "<p>end</p>", "") == "end"
    kept = '<article><h1>T</h1><p class="notice-period">one</p><p id="related-work">two</p><div class="share-price">three <math><mi>x</mi></math></div><div class="share-buttons">s</div><div class="relatedPosts">r</div><p data-id="nav">four</p></article>'
    assert html_wrapper.main_text(kept, "") == "T\n\none\n\ntwo\n\nthree x\n\nfour"
    assert html_wrapper.main_text('<article><p>a<img alt="5" tall">b <a href=x title=\'q">\'>c</a></p><p title="x > y">d</p></article>', "") == "ab c\n\nd"
    assert html_wrapper.main_text("<p>a</p></div></p></b><select><option>x<option>y</select><p>b</p>", "") == "a\n\nb"


def test_long_pages_are_read_in_linear_time(spark):
    import time

    page = lambda n, k: "<article>" + "".join(f"<h2>Head {k} {i}</h2><p>Text {k} {i} of some words</p>" for i in range(n)) + "</article>"
    template = html_wrapper.induce([page(12_000, 0), page(12_000, 1)])
    start = time.perf_counter()
    got = html_wrapper.main_text(page(12_000, 2), template)
    assert len(page(12_000, 2)) > 600_000 and got.count("\n\n") == 23_999 and time.perf_counter() - start < 6
    many = "".join(f"<x-{'abcdefghij'[i % 10]}{'klmnopqrst'[i // 10 % 10]}{i}>w{i}</x-{'abcdefghij'[i % 10]}{'klmnopqrst'[i // 10 % 10]}{i}>" for i in range(20_000))
    start = time.perf_counter()
    html_wrapper.induce([many, many + "<p>x</p>"])
    assert time.perf_counter() - start < 6


class Blocks(html.parser.HTMLParser):
    """Texts of block elements with the path of tags and classes to them; well-formed pages only."""

    def __init__(self, page):
        super().__init__(convert_charrefs=True)
        self.path, self.found, self.words = [], [], []
        self.feed(page)

    def flush(self):
        if text := " ".join("".join(self.words).split()):
            self.found.append((tuple(self.path), text))
        self.words = []

    def handle_starttag(self, tag, attrs):
        if tag == "br":
            self.words.append(" ")
        elif tag != "meta":
            if tag not in ("b", "i", "a"):
                self.flush()
            self.path.append((tag, dict(attrs).get("class", "")))

    def handle_endtag(self, tag):
        if tag not in ("b", "i", "a"):
            self.flush()
        self.path.pop()

    def handle_data(self, data):
        self.words.append(data)


def brute_texts(pages):
    """Main texts of one host's pages: what is not on all pages that have the path, and not in furniture by tag or class."""
    seen = [Blocks(p).found for p in pages]
    out = []
    for mine in seen:
        keep = []
        for path, text in mine:
            on = [x for x in seen if any(p == path for p, _ in x)]
            constant = all((path, text) in x for x in on) and len({pages[i] for i, x in enumerate(seen) if x in on}) > 1
            if not constant and not any(t in ("head", "nav", "footer", "aside", "script", "style", "title") or c in ("ad", "comments") for t, c in path):
                keep.append(text)
        out.append("\n\n".join(keep))
    return out


def test_wrappers_equal_brute_force(spark):
    rng = random.Random(4)
    pages = []
    for i in range(14):
        body = "".join(f"<p>{rng.choice(['Shared line of the site', f'Own line {i} {k}', f'Line {k} with <b>bold {i}</b> words'])}</p>" for k in range(6))
        extra = "<section class=more><h2>Read on</h2><p>Always the same</p><p>More {i}</p></section>".replace("{i}", str(i)) if i % 3 else ""
        pages.append(f"<html><head><title>t{i}</title></head><body><nav><a>n</a></nav><div class=lead>Lead {i % 5}</div><div class=ad>buy {i}</div><article><h1>Title {i}</h1>{body}<p>End note of all</p></article>{extra}<div class=legal>All rights</div><footer>f</footer></body></html>")
    got = extracted(spark, pages)
    assert [got[i] for i in range(len(pages))] == brute_texts(pages)


def extracted(spark, pages):
    d = spark.createDataFrame([(i, "http://h.example/x", p) for i, p in enumerate(pages)], "page_id bigint, url string, html string")
    return {r.page_id: r.text for r in html_wrapper.extract(d).collect()}


def test_template_decides_inside_and_around_articles(spark):
    got = extracted(spark, [f"<body><div class=lead>Lead {i}</div><article><h1>T{i}</h1><p>Text {i}</p><p>Same line on each page</p></article><div class=end>All rights</div></body>" for i in range(6)])
    assert got == {i: f"Lead {i}\n\nT{i}\n\nText {i}" for i in range(6)}


def test_all_pages_of_a_host_make_its_template(spark):
    a = [f"<body><div class=x>Menu of the site</div><div class=text><p>First {i} words</p></div></body>" for i in range(7)]
    b = [f"<body><section class=y>Other menu</section><main><h2>Second {i}</h2></main></body>" for i in range(2)]
    late = "<body><div class=x>Not the menu</div><div class=text><p>Odd one</p></div></body>"
    got = extracted(spark, [p for p in a + b for _ in range(40)])
    assert set(got.values()) == {f"First {i} words" for i in range(7)} | {f"Second {i}" for i in range(2)}
    got = extracted(spark, a + [late])
    assert got[0] == "Menu of the site\n\nFirst 0 words" and got[7] == "Not the menu\n\nOdd one"


def test_text_beside_the_largest_element_and_second_articles_stay(spark):
    page = "<body><h1>Head {n}</h1><p>Lead {n}</p><div class=content><p>{long}</p></div><div class=more><p>More {n}</p></div><div class=menubar>m</div></body>"
    got = extracted(spark, [page.replace("{n}", str(i)).replace("{long}", f"long {i} text " * 60) for i in range(5)])
    assert all(got[i].split("\n\n")[:2] == [f"Head {i}", f"Lead {i}"] and got[i].endswith(f"More {i}") and "long" in got[i] for i in range(5))
    two = "<main><article><p>one</p></article></main><main><article><p>two, longer</p></article></main><article class=comment><p>c</p></article>"
    assert html_wrapper.main_text(two, "") == "one\n\ntwo, longer"


# ---- archives (5)


def test_archive_round_trip_at_any_split(spark):
    rng = random.Random(4)
    noise = "".join(chr(rng.randrange(32, 1000)) for _ in range(70_000))
    body = "y" * 1500
    rows = [(1, "u\n%0A", body), (5, "v", body), (3, None, body), (7, "s", "short"), (8, "s", "short"), (9, None, None), (None, "n", body), (10, "big", noise), (10, "big", noise), (11, "z", noise)]
    d = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("sw_x", F.lit(1)).repartition(3)
    files = warc.write(d, fresh_dir(spark, "t"))
    want = None
    for split in (100, 1000, 1 << 20):
        got = sorted(warc.read(files, payloads=True, split_bytes=split).collect(), key=str)
        assert len(got) == len(rows)
        want = want or got
        assert got == want
    by = {}
    for r in want:
        by.setdefault(r.page_id, r)
    assert by[1].record_type == "revisit" and by[1].refers_to == 5 and by[5].record_type == "response" and bytes(by[5].payload).decode() == body and by[1].url == "u\n%0A"
    assert by[7].record_type == by[8].record_type == "response" and by[None].record_type == "response" and by[10].refers_to == 11 and by[9].payload_bytes == 0
    assert warc.read(warc.write(d.limit(0), fresh_dir(spark, "t"))).count() == 0


# ---- vectors (6)


def test_recall_and_scores(spark, sf):
    rows = spark.read.parquet(f"{sf}/embeddings.parquet")
    got = hash_forest.op6_hash_forest(spark, sf).toPandas()
    p = rows.toPandas().sort_values("vec_id")
    x, ids = np.array(p.embedding.tolist(), dtype=float), p.vec_id.to_numpy()
    n = np.linalg.norm(x, axis=1)
    hit = total = 0
    for i in np.flatnonzero(ids % 50 == 0):
        cos = x @ x[i] / (n * n[i])
        want = [b for _, b in sorted((-c, d) for c, d in zip(cos, ids) if d != ids[i])[:5]]
        mine = got[got.query_id == ids[i]].sort_values("rank")
        assert mine["rank"].tolist() == [1, 2, 3, 4, 5] and np.allclose(mine.score, cos[np.searchsorted(ids, mine.vec_id)], atol=1e-12)
        hit, total = hit + len(set(want) & set(mine.vec_id)), total + 5
    assert hit / total >= 0.9


def test_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (1, [2.0, 0.0]), (2, [0.0, 0.0]), (3, None), (4, [float("nan"), 1.0]), (5, [1.0, None]), (6, [1.0]), (7, [0.0, 1.0]), (8, [1.0, 0.0]), (9, [float("inf"), 0.0]), (50, [1.0, 0.0]), (None, [1.0, 1.0])]
    d = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").withColumn("v", F.lit(0)).withColumn("shard", F.lit(0))
    got = [(r.query_id, r["rank"], r.vec_id) for r in hash_forest.search(d, d.where("vec_id % 50 = 0")).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 1), (0, 2, 8), (0, 3, 50), (0, 4, 7), (50, 1, 0), (50, 2, 1), (50, 3, 8), (50, 4, 7)]
    assert hash_forest.search(d.limit(0), d.limit(0)).count() == 0


def test_forest_levels():
    x = np.random.default_rng(1).standard_normal((300, 8))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    f = hash_forest.Forest(x, 8)
    for rows, q in zip(f.candidates(x[:20], 30), range(20)):
        assert q in rows and len(rows) >= 30
    assert all(len(r) == 300 for r in f.candidates(x[:3], 10_000))


# ---- chats (7)


def test_escapes_and_parts(spark):
    for t in ("<|a", "<\\|a", "<\\\\|<<||", "a<b|", "<|im_end|>\n<|im_start|>assistant\n", "|<|"):
        assert chat_format.unescape(chat_format.escape(t)) == t and "<|" not in chat_format.escape(t)
        assert chat_format.unescape_role(chat_format.escape_role(t + "\\n\n")) == t + "\\n\n"
    parts = [{"kind": "image", "uri": "i", "width": 280, "height": 140}, {"kind": "text", "text": " then <|x|>"}, {"kind": "audio", "uri": "a", "seconds": 2.0}, {"kind": "document", "uri": "d", "pages": 3}, {"kind": "smell"}]
    text, spans, attached = chat_format.render([("user", "see ", parts), ("assistant", "ok <|", None)])
    assert [a["tokens"] for a in attached] == [50, 50, 774, 1] and "<|image:1|> then <\\|x|><|audio:2|><|document:3|><|unknown:4|>" in text
    assert [text[a:b] for a, b in spans] == ["ok <\\|"]


def test_odd_conversations(spark):
    rows = [(1, 1, "assistant", "b"), (1, 0, "user", None), (1, 1, "assistant", "a"), (1, None, None, ""), (None, 0, "assistant", "x" * 5000), (2, 0, "assistant", "same"), (2, 0, "assistant", "same")]
    d = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").withColumn("c", F.lit(1)).withColumn("n", F.lit(1))
    got = {r.conv_id: chat_format.read_back(r.formatted) for r in chat_format.format_conversations(d).collect()}
    assert got[1] == [("", ""), ("user", ""), ("assistant", "a"), ("assistant", "b")] and got[None] == [("assistant", "x" * 5000)] and got[2] == [("assistant", "same")] * 2
    assert chat_format.format_conversations(d.limit(0)).count() == 0


# ---- shards (8)


def test_tiers_versions_and_vacuum(spark):
    schema = spark.createDataFrame([], "k bigint, block string").schema
    store = shard_store.ShardStore(spark, fresh_dir(spark, "s"), schema, target_bytes=1 << 16)
    assert store.read().count() == 0 and store.version() == 0
    for i in range(9):
        store.append(spark.createDataFrame([(i, "x"), (i, None)], schema))
    assert store.compact() >= 2 and store.version() > 9
    assert sorted(r.k for r in store.read().collect()) == sorted([*range(9)] * 2)
    assert len(store.runs()) < 9 and store.read(3).count() == 6
    before = store.version()
    with pytest.raises(RuntimeError):
        store.commit(before - 1, [])
    assert store.vacuum() > 0 and store.version() == before and store.read().count() == 18
    store.append(spark.createDataFrame([], schema))
    assert store.read().count() == 18


def test_one_of_two_writers_commits(spark):
    schema = spark.range(1).schema
    root = fresh_dir(spark, "writers")
    stores = [shard_store.ShardStore(spark, root, schema) for _ in range(6)]
    from concurrent.futures import ThreadPoolExecutor

    def commit(s):
        try:
            return s.commit(0, [])
        except RuntimeError:
            return None

    with ThreadPoolExecutor(6) as pool:
        assert sorted(map(str, pool.map(commit, stores))) == ["1"] + ["None"] * 5
    assert stores[0].version() == 1 and stores[0].runs() == []
    qualified = stores[0]._path(f"{root}/_manifests/v0000000001.json")
    for by_link in (True, False):
        held = stores[0]._path(f"{root}/_manifests/.held{by_link}")
        stores[0]._fs.create(held, False).close()
        with pytest.raises(Exception, match="Exists"):
            stores[0]._publish(held, qualified, by_link)
        stores[0]._publish(held, stores[0]._path(f"{root}/_manifests/v000000000{2 + by_link}.json"), by_link)
    assert stores[0].version() == 3


def test_store_keeps_odd_rows(spark, docs_schema):
    store = shard_store.ShardStore(spark, fresh_dir(spark, "odd"), spark.createDataFrame([], docs_schema).schema)
    rows = [(None, None, None, None, None), (1, "", "en", "s", 0), (1, "", "en", "s", 0), (2, "x" * 2_000_000, "en", "s", 2_000_000)]
    d = spark.createDataFrame(rows, docs_schema)
    for part in (d.withColumn("more", F.lit(1)), d.limit(0), d, d, d):
        store.append(part)
    store.compact()
    got = sorted(map(repr, store.read().collect()))
    assert got == sorted(4 * list(map(repr, d.collect())))


def test_no_python_on_the_main_path(spark, sf):
    plan = shard_store.op8_size_tiered_shards(spark, sf)._jdf.queryExecution().toString()
    assert not any(w in plan for w in ("Python", "Pandas", "Arrow"))
