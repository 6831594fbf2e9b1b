"""Main text, archives, licences, language and the pipeline."""

import hashlib
import re
import time
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from incdep.llm import language, licenses, main_text, mixing, warc
from incdep.llm.common import read_file, write_file
from incdep.llm.dom import parse
from incdep.llm.license_texts import TEMPLATES
from incdep.llm.page_maker import MARK, labelled_pages

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var a="</p>";</script></head><body>
<header class="site-header"><h1>My site</h1><a href=/>Home</a></header><nav><ul><li><a href=/a>One</a><li><a href=/b>Two</a></ul></nav>
<div class="cookie-notice">We use cookies on this site. <button>OK</button></div>
<article><h1>A &amp; B&#39;s   story</h1><p>First <b>para</b>graph,
with  lines.<p>Unclosed &lt;p&gt; here.<ul><li>item one<li>item two</ul><div class="ad">Buy now, it is cheap.</div><p>End.</p></article>
<aside class="sidebar"><h3>Related</h3><p>Other things to read today.</p></aside>
<section id="comments"><h2>2 comments</h2><div class="comment"><p>I liked this a lot, thank you very much.</p></div></section>
<form><label>Mail</label><input><button>Send</button></form><footer>&copy; 2024 Somebody</footer></body></html>"""


def test_main_text_of_a_page():
    got = main_text.page_texts([PAGE, None, "", "<p>only this</p>", "<<<>>&&&; <b", "<div " * 2000], *main_text.trained())
    assert got[0] == "A & B's story First paragraph, with lines. Unclosed <p> here. item one item two End."
    assert got[1:3] == ["", ""] and got[3] == "only this"


def test_content_model_on_unseen_layouts():
    forest = main_text.Forest([parse(p) for p in labelled_pages(150, seed=99)])
    y = np.zeros(len(forest.nodes))
    for k, n in enumerate(forest.nodes):
        y[k] = float(n.attrs[MARK]) if MARK in n.attrs else y[forest.parent[k]] if forest.parent[k] >= 0 else 1.0
    p, _ = forest.marginals(*main_text.trained())
    assert ((p >= 0.5) == y)[forest.text].mean() > 0.98


# Written by hand, none in a layout of the page maker: (page, its main text)
OTHER_LAYOUTS = [
    (
        """<table width="100%"><tr><td colspan=2 bgcolor=navy><font color=white>The Harbour Chronicle</font></td></tr><tr><td valign=top width=120>
        <a href=i.html>Index</a><br><a href=w.html>Weather</a><br><a href=t.html>Tides</a></td><td><h2>Ferry service resumes</h2>
        The ferry between the two islands sailed again on Monday after three weeks of repairs to its engine.<br><br>Passengers who had waited on the
        quay since dawn said that they were glad to be going home at last.</td></tr><tr><td colspan=2><small>Copyright 1999 Harbour Press</small></td></tr></table>""",
        "Ferry service resumes The ferry between the two islands sailed again on Monday after three weeks of repairs to its engine. Passengers who had waited on the quay since dawn said that they were glad to be going home at last.",
    ),
    (
        """<body><div id="mw-page-base"></div><div class="mw-body" role="main"><h1 class="firstHeading">Limestone</h1><div class="toc"><ul><li><a href="#a">1 Origin</a></li>
        <li><a href="#b">2 Uses</a></li></ul></div><p>Limestone is a <a href="/s">sedimentary rock</a> made mostly of <a href="/c">calcite</a>, and it forms in warm shallow seas.</p>
        <h2>Uses</h2><p>It has been cut for buildings since ancient times, and it is burned to make lime for mortar.</p></div>
        <div id="mw-navigation" role="navigation"><ul><li><a href="/m">Main page</a></li><li><a href="/r">Random page</a></li></ul></div>
        <div id="footer"><ul><li>This page was last edited on 3 May.</li><li><a href="/p">Privacy policy</a></li></ul></div></body>""",
        "Limestone Limestone is a sedimentary rock made mostly of calcite, and it forms in warm shallow seas. Uses It has been cut for buildings since ancient times, and it is burned to make lime for mortar.",
    ),
    (
        """<main><div class="css-1x9"><div class="css-77a"><h1>Baking with rye</h1><div class="css-k2"><span>By Ada Moss</span> <time>4 June</time></div>
        <div class="css-p0">Rye flour has little gluten, so a loaf made with it alone stays dense and moist for days.</div>
        <div class="css-p0">Mix it with a third of wheat flour, and let the dough rest overnight in a cool room before you shape it.</div></div>
        <div class="share-buttons"><a href="#">Share</a><a href="#">Pin</a></div><div class="newsletter-box"><p>Get our recipes by mail every week.</p><form><input><button>Sign up</button></form></div></div></main>
        <footer><nav><a href="/a">About</a> <a href="/c">Contact</a></nav></footer>""",
        "Baking with rye Rye flour has little gluten, so a loaf made with it alone stays dense and moist for days. Mix it with a third of wheat flour, and let the dough rest overnight in a cool room before you shape it.",
    ),
    (
        """<div class="wrapper"><div class="masthead"><a href="/">devnotes</a></div><div class="sidebar-left"><a href="/1">Install</a><a href="/2">Configure</a><a href="/3">Deploy</a></div>
        <div class="content"><h1>Configure</h1><p>The server reads one file when it starts and does not look at it again.</p><pre>port = 80
        host = any</pre><p>Write each option on a line of its own, with a comment above it where the value is not obvious.</p>
        <ol><li>Stop the server first.</li><li>Edit the file and save it.</li></ol></div><div class="pagination"><a href="/1">Previous</a><a href="/3">Next</a></div></div>""",
        "Configure The server reads one file when it starts and does not look at it again. port = 80 host = any Write each option on a line of its own, with a comment above it where the value is not obvious. Stop the server first. Edit the file and save it.",
    ),
    (
        """<div class=top><ul><li><a href=/>Home</a><li><a href=/s>Sport</a><li><a href=/m>Money</a></ul></div><div class=gdpr-banner>We value your privacy. <button>Accept all</button></div>
        <div class=story><h1>Council votes for new bridge</h1><p>The council voted on Tuesday to build a second bridge across the river, after a debate that lasted until midnight.</p>
        <div class=advertisement>Cheap flights from 19!</div><blockquote>We have waited thirty years for this, said one member.</blockquote><p>Work is expected to begin in the spring and to take about four years.</p></div>
        <div class=related><h3>More news</h3><ul><li><a href=/x>Storm closes school</a><li><a href=/y>Mayor resigns</a></ul></div>
        <div class=comments><h3>Comments</h3><div class=reply><p>Finally! It was about time that they did this.</p></div></div>""",
        "Council votes for new bridge The council voted on Tuesday to build a second bridge across the river, after a debate that lasted until midnight. We have waited thirty years for this, said one member. Work is expected to begin in the spring and to take about four years.",
    ),
    (
        """<h1>On walking</h1><p>I have walked the same road each morning for ten years, and I have never seen it twice.</p><p>The light changes, the hedges grow, and the people whom I meet are older.</p>
        <hr><p><a href="/prev">older</a> | <a href="/next">newer</a></p>""",
        "On walking I have walked the same road each morning for ten years, and I have never seen it twice. The light changes, the hedges grow, and the people whom I meet are older.",
    ),
]


def test_content_model_on_pages_by_hand():
    """Word-level F1 of pages whose layouts the training pages don't have."""
    f1 = []
    for got, (_, want) in zip(main_text.page_texts([h for h, _ in OTHER_LAYOUTS], *main_text.trained()), OTHER_LAYOUTS, strict=True):
        a, b = Counter(got.split()), Counter(want.split())
        f1.append(2 * (a & b).total() / (a.total() + b.total()))
    assert np.mean(f1) > 0.9, f1


@pytest.mark.parametrize("part,close", [("<a ", ""), ('<a "', ""), ('<a b=">"', '"'), ("<!", ""), ("<!--", ""), ("<", ""), ("<a", ">"), ("<script>", ""), ("&", ""), ("<p><table><td><div>", ""), ("<li><div>x", "")])
def test_broken_markup_takes_linear_time(part, close):
    began = time.process_time()
    parse(part * ((1 << 19) // len(part)) + close)
    assert time.process_time() - began < 10


def test_deep_nesting():
    assert main_text.page_texts(["<div>" * 100_000 + "<p>A sentence that stands deep inside of a page, with some words.</p>"], *main_text.trained())[0] in ("", "A sentence that stands deep inside of a page, with some words.")
    depth = {}
    for k, n in enumerate(nodes := parse("<div>" * 2000)):
        depth[k] = depth[n.parent] + 1 if n.parent >= 0 else 0
    assert max(depth.values()) <= 513 and len(nodes) == 2001


def test_messages_give_exact_marginals():
    """Against the sum over all labellings of a small tree."""
    import itertools

    nodes = parse("<div><p>a b c d e</p><p class=ad>f</p><ul><li>g</ul></div>")
    forest = main_text.Forest([nodes])
    r = np.random.default_rng(0)
    w, pair = r.normal(size=len(main_text._FEATURES)), r.normal(size=(2, 2, 2))
    own = np.bincount(forest.owner, w[forest.feature], len(forest.nodes))
    total, one = 0.0, np.zeros(len(forest.nodes))
    for y in itertools.product((0, 1), repeat=len(forest.nodes)):
        s = sum(own[k] * y[k] for k in range(len(y))) + sum(pair[int(forest.text[k])][y[p], y[k]] for k, p in enumerate(forest.parent) if p >= 0)
        total += np.exp(s)
        one += np.exp(s) * np.asarray(y)
    assert forest.marginals(w, pair)[0] == pytest.approx(one / total)


def test_extract_rows(spark):
    df = spark.createDataFrame([(1, "u", PAGE, 5), (None, None, None, 6), (1, "u", PAGE, 5)], "page_id long, url string, html string, text int")
    got = main_text.extract(df).collect()
    assert len(got) == 3 and all(r["n_chars"] == len(r["text"]) for r in got) and got[1]["text"] == ""
    assert main_text.extract(df.limit(0)).count() == 0


def trick(k):
    return f"<p>{k}</p>WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:{900 + k}>\r\nContent-Length: {k}\r\n\r\nHTTP/1.1 200 OK\r\nContent-Length: 0\r\n\r\n" + "x" * (90 + k)


@pytest.fixture(scope="module")
def page_rows():
    rows = [(k, f"http://h/{k} \r\nx", trick(k)) for k in range(40)]
    rows += [(100 + k, "http://s", "same " * 50) for k in range(9)] + [(200 + k, None, "short") for k in range(3)]
    rows += [(300, "u", None), (301, "u", ""), (302, "ü", "é" * 60), (302, "ü", "é" * 60), (None, "n", "no id " * 30), (303, "u", "W" * 5000)]
    return rows


@pytest.mark.parametrize("range_bytes", [200, 1000, 1 << 20])
def test_archives(spark, page_rows, range_bytes):
    df = spark.createDataFrame(page_rows, "page_id long, url string, html string").withColumn("digest", F.lit(1)).repartition(3)
    manifest = warc.write_archives(df, file_bytes=4000)
    assert manifest.count() > 3
    got = warc.read_archives(manifest, range_bytes, head_bytes=2000, payloads=True).collect()
    first = {}
    for i, _, h in page_rows:
        b = (h or "").encode()
        if len(b) >= 100 and i is not None:
            first[b] = min(i, first.get(b, i))
    want = []
    for i, _, h in page_rows:
        b = (h or "").encode()
        to = first.get(b) if i is not None and first.get(b, i) != i else None
        want.append((-1 if i is None else i, len(b), hashlib.sha256(b).hexdigest(), "response" if to is None else "revisit", to))
    key = lambda r: tuple(-1 if x is None else x for x in r)
    assert sorted(((-1 if r["page_id"] is None else r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in got), key=key) == sorted(want, key=key)
    text = {r["page_id"]: r["payload"] for r in got if r["record_type"] == "response"}
    assert all(text[i] == (h or "") for i, _, h in page_rows if i is not None and i < 40)


def test_cut_archive_and_no_pages(spark, page_rows, tmp_path):
    df = spark.createDataFrame(page_rows[:10], "page_id long, url string, html string").coalesce(1)
    m = warc.write_archives(df).first()
    data = read_file(m["path"])
    write_file(f"file://{tmp_path}/cut.warc", data[:-20])
    cut = spark.createDataFrame([(f"file://{tmp_path}/cut.warc", len(data) - 20)], "path string, bytes long")
    assert warc.read_archives(cut, 500).count() == 9
    assert warc.read_archives(warc.write_archives(df.limit(0))).count() == 0


@pytest.mark.parametrize("range_bytes", [500, 1 << 20])
def test_headers_longer_than_the_window(spark, range_bytes):
    """A record whose header ends beyond range and window is read, and so is all that follows it."""
    urls = ["u", "http://h/" + "x" * 3000, "http://h/" + " y" * 40000, "v"]
    df = spark.createDataFrame([(k, urls[k % 4], trick(k)) for k in range(16)], "page_id long, url string, html string").coalesce(1)
    got = warc.read_archives(warc.write_archives(df), range_bytes, head_bytes=100).collect()
    assert sorted((r["page_id"], r["payload_bytes"]) for r in got) == [(k, len(trick(k))) for k in range(16)]
    assert {r["page_id"]: r["url"] for r in got} == {k: urls[k % 4].replace(" ", "%20") for k in range(16)}


def test_broken_chain_is_an_error(spark, page_rows, tmp_path):
    df = spark.createDataFrame(page_rows[:10], "page_id long, url string, html string").coalesce(1)
    data = read_file(warc.write_archives(df).first()["path"])
    at = data.index(b"\r\n\r\nWARC/1.1", len(data) // 2) + 4
    for name, got, size in (("bad", data[:at] + b"X" + data[at + 1 :], len(data)), ("short", data[:at], len(data))):
        write_file(f"file://{tmp_path}/{name}.warc", got)
        manifest = spark.createDataFrame([(f"file://{tmp_path}/{name}.warc", size)], "path string, bytes long")
        for range_bytes in (500, 1 << 20):
            with pytest.raises(Exception, match="no record at byte|which the manifest gives"):
                warc.read_archives(manifest, range_bytes).count()


def brute_matches(text, least):
    """Every template at every word of the text, word by word."""
    w, starts, ends = licenses.words(text.encode().lower())
    found = []
    for name, t in TEMPLATES.items():
        seq = licenses.words(t.encode().lower())[0]
        for a in range(len(w)):
            n = (w[a : a + len(seq)] == seq[: len(w) - a]).sum()
            if n >= least * len(seq) and w[a] == seq[0]:
                found.append((n, -len(seq), a, a + len(seq), name))
    out = []
    for m in sorted(found, key=lambda m: (-m[0], -m[1], m[2])):
        if all(min(m[3], o[3]) <= max(m[2], o[2]) for o in out):
            out.append(m)
    return sorted((o[4], int(starts[o[2]]), int(ends[o[3] - 1])) for o in out)


def test_licences_against_every_place(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet").filter("doc_id < 400")
    got: dict = {}
    for r in licenses.scan(docs).collect():
        got.setdefault(r["doc_id"], []).append(r)
    n = 0
    for r in docs.collect():
        if any(w in r["text"].lower() for w in ("licen", "permission", "public", "rights")):
            ascii_ = r["text"].isascii()
            want = brute_matches(r["text"], 0.95)
            mine = [(m["license"], m["start"], m["end"]) for m in got.get(r["doc_id"], []) if m["coverage"] >= 0.95]
            assert [x[0] for x in want] == sorted(x[0] for x in mine)
            assert not ascii_ or want == sorted(mine)
            n += len(want)
        else:
            assert r["doc_id"] not in got
    assert n > 5


def test_licences_changed_and_repeated(odd_docs, no_docs):
    ix = licenses.index(TEMPLATES)
    changed = TEMPLATES["mit"].replace("merge, ", "").replace("OTHER LIABILITY", "OTHER strange LIABILITY")
    got = licenses.scan_text(f"é before {changed} after", ix, 0.8)
    assert [(m[0], round(m[1], 2)) for m in got] == [("mit", 0.99)] and got[0][3:] == (9, 9 + len(changed) - 1)
    three = "Released under the MIT License. " * 3
    assert [m[3] for m in licenses.scan_text(three, ix, 0.8)] == [0, 32, 64]
    assert licenses.scan(odd_docs).count() == 0 and licenses.scan(no_docs).count() == 0


def test_language_on_held_out_documents(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    got = language.predictions(docs).join(docs, "doc_id").filter("held_out")
    assert got.filter("lang_pred = lang").count() >= 0.98 * got.count()
    assert got.filter("score < 0 or score > 1").isEmpty()


def test_language_odd_rows(odd_docs, no_docs):
    rows = {r["doc_id"]: r for r in language.predictions(odd_docs).collect()}
    assert language.predictions(odd_docs).count() == odd_docs.count()
    assert all(rows[k]["lang_pred"] == "und" and rows[k]["score"] == 0 for k in (0, 1, 2, 11))
    assert rows[4]["lang_pred"] in ("en", "de")
    unlabelled = language.predictions(odd_docs.withColumn("lang", F.lit(None).cast("string")))
    assert unlabelled.filter("lang_pred <> 'und'").isEmpty() and language.predictions(no_docs).count() == 0
    kept = language.keep_identified(odd_docs)
    assert kept.columns == odd_docs.columns and kept.filter("doc_id in (0, 1, 2, 11)").isEmpty() and not kept.filter("score = 0.5").isEmpty()


@pytest.mark.parametrize("size", [10, 1000])
def test_counts_do_not_depend_on_pieces(size):
    text = "Ünïted, we STAND\n\nand 123 fall —  apart " * 20
    assert (language.counts(text, size) == language.counts(text)).all()


def test_pipeline(spark, small, odd_docs):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    state = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        state = stage(spark, state, small)
        assert state.columns == docs.columns, name
        assert state.count() > 0.4 * docs.count()
    out = corpus_pipeline.run(spark, small)
    from test_tokens import packed

    packed(out.collect(), 1024)
    ids = {r["doc_id"]: r["n"] for r in state.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    got = {r["doc_id"]: r["n"] for r in out.filter("piece = 0").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert got == ids


def test_pipeline_stages_on_odd_rows(spark, odd_docs, no_docs):
    for docs in (odd_docs, no_docs):
        state = docs
        for _, stage in corpus_pipeline.STAGES:
            state = stage(spark, state, "")
            state.collect()


def test_mixture_takes_rows_as_planned(spark, odd_docs):
    """Rows without an id, and rows that share one, each come out as often as op3 plans."""
    rows = [(None, f"no id {'w ' * k}", "en", "a", 1) for k in range(30)] + [(7, f"same id {'w ' * k}", "en", "abc"[k % 3], 1) for k in range(30)]
    rows += [(100 + k, "some more words here", "en", "abc"[k % 3], 1) for k in range(60)]
    for docs in (spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long"), odd_docs):
        sizes = lambda r: len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or ""))
        plan = Counter()
        for r in mixing.mix(docs).collect():
            plan[r["doc_id"], r["source"], r["size"]] += r["copies"]
        got = corpus_pipeline.mixture(spark, docs, "")
        assert got.columns == docs.columns
        assert Counter((r["doc_id"], r["source"], sizes(r)) for r in got.collect()) == +plan
        assert docs is odd_docs or any(k[0] is None and k[2] for k in +plan)


def test_mixture_shuffles_no_texts(spark, small):
    """Also where the planned copies are too many to be broadcast, only row numbers are shuffled."""
    docs = spark.read.parquet(f"{small}/documents.parquet")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        got = corpus_pipeline.mixture(spark, docs, "")
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert "Exchange hashpartitioning" not in plan and "SortMergeJoin" not in plan
        assert plan.count("ArrowEvalPython") == 1
        assert got.count() > 0 and got.columns == docs.columns
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
