"""URL filter, packing, chat, HTML, decontamination, neighbours and language ID."""

import hashlib
import json
import random
import re
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from graphdist.llm import ann_search, chat_format, decontaminate, html_extract, language_id, packing, queries, url_filter


# URL filter ---------------------------------------------------------------------------------------------------

URLS = [
    "http://a.example.net/en/x", "https://EXAMPLE.net/de/", "http://example.com/de/y?q", "http://sub.example.com/de", "http://x.org/fr/", "http://org/fr/a#b", "http://myexample.net/en/",
    "no scheme", None, "", "http://", "http://net", "http://net/", "ftp://h?x://b", "http://a.b.org#/fr/", "http://é.net/", "http://x.org/fr", "http://notorg/fr/", "http://user@example.net:80/en/",
]


def judge(url):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        host = re.split("[/?#]", rest, maxsplit=1)[0]
        path = re.split("[?#]", rest[len(host) :], maxsplit=1)[0]
        host = re.sub("[A-Z]", lambda m: m[0].lower(), host)
    fits = [(len(h + p), len(h), h + p, v) for h, p, v in url_filter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return (host, path, *(max(fits)[2:] if fits else (None, "allow")))


def test_url_rules(spark):
    r = random.Random(1)
    urls = URLS * 3 + [f"http://{r.choice(['a.', 'b.c.', ''])}{r.choice(['example.net', 'example.com', 'x.org', 'de', 'net'])}{r.choice(['/en/', '/de/1', '/fr/', ''])}" for _ in range(300)]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumn("rule", F.lit("clash")).withColumn("m", F.create_map(F.lit("a"), F.lit(1)))
    got = {x["page_id"]: (x["host"], x["path"], x["rule"], x["verdict"]) for x in url_filter.judge_urls(pages, url_filter.rules_frame(spark)).collect()}
    assert got == {k: judge(u) for k, u in enumerate(urls)}
    assert url_filter.judge_urls(pages.limit(0), url_filter.rules_frame(spark)).isEmpty()


def test_url_nested_rules(spark):
    rules = [("com", "/", "block"), ("b.com", "/", "allow"), ("a.b.com", "/x/", "block"), ("a.b.com", "/x/y/", "allow")]
    pages = spark.createDataFrame([(1, "http://q.a.b.com/x/y/z"), (2, "http://a.b.com/x/z"), (3, "http://a.b.com/"), (4, "http://c.com/"), (5, "http://com.net/")], "page_id long, url string")
    got = {x["page_id"]: x["verdict"] for x in url_filter.judge_urls(pages, url_filter.rules_frame(spark, rules)).collect()}
    assert got == {1: "allow", 2: "block", 3: "allow", 4: "block", 5: "allow"}


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_oracles(spark, sf, name):
    c = duckdb.connect()
    for t in ("pages", "conversations"):
        c.sql(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    cur = c.execute(queries.oracle_sql()[name])
    names = [x[0] for x in cur.description]
    want = sorted(map(repr, cur.fetchall()))
    assert sorted(repr(tuple(r)) for r in queries.queries()[name](spark, sf).select(*names).collect()) == want


# packing ------------------------------------------------------------------------------------------------------


def test_ids_equal_those_of_whole_texts():
    coder = packing.encoder()
    r = random.Random(4)
    alphabet = list("abcXYZ '.,!?|%0129_-&*#$\n\t\x1c\x85\u00a0") + ["é", "É", "ß", "Σ", "ς", "İ", "ı", "\u0327", "ǅ", "中", "한", "…", "<|endoftext|>", "it's", "don't", "...'s"]
    texts = ["".join(r.choice(alphabet) for _ in range(r.randrange(40))) for _ in range(3000)] + ["", " ", "\n", "a" * 5000]
    for t, got in zip(texts, coder.ids([t.encode() for t in texts])):
        assert got == np.array(coder.tokenizer.encode(t, add_special_tokens=False).ids, dtype="<u4").tobytes(), repr(t)


def test_packing(spark, make_docs):
    r = random.Random(3)
    rows = [(i, " ".join(r.choice("alpha beta gamma".split()) for _ in range(r.choice([3, 50, 300, 2000, 9000])))) for i in range(150)] + [(900, None), (901, ""), (None, "x y"), (5, "again")]
    got = packing.pack(make_docs(rows)).collect()
    coder = packing.encoder().tokenizer
    want = []
    for d, t in rows:
        ids = coder.encode(t or "", add_special_tokens=False).ids + [1]
        want += [(-1 if d is None else d, k // 4096, k, len(ids[k : k + 4096]), zlib.crc32(np.array(ids[k : k + 4096], dtype="<u4").tobytes())) for k in range(0, len(ids), 4096)]
    assert sorted((-1 if x["doc_id"] is None else x["doc_id"], x["piece"], x["start"], x["length"], x["ids_crc32"]) for x in got) == sorted(want)
    bins = {}
    for x in got:
        bins.setdefault(x["sequence_id"], []).append((x["offset"], x["length"]))
    for b in bins.values():
        b.sort()
        assert [o for o, _ in b] == [sum(n for _, n in b[:i]) for i in range(len(b))] and sum(n for _, n in b) <= 4096
    assert len(bins) <= -(-sum(x["length"] for x in got) // 4096) + 1
    assert packing.pack(make_docs([])).isEmpty()


def test_local_search_empties_bins():
    lengths = [6, 5, 5, 4, 4, 3, 3]  # first: three bins of 10 would do
    bins = packing.local_search([[0, 5], [1, 3], [2, 4], [6]], lengths, 10)
    assert len(bins) == 3 and sorted(k for b in bins for k in b) == list(range(7)) and all(sum(lengths[k] for k in b) <= 10 for b in bins)
    r = random.Random(2)
    lengths = [r.randrange(1, 60) for _ in range(500)]
    packed = packing.local_search(packing.best_fit(lengths, 100), lengths, 100)
    assert len(packed) <= -(-sum(lengths) // 100) + 1


def test_local_search_ends_only_where_no_exchange_is_left():
    r = random.Random(1)
    lengths = [r.randrange(1000, 2701) for _ in range(2500)]
    packed = packing.local_search(packing.best_fit(lengths, 4096), lengths, 4096)
    assert sorted(k for b in packed for k in b) == list(range(2500))
    bins = [sorted(lengths[k] for k in b) for b in packed]
    fill = np.array([sum(b) for b in bins])
    sums = [(t, m) for t, b in enumerate(bins) for m in {0, *b}]
    pairs = [(t, x + y) for t, b in enumerate(bins) for i, x in enumerate(b) for y in b[i + 1 :]]
    for outs, backs in ((sums, sums), (sums, pairs), (pairs, sums)):
        t, m = np.array(backs).T
        for g, n in outs:
            d = n - m
            assert not ((t != g) & (d > 0) & (d <= 4096 - fill[t]) & (fill[t] + d > fill[g])).any()


# chat ---------------------------------------------------------------------------------------------------------


def call(i, name="search", **args):
    return {"id": i, "name": name, "arguments": args}


def test_chat_linking(spark):
    say = lambda *calls: json.dumps({"content": "c", "tool_calls": list(calls)})
    result = lambda i: json.dumps({"tool_call_id": i, "content": {"b": 1, "a": 2}})
    rows = [
        (1, 0, "user", "hi"), (1, 1, "tool", result("k1")), (1, 2, "assistant", say(call("k1", query="q"), call("k2", query=3))), (1, 3, "tool", result("k2")), (1, 4, "tool", result("zz")),
        (2, 0, "assistant", say(call("a", query="$ref:b"))), (2, 1, "tool", result("b")), (2, 2, "assistant", say(call("b", "calculator", expression="1"))),
        (3, 0, "assistant", say(call("p", query="$ref:q"))), (3, 1, "assistant", say(call("q", query="$ref:p"))), (3, 2, "tool", result("p")), (3, 3, "tool", result("q")),
        (None, 0, "user", None), (4, 0, "user", "{not json"), (4, 0, "user", "{not json"), (5, 0, "assistant", say(call("u", "unknown"))),
    ]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("mid", F.lit("clash"))
    got = {}
    out = chat_format.format_chats(df).collect()
    for x in out:
        got.setdefault(x["conv_id"], []).append(x)
    for v in got.values():
        v.sort(key=lambda x: x["position"])
        assert [x["position"] for x in v] == list(range(len(v)))
    one = got[1]
    assert [x["turn"] for x in one] == [0, 2, 1, 3, 4]  # the result that came too early stands behind its call
    assert (one[1]["n_calls"], one[1]["n_invalid"]) == (2, 1) and one[2]["linked"] and one[4]["orphan"]
    assert one[2]["json"] == '{"content":{"a":2,"b":1},"role":"tool","tool_call_id":"k1"}'
    assert [x["turn"] for x in got[2]] == [2, 1, 0]
    assert [x["cyclic"] for x in got[3]] == [True] * 4
    assert got[None][0]["json"] == '{"content":null,"role":"user"}' and len(got[4]) == 2 and got[5][0]["n_invalid"] == 1
    assert len(out) == len(rows)
    assert chat_format.format_chats(df.limit(0)).isEmpty()


def chain(n, extra=()):
    """Message k + 1 follows message k although all stand in the opposite order of turns."""
    return {k: n - k for k in range(n)}, [(k + 1, k) for k in range(n - 1)] + list(extra)


def test_order_of_long_chains_and_cycles(spark):
    turns, before = chain(1000)
    found = chat_format.order_messages(turns, before)
    assert sorted(found, key=lambda m: found[m][:2]) == list(range(1000)) and not any(v[2] for v in found.values())
    turns, before = chain(40, [(10, 12)])  # 10, 11 and 12 follow each other
    found = chat_format.order_messages(turns, before)
    assert [m for m in found if found[m][2]] and {m for m in found if found[m][2]} == {10, 11, 12}
    after = sorted((m for m in found if m > 12), key=lambda m: found[m][:2])
    assert after == list(range(13, 40))
    # the same by rounds of joins, as for components too large for a task
    turns, before = chain(8, [(3, 5)])
    read = spark.createDataFrame(list(turns.items()), "mid long, turn long")
    edges = spark.createDataFrame(before, "mid long, from_mid long")
    for local in (100, 1):
        got = {r["mid"]: (r["late"], r["depth"], r["cyclic"]) for r in chat_format._order(read, edges, local).collect()}
        assert {m for m in got if got[m][2]} == {3, 4, 5}
        assert sorted((m for m in got if m < 3), key=lambda m: got[m][:2]) == [0, 1, 2]


def test_schema_checks():
    s = {"type": "object", "required": ["a"], "properties": {"a": {"type": "integer"}, "b": {"enum": ["x"]}, "c": {"type": "array", "items": {"type": "number"}}}, "additionalProperties": False}
    good = [{"a": 1}, {"a": 1, "b": "x", "c": [1, 2.5]}]
    bad = [{}, {"a": True}, {"a": 1, "b": "y"}, {"a": 1, "c": ["x"]}, {"a": 1, "z": 0}, [], None]
    assert all(chat_format.conforms(x, s) for x in good) and not any(chat_format.conforms(x, s) for x in bad)


# HTML ---------------------------------------------------------------------------------------------------------

FURNITURE = (
    '<nav><ul><li><a href="/a">Menu</a></ul></nav>', "<header><div>Site name and a long slogan of many words here</div></header>", '<aside class="sidebar"><p>Side story text</p></aside>',
    '<div class="cookie-notice">We use cookies. Read this long notice about them.</div>', '<div class="ad">Buy now.</div>', '<form><label>Mail</label><input name="x"></form>',
    '<section id="comments"><p>First! Nice article, I liked reading it.</p></section>', "<script>var t='</p>';</script>", "<style>p{margin:0}</style>", "<footer>&copy; us</footer>", "<!-- <p>gone</p> -->",
)


def page(inner, around=FURNITURE):
    return "<!DOCTYPE html><html><head><title>T</title></head><body>" + "".join(around[:6]) + inner + "".join(around[6:]) + "</body></html>"


def test_html_main_text():
    tree = html_extract.train()
    text = lambda p: html_extract.main_text(p, tree)
    body = "<article><h1>Title &amp; more</h1><p><b>One\n two</b><br><p>Three &eacute;&#33;</p><p>S.</p><ul><li>x<li>y</ul></article>"
    assert text(page(body)) == "Title & more\n\nOne two\n\nThree é!\n\nS.\n\nx\n\ny"
    assert text(page("<article><p>A b c</p><div class='share-buttons'>Share this</div><aside>More</aside><p>D</p></article>")) == "A b c\n\nD"
    assert text(page("<main><p>Words in main</p></main>")) == "Words in main"
    assert text(page("<article><p>cut off &am")) .startswith("cut off &am")
    assert text("<article><p>a < b and c > d</p><p>e</p><scr") == "a < b and c > d\n\ne"
    assert text(None) == "" and text("") == "" and text("<html><body></body></html>") == "" and text("<article><script>x") == ""
    assert len(text("<article>" + "<p>w</p>" * 20000 + "</article>")) == 20000 * 3 - 2


HIDDEN = {
    "plain": (
        "<body><div class='k1'><a href='/'>Home</a></div><div class='k1'><a href='/n'>News</a></div><div class='k2'><a href='/l'>Log in</a></div>"
        "<div class='zz'><h1>The river that runs uphill</h1><p>{0}</p><p>{1}</p><p>{2}</p></div>"
        "<div class='q7'>Copyright 2020 All rights reserved</div><div><a href='/x'>Contact us</a></div></body>"
    ),
    "teaser": (
        "<body><article><h2>Teaser</h2></article><div class='b1'><h1>The river that runs uphill</h1><p>{0}</p><p>{1}</p><p>{2}</p></div>"
        "<div class='b9'>Copyright 2020 All rights reserved</div></body>"
    ),
    "table": (
        "<table><tr><td><a href='/1'>one two</a></td><td><a href='/2'>three four</a></td></tr><tr><td><a href='/3'>Log in</a></td></tr>"
        "<tr><td><b>The river that runs uphill</b><p>{0}<p>{1}<p>{2}</td></tr><tr><td><a href='/4'>Older posts of this site</a></td></tr></table>"
    ),
}


@pytest.mark.parametrize("name", HIDDEN)
def test_html_layouts_without_marks(name):
    """Layouts the labelled pages don't hold, with class names that say nothing."""
    r = random.Random(4)
    paragraphs = [" ".join(r.choice(["water", "stone", "of", "the", "valley", "and"]) for _ in range(n)) for n in (48, 61, 39)]
    got = html_extract.main_text(HIDDEN[name].format(*paragraphs), html_extract.train())
    assert got == "\n\n".join(["The river that runs uphill", *paragraphs])


def test_html_tree_uses_words_and_neighbours():
    used, stack = set(), [html_extract.train()]
    while stack:
        t = stack.pop()
        if isinstance(t, tuple):
            used.add(t[0])
            stack += t[2:]
    assert 0 in used and used & {2, 3, 4, 5}
    table = html_extract.labelled_table()
    tree = html_extract.train()
    assert np.mean([html_extract.classify(tree, x[:-1]) == x[-1] for x in table]) > 0.97


def test_html_table(spark):
    df = spark.createDataFrame([(1, "u", "<article><p>Hello</p></article>"), (2, None, None), (2, None, None)], "page_id long, url string, html string").withColumn("text", F.lit("clash"))
    got = sorted(tuple(r) for r in html_extract.extract(df).select("page_id", "text", "n_chars").collect())
    assert got == [(1, "Hello", 5), (2, "", 0), (2, "", 0)]
    assert html_extract.extract(df.limit(0)).isEmpty()


def test_html_given_pages(spark, sf):
    """All blocks of the article and nothing else, against an independent reading of the given pages' template."""
    import html

    for r in html_extract.extract(spark.read.parquet(f"{sf}/pages.parquet")).join(spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "html"), "page_id").collect():
        inner = r["html"].split("<article>", 1)[1].split("</article>")[0]
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]*>", " ", b)).split()) for b in re.split(r"</?(?:p|h1)>", inner)]
        assert r["text"] == "\n\n".join(b for b in blocks if b)


# decontamination ----------------------------------------------------------------------------------------------


def brute_hits(text, items, window=13):
    low = lambda s: re.sub("[A-Z]", lambda m: m[0].lower(), s or "")
    words = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+").findall
    w = words(low(text))
    hit, found = [False] * len(w), set()
    for i, t in items:
        q = words(low(t))
        m = min(window, len(q))
        wins = {tuple(q[k : k + m]) for k in range(len(q) - m + 1)} if q else ()
        for k in range(len(w) - m + 1) if wins else ():
            if tuple(w[k : k + m]) in wins:
                found |= {i} - {None}  # an item without an id hits words but isn't counted
                hit[k : k + m] = [True] * m
    n = sum(hit)
    return len(w), n, len(found), hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest(), n > 0 and 20 * n >= len(w)


@pytest.mark.parametrize("max_bytes", [decontaminate.MAX_BYTES, 300])
def test_decontamination_matches_brute_force(spark, make_docs, max_bytes):
    r = random.Random(6)
    v = [f"word{i}" for i in range(30)] + ["É", "ñandú", "a"]
    items = [(i, " ".join(r.choice(v) for _ in range(r.choice([1, 2, 5, 13, 14, 40])))) for i in range(12)] + [(50, None), (51, "?!"), (None, "word1"), (10, "zz")]
    rows = [(i, ("; ".join(r.choice(v) for _ in range(r.randrange(60))) + " " + r.choice(items[:12])[1].upper() + ", " + " ".join(r.choice(v) for _ in range(r.randrange(200))))) for i in range(40)]
    rows += [(100, None), (101, ""), (102, "Clean text, nothing of it."), rows[0]]
    bench = spark.createDataFrame(items, "item_id long, text string")
    clash = make_docs(rows).withColumn("n_hit", F.lit("clash")).withColumn("h", F.lit(1)).withColumn("i", F.lit(1)).withColumn("_row", F.lit(1)).withColumn("key", F.create_map(F.lit("a"), F.lit(1)))
    out = decontaminate.contamination(clash, bench, max_bytes=max_bytes).collect()
    got = sorted((x["doc_id"], x["n_words"], x["n_hit"], x["n_items"], x["items_sha256"], x["contaminated"]) for x in out)
    assert got == sorted((d, *brute_hits(t, items)) for d, t in rows)
    assert decontaminate.contamination(make_docs([]), bench).isEmpty()
    assert decontaminate.keep_clean(make_docs(rows), bench.limit(0)).count() == len(rows)


# neighbours ---------------------------------------------------------------------------------------------------


def brute_neighbours(ids, x, every=20, k=20):
    """{(id, its row's place)}: the k nearest others of each query row, compared with all rows of its length."""
    out = []
    for q in np.flatnonzero(ids % every == 0):
        s = (x * x[q]).sum(axis=1)
        order = [j for j in np.lexsort((ids, -s)) if j != q][:k]
        out.append((int(ids[q]), [(int(ids[j]), float(s[j])) for j in order]))
    return out


@pytest.mark.parametrize("rows", [1000, 6000])
def test_neighbours_recall_of_the_routed_search(spark, rows):
    """Vectors that hardly cluster, more than one can hold in a partition: at most half of the partitions are probed at either size."""
    r = np.random.default_rng(3)
    x = r.normal(size=(rows, 48)).astype(np.float32) + 0.6 * r.normal(size=(40, 48))[r.integers(0, 40, rows)].astype(np.float32)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    table = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = {}
    for f in ann_search.search(table).collect():
        got.setdefault(f["query_id"], []).append((f["rank"], f["vec_id"], f["score"]))
    want = brute_neighbours(np.arange(rows), x.astype(np.float64))
    assert set(got) == {q for q, _ in want} and all(len(v) == 20 for v in got.values())
    hits = sum(len({v for v, _ in near} & {v for _, v, _ in got[q]}) for q, near in want)
    assert hits / (20 * len(want)) >= 0.9
    assert ann_search.SHARE <= 0.5


def test_neighbours(spark, sf):
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    rows = e.collect()
    bad = [(9000, None), (9020, [0.0] * 64), (9040, [float("nan")] + [1.0] * 63), (9080, [None] + [1.0] * 63), (None, [1.0] * 64)]
    short = [(9060, [1.0, 2.0]), (9061, [3.0, 1.0])]  # another length: compared among themselves
    hot = rows[20]["embedding"]
    again = (int(rows[40]["vec_id"]), rows[7]["embedding"])  # an id that repeats with another vector
    both = e.select("vec_id", "embedding").union(spark.createDataFrame(bad + short + [again] + [(10000 + i, hot) for i in range(60)], "vec_id long, embedding array<float>"))
    got = {}
    for f in ann_search.search(both).collect():
        got.setdefault(f["query_id"], []).append((f["rank"], f["vec_id"], f["score"]))
    assert got.pop(9060) == [(1, 9061, 5.0)]
    ids = np.array([r["vec_id"] for r in rows] + [again[0]] + [10000 + i for i in range(60)])
    x = np.array([r["embedding"] for r in rows] + [again[1]] + [hot] * 60, dtype=float)
    want = brute_neighbours(ids, x)
    assert sorted(got) == sorted({q for q, _ in want}) and len(got[again[0]]) == 40
    hits = total = 0
    for q, near in want:
        found = sorted(got[q])
        if q != again[0]:
            assert [k for k, _, _ in found] == list(range(1, 21))
            assert [(-sc, v) for _, v, sc in found] == sorted((-sc, v) for _, v, sc in found)
            exact = dict(near)
            assert all(abs(exact[v] - sc) < 1e-12 for _, v, sc in found if v in exact)
            hits += len(set(exact) & {v for _, v, _ in found})
            total += 20
    assert hits / total >= 0.9
    assert ann_search.search(both.limit(0)).isEmpty()
    few = ann_search.search(both.filter("vec_id < 5")).collect()
    assert sorted(r["vec_id"] for r in few) == [1, 2, 3, 4]


def test_partitions_are_balanced():
    r = np.random.default_rng(0)
    x = r.normal(size=(800, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    label = ann_search.balanced_partition(x, ann_search.neighbour_graph(x), 8)
    assert np.bincount(label, minlength=8).max() <= np.ceil(1.15 * 100)


# language ID --------------------------------------------------------------------------------------------------


def test_viterbi_matches_a_plain_one():
    r = np.random.default_rng(1)
    words = [f"w{k}" for k in range(30)]

    class Fixed:
        langs = ["a", "b", "c"]
        table = {w: r.normal(size=3).astype(np.float32) * 6 for w in words}

        def score(self, ws):
            return np.array([self.table[w] for w in ws]), np.ones(len(ws), dtype=bool)

    texts = [" ".join(r.choice(words, size=n)) for n in (1, 2, 5, 17, 40)] + [None, ""]
    labels = language_id.label_words(texts, Fixed(), 4.0)[0]
    for text, got in zip(texts, labels):
        ws = (text or "").split()
        best = {0: (0.0, []), 1: (0.0, []), 2: (0.0, [])}
        for w in ws:
            step = {}
            for k in range(3):
                value, path = max(((best[j][0] - 4.0 * (j != k), best[j][1]) for j in range(3)), key=lambda t: t[0])
                step[k] = (value + float(Fixed.table[w][k]), [*path, k])
            best = step
        path = max(best.values(), key=lambda t: t[0])[1] if ws else []
        cost = lambda p: sum(float(Fixed.table[w][k]) for w, k in zip(ws, p)) - 4.0 * sum(a != b for a, b in zip(p, p[1:]))
        assert len(got) == len(ws) and abs(cost(got.tolist()) - cost(path)) < 1e-3


def test_language_held_out_accuracy(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    found = queries.queries()["op10_language_id"](spark, sf).join(docs.select("doc_id", "lang"), "doc_id").collect()
    out = [r for r in found if r["held_out"]]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in found)
    assert sum(r["lang"] == r["lang_pred"] for r in out) / len(out) >= 0.97
    assert all(0 <= r["score"] <= 1 for r in found)


def test_language_spans_and_edge_cases(spark, make_docs):
    r = random.Random(2)
    en, fr, ru = "the and with that have this from they".split(), "le être avec pour dans une été où".split(), "и не что он на я быть это".split()
    text = lambda ws, n: " ".join(r.choice(ws) for _ in range(n))
    labelled = spark.createDataFrame([(i, text(ws, 60), g) for i, (ws, g) in enumerate([(en, "en"), (fr, "fr"), (ru, "ru")] * 20)] + [(99, None, "en"), (98, "x", None)], "doc_id long, text string, lang string")
    model = language_id.train(labelled)
    assert model.langs == ["en", "fr", "ru"]
    mixed = text(en, 30) + " " + text(fr, 30) + " " + text(ru, 30)
    docs = make_docs([(1, mixed), (2, None), (3, ""), (4, "123 !? 45"), (5, text(ru, 5)), (6, "漢字 かな"), (6, "漢字 かな"), (7, text(fr, 20000))])
    got = {x["doc_id"]: x for x in language_id.identify(docs.withColumn("score", F.lit("clash")), model).collect()}
    assert [s["lang"] for s in got[1]["spans"]] == ["en", "fr", "ru"]
    assert [got[k]["lang_pred"] for k in (2, 3, 4)] == ["und"] * 3 and got[5]["lang_pred"] == "ru" and got[6]["lang_pred"] in model.langs
    assert got[7]["lang_pred"] == "fr" and got[7]["score"] > 0.9
    assert language_id.keep_identified(docs, model).count() == 5
    assert language_id.identify(make_docs([]), model).isEmpty()
    empty = language_id.train(labelled.limit(0))
    assert {x["lang_pred"] for x in language_id.identify(docs, empty).collect()} == {"und"}


def test_every_letter_counts():
    texts = {"dv": "ދިވެހި ބަސް ރާއްޖޭގެ", "en": "ｈｅｌｌｏ ｗｏｒｌｄ", "ii": "ꆈꌠ ꉙ ꁱꂷ"}  # Thaana, fullwidth Latin, Yi
    langs = sorted(texts)
    counts, scripts = np.zeros((1 << 16, 3)), np.zeros((language_id.N_SCRIPTS, 3))
    for k, g in enumerate(langs):
        feat, _, script = language_id._features(texts[g].split(), 16)
        np.add.at(counts[:, k], feat, 1)
        np.add.at(scripts[:, k], script, 1)
    model = language_id.Model(langs, counts, scripts, 16)
    for g, t in texts.items():
        got, score, spans = language_id.predict([t], model)[0]
        assert got == g and score > 0.5 and [x[2] for x in spans] == [g]
    assert [x[0] for x in language_id.predict(["123 !?", "१२३ ×", None], model)] == ["und"] * 3
