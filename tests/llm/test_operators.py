"""Operators 1, 2, 4, 5, 9 and 10 against brute force, planted cases and hard rows."""

import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from tests.oracle import assert_same
from vintage.llm import queries, toxicity
from vintage.llm.chat_format import escape, events_of, format_chats, parse, render, unescape
from vintage.llm.embedding_dedup import near_duplicates, quantise, tile_links
from vintage.llm.quality_rules import COUNTS, FEATURES, Trees, base_failed, features, judge, statistics
from vintage.llm.sharding import assign, latest_map, measured, rebalance, rebalance_stored, shard, stored_maps
from vintage.llm.toxicity import Grammar, learn
from vintage.llm.toxicity import judge as judge_toxic
from vintage.llm.url_filter import filter_urls, node_of
from vintage.operators.components import connected_components

# --- 1 ---------------------------------------------------------------------


def brute_vectors(rows, threshold=0.9):
    ok = {k: np.array(v, np.float64) for k, v in rows if k is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v)}
    n, top = Counter(), {k: k for k in ok}

    def find(k):
        while top[k] != k:
            k = top[k]
        return k

    ids = sorted(ok)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if len(ok[a]) == len(ok[b]) and ok[a] @ ok[b] / (np.sqrt(ok[a] @ ok[a]) * np.sqrt(ok[b] @ ok[b])) >= threshold:
                n[a] += 1
                n[b] += 1
                p, q = sorted((find(a), find(b)))
                top[q] = p
    return {k: (n[k], find(k) if k in ok else k) for k, _ in rows}


def test_vectors_whole_table(spark, sf):
    rows = [(r.vec_id, r.embedding) for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect()]
    got = {r.vec_id: (r.n_links, r.component_id) for r in queries.op1_embedding_near_dedup(spark, sf).collect()}
    assert got == brute_vectors(rows)


@pytest.mark.parametrize("kind", ["float", "double"])
def test_vectors_hard_rows(spark, kind):
    rng = np.random.default_rng(5)
    base = rng.normal(size=(6, 16))
    rows = [(k, (base[k % 6] + rng.normal(size=16) * 0.22).astype(np.float32).tolist()) for k in range(300)]
    rows += [(300 + k, rows[0][1]) for k in range(40)]
    rows += [(400, None), (401, []), (402, [0.0] * 16), (403, [float("nan")] * 16), (404, [None] + [1.0] * 15), (405, [float("inf")] * 16), (406, [1.0, 2.0]), (407, [2.0, 4.0]), (408, [-0.0] * 15 + [1.0])]
    df = spark.createDataFrame([(k, v, 1, "x") for k, v in rows], f"vec_id long, embedding array<{kind}>, n_links int, v string")
    got = {r.vec_id: (r.n_links, r.component_id) for r in near_duplicates(df, tile_rows=32).collect()}
    assert got == brute_vectors(rows)
    assert near_duplicates(df.where("false")).count() == 0
    assert near_duplicates(spark.createDataFrame([(None, [1.0])], "vec_id long, embedding array<double>")).first().kept


def test_quantisation_bound_holds_and_spares_work():
    rng = np.random.default_rng(6)
    x = rng.normal(size=(200, 64))
    u = x / np.sqrt((x * x).sum(1))[:, None]
    q, s, e = quantise(u)
    about = (q.astype(float) * s[:, None]) @ (q.astype(float) * s[:, None]).T
    assert (np.abs(about - u @ u.T) <= e[:, None] + (1 + e)[:, None] * e[None, :]).all()
    links, recomputed = tile_links(x, x, 0.9, True)
    assert links.sum() == ((u @ u.T) >= 0.9).sum() - 200 and recomputed < 400


# --- 2 ---------------------------------------------------------------------

#: The contract's list, written out here so that a wrong word in the code or the SQL shows.
RULES = [("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block")]


def test_url_query_equals_its_sql(spark, sf):
    assert_same(spark, sf, queries.op2_url_filter, queries.ORACLE_SQL["op2_url_filter"])


def test_rules_decide_by_the_words_of_the_contract(spark, tmp_path):
    import duckdb

    link, moved = '<link rel="canonical" href="{}">', '<meta http-equiv="refresh" content="0;url={}">'
    rows = [
        (1, "http://a.com/en/1", ""), (2, "http://www.example.com/en/71", ""), (3, "http://a.net/de/1", ""), (4, "http://example.net/de/7", ""), (5, "http://www.Example.NET/de/8?q", ""), (6, "http://a.org/es/", ""),
        (7, "http://x.io/", link.format("http://never-seen.example.net/de/8")), (8, "http://y.io/", link.format("http://b.com/en/1") + moved.format("http://never-seen.net/de/1")), (9, "http://z.io/", link.format("http://c.com/en/1")),
    ]
    want = {1: ("com/en/", "block"), 2: ("example.com/en/7", "allow"), 3: ("net/de/", "allow"), 4: ("net/de/", "allow"), 5: ("example.net/de/8", "block"), 6: ("org/es/", "block"), 7: (None, "block"), 8: (None, "allow"), 9: (None, "block")}
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    df.toPandas().to_parquet(f"{tmp_path}/pages.parquet")
    assert {r.page_id: (r.rule, r.verdict) for r in queries.op2_url_filter(spark, str(tmp_path)).collect()} == want
    con = duckdb.connect()
    con.execute(f"CREATE VIEW pages AS SELECT * FROM '{tmp_path}/pages.parquet'")
    assert {k: v for k, *v in con.execute(f"SELECT page_id, rule, verdict FROM ({queries.ORACLE_SQL['op2_url_filter']})").fetchall()} == {k: list(v) for k, v in want.items()}


def test_aliases_take_decisions_and_allow_goes_first(spark):
    link = '<link href="{}" rel="canonical">'
    rows = [
        (1, "http://bad.com/en/x", ""), (2, "https://Mirror.net/a", link.format("http://bad.com/en/x")), (3, "https://third.net/b?q#f", '<meta http-equiv="refresh" content="0;url=https://mirror.net:443/a">'),
        (4, "HTTPS://third.net/b?q", ""), (5, "http://free.net/c", ""), (6, "http://example.com/en/7", link.format("http://good.net/")), (7, "http://good.net", ""), (8, "http://both.net/", link.format("http://good.net/")),
        (9, "http://both.net/", link.format("http://bad.com/en/x")), (10, None, None), (11, "no scheme", None), (12, "ftp://EXAMPLE.com:80/en/71?x", ""), (13, "http://com/en/", ""), (14, "http://xcom/en/", ""), (1, "http://bad.com/en/x", ""), (15, "http://moved.net/", ""),
    ]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, host string")
    moved = spark.createDataFrame([("http://moved.net/", "http://never-seen.example.net/de/1"), (None, "http://x.net/")], "from_url string, to_url string")
    got = {(r.page_id, r.verdict) for r in filter_urls(df, redirects=moved).collect()}
    # 8 and 9 tie both groups together: an allow among aliases goes before a block, rules of their own stay.
    assert got == {(1, "block"), (2, "allow"), (3, "allow"), (4, "allow"), (5, "allow"), (6, "allow"), (7, "allow"), (8, "allow"), (9, "allow"), (10, "allow"), (11, "allow"), (12, "allow"), (13, "block"), (14, "allow"), (15, "allow")}
    got = {(r.page_id, r.verdict) for r in filter_urls(df.where("page_id < 5")).collect()}
    assert got == {(k, "block") for k in (1, 2, 3, 4)}
    r = {x.page_id: (x.host, x.path, x.rule) for x in filter_urls(df).collect()}
    assert r[10] == r[11] == ("", "", None) and r[6] == ("example.com", "/en/7", "example.com/en/7")
    assert filter_urls(df.where("false")).count() == 0


def test_nodes(spark):
    from pyspark.sql import functions as F

    urls = ["HTTP://A.com:80/x/", "http://a.com/x?utm_source=1&ref=2#y", "https://a.com:443", "https://a.com:80?q", "https://a.com/x?p=1&utm_medium=z", None, "none"]
    df = spark.createDataFrame([(u,) for u in urls], "u string")
    assert [r[0] for r in df.select(node_of(F.col("u"))).collect()] == ["http://a.com/x/", "http://a.com/x?utm_source=1&ref=2", "https://a.com/", "https://a.com:80/?q", "https://a.com/x?p=1&utm_medium=z", None, None]
    assert [r[0] for r in df.select(node_of(F.col("u"), True)).collect()] == ["a.com/x", "a.com/x", "a.com", "a.com?q", "a.com/x?p=1", None, None]


def plain_verdicts(rows):
    """Verdicts by Python's own url functions and a plain search over links."""
    from urllib.parse import urljoin, urlsplit

    def ruled(url):
        rest = url.partition("://")[2] if url and "://" in url else ""
        host = re.match("[^/?#]*", rest)[0].lower()
        path = re.match("[^?#]*", rest[len(host) :])[0]
        fits = [(len(h + p), h + p, d) for h, p, d in RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        return max(fits)[2] if fits else None

    def node(url):
        u = urlsplit(url.partition("#")[0])
        port = {"http": ":80", "https": ":443"}.get(u.scheme.lower(), ":none")
        return u.scheme.lower(), u.netloc.lower().removesuffix(port), u.path or "/", u.query

    near, own = defaultdict(set), defaultdict(set)
    for _, url, html in rows:
        tags = [re.search(p, html or "") for p in (r'<link rel="canonical" href="([^"]*)">', r'<meta http-equiv="refresh" content="0;url=([^"]*)">')]
        for t in (m[1] for m in tags if m):
            to = urljoin(url, t) if url and "://" in url and t and t[0] != "#" and not t.startswith("mailto:") else t if "://" in t else None
            if to and url and "://" in url:
                near[node(url)].add(node(to))
                near[node(to)].add(node(url))
                for u in (url, to):
                    own[node(u)].add(ruled(re.sub(r"^(\w+://[^/?#:]*):(80|443)(?=[/?#]|$)", r"\1", u)))
    out = {}
    for k, url, _ in rows:
        verdict = ruled(url)
        if not verdict and url and "://" in url:
            seen, todo = {node(url)}, [node(url)]
            while todo:
                for n in near[todo.pop()] - seen:
                    seen.add(n)
                    todo.append(n)
            votes = set().union(*(own[n] for n in seen))
            verdict = "allow" if "allow" in votes else "block" if "block" in votes else None
        out[k] = verdict or "allow"
    return out


@pytest.mark.parametrize("dots", [False, True])
def test_links_between_many_pages(spark, tmp_path, dots):
    import duckdb

    rng = random.Random(21)
    hosts = ["a.com", "www.example.com", "b.net", "EXAMPLE.net", "c.org", "x.io", "y.io:80", "z.io"]
    paths = ["", "/", "/en/", "/en/7", "/en", "/de/8x", "/es/q?r=1", "/f/g/h", "/k?ref=2"] + (["/u/../en/v", "/de/./w/.."] if dots else [])
    targets = ["/en/1", "//b.net/de/2", "?z", "rel/x", "#s", "mailto:a@b", "", "https://a.com/en/"] + (["../de/9", "../../es/x", "./q", ".."] if dots else [])
    url = lambda: rng.choice(["http", "https"]) + "://" + rng.choice(hosts) + rng.choice(paths) + rng.choice(["", "", "#f"])
    rows = [(900, None, '<link rel="canonical" href="http://a.com/en/1">'), (901, "no scheme", None), (902, "http://only.io/x", "")]
    for k in range(400):
        html = rng.choice(["", f'<link rel="canonical" href="{rng.choice([url(), rng.choice(targets)])}">']) + rng.choice(["", "", f'<meta http-equiv="refresh" content="0;url={rng.choice([url(), rng.choice(targets)])}">'])
        rows.append((k, url().replace(".io", f"{k % 40}.io"), html))
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.verdict for r in filter_urls(df).collect()}
    assert got == plain_verdicts(rows) and Counter(got.values())["block"] > 25
    if not dots:
        df.toPandas().to_parquet(f"{tmp_path}/pages.parquet")
        con = duckdb.connect()
        con.execute(f"CREATE VIEW pages AS SELECT * FROM '{tmp_path}/pages.parquet'")
        cur = con.execute(queries.ORACLE_SQL["op2_url_filter"])
        names = [d[0] for d in cur.description]
        assert sorted(map(str, cur.fetchall())) == sorted(str(tuple(r[n] for n in names)) for r in filter_urls(df).collect())


def test_spelling_joins_only_if_asked(spark):
    df = spark.createDataFrame([(1, "http://a.com/en/", ""), (2, "http://a.com/en", ""), (3, "https://a.com/en?utm_source=x", "")], "page_id long, url string, html string")
    assert {r.page_id: r.verdict for r in filter_urls(df).collect()} == {1: "block", 2: "allow", 3: "allow"}
    assert {r.page_id: r.verdict for r in filter_urls(df, loose=True).collect()} == {1: "block", 2: "block", 3: "block"}


def test_url_filter_is_generated_code(spark):
    df = spark.createDataFrame([(k, f"http://h{k}.com/en/{k}", '<link rel="canonical" href="/x"><meta http-equiv="refresh" content="0;url=../y">') for k in range(50)], "page_id long, url string, html string")
    kept = spark.conf.get("spark.sql.codegen.fallback")
    spark.conf.set("spark.sql.codegen.fallback", "false")  # code beyond the limit of a method is an error then
    try:
        assert filter_urls(df).count() == 50
    finally:
        spark.conf.set("spark.sql.codegen.fallback", kept)


@pytest.mark.parametrize("contract,task", [(False, 1), (True, 100), (True, 10**6)])
def test_components_of_random_graphs(spark, monkeypatch, contract, task):
    monkeypatch.setattr("vintage.operators.components.TASK_EDGES", task)
    rng = random.Random(8)
    chain = [(i, i + 1) for i in range(200)]
    edges = [(rng.randint(1000, 1400), rng.randint(1000, 1400)) for _ in range(250)] + chain + [(5, 5), (None, 3)] + [(5000, 5001 + i) for i in range(300)]
    top = {k: k for e in edges for k in e if k is not None}

    def find(k):
        while top[k] != k:
            k = top[k]
        return k

    for a, b in edges:
        if a is not None:
            p, q = sorted((find(a), find(b)))
            top[q] = p
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "a long, b long"), "a", "b", contract=contract).collect()}
    assert got == {k: find(k) for e in edges for k in e if None not in e and e[0] != e[1]}
    assert connected_components(spark.createDataFrame([], "a long, b long"), "a", "b", contract=contract).count() == 0


# --- 4 ---------------------------------------------------------------------


def test_chat_query_equals_its_sql(spark, sf):
    assert_same(spark, sf, queries.op4_chat_format, queries.ORACLE_SQL["op4_chat_format"])


def test_any_text_comes_back():
    rng = random.Random(4)
    parts = ["<|", "|>", "<|end|>\n", "<|turn|>", "</s>", "[INST]", "[/INST]", "\\", "\n", "a", "<", "|", "/s>", "[", "\\\\", "é\U0001f600"]
    for _ in range(3000):
        turns = [(rng.choice(["user", "assistant", "a\nb\\", "", "<|end|>\n"]), "".join(rng.choice(parts) for _ in range(rng.randint(0, 9)))) for _ in range(rng.randint(0, 5))]
        text, spans = render(turns)
        assert parse(text) == turns
        assert [unescape(text[a:b]) for a, b in spans] == [t for r, t in turns if r == "assistant"]
        assert all(c not in escape(t) for _, t in turns for c in ("<|", "</s>", "[INST]", "[/INST]"))


def test_events_fold(spark):
    log = [
        (1, 0, "m", 0, "message", "user", "hi"), (1, 1, "m", 0, "message", "assistant", "wro"), (1, 1, "m", 1, "delta", None, "ng"), (1, 1, "m", 2, "regenerate", None, "ri"), (1, 1, "m", 3, "delta", None, "ght"),
        (1, 2, "m", 0, "message", "user", "x"), (1, 2, "m", 1, "edit", "user", "y"), (1, 3, "m", 0, "message", "user", "gone"), (1, 3, "m", 1, "delete", None, None), (1, 4, "m", 0, "delta", "tool", None),
        (None, 0, "m", 0, "message", "user", "a"), (None, 0, "m", 0, "message", "user", "b"), (2, None, None, None, None, None, None),
    ]
    rng = random.Random(1)
    rng.shuffle(log)
    df = spark.createDataFrame(log, "conv_id long, turn long, message string, seq long, kind string, role string, text string")
    got = sorted(((r.conv_id, parse(r.formatted)) for r in format_chats(df).collect()), key=str)
    assert got == sorted([(1, [("user", "hi"), ("assistant", "right"), ("user", "y"), ("tool", "")]), (2, [("", "")]), (None, [("user", "a")]), (None, [("user", "b")])], key=str)
    assert format_chats(df.where("false")).count() == 0


def test_long_texts_without_a_conversation(spark):
    """A row without an id is one conversation, however long, and as often as it stands."""
    text = "</s> é " * 2000
    rows = [(None, 0, "user", text), (None, 0, "user", text), (None, 1, "assistant", None), (5, 0, "user", text), (5, 0, "user", text), (5, 1, "assistant", "a" * 401)]
    got = [(r.conv_id, parse(r.formatted)) for r in format_chats(events_of(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))).collect()]
    assert sorted(got, key=str) == sorted([(None, [("user", text)])] * 2 + [(None, [("assistant", "")]), (5, [("user", text), ("user", text), ("assistant", "a" * 401)])], key=str)


# --- 5 ---------------------------------------------------------------------


def plain_clause(g, words):
    """The weight of a clause, hit by hit, without any automaton."""
    best, aimed = 0.0, any(w in toxicity.TARGETS for w in words)
    for i, w in enumerate(words):
        kind, x = g.symbol(w)
        if kind in toxicity.HITS:
            x *= toxicity.NEGATED if any(v in toxicity.NEGATIONS for v in words[max(0, i - toxicity.REACH) : i]) else 1
            x *= toxicity.REPORTED if any(v in toxicity.REPORTS for v in words[:i]) else 1
            best = max(best, (x + toxicity.TARGETED * (1 - x) if aimed else x) if kind == "insult" else x if aimed else toxicity.UNARMED * x)
    return best


def test_composed_automaton_equals_plain_rules():
    rng = random.Random(13)
    g = Grammar({"idiot": 0.9, "scum": 0.7}, {"lowei": 0.8})
    words = ["idiot", "scum", "loweis", "kill", "you", "not", "said", "a", "b", "c"]
    for _ in range(3000):
        w = [rng.choice(words) for _ in range(rng.randint(0, 9))]
        assert g.clause(w) == pytest.approx(plain_clause(g, w))
    text = "".join(rng.choice(words) + rng.choice([" ", " ", ", ", ". ", "\n"]) for _ in range(600))
    miss = 0.99
    for part in toxicity.CLAUSE_END.split(text.lower()):
        miss *= 1 - plain_clause(g, toxicity.WORD.findall(part))
    assert g.score(text) == pytest.approx(1 - miss)


def test_transducers_rewrite_one_after_another():
    mark = lambda t, tape: [s := t.start] and [(o := t.step(s, x)[0], s := o[0])[0][1] for x in tape]  # noqa: E731, F841
    tape = ["report", "negation", "other", "insult", "target", "insult"]
    once = mark(toxicity.negating(2), tape)
    assert once == ["report", "negation", "other", "insult-", "target", "insult"]
    assert mark(toxicity.reporting(), once) == ["report", "negation", "other", 'insult-"', "target", 'insult"']
    both = toxicity.compose(toxicity.negating(2), toxicity.reporting(), toxicity.SYMBOLS)
    assert mark(both, tape) == mark(toxicity.reporting(), once)


def test_whole_table_scores_by_plain_rules(spark):
    d = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    g = learn(docs, spark.read.parquet(f"{d}/labels.parquet"))
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in queries.op5_toxicity(spark, d).collect():
        miss = 0.99
        for part in toxicity.CLAUSE_END.split((texts[r.doc_id] or "").lower()):
            miss *= 1 - plain_clause(g, toxicity.WORD.findall(part))
        assert r.score == pytest.approx(1 - miss)


def test_toxicity_on_held_out_rows(spark):
    d = "/root/testdata/sf0.1"
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    rows = queries.op5_toxicity(spark, d).collect()
    assert len(rows) == 10_000 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in rows)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    met = Counter((labels[r.doc_id], r.predicted) for r in rows if r.held_out and r.doc_id in labels)
    assert met[1, 1] / (met[1, 1] + met[1, 0]) > 0.85 and met[0, 1] / (met[0, 1] + met[0, 0]) < 0.03


def test_clauses_not_words():
    g = Grammar({"idiot": 0.9}, {"lowei": 0.9})
    plain, negated, reported, aimed = (g.score(t) for t in ("that idiot came.", "that is not an idiot.", "he said that idiot came.", "you idiot."))
    assert negated < reported < plain < aimed
    assert g.score("Loweisch.") > 0.8 and g.score("slowei idiotic") == pytest.approx(0.01) and g.score("") == pytest.approx(0.01)
    assert g.score("not so. idiot") == pytest.approx(plain)  # a negation ends with its clause
    assert g.score("i will kill you") > 0.3 > g.score("kill the lights")


def test_toxicity_hard_rows(spark):
    docs = spark.createDataFrame([(1, None, 5), (2, "", 5), (None, "you idiot " * 20_000, 5)], "doc_id long, text string, toxic int")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = judge_toxic(docs, learn(docs, labels)).collect()
    assert len(got) == 3 and all(r.toxic == 0 for r in got)
    assert [r.toxic for r in judge_toxic(docs.where("doc_id is null"), Grammar({"idiot": 0.9}, {})).collect()] == [1]
    assert judge_toxic(docs.where("false"), Grammar({}, {})).count() == 0


# --- 9 ---------------------------------------------------------------------


def test_shards(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = queries.op9_sharding(spark, sf).collect()
    assert {r.doc_id: (r.size, r.text_crc32) for r in rows} == {k: (len(t.encode()) + 16, zlib.crc32(t.encode())) for k, t in texts.items()}
    by = defaultdict(list)
    for r in rows:
        by[r.shard].append(r)
    assert all(sorted(x.slot for x in v) == list(range(len(v))) for v in by.values()) and set(by) <= set(range(40))


def test_bytes_are_near_equal_also_with_one_hot_text(spark):
    d = "/root/testdata/sf0.1"
    load = Counter()
    for r in queries.op9_sharding(spark, d).collect():
        load[r.shard] += r.size
    assert len(load) == 40 and max(load.values()) < 1.02 * min(load.values())
    # A third of all rows hold one text; it is spread, as bytes could not be near equal otherwise.
    hot = spark.range(30_000).selectExpr("id as doc_id", "case when id % 3 = 0 then repeat('x', 500) else concat('t', id) end as text")
    load, copies = Counter(), Counter()
    for r in shard(hot).collect():
        load[r.shard] += r.size
        copies[r.shard] += r.size == 516
    assert max(load.values()) < 1.1 * min(load.values()) and min(copies.values()) > 150


def test_stored_map_is_versioned_and_edited(spark, tmp_path):
    docs = spark.range(20_000).selectExpr("id as doc_id", "repeat('y', cast(id % 90 as int)) as text")
    maps = f"{tmp_path}/map"
    first = {r.doc_id: (r.slot_id, r.shard) for r in shard(docs, 10, maps=maps).collect()}
    version, mapping = latest_map(spark, maps)
    assert version == 1 and len(mapping) == 8192 and all(mapping[s] == k for s, k in first.values())
    assert {r.doc_id: (r.slot_id, r.shard) for r in shard(docs, 99, maps=maps).collect()} == first  # the stored map decides
    version, moved = rebalance_stored(spark, maps, measured(docs), 11)
    assert version == 2 and 0 < moved < 8192 / 8
    grown = {r.doc_id: (r.slot_id, r.shard) for r in shard(docs, 11, maps=maps).collect()}
    assert all(grown[k][0] == s for k, (s, _) in first.items())  # records keep their slots
    changed = [k for k in first if first[k][1] != grown[k][1]]
    assert {grown[k][1] for k in changed} == {10} and len(changed) < 0.13 * len(first)
    assert sorted(r.version for r in stored_maps(spark, maps).select("version").distinct().collect()) == [1, 2]
    more = docs.union(spark.range(20_000, 40_000).selectExpr("id", "'new'"))
    assert shard(more, 11, maps=maps).count() == 40_000


def test_near_equal_bytes_and_few_moves():
    rng = random.Random(1)
    sums = {s: rng.randint(1000, 9000) for s in range(8192)}
    m = assign(sums, 40)
    loads = Counter()
    for s, k in m.items():
        loads[k] += sums[s]
    assert max(loads.values()) / min(loads.values()) < 1.002
    grown = rebalance(m, sums, 41)
    loads = Counter()
    for s, k in grown.items():
        loads[k] += sums[s]
    assert max(loads.values()) < 1.02 * sum(sums.values()) / 41 and sum(grown[s] != m[s] for s in m) < 1.5 * len(m) / 41
    shrunk = rebalance(m, sums, 39)
    assert set(shrunk) == set(m) and all(shrunk[s] == m[s] for s in m if m[s] < 39)


def test_shard_hard_rows(spark):
    df = spark.createDataFrame([(None, None, 1), (None, "a", 1), (1, "", 1), (1, "", 1), (2, "é", 1)], "doc_id long, text string, size int")
    got = sorted(((r.doc_id, r.size, r.text_crc32) for r in shard(df).collect()), key=str)
    assert got == sorted([(None, 16, 0), (None, 17, zlib.crc32(b"a")), (1, 16, 0), (1, 16, 0), (2, 18, zlib.crc32("é".encode()))], key=str)
    assert shard(df.where("false")).count() == 0


# --- 10 --------------------------------------------------------------------

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def by_hand(t):
    w = WORD.findall(t)
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    grams = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    hit = {i + k for i in range(len(w) - 4) if grams[tuple(w[i : i + 5])] > 1 for k in range(5)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(hit)


def test_statistics_by_hand():
    rng = random.Random(3)
    texts = ["", " ", "a\na\n \n\n a", "é ü\xa0x\x1c y", *("".join(rng.choice(["a", "b", " ", "\n", "\t", "#", "é", "c d e f g h "]) for _ in range(rng.choice([5, 60, 900]))) for _ in range(150))]
    got = statistics(texts)
    assert [tuple(r[:5]) for r in got.tolist()] == [by_hand(t) for t in texts]


def test_quality_whole_table(spark):
    d = "/root/testdata/sf0.01"
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{d}/documents.parquet").collect()}
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    rows = queries.op10_quality_rules(spark, d).collect()
    right = []
    for r in rows:
        want = by_hand(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0]) and not (r.base_failed and r.kept)
        if r.doc_id in labels and zlib.crc32(str(r.doc_id).encode()) % 4 == 2:
            right.append((r.quality_score >= 0.5) == labels[r.doc_id])
    assert np.mean(right) > 0.9


def test_trees_learn_and_stay_monotonic():
    rng = np.random.default_rng(2)
    x = rng.uniform(size=(3000, 3))
    y = ((x[:, 0] < 0.6) & (x[:, 1] > 0.3) | (rng.uniform(size=3000) < 0.05)).astype(float)
    t = Trees().fit(x, y, [-1, 0, 0])
    assert ((t.score(x) >= 0.5) == y).mean() > 0.93
    line = rng.uniform(size=(50, 3))
    scores = []
    for v in np.linspace(0, 1, 40):
        line[:, 0] = v
        scores.append(t.score(line))
    assert (np.diff(scores, axis=0) <= 1e-12).all()


def test_quality_hard_rows(spark):
    df = spark.createDataFrame([(1, None, 9), (None, "a b " * 30_000, 9), (2, " ".join(map(str, range(30))), 9)], "doc_id long, text string, n_words int")
    got = {r.doc_id: (r.n_words, r.base_failed, r.kept) for r in judge(df, None).collect()}
    assert got == {1: (0, True, False), None: (60_000, True, False), 2: (30, False, True)}
    assert judge(df.where("false"), None).count() == 0
    assert len(FEATURES) == features(np.ones((1, len(COUNTS)))).shape[1] and base_failed(np.zeros((1, len(COUNTS)), int))[0]


# --- the pipeline ----------------------------------------------------------


def test_pipeline_stage_by_stage(spark, sf):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    all_rows = {r.doc_id: r for r in docs.collect()}
    kept = set(all_rows)
    quality = {r.doc_id for r in queries.op10_quality_rules(spark, sf).collect() if r.kept}
    for k, (name, stage) in enumerate(p.STAGES):
        out = stage(spark, docs, sf)
        if k == 3:
            assert {r.doc_id for r in out.collect()} == kept
            break
        assert out.columns == docs.columns
        rows = out.collect()
        now = {r.doc_id for r in rows}
        assert len(rows) == len(now) and now <= kept and all(r == all_rows[r.doc_id] for r in rows)
        if k == 0:
            assert now == quality
        if k == 2:
            from tests.llm.test_minhash import brute

            assert now == {i for i, (_, c) in brute([(i, all_rows[i].text) for i in kept], 80).items() if i == c}
        kept = now
        docs = spark.createDataFrame(rows, docs.schema)


def test_pipeline_joins_copies_that_are_four_fifths_alike(spark):
    import corpus_pipeline as p

    words = [f"w{k}" for k in range(200)]
    copy = [f"x{k}" if k in (20, 70, 120, 170) else w for k, w in enumerate(words)]  # 176 of 216 shingles
    far = [f"y{k}" if k in (20, 60, 100, 140, 180) else w for k, w in enumerate(words)]  # 171 of 221: stays
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(copy)), (3, " ".join(far))], "doc_id long, text string")
    assert {r.doc_id for r in p.near_dedup(spark, docs, "").collect()} == {1, 3}


def test_near_dedup_stage_against_brute_force_at_80(spark, sf):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    sets = {}
    for r in docs.collect():
        w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in r.text or ""))
        sets[r.doc_id] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    part = {k: k for k in sets}
    for a in sorted(sets):
        for b in sorted(sets):
            both = len(sets[a] & sets[b])
            if a < b and both and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both) and part[a] != part[b]:
                low, high = sorted((part[a], part[b]))
                part = {k: low if c == high else c for k, c in part.items()}
    assert {r.doc_id for r in p.near_dedup(spark, docs, sf).collect()} == {k for k, c in part.items() if k == c}


def test_relative_targets_both_tags_and_slashes_of_targets(spark):
    from pyspark.sql import functions as F

    from vintage.llm.url_filter import resolved

    link, moved = '<link rel="canonical" href="{}">', '<meta http-equiv="refresh" content="0;url={}">'
    rows = [
        (1, "http://a.net/x/y", link.format("/de/1")), (2, "http://b.net/x", link.format("//shop.com/en/q")), (3, "http://c.net/x", link.format("http://c.net/other") + moved.format("http://d.com/en/z")),
        (4, "http://e.net/x", link.format("https://a.com/en/")), (5, "http://f.net/x/y", moved.format("../de/9")), (6, "http://g.net/x", link.format("mailto:x@y.com") + moved.format("#top")), (7, "http://h.net/x", link.format("http://k.com:80/en/1")),
        (8, "http://a.org/x/y", link.format("/es/1")), (9, "http://f.org/x/y", moved.format("../es/9")),
    ]
    got = {r.page_id: r.verdict for r in filter_urls(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {1: "allow", 2: "block", 3: "block", 4: "block", 5: "allow", 6: "allow", 7: "block", 8: "block", 9: "block"}
    want = {"g": "http://a/b/g", "./g": "http://a/b/g", "../g": "http://a/g", "../../../g": "http://a/g", "..": "http://a/", ".": "http://a/b/", "/g": "http://a/g", "//g": "http://g", "?y": "http://a/b/c?y", "g?y/../x": "http://a/b/g?y/../x", "#s": None, "mailto:a": None, "ftp://z/": "ftp://z/"}
    df = spark.createDataFrame([(t, "http://a/b/c?q#f") for t in want], "t string, u string")
    assert {r[0]: r[1] for r in df.select("t", resolved(F.col("t"), F.col("u"))).collect()} == want


def test_long_clause_is_read_from_its_start():
    from vintage.llm.toxicity import Grammar

    g = Grammar({}, {})
    far = "you " + "word " * 400 + "kill"
    assert g.score(far) == pytest.approx(1 - 0.99 * (1 - 0.6))
    assert g.score("x. " + far + ". kill") == pytest.approx(1 - 0.99 * (1 - 0.6) * (1 - 0.12))
    assert g.score("said " + "word " * 400 + "you kill") == pytest.approx(1 - 0.99 * (1 - 0.3))


def test_pipeline_stages_on_hard_rows(spark, sf):
    """Null ids and texts, repeated rows, clashing extra columns and an empty table, stage by stage."""
    import corpus_pipeline as p

    good = [r.text for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("lang = 'en' and n_chars between 800 and 3000").orderBy("doc_id").limit(3).collect()]
    rows = [(None, good[0], "x", 1), (1, None, "x", 1), (2, good[1], None, None), (2, good[1], None, None), (3, "", "y", 2), (4, good[2], "y", 2), (None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score string, n_words long")
    for empty in (False, True):
        now = docs.where("false") if empty else docs
        for k, (_, stage) in enumerate(p.STAGES):
            out = stage(spark, now, "/root/testdata/sf0.01")
            if k < 3:
                assert out.columns == docs.columns
                now = spark.createDataFrame(out.collect(), docs.schema)
            else:
                assert (out.count() == 0) == empty
