"""Hand-sized examples, brute force and invariants of the methods."""

import math
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from vintage.functions.text import canonical, fold, near, sentences, tokens
from vintage.plans import ablate, audit, compare, corpora, curves, mining, ngram_lm, probes


def curve_of(spark, values, model="m"):
    return spark.createDataFrame([(model, i, float(v), 1) for i, v in enumerate(values)], "model string, month_ix int, ppl double, n long")


def test_relative_and_argmin(spark):
    rows = curves.relative(curve_of(spark, [2, 4, 3])).orderBy("month_ix").collect()
    assert [r.rel for r in rows] == [0.0, 1.0, 0.5]
    assert all(r.rel is None for r in curves.relative(curve_of(spark, [5, 5])).collect())
    assert curves.effective_cutoff(curves.relative(curve_of(spark, [3, 1, 2, 1]))).first().cutoff == 1
    assert curves.effective_cutoff(curves.relative(curve_of(spark, [5, 5]))).count() == 0


def test_scaling_a_curve_leaves_it_alone(spark):
    rng = random.Random(1)
    values = [rng.uniform(1, 9) for _ in range(20)]
    one, other = (sorted((r.month_ix, round(r.rel, 9)) for r in curves.relative(curve_of(spark, [k * v for v in values])).collect()) for k in (1, 37.5))
    assert one == other and min(x for _, x in one) == 0 and max(x for _, x in one) == 1


@pytest.mark.parametrize("n,k", [(1, 0), (39, 0), (40, 1), (80, 2)])
def test_trim(spark, n, k):
    rng = random.Random(n)
    values = [rng.uniform(0, 100) for _ in range(n)]
    df = spark.createDataFrame([("m", 0, i, v) for i, v in enumerate(values)], "model string, month_ix int, topic_id long, ppl double")
    kept = sorted(values)[k : n - k]
    assert curves.trimmed_mean(df).first().ppl == pytest.approx(sum(kept) / len(kept))


def test_rise_rule(spark):
    flat = curves.relative(curve_of(spark, [1, 1.1, 0.9, 1, 8, 9, 8]))
    assert curves.effective_cutoff(flat, "rise").first().cutoff == 3
    assert curves.effective_cutoff(curves.relative(curve_of(spark, [9, 8, 1])), "rise").count() == 0


def test_spread_sums_to_one(spark):
    r = curves.cutoff_spread(curves.relative(curve_of(spark, [3, 1, 1.01, 2]))).first()
    assert r.months == [1, 2] and sum(w.weight for w in r.weights) == pytest.approx(1)


def lm_by_hand(docs, probe, order, lam=ngram_lm.LAMBDA, v=ngram_lm.VOCABULARY):
    grams = [Counter(tuple(d[i : i + n]) for d in docs for i in range(len(d) - n + 1)) for n in (1, 2, 3)]
    total = sum(len(d) for d in docs)
    out = []
    for i, w in enumerate(probe):
        p = (grams[0][(w,)] + 1) / (total + v)
        for n in range(2, order + 1):
            if i >= n - 1 and grams[n - 2][tuple(probe[i - n + 1 : i])]:
                p = lam * grams[n - 1][tuple(probe[i - n + 1 : i + 1])] / grams[n - 2][tuple(probe[i - n + 1 : i])] + (1 - lam) * p
        out.append(math.log(p))
    return math.exp(-sum(out) / len(out))


@pytest.mark.parametrize("order", [1, 2, 3])
def test_model_against_hand_counts(spark, order):
    rng = random.Random(order)
    docs = [[rng.choice("abcde") for _ in range(rng.randint(1, 30))] for _ in range(20)]
    probes_ = [[rng.choice("abcdef") for _ in range(12)] for _ in range(5)]
    arrays = lambda x: spark.createDataFrame([(i, d) for i, d in enumerate(x)], "id long, toks array<string>")
    grams = ngram_lm.grams_of_arrays(arrays(docs), "toks").select("a", "b", "c", F.lit(1).cast("long").alias("m"))
    probe = ngram_lm.grams_of_arrays(arrays(probes_), "toks", "id")
    for only in (None, probe):
        scored = ngram_lm.score(ngram_lm.train(grams, ["m"], only), probe, order)
        got = {r.id: r.ppl for r in scored.groupBy("id").agg(F.exp(-F.avg("lp_m")).alias("ppl")).collect()}
        assert got == pytest.approx({i: lm_by_hand(docs, p, order) for i, p in enumerate(probes_)})


def test_weights_stand_for_copies(spark):
    toks = spark.createDataFrame([(list("abcab"),)], "toks array<string>")
    once = ngram_lm.grams_of_arrays(toks, "toks").select("a", "b", "c", F.lit(3).cast("long").alias("m"))
    thrice = ngram_lm.grams_of_arrays(toks.union(toks).union(toks), "toks").select("a", "b", "c", F.lit(1).cast("long").alias("m"))
    counts = lambda g: sorted(map(str, ngram_lm.train(g, ["m"]).counts.collect()))
    assert counts(once) == counts(thrice)


def test_intervals_equal_monthly_versions(spark):
    docs = spark.createDataFrame([(1, " ".join(f"w{i}" for i in range(120)))], "doc_id long, text string")
    rng = random.Random(3)
    log = [(1, rng.randint(0, 79), rng.randint(1, 9999), rng.randint(1, 7), rng.randint(1, 50)) for _ in range(60)]
    edits = spark.createDataFrame(log, "topic_id long, month_ix int, major long, minor long, payload long")
    ints = probes.evolving_set(docs, edits, spark.createDataFrame([(1,)], "topic_id long"))
    got = {(r.month_ix, r.pos): r.token for r in probes.at_months(ints, [0, 5, 41, 79]).collect()}
    for m in (0, 5, 41, 79):
        text = [f"w{i}" for i in range(120)]
        for _, _, a, b, p in sorted(e for e in log if e[1] <= m):
            text[(a * 31 + b * 97) % 120] = f"p{p}"
        assert [got[m, i] for i in range(120)] == text


def test_planted_month_is_found(spark):
    """A corpus that holds one month's versions only has its minimum there."""
    rng = random.Random(9)
    docs = spark.createDataFrame([(i, " ".join(f"w{rng.randint(0, 300)}" for _ in range(150))) for i in range(12)], "doc_id long, text string")
    log = [(i, rng.randint(0, 79), rng.randint(1, 9999), rng.randint(1, 7), rng.randint(1, 500)) for i in range(12) for _ in range(60)]
    edits = spark.createDataFrame(log, "topic_id long, month_ix int, major long, minor long, payload long")
    ints = probes.evolving_set(docs, edits, docs.select(F.col("doc_id").alias("topic_id")))
    grid = probes.month_grid(spark, 10)
    for order in (2, 3):
        grams = ngram_lm.grams_of_intervals(ints, order)
        for month in (20, 60):
            model = ngram_lm.train(grams.select("a", "b", "c", ngram_lm.planted_weight({month: 1}).alias("m")), ["m"])
            ppl = ngram_lm.monthly_perplexity(ngram_lm.score(model, grams, order), grid, ["m"])
            assert curves.effective_cutoff(curves.relative(curves.trimmed_mean(ppl))).first().cutoff == month


def lev(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prev, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prev + (x != y))
    return row[-1]


def test_near_equals_plain_distance(spark):
    rng = random.Random(2)
    rows = []
    for _ in range(150):
        a = "".join(rng.choice("abc ") for _ in range(rng.choice([0, 1, 5, 10, 200])))
        b = list(a)
        for _ in range(rng.choice([0, 1, 2, len(a) // 5, len(a) // 4])):
            if b:
                b[rng.randrange(len(b))] = rng.choice("xyz")
        rows.append((a, "".join(b) + "q" * rng.choice([0, 0, 1, 9])))
    df = spark.createDataFrame(rows, "a string, b string")
    for inclusive in (False, True):
        for r in df.select("a", "b", near(F.col("a"), F.col("b"), 0.2, inclusive).alias("d")).collect():
            d, most = lev(r.a, r.b), len(r.a) / 5
            assert r.d == (d if (d <= most if inclusive else d < most) else None)


def test_exact_fifth_is_out_unless_inclusive(spark):
    df = spark.createDataFrame([("abcde", "abcdX")], "a string, b string")
    assert df.select(near(F.col("a"), F.col("b"), 0.2)).first()[0] is None
    assert df.select(near(F.col("a"), F.col("b"), 0.2, True)).first()[0] == 1


def test_bm25_by_hand_and_scan_equals_index(spark):
    docs = {1: "a b a c", 2: "b c d", 3: "d d d d e"}
    corpus = spark.createDataFrame([(k, t.split()) for k, t in docs.items()], "doc_id long, toks array<string>")
    q = spark.createDataFrame([(7, "a b b".split())], "topic_id long, toks array<string>")
    n, mean, want = 3, sum(len(t.split()) for t in docs.values()) / 3, {}
    for k, t in docs.items():
        w = t.split()
        for term in ("a", "b", "b"):
            df = sum(term in x.split() for x in docs.values())
            tf = w.count(term)
            want[k] = want.get(k, 0) + math.log(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len(w) / mean))
    terms = mining.query_terms(q)
    one = {r.doc_id: r.score for r in mining.top_k(mining.build_index(corpus), terms).collect()}
    assert one == pytest.approx({k: v for k, v in want.items() if v}, abs=1e-6)
    assert one == {r.doc_id: r.score for r in mining.top_k_scan(corpus, terms).collect()}


@pytest.mark.parametrize("ties,months", [("all", {3: 1, 4: 1, 9: 1}), ("split", {3: 1 / 3, 4: 1 / 3, 9: 1 / 3}), ("earliest", {3: 1}), ("latest", {9: 1})])
def test_ties(spark, ties, months):
    m = spark.createDataFrame([(1, 5, 3, 4, 7), (1, 5, 9, 9, 7), (1, 5, 10, 12, 8)], "topic_id long, doc_id long, version_from int, version_to int, dist int")
    assert {r.month_ix: r.weight for r in mining.attribute(m, ties).collect()} == pytest.approx(months)


def test_histogram_keeps_empty_months_and_share_older(spark):
    grid = probes.month_grid(spark)
    a = spark.createDataFrame([(1, 1, 3, 1.0), (1, 2, 3, 1.0), (2, 3, 70, 1.0)], "topic_id long, doc_id long, month_ix int, weight double")
    hist = mining.histogram(a, grid)
    assert hist.count() == 80 and hist.agg(F.sum("n")).first()[0] == 3
    assert audit.share_older(hist, 70).first().share_older == pytest.approx(2 / 3)
    assert audit.share_older(hist.where("false"), 70).first().share_older is None


def test_unknown_stated_date_has_no_gap(spark):
    eff = spark.createDataFrame([("a", 5), ("b", 6)], "model string, cutoff int")
    assert {r.model: r.gap for r in compare.gap(eff, compare.cards(spark, {"a": 9, "b": None})).collect()} == {"a": -4, "b": None}


def test_inverse_relation(spark):
    curve = curves.relative(curve_of(spark, [5, 4, 1, 3]))
    hist = spark.createDataFrame([("m", i, n) for i, n in enumerate([0.0, 2.0, 9.0, 3.0])], "model string, month_ix int, n double")
    r = compare.curve_vs_hist(curve, hist).first()
    assert r.pearson < -0.9 and r.spearman == pytest.approx(-1)


def test_dedup_pipelines(spark):
    docs = spark.createDataFrame([(1, "A b. C d. E f. G."), (2, "X. C d. E f. G. Y."), (3, "A b. C d. E f. G."), (4, "p\nq\np"), (5, "q"), (6, "")], "doc_id long, text string")
    assert sorted(r.doc_id for r in corpora.dedup_docs(docs).collect()) == [1, 2, 4, 5, 6]
    spans = corpora.dedup_spans(docs)
    assert {r.doc_id: r.text for r in spans.collect()} == {1: "A b. C d. E f. G.", 2: "X. Y.", 3: "", 4: "p\nq\np", 5: "q", 6: ""}
    left = audit.spans(spans.select("doc_id", "text"))
    assert left.count() == 0
    once = corpora.dedup_paragraphs(docs)
    assert {r.doc_id: r.text for r in once.where("doc_id in (4, 5)").collect()} == {4: "p\nq", 5: ""}
    twice = corpora.dedup_paragraphs(once.select("doc_id", "text"))
    assert sorted((r.doc_id, r.text) for r in twice.collect()) == sorted((r.doc_id, r.text) for r in once.collect())


def test_fuzzy_components_are_confirmed(spark):
    base = [f"w{i}" for i in range(200)]
    near_copy = base[:]
    near_copy[100] = "zz"
    rows = [(1, " ".join(base)), (2, " ".join(near_copy)), (3, " ".join(base[::-1])), (4, "short"), (5, " ".join(base))]
    got = {r.doc_id: r.component for r in corpora.dedup_fuzzy(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 1, 3: 3, 4: 4, 5: 1}


def test_folding(spark):
    df = spark.createDataFrame([("Éß  Ñ\n x ",), ("",), (None,), ("日本",)], "t string")
    t = F.col("t")
    assert [tuple(r) for r in df.select(fold(t), canonical(t), tokens(t)).collect()] == [("es  n\n x ", "es n x", ["es", "n", "x"]), ("", "", []), (None, None, []), ("日本", "日本", ["日本"])]
    assert df.limit(1).select(sentences(F.lit("A b. C! D? e"))).first()[0] == ["A b.", "C!", "D?", "e"]


def test_fuzzy_links_past_a_head_and_short_texts(spark):
    import random

    rng = random.Random(4)
    base = [f"w{k}" for k in range(120)]

    def edited(n):
        out = list(base)
        for k in rng.sample(range(120), n):
            out[k] = f"x{rng.randint(0, 10**6)}"
        return out

    one = edited(12)
    texts = [" ".join(edited(6)) for _ in range(40)] + [" ".join(one), " ".join([*one[:60], "y", *one[61:]]), "two words", "Two  words", "", ""]
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set() for w in (t.lower().split() for t in texts)]
    part = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            if sets[a] and sets[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                low, high = sorted((part[a], part[b]))
                part = [low if c == high else c for c in part]
    got = {r.doc_id: r.component for r in corpora.dedup_fuzzy(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got == dict(enumerate(part)) and got[43] == 42 and got[41] == 40 and got[45] == 45


def test_leak_of_runs_that_several_pages_hold(spark):
    words = [f"w{k}" for k in range(12)]
    other = [*(f"v{k}" for k in range(4)), *words[:8]]
    rows = [(1, "in", words), (2, "in", words), (3, "in", other), (4, "out", words), (5, "out", words[:8]), (6, "out", ["z"] * 12)]
    pages = spark.createDataFrame(rows, "page_id long, host string, toks array<string>")
    got = audit.leak_through(pages, F.col("host") == "in", pages.where("host = 'in'"))
    # Pages 1 and 2 are one text; the run w0-w7 stands on it and on page 3.
    assert {r.page_id: (r.runs, r.sources, r.weight) for r in got.collect()} == {4: (5, 2, 4.5), 5: (1, 2, 0.5)}


def test_content_filter_takes_lists_and_learned_words(spark):
    texts = ["you Flurb!", "a flurb b", "flurb c", "nice day", "clean x", "see our Privacy Policy", "f() { }", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(0, 1), (1, 1), (2, 1), (2, 1), (3, 0), (4, 0), (9, 1), (5, None)], "doc_id long, toxic int")
    words = corpora.unwanted_words(docs, labels)
    assert [r.word for r in words.collect()] == ["flurb"]
    want = {0: "words", 1: "words", 2: "words", 3: None, 4: None, 5: "boilerplate", 6: "code", 7: None}
    for given in (words, ["flurb"]):
        assert {r.doc_id: r.reason for r in corpora.content_filter(docs, given).collect()} == want
    got = corpora.content_filter(docs, [], ["nice"], ["x"]).where("reason is not null")
    assert {r.doc_id: r.reason for r in got.collect()} == {3: "boilerplate", 4: "code"}


def packed_of(spark, rows):
    return spark.createDataFrame(rows, "topic_id long, toks array<string>, tail string, edits array<struct<month:int,pos:int,token:string>>")


def history(rng, n, edits, tail=""):
    """A topic's row, and its texts by (first month, last month), written out the plain way."""
    words = [f"w{rng.randint(0, 400)}" for _ in range(n)]
    log = sorted({(rng.randint(0, 79), rng.randrange(n)): f"p{rng.randint(0, 9999)}" for _ in range(edits)}.items())
    log = [(m, p, t) for (m, p), t in log]
    starts = sorted({0, *(m for m, _, _ in log)})
    texts = {}
    for f, t in zip(starts, [*(x - 1 for x in starts[1:]), 79], strict=True):
        now = list(words)
        for m, p, w in log:
            if m <= f:
                now[p] = w
        texts[f, t] = " ".join([*now, tail] if tail else now)
    return (words, tail, log), texts


def test_packed_versions_equal_intervals_and_plain_edits(spark, sf):
    from vintage.sources.tables import table
    from vintage.workloads import setup

    docs, edits, chosen = table(spark, sf, "documents", "doc_id", "text"), setup.edits(spark, sf), setup.chosen_topics(spark, sf)
    heads = probes.whole_versions(probes.packed_set(docs, edits, chosen).withColumn("tail", F.lit("")))
    plain = probes.version_texts(probes.evolving_set(docs, edits, chosen))
    assert heads.exceptAll(plain).count() == plain.exceptAll(heads).count() == 0
    row, texts = history(random.Random(6), 30, 40, "and more")
    got = {(r.version_from, r.version_to): r.text for r in probes.whole_versions(packed_of(spark, [(1, *row)])).collect()}
    assert got == texts


def test_leak_matches_equal_all_distances(spark):
    rng = random.Random(12)
    pages, texts = [], {}
    for k in range(40):
        words = [f"w{rng.randint(0, 30)}" for _ in range(25)] if k < 8 or k % 3 else list(texts[k % 8])
        for _ in range(rng.choice([0, 1, 3, 9]) if k >= 8 else 0):
            words[rng.randrange(25)] = f"é{rng.randint(0, 99)}"
        texts[k] = words
        pages.append((k, "in" if k < 8 else "out", words))
    got = audit.leak_matches(spark.createDataFrame(pages, "page_id long, host string, toks array<string>"), F.col("host") == "in", k=32)
    want = {}
    for a in range(8):
        for b in range(8, 40):
            doc = " ".join(texts[b])
            d = lev(" ".join(texts[a]), doc)
            if d < 0.2 * len(doc) and set(texts[a]) & set(texts[b]):
                want[a, b] = d
    assert {(r.source, r.page_id): r.dist for r in got.collect()} == want and len(want) > 5


def test_stability_by_family(spark):
    rows = [("a_5000", 10, 0.2), ("a_50", 14, 0.4), ("b_c_5000", 3, 0.1), ("b_c_50", 3, 0.1)]
    got = ablate.stability(spark.createDataFrame(rows, "model string, cutoff int, deviation double"), "5000")
    assert {r.family: (r.max_shift, r.mean_deviation) for r in got.collect()} == {"a": (4, 0.3), "b_c": (0, 0.1)}


def test_retrieval_reads_whole_texts(spark, sf):
    from vintage.workloads import retrieval

    packed = retrieval._topics(spark, sf)
    words = {r.doc_id: r.toks for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", tokens(F.col("text")).alias("toks")).collect()}
    rows = retrieval._corpus(spark, sf, packed).collect()
    assert {r.doc_id: r.toks for r in rows if r.subcorpus == "background"} == words
    planted = [((r.doc_id - retrieval.OFFSET) // 100, r.toks) for r in rows if r.subcorpus != "background"]
    assert any(len(t) > 512 for _, t in planted)
    assert all(len(t) == len(words[k]) and t[512:] == words[k][512:] for k, t in planted)
    texts = probes.whole_versions(packed).collect()
    assert all(len(r.text.split(" ")) == len(words[r.topic_id]) for r in texts)


def test_bounded_distance_equals_plain_table():
    from vintage.functions.distance import bounded

    rng = random.Random(8)
    for _ in range(1500):
        a = [rng.choice("abc é") for _ in range(rng.randint(0, 40))]
        b = list(a)
        for _ in range(rng.randint(0, 12)):
            k = rng.randint(0, len(b))
            b[k : k + rng.randint(0, 1)] = [rng.choice("abcd")] * rng.randint(0, 1)
        if rng.random() < 0.3:
            b = [rng.choice("abc é") for _ in range(rng.randint(0, 40))]
        a, b, most = "".join(a), "".join(b), rng.randint(0, 25)
        d = lev(a, b)
        assert bounded(a, b, most, rng.choice([1, 2, 64])) == (d if d <= most else None)


def test_edit_matches_equal_all_distances(spark):
    """Every hit against every version, the plain way: also where the widened first bound or neighbours decide."""
    rng = random.Random(5)
    rows, plain, docs = [], {}, {}
    for topic in range(6):
        row, plain[topic] = history(rng, rng.choice([20, 40]), rng.choice([0, 5, 40]), rng.choice(["", "some é tail here"]))
        rows.append((topic, *row))
    for k in range(60):
        text = list(rng.choice(list(plain[k % 6].values())))
        for _ in range(rng.choice([0, 1, len(text) // 10, len(text) // 5, len(text) // 3])):
            text[rng.randrange(len(text))] = rng.choice("xyz ")
        docs[k] = "".join(text) if k % 10 else ""
    corpus = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    hits = spark.createDataFrame([(t, k) for t in range(6) for k in docs], "topic_id long, doc_id long")
    apart = {(t, k, text): lev(doc, text) for t in range(6) for k, doc in docs.items() for text in plain[t].values()}
    for threshold, inclusive in ((0.2, False), (0.2, True), (0.35, False)):
        compared = mining.compare_versions(hits, corpus, packed_of(spark, rows), threshold, inclusive)
        got = {(r.topic_id, r.doc_id, r.version_from, r.version_to): r.dist for r in mining.edit_match(compared).collect()}
        want = {}
        for t in range(6):
            for k, doc in docs.items():
                for span, text in plain[t].items():
                    d, most = apart[t, k, text], threshold * len(doc)
                    if d < most - 1e-9 or inclusive and d <= most + 1e-9:
                        want[(t, k, *span)] = d
        assert got == want and len(want) > 100
    cost = mining.costs(compared).first()
    assert cost.hits == 360 and cost.pairs == sum(len(plain[t]) for t in range(6)) * 60 and cost.matched == len(want)
    assert cost.distances + cost.ruled_out_by_length < cost.pairs


def test_planted_versions_come_back(spark, sf):
    """The document planted for a month is matched, at distance 0, by the version of that month alone."""
    from vintage.workloads import retrieval

    matched = retrieval.edit_matches(spark, sf).where(f"doc_id >= {retrieval.OFFSET} and dist = 0 and topic_id = (doc_id - {retrieval.OFFSET}) div 100").collect()
    at = {(r.doc_id - retrieval.OFFSET) % 100 for r in matched}
    topics = retrieval._topics(spark, sf).count()
    assert at == set(retrieval.s.MIXES[retrieval.MIX]) and len({r.doc_id for r in matched}) == len(at) * topics
    assert all(r.version_from <= (r.doc_id - retrieval.OFFSET) % 100 <= r.version_to for r in matched)


def test_all_topics_are_mined(spark, sf):
    from vintage.workloads import retrieval, setup

    topics = {r.topic_id for r in setup.chosen_topics(spark, sf).collect()}
    packed = retrieval._topics(spark, sf)
    assert len(topics) > 60 and {r.topic_id for r in packed.select("topic_id").collect()} == topics
    assert retrieval._corpus(spark, sf, packed).where("subcorpus = 'direct'").count() == len(topics)
    assert {r.versions for r in retrieval.static_inclusion(spark, sf).collect()} == {80 * len(topics)}


def test_runs_of_a_long_text_take_one_walk(spark):
    import time

    from vintage.functions.text import shingles

    df = spark.createDataFrame([(" ".join(f"w{k % 7000}" for k in range(n)),) for n in (20_020, 3, 5)] + [("",), (None,)], "text string")
    began = time.perf_counter()
    got = [r.n for r in df.select(F.size(shingles(tokens(F.col("text")), 5)).alias("n")).collect()]
    assert got == [7000, 0, 1, 0, 0] and time.perf_counter() - began < 20


def test_queries_go_in_blocks_of_topics(spark, monkeypatch):
    rng = random.Random(11)
    corpus = spark.createDataFrame([(k, [rng.choice("abcdefgh") for _ in range(rng.randint(0, 12))] if k else None) for k in range(60)], "doc_id long, toks array<string>")
    terms = mining.query_terms(spark.createDataFrame([(t, [rng.choice("abcdxy") for _ in range(5)]) for t in range(9)], "topic_id long, toks array<string>"))
    whole = sorted(map(tuple, mining.top_k_scan(corpus, terms, 4).collect()))
    assert sorted(map(tuple, mining.top_k(mining.build_index(corpus), terms, 4).collect())) == whole
    monkeypatch.setattr(mining, "BROADCAST_TERMS", 7)
    assert sorted(map(tuple, mining.top_k_scan(corpus, terms, 4).collect())) == whole
    assert mining.build_index(corpus).postings().groupBy("doc_id").agg(F.sum("tf")).count() == corpus.where("size(toks) > 0").count()
    assert mining.top_k_scan(corpus.where("false"), terms).count() == mining.top_k(mining.build_index(corpus.where("false")), terms).count() == 0
    assert mining.top_k_scan(corpus, terms.where("false")).count() == 0
