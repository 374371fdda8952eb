import itertools
import random
import zlib
from collections import Counter, defaultdict

import numpy as np

from vintage.llm import queries
from vintage.llm.packing import CAPACITY, VOCABULARY, Ids, Plan, cuts
from vintage.llm.bpe import vocabulary_path


def unpacked(plan, counts):
    """Every piece placed once, without overlap or gap."""
    used = defaultdict(list)
    ranks = defaultdict(list)
    for k, r, n, s, o in plan.ranges:
        ranks[k] += range(r, r + n)
        for i in range(n):
            used[s + i].append((o, k))
    assert {k: sorted(v) for k, v in ranks.items()} == {k: list(range(n)) for k, n in counts.items() if n}
    for s, parts in used.items():
        at = 0
        for o, k in sorted(parts):
            assert o == at
            at += k
        assert at <= plan.capacity
    assert set(used) == set(range(plan.sequences))
    return plan.sequences


def optimum(items, capacity):
    best = [len(items)]
    items = sorted(items, reverse=True)

    def go(k, bins):
        if len(bins) >= best[0]:
            return
        if k == len(items):
            best[0] = len(bins)
            return
        for i in sorted({b: i for i, b in enumerate(bins)}.values()):
            if bins[i] + items[k] <= capacity:
                bins[i] += items[k]
                go(k + 1, bins)
                bins[i] -= items[k]
        go(k + 1, [*bins, items[k]])

    go(0, [])
    return best[0]


def test_reduction_never_costs_a_sequence():
    rng = random.Random(3)
    for _ in range(400):
        cap = rng.choice([10, 13, 20, 31])
        items = [rng.randint(rng.choice([1, 3, 5]), cap) for _ in range(rng.randint(1, 9))]
        plan = Plan(Counter(items), cap)
        plan.reduce()
        rest = list(itertools.chain.from_iterable([k] * n for k, n in enumerate(plan.left)))
        assert plan.fixed + optimum(rest, cap) == optimum(items, cap), (cap, items)


def test_plans_are_packings():
    rng = random.Random(5)
    for _ in range(200):
        cap = rng.choice([16, 64, 2048])
        counts = Counter(rng.randint(1, cap) for _ in range(rng.randint(0, 3000)))
        plan = Plan(counts, cap)
        low = plan.bound()
        got = unpacked(plan.solve(), counts)
        assert low <= got <= 11 / 9 * low + 1 + sum(n for k, n in counts.items() if 2 * k > cap)


def test_cuts():
    assert cuts(1) == [(0, 1)] and cuts(2048) == [(0, 2048)] and cuts(4096) == [(0, 2048), (2048, 2048)]
    assert cuts(2049) == [(0, 1), (1, 2048)]


def test_ids_equal_the_tokenizers_library():
    from tokenizers import Tokenizer

    exact = Tokenizer.from_file(vocabulary_path(VOCABULARY))
    exact.encode_special_tokens = True
    ids = Ids()
    texts = ["", "a b  c\n\n d", "<|endoftext|> x", "été ²³½ 12", "日本 \U0001f600", *("".join(f"a{chr(c)}1 {chr(c)} " for c in range(s, s + 16)) for s in range(0, 0x250, 16))]
    for t in texts:
        assert ids(t).tolist() == exact.encode(t, add_special_tokens=False).ids


def test_whole_table(spark, sf):
    ids = Ids()
    want = {}
    for d in spark.read.parquet(f"{sf}/documents.parquet").collect():
        own = np.append(ids(d.text or ""), 0).astype("<u4")
        for p, (s, n) in enumerate(cuts(len(own))):
            want[d.doc_id, p] = (s, n, zlib.crc32(own[s : s + n].tobytes()))
    rows = queries.op6_best_fit_packing(spark, sf).collect()
    assert {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in rows} == want and len(rows) == len(want)
    by = defaultdict(list)
    for r in rows:
        by[r.sequence_id].append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= CAPACITY
    assert len(by) <= -(-sum(n for _, n, _ in want.values()) // CAPACITY) * 1.02 + 1


def test_hard_rows(spark):
    rows = [(1, None, 2), (1, "", 3), (None, "x y", 4), (2, "word " * 30_000, 5), (2, "word " * 30_000, 5)]
    from vintage.llm.packing import pack, pieces

    got = pack(pieces(spark.createDataFrame(rows, "doc_id long, text string, length long"))).collect()
    assert Counter(r.length for r in got if r.doc_id == 1) == {1: 2}
    assert len({(r.sequence_id, r.offset) for r in got}) == len(got)
    assert pack(pieces(spark.createDataFrame([], "doc_id long, text string"))).count() == 0
