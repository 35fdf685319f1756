"""Scores, bounds, engines and traps on small graphs, by hand and against brute force."""

import math
import random

import pytest
from pyspark.sql import functions as F

from semgraph.functions.scores import psi, psi_hat
from semgraph.model import KG, KG_EDGES, KG_NODES, Params, QueryNode, SubQuery
from semgraph.operators import assembly as A
from semgraph.operators import search as S


def graph(spark, weights, sources, targets):
    """A graph whose predicates carry the weights: the query predicate is q, a predicate wX has cosine X with it."""
    nodes = sorted({n for a, b, _ in weights for n in (a, b)})
    types = {n: ["S"] if n in sources else ["T"] if n in targets else ["N"] for n in nodes}
    kg = KG(
        spark.createDataFrame([(n, f"n{n}", types[n], None) for n in nodes], KG_NODES),
        spark.createDataFrame([(a, f"w{w}", b) for a, b, w in weights], KG_EDGES),
    )
    space = {"q": [1.0, 0.0]} | {f"w{w}": [w, math.sqrt(1 - w * w)] for _, _, w in weights}
    sub = SubQuery(0, (QueryNode("s", ("S",)), QueryNode("t", ("T",))), ("q",), 1)
    return kg, sub, space


def brute(weights, sources, targets, n_hat, tau):
    around = {}
    for a, b, w in weights:
        around.setdefault(a, []).append((b, w))
        around.setdefault(b, []).append((a, w))
    best = {}

    def walk(path, w):
        for nbr, x in around.get(path[-1], ()):
            if nbr in path or len(path) > n_hat:
                continue
            score = (w * x) ** (1 / len(path))
            if nbr in targets:
                if score >= tau - 1e-12:
                    best[nbr] = max(best.get(nbr, 0), score)
            elif len(path) < n_hat:
                walk([*path, nbr], w * x)

    for s in sources:
        walk([s], 1.0)
    return best


def scores(df):
    df = df.matches if isinstance(df, S.Found) else df
    return {r.pivot_id: r.psi for r in df.collect()}


TRACE = [(1, 2, 0.6), (1, 3, 0.74), (1, 4, 0.5), (3, 7, 0.74), (2, 5, 0.7175), (2, 6, 0.66), (5, 9, 0.875), (9, 12, 0.84), (4, 8, 0.568), (6, 10, 0.717), (4, 11, 0.5), (8, 12, 0.5), (10, 11, 0.5)]
TRAP = [(1, 2, 0.6), (2, 3, 1.0), (1, 4, 0.7), (4, 5, 0.8), (2, 5, 0.1), (5, 6, 0.8)]


def test_scores(spark):
    r = spark.range(1).select(psi(F.lit(0.81), F.lit(2)).alias("a"), psi_hat(F.lit(0.5), F.lit(0.8), 4).alias("b")).first()
    assert r.a == pytest.approx(0.9) and r.b == pytest.approx(0.4**0.25)


def test_trace_best_first_pops_in_order(spark):
    """Targets 7 and 12; the best is 12 by 1-2-5-9-12 with .75 against .74 for 7."""
    kg, sub, space = graph(spark, TRACE, {1}, {7, 12})
    stats = S.Stats()
    prep = S.prepare(kg, [sub], space, Params(k=1, tau=0.0, batch=1))
    found = scores(S.best_first(prep, stats))
    assert max(found, key=found.get) == 12 and found[12] == pytest.approx((0.6 * 0.7175 * 0.875 * 0.84) ** 0.25)
    assert round(found[12], 2) == 0.75 and len(stats.rounds) <= 5


def test_discovery_trap(spark):
    """Marking nodes when they are discovered loses the optimum; simple paths keep it."""
    kg, sub, space = graph(spark, TRAP, {1}, {6})
    exact = scores(S.layered(S.prepare(kg, [sub], space, Params(k=1, tau=0.0))))
    assert exact[6] == pytest.approx((0.7 * 0.8 * 0.8) ** (1 / 3))
    literal = scores(S.best_first(S.prepare(kg, [sub], space, Params(k=1, tau=0.0, batch=1, revisit="on_discovery"))))
    assert literal[6] == pytest.approx((0.6 * 0.1 * 0.8) ** (1 / 3))


def test_padding_raises_the_root(spark):
    kg, sub, space = graph(spark, [(1, 4, 0.5), (1, 2, 1.0), (2, 3, 1.0), (3, 4, 0.5)], {1}, {4})
    assert scores(S.layered(S.prepare(kg, [sub], space, Params(tau=0.0))))[4] == pytest.approx(0.5 ** (1 / 3))


@pytest.mark.parametrize("seed", [1, 2])
def test_engines_agree_with_brute_force(spark, seed):
    rng = random.Random(seed)
    pairs = sorted({tuple(sorted(rng.sample(range(12), 2))) for _ in range(24)})
    weights = [(a, b, round(rng.uniform(0.3, 1.0), 3)) for a, b in pairs]
    sources, targets = {0}, {9, 10, 11}
    kg, sub, space = graph(spark, weights, sources, targets)
    tau = 0.55
    want = brute(weights, sources, targets, 3, tau)
    p = Params(k=10, tau=tau, max_hops=3, batch=7)
    for engine in ("layered", "best_first", "local"):
        got = scores(S.search(kg, [sub], space, p, engine))
        assert got == pytest.approx(want), engine
    for change in ({"bound": "tight"}, {"m_mode": "loose"}, {"use_estimate": False}, {"static_cut": False}, {"topk_prune": True}, {"m_mode": "scan"}):
        assert scores(S.search(kg, [sub], space, p.but(**change))) == pytest.approx(want), change
    walks = scores(S.search(kg, [sub], space, p.but(revisit="dominance")))
    assert all(walks[t] >= s - 1e-9 for t, s in want.items())


def test_estimate_bounds_every_completion(spark):
    kg, sub, space = graph(spark, TRACE, {1}, {7, 12})
    prep = S.prepare(kg, [sub], space, Params(tau=0.0))
    first = S.expand(prep, prep.start)
    hats = {r.node: r.psi_hat for r in first.filter("NOT done").collect()}
    best = brute(TRACE, {1}, {7, 12}, 4, 0.0)
    assert max(hats.values()) >= max(best.values()) - 1e-12


def lists(spark, *rows):
    return spark.createDataFrame([(i, p, s) for i, own in enumerate(rows) for p, s in own], "sub_id int, pivot_id long, psi double")


def test_threshold_equals_full_join(spark):
    rng = random.Random(5)
    data = lists(spark, *[[(p, round(rng.random(), 3)) for p in rng.sample(range(60), 40)] for _ in range(3)])
    for mode in ("complete", "partial"):
        a = A.assemble(data, [0, 1, 2], 5, mode, "threshold", step=5).collect()
        b = A.assemble(data, [0, 1, 2], 5, mode, "full").collect()
        assert a == b


def test_bounds_close_in(spark):
    data = lists(spark, [(i, 1 - i / 50) for i in range(40)], [(39 - i, 1 - i / 40) for i in range(40)])
    low, high = -1.0, 99.0
    for depth in (5, 10, 20, 40):
        b = A.bounds(data, [0, 1], depth, 3, "partial")
        assert b.kth_lower >= low - 1e-12 and b.best_other <= high + 1e-12 or depth == 5
        low, high = b.kth_lower, b.best_other
        assert b.accesses <= 80


def test_unseen_pivot_trap(spark):
    data = lists(spark, [(1, 0.9), (3, 0.89)], [(2, 0.9), (3, 0.89)])
    got = A.assemble(data, [0, 1], 2, "partial", "threshold", step=1).collect()
    assert [(r.pivot_id, round(r.score, 2)) for r in got] == [(3, 1.78), (1, 0.9)]


def two_sided(spark, *sides):
    """A graph with a source for each side: (pivot, weight) is an edge from it, (pivot, weight, weight) two by way of a node of its own."""
    nodes, edges, fresh = [(i + 1, f"s{i}", [f"S{i}"], None) for i in range(len(sides))], [], 1000
    pivots = sorted({row[0] for side in sides for row in side})
    nodes += [(p, f"n{p}", ["T"], None) for p in pivots]
    for i, side in enumerate(sides):
        for p, *ws in side:
            at = i + 1
            for w in ws[:-1]:
                fresh += 1
                nodes.append((fresh, f"n{fresh}", ["N"], None))
                edges.append((at, f"w{w}", fresh))
                at = fresh
            edges.append((at, f"w{ws[-1]}", p))
    kg = KG(spark.createDataFrame(nodes, KG_NODES), spark.createDataFrame(sorted(set(edges)), KG_EDGES))
    space = {"q": [1.0, 0.0]} | {p: [float(p[1:]), math.sqrt(1 - float(p[1:]) ** 2)] for _, p, _ in edges}
    subs = [SubQuery(i, (QueryNode("s", (f"S{i}",), f"s{i}"), QueryNode("t", ("T",))), ("q",), 1) for i in range(len(sides))]
    return kg, subs, space


VARIANTS = [("layered", {}), ("layered", {"topk_prune": True}), ("best_first", {"batch": 1}), ("best_first", {"batch": 50}), ("local", {})]


def test_lists_whose_tops_do_not_overlap(spark):
    """The best answer is last in both lists: an engine that stops at a list's k-th score must go on."""
    from semgraph.plans import engine as E

    kg, subs, space = two_sided(spark, [(10, 0.95), (11, 0.94), (14, 0.9, 0.9)], [(12, 0.95), (13, 0.94), (14, 0.9)])
    for engine, change in VARIANTS:
        got = E.exact_query(kg, None, space, Params(k=1, max_hops=2, fetch_factor=1, **change), engine=engine, subs=subs)
        assert [(r.pivot_id, round(r.score, 6)) for r in got.answers.collect()] == [(14, 1.8)], (engine, change)


def test_ties_go_by_id_in_every_engine(spark):
    from semgraph.plans import engine as E

    same = [(p, 0.9) for p in range(10, 40)]
    kg, subs, space = two_sided(spark, same, same[5:])
    for i, (engine, change) in enumerate(VARIANTS):
        got = E.exact_query(kg, None, space, Params(k=3, max_hops=2, fetch_factor=1, **change), engine=engine, subs=subs, assembly=("complete", "partial")[i % 2]).answers.collect()
        assert [(r.rank, r.pivot_id, round(r.score, 6)) for r in got] == [(1, 15, 1.8), (2, 16, 1.8), (3, 17, 1.8)], (engine, change)


@pytest.mark.parametrize("seed", [3, 4])
def test_engines_agree_on_three_random_lists(spark, seed):
    from semgraph.plans import engine as E

    rng = random.Random(seed)
    sides = [[(p, *[round(rng.uniform(0.5, 1), 1) for _ in range(rng.choice([1, 1, 2]))]) for p in rng.sample(range(10, 40), 20)] for _ in range(3)]
    kg, subs, space = two_sided(spark, *sides)
    p = Params(k=4, max_hops=2, tau=0.5, fetch_factor=1)
    mode = ("complete", "partial")[seed % 2]
    want = E.exact_query(kg, None, space, p, subs=subs, assembly=mode, strategy="full").answers.collect()
    for engine, change in [v for v in VARIANTS if v[1] != {"batch": 1}]:
        assert E.exact_query(kg, None, space, p.but(**change), engine=engine, subs=subs, assembly=mode).answers.collect() == want, (engine, change, mode)


def test_hubs_are_split_and_large_frontiers_shuffled(spark, monkeypatch):
    """With slots of two rows and no broadcast, answers stay the same."""
    from semgraph.sources import index as X

    rng = random.Random(9)
    pairs = sorted({tuple(sorted(rng.sample(range(14), 2))) for _ in range(45)})
    weights = [(a, b, round(rng.uniform(0.4, 1.0), 3)) for a, b in pairs]
    want = brute(weights, {0}, {10, 11, 12, 13}, 3, 0.5)
    monkeypatch.setattr(X, "SLOT_ROWS", 2)
    monkeypatch.setattr(X, "SLOTS", "CAST(greatest(1, ceil(degree / 2)) AS INT)")
    monkeypatch.setattr(S, "SLOTS", X.SLOTS)
    monkeypatch.setattr(S, "BROADCAST_STATES", -1)
    monkeypatch.setattr(X, "MOST_PROFILES", 1)
    kg, sub, space = graph(spark, weights, {0}, {10, 11, 12, 13})
    prep = S.prepare(kg, [sub], space, Params(tau=0.5, max_hops=3))
    assert X.index_of(kg).adj.agg(F.max("slot")).first()[0] > 0 and not prep.small_info
    assert scores(S.layered(prep)) == pytest.approx(want)
    plan = S.expand(prep, prep.start)._jdf.queryExecution().executedPlan().toString()
    assert "slot" in plan


def test_a_hop_reads_the_adjacency_once_and_aggregates_nothing(spark):
    kg, sub, space = graph(spark, TRACE, {1}, {7, 12})
    prep = S.prepare(kg, [sub], space, Params(tau=0.5))
    physical = S.expand(prep, prep.start, None, 1, prep.start_span)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [predicate" in physical and "PushedFilters" in physical and "node" in physical.split("PushedFilters")[1][:120]
    assert physical.count("FileScan parquet") == 1 and "Aggregate" not in physical and "SortMergeJoin" not in physical


def test_running_example(spark):
    """A car made in Germany: an assembly and a country edge score .891; a second list that scores 1 makes 1.891."""
    from semgraph.plans import engine as E

    nodes = [(1, "Germany", ["Country"], None), (2, "Regensburg", ["City"], None), (3, "Roadster", ["Automobile"], None), (4, "Maker", ["Company"], None)]
    edges = [(3, "assembly", 2), (2, "country", 1), (3, "manufacturer", 4)]
    kg = KG(spark.createDataFrame(nodes, KG_NODES), spark.createDataFrame(edges, KG_EDGES))
    country = 0.891**2 / 0.98
    space = {"product": [1.0, 0.0, 0.0], "assembly": [0.98, math.sqrt(1 - 0.98**2), 0.0], "country": [country, math.sqrt(1 - country**2), 0.0], "manufacturer": [0.0, 0.0, 1.0]}
    car = QueryNode("v", ("Automobile",))
    subs = [SubQuery(0, (QueryNode("g", ("Country",), "Germany"), car), ("product",), 1), SubQuery(1, (QueryNode("m", ("Company",), "Maker"), car), ("manufacturer",), 1)]
    first = scores(S.search(kg, subs[:1], space, Params(k=1)))
    assert round(first[3], 3) == 0.891
    answer = E.exact_query(kg, None, space, Params(k=1), subs=subs).answers.first()
    assert answer.pivot_id == 3 and round(answer.score, 3) == 1.891
