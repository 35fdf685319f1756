"""What the findings of round 2 would have shown."""

from semgraph.sources import builders as G


def test_vector_pairs_with_null_components_and_across_blocks(spark, tmp_path):
    """A null component counts as zero, as in SQL; each pair is found once, whichever blocks it lies in."""
    rows = [(i, [1.0, None, 0.1 * i], 0) for i in range(40)] + [(100, None, 0), (101, [0.0, 1.0], 0), (102, [0.2, 0.8, 0.0], 0)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(str(tmp_path / "embeddings.parquet"))
    base = G.KINDS["vector"] * G.BASE
    got = sorted((r.src - base, r.dst - base) for r in G.vector_kg(spark, str(tmp_path)).edges.collect())
    pad = {i: [float(c) if c is not None else 0.0 for c in (v or [])] + [0.0] * (3 - len(v or [])) for i, v, _ in rows}
    want = sorted((a, b) for a in pad for b in pad if a < b and a != 100 and b != 100 and sum(x * y for x, y in zip(pad[a], pad[b])) >= 0.35)
    assert got == want and (101, 102) in got and (0, 1) in got


def test_appended_rows_of_a_stream_do_not_stay_on_the_driver(spark, sf):
    from semgraph.streaming import edges as SE

    got = SE.drain(SE.distinct_edges(SE.stream_edges(spark, sf, "3650 days", name="events.parquet")), "findings_distinct")
    assert "LocalTableScan" not in got._jdf.queryExecution().toString() and "MemoryPlan" not in got._jdf.queryExecution().toString()
    want = spark.read.parquet(f"{sf}/events.parquet").selectExpr("user_id", "event_type", "get_json_object(props, '$.k') AS k").distinct().count()
    assert got.count() == want


def test_of_equal_balances_the_first_customer_counts(spark, tmp_path):
    from semgraph.plans import surround as R

    rows = [(0, "a", 1, 5.0), (1, "b", 1, 5.0), (2, "c", 1, -1.0), (3, "d", 1, -1.0), (4, "e", 1, None), (5, None, 1, 9.0), (6, "f", 2, None)]
    spark.createDataFrame(rows, "c_custkey long, c_name string, c_nationkey int, c_acctbal double").coalesce(1).write.parquet(str(tmp_path / "customer.parquet"))
    assert sorted(map(tuple, R.QUERIES["agg_max_by"](spark, str(tmp_path)).collect())) == [(1, "a", "c"), (2, None, None)]


def test_the_last_hop_stores_scores_and_expands_undominated_states(spark, sf):
    """Whole lists without their paths have the scores of those with paths; of states that wait at one node few are expanded."""
    from semgraph.model import Params
    from semgraph.operators import search as S
    from semgraph.plans import catalog as C

    kg = G.stored_kg(spark, sf, "star")
    prep = S.prepare(kg, C.Q2_SUBS, C._space(spark), Params(max_hops=3))
    found = S.layered(prep)
    scores = {(r.sub_id, r.pivot_id): round(r.psi, 9) for r in found.scores.collect()}
    lazy = S.layered(S.prepare(kg, C.Q2_SUBS, C._space(spark), Params(max_hops=3, eager=False))).matches
    assert scores == {(r.sub_id, r.pivot_id): round(r.psi, 9) for r in lazy.collect()} == {(r.sub_id, r.pivot_id): round(r.psi, 9) for r in found.matches.collect()}
    assert sorted(map(repr, found.matches.collect())) == sorted(map(repr, lazy.collect()))
    states = prep.start
    for _ in range(2):
        states = S.expand(prep, states).filter("NOT done").localCheckpoint()
    kept = S.undominated(prep, states)
    assert 0 < kept.filter("only IS NULL").count() == states.select("sub_id", "node", "stage", "pivot_id").distinct().count() <= kept.count() < states.count()
    assert states.filter("sub_id = 1 AND stage = 0").isEmpty()  # with two edges to go, one hop is too few


def test_a_large_neighbourhood_is_no_error_of_the_local_engine(spark, sf, monkeypatch):
    from semgraph.model import Params
    from semgraph.operators import search as S
    from semgraph.plans import catalog as C

    kg = G.stored_kg(spark, sf, "star")
    rows = lambda: sorted(map(tuple, C.QUERIES["exact_two_subqueries_local"](spark, sf).collect()))
    want = rows()
    for most in (100, 1):  # within the count of a hop, and over it
        monkeypatch.setattr(S, "MOST_LOCAL_EDGES", most)
        assert rows() == want
    assert S.reachable(S.prepare(kg, C.Q2_SUBS, C._space(spark), Params(max_hops=3)), 1) is None


def test_hop_bounded_stops_where_k_are_found(spark, sf):
    """A level that can only score less is not made, and the k best are those of all levels."""
    from semgraph.operators import baselines as B
    from semgraph.operators.library import build_library
    from semgraph.plans import catalog as C

    kg = G.stored_kg(spark, sf, "star")
    library = build_library(kg)
    whole = B.hop_bounded_scores(kg, [C.Q1_SUB], 4, library)
    for k in (1, 5, 20):
        few = B.hop_bounded_scores(kg, [C.Q1_SUB], 4, library, k)
        assert few.count() < whole.count()
        assert B._joined(few, 1, k).collect() == B._joined(whole, 1, k).collect()


def test_queries_read_given_tables(spark, sf):
    from semgraph.plans import catalog as C

    columns = {
        "correlation_users": {"c_acctbal", "o_custkey"}, "pred_cosine_authored": {"event_type"}, "pred_top10_similar": {"embedding"}, "pred_weights_rescaled": {"embedding"},
        "recursive_paths": {"l_discount"}, "sql_functions": {"embedding"}, "udtf_split_path": {"c_mktsegment"},
    }
    for name, want in columns.items():
        plan = C.QUERIES[name](spark, sf)._jdf.queryExecution().toString()
        assert all(c in plan for c in want), name
    # made of the stored graph, which is made of all tables of the star
    assert sum(r.edges for r in C.QUERIES["pred_static_cut"](spark, sf).collect()) > 0


def test_embedding_with_held_vectors_is_that_of_joins(spark, monkeypatch):
    from semgraph.operators import embedding as M

    rows = [(i, "a", 100 + i % 3) for i in range(12)] + [(i, "b", 200 + i % 2) for i in range(12)]
    edges = spark.createDataFrame(rows, "src long, predicate string, dst long").coalesce(1)
    for norm in (1, 2):
        got = []
        for most in (M.MOST_HELD, 0):
            monkeypatch.setattr(M, "MOST_HELD", most)
            m = M.TranslationEmbedding(dim=8, epochs=3, rate=0.1, norm=norm)
            entities, predicates = m.fit(edges)
            got.append((m.losses, {r.id: list(r.vec) for r in entities.collect()}, {r.predicate: list(r.vec) for r in predicates.collect()}))
            if most:
                first = most
        monkeypatch.setattr(M, "MOST_HELD", first)
        (la, ea, pa_), (lb, eb, pb) = got
        close = lambda x, y: max(abs(a - b) for a, b in zip(x, y)) < 1e-9
        assert close(la, lb) and ea.keys() == eb.keys() and all(close(ea[i], eb[i]) for i in ea) and all(close(pa_[i], pb[i]) for i in pa_)


def test_a_prior_sweep_searches_each_pattern_once(spark, sf, monkeypatch):
    from semgraph.model import Params
    from semgraph.operators import baselines as B
    from semgraph.operators.library import build_library
    from semgraph.plans import catalog as C
    from semgraph.plans import workloads as W

    kg = G.stored_kg(spark, sf, "star")
    library, asked, plain = build_library(kg), [], B.exact_schema_scores
    monkeypatch.setattr(B, "exact_schema_scores", lambda kg, subs, *a: asked.append(subs[0].predicates) or plain(kg, subs, *a))
    params = Params(k=100, max_hops=2)
    got = W.prior_sweep(kg, C._space(spark), params, library, (0, 20), 20).collect()
    assert len(asked) == len(set(asked)) > 0
    truth = W.origin_truths(kg, list(range(25)))
    for r in got:
        one = W.quality(W.run_method("pattern_miner", kg, W.origin_queries(), C._space(spark), params, library, prior=W.prior_pairs(kg, 20, r.percent)), truth, (100,)).first()
        assert (r.precision, r.recall, r.f1) == (one.precision, one.recall, one.f1)


def test_many_queries_of_one_list_expand_what_can_reach_their_kth_score(spark, sf):
    """F8, F11: answers are those of whole lists, from fewer edges; a query of several lists is not cut."""
    from semgraph.model import Params
    from semgraph.operators import library as L
    from semgraph.operators import search as S
    from semgraph.plans import catalog as C
    from semgraph.plans import engine as E
    from semgraph.plans import workloads as W

    kg = G.stored_kg(spark, sf, "star")
    library, params, space = L.build_library(kg), Params(k=5, max_hops=3), C._space(spark)
    cut, whole = S.Stats(), S.Stats()
    got, _ = E.exact_many(kg, W.origin_queries(), space, params, library, stats=cut)
    subs, owner = E.plan_many(kg, W.origin_queries(), space, params, library)
    want = E.answers_of_many(S.layered(S.prepare(kg, subs, space, params, library), whole).scores, owner, 5)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert sum(r["edges"] for r in cut.rounds) < sum(r["edges"] for r in whole.rounds) / 2
    both = {0: W.two_lists(), 1: W.origin()}
    got, found = E.exact_many(kg, both, space, params, library)
    assert not found.missing
    assert [r.score for r in got.filter("query_id = 0").orderBy("rank").collect()] == [r.score for r in E.exact_query(kg, W.two_lists(), space, params, library).answers.orderBy("rank").collect()]


def test_methods_stop_where_k_are_proven(spark, sf, monkeypatch):
    """keyword and pattern search find the same k best with fewer levels and patterns; what no type is like is not walked."""
    from semgraph.model import Params
    from semgraph.operators import baselines as B
    from semgraph.operators import library as L
    from semgraph.plans import catalog as C
    from semgraph.plans import engine as E
    from semgraph.plans import workloads as W

    kg = G.stored_kg(spark, sf, "star")
    library, space, owner = L.build_library(kg), C._space(spark), {0: 0, 1: 1}
    subs, _ = E.plan_many(kg, {0: W.origin("N7"), 1: W.origin("N3")}, space, Params(), library)
    top = lambda scores, up: sorted(map(tuple, E.answers_of_many(scores.withColumnRenamed("query_id", "sub_id").withColumnRenamed("score", "psi"), owner, 5, ascending=up).collect()))
    done, stored, schema = [], B.keep, B.exact_schema_scores
    monkeypatch.setattr(B, "keep", lambda df, name, *m: (done.append(name), stored(df, name, *m))[1])
    terms, keys = {0: ["nation 7", "originnation"], 1: ["nation 3", "originnation"]}, {0: {"order"}, 1: {"order"}}
    whole, n = top(B.keyword_scores(kg, terms, keys, 3), True), done.count("level")
    assert len(whole) == 10 and top(B.keyword_scores(kg, terms, keys, 3, 5), True) == whole and done.count("level") - n < n
    monkeypatch.setattr(B, "exact_schema_scores", lambda *a: (done.append("pattern"), schema(*a))[1])
    patterns = [("originNation", 1.0), ("customerNation placedBy", 0.5), ("originNation containsPart containsPart", 0.2)]
    few = top(B.pattern_miner_scores(kg, subs, patterns, library, k=5), False)
    assert done.count("pattern") < 3
    assert few == top(B.pattern_miner_scores(kg, subs, patterns, library), False) and len(few) == 10
    monkeypatch.setattr(B, "_levels", lambda *a: 1 / 0)
    unlike, _ = E.plan_many(kg, {0: W.origin("N7", "Zzzzzzzzzz")}, space, Params(), library)
    assert B.homomorphism_scores(kg, unlike, 0.6, 4).isEmpty()


def test_an_epoch_of_joins_lets_its_shuffles_go(spark, monkeypatch):
    """shuffles of triples with vectors do not pile up over epochs, and the triples are stored as packed files."""
    from semgraph.operators import embedding as X

    done, let_go, stored = [], X._let_go, X.keep
    monkeypatch.setattr(X, "MOST_HELD", 0)
    monkeypatch.setattr(X, "_let_go", lambda s: (done.append("let go"), let_go(s))[1])
    monkeypatch.setattr(X, "keep", lambda df, name, *m: (done.append(name), stored(df, name, *m))[1])
    edges = spark.createDataFrame([(i, "p", i + 1) for i in range(20)], "src long, predicate string, dst long")
    assert X.TranslationEmbedding(dim=4, epochs=2).fit(edges)[0].count() == 21
    assert done.count("let go") == 2 and done.count("triples") == 1


def test_both_decompositions_expand_only_what_the_k_best_sums_can_hold(spark, sf, monkeypatch):
    """Answers are those of whole lists; the search ends where k sums are proven, and beside a list that is whole only its pivots are asked for."""
    from semgraph.model import Params
    from semgraph.operators import library as L
    from semgraph.operators import search as S
    from semgraph.plans import catalog as C
    from semgraph.plans import decompose as D
    from semgraph.plans import engine as E
    from semgraph.plans import workloads as W

    kg, space = G.stored_kg(spark, sf, "star"), C._space(spark)
    library, params = L.build_library(kg), Params(k=2, max_hops=3)
    spared = set()
    for gq in (W.two_lists(), W.cycle(), W.star()):
        for objective in ("min", "max"):
            whole = E.exact_query(kg, gq, space, params, library, decomposition=objective, strategy="full", measured=True)
            part = E.exact_query(kg, gq, space, params, library, decomposition=objective, measured=True)
            assert part.answers.collect() == whole.answers.collect(), (gq.label, objective)
            assert part.stats.list_rows <= whole.stats.list_rows and part.stats.edges_weighted <= whole.stats.edges_weighted
            spared |= {gq.label} if part.stats.edges_weighted < whole.stats.edges_weighted and part.stats.list_rows < whole.stats.list_rows else set()
            if objective == "max":
                continue
            best = {(r.sub_id, r.pivot_id): r.psi for r in whole.matches.collect()}
            answers = {r.pivot_id for r in part.answers.collect()}
            assert {(r.sub_id, r.pivot_id): r.psi for r in part.matches.collect() if r.pivot_id in answers} == {k: v for k, v in best.items() if k[1] in answers}

    assert "two lists" in spared
    want = {r.predicate: 2 * r["count"] for r in kg.edges.groupBy("predicate").count().collect()}
    assert D.collect_stats(kg) == D.GraphStats(want, kg.nodes.count())
    assert D.source_counts(kg, W.star(), library, params) == {n.key: L.match_nodes(kg, library, n).count() for n in W.star().nodes if n.specific}
    monkeypatch.setattr(S, "MOST_NAMED", 0)
    assert D.source_counts(kg, W.origin("N3"), library, params) == {"n": 1}

    calls, search = [], E.exact_query
    monkeypatch.setattr(E, "exact_query", lambda *a, **b: calls.append(b["decomposition"]) or search(*a, **b))
    monkeypatch.setattr(S, "MOST_NAMED", 10_000)
    ((label, shape, optimal, worst, gain),) = W.decomposition_times(kg, [W.star()], space, params, library).collect()  # one cover only
    assert (label, shape, gain, calls) == ("star", "star", 0.0, ["min", "min"]) and optimal == worst > 0


def test_embedding_in_blocks_is_that_of_joins(spark, monkeypatch):
    """where tasks hold all vectors, no triple is widened by vectors, hubs are summed by all tasks, and only the newest vectors stay stored."""
    from semgraph.operators import embedding as X

    rows = [(i, "a", 100 + i % 3) for i in range(40)] + [(i, "b", 200) for i in range(40)] + [(200, "c", 100)]
    edges = spark.createDataFrame(rows, "src long, predicate string, dst long").coalesce(2)
    want = {r.at for r in edges.selectExpr(f"explode(array({', '.join(f'xxhash64(src, predicate, dst, 1, 0, {e})' for e in range(3))})) AS at").collect()}
    first = np_of(edges.selectExpr("xxhash64(src, predicate, dst, 1, 0) AS h"))
    assert {int(x) for e in range(3) for x in X._last_hash(first, e)} == want

    got, dropped, drop = [], [], X.drop
    monkeypatch.setattr(X, "drop", lambda df: (dropped.append(df), drop(df)))
    monkeypatch.setattr(X, "VECTORS", 7)
    for most, ends, triples in ((1 << 40, 1 << 40, 10), (1 << 40, 5, 100), (0, 0, 0)):
        monkeypatch.setattr(X, "MOST_HELD", most)
        monkeypatch.setattr(X, "HUB_ENDS", ends)
        monkeypatch.setattr(X, "TASK_TRIPLES", triples)
        if most:
            monkeypatch.setattr(X.TranslationEmbedding, "_gradients", lambda *a: 1 / 0)
        else:
            monkeypatch.undo()
            monkeypatch.setattr(X, "MOST_HELD", 0)
        m = X.TranslationEmbedding(dim=8, epochs=3, rate=0.1, negatives=2)
        entities, predicates = m.fit(edges)
        got.append((m.losses, {r.id: list(r.vec) for r in entities.collect()}, {r.predicate: list(r.vec) for r in predicates.collect()}))
    assert len(dropped) == 6
    close = lambda x, y: max(abs(a - b) for a, b in zip(x, y, strict=True)) < 1e-9
    for losses, e, p in got[:2]:
        assert close(losses, got[2][0]) and e.keys() == got[2][1].keys() and p.keys() == got[2][2].keys()
        assert all(close(e[i], got[2][1][i]) for i in e) and all(close(p[i], got[2][2][i]) for i in p)


def np_of(df):
    import numpy as np

    return np.array([r[0] for r in df.collect()], np.int64)
