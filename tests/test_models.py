"""Semantics of the two models, rule programs, measures and cost rules on small inputs."""

import pandas as pd
import pytest
from pyspark.sql import functions as F

from fixflow.functions.measures import cost_optimal, machine_seconds, plan_regret, scaleup, speedup
from fixflow.operators.mru import MRU, check_aggregate_laws, run_mru
from fixflow.operators.reduce import TOPOLOGIES, reduce_columns
from fixflow.operators.vertex import VertexGraph, VertexProgram, run_vertex
from fixflow.plans import cost
from fixflow.plans.analysis import Violation, check_safety, stage_stratify, stratify
from fixflow.plans.evaluate import evaluate, infer_schemas, run_stages
from fixflow.plans.rules import ParseError, parse_program
from fixflow.tasks import graphs as G
from fixflow.tasks.learning import bgd, gaussian_bayes, gaussian_bayes_predict, ols
from fixflow.tasks.queries import PUBLISHED


def edges(spark, *pairs):
    return spark.createDataFrame(list(pairs), "src long, dst long")


def test_equal_payloads_both_count(spark):
    e = edges(spark, (1, 3), (2, 3))
    p = VertexProgram(init=lambda: F.lit(1).cast("long"), emit=lambda: F.col("state"), update=lambda: F.col("inbox"), combine="sum")
    state, report = run_vertex(p, VertexGraph(G.vertices(e), e), 5)
    assert {r.id: r.state for r in state.collect()} == {1: 1, 2: 1, 3: 2}
    assert report.active == [1, 0]  # the sink that ran has no one to send to


def test_unknown_ids_are_dropped_and_null_keeps_the_state(spark):
    ids = spark.createDataFrame([(1,), (2,)], "id long")
    p = VertexProgram(init=lambda: F.col("id"), emit=lambda: F.lit(7).cast("long"), update=lambda: F.lit(None).cast("long"), combine=None)
    state, _ = run_vertex(p, VertexGraph(ids, edges(spark, (1, 2), (1, 99))), 2)
    assert {r.id: r.state for r in state.collect()} == {1: 1, 2: 2}


def test_rank_invariants(spark):
    cycle = edges(spark, (0, 1), (1, 2), (2, 3), (3, 0))
    ranks = {r.id: r.rank for r in G.pagerank(cycle)[0].collect()}
    assert all(abs(v - 0.25) < 1e-12 for v in ranks.values())
    star = edges(spark, (0, 1), (2, 1))
    total = sum(r.rank for r in G.pagerank(star, dangling="redistribute", iterations=3)[0].collect())
    assert abs(total - 1) < 1e-12


@pytest.mark.parametrize("store", ["replace", "append_latest", "delta_merge"])
def test_stores_agree(spark, store):
    e = edges(spark, (0, 1), (1, 2), (2, 0), (0, 2))
    want = {r.id: round(r.rank, 12) for r in G.pagerank_dense(e, iterations=3).collect()}
    got = {r.id: round(r.rank, 12) for r in G.pagerank_supersteps(e, iterations=3, store=store)[0].collect()}
    assert got == want


def test_components_and_distances(spark):
    e = edges(spark, (5, 4), (4, 9), (1, 2))
    assert {r.id: r.component for r in G.connected_components(e)[0].collect()} == {5: 4, 4: 4, 9: 4, 1: 1, 2: 1}
    one = spark.createDataFrame([(5,)], "id long")
    assert {r.id: r.distance for r in G.sssp(e, one)[0].collect()} == {5: 0, 4: 1, 9: 2, 1: None, 2: None}


def test_triangles(spark):
    e = edges(spark, (1, 2), (2, 3), (3, 1), (3, 4))
    assert {r.id: r.triangles for r in G.triangle_count(e).collect()} == {1: 1, 2: 1, 3: 1}


def test_mru_stops_when_the_model_stays(spark):
    m = MRU(init=lambda: 0, map=lambda w: {"n": F.lit(1)}, update=lambda j, w, s: min(s["n"], 3))
    model, report, models = run_mru(m, spark.range(5), 10)
    assert model == 3 and models == [0, 3, 3] and len(report.iteration_seconds) == 2


def test_topologies_agree(spark):
    df = spark.range(1000).select(*[(F.col("id") * k).alias(f"v{k}") for k in range(5)])
    want = {f"v{k}": 499500 * k for k in range(5)}
    for t in TOPOLOGIES:
        assert reduce_columns(df, {f"v{k}": F.col(f"v{k}") for k in range(5)}, t) == want, t


def test_descent_reaches_least_squares(spark):
    x = spark.createDataFrame([(1.0, float(k) / 10, 2 + 3 * k / 10) for k in range(10)], "a double, b double, y double")
    w, report, _ = bgd(x, ["a", "b"], eta=1.0, iterations=60)
    assert all(q <= p + 1e-12 for p, q in zip(report.loss, report.loss[1:]))
    assert ols(x, ["a", "b"]) == pytest.approx([2, 3], abs=1e-9)
    assert w == pytest.approx([2, 3], abs=0.1)


def test_laws():
    assert check_aggregate_laws(lambda a, b: a + b, [1, 2, 3]) == []
    assert check_aggregate_laws(lambda a, b: a - b, [1, 2, 3]) == ["associative", "commutative"]


def test_parser_and_safety():
    p = parse_program("derive path(x, z) from edge(x, y), path(y, z) where x != z;")
    assert [str(a) for a in p.rules[0].atoms()] == ["edge/2", "path/2"]
    with pytest.raises(ParseError, match="line 1"):
        parse_program("derive path(x from edge(x, y)")
    with pytest.raises(Violation, match="not bound"):
        check_safety(parse_program("derive p(x, z) from q(x, y);"))
    with pytest.raises(Violation, match="not bound"):
        check_safety(parse_program("derive p(x) from q(x), not r(y);"))


def test_strata_and_stages():
    assert stratify(parse_program("derive a(x) from e(x); derive b(x) from e(x), not a(x);")) == [["a"], ["b"]]
    with pytest.raises(Violation, match="cycle"):
        stratify(parse_program("derive a(x) from e(x), not a(x);"))
    good = "derive s@0(x) from v(x); derive t@J(sum(x)) from s@J(x); derive s@J+1(x) from t@J(x);"
    assert [r.head.name for r in stage_stratify(parse_program(good)).step] == ["t", "s"]
    with pytest.raises(Violation, match="no stage"):
        stage_stratify(parse_program("derive a(x) from e(x); derive a(x) from a(x), e(x);"))
    with pytest.raises(Violation, match="same stage"):
        stage_stratify(parse_program("derive a@J(x) from b@J(x); derive b@J(sum(x)) from a@J(x);"))
    with pytest.raises(Violation, match="stage J from"):
        stage_stratify(parse_program("derive a@J(x) from b@J+1(x); derive b@J+1(x) from a@J(x);"))


def test_evaluation_modes_agree_and_negation(spark):
    e = edges(spark, (1, 2), (2, 3), (3, 1), (3, 4))
    p = parse_program("derive r(x, y) from e(x, y); derive r(x, z) from r(x, y), e(y, z); derive loop(x) from r(x, x); derive line(x) from e(x, _), not loop(x);")
    a, b = evaluate(p, {"e": e}, "naive"), evaluate(p, {"e": e}, "semi_naive")
    assert sorted(map(tuple, a["r"].collect())) == sorted(map(tuple, b["r"].collect()))
    assert sorted(r[0] for r in b["loop"].collect()) == [1, 2, 3] and b["line"].count() == 0


def test_stages_keep_bags(spark):
    p = parse_program("derive s@0(v, c) from v(v, c); derive m@J(sum(c)) from s@J(_, c); derive s@J+1(x, c) from m@J(c), k(x);")
    out, n = run_stages(p, {"v": spark.createDataFrame([(1, 2), (2, 2)], "v long, c long"), "k": spark.createDataFrame([(9,)], "x long")}, 1)
    assert n == 1 and [tuple(r) for r in out["s"].collect()] == [(9, 4)]


def test_published_costs_and_choices():
    ref = [(m, s) for n, m, s in PUBLISHED if n == "bgd_ref"]
    assert cost_optimal(ref) == 10 and cost_optimal([(m, s) for n, m, s in PUBLISHED if n == "bgd_im"]) == 30
    assert machine_seconds(10, 70.4069) == pytest.approx(704.069)
    assert speedup(ref)[0][1] == 1 and scaleup([(70, 10.0), (140, 12.0)])[1][1] == pytest.approx(1.2)
    assert plan_regret(2.0, {"a": 1.0, "b": 2.0}) == 2
    c = cost.predict_reduce_cost(720, 180, 16e6, 125e6)
    assert c["tree"] < c["local_sqrt"] < c["sqrt"] < c["flat"]
    assert cost.choose_reduce(720, 180, 16e6, 125e6) == "blocks" and cost.choose_reduce(2, 1, 100, 125e6) == "flat"
    assert cost.choose_model_family(16e6, 80e9) == "mru" and cost.choose_model_family(20e9, 70e9) == "vertex"
    assert cost.choose_store(100, 5) == "delta_merge" and cost.choose_layout(10**9) == "feature_table"
    assert cost.choose_join(1e6, 1e12, False) == "broadcast" and cost.choose_join(1e10, 1e12, True) == "merge"


def test_one_exchange_a_round(spark, sf):
    from fixflow.sources.tables import graph

    e = graph(spark, sf, "g_part_supp")
    plans = [G.pagerank_dense(e, iterations=k)._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning(dst") for k in (1, 2, 3)]
    assert plans[1] - plans[0] == plans[2] - plans[1] <= 2  # the rank's own, and its ordering for the join; never the edges


@pytest.mark.parametrize("kind", ["hash_agg", "hash_sort", "sorted"])
def test_each_exchange_is_one_and_combined(spark, kind):
    """The three exchanges give the same inboxes, with a single exchange of messages that senders have combined."""
    from fixflow.operators.vertex import deliver

    mail = spark.range(6000).selectExpr("id % 37 as dst", "cast(id as double) as payload").repartition(5)
    for f, want in (("sum", sum), ("min", min), ("max", max)):
        got = deliver(mail, f, kind)
        assert {r.dst: r.inbox for r in got.collect()} == {k: float(want(range(k, 6000, 37))) for k in range(37)}
    plan = deliver(spark.range(6000).selectExpr("id % 37 as dst", "cast(id as double) as payload"), "sum", kind)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1
    below = plan.split("Exchange hashpartitioning")[1]
    assert ("partial_sum" in below) if kind == "hash_agg" else ("MapInArrow" in below and "Sort" in plan.split("Exchange hashpartitioning")[0])


def test_no_fixpoint_within_the_cap_is_an_error(spark):
    path = spark.range(8).selectExpr("id as src", "id + 1 as dst")
    with pytest.raises(RuntimeError):
        G.connected_components(path, 3)
    from fixflow.plans.evaluate import evaluate
    from fixflow.plans.queries import CLOSURE
    from fixflow.plans.rules import parse_program

    with pytest.raises(RuntimeError):
        evaluate(parse_program(CLOSURE), {"edge": path}, max_rounds=3)
    assert evaluate(parse_program(CLOSURE), {"edge": path})["path"].count() == 36


def test_ranking_options_run_supersteps(spark, sf):
    from fixflow.sources.tables import graph

    e = graph(spark, sf, "g_pages")
    plain = {r.id: r.rank for r in G.pagerank(e, iterations=3)[0].collect()}
    for options in ({"store": "replace"}, {"exchange": "hash_sort"}, {"exchange": "sorted"}, {"early_grouping": False}):
        ranks, report = G.pagerank(e, iterations=3, **options)
        assert len(report.active) == 3, options
        assert {r.id: pytest.approx(r.rank, abs=1e-12) for r in ranks.collect()} == plain


def test_messages_to_any_id_create_vertices_and_aggregate(spark):
    """Vertex 1 counts down through ids that don't exist yet; every superstep sees how many vertices there were at the end of the last."""
    none = spark.createDataFrame([], "src long, dst long")
    ids = spark.createDataFrame([(1,)], "id long")
    to_next = F.array(F.struct((F.col("src") + 1).alias("dst"), (F.col("state.left") - 1).alias("payload")))
    state = lambda left, seen: F.struct(left.cast("long").alias("left"), seen.cast("long").alias("seen"))
    p = VertexProgram(
        init=lambda: state(F.lit(3), F.lit(0)),
        emit=None,
        update=lambda: state(F.col("inbox"), F.col("agg_vertices")),
        combine="max",
        send=lambda: F.when(F.col("state.left") > 0, to_next),
        aggregates={"vertices": lambda: F.count("*")},
        on_unknown="create",
    )
    out, report = run_vertex(p, VertexGraph(ids, none), 9)
    assert {r.id: tuple(r.state) for r in out.collect()} == {1: (3, 0), 2: (2, None), 3: (1, 2), 4: (0, 3)}
    assert report.active == [1, 1, 1, 0]
    p.on_unknown = "drop"
    assert [tuple(r.state) for r in run_vertex(p, VertexGraph(ids, none), 9)[0].collect()] == [(3, 0)]


def test_layouts_agree_and_descent_on_vertices_is_descent(spark):
    from fixflow.baselines.runs import bgd_as_vertices
    from fixflow.tasks.learning import bgd_feature_table

    rows = [(k, float(k % 2), [1.0, (k % 5) / 5, (k % 3) / 3]) for k in range(40)]
    x = spark.createDataFrame(rows, "id long, y double, f array<double>").select("id", "y", *[F.col("f")[k].alias(f"x{k}") for k in range(3)])
    entries = x.select("id", F.posexplode(F.array("x0", "x1", "x2")).alias("feature", "x"))
    want = bgd(x, ["x0", "x1", "x2"], "logistic", iterations=4)[0]
    for layout in ("broadcast_dense", "feature_table"):
        got = {r.feature: r.weight for r in bgd_feature_table(x, entries, iterations=4, layout=layout).collect()}
        assert [got[k] for k in range(3)] == pytest.approx(want, abs=1e-12), layout
    assert bgd_as_vertices(x, ["x0", "x1", "x2"], "logistic", iterations=4) == pytest.approx(want, abs=1e-12)


def test_auc_counts_ties_half(spark):
    from fixflow.tasks.learning import evaluate as measured

    rows = [(k % 3 % 2, (k * 7 % 11) / 10.0) for k in range(60)]
    pairs = [(a, b) for y, a in rows if y for z, b in rows if not z]
    want = sum(1.0 if a > b else 0.5 if a == b else 0.0 for a, b in pairs) / len(pairs)
    assert measured(spark.createDataFrame(rows, "y int, prediction double")).first().auc == pytest.approx(want, abs=1e-12)


def test_experiment_summary():
    from fixflow.experiments import summary

    points = [{"method": "m", "cores": c, "copies": n, "seconds": s} for c, n, s in ((1, 1, 8.0), (2, 1, 4.0), (4, 1, 4.0), (2, 2, 10.0))]
    out = summary(points)
    assert out[0] == {"method": "m", "copies": 1, "speedup": [(1, 1.0, 1.0), (2, 2.0, 1.0), (4, 2.0, 0.5)], "core_seconds": {1: 8.0, 2: 8.0, 4: 16.0}, "cost_optimal_cores": 1}
    assert {"method": "m", "scaleup_same_data_per_core": 1.0, "points": [(1, 1.0), (2, 1.25)]} in out
    assert {"method": "m", "growth_same_cores": 2, "points": [(1, 1.0), (2, 2.5)]} in out


def test_types_of_predicates_are_inferred(spark):
    e = edges(spark, (1, 2))
    closure = parse_program("derive path(x, y) from edge(x, y); derive path(x, z) from path(x, y), edge(y, z); derive degree(x, count(y)) from path(x, y);")
    assert {p: [f.dataType.simpleString() for f in s] for p, s in infer_schemas(closure, {"edge": e}).items()} == {"edge": ["bigint"] * 2, "path": ["bigint"] * 2, "degree": ["bigint"] * 2}
    staged = parse_program("derive s@0(x, r) from edge(x, y), r := one(); derive s@J+1(x, q) from latest_s(x, r), q := half(r);", {"one": lambda: F.lit(1), "half": lambda r: r / 2})
    assert [f.dataType.simpleString() for f in infer_schemas(staged, {"edge": e})["s"]] == ["bigint", "double"]
    with pytest.raises(Violation, match="elsewhere"):
        infer_schemas(parse_program("derive p(x) from edge(x, y); derive p('a') from edge(x, y);"), {"edge": e})
    with pytest.raises(Violation, match="unknown types"):
        infer_schemas(parse_program("derive p(x) from p(x);"), {"edge": e})


def test_a_null_differs_from_a_value_only(spark):
    e = spark.createDataFrame([(1, None), (2, 2), (3, 4), (None, None)], "src long, dst long")
    out = evaluate(parse_program("derive p(x, y) from edge(x, y) where x != y;"), {"edge": e})["p"]
    assert {tuple(r) for r in out.collect()} == {(1, None), (3, 4)}


def test_bayes_with_a_constant_component(spark):
    x = spark.createDataFrame([([0.0, 1.0], 0.0), ([0.2, 1.0], 0.0), ([5.0, 1.0], 1.0), ([5.4, 1.0], 1.0), (None, 1.0), ([9.0, 1.0], None)], "x array<double>, y double")
    model = gaussian_bayes(x, 2)
    assert [(c, n) for c, n, _, _ in model] == [(0.0, 2), (1.0, 2)]
    assert model[1][2] == pytest.approx([5.2, 1.0]) and model[1][3] == pytest.approx([0.04, 0.0], abs=1e-8)
    assert [r.prediction for r in gaussian_bayes_predict(x.where("y is not null and x is not null"), model).orderBy("x").collect()] == [0.0, 0.0, 1.0, 1.0]


def test_an_aggregate_of_user_code_and_members(spark):
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("double")
    def middle(v: pd.Series) -> float:
        return float(v.median())

    e = edges(spark, (1, 2), (1, 4), (1, 100), (2, 7))
    out = evaluate(parse_program("derive m(x, middle(y)) from edge(x, y); derive l(x, list(y)) from edge(x, y); derive back(x, each(s)) from l(x, s);", {"middle": middle}), {"edge": e})
    assert {tuple(r) for r in out["m"].collect()} == {(1, 4.0), (2, 7.0)}
    assert {tuple(r) for r in out["back"].collect()} == {(1, 2), (1, 4), (1, 100), (2, 7)}


def test_a_run_halts_and_goes_on_from_its_store(spark, tmp_path):
    x = spark.createDataFrame([(1.0,), (3.0,)], "v double")
    loop = MRU(lambda: 0.0, lambda w: {"g": F.col("v") - w}, lambda j, w, s: w + (j + 1) * s["g"] / 16)
    whole = run_mru(loop, x, 4)[2]
    assert run_mru(loop, x, 2, store=str(tmp_path / "m"))[0] == whole[2]
    again, report, models = run_mru(loop, x, 4, store=str(tmp_path / "m"), resume=True)
    assert again == whole[4] and models == whole[2:] and len(report.iteration_seconds) == 2
    assert run_mru(loop, x, 4, store=str(tmp_path / "m"), resume=True)[0] == whole[4]  # nothing is left to do
    assert run_mru(MRU(loop.init, loop.map, loop.update, halt=lambda w: w >= whole[2]), x, 9)[0] == whole[2]


def test_scores_of_a_stream_stay_in_files(spark, sf):
    from fixflow.streaming.windows import score_stream

    out = score_stream(spark, sf)
    assert out.inputFiles() and out.count() == spark.read.parquet(f"{sf}/events.parquet").count()


def test_hubs_send_by_broadcast_and_leave_no_tables(spark):
    before = {t.name for t in spark.catalog.listTables()}
    out = [(-1, k, float(k)) for k in range(50)] + [(-2, k, 2.0) for k in range(0, 50, 3)]
    back = [(k, a, w) for a, k, w in out]
    ids = spark.createDataFrame([(i,) for i in range(-2, 50)], "id long")
    frame = lambda rows: spark.createDataFrame(rows, "src long, dst long, weight double")
    p = VertexProgram(init=lambda: F.col("id").cast("double"), emit=lambda: F.col("state") * F.col("weight"), update=lambda: F.col("inbox") / 100)
    plain = {r.id: r.state for r in run_vertex(p, VertexGraph(ids, frame(out + back)), 3)[0].collect()}
    got = run_vertex(p, VertexGraph(ids, frame(back), [-1, -2], frame(out)), 3)[0]
    assert {r.id: r.state for r in got.collect()} == pytest.approx(plain)
    assert len({t.name for t in spark.catalog.listTables()} - before) == 1  # the last state; the others went with their successors


def test_triangles_by_ranges_equal_triangles_of_all_vertices(spark):
    import itertools
    import random

    r = random.Random(3)
    own = sorted({tuple(sorted(r.sample(range(40), 2))) for _ in range(260)})
    want = {k: 0 for k in range(40)}
    for t in itertools.combinations(range(40), 3):
        if all(p in set(own) for p in itertools.combinations(t, 2)):
            for k in t:
                want[k] += 1
    want = {k: n for k, n in want.items() if n}
    e = edges(spark, *own, *[(b, a) for a, b in own[::3]], (7, 7), *own[:5])
    for block in (1 << 19, 20, 3):
        assert {x.id: x.triangles for x in G.triangle_count(e, block).collect()} == want, block
    named = e.select(F.concat(F.lit("v"), "src").alias("src"), F.concat(F.lit("v"), "dst").alias("dst"))
    assert {x.id: x.triangles for x in G.triangle_count(named, 50).collect()} == {f"v{k}": n for k, n in want.items()}
    assert G.triangle_count(e.where("false")).count() == 0


def test_least_costs_come_from_a_table_of_runs(spark, sf):
    from fixflow.functions.measures import cost_optimal_points
    from fixflow.tasks.queries import cost_optimal_published

    out = cost_optimal_points(spark.createDataFrame(PUBLISHED, "method string, machines long, seconds double"))
    assert {r.method: r.machines for r in out.collect()} == {m: cost_optimal([(k, s) for n, k, s in PUBLISHED if n == m]) for m, _, _ in PUBLISHED}
    assert any("lineitem" in f for f in cost_optimal_published(spark, sf).inputFiles())


def test_costs_of_reduces_come_from_a_table(spark, sf):
    from fixflow.tasks.queries import reduce_cost_model

    out = reduce_cost_model(spark, sf)
    assert any("lineitem" in f for f in out.inputFiles())
    for r in out.collect():
        want = cost.predict_reduce_cost(4 * r.machines, r.machines, 16e6, 125e6)
        assert [r.flat, r.sqrt, r.local_sqrt, r.tree] == pytest.approx([want[k] for k in ("flat", "sqrt", "local_sqrt", "tree")], abs=1e-3)
