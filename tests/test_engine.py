"""Trees, queries and joins against plain plans."""

import math

import pytest
from pyspark.sql import functions as F

from treesieve import streaming, workloads
from treesieve.functions.expr import AnalysisError, E, abs_, bind, both, col, lit, sqrt_
from treesieve.operators import baselines, joins, measures, pairs
from treesieve.operators.tree import Agg, Forest, TreeSpec, build, read_index
from treesieve.plans.query import Q, prune_with

X = col("x")


def points(spark, n, salt=7919):
    return spark.range(n).select("id", ((F.col("id") * salt) % 1009).cast("double").alias("x"), ((F.col("id") * 31) % 97).cast("double").alias("y"))


@pytest.fixture(scope="module")
def tree(spark):
    return build(points(spark, 500), TreeSpec.interval("x", Agg("count"), Agg("sum", "y"), Agg("min", "id"), Agg("max", "id"), leaf_rows=20, fanout=3))


def test_every_row_is_in_one_leaf_and_parents_sum_their_children(tree):
    assert tree.n == 500 and tree.n_leaves == 25 and tree.height == 3
    assert tree.rows.count() == 500 and tree.rows.select("id").distinct().count() == 500
    for level in tree.levels:
        assert level.agg(F.sum("__rows")).first()[0] == 500
    nodes = {r["node_id"]: r for r in tree.levels[1].collect()}
    for r in tree.levels[0].collect():
        up = nodes[r["node_id"] // 3]
        assert up["x_lo"] <= r["x_lo"] <= r["x_hi"] <= up["x_hi"]


@pytest.mark.parametrize("n", [0, 21])
def test_shapes(spark, n):
    t = build(points(spark, n), TreeSpec.interval("x", Agg("count"), leaf_rows=20, fanout=3))
    assert Q(t).count().first()[0] == n
    assert Q(t).filter(X >= 500).count().first()[0] == points(spark, n).where("x >= 500").count()
    assert Q(t).min(abs_(X - 3)).first()[0] == points(spark, n).agg(F.min(F.abs(F.col("x") - 3))).first()[0]


@pytest.mark.parametrize("method", ["tile", "median"])
def test_builders_agree(spark, method):
    t = build(points(spark, 300), TreeSpec(("x", "y"), (Agg("count"),), method=method, leaf_rows=16, fanout=4))
    p = both(X.between(100, 500), col("y") < 40)
    want = sorted(r[0] for r in points(spark, 300).where("x BETWEEN 100 AND 500 AND y < 40").select("id").collect())
    assert sorted(r["id"] for r in Q(t).filter(p).rows().collect()) == want
    assert Q(t).filter(p).count().first()[0] == len(want)


def test_reductions_agree_with_plain_plans(tree):
    for p, sql in ((X.between(100, 300), "x BETWEEN 100 AND 300"), (abs_(X - 500) > 450, "abs(x - 500) > 450"), (X < -1, "x < -1")):
        rows = tree.scan().where(sql)
        want = rows.agg(F.sum("y"), F.min("id"), F.max("id")).first()
        assert tuple(Q(tree).filter(p).reduce(k, c).first()[0] for k, c in (("sum", "y"), ("min", "id"), ("max", "id"))) == tuple(want)
    for q in (Q(tree, stored=False), Q(tree, prune=False), Q(tree, fuse=False)):
        assert q.filter(p).reduce("sum", "y").first()[0] == want[0]
    assert Q(tree).any(X > 900).first()[0] is True and Q(tree).all(X > 200).first()[0] is False and Q(tree).all(X >= 0).first()[0] is True


def test_stored_values_save_rows(tree):
    c = Q(tree).filter(X.between(100, 800)).explain_analyze().collect()
    assert sum(r["taken"] for r in c) > 0 and sum(r["pruned"] for r in c) > 0 and sum(r["rows_tested"] for r in c) <= 2 * 20
    m = measures.tightness(Q(tree).filter(X.between(100, 800))).first()
    assert m["missed_rows"] == 0 and m["wrong_rows"] == 0
    by_hand = prune_with(tree, (F.col("x_hi") >= 100) & (F.col("x_lo") <= 800), (F.col("x_lo") >= 100) & (F.col("x_hi") <= 800))
    seen = {s.count() for s in by_hand}
    assert seen == {r["taken"] + r["descended"] + r["pruned"] for r in c}


def test_argmin_has_a_member_under_ties(spark):
    for values in ((1.0, 0.0, 0.0), (0.0, 0.0, 0.0)):
        df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "id long, x double")
        t = build(df, TreeSpec.interval("x", leaf_rows=1, fanout=2))
        assert Q(t).filter(X <= 1).argmin("x", ("id",)).first()["id"] == min(range(3), key=lambda i: (values[i], i))


def test_null_nan_and_infinity(spark):
    df = spark.createDataFrame([(0, None), (1, float("nan")), (2, 0.0), (3, -0.0), (4, math.inf), (5, -math.inf), (6, 7.0)], "id long, x double")
    t = build(df, TreeSpec.interval("x", Agg("count"), leaf_rows=2, fanout=2))
    for p, sql in ((X > 1, "x > 1"), (X <= 0, "x <= 0"), (~(X < 5), "not x < 5"), (X.is_null(), "x is null"), (X.not_null(), "x is not null"), (abs_(X) >= 0, "abs(x) >= 0")):
        want = sorted(r[0] for r in df.where(sql).select("id").collect())
        assert sorted(r["id"] for r in Q(t).filter(p).rows().collect()) == want, sql


def test_joins_agree(spark):
    a, b = points(spark, 120), points(spark, 90, 457)
    spec = TreeSpec(("x", "y"), (Agg("count"),), method="zorder", leaf_rows=8, fanout=3)
    ta, tb = build(a, spec), build(b, spec)
    p = both(abs_(col("x", 0) - col("x", 1)) <= 30, col("y", 0) < col("y", 1))
    want = sorted((r["id"], r["r_id"]) for r in joins.nested_join(a, b, p).collect())
    assert sorted((r["id"], r["r_id"]) for r in joins.dual_index_join(ta, tb, p).collect()) == want
    assert sorted((r["id"], r["r_id"]) for r in joins.single_index_join(a, tb, p).collect()) == want
    assert joins.Pairs(ta, tb, p).count().first()[0] == len(want)
    all_pairs = col("x", 0) < col("x", 1) + 5000
    assert joins.Pairs(ta, tb, all_pairs).count().first()[0] == 120 * 90  # taken at the root
    top = joins.Pairs(ta, tb, col("x", 0) > col("x", 1) + 5000).counters().where("level > 0 AND pairs > 0").collect()
    assert len(top) == 1 and top[0]["pairs"] == 1  # separated roots end it
    grouped = {r["id"]: sorted(m["id"] for m in r["members"]) for r in joins.single_index_join(a, tb, p, "grouped", ("id",)).collect()}
    assert len(grouped) == 120 and sorted((i, j) for i, js in grouped.items() for j in js) == want
    met = {i for i, _ in want}
    assert {r["id"] for r in joins.exists_join(a, tb, p, ("id",)).collect()} == met
    assert {r["id"] for r in joins.exists_join(a, tb, p, ("id",), negate=True).collect()} == set(range(120)) - met
    near = {r["id"]: r["r_id"] for r in joins.nearest(a, tb, abs_(col("x", 0) - col("x", 1)), ("id",), ("id",)).collect()}
    xs, ys = ({r["id"]: r["x"] for r in df.collect()} for df in (a, b))
    assert near == {i: min(ys, key=lambda j: (abs(x - ys[j]), j)) for i, x in xs.items()}
    costs = joins.choose_side(ta, tb, p)
    assert costs["dual"] <= costs["nested"]


def test_saved_index_forest_and_errors(spark, tree):
    again = read_index(spark, tree.path)
    assert again.spec == tree.spec and Q(again).filter(X < 50).count().first() == Q(tree).filter(X < 50).count().first()
    f = Forest([tree]).append(points(spark, 40))
    assert sum(Q(t).count().first()[0] for t in f.members) == 540 and Q(f.compact().members[0]).count().first()[0] == 540
    for bad in (lambda: Q(tree).filter(col("nope") < 1), lambda: Q(tree).filter(X + 1), lambda: build(points(spark, 3), TreeSpec.interval("nope"))):
        with pytest.raises(AnalysisError):
            bad()


def test_map_then_filter_and_measures(tree):
    q = Q(tree).map(z=abs_(X - 500), k=col("id")).filter(col("z") <= 20)
    assert sorted(r["k"] for r in q.select().collect()) == sorted(r["id"] for r in tree.scan().where("abs(x - 500) <= 20").collect())
    m = measures.measure(lambda: q.select(), runs=3)
    assert m.seconds > 0 and len(m.runs) == 3 and measures.slope([(1, 2), (10, 20), (100, 200)]) == pytest.approx(1)
    assert measures.lowering_ms(q) < 1000 and measures.index_bytes(tree)[0] > 0
    assert measures.selectivity(q).first()["n"] == 500 and "maybe" in q.explain()


def test_streams(spark, tree, tmp_path):
    rows = points(spark, 60).withColumn("ts", F.timestamp_seconds(F.col("id") * 60))
    rows.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = lambda: streaming.read_stream(spark, rows, str(tmp_path / "in"))
    p = abs_(col("x", 0) - col("x", 1)) <= 1
    got = streaming.drain(streaming.probe_stream(stream().select("id", "x"), tree, p).select("id", "r_id"), "probed", str(tmp_path / "c1"))
    want = joins.nested_join(rows.select("id", "x"), tree.scan(), p).select("id", "r_id")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    wins = streaming.drain(streaming.windowed(stream(), "ts", "2 hours", "10 minutes"), "wins", str(tmp_path / "c2"), "complete")
    assert wins.agg(F.sum("n")).first()[0] == 60
    low = streaming.drain(streaming.running_extremes(stream().withColumn("k", F.col("id") % 3), "k", "x", "id"), "low", str(tmp_path / "c3"), "complete")
    assert low.count() == 3
    start = Forest([build(points(spark, 10).withColumn("ts", F.timestamp_seconds(F.col("id"))), TreeSpec.interval("x", leaf_rows=20, fanout=3))])
    q, forest = streaming.keep_index(stream(), start, str(tmp_path / "c4"), compact_at=3)
    q.awaitTermination()
    assert sum(Q(t).count().first()[0] for t in forest().members) == 70


def test_restart_keeps_the_index(spark, tmp_path):
    rows = points(spark, 60)
    folder = str(tmp_path / "in")
    rows.where("id < 20").coalesce(1).write.mode("append").parquet(folder)
    start = Forest([build(rows.where("id >= 40"), TreeSpec.interval("x", leaf_rows=8, fanout=4))])
    for least, most, want in ((None, None, 40), (20, 40, 60), (None, None, 60)):  # the last restart has nothing new
        if least is not None:
            rows.where(f"id >= {least} AND id < {most}").coalesce(1).write.mode("append").parquet(folder)
        q, forest = streaming.keep_index(streaming.read_stream(spark, rows, folder), start, str(tmp_path / "c"))
        q.awaitTermination()
        assert sum(t.n for t in forest().members) == want
    with pytest.raises(Exception):
        forest().save(str(tmp_path / "c-forest"), Forest.versions(spark, str(tmp_path / "c-forest"))[-1])


def test_nulls_in_outer_and_nearest(spark):
    inner = spark.createDataFrame([(1, 5.0, None), (1, 5.0, None), (2, 7.0, "a"), (3, None, None), (4, 50.0, None)], "k long, v double, w string")
    outer = spark.createDataFrame([(1, 4.0, 8.0), (2, 90.0, 91.0)], "id long, lo double, hi double")
    t = build(inner, TreeSpec(("v",), leaf_rows=2, fanout=2))
    p = col("v", 1).between(col("lo", 0), col("hi", 0))
    for how in ("left", "right", "full"):
        got = [tuple(r) for r in joins.single_index_join(outer, t, p, key=("id",), how=how).select("id", "r_k").collect()]
        want = [(1, 1), (1, 1), (1, 2)] + ([(2, None)] if how != "right" else []) + ([(None, 3), (None, 4)] if how != "left" else [])
        assert sorted(got, key=str) == sorted(want, key=str)
    holes = spark.createDataFrame([(1, 0.0, None), (2, None, 0.0), (3, 9.0, 9.0), (4, 8.0, 20.0)], "k long, a double, b double")
    t = build(holes, TreeSpec(("a", "b"), order=("k",), leaf_rows=2, fanout=2))
    m = abs_(col("a", 1) - col("x", 0)) + abs_(col("b", 1) - col("x", 0))
    got = joins.nearest(spark.createDataFrame([(7, 0.0)], "id long, x double"), t, m, ("id",), ("k",)).collect()
    assert [(r["id"], r["r_k"], r["metric"]) for r in got] == [(7, 3, 18.0)]


def test_roots_of_negative_numbers_and_timestamps(spark):
    rows = spark.range(-50, 50).select(F.col("id").cast("double").alias("x"), (F.timestamp_seconds(F.lit(1704067200) + F.col("id") * 3600)).alias("ts"))
    t = build(rows, TreeSpec(("x", "ts"), (Agg("count"),), order=("x",), leaf_rows=5, fanout=3))
    for p, sql in ((sqrt_(col("x")) < 3, "sqrt(x) < 3"), (sqrt_(col("x")) > 3, "sqrt(x) > 3"), (lit(0) - sqrt_(col("x")) > 5, "0 - sqrt(x) > 5")):
        assert Q(t).filter(p).count().first()[0] == Q(t).filter(p).rows().count() == rows.where(sql).count()
    from treesieve.sources import files

    got = files.tree_source(spark, t.path)
    for sql in ("ts >= timestamp'2024-01-01 10:00:00'", "x < -20", "ts = timestamp'2024-01-01 00:00:00'"):
        assert got.where(sql).count() == rows.where(sql).count() > 0


def test_extremes_prune_by_stored_values(spark):
    """The smallest id in a range of x: nodes that are taken whole give it, and leaves that can't beat it aren't read."""
    n = 4000
    rows = spark.range(n).select(F.col("id"), F.col("id").cast("double").alias("x"), F.when(F.col("id") % 7 > 0, F.col("id") * 2).alias("q"))
    t = build(rows, TreeSpec(("x", "q"), (Agg("min", "id"), Agg("max", "id"), Agg("sum", "q")), order=("x",), leaf_rows=10, fanout=4))
    q = Q(t).filter(col("x").between(105.5, 3004.5))
    read: list = []
    from treesieve.plans import query as plans

    fetch = plans.fetch
    plans.fetch = lambda tree, leaves, p: (read.append(leaves.count()), fetch(tree, leaves, p))[1]
    try:
        assert q.min("id").first()[0] == 106 and q.max("id").first()[0] == 3004
        assert read == [1, 1]  # of two border leaves, the one that may beat the others
        assert q.but(stored=False).min("id").first()[0] == 106
        assert Q(t).filter(col("x") > 1e9).min("id").first()[0] is None
    finally:
        plans.fetch = fetch
    want = rows.where("x between 105.5 and 3004.5").agg(F.avg("q")).first()[0]
    assert q.reduce("avg", "q").first()[0] == pytest.approx(want) == q.but(stored=False).reduce("avg", "q").first()[0]
    assert q.user_reduce(0, lambda a, b: a + b, "id", "long").first()[0] == rows.where("x between 105.5 and 3004.5").agg(F.sum("id")).first()[0]


def test_bound_terms_keep_the_value_and_the_guards_of_divisions(spark):
    x, y = col("x"), col("y")
    s = (x - y) * (x - y) + 1
    e = E("case", (y.eq(0.0), lit(-1.0), s * s / y + s * (s + x / y)))
    df = spark.createDataFrame([(1.0, 0.0, 7), (3.0, 2.0, 8), (None, 2.0, 9)], "x double, y double, `a.b` int")
    got = bind(df, e, lambda c, _: F.col(c), "m")
    assert got.columns == ["x", "y", "a.b", "m"]
    assert [r["m"] for r in got.orderBy("`a.b`").collect()] == [-1.0, 4.0 / 2.0 + 2.0 * (2.0 + 1.5), None]


def test_closest_by_hand_and_by_brute_force_agree(spark):
    t = workloads.fixture(spark, "/root/testdata/sf0.001", "tri").where("id < 60")
    indexed = build(t, TreeSpec.boxes(workloads.TRI, order=("ax", "ay", "az"), leaf_rows=8, fanout=3))
    seen = lambda df: sorted((r["id"], r["r_id"], round(r["m"], 9)) for r in df.collect())
    points = workloads.fixture(spark, "/root/testdata/sf0.001", "point").where("id < 30")
    want = seen(baselines.brute_nearest(points, t, workloads.TO_TRI))
    assert len(want) == 30 and seen(baselines.closest_point(points, indexed, workloads.TO_TRI)) == want
    assert seen(joins.nearest(points, indexed, workloads.TO_TRI, ("id",), ("id",), name="m")) == want
    rays = workloads.fixture(spark, "/root/testdata/sf0.001", "ray")
    want = seen(baselines.brute_nearest(rays, t, workloads.TRAVEL))
    assert want and seen(baselines.closest_hit(rays, indexed, workloads.TRAVEL)) == want
    assert seen(joins.nearest(rays, indexed, workloads.TRAVEL, ("id",), ("id",), workloads.HIT, name="m")) == want


def test_sorted_join_sends_pairs_in_batches(spark, monkeypatch):
    monkeypatch.setattr(baselines, "PAIRS_AT_ONCE", 500)
    monkeypatch.setattr(baselines, "BUCKET_ROWS", 20)
    rows = [(i, None if i == 7 else float(i % 13), None if i == 9 else float("nan") if i == 11 else float(-(i % 17))) for i in range(400)]
    df = spark.createDataFrame(rows, "id long, a double, b double")
    got = baselines.inequality_join(df, df, "a", "b", "id")
    want = df.toDF("id", "a", "b").join(df.toDF("r", "c", "d"), F.expr("a < c AND b > d"))
    assert sorted(map(tuple, got.collect())) == sorted(tuple(x) for x in want.select("id", "r").collect())
    assert "MapInArrow" in got._jdf.queryExecution().toString() and "CoGroup" not in got._jdf.queryExecution().toString()


def test_index_probe_searches_its_run(spark, monkeypatch):
    monkeypatch.setattr(baselines, "PAIRS_AT_ONCE", 50)
    rows = [(i, None if i == 7 else float("nan") if i == 11 else (i * 37 % 101) / 4.0, None if i == 9 else i % 23) for i in range(300)]
    df = spark.createDataFrame(rows, "id long, x double, y int")
    got = baselines.index_probe_join(df, df, "x", "y", 2.5, 3, ("id", "id"))
    assert got.columns == ["a_id", "a_x", "a_y", "b_id", "b_x", "b_y"] and got.schema["a_y"].dataType.simpleString() == "int"
    want = df.toDF("id", "x", "y").join(df.toDF("r", "c", "d"), F.expr("abs(x - c) <= 2.5 AND abs(y - d) <= 3"))
    assert sorted(map(tuple, got.select("a_id", "b_id").collect())) == sorted(map(tuple, want.select("id", "r").collect()))
    assert "MapInArrow" in got._jdf.queryExecution().toString()  # no pair of a bucket is made before the run is searched


def test_best_of_all_pairs_is_hashed_and_ties_go_to_the_smallest_id(spark):
    near = abs_(col("v", 0) - col("v", 1))
    a = spark.createDataFrame([(i, float(i)) for i in range(30)] + [(99, None)], "id long, v double")
    b = spark.createDataFrame([(100 + i, float(i % 10)) for i in range(40)] + [(90, None)], "id long, v double")
    got = baselines.brute_nearest(a, b, near)
    assert sorted(map(tuple, got.collect())) == [(i, 100 + min(i, 9), float(max(0, i - 9))) for i in range(30)]
    assert "SortAggregate" not in got._jdf.queryExecution().executedPlan().toString()


def test_only_what_beats_the_bound_is_ranked(spark):
    t = build(points(spark, 500), TreeSpec.interval("x", leaf_rows=20, fanout=3))
    outer = spark.createDataFrame([(i, i * 97.5) for i in range(10)], "id long, v double")
    for k in (1, 2):
        got = joins.nearest(outer, t, abs_(col("v", 0) - col("x", 1)), ("id",), ("id",), k=k)
        want = {i: sorted((abs(i * 97.5 - r["x"]), r["id"]) for r in t.rows.collect())[:k] for i in range(10)}
        assert sorted((r["id"], r["metric"], r["r_id"]) for r in got.collect()) == sorted((i, *w) for i, ws in want.items() for w in ws)
        assert "monotonically_increasing_id" in got._jdf.queryExecution().optimizedPlan().toString()


def test_grouped_folds_need_no_arrays(spark):
    t = build(points(spark, 200), TreeSpec.interval("x", leaf_rows=20, fanout=3))
    outer = spark.createDataFrame([(1, 0.0, 300.0), (2, 5000.0, 6000.0)], "id long, lo double, hi double")
    got = joins.single_index_join(outer, t, col("x", 1).between(col("lo", 0), col("hi", 0)), "grouped", ("id",), folds={"n": lambda of: F.count("*"), "s": lambda of: F.sum(of("id"))})
    want = points(spark, 200).where("x BETWEEN 0 AND 300").agg(F.count("*"), F.sum("id")).first()
    assert sorted(map(tuple, got.select("id", "n", "s").collect())) == [(1, *want), (2, None, None)]
    assert "collect_list" not in got._jdf.queryExecution().toString()


def test_best_members_are_found_in_tasks(spark):
    """No pair of an outer row and a node is shuffled or sorted; nulls, NaN and ties are as in all pairs."""
    nan = float("nan")
    rows = [(i, None if i % 50 == 7 else nan if i % 50 == 9 else float(i * 37 % 101), i % 13) for i in range(400)]
    t = build(spark.createDataFrame(rows, "id long, x double, y int"), TreeSpec.boxes(("x", "y"), leaf_rows=8, fanout=3))
    probes = [(i, None if i == 5 else nan if i == 6 else i * 3.5, i % 13) for i in range(40)]
    outer = spark.createDataFrame(probes, "id long, v double, w int")
    m, p = abs_(col("v", 0) - col("x", 1)), col("w", 0).eq(col("y", 1))
    order = lambda x: (x != x, 0 if x != x else x)
    for k in (1, 3):
        got = joins.nearest(outer, t, m, ("id",), ("id",), p, k=k)
        assert "MapInArrow" in got._jdf.queryExecution().toString() and "Window" not in got._jdf.queryExecution().toString()
        want = []
        for i, v, w in probes:
            near = sorted((order(abs(v - x)), j) for j, x, y in rows if v is not None and x is not None and y == w)[:k]
            want += [(i, j) for _, j in near]
        assert sorted((r["id"], r["r_id"]) for r in got.collect()) == sorted(want)
    hit = both(p, m < 0.75)
    some = {i for i, v, w in probes if v is not None and any(x is not None and y == w and order(abs(v - x)) < (False, 0.75) for _, x, y in rows)}
    for negate in (False, True):
        got = joins.exists_join(outer, t, hit, ("id",), negate)
        assert "MapInArrow" in got._jdf.queryExecution().toString()
        assert {r["id"] for r in got.collect()} == (set(range(40)) - some if negate else some)


def test_members_are_counted_in_tasks(spark):
    nan = float("nan")
    rows = [(i, None if i % 50 == 7 else nan if i % 50 == 9 else float(i * 37 % 101), i % 13) for i in range(400)]
    df = spark.createDataFrame(rows, "id long, x double, y int")
    t = build(df, TreeSpec.boxes(("x", "y"), leaf_rows=8, fanout=3))
    for p, sql in ((both(abs_(col("x", 0) - col("x", 1)) <= 2, col("y", 0) < col("y", 1)), "abs(x - v) <= 2 AND y < w"), (both(col("x", 0) >= col("x", 1)), "x >= v")):
        got = joins.count_join(df, t, p)
        want = df.join(df.toDF("r", "v", "w"), F.expr(sql)).groupBy("id").count()
        assert got.columns == ["id", "x", "y", "n"] and sorted((r["id"], r["n"]) for r in got.collect()) == sorted(map(tuple, want.collect()))
        assert "MapInArrow" in got._jdf.queryExecution().toString()
    overlaps = workloads.QUERIES["interval_overlap"](spark, "/root/testdata/sf0.001")
    assert "MapInArrow" in overlaps._jdf.queryExecution().toString()  # no pair of sessions leaves a task


def odd_rows(n):
    nan = float("nan")
    return [(i, None if i % 50 == 7 else nan if i % 50 == 9 else float("inf") if i % 50 == 11 else float(i * 37 % 101), i % 13) for i in range(n)]


CLOSE_PAIRS = [
    (both(abs_(col("x", 0) - col("x", 1)) <= 2, col("y", 0) < col("y", 1)), "abs(x - v) <= 2 AND y < w"),
    (both(col("x", 0) < col("x", 1), col("y", 0) > col("y", 1)), "x < v AND y > w"),
    (both((col("x", 0) - col("x", 1)) * (col("x", 0) - col("x", 1)) + (col("y", 0) - col("y", 1)) * (col("y", 0) - col("y", 1)) >= 9, (col("x", 0) - col("x", 1)) * (col("x", 0) - col("x", 1)) <= 25), "(x - v) * (x - v) + (y - w) * (y - w) >= 9 AND (x - v) * (x - v) <= 25"),
    (both(col("y", 0) < col("y", 1) - 10, col("id", 0) < col("id", 1)), "y < w - 10 AND id < r"),
]


@pytest.mark.parametrize("odd", [True, False])
def test_leaves_meet_in_tasks(spark, odd):
    """Rows of paired leaves are no rows of a join; pairs leave a task in arrays."""
    df = spark.createDataFrame([r for r in odd_rows(400) if odd or r[1] is not None and r[1] - r[1] == 0], "id long, x double, y int")
    t = build(df, TreeSpec.boxes(("x", "y"), Agg("count"), leaf_rows=8, fanout=3))
    for p, sql in CLOSE_PAIRS:
        want = sorted(map(tuple, df.join(df.toDF("r", "v", "w"), F.expr(sql)).select("id", "r").collect()))
        made = joins.Pairs(t, t, p)
        got = made.rows((["id"], ["id"]))
        assert got.columns == ["_l_id", "_r_id"] and sorted(map(tuple, got.collect())) == want
        assert sorted((r["id"], r["r_id"]) for r in joins.dual_index_join(t, t, p).collect()) == want
        assert made.count().first()[0] == len(want)
        for plan in (got, made.count()):
            assert "MapInArrow" in plan._jdf.queryExecution().toString()
    assert joins.dual_index_join(t, t, CLOSE_PAIRS[0][0]).schema.simpleString() == "struct<id:bigint,x:double,y:int,r_id:bigint,r_x:double,r_y:int>"

@pytest.mark.parametrize("odd", [True, False])
def test_all_pairs_are_tested_in_tasks(spark, monkeypatch, odd):
    monkeypatch.setattr(pairs, "WIDTH", 24)
    monkeypatch.setattr(pairs, "WORK", 1 << 10)
    df = spark.createDataFrame([r for r in odd_rows(400) if odd or r[1] is not None and r[1] - r[1] == 0], "id long, x double, y int")
    other = df.where("id % 3 <> 1")
    for p, sql in CLOSE_PAIRS:
        want = sorted(map(tuple, df.join(other.toDF("r", "v", "w"), F.expr(sql)).select("id", "r").collect()))
        got = joins.nested_join(df, other, p, out=(["id"], ["id"]))
        assert got.columns == ["id", "r_id"] and sorted(map(tuple, got.collect())) == want
        whole = joins.nested_join(df, other, p)
        assert whole.columns == ["id", "x", "y", "r_id", "r_x", "r_y"] and sorted((r["id"], r["r_id"]) for r in whole.collect()) == want
        assert "MapInArrow" in got._jdf.queryExecution().toString() and "NestedLoop" not in got._jdf.queryExecution().toString()


def test_least_of_all_pairs_is_found_in_tasks(spark):
    """No pair is a row: nulls, NaN, infinity, ties and rows with one id are as in all pairs."""
    nan = float("nan")
    inner = spark.createDataFrame([(900 - i, x) for i, x, _ in odd_rows(300)], "id long, x double")
    probes = [(i % 35, None if i == 5 else nan if i == 6 else i * 3.5) for i in range(40)]
    got = baselines.brute_nearest(spark.createDataFrame(probes, "id long, v double"), inner, abs_(col("v", 0) - col("x", 1)))
    order = lambda x: (x != x, 0 if x != x else x)
    want = {}
    for i, v in probes:
        near = [(order(abs(v - r["x"])), r["id"]) for r in inner.collect() if v is not None and r["x"] is not None] if i not in want else want[i]
        want[i] = near if i not in want else near + [(order(abs(v - r["x"])), r["id"]) for r in inner.collect() if v is not None and r["x"] is not None]
    assert sorted((r["id"], r["r_id"], order(r["m"])) for r in got.collect()) == sorted((i, min(n)[1], min(n)[0]) for i, n in want.items() if n)
    plan = got._jdf.queryExecution().toString()
    assert "MapInArrow" in plan and "Cartesian" not in plan and "NestedLoop" not in plan
