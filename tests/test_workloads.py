"""Workloads on the given tables: known values, SQL on a small scale, planner, reports, streams, sources and sinks."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from linform import experiments
from linform import workloads as W
from linform.functions import semirings as S
from linform.operators import evaluate as E
from linform.operators import relational
from linform.operators.relation import AnnotatedRelation as Rel
from linform.operators.relation import Database
from linform.plans import covers, planner, sqlapi, trees
from linform.plans.query import parse_query
from linform.sources import fixtures, shared, tables
from linform.streaming import delta

SMALL, MIDDLE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in fixtures.TABLES:
        con.sql(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    return con


@pytest.mark.parametrize(
    ("name", "rows", "total"),
    [
        ("threesum_count", 1, 52), ("minconv_days", 4807, 10672427349), ("conv1d_hours", 743, 14889197100), ("autocorr_hours", 169, 510381893761507),
        ("skew_triangle", 351196, 75392043), ("matmul", 149707, 1858320), ("linear_guard", 1, 9933), ("quad_tree", 19, 7114058132445138),
        ("ksum_docs", 1, 1195), ("five_atoms", 101, 544164223364), ("sum_equality5", 1, 835011550465496), ("gf7_conv", 7, 514262064),
        ("exact_path4_count", 1, 10680), ("degenerate_sum", 1, 15000), ("ksum4", 1, 386505688602320722181), ("bag_example", 13, 11875217490),
    ],
)
def test_known_values(spark, name, rows, total):
    got = W.WORKLOADS[name].run(spark, MIDDLE).agg(F.count("*"), F.sum("ann")).first()
    assert tuple(got) == (rows, total)


@pytest.mark.parametrize("name", ["triangle__plain_levelwise", "conv2d_counts__joined", "quad_tree__domain", "gf7_conv__grid", "as_of_lag", "sessions", "conv1d_hours__window", "relation_union", "rational_scaling__where", "dictionary_ids", "constraints_atoms__linear_guard"])
def test_against_sql(spark, duck, name):
    got, want = W.queries()[name](spark, SMALL), duck.sql(W.oracles()[name])
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    key = lambda rows: sorted(map(str, rows))
    assert key([tuple(r[c] for c in cols) for r in got.collect()]) == key(want.select(*[f'"{c}"' for c in cols]).fetchall())


def test_adversarial_messages(spark):
    rows = {(r.n, r.method, r.node): r.message_rows for r in W.adversarial_messages(spark, SMALL).collect()}
    for n in W.WIDE:
        assert [rows[n, "unguarded", v] for v in (3, 2, 1)] == [n**2, n**3, n**4]
        assert all(rows[n, "domain", v] <= n**3 for v in (3, 2, 1)) and rows[n, "domain", 1] <= n**2


def test_rows_grow_as_the_exponents_say(spark):
    found = experiments.exponents(experiments.growth(spark))
    assert abs(found["skew_triangle", "square", "sparse"] - 1.5) < 0.08
    assert found["skew_triangle", "hub", "sparse"] < 1.05
    assert all(found["skew_triangle", "hub", m] > 1.9 for m in ("integral", "inequality_bags", "joined"))
    assert found["linear_guard", "hub", "sparse"] < 1.05 and found["linear_guard", "hub", "inequality_bags"] > 1.9
    assert abs(found["ksum5", "spread", "unguarded"] - 4) < 0.01 and found["ksum5", "spread", "domain"] < 3.01


def test_growth_equals_its_closed_forms(spark):
    for workload, shape, method, n, _, rows in experiments.growth(spark, hubs=(7,), squares=(3,), sums=(2,)):
        assert rows == eval(experiments.ROWS[workload, shape, method], {"n": n}), (workload, shape, method)


def test_sql_by_hand_equals_sql_from_equations(duck):
    def rows(sql):
        run = duck.execute(sql)
        names = [x[0] for x in run.description]
        return sorted(str(sorted(zip(names, r, strict=True))) for r in run.fetchall())

    for name, text in W.BY_HAND.items():
        if name not in ("ksum5", "sum_equality5", "hub_triangle", "hub_skew"):  # where the equations leave large cross products
            assert rows(W.WORKLOADS[name].sql(text)) == rows(W.WORKLOADS[name].sql()), name


def hubs(spark, n):
    return Database({a: Rel(fixtures.frame(spark, SMALL, "hub").where(f"c0 < {n} and c1 < {n}"), 2) for a in "RST"})


def test_planner_does_not_take_joins_without_a_bound(spark):
    q = parse_query("Q(X,Y,Z) <- R(X,Y)*S(Y,Z)*T(X,Z)")
    db = hubs(spark, fixtures.HUB)
    assert planner.joined_estimate(q, db) < 20_000 and E.join_bound(q, db) >= 9_002_999
    s = planner.plan(q, db)
    assert s.name == "sparse" and s.bound < 500_000
    q2 = parse_query("Q(X,Y,Z) <- R(X,Y)*S(Y,Z)")  # the answer itself is that large
    with pytest.raises(ValueError, match="least bound"):
        planner.plan(q2, db, budget=1e6)


@pytest.mark.parametrize("name", ["skew_triangle", "triangle", "matmul", "quad_tree", "five_atoms", "linear_guard", "conv2d_blur", "exact_path4_count"])
def test_intermediate_results_stay_within_the_stated_bounds(spark, name):
    w = W.WORKLOADS[name]
    q, db = w.query(), w.database(spark, SMALL)
    s, bound = planner.plan(q, db), E.join_bound(q, db)
    assert experiments.joined(q, db) <= bound
    assert E.sparse_guard(q, db, covers.cover_number(q, costs=E.size_costs(q, db))).df.count() <= s.bounds["sparse"] * (1 + 1e-9)
    for kind in ("domain", "size"):
        most = []
        E.EVALUATORS[kind](q, db, trees.find_tree(q, {"domain": "vec", "size": "frac"}[kind]), watch=lambda v, g, out: most.append(g.df.count()))
        assert max(most) <= s.bounds[kind] * (1 + 1e-9)


def test_sums_beyond_64_bits(spark):
    w = W.WORKLOADS["quad_tree_min"]
    q = w.query()
    plain = Database({a: fixtures.relation(spark, MIDDLE, f) for a, f in w.atoms.items()})
    s = planner.plan(q, plain)
    small = Database({a: fixtures.relation(spark, SMALL, f) for a, f in w.atoms.items()})
    assert planner.widened(q, small, planner.plan(q, small)).semiring is S.COUNT or planner.annotation_bound(q, small, planner.plan(q, small).bound) >= 2**63
    assert planner.annotation_bound(q, plain, s.bound) >= planner.evaluate(q, plain).agg(F.sum("ann")).first()[0]
    wide = W.quad_tree_wide(spark, MIDDLE)
    assert dict(wide.dtypes)["ann"] == "decimal(38,0)"
    assert sorted((r.h0, int(r.ann)) for r in wide.collect()) == sorted((r.h0, int(r.ann) * 10**8) for r in W.WORKLOADS["quad_tree"].run(spark, MIDDLE).collect())
    far = Database({a: fixtures.relation(spark, SMALL, f).shift([2**62]) for a, f in w.atoms.items()})
    with pytest.raises(OverflowError, match="keys"):
        planner.widened(q, far, planner.plan(q, small))
    vast = Database({a: fixtures.relation(spark, SMALL, f).scale(10**12) for a, f in w.atoms.items()})
    with pytest.raises(OverflowError, match="38 digits"):
        planner.evaluate(q, vast, widen=True)


def test_products_beyond_64_bits(spark):
    w = W.WORKLOADS["quad_tree_product"]
    q, db = w.query(), w.database(spark, SMALL)
    assert planner.widened_sums(q, db).semiring is S.MAX_TIMES  # small products stay in 64 bits
    large = planner.widened_sums(q, Database({n: r.scale(10**4) for n, r in db.relations.items()}, S.MAX_TIMES))
    want = {r.h0: int(r.ann) * 10**16 for r in E.eval_by_size(q, db).collect()}
    assert {r.h0: int(r.ann) for r in E.eval_by_size(q, large).collect()} == want and max(want.values()) > 2**63


@pytest.mark.parametrize("name", ["bag_example", "adversarial_messages"])
def test_examples_read_a_given_table(spark, name):
    got = W.queries()[name](spark, SMALL)
    if name == "bag_example":
        assert any("lineitem" in f for f in got.inputFiles())
    assert "lineitem" in W.oracles()[name]


def test_written_tables_go(spark, tmp_path):
    with shared.scope(spark):
        kept = shared.written(spark.range(5), "some")
        place = kept.inputFiles()[0].removeprefix("file://").rpartition("/")[0]
        assert kept.count() == 5 and os.path.isdir(place)
    assert not os.path.isdir(place)


def test_planner(spark):
    w = W.WORKLOADS["quad_tree"]
    q, db = w.query(), w.database(spark, SMALL)
    s = planner.plan(q, db)
    assert s.bound == min(s.bounds.values()) and s.name != "dense"
    assert [r["seconds"] > 0 and r["shuffle_bytes"] >= 0 for r in planner.report(q, db, "size")] == [True, True]
    text = planner.explain(q, db)
    assert "chosen" in text and "node 0" in text
    with pytest.raises(ValueError, match="least bound"):
        planner.plan(q, db, budget=1)
    assert planner.exists(q, db)
    assert sorted(map(tuple, planner.evaluate(q, db, settle=True).collect())) == sorted(map(tuple, planner.evaluate(q, db).collect()))
    for name in ("domain", "size", "value", "unguarded"):
        for r in planner.report(q, db, name):
            if name != "unguarded":
                assert r["guard_rows"] <= r["bound"] + 1e-6
            assert r["message_rows"] >= 0
    skew = W.WORKLOADS["skew_triangle"]
    s = planner.plan(skew.query(), skew.database(spark, SMALL))
    assert set(s.bounds) == set(planner.ORDER) and s.bound == min(s.bounds.values())


def test_sql_surface(spark):
    Rel.of_rows(spark, [(1, 2), (2, 3)], 1).df.createOrReplaceTempView("first_view")
    Rel.of_rows(spark, [(3, 5)], 1).df.createOrReplaceTempView("second_view")
    out = sqlapi.linear_sql(spark, "Q(X) <- first_view(X)*first_view(Y)*second_view(X+Y)", view="answer")
    assert sorted(map(tuple, out.collect())) == [(1, 30), (2, 30)] and spark.table("answer").count() == 2


def test_stream_of_deltas(spark, tmp_path):
    schema = "c0 long, c1 long, ann long"
    q = parse_query("Q(X) <- R(X,Y)*S(Y,X+Y)")
    static = Rel.of_rows(spark, [(2, 3, 1), (2, 5, 4), (4, 6, 2)], 2)
    parts = [[(1, 2, 1), (3, 2, 2)], [(2, 4, 5), (1, 2, 1)]]
    for i, p in enumerate(parts):
        spark.createDataFrame(p, schema).coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    stream = spark.readStream.schema(schema).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    db = Database({"S": static})
    run = delta.stream_delta(q, 0, stream, db).writeStream.outputMode("complete").format("memory").queryName("deltas").option("checkpointLocation", str(tmp_path / "check")).start()
    try:
        run.processAllAvailable()
    finally:
        run.stop()
    whole = Database({"R": Rel.of_rows(spark, [r for p in parts for r in p], 2), "S": static})
    assert sorted(map(tuple, spark.table("deltas").collect())) == sorted(map(tuple, E.eval_sparse(q, whole).collect()))


def test_stream_windows_and_lags(spark, tmp_path):
    events = tables.table(spark, SMALL, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = lambda: spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))

    def out(df, name):
        run = df.writeStream.outputMode("append").format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).start()
        try:
            run.processAllAvailable()
        finally:
            run.stop()
        return spark.table(name)

    days = out(delta.ticks(stream(), "ts", "1 day", keys=["event_type"]), "days")
    want = events.groupBy(F.window("ts", "1 day"), "event_type").count()
    assert 0 < days.count() <= want.count() and days.agg(F.sum("ann")).first()[0] <= events.count()
    assert out(delta.session_ticks(stream(), "ts", "6 hours", "user_id"), "sess").count() > 0
    pairs = out(delta.lag_pairs(stream(), stream(), "user_id", "ts", "1 hour"), "pairs")
    exact = events.alias("a").join(events.alias("b"), F.expr("a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")).count()
    assert pairs.count() == exact


def test_sources_and_sinks(spark, tmp_path):
    rel = fixtures.relation(spark, SMALL, "skew_a")
    tables.write_parquet(rel.df, str(tmp_path / "p"), by="c0", buckets=4)
    assert spark.read.parquet(str(tmp_path / "p")).count() == rel.df.count()
    tables.write_parquet(rel.df, str(tmp_path / "q"))
    df = spark.createDataFrame([(1, (2, (3, 4))), (None, (5, (6, 7)))], "a long, s struct<x: long, t: struct<y: long, z: long>>")
    assert tables.flatten(df).columns == ["a", "s_x", "s_t_y", "s_t_z"] and tables.dropped_rows(df, ["a"]).first()[0] == 1
    assert tables.entries(spark.createDataFrame([(1, {"k": 2})], "i long, m map<string, long>"), "m", ["i"]).first() == (1, "k", 2)
    assert tables.common_scale(["1/2", "1/3"]) == 6
    (tmp_path / "t.csv").write_text("a,b\n1,2\n")
    (tmp_path / "t.json").write_text('{"a": 1, "b": 2}\n')
    for kind in ("csv", "json"):
        assert tables.read_text(spark, str(tmp_path / f"t.{kind}"), kind, "a long, b long").first() == (1, 2)
    a = spark.createDataFrame([(1, 5, 3)], "c0 long, c1 long, ann long")
    assert relational.difference(a, a).isEmpty() and relational.difference(a, a.limit(0)).count() == 1


def test_boolean_and_witness_threesum(spark):
    w = W.WORKLOADS["threesum_count"]
    s = S.witness("bigint")
    db = Database({a: Rel(fixtures.frame(spark, MIDDLE, f).select("c0", F.struct(F.col("c0").alias("cost"), F.array("c0").alias("wit")).alias("ann")), 1, s) for a, f in w.atoms.items()}, s)
    got = E.eval_sparse(w.query(), db).first().ann
    assert got.wit[0] + got.wit[1] == got.wit[2] and got.cost == sum(got.wit)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    names = set(e.queries())
    assert set(e.oracle_sql()) <= names and len(names) > 100
