"""The cube engine: worked example, equality of methods, invariants, ledger and plans."""

import itertools
import re

import pytest
from pyspark.sql import functions as F

from segcube import workloads as W
from segcube.functions import measures as M
from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema, Dimension, Grouping
from segcube.operators import batch_area, broadcast, layered_chain, query, value_shards
from segcube.operators.grouped_phases import _first_phase_slice, grouped_cube, grouped_states, phase_deltas, phase_outputs, run_phase, sliced_cube
from segcube.plans import advisor, balance, ledger
from segcube.sources import scratch, tables
from segcube.streaming import cubes

SF = "/root/testdata/sf0.001"
SHAPE = "land>town | kind, shop"


def cube_rows(df, schema):
    return sorted(repr((*[r[c] for c in schema.columns], r[MASK], *[r[m.name] for m in schema.measures])) for r in df.collect())


def plain_cube(rows, schema):
    """Every segment of (values, number) rows by brute force."""
    out = {}
    for values, n in rows:
        for mask in S.legal_masks(schema):
            key = tuple(None if mask & schema.bit(c) else v for c, v in zip(schema.columns, values, strict=True)), mask
            a, b = out.get(key, (0, 0))
            out[key] = a + 1, b + n
    return sorted(repr((*k, m, *v)) for (k, m), v in out.items())


ROWS = [(("US", "A", "x", "s*1"), 4), (("US", "A", "x", "s*1"), 3), (("US", "B", "y", "a,b"), -2), (("CN", "A", "x", None), 0), ((None, None, "y", "a,b"), 7), (("CN", "Z", None, "s*1"), 5)]


def example(spark, rows=ROWS):
    df = spark.createDataFrame([(*v, n) for v, n in rows], "land string, town string, kind string, shop string, v bigint")
    return (df, *CubeSchema.parse(SHAPE, (M.count("n"), M.total("v"))))


def test_worked_example_by_hand(spark):
    df = spark.createDataFrame([("US", "A", "x", 4), ("US", "A", "x", 3), ("US", "B", "x", 2)], "land string, town string, kind string, v bigint")
    schema, grouping = CubeSchema.parse("land>town | kind", (M.total("v"),))
    want = [
        ("US", "A", "x", 0, 7), ("US", "B", "x", 0, 2), ("US", "A", None, 1, 7), ("US", "B", None, 1, 2), ("US", None, "x", 2, 9), ("US", None, None, 3, 9), (None, None, "x", 6, 9), (None, None, None, 7, 9),
    ]
    assert cube_rows(grouped_cube(df, grouping), schema) == sorted(map(repr, want))


def methods():
    yield "grouped", lambda df, s, g: grouped_states(df, g)
    for kernel in ("layers", "sweep", "direct", "union", "arrow"):
        yield kernel, lambda df, s, g, k=kernel: grouped_states(df, g, kernel=k)
    for heavy in ("last_parent", "all_parents"):
        yield heavy, lambda df, s, g, h=heavy: grouped_states(df, g, heavy=h)
    yield "premerge", lambda df, s, g: grouped_states(df, g, premerge=True)
    yield "broadcast", lambda df, s, g: broadcast.broadcast_states(df, s)
    yield "uncombined", lambda df, s, g: broadcast.broadcast_states(df, s, combine=False)
    yield "grouping sets", lambda df, s, g: broadcast.grouping_sets_states(df, s)
    yield "layered", lambda df, s, g: layered_chain.layered_states(df, s)
    yield "layered rounds", lambda df, s, g: layered_chain.layered_states(df, s, carry=False, checkpoint="each")
    for sizes in ((4,), (1, 1, 1, 1), (1, 3), (2, 1, 1), (3, 1)):
        yield f"groups {sizes}", lambda df, s, g, z=sizes: grouped_states(df, Grouping.by_sizes(s, z, "guard"))
        yield f"groups {sizes} heavy", lambda df, s, g, z=sizes: grouped_states(df, Grouping.by_sizes(s, z, "guard"), heavy="all_parents")
    for load in (1000, 3, 1):
        yield f"areas {load}", lambda df, s, g, m=load: batch_area.batch_area_states(df, s, batch_area.plan_batch_areas(s, batch_area.estimate_load(df, s, 1.0), m))


@pytest.mark.parametrize(("name", "method"), list(methods()), ids=[n for n, _ in methods()])
def test_every_method_gives_the_cube(spark, name, method):
    df, schema, grouping = example(spark)
    assert cube_rows(S.finalise(method(df, schema, grouping), schema), schema) == plain_cube(ROWS, schema)
    if name in ("grouped", "broadcast", "layered", "grouping sets", "areas 1000"):
        assert method(df.limit(0), schema, grouping).count() == 0


def test_masks_children_and_parents():
    schema, _ = CubeSchema.parse("country>state>city, category, advertiser", (M.count(),))
    masks = S.legal_masks(schema)
    assert len(masks) == 4 * 2 * 2 and all(S.legal(m, schema) for m in masks) and not S.legal(schema.bit("state"), schema)
    bits = lambda *c: schema.bits(c)
    assert S.child_slot(bits("city", "category"), schema) == "category"
    assert S.child_slot(bits("state", "city"), schema) == "state" and S.child_slot(0, schema) is None
    assert S.primary_parents(0, schema) == [bits("advertiser"), bits("category"), bits("city")]
    for m in masks:
        parents = S.primary_parents(m, schema)
        assert len(parents) <= len(schema.dims)
        for p in parents:
            assert S.legal(p, schema) and S.stars(p) == S.stars(m) + 1 and p == m | schema.bit(S.child_slot(p, schema))
        if m:
            assert any(m in S.primary_parents(k, schema) for k in masks)


def test_mask_columns_agree_with_plain_masks(spark):
    schema, grouping = CubeSchema.parse("a>b>c | d, e>f | g", (M.count(),))
    df = spark.range(1 << 7).select(F.col("id").alias(MASK))
    rows = df.select(MASK, S.is_legal(schema).alias("ok"), S.number_of_parents(schema).alias("parents"), S.phase_of(grouping).alias("phase"), S.layer().alias("layer")).collect()
    for r in rows:
        m = r[MASK]
        assert r.ok == S.legal(m, schema) and r.layer == S.stars(m)
        if r.ok:
            assert r.parents == len(S.primary_parents(m, schema)) and r.phase == S.phase_of_mask(m, grouping)


def test_schema_refuses_what_cannot_be(spark):
    one = (M.count(),)
    with pytest.raises(ValueError):
        CubeSchema((), one)
    with pytest.raises(ValueError):
        CubeSchema((Dimension("a", ("x",)), Dimension("b", ("x",))), one)
    with pytest.raises(ValueError):
        CubeSchema(tuple(Dimension(str(i), (f"c{i}",)) for i in range(64)), one)
    wide = CubeSchema(tuple(Dimension(str(i), (f"c{i}",)) for i in range(63)), one)
    assert wide.bit("c0") == 1 << 62 and wide.bit("c62") == 1
    schema, _ = CubeSchema.parse("a>b | c", one)
    for groups in ([["a", "b"]], [["a", "b", "c"], []], [["a"], ["c", "b"]], [["a"], ["b", "c"]]):
        with pytest.raises(ValueError):
            Grouping.of(schema, groups)
    with pytest.raises(ValueError):
        schema.validate(spark.createDataFrame([(1.0, 1, 1)], "a double, b int, c int"))


def test_keys_are_written_and_read(spark):
    df, schema, grouping = example(spark)
    for r in grouped_cube(df, grouping).withColumn("key", S.render_key(schema)).collect():
        assert S.parse_key(r.key) == [... if r[MASK] & schema.bit(c) else r[c] for c in schema.columns]


def test_algebraic_measures_sketches_and_sets(spark):
    rows = [("a", "x", 1, 10), ("a", "x", 5, 20), ("a", "y", 3, None), ("b", "y", -2, 40)]
    df = spark.createDataFrame(rows, "k string, l string, v bigint, w bigint")
    measures = (M.mean("v"), M.variance("v"), M.variance("v", "svar", sample=True), M.deviation("v"), M.least("v"), M.greatest("v"), M.distinct_exact("v"), M.distinct_estimate("v", "about"), M.quantile_estimate("v", 0.5, "median"), M.mean("w"), M.top_member("l", "v", "top"), M.correlation("v", "v", "corr"))
    schema, grouping = CubeSchema.parse("k | l", measures)
    got = {(r.k, r.l, r[MASK]): r for r in grouped_cube(df, grouping).collect()}
    total, a = got[None, None, 3], got["a", None, 1]
    assert total.avg_v == 1.75 and total.var_v == 6.6875 and abs(total.svar - 26.75 / 3) < 1e-12 and total.std_v == 6.6875**0.5
    assert (a.min_v, a.max_v, a.distinct_v, a.about, a.top) == (1, 5, 3, 3, "x") and a.avg_w == 15.0 and abs(total["corr"] - 1) < 1e-12
    assert got["b", "y", 0].svar is None and got["a", "y", 0].avg_w is None


def test_invariants_of_a_real_cube(spark):
    rows = tables.wide(spark, SF)
    schema, grouping = W.shaped(W.S5)
    cube = scratch.materialised(grouped_states(rows, grouping), "cube")
    assert query.check_children_sum(cube, schema).count() == 0
    assert cube.filter(~S.is_legal(schema)).count() == 0
    assert cube.filter(F.col(MASK) == 31).first()["n"] == 6000
    one, two = phase_outputs(rows, grouping, store=True)
    assert one.exceptAll(two).count() == 0
    deltas = [d for _, d in phase_deltas(rows, grouping)]
    both = deltas[0].unionByName(deltas[1]).unionByName(deltas[2])
    assert both.exceptAll(cube).count() == 0 and cube.exceptAll(both).count() == 0
    broken = cube.withColumn("n", F.when((F.col(MASK) == 31), F.col("n") + 1).otherwise(F.col("n")))
    assert query.check_children_sum(broken, schema).count() > 0


def test_ledger_gives_the_known_numbers(spark):
    schema, grouping = W.shaped(W.S5)
    rows = ledger.phase_stats(tables.wide(spark, SF), grouping)
    assert [(r[1], r[4], r[5]) for r in rows] == [(6000, 6754, 9976), (6754, 9069, 8992)]
    t = ledger.totals(rows)
    assert (t["remote_msgs"], t["remote_msgs_after_first"], t["local_msgs"]) == (12_754, 6_754, 18_968) and round(t["locality"], 3) == 0.737
    assert ledger.broadcast_messages(6000, schema) == 90_000 and ledger.broadcast_messages(6000, schema, own=True) == 96_000


def test_arithmetic_of_the_published_run():
    phases = [(1, 24.9, 24.9, 24.9, 1.8, 4.5), (2, 1.8, 1.8, 1.8, 5.3, 8.0), (3, 5.3, 5.3, 5.3, 35.0, 45.6)]
    rows = [(*p, p[4] / p[1], p[5] / p[2], 0, 0, 0, 0, 0, 0) for p in phases]
    t = ledger.totals(rows)
    assert round(t["remote_msgs_after_first"], 1) == 7.1 and round(t["locality"], 2) == 0.89 and t["messages_per_segment"] < 3
    assert [round(r[6], 1) for r in rows[1:]] == [2.9, 6.6] and [round(r[7], 1) for r in rows[1:]] == [4.4, 8.6]


def test_two_groups_balance_hot_ids(spark):
    rows = tables.skewed(tables.wide(spark, SF))
    one = balance.shard_share(rows, ["hot_supp"]).first().share
    two = balance.shard_share(rows, ["hot_supp", "l_returnflag", "hot_part", "p_type"]).first().share
    assert one > 0.25 and two < one / 10


def test_a_phase_is_one_exchange(spark):
    rows = scratch.materialised(tables.wide(spark, SF), "wide")
    for shape, phases in ((W.S5, 2), ("c_region>c_nation, c_mktsegment | p_brand, p_type | l_returnflag, l_linestatus", 3)):
        schema, grouping = W.shaped(shape)
        layers = grouped_cube(rows, grouping, kernel="layers")._jdf.queryExecution().executedPlan().toString()
        assert len(re.findall(r"\bExchange\b", layers)) == phases
        plan = grouped_cube(rows, grouping)._jdf.queryExecution().executedPlan().toString()
        assert len(re.findall(r"\bExchange\b", plan)) == phases and "Expand" not in plan and "Python" not in plan
        read = re.search(r"ReadSchema: struct<([^>]*)", plan)[1]
        assert "l_orderkey" not in read and "ship_year" not in read
    pushed = tables.read_table(spark, SF, "lineitem").filter("l_orderkey < 10").select("l_partkey")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_orderkey), LessThan(l_orderkey,10)]" in pushed


def test_a_filter_prunes_nothing_inside(spark):
    df, schema, grouping = example(spark)
    kept = grouped_cube(df, grouping, F.col("sum_v") >= 7)
    assert cube_rows(kept, schema) == [r for r in plain_cube(ROWS, schema) if int(r.rsplit(", ", 1)[1][:-1]) >= 7]


def test_heavy_phases_are_one_exchange_and_one_group_is_no_single_task(spark):
    rows = scratch.materialised(tables.wide(spark, SF), "wide")
    schema, grouping = W.shaped(W.S5)
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    for heavy in ("last_parent", "all_parents"):
        assert len(re.findall(r"\bExchange\b", plan(grouped_cube(rows, grouping, heavy=heavy)))) == 2
    for heavy in (None, "all_parents"):
        assert "SinglePartition" not in plan(grouped_cube(rows, Grouping.by_sizes(schema, (5,)), heavy=heavy))


def test_combiners_add_up_in_tasks(spark, monkeypatch):
    from segcube.operators import grouped_phases

    schema, grouping = CubeSchema.parse("a | b>c", (M.count("n"), M.least("v"), M.mean("v")))
    df = spark.range(1000, numPartitions=2).select((F.col("id") % 3).alias("a"), F.lit(None).cast("string").alias("b"), (F.col("id") % 5).cast("string").alias("c"), F.col("id").alias("v"))
    for limit in (500_000, 7):
        monkeypatch.setattr(grouped_phases, "COMBINE_ROWS", limit)
        combined = grouped_phases.combined_in_tasks(S.lift(df, schema), schema)
        assert combined.count() == (30 if limit > 7 else combined.count()) and combined.agg(F.sum("n")).first()[0] == 1000
        assert cube_rows(grouped_cube(df, grouping, heavy="last_parent"), schema) == cube_rows(grouped_cube(df, grouping), schema)


def test_batch_areas_are_valid_and_split_what_does_not_fit():
    schema, _ = CubeSchema.parse("a>b, c, d", (M.count(),))
    load = {m: 10 ** S.stars(m) for m in S.legal_masks(schema)}
    areas = batch_area.plan_batch_areas(schema, load, 100)
    assert sorted(m for a in areas for m in (*a.masks, *a.partitioned)) == S.legal_masks(schema)
    concrete = lambda m: {c for c in schema.columns if not m & schema.bit(c)}
    for a in areas:
        assert all(set(a.shard) <= concrete(m) and load[m] <= 100 for m in a.masks)
        # the parts of a split cuboid are keys of a finer cuboid of its area, which fits
        assert all(load[m] > 100 and any(concrete(m) < concrete(n) for n in a.masks) for m in a.partitioned)
    assert any(a.partitioned for a in areas) and not any(a.partitioned for a in batch_area.plan_batch_areas(schema, load, 10**6))
    big = {m: 1 if not m & schema.bits(("a", "b")) else 1000 for m in S.legal_masks(schema)}  # only a>b splits anything
    assert {a.shard for a in batch_area.plan_batch_areas(schema, big, 10)} == {("a", "b")}


def test_merge_subtract_and_compare(spark):
    df, schema, grouping = example(spark)
    first, second = df.filter("v > 3"), df.filter("v <= 3")
    a, b, whole = (grouped_states(x, grouping) for x in (first, second, df))
    assert cube_rows(query.merge_cubes(a, b, schema), schema) == cube_rows(whole, schema)
    assert cube_rows(query.subtract_cubes(whole, b, schema, "n"), schema) == cube_rows(a, schema)
    diff = query.compare(a, whole, schema, "sum_v")
    assert diff.filter(F.col(MASK) == 15).first().after == 17 and diff.count() == whole.count()


def test_advisor_puts_small_columns_right(spark):
    schema, _ = CubeSchema.parse("l_returnflag, c_region>c_nation, p_brand", (M.count("n"),))
    found = advisor.advise_grouping(tables.wide(spark, SF), schema, g=2, sample=0.3, max_share=1.0)
    assert found.schema.columns[-1] == "l_returnflag" and len(found.grouping.groups) == 2 and found.expected["cube_rows"] > 0
    assert advisor.choose_method(10**9, 10**6, W.shaped(W.S8)[0]) == "grouped" and advisor.choose_method(100, 100, W.shaped(W.S5)[0]) == "grouping_sets"


def test_sinks_and_other_formats(spark, tmp_path):
    df, schema, grouping = example(spark)
    cube = grouped_cube(df, grouping)
    tables.write_cube(cube, str(tmp_path / "cube"))
    again = cube.filter(F.col(MASK) == 15).withColumn("n", F.lit(99).cast("bigint"))
    tables.write_cube(again, str(tmp_path / "cube"))
    back = spark.read.parquet(str(tmp_path / "cube"))
    assert back.count() == cube.count() and back.filter(F.col(MASK) == 15).first().n == 99
    for kind in ("json", "csv", "orc"):
        df.write.format(kind).options(header=True).save(str(tmp_path / f"x.{kind}"))
        assert tables.read_table(spark, str(tmp_path), "x", kind, df.schema if kind != "orc" else None).count() == 6
    coded, words = tables.encode(df, "shop")
    assert words.count() == 2 and coded.schema["shop"].dataType.simpleString() == "int"
    tables.write_bucketed(cube.drop("town"), "bucketed_cube", ["land"], 4)
    plan = spark.table("bucketed_cube").groupBy("land").count()._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    spark.sql("DROP TABLE bucketed_cube")


def test_replayed_batches_change_nothing(spark, tmp_path):
    df, schema, grouping = example(spark)
    store = cubes.batch_sink(str(tmp_path / "s"), grouping)
    store(df.filter("v > 3"), 0)
    store(df.filter("v <= 3"), 1)
    store(df.filter("v <= 3"), 1)
    assert cube_rows(cubes.stored_states(spark, str(tmp_path / "s"), schema), schema) == cube_rows(grouped_states(df, grouping), schema)


def test_late_rows_are_dropped_only_behind_the_watermark(spark, tmp_path):
    schema, _ = CubeSchema.parse("k", (M.count("n"),))
    for i, rows in enumerate([[("2024-01-01 10:00:00", "a")], [("2024-01-03 10:00:00", "a")], [("2024-01-03 09:00:00", "b")], [("2024-01-01 11:00:00", "late")], [("2024-01-06 00:00:00", "z")], [("2024-01-06 00:00:01", "z")]]):
        spark.createDataFrame(rows, "t string, k string").select(F.to_timestamp("t").alias("ts"), "k").coalesce(1).write.parquet(str(tmp_path / f"in/b{i}"))
    stream = tables.read_stream(spark, str(tmp_path / "in/*"), "ts timestamp, k string", 1)
    got = cubes.drain(cubes.continuous_states(stream, schema, time="ts", window="1 day")).collect()
    keys = {r.k for r in got}
    assert "late" not in keys and {"a", "b"} <= keys


def test_the_full_shape_by_brute_force(spark, monkeypatch):
    whole = tables.wide(spark, SF).filter("l_orderkey % 50 = 0 and ship_year in (1996, 1997)").cache()
    monkeypatch.setattr(tables, "wide", lambda *_: whole)
    dims = [part.strip().split(">") for part in W.S14.replace("|", ",").split(",")]
    columns = [c for d in dims for c in d]
    cuboids = [[c for kept in choice for c in kept] for choice in itertools.product(*([d[:k] for k in range(len(d) + 1)] for d in dims))]
    assert (len(dims), len(columns), len(cuboids)) == (11, 14, 6912)
    want = {}
    for r in whole.collect():
        for kept in cuboids:
            key = tuple(r[c] if c in kept else None for c in columns)
            want[key] = want.get(key, 0) + (r.cents if r.ship_year == 1997 else -r.cents)
    want = {k: v for k, v in want.items() if abs(v) >= W.SIGNIFICANT // 20}
    monkeypatch.setattr(W, "SIGNIFICANT", W.SIGNIFICANT // 20)
    got = [(tuple(r[c] for c in columns), r.change) for r in W.QUERIES["s14_change_significant"](spark, SF).collect()]
    assert len(want) > 100 and len(got) == len(want) and dict(got) == want


def test_the_skewed_cube_is_given_whole(spark):
    whole = W.QUERIES["skewed_cube_whole"](spark, SF).cache()
    rows = tables.skewed(tables.wide(spark, SF)).cache()
    assert whole.filter(F.col(MASK) == 0).count() == rows.select("hot_cust", "c_mktsegment", "hot_part", "p_type", "hot_supp", "l_returnflag").distinct().count()
    assert whole.filter("n < 20").count() > 0 and whole.agg(F.sum("n")).first()[0] == 64 * rows.count()
    assert sorted(map(repr, whole.filter("n >= 20").collect())) == sorted(map(repr, W.QUERIES["skewed_cube"](spark, SF).collect()))


def test_segments_of_a_row_in_sql(spark):
    from segcube.functions import sql

    df, schema, _ = example(spark, ROWS[:1])
    sql.register_segments_of(spark, df, schema, "segments_of_row")
    sql.register_star_layer(spark)
    df.createOrReplaceTempView("one_row")
    got = spark.sql("SELECT s.*, star_layer(s.star_mask) AS stars FROM one_row r, LATERAL segments_of_row(r.land, r.town, r.kind, r.shop) s").collect()
    assert sorted(r[MASK] for r in got) == S.legal_masks(schema) and all(r.stars == S.stars(r[MASK]) for r in got)
    assert all((r[c] is None) == bool(r[MASK] & schema.bit(c)) for r in got for c in schema.columns)


def test_entities_form_groups(spark):
    schema, _ = CubeSchema.parse("flag, region>nation, brand", (M.count(),))
    entity = {"flag": "line", "region": "user", "brand": "part"}
    grouping = Grouping.by_entity(schema, entity, ["user", "part", "line"])
    assert grouping.groups == (("region", "nation"), ("brand",), ("flag",))
    with pytest.raises(ValueError, match="brand"):
        Grouping.by_entity(schema, {"flag": "line", "region": "user"}, ["user", "line"])


def test_every_registered_query_has_a_name_and_a_plan(spark):
    import __spark_entry__ as entry

    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 80
    assert entry.entry(spark).limit(5).count() == 5


def test_equal_leaves_are_added_up_before_they_are_sent(spark):
    """Each method of broadcasting and the batch areas send a leaf segment once, however many rows it has."""
    schema, _ = CubeSchema.parse("a | b", [M.count("n")])
    rows = spark.range(1000).selectExpr("id % 2 as a", "id % 3 as b")
    areas = batch_area.plan_batch_areas(schema, batch_area.estimate_load(rows, schema, 1.0), 1000)
    assert batch_area.area_messages(rows, schema, areas).count() == 6 * len(areas)
    assert batch_area.estimate_load(rows, schema, 1.0) == {0: 167, 1: 500, 2: 334, 3: 1000}
    for style in ("explode", "grouping_sets", "cube"):
        plan = broadcast.broadcast_cube(rows, schema, style)._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("Aggregate") >= 2 and "transform(" not in plan
        assert {(r.a, r.b, r.star_mask): r.n for r in broadcast.broadcast_cube(rows, schema, style).collect()}[None, None, 3] == 1000


def test_messages_need_no_second_cube(spark):
    """Loads of the batch plan come from the cube that is counted, not from sending all rows once more."""
    schema, grouping = CubeSchema.parse("a | b", [M.count("n")])
    seen = []
    out = ledger.method_messages(spark, spark.range(60).selectExpr("id % 2 as a", "id % 3 as b"), grouping, lambda cube: seen.append(cube.count()) or 2)
    assert {r.method: r.remote_msgs for r in out.collect()}["batch_area"] == 120 and seen == [12]


def test_many_orders_are_not_broadcast(spark, monkeypatch):
    folder = "/root/testdata/sf0.001"
    hints = lambda join: tables.wide(spark, folder, join)._jdf.queryExecution().analyzed().toString().count("strategy=broadcast")
    want = tables.wide(spark, folder).count()
    assert hints("broadcast") == hints(None) + 1
    monkeypatch.setattr(tables, "BROADCAST_ROWS", 100)
    assert hints("broadcast") == hints(None) and tables.wide(spark, folder, "broadcast").count() == want


def test_slices_are_the_whole_cube_and_leave_no_shuffle(spark, monkeypatch):
    df, schema, grouping = example(spark)
    assert cube_rows(sliced_cube(df, grouping), schema) == plain_cube(ROWS, schema)
    guarded = Grouping.by_sizes(schema, (1, 3), "guard")
    assert cube_rows(sliced_cube(df, guarded), schema) == plain_cube(ROWS, schema)
    kept = sliced_cube(df, grouping, F.col("sum_v") >= 7)
    assert cube_rows(kept, schema) == [r for r in plain_cube(ROWS, schema) if int(r.rsplit(", ", 1)[1][:-1]) >= 7]
    assert sliced_cube(df.limit(0), grouping).count() == 0

    rows = scratch.materialised(tables.wide(spark, SF), "wide")
    schema, grouping = W.shaped(W.S8)
    leaves = scratch.materialised(S.lift(rows, schema), "leaves")
    now = _first_phase_slice(leaves, grouping, schema.bits(grouping.group(1)), 8)
    for phase in (2, 3):
        now = run_phase(now, grouping, phase, partitions=8)
    assert len(re.findall(r"\bExchange\b", now._jdf.queryExecution().executedPlan().toString())) == 3

    few = rows.filter("l_orderkey % 50 = 0 and ship_year in (1996, 1997)").cache()
    monkeypatch.setattr(tables, "wide", lambda *_: few)
    plan = W.QUERIES["s14_change_significant"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan  # the shuffles of its three phases have gone with their slices


@pytest.mark.parametrize(("above", "by"), [(0, ("town", "shop")), (1, ("town", "shop")), (2, ("shop", "land", "town", "kind")), (10_000, ("land", "town")), (1, ("kind",)), (1, ())])
def test_a_cube_by_value_is_whole_whatever_counts_as_heavy(spark, monkeypatch, above, by):
    monkeypatch.setattr(value_shards, "HEAVY_ROWS", above)
    more = [*ROWS, ((None, None, None, None), 1), ((None, None, None, None), 1), (("US", None, "x", "s*1"), 1), (("CN", "Z", "y", "a,b"), 9)]
    df, schema, _ = example(spark, more)
    assert cube_rows(value_shards.value_sharded_cube(df, schema, by), schema) == plain_cube(more, schema)
    assert value_shards.value_sharded_cube(df.limit(0), schema, by).count() == 0


def test_the_whole_skewed_cube_sends_a_row_once_for_each_id(spark, monkeypatch):
    monkeypatch.setattr(value_shards, "HEAVY_ROWS", 100)
    cube = W.QUERIES["skewed_cube_whole"](spark, SF)
    want = grouped_cube(tables.skewed(tables.wide(spark, SF)), W.shaped(W.SKEW)[1])
    assert sorted(map(repr, cube.collect())) == sorted(map(repr, want.collect()))
    plan = cube._jdf.queryExecution().sparkPlan().toString()
    exchanged = re.findall(r"(?:Repartition|RepartitionByExpression|Exchange) ?(?:hashpartitioning\()?\[?(hot_\w+)", plan)
    assert sorted(exchanged) == ["hot_cust", "hot_part", "hot_supp"], plan
