"""Experiment workloads on the given tables: each as a query, and where SQL can express it, as DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable
from itertools import product

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from segcube.functions import measures as M
from segcube.functions import segments as S
from segcube.functions.schema import MASK, CubeSchema, Grouping
from segcube.operators import batch_area, broadcast, layered_chain, query, value_shards
from segcube.operators.grouped_phases import grouped_cube, grouped_states, phase_deltas, sliced_cube
from segcube.plans import advisor, balance, ledger
from segcube.sources import scratch, tables

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

S5 = "c_region>c_nation>c_custkey | p_type, s_nation"
S8 = "c_region>c_nation, o_orderpriority, c_mktsegment | p_brand, p_type | l_returnflag, l_linestatus"
S14 = "c_nation>c_custkey, c_mktsegment, o_orderpriority, o_orderstatus | p_brand>l_partkey, p_type, p_size | s_nation>l_suppkey, l_returnflag, l_linestatus, discount_band"
FLAT = "p_type, o_orderpriority | l_returnflag, l_linestatus"
TIME = "ship_year>ship_month | p_type, l_returnflag"
SKEW = "hot_cust, c_mktsegment | hot_part, p_type | hot_supp, l_returnflag"
SIGNIFICANT = 100_000_000

WIDE_SQL = """wide AS (
  SELECT l.l_orderkey, cr.r_name AS c_region, cn.n_name AS c_nation, o.o_custkey AS c_custkey, c.c_mktsegment, o.o_orderpriority, o.o_orderstatus, p.p_brand, l.l_partkey, p.p_type, p.p_size,
         sr.r_name AS s_region, sn.n_name AS s_nation, l.l_suppkey, l.l_returnflag, l.l_linestatus, CAST(year(l.l_shipdate) AS INTEGER) AS ship_year, CAST(month(l.l_shipdate) AS INTEGER) AS ship_month,
         CAST(CASE WHEN l.l_discount >= 0.07 THEN 2 WHEN l.l_discount >= 0.03 THEN 1 ELSE 0 END AS INTEGER) AS discount_band,
         CAST(1 AS BIGINT) AS rows_1, CAST(l.l_quantity AS BIGINT) AS qty, CAST(round(l.l_extendedprice * 100) AS BIGINT) AS cents,
         CASE WHEN l.l_orderkey % 10 < 3 THEN 0 ELSE l.l_suppkey END AS hot_supp, CASE WHEN l.l_orderkey % 7 < 2 THEN 0 ELSE l.l_partkey END AS hot_part, CASE WHEN l.l_orderkey % 11 < 3 THEN 0 ELSE o.o_custkey END AS hot_cust
  FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey JOIN customer c ON o.o_custkey = c.c_custkey JOIN nation cn ON c.c_nationkey = cn.n_nationkey JOIN region cr ON cn.n_regionkey = cr.r_regionkey
  JOIN part p ON l.l_partkey = p.p_partkey JOIN supplier s ON l.l_suppkey = s.s_suppkey JOIN nation sn ON s.s_nationkey = sn.n_nationkey JOIN region sr ON sn.n_regionkey = sr.r_regionkey)"""
EVENTS_SQL = "ev AS (SELECT *, CAST(ts AS DATE) AS day, CAST(hour(ts) AS INTEGER) AS hour, CAST(round(value * 100) AS BIGINT) AS cents FROM events)"
DOCUMENTS_SQL = """dl AS (SELECT d.source, d.lang, CAST(CASE WHEN d.n_chars >= 10000 THEN 3 WHEN d.n_chars >= 2000 THEN 2 WHEN d.n_chars >= 500 THEN 1 ELSE 0 END AS INTEGER) AS band, d.n_chars, coalesce(l.toxic, 0) AS toxic, CASE WHEN l.doc_id IS NULL THEN 0 ELSE 1 END AS labelled
  FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id)"""

BASIC = (M.count("n"), M.total("qty"), M.total("cents"))
BASIC_SQL = {"n": "count(*)", "sum_qty": "sum(qty)", "sum_cents": "sum(cents)"}


def big(expression: str) -> str:
    return f"CAST({expression} AS BIGINT)"


def cube_select(schema: CubeSchema, source: str, values: dict[str, str], where: str = "", concrete: tuple[str, ...] = ()) -> str:
    """A cube by concatenated roll-ups; dimensions in ``concrete`` keep their values."""
    columns = ", ".join(schema.columns)
    parts = [", ".join(d.columns) if set(d.columns) <= set(concrete) else f"ROLLUP({', '.join(d.columns)})" for d in schema.dims]
    chosen = "".join(f", {sql} AS {name}" for name, sql in values.items())
    return f"SELECT {columns}, {big(f'GROUPING({columns})')} AS star_mask{chosen} FROM {source}{' WHERE ' + where if where else ''} GROUP BY {', '.join(parts)}"


def cube_sql(shape: str, source: str = WIDE_SQL, values: dict[str, str] | None = None, where: str = "") -> str:
    schema, _ = CubeSchema.parse(shape, BASIC)
    plain = values if values is not None else {k: big(v) for k, v in BASIC_SQL.items()}
    return f"WITH {source} {cube_select(schema, source.split()[0], plain, where)}"


_COUNT = (M.count("n"),)
_COUNT_SQL = {"n": big("count(*)")}


def register(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return add


def shaped(shape: str, measures=BASIC):
    return CubeSchema.parse(shape, measures)


# methods and variants on the same shapes


def _grouped(shape: str, measures=BASIC, groups=None, straddle: str = "reject", keep=None, **options) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        schema, grouping = shaped(shape, measures)
        if groups:
            grouping = Grouping.by_sizes(schema, groups, straddle)
        return grouped_cube(tables.wide(spark, folder), grouping, keep, **options)

    return run


def _other(shape: str, method, **options) -> Query:
    return lambda spark, folder: method(tables.wide(spark, folder), shaped(shape)[0], **options)


_METHODS: dict[str, tuple[str, Query]] = {
    "s5_grouped": (S5, _grouped(S5)),
    "s5_broadcast": (S5, _other(S5, broadcast.broadcast_cube)),
    "s5_broadcast_uncombined": (S5, _other(S5, broadcast.broadcast_cube, combine=False)),
    "s5_grouping_sets": (S5, _other(S5, broadcast.broadcast_cube, style="grouping_sets")),
    "s5_layered": (S5, _other(S5, layered_chain.layered_cube)),
    "s5_layered_rounds": (S5, _other(S5, layered_chain.layered_cube, carry=False, checkpoint="each")),
    "s5_batch_area": (S5, _other(S5, batch_area.batch_area_cube, max_load=20_000, fraction=0.2)),
    "s5_batch_area_value_partition": (S5, _other(S5, batch_area.batch_area_cube, max_load=500, fraction=1.0)),
    "s5_grouped_premerge": (S5, _grouped(S5, premerge=True)),
    "s5_grouped_heavy_last": (S5, _grouped(S5, heavy="last_parent")),
    "s5_grouped_heavy_all": (S5, _grouped(S5, heavy="all_parents")),
    "s5_kernel_layers": (S5, _grouped(S5, kernel="layers")),
    "s5_kernel_sweep": (S5, _grouped(S5, kernel="sweep")),
    "s5_kernel_direct": (S5, _grouped(S5, kernel="direct")),
    "s5_kernel_union": (S5, _grouped(S5, kernel="union")),
    "s5_kernel_arrow": (S5, _grouped(S5, kernel="arrow")),
    "s5_stored_phases": (S5, _grouped(S5, store=True)),
    "s5_g1": (S5, _grouped(S5, groups=(5,))),
    "s5_g1_heavy": (S5, _grouped(S5, groups=(5,), heavy="all_parents")),
    "s5_gn": (S5, _grouped(S5, groups=(3, 1, 1))),
    "s5_gm": (S5, _grouped(S5, groups=(1, 1, 1, 1, 1), straddle="guard")),
    "s5_straddle_guard": (S5, _grouped(S5, groups=(2, 3), straddle="guard")),
    "s8_grouped": (S8, _grouped(S8)),
    "s8_grouped_layers": (S8, _grouped(S8, kernel="layers")),
    "s8_batch_area": (S8, _other(S8, batch_area.batch_area_cube, max_load=20_000, fraction=0.2)),
    "s8_layered": (S8, _other(S8, layered_chain.layered_cube)),
    "s8_broadcast": (S8, _other(S8, broadcast.broadcast_cube)),
    "s8_grouping_sets": (S8, _other(S8, broadcast.broadcast_cube, style="grouping_sets")),
    "flat_grouped": (FLAT, _grouped(FLAT)),
    "flat_cube": (FLAT, _other(FLAT, broadcast.broadcast_cube, style="cube")),
}
for _name, (_shape, _query) in _METHODS.items():
    QUERIES[_name], ORACLE_SQL[_name] = _query, cube_sql(_shape)


_ENTITIES = {"l_returnflag": "advertisers", "c_region": "users", "p_brand": "websites", "o_orderpriority": "users", "l_linestatus": "advertisers", "p_type": "websites", "c_mktsegment": "users"}


@register("s8_by_entity", cube_sql(S8))
def s8_by_entity(spark, folder):
    """S8 from dimensions in any order: those of an entity (customer, part, line) form a group."""
    given, _ = shaped("l_returnflag, c_region>c_nation, p_brand, o_orderpriority, l_linestatus, p_type, c_mktsegment")
    return grouped_cube(tables.wide(spark, folder), Grouping.by_entity(given, _ENTITIES, ["users", "websites", "advertisers"]))


@register("s5_deltas", cube_sql(S5).replace("SELECT c_region", "SELECT CAST(CASE WHEN GROUPING(c_region, c_nation, c_custkey) > 0 THEN 2 WHEN GROUPING(p_type, s_nation) > 0 THEN 1 ELSE 0 END AS INTEGER) AS phase, c_region", 1))
def s5_deltas(spark, folder):
    """What each phase adds; together the cube."""
    schema, grouping = shaped(S5)
    out = None
    for phase, delta in phase_deltas(tables.wide(spark, folder), grouping):
        part = S.finalise(delta, schema).withColumn("phase", F.lit(phase))
        out = part if out is None else out.unionByName(part)
    return out


@register("s5_explicit_sets", f"SELECT * FROM ({cube_sql(S5)}) WHERE star_mask IN (0, 1, 7, 28, 31)")
def s5_explicit_sets(spark, folder):
    """Only some cuboids, by an explicit list of grouping sets."""
    schema, _ = shaped(S5)
    return S.finalise(broadcast.grouping_sets_states(tables.wide(spark, folder), schema, [0, 1, 7, 28, 31]), schema)


_DOUBLE = "CAST({} AS DOUBLE)"
_ALGEBRA_SQL = {
    "n": big("count(*)"),
    "avg_qty": "CAST(sum(qty) AS DOUBLE) / CAST(count(qty) AS DOUBLE)",
    "std_qty": "sqrt(CAST(count(qty) * sum(qty * qty) - sum(qty) * sum(qty) AS DOUBLE) / (CAST(count(qty) AS DOUBLE) * CAST(count(qty) AS DOUBLE)))",
    "price": "CAST(sum(cents) AS DOUBLE) / CAST(sum(qty) AS DOUBLE)",
    "cov_qty_discount_band": "CAST(count(qty) * sum(qty * discount_band) - sum(qty) * sum(discount_band) AS DOUBLE) / (CAST(count(qty) AS DOUBLE) * CAST(count(qty) AS DOUBLE))",
}
_ALGEBRA = (M.count("n"), M.mean("qty"), M.deviation("qty"), M.ratio("cents", "qty", "price"), M.covariance("qty", "discount_band"))
QUERIES["s5_algebraic"], ORACLE_SQL["s5_algebraic"] = _grouped(S5, _ALGEBRA), cube_sql(S5, values=_ALGEBRA_SQL)
QUERIES["s5_minmax"] = _grouped(S5, (M.least("cents"), M.greatest("cents"), M.top_member("l_orderkey", "cents", "top_order")))
ORACLE_SQL["s5_minmax"] = cube_sql(S5, values={"min_cents": big("min(cents)"), "max_cents": big("max(cents)"), "top_order": "max({'value': cents, 'member': l_orderkey}).member"})
QUERIES["distinct_per_segment"] = _grouped(TIME, (M.count("n"), M.distinct_exact("c_custkey", "customers")))
ORACLE_SQL["distinct_per_segment"] = cube_sql(TIME, values={"n": big("count(*)"), "customers": big("count(DISTINCT c_custkey)")})
QUERIES["sketches_per_segment"] = _grouped(TIME, (M.distinct_estimate("c_custkey", "customers"), M.quantile_estimate("qty", 0.5, "median_qty")))

_INNER = TIME + ", c_custkey"


@register("distinct_by_inner_column", cube_sql(TIME, values={"customers": big("count(DISTINCT c_custkey)")}))
def distinct_by_inner_column(spark, folder):
    """Exact distinct counts without sets: the counted column is cubed as the innermost one."""
    schema, grouping = shaped(_INNER, _COUNT)
    return query.distinct_members(grouped_cube(tables.wide(spark, folder), grouping), schema, "c_custkey", "customers")


_INNER_SQL = f"SELECT ship_year, ship_month, p_type, l_returnflag, c_custkey, star_mask >> 1 AS star_mask, sum_cents FROM ({cube_sql(_INNER, values={'sum_cents': big('sum(cents)')})}) WHERE star_mask & 1 = 0"


@register(
    "top_members_per_segment",
    f"SELECT * FROM (SELECT *, CAST(row_number() OVER (PARTITION BY star_mask, ship_year, ship_month, p_type, l_returnflag ORDER BY sum_cents DESC, c_custkey NULLS FIRST) AS INTEGER) AS place FROM ({_INNER_SQL})) WHERE place <= 3",
)
def top_members_per_segment(spark, folder):
    """The three customers with the largest revenue of each segment."""
    schema, grouping = shaped(_INNER, (M.total("cents"),))
    return query.top_members(grouped_cube(tables.wide(spark, folder), grouping), schema, "c_custkey", "sum_cents", 3)


_NULL_SQL = WIDE_SQL + ", nulled AS (SELECT * REPLACE (CASE WHEN p_type = 'PROMO' OR p_size < 10 THEN NULL ELSE p_type END AS p_type) FROM wide)"


@register("s5_null_dim", f"WITH {_NULL_SQL} " + cube_select(CubeSchema.parse(S5, BASIC)[0], "nulled", {k: big(v) for k, v in BASIC_SQL.items()}))
def s5_null_dim(spark, folder):
    """A null is a value of its own, apart from the star."""
    _, grouping = shaped(S5)
    rows = tables.wide(spark, folder).withColumn("p_type", F.when((F.col("p_type") == "PROMO") | (F.col("p_size") < 10), None).otherwise(F.col("p_type")))
    return grouped_cube(rows, grouping)


# cost and accuracy measures


def _parents_case(schema: CubeSchema, columns) -> str:
    cases = {m: len(S.primary_parents(m, schema, columns)) for m in S.legal_masks(schema)}
    return "CASE star_mask " + " ".join(f"WHEN {m} THEN {n}" for m, n in cases.items()) + " END"


def _phase_sql(shape: str) -> tuple[CubeSchema, Grouping, str]:
    schema, grouping = shaped(shape)
    parts = [WIDE_SQL]
    for p in grouping.phases:
        concrete = tuple(c for q in grouping.phases if q > p for c in grouping.group(q))
        parts.append(f"o{p} AS ({cube_select(schema, 'wide', {}, concrete=concrete)})")
        others = "".join(f"{c}, " for c in grouping.others(p))
        parts.append(f"k{p} AS (SELECT {others}star_mask & {schema.bits(grouping.others(p))} AS om, count(*) AS nodes, sum({_parents_case(schema, grouping.group(p))}) AS msgs FROM o{p} GROUP BY ALL)")
    return schema, grouping, "WITH " + ", ".join(parts)


def ledger_sql(shape: str) -> str:
    _, grouping, ctes = _phase_sql(shape)
    rows = []
    for p in grouping.phases:
        n_in = "(SELECT count(*) FROM wide)" if p == 1 else f"(SELECT count(*) FROM o{p - 1})"
        rows.append(
            f"SELECT CAST({p} AS INTEGER) AS phase, {big(n_in)} AS input_rows, {big(n_in)} AS remote_msgs, {big(n_in)} AS h0_inserts, {big('sum(nodes)')} AS output_rows, {big('sum(msgs)')} AS local_msgs, "
            f"CAST(sum(nodes) AS DOUBLE) / {n_in} AS phase_blow_up, CAST(sum(msgs) AS DOUBLE) / {n_in} AS local_per_remote, {big('max(nodes)')} AS max_nodes_per_key, {big('max(msgs)')} AS max_local_per_key, "
            f"CAST(max(nodes) AS DOUBLE) / CAST(sum(nodes) AS DOUBLE) AS node_share, CAST(max(msgs) AS DOUBLE) / CAST(sum(msgs) AS DOUBLE) AS local_share, {big(n_in)} AS shuffle_records FROM k{p}"
        )
    return ctes + " " + " UNION ALL ".join(rows)


def _ledger(shape: str, **options) -> Query:
    return lambda spark, folder: ledger.phase_ledger(tables.wide(spark, folder), shaped(shape)[1], **options).drop("seconds")


for _name, _shape in (("s5_phase_ledger", S5), ("s8_phase_ledger", S8)):
    QUERIES[_name], ORACLE_SQL[_name] = _ledger(_shape), ledger_sql(_shape)
ORACLE_SQL["blow_up_by_phase"] = f"SELECT phase, phase_blow_up FROM ({ledger_sql(S8)})"


@register("blow_up_by_phase", ORACLE_SQL["blow_up_by_phase"])
def blow_up_by_phase(spark, folder):
    return _ledger(S8)(spark, folder).select("phase", "phase_blow_up")


_REDUNDANT = "p_type | l_returnflag, l_linestatus"


@register("redundant_input_ledger", ledger_sql(_REDUNDANT))
def redundant_input_ledger(spark, folder):
    """Sixty thousand rows onto a few dozen leaf keys: phase 1 shrinks its input."""
    return _ledger(_REDUNDANT)(spark, folder)


def totals_sql(shape: str) -> str:
    """The totals of a run from its phases, a row for each."""
    value = {
        "input_rows": "raw", "cube_rows": "cube", "output_rows": "outs", "remote_msgs": "remote", "remote_msgs_after_first": "remote - raw", "local_msgs": "msgs", "h0_inserts": "remote", "local_with_h0": "msgs + remote",
        "locality": "msgs / (msgs + remote - raw)", "blow_up": "cube / raw", "local_per_segment": "msgs / cube", "messages_per_segment": "(msgs + remote) / cube", "remote_per_input_row": "remote / raw",
        "remote_after_first_per_input_row": "(remote - raw) / raw", "shuffle_records": "remote", "largest_local_share": "top_local", "largest_node_share": "top_node",
    }
    sums = "CAST(max(CASE WHEN phase = 1 THEN input_rows END) AS DOUBLE) AS raw, CAST(max_by(output_rows, phase) AS DOUBLE) AS cube, CAST(sum(output_rows) AS DOUBLE) AS outs, CAST(sum(remote_msgs) AS DOUBLE) AS remote, CAST(sum(local_msgs) AS DOUBLE) AS msgs, max(local_share) AS top_local, max(node_share) AS top_node"
    rows = " UNION ALL ".join(f"SELECT '{k}' AS measure, CAST({v} AS DOUBLE) AS value FROM t" for k, v in value.items())
    return f"WITH phases AS ({ledger_sql(shape)}), t AS (SELECT {sums} FROM phases) {rows}"


for _name, _shape in (("s5_run_totals", S5), ("s8_run_totals", S8)):
    QUERIES[_name] = lambda spark, folder, shape=_shape: ledger.total_rows(spark, ledger.phase_stats(tables.wide(spark, folder), shaped(shape)[1]))
    ORACLE_SQL[_name] = totals_sql(_shape)


@register("s8_run_times")
def s8_run_times(spark, folder):
    """Seconds and records shuffled by phase, and in total (phase null); seconds cover computing and storing a phase."""
    rows = ledger.phase_stats(tables.wide(spark, folder), shaped(S8)[1])
    rows = [(r[0], r[1], r[4], r[12], r[13]) for r in rows]
    return spark.createDataFrame([*rows, (None, *(sum(r[k] for r in rows) for k in range(1, 5)))], "phase int, input_rows bigint, output_rows bigint, shuffle_records bigint, seconds double")


@register("s8_premerged_records")
def s8_premerged_records(spark, folder):
    """What pre-merging and the combiners of heavy phases leave of the records that each phase shuffles."""
    rows, (_, grouping), out = tables.wide(spark, folder), shaped(S8), None
    for name, options in (("plain", {}), ("premerge", {"premerge": True}), ("heavy", {"heavy": "all_parents"})):
        part = ledger.phase_ledger(rows, grouping, **options).select(F.lit(name).alias("variant"), "phase", "input_rows", "shuffle_records")
        out = part if out is None else out.unionByName(part)
    return out


#: Number of groups, columns in or out of the last group, and large columns first instead of small ones.
_CHOICES = {
    "one group": "c_region>c_nation, o_orderpriority, c_mktsegment, p_brand, p_type, l_returnflag, l_linestatus",
    "two groups": "c_region>c_nation, o_orderpriority, c_mktsegment | p_brand, p_type, l_returnflag, l_linestatus",
    "three groups": S8,
    "a group for each dimension": "c_region>c_nation | o_orderpriority | c_mktsegment | p_brand | p_type | l_returnflag | l_linestatus",
    "large last group": "c_region>c_nation, o_orderpriority, c_mktsegment, p_brand | p_type | l_returnflag, l_linestatus",
    "small last group": "c_region>c_nation | o_orderpriority, c_mktsegment, p_brand, p_type | l_returnflag, l_linestatus",
    "large columns first": "l_returnflag, l_linestatus | p_type, p_brand | c_mktsegment, o_orderpriority, c_region>c_nation",
}
_CHOICE_MEASURES = ("remote_msgs", "local_msgs", "locality", "messages_per_segment", "largest_local_share", "cube_rows")


def _choices_sql() -> str:
    picked = ", ".join(f"max(CASE WHEN measure = '{m}' THEN value END) AS {m}" for m in _CHOICE_MEASURES)
    return " UNION ALL ".join(f"SELECT '{name}' AS grouping, {picked} FROM ({totals_sql(shape)})" for name, shape in _CHOICES.items())


@register("grouping_choices", _choices_sql())
def grouping_choices(spark, folder):
    """Locality and balance of several groupings of the columns of S8."""
    rows, out = scratch.materialised(tables.wide(spark, folder), "wide"), []
    for name, shape in _CHOICES.items():
        t = ledger.totals(ledger.phase_stats(rows, shaped(shape)[1]))
        out.append((name, *(None if t[m] is None else float(t[m]) for m in _CHOICE_MEASURES)))
    return spark.createDataFrame(out, "grouping string, " + ", ".join(f"{m} double" for m in _CHOICE_MEASURES))


#: Sixteenths of the orders.
_PARTS = (1, 4, 16)


@register(
    "cube_scaling",
    f"WITH {WIDE_SQL} " + " UNION ALL ".join(
        f"SELECT CAST({k} AS INTEGER) AS sixteenths, (SELECT count(*) FROM wide WHERE l_orderkey % 16 < {k}) AS input_rows, count(*) AS cube_rows, CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM wide WHERE l_orderkey % 16 < {k}) AS blow_up "
        f"FROM ({cube_select(shaped(S5)[0], 'wide', {}, where=f'l_orderkey % 16 < {k}')})" for k in _PARTS
    ),
)
def cube_scaling(spark, folder):
    """How the cube grows with its input, for parts of the orders; the last is the whole table."""
    rows, out = tables.wide(spark, folder), []
    for k in _PARTS:
        t = ledger.totals(ledger.phase_stats(rows.filter(F.col("l_orderkey") % 16 < k), shaped(S5)[1]))
        out.append((k, t["input_rows"], t["cube_rows"], t["blow_up"]))
    return spark.createDataFrame(out, "sixteenths int, input_rows bigint, cube_rows bigint, blow_up double")


@register("cube_bytes")
def cube_bytes(spark, folder):
    """Rows and stored bytes of the joined input and of its cube."""
    schema, grouping = shaped(S5)
    out = []
    for name, df in (("input", tables.wide(spark, folder).select(*schema.columns, "qty", "cents")), ("cube", grouped_states(tables.wide(spark, folder), grouping))):
        path = scratch.new_folder(spark, name)
        df.write.parquet(path)
        out.append((name, *ledger.sizes(path, spark)))
    return spark.createDataFrame(out, "what string, rows bigint, bytes bigint")


#: Batch areas take cuboids whose largest key has at most this share of the rows.
_AREA_SHARE = 10


def _area_count_sql(shape: str) -> str:
    """The number of areas by the same greedy choice, on exact loads: lists of masks in a recursive query."""
    schema, _ = shaped(shape)
    masks = "[" + ", ".join(map(str, S.legal_masks(schema))) + "]"
    inside = "list_filter({0}, lambda x: (x & ~{1}) = 0)"
    best = f"list_max(list_transform(fits, lambda f: len({inside.format('left_over', 'f')}) * 1000000 + f))"
    return (
        f"loads AS (SELECT star_mask, max(n) AS load FROM ({cube_select(schema, 'wide', _COUNT_SQL)}) GROUP BY 1), "
        f"fitting AS (SELECT list_filter({masks}, lambda m: m = 0 OR list_contains(list(star_mask) FILTER (WHERE load * {_AREA_SHARE} <= (SELECT count(*) FROM wide)), m)) AS fits FROM loads), "
        f"areas AS (SELECT fits, fits AS left_over, 0 AS n FROM fitting UNION ALL SELECT fits, list_filter(left_over, lambda x: (x & ~({best} % 1000000)) <> 0), n + 1 FROM areas WHERE len(left_over) > 0)"
    )


def _messages_sql(shape: str) -> str:
    schema, grouping, ctes = _phase_sql(shape)
    last = len(grouping.groups)
    remote = " + ".join(["(SELECT count(*) FROM wide)", *(f"(SELECT count(*) FROM o{p})" for p in grouping.phases if p < last)])
    local = " + ".join(f"(SELECT sum(msgs) FROM k{p})" for p in grouping.phases)
    raw = "(SELECT count(*) FROM wide)"
    chain = f"(SELECT sum({_parents_case(schema, schema.columns)}) FROM o{last})"
    return (
        f"{ctes.replace('WITH ', 'WITH RECURSIVE ', 1)}, {_area_count_sql(shape)} SELECT 'grouped' AS method, {big(remote)} AS remote_msgs, {big(local)} AS local_msgs UNION ALL SELECT 'layered', {big(f'{raw} + {chain}')}, CAST(0 AS BIGINT) "
        f"UNION ALL SELECT 'broadcast', {big(f'{raw} * {len(S.legal_masks(schema)) - 1}')}, CAST(0 AS BIGINT) UNION ALL SELECT 'batch_area', {big(f'{raw} * (SELECT max(n) FROM areas)')}, NULL"
    )


def _messages(shape: str) -> Query:
    """Messages of all methods; batched areas by their plan on exact loads, which the cube holds as counts."""

    def run(spark, folder):
        schema, grouping = shaped(shape)

        def areas(cube: DataFrame) -> int:
            load = {r[MASK]: r.max_load for r in cube.groupBy(MASK).agg(F.max("n").alias("max_load")).collect()}  # one row per cuboid
            return len(batch_area.plan_batch_areas(schema, load, load.get(max(S.legal_masks(schema)), 0) // _AREA_SHARE))

        return ledger.method_messages(spark, tables.wide(spark, folder), grouping, areas)

    return run


QUERIES["method_messages"], ORACLE_SQL["method_messages"] = _messages(S8), _messages_sql(S8)
QUERIES["method_messages_s5"], ORACLE_SQL["method_messages_s5"] = _messages(S5), _messages_sql(S5)


_SHARE = "SELECT {0} AS sharding, CAST(count(*) AS BIGINT) AS keys, CAST(max(n) AS BIGINT) AS max_rows, CAST(sum(n) AS BIGINT) AS rows, CAST(max(n) AS DOUBLE) / CAST(sum(n) AS DOUBLE) AS share FROM (SELECT count(*) AS n FROM wide GROUP BY {1})"


def _shares(choices: dict[str, tuple[str, ...]]) -> tuple[Query, str]:
    def run(spark, folder):
        rows, out = tables.skewed(tables.wide(spark, folder)), None
        for name, columns in choices.items():
            part = balance.shard_share(rows, columns).withColumn("sharding", F.lit(name))
            out = part if out is None else out.unionByName(part)
        return out

    return run, f"WITH {WIDE_SQL} " + " UNION ALL ".join(_SHARE.format(f"'{n}'", ", ".join(c)) for n, c in choices.items())


QUERIES["balance_one_column"], ORACLE_SQL["balance_one_column"] = _shares({"supplier": ("hot_supp",), "part": ("hot_part",), "customer": ("hot_cust",), "safe": ("l_orderkey",)})
QUERIES["balance_two_groups"], ORACLE_SQL["balance_two_groups"] = _shares(
    {"supplier and part": ("hot_supp", "l_returnflag", "hot_part", "p_type"), "supplier and customer": ("hot_supp", "l_returnflag", "hot_cust", "c_mktsegment"), "part and customer": ("hot_part", "p_type", "hot_cust", "c_mktsegment")}
)


@register("max_key_load", (lambda g: f"{_phase_sql(S8)[2]} " + " UNION ALL ".join(f"SELECT CAST({p} AS INTEGER) AS phase, {big('max(nodes)')} AS max_nodes, {big('max(msgs)')} AS max_local FROM k{p}" for p in g.phases))(shaped(S8)[1]))
def max_key_load(spark, folder):
    return ledger.phase_ledger(tables.wide(spark, folder), shaped(S8)[1]).select("phase", F.col("max_nodes_per_key").alias("max_nodes"), F.col("max_local_per_key").alias("max_local"))


_SHARDINGS = {"supplier": ["hot_supp"], "supplier and part": ["hot_supp", "l_returnflag", "hot_part", "p_type"]}
_MACHINES = 100


def _machines_sql(name: str, columns: list[str]) -> str:
    text = " || '|' || ".join(f"CAST({c} AS VARCHAR)" for c in columns)
    dealt = f"SELECT ('0x' || substr(md5({text}), 1, 8))::BIGINT % {_MACHINES} AS machine, count(*) AS work FROM wide GROUP BY 1"
    return f"SELECT '{name}' AS sharding, {big('max(work)')} AS max_work, {big('sum(work)')} AS all_work, CAST(max(work) AS DOUBLE) * {_MACHINES} / CAST(sum(work) AS DOUBLE) AS max_over_mean FROM ({dealt})"


@register("machine_balance", f"WITH {WIDE_SQL} " + " UNION ALL ".join(_machines_sql(n, c) for n, c in _SHARDINGS.items()))
def machine_balance(spark, folder):
    """Work of the busiest of 100 machines over the mean: sharding by one hot column and by two groups."""
    rows = tables.skewed(tables.wide(spark, folder))
    out = None
    for name, columns in _SHARDINGS.items():
        loads = rows.groupBy(*columns).agg(F.count(F.lit(1)).alias("work"))
        part = balance.machine_balance(loads, columns, "work", _MACHINES).withColumn("sharding", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


@register("segments_by_layer", f"SELECT CAST(bit_count(star_mask) AS INTEGER) AS layer, {big('count(*)')} AS segments FROM ({cube_sql(S8)}) GROUP BY 1")
def segments_by_layer(spark, folder):
    return layered_chain.layer_sizes(_grouped(S8)(spark, folder))


@register("primary_parent_histogram", f"SELECT {big(_parents_case(shaped(S8)[0], shaped(S8)[0].columns))} AS parents, {big('count(*)')} AS segments FROM ({cube_sql(S8)}) GROUP BY 1")
def primary_parent_histogram(spark, folder):
    return ledger.primary_parent_histogram(_grouped(S8)(spark, folder), shaped(S8)[0])


@register("children_sum_violations", "SELECT CAST(0 AS BIGINT) AS violations")
def children_sum_violations(spark, folder):
    """Every aggregate equals the sum over its primary children."""
    schema, grouping = shaped(S5)
    states = scratch.materialised(grouped_states(tables.wide(spark, folder), grouping), "cube")
    return query.check_children_sum(states, schema).agg(F.count(F.lit(1)).alias("violations"))


# workloads


def _change(spark, folder, shape=S8, keep=None, method=grouped_cube):
    before, after = (lambda: F.col("ship_year") == 1996), (lambda: F.col("ship_year") == 1997)
    schema, grouping = shaped(shape, M.change("cents", before, after))
    return schema, method(tables.wide(spark, folder).filter(F.col("ship_year").isin(1996, 1997)), grouping, keep)


_CHANGE_VALUES = {"before": big("sum(CASE WHEN ship_year = 1996 THEN cents ELSE 0 END)"), "after": big("sum(CASE WHEN ship_year = 1997 THEN cents ELSE 0 END)")}
_CHANGE_SQL = f"SELECT *, after - before AS change, CAST(after - before AS DOUBLE) / nullif(CAST(abs(before) AS DOUBLE), 0) AS relative_change FROM ({cube_sql(S8, values=_CHANGE_VALUES, where='ship_year IN (1996, 1997)')})"


@register("change_significant", f"SELECT * FROM ({_CHANGE_SQL}) WHERE abs(change) >= {SIGNIFICANT}")
def change_significant(spark, folder):
    """Segments whose revenue changed by a threshold or more; nothing is pruned before the cube is whole."""
    return _change(spark, folder)[1].filter(F.abs("change") >= SIGNIFICANT)


_KEY_ORDER = ", ".join(f"{c} NULLS FIRST" for c in shaped(S8)[0].columns)


@register("change_top_k", f"SELECT * FROM ({_CHANGE_SQL}) ORDER BY abs(change) DESC, star_mask, {_KEY_ORDER} LIMIT 100")
def change_top_k(spark, folder):
    schema, cube = _change(spark, folder)
    return query.top_segments(cube, schema, 100, F.abs("change").desc())


@register("change_relative", f"SELECT * FROM ({_CHANGE_SQL}) WHERE before >= {SIGNIFICANT} AND abs(relative_change) >= 0.5")
def change_relative(spark, folder):
    return _change(spark, folder)[1].filter((F.col("before") >= SIGNIFICANT) & (F.abs("relative_change") >= 0.5))


def _cube_in_parts(schema: CubeSchema, source: str, values: dict[str, str], having: str, fixed: int) -> str:
    """The cube by sending rows to cuboids, one query for each choice of levels of the first ``fixed`` dimensions, so that DuckDB never holds all of it."""
    right = CubeSchema(schema.dims[fixed:], schema.measures)
    masks = f"unnest([{', '.join(map(str, S.legal_masks(right)))}]) AS m(m)"
    free = ", ".join(f"CASE WHEN m & {right.bit(c)} = 0 THEN {c} END AS {c}" for c in right.columns)
    chosen = ", ".join(f"{sql} AS {name}" for name, sql in values.items())
    parts = []
    for kept in product(*(range(len(d.columns), -1, -1) for d in schema.dims[:fixed])):
        starred = [c for d, k in zip(schema.dims, kept, strict=False) for c in d.columns[k:]]
        columns = ", ".join(f"NULL AS {c}" if c in starred else c for d in schema.dims[:fixed] for c in d.columns)
        sent = f"SELECT {columns}, {free}, {big(f'{schema.bits(starred)} + m')} AS star_mask, ship_year, cents FROM {source}, {masks}"
        parts.append(f"SELECT {', '.join(schema.columns)}, star_mask, {chosen} FROM ({sent}) GROUP BY ALL HAVING {having}")
    return " UNION ALL ".join(parts)


_S14_PARTS = _cube_in_parts(shaped(S14)[0], "two_years", _CHANGE_VALUES, f"abs(sum(CASE WHEN ship_year = 1997 THEN cents ELSE -cents END)) >= {SIGNIFICANT}", 5)
_S14_CHANGE_SQL = f"WITH {WIDE_SQL}, two_years AS MATERIALIZED (SELECT * FROM wide WHERE ship_year IN (1996, 1997)) SELECT *, after - before AS change, CAST(after - before AS DOUBLE) / nullif(CAST(abs(before) AS DOUBLE), 0) AS relative_change FROM ({_S14_PARTS})"


@register("s14_change_significant", _S14_CHANGE_SQL)
def s14_change_significant(spark, folder):
    """The full shape, 11 dimensions in 14 columns and 6,912 cuboids: as :func:`change_significant`, each slice whole before the filter."""
    return _change(spark, folder, S14, F.abs("change") >= SIGNIFICANT, sliced_cube)[1]


@register("skewed_cube", f"SELECT * FROM ({cube_sql(SKEW)}) WHERE n >= 20")
def skewed_cube(spark, folder):
    """The segments of at least 20 rows; the cube is computed whole before, by the grouped method; :func:`skewed_cube_whole` returns all of it."""
    return grouped_cube(tables.skewed(tables.wide(spark, folder)), shaped(SKEW)[1], F.col("n") >= 20)


@register("skewed_cube_whole", cube_sql(SKEW))
def skewed_cube_whole(spark, folder):
    """All segments; by value, since most of them have few rows and the grouped method sends nearly half of them through a shuffle."""
    return value_shards.value_sharded_cube(tables.skewed(tables.wide(spark, folder)), shaped(SKEW)[0], ("hot_cust", "hot_part", "hot_supp"))


def events(spark: SparkSession, folder: str) -> DataFrame:
    return _event_columns(tables.read_table(spark, folder, "events"))


def _event_columns(df: DataFrame) -> DataFrame:
    return df.withColumns({"day": F.to_date("ts"), "hour": F.hour("ts"), "cents": F.round(F.col("value") * 100).cast("bigint")})


_EVENTS = "day>hour | event_type"
_EVENT_MEASURES = (M.count("n"), M.total("cents"), M.mean("cents"), M.deviation("cents"))
_EVENT_VALUES = {
    "n": big("count(*)"), "sum_cents": big("sum(cents)"), "avg_cents": "CAST(sum(cents) AS DOUBLE) / CAST(count(cents) AS DOUBLE)",
    "std_cents": "sqrt(CAST(count(cents) * sum(CAST(cents AS HUGEINT) * cents) - sum(cents) * sum(cents) AS DOUBLE) / (CAST(count(cents) AS DOUBLE) * CAST(count(cents) AS DOUBLE)))",
}
def _cube_of(source: Callable[[SparkSession, str], DataFrame], shape: str, measures) -> Query:
    return lambda spark, folder: grouped_cube(source(spark, folder), shaped(shape, measures)[1])


QUERIES["events_cube"], ORACLE_SQL["events_cube"] = _cube_of(events, _EVENTS, _EVENT_MEASURES), cube_sql(_EVENTS, EVENTS_SQL, _EVENT_VALUES)
QUERIES["events_by_user"], ORACLE_SQL["events_by_user"] = _cube_of(events, "user_id | event_type", _COUNT), cube_sql("user_id | event_type", EVENTS_SQL, _COUNT_SQL)
QUERIES["redundant_input_cube"], ORACLE_SQL["redundant_input_cube"] = _cube_of(tables.wide, "p_type | l_returnflag, l_linestatus", _COUNT), cube_sql("p_type | l_returnflag, l_linestatus", values=_COUNT_SQL)
QUERIES["json_dimension"] = _cube_of(lambda s, d: events(s, d).withColumn("tens", F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("bigint")), "tens | event_type", _COUNT)
ORACLE_SQL["json_dimension"] = cube_sql("tens | event_type", EVENTS_SQL.replace("SELECT *", "SELECT *, CAST(floor(CAST(json_extract_string(props, '$.k') AS INTEGER) / 10) AS BIGINT) AS tens"), _COUNT_SQL)


def labelled_documents(spark, folder):
    labels = tables.read_table(spark, folder, "labels").select("doc_id", F.col("toxic"), F.lit(1).alias("labelled"))
    docs = tables.read_table(spark, folder, "documents").select("doc_id", "source", "lang", "n_chars", tables.band(F.col("n_chars"), 500, 2000, 10_000).alias("band"))
    return docs.join(labels, "doc_id", "left").withColumns({"toxic": F.coalesce("toxic", F.lit(0)), "labelled": F.coalesce("labelled", F.lit(0))})


QUERIES["documents_cube"] = _cube_of(labelled_documents, "source | lang, band", (M.count("n"), M.total("n_chars"), M.total("toxic"), M.total("labelled")))
ORACLE_SQL["documents_cube"] = cube_sql("source | lang, band", DOCUMENTS_SQL, {"n": big("count(*)"), "sum_n_chars": big("sum(n_chars)"), "sum_toxic": big("sum(toxic)"), "sum_labelled": big("sum(labelled)")})
_TURNS = "cv AS (SELECT *, length(text) AS size FROM conversations)"
QUERIES["conversations_cube"] = _cube_of(lambda s, d: tables.read_table(s, d, "conversations").withColumn("size", F.length("text")), "role | turn", (M.count("n"), M.total("size")))
ORACLE_SQL["conversations_cube"] = cube_sql("role | turn", _TURNS, {"n": big("count(*)"), "sum_size": big("sum(size)")})
_HOSTS = "pg AS (SELECT split_part(url, '://', 1) AS scheme, regexp_extract(url, '://([^/?#]*)', 1) AS host, length(html) AS size FROM pages)"
QUERIES["pages_host_cube"] = _cube_of(
    lambda s, d: tables.read_table(s, d, "pages").select(F.substring_index("url", "://", 1).alias("scheme"), F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), F.length("html").alias("size")), "host | scheme", (M.count("n"), M.total("size"))
)
ORACLE_SQL["pages_host_cube"] = cube_sql("host | scheme", _HOSTS, {"n": big("count(*)"), "sum_size": big("sum(size)")})
QUERIES["embeddings_label_cube"] = lambda spark, folder: grouped_cube(tables.read_table(spark, folder, "embeddings"), shaped("label", _COUNT)[1])
ORACLE_SQL["embeddings_label_cube"] = cube_sql("label", "eb AS (SELECT * FROM embeddings)", _COUNT_SQL)


@register("advise_cardinalities")
def advise_cardinalities(spark, folder):
    return advisor.cardinalities(tables.wide(spark, folder), shaped(S8)[0])


@register("advised_grouping")
def advised_grouping(spark, folder):
    """Groups that the advisor picks for five columns, with what it expects of them."""
    found = advisor.advise_grouping(tables.wide(spark, folder), shaped("c_region>c_nation, p_brand | p_type, l_returnflag")[0], g=2, sample=0.05)
    rows = [(p, ", ".join(found.grouping.group(p)), found.expected.get("locality"), found.expected.get("largest_local_share")) for p in found.grouping.phases]
    return spark.createDataFrame(rows, "phase int, columns string, locality double, largest_local_share double")


@register("exact_load", f"SELECT star_mask, {big('max(n)')} AS max_load FROM ({cube_sql(S5)}) GROUP BY 1")
def exact_load(spark, folder):
    return batch_area.sample_load(tables.wide(spark, folder), shaped(S5)[0], 1.0)


@register("sample_load")
def sample_load(spark, folder):
    return batch_area.sample_load(tables.wide(spark, folder), shaped(S5)[0], 0.1)


# questions to a cube


def _time_cube(spark, folder):
    return shaped(TIME)[0], _grouped(TIME)(spark, folder)


_T = cube_sql(TIME)


@register("segment_lookup", f"SELECT * FROM ({_T}) WHERE star_mask = 5 AND ship_year = 1997 AND p_type = 'ECONOMY'")
def segment_lookup(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.segment(cube, schema, ship_year=1997, p_type="ECONOMY")


@register("slice", f"SELECT * FROM ({_T}) WHERE star_mask = 4 AND ship_year = 1997")
def slice_query(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.slice_(cube, schema, {"ship_year": 1997}, ["p_type", "l_returnflag"])


@register("dice", f"SELECT * FROM ({_T}) WHERE star_mask = 4 AND ship_year IN (1996, 1998) AND l_returnflag IN ('A', 'R')")
def dice_query(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.dice(cube, schema, {"ship_year": [1996, 1998], "l_returnflag": ["A", "R"]}, ["p_type"])


@register("drill_down", f"SELECT * FROM ({_T}) WHERE star_mask = 3 AND ship_year = 1997")
def drill_down(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.drill_down(cube, schema, "ship_year", ship_year=1997)


@register("roll_up", f"SELECT * FROM ({_T}) WHERE star_mask = 6 AND ship_year = 1997 AND l_returnflag = 'R'")
def roll_up(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.roll_up(cube, schema, "ship_year", ship_year=1997, ship_month=3, l_returnflag="R")


@register("primary_children", f"SELECT * FROM ({_T}) WHERE star_mask = 4 AND ship_year = 1997 AND p_type = 'PROMO'")
def primary_children(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.primary_children(cube, schema, ship_year=1997, p_type="PROMO")


@register("answer_group_by", f"WITH {WIDE_SQL} SELECT ship_year, l_returnflag, {big('count(*)')} AS n, {big('sum(qty)')} AS sum_qty, {big('sum(cents)')} AS sum_cents FROM wide GROUP BY 1, 2")
def answer_group_by(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.answer(cube, schema, ("ship_year", "l_returnflag"))


_SHARE_SQL = f"""SELECT c.*, p.n AS parent_value, CAST(c.n AS DOUBLE) / CAST(p.n AS DOUBLE) AS share FROM ({_T}) c JOIN ({_T}) p ON
  p.star_mask = CASE WHEN c.star_mask & 4 = 0 THEN c.star_mask | 4 ELSE c.star_mask | 8 END AND (c.star_mask & 8) = 0
  AND p.ship_year IS NOT DISTINCT FROM (CASE WHEN c.star_mask & 4 = 0 THEN c.ship_year END) AND p.ship_month IS NULL
  AND p.p_type IS NOT DISTINCT FROM c.p_type AND p.l_returnflag IS NOT DISTINCT FROM c.l_returnflag"""


@register("parent_share", _SHARE_SQL)
def parent_share(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.with_parent_share(scratch.materialised(cube, "cube"), schema, "ship_year", "n")


_RANK_KEY = "ship_year NULLS FIRST, ship_month NULLS FIRST, p_type NULLS FIRST, l_returnflag NULLS FIRST"


@register(
    "rank_in_cuboid",
    f"""SELECT *, CAST(row_number() OVER o AS INTEGER) AS row_number, CAST(rank() OVER v AS INTEGER) AS rank, CAST(dense_rank() OVER v AS INTEGER) AS dense_rank, CAST(ntile(4) OVER o AS INTEGER) AS quarter, percent_rank() OVER v AS percent
  FROM ({_T}) WINDOW o AS (PARTITION BY star_mask ORDER BY sum_cents DESC, {_RANK_KEY}), v AS (PARTITION BY star_mask ORDER BY sum_cents DESC)""",
)
def rank_in_cuboid(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return query.rank_in_cuboid(cube, schema, "sum_cents")


_DAILY = f"SELECT day, event_type, n FROM ({cube_sql(_EVENTS, EVENTS_SQL, _COUNT_SQL)}) WHERE star_mask = 2"


def _daily(spark, folder):
    schema, grouping = shaped(_EVENTS, _COUNT)
    return query.answer(grouped_cube(events(spark, folder), grouping), schema, ("day", "event_type"))


def _by_day():
    return Window.partitionBy("event_type").orderBy("day")


@register("running_total", f"SELECT *, {big('sum(n) OVER (PARTITION BY event_type ORDER BY day ROWS UNBOUNDED PRECEDING)')} AS so_far FROM ({_DAILY})")
def running_total(spark, folder):
    return _daily(spark, folder).withColumn("so_far", F.sum("n").over(_by_day().rowsBetween(Window.unboundedPreceding, 0)))


@register("moving_average", f"SELECT *, CAST(sum(n) OVER w AS DOUBLE) / CAST(count(*) OVER w AS DOUBLE) AS week FROM ({_DAILY}) WINDOW w AS (PARTITION BY event_type ORDER BY day ROWS 6 PRECEDING)")
def moving_average(spark, folder):
    week = _by_day().rowsBetween(-6, 0)
    return _daily(spark, folder).withColumn("week", F.sum("n").over(week).cast("double") / F.count(F.lit(1)).over(week).cast("double"))


@register("lag_change", f"SELECT *, n - lag(n) OVER w AS day_change, first_value(n) OVER w AS first_n, lead(n) OVER w AS next_n FROM ({_DAILY}) WINDOW w AS (PARTITION BY event_type ORDER BY day)")
def lag_change(spark, folder):
    w = _by_day()
    return _daily(spark, folder).withColumns({"day_change": F.col("n") - F.lag("n").over(w), "first_n": F.first("n").over(w), "next_n": F.lead("n").over(w)})


@register("share_of_siblings", f"SELECT *, CAST(n AS DOUBLE) / CAST(sum(n) OVER (PARTITION BY day) AS DOUBLE) AS share FROM ({_DAILY})")
def share_of_siblings(spark, folder):
    return _daily(spark, folder).withColumn("share", F.col("n").cast("double") / F.sum("n").over(Window.partitionBy("day")).cast("double"))


@register("pivot_cuboid", f"WITH c AS (SELECT * FROM ({_T}) WHERE star_mask = 6) SELECT ship_year, " + ", ".join(f"{big(f'sum(n) FILTER (WHERE l_returnflag = {chr(39)}{x}{chr(39)})')} AS {x}" for x in "ANR") + " FROM c GROUP BY 1")
def pivot_cuboid(spark, folder):
    schema, cube = _time_cube(spark, folder)
    return cube.filter(F.col(MASK) == query.mask_of(schema, ("ship_year", "l_returnflag"))).groupBy("ship_year").pivot("l_returnflag", ["A", "N", "R"]).agg(F.sum("n"))


def _years(spark, folder, *years):
    schema, grouping = shaped("p_type | s_nation")
    return schema, method(tables.wide(spark, folder).filter(F.col("ship_year").isin(*years)), grouping)


def _years_sql(*years):
    return cube_sql("p_type | s_nation", where=f"ship_year IN ({', '.join(map(str, years))})")


_SAME_KEY = "a.star_mask = b.star_mask AND a.p_type IS NOT DISTINCT FROM b.p_type AND a.s_nation IS NOT DISTINCT FROM b.s_nation"
_SIG = f"(SELECT p_type FROM ({_years_sql(1997)}) WHERE star_mask = 1 AND n >= (SELECT max(n) * 0.95 FROM ({_years_sql(1997)}) WHERE star_mask = 1))"


def _in_large_types(kind: str) -> Query:
    def run(spark, folder):
        _, cube = _years(spark, folder, 1997)
        large = cube.filter(F.col(MASK) == 1).withColumn("top", F.max("n").over(Window.partitionBy(MASK))).filter("n >= top * 0.95").select("p_type")
        return tables.wide(spark, folder).select("l_orderkey", "p_type", "cents").join(large, "p_type", kind).groupBy("p_type").agg(F.count(F.lit(1)).alias("n"))

    return run


QUERIES["cube_semi"], ORACLE_SQL["cube_semi"] = _in_large_types("left_semi"), f"WITH {WIDE_SQL} SELECT p_type, {big('count(*)')} AS n FROM wide WHERE p_type IN {_SIG} GROUP BY 1"
QUERIES["cube_anti"], ORACLE_SQL["cube_anti"] = _in_large_types("left_anti"), f"WITH {WIDE_SQL} SELECT p_type, {big('count(*)')} AS n FROM wide WHERE p_type NOT IN {_SIG} GROUP BY 1"


@register(
    "cube_full_outer",
    f"SELECT coalesce(a.p_type, b.p_type) AS p_type, coalesce(a.s_nation, b.s_nation) AS s_nation, coalesce(a.star_mask, b.star_mask) AS star_mask, coalesce(a.n, 0) AS before, coalesce(b.n, 0) AS after FROM ({_years_sql(1996)}) a FULL JOIN ({_years_sql(1997)}) b ON {_SAME_KEY}",
)
def cube_full_outer(spark, folder):
    schema, before = _years(spark, folder, 1996)
    return query.compare(before, _years(spark, folder, 1997)[1], schema, "n")


_KEYS = "SELECT p_type, s_nation, star_mask FROM ({})"


@register("cube_intersect", f"{_KEYS.format(_years_sql(1995))} INTERSECT {_KEYS.format(_years_sql(2001))}")
def cube_intersect(spark, folder):
    return _years(spark, folder, 1995)[1].select("p_type", "s_nation", MASK).intersect(_years(spark, folder, 2001)[1].select("p_type", "s_nation", MASK))


@register("cube_except", f"{_KEYS.format(_years_sql(1995))} EXCEPT {_KEYS.format(_years_sql(2001))}")
def cube_except(spark, folder):
    return _years(spark, folder, 1995)[1].select("p_type", "s_nation", MASK).exceptAll(_years(spark, folder, 2001)[1].select("p_type", "s_nation", MASK))


def _states(spark, folder, *years):
    schema, grouping = shaped("p_type | s_nation")
    return schema, grouped_states(tables.wide(spark, folder).filter(F.col("ship_year").isin(*years)), grouping)


@register("cube_merge", _years_sql(1996, 1997))
def cube_merge(spark, folder):
    schema, one = _states(spark, folder, 1996)
    return S.finalise(query.merge_cubes(one, _states(spark, folder, 1997)[1], schema), schema)


@register("cube_subtract", _years_sql(1996))
def cube_subtract(spark, folder):
    schema, both = _states(spark, folder, 1996, 1997)
    return S.finalise(query.subtract_cubes(both, _states(spark, folder, 1997)[1], schema, "n"), schema)


@register("brute_force_theta", f"SELECT p_type, l_returnflag, l_linestatus, star_mask, n FROM ({cube_sql('p_type | l_returnflag, l_linestatus')})")
def brute_force_theta(spark, folder):
    """Each segment's rows counted by a theta join instead of the cube."""
    schema, grouping = shaped("p_type | l_returnflag, l_linestatus", _COUNT)
    rows = tables.wide(spark, folder)
    cube = grouped_cube(rows, grouping)
    pairs = query.containing_segments(cube, schema, rows.select(*schema.columns))
    return pairs.groupBy(*(F.col(f"s.{c}").alias(c) for c in schema.columns), F.col(f"s.{MASK}").alias(MASK)).agg(F.count(F.lit(1)).alias("n"))


@register("asof_events", "SELECT event_id, user_id, lag(event_id) OVER w AS last_event, lag(event_type) OVER w AS last_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def asof_events(spark, folder):
    """Each event with its user's last earlier event."""
    earlier = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    rows = tables.read_table(spark, folder, "events")
    return rows.select("event_id", "user_id", F.last("event_id").over(earlier).alias("last_event"), F.last("event_type").over(earlier).alias("last_type"))


@register("key_render", "SELECT '(' || CASE WHEN star_mask & 4 > 0 THEN '*' ELSE p_type END || ', ' || CASE WHEN star_mask & 2 > 0 THEN '*' ELSE l_returnflag END || ', ' || CASE WHEN star_mask & 1 > 0 THEN '*' ELSE l_linestatus END || ')' AS key, n FROM (" + cube_sql("p_type | l_returnflag, l_linestatus", values=_COUNT_SQL) + ")")
def key_render(spark, folder):
    schema, grouping = shaped("p_type | l_returnflag, l_linestatus", _COUNT)
    return grouped_cube(tables.wide(spark, folder), grouping).select(S.render_key(schema).alias("key"), "n")


def _joined(hint: str) -> Query:
    return lambda spark, folder: tables.wide(spark, folder, hint).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("cents").alias("sum_cents"))


for _hint in ("merge", "shuffle_hash", "broadcast"):
    QUERIES[f"wide_{_hint}_join"] = _joined(_hint)
    ORACLE_SQL[f"wide_{_hint}_join"] = f"WITH {WIDE_SQL} SELECT o_orderpriority, {big('count(*)')} AS n, {big('sum(cents)')} AS sum_cents FROM wide GROUP BY 1"
