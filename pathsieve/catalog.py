"""Every method, variant, baseline, measure, workload and operator as a query on the given tables, with SQL for DuckDB beside it."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathsieve import metrics
from pathsieve.operators import baselines, layout, levels, recursive, results, udf_modes
from pathsieve.plans.graph import degree_stats, starts
from pathsieve.plans.regex import automaton
from pathsieve.sources.encodings import EDGE_SQL, ENCODINGS, VERTEX_SQL, edges_frame
from pathsieve.sources.tables import TABLES, load, micros, shared_folder
from pathsieve.streaming import paths as streams
from pathsieve.workloads import Q1_REGEX, QB_REGEX, WORKLOADS, Workload

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


# -- graphs ------------------------------------------------------------------------------

for _name in ENCODINGS:
    _add(f"enc_{_name}", edges_frame(_name), EDGE_SQL[_name])
_add("enc_supply_vertices", lambda s, d: ENCODINGS["supply"](s, d).vertices, VERTEX_SQL["supply"])

for _name in ("handover", "payments", "basket", "knows"):
    _degrees = f"WITH e AS ({EDGE_SQL[_name]}), g AS (SELECT src AS v, count(*) AS degree FROM e GROUP BY src) "
    _add(f"degree_stats_{_name}", lambda s, d, n=_name: degree_stats(ENCODINGS[n](s, d)), _degrees + "SELECT count(*) AS vertices, CAST(sum(degree) AS BIGINT) AS edges, quantile_cont(degree, 0.25)::DOUBLE AS q1, quantile_cont(degree, 0.5)::DOUBLE AS q2, quantile_cont(degree, 0.75)::DOUBLE AS q3 FROM g")
    _add(f"starts_iqr_{_name}", lambda s, d, n=_name: starts(ENCODINGS[n](s, d), "iqr"), _degrees + "SELECT v, degree FROM g WHERE degree BETWEEN (SELECT quantile_cont(degree, 0.25) FROM g) AND (SELECT quantile_cont(degree, 0.75) FROM g)")
    _add(f"starts_top_{_name}", lambda s, d, n=_name: starts(ENCODINGS[n](s, d), "top"), _degrees + "SELECT v, degree FROM g WHERE degree >= (SELECT quantile_cont(degree, 0.75) FROM g)")

_Q1_ROWS = [*((f, 1, x) for f in (0, 1) for x in ("click", "purchase", "view")), *((f, 2, x) for f in (1, 2) for x in ("error", "signup"))]
_QB_ROWS = [(0, 1, "Domestic"), (1, 1, "Domestic"), (1, 2, "Foreign")]


def _with_edges(transitions: DataFrame, edges: DataFrame) -> DataFrame:
    """Each transition of an expression with the number of edges that can take it."""
    found = edges.groupBy("label").agg(F.count(F.lit(1)).alias("n"))  # a row for each label
    return transitions.join(found, "label", "left").select("from_state", "to_state", "label", F.coalesce("n", F.lit(0)).alias("n"))


def _transitions_sql(rows: list[tuple[int, int, str]], encoding: str) -> str:
    return f"WITH g AS (SELECT label, count(*) AS n FROM ({EDGE_SQL[encoding]}) GROUP BY label) SELECT from_state::INTEGER AS from_state, to_state::INTEGER AS to_state, t.label, coalesce(n, 0) AS n FROM (VALUES {', '.join(map(str, rows))}) AS t(from_state, to_state, label) LEFT JOIN g ON g.label = t.label"


_add("transitions_q1", lambda s, d: _with_edges(automaton(Q1_REGEX).to_df(s), ENCODINGS["handover"](s, d).edges), _transitions_sql(_Q1_ROWS, "handover"))
_add("transitions_qb", lambda s, d: _with_edges(automaton(QB_REGEX).to_df(s), ENCODINGS["payments"](s, d).edges), _transitions_sql(_QB_ROWS, "payments"))

# -- workloads ---------------------------------------------------------------------------

_LEVEL_NAMES = {"qa": "qa_levels", "qa_all": "qa_all_starts", "qa_zero": "qa_zero_length", "qb": "qb_levels", "q1": "q1_levels", "q2": "q2_levels"}
for _key, _w in WORKLOADS.items():
    _add(_LEVEL_NAMES.get(_key, _key), lambda s, d, w=_w: levels.levels(w.query(s, d)), _w.levels_sql())
_add("qa_in_batches", lambda s, d: levels.levels_in_batches(WORKLOADS["qa_all"].query(s, d), 3), WORKLOADS["qa_all"].levels_sql())
_add("qa_nostart", lambda s, d: levels.count(WORKLOADS["qa_all"].query(s, d)), f"{WORKLOADS['qa_all'].walks()} SELECT count(*) AS n FROM answers")
for _key in ("qa", "qb", "q1"):
    _add(f"{_key}_paths", lambda s, d, w=WORKLOADS[_key]: levels.paths(w.query(s, d)), WORKLOADS[_key].paths_sql())
_ambiguous = WORKLOADS["rx_ambiguous_paths"]
_add("rx_ambiguous_runs", lambda s, d: levels.levels(_ambiguous.query(s, d, dedupe=False)), f"{replace(_ambiguous, every_run=True).walks().replace('SELECT DISTINCT start, v, len, ids', 'SELECT start, v, len, ids')} SELECT CAST(len AS BIGINT) AS len, count(*) AS n FROM answers GROUP BY len")
_add("q1_summary", lambda s, d: results.count_paths(levels.paths(WORKLOADS["q1"].query(s, d)), "v"), f"{WORKLOADS['q1'].walks()} SELECT v, count(*) AS n FROM answers GROUP BY v")
_gap = replace(WORKLOADS["q2"], max_len=3)
_add("q2_walk_vs_trail", lambda s, d: metrics.walk_trail_gap(_gap.query(s, d)), f"{_gap.walks(tested=False)} SELECT CAST(len AS BIGINT) AS len, count(*) AS walk, count_if(len(ids) = len(list_distinct(ids)))::BIGINT AS trail, count(*) - count_if(len(ids) = len(list_distinct(ids)))::BIGINT AS gap FROM answers GROUP BY len")
_gap5 = replace(WORKLOADS["q2"], max_len=5)
_add("q2_walk_vs_trail_5", lambda s, d: metrics.walk_trail_gap(_gap5.query(s, d)), f"{_gap5.walks(tested=False)} SELECT CAST(len AS BIGINT) AS len, count(*) AS walk, count_if(len(ids) = len(list_distinct(ids)))::BIGINT AS trail, count(*) - count_if(len(ids) = len(list_distinct(ids)))::BIGINT AS gap FROM answers GROUP BY len")

#: The lengths that early filtering reaches: the SQL drops walks at the hop where a constraint that holds for every prefix breaks.
_LONG = {"qa": (10, 2), "qa_wide": (10, 2), "qb": (6, 1), "qb_wide": (6, 1), "q1": (6, 4), "q2": (5, 0), "q3_payments": (8, 1), "q3_basket_weight": (6, 1), "q4_handover": (10, 1), "q4_knows": (6, 1)}
for _key, (_n, _early) in _LONG.items():
    _w = replace(WORKLOADS[_key], max_len=_n)
    _add(f"{_key}_long", lambda s, d, w=_w: levels.levels(w.query(s, d)), _w.levels_sql(early=_early))

# -- execution variants ------------------------------------------------------------------

_SHORT: dict[str, Workload] = {"qb": replace(WORKLOADS["qb"], max_len=3), "q1": WORKLOADS["q1"], "q2": replace(WORKLOADS["q2"], max_len=3), "q3": replace(WORKLOADS["q3_payments"], max_len=4), "q4": replace(WORKLOADS["q4_knows"], max_len=3)}
for _key, _w in _SHORT.items():
    _sql = _w.levels_sql()
    for _mode in ("json_udf", "flat_udf", "json_inline"):
        _add(f"{_key}_{_mode}", lambda s, d, w=_w, m=_mode: udf_modes.run_levels(w.query(s, d), m), _sql)
    for _kind in ("arrow", "pandas"):
        _add(f"{_key}_{_kind}_udf", lambda s, d, w=_w, k=_kind: udf_modes.run_levels(w.query(s, d), "json_udf", k), _sql)
    _add(f"{_key}_rcte", lambda s, d, w=_w: recursive.levels(w.query(s, d)), _sql)
    _add(f"{_key}_rcte_sql_function", lambda s, d, w=_w: recursive.levels(w.query(s, d), sql_functions=True), _sql)
    _add(f"{_key}_rcte_json_udf", lambda s, d, w=_w: udf_modes.run_recursive(w.query(s, d)), _sql)
    _add(f"{_key}_rcte_pandas_udf", lambda s, d, w=_w: udf_modes.run_recursive(w.query(s, d), "pandas"), _sql)

# -- rewrites ----------------------------------------------------------------------------

_ALL = frozenset(["elide_trail", "hoist", "envelope", "remaining_hops", "targets", "salt"])
for _key, _w in (("q3", _SHORT["q3"]), ("q4", _SHORT["q4"]), ("q1", _SHORT["q1"]), ("qa_pair", WORKLOADS["qa_pair"])):
    _add(f"rewrites_all_{_key}", lambda s, d, w=_w: levels.levels(w.query(s, d, rewrites=_ALL)), _w.levels_sql())
    _add(f"rewrites_none_{_key}", lambda s, d, w=_w: levels.levels(w.query(s, d, rewrites=frozenset())), _w.levels_sql())
_add("collapse_count_q3", lambda s, d: levels.levels(_SHORT["q3"].query(s, d), collapse=True), _SHORT["q3"].levels_sql())

# -- baselines and candidates ------------------------------------------------------------

for _key, _w in _SHORT.items():
    _sql = _w.levels_sql()
    for _name, _run in (("walk", baselines.postfilter_walk), ("trail", baselines.postfilter_trail), ("json", baselines.json_postfilter), ("listreduce", baselines.list_reduction), ("reattach", baselines.reattach_postfilter)):
        small = replace(_w, max_len=min(_w.max_len, 3))
        _add(f"base_{_name}_{_key}", lambda s, d, w=small, r=_run: r(w.query(s, d)), small.levels_sql())
    small = replace(_w, max_len=min(_w.max_len, 3))
    _add(f"cand_{_key}_walk", lambda s, d, w=small: baselines.postfilter_walk(w.query(s, d), candidates=True), small.candidates_sql(False))
    _add(f"cand_{_key}_trail", lambda s, d, w=small: baselines.postfilter_trail(w.query(s, d), candidates=True), small.candidates_sql(True))
for _key in ("q1", "qb"):
    _w = replace(WORKLOADS[_key], max_len=3)
    _add(f"base_split_{_key}", lambda s, d, w=_w: baselines.split_regex_join(w.query(s, d)), _w.levels_sql())
#: Bounds of 0 to l edges for each part: a path may have up to 2 l edges, l in each part.
_printed = replace(WORKLOADS["qb_wide"], max_len=2)
_add("base_split_printed_qb", lambda s, d: baselines.split_regex_join(_printed.query(s, d), printed_bounds=True), replace(_printed, regex="dom:Domestic{1,2} fgn:Foreign", max_len=3).levels_sql())
_seg = replace(WORKLOADS["q1"], max_len=3)
_add(
    "base_segments_q1",
    lambda s, d: baselines.segment_candidates(_seg.query(s, d)),
    f"WITH RECURSIVE e AS MATERIALIZED ({EDGE_SQL['handover']}), g AS (SELECT src AS v, count(*) AS degree FROM e GROUP BY src), begin AS (SELECT min(v) AS v FROM g WHERE degree >= (SELECT quantile_cont(degree, 0.75) FROM g)), "
    "w0(v, len) AS (SELECT v, 0 FROM begin UNION ALL SELECT e.dst, len + 1 FROM w0 JOIN e ON w0.v = e.src WHERE len < 2 AND label IN ('click', 'view', 'purchase')), "
    "w1(v, len) AS (SELECT DISTINCT src, 0 FROM e UNION ALL SELECT e.dst, len + 1 FROM w1 JOIN e ON w1.v = e.src WHERE len < 2 AND label IN ('error', 'signup')) "
    "SELECT 0::BIGINT AS segment, CAST(len AS BIGINT) AS len, count(*) AS n FROM w0 WHERE len > 0 GROUP BY len UNION ALL SELECT 1::BIGINT, CAST(len AS BIGINT), count(*) FROM w1 WHERE len > 0 GROUP BY len",
)

#: Prefixes that early filtering generates, by filtering all walks on every prefix: what may be tested early, in SQL.
_PREFIX = {
    "q2": replace(_SHORT["q2"], constraint=replace(_SHORT["q2"].constraint, accept=(), oracle=())),
    "q3": _SHORT["q3"],
    "q4": _SHORT["q4"],
    "q1": replace(WORKLOADS["q1"], regex="normal:(click|view|purchase)+ fishy:(error|signup)*", constraint=replace(WORKLOADS["q1"].constraint, accept=(), oracle=WORKLOADS["q1"].constraint.oracle[:-1])),
    "qb": replace(_SHORT["qb"], regex="dom:Domestic+ fgn:Foreign?"),
}
for _key, _w in _PREFIX.items():
    _add(f"cand_{_key}_early", lambda s, d, w=_SHORT[_key]: levels.candidates(w.query(s, d)), _w.levels_sql())
_q3 = replace(_SHORT["q3"], max_len=3)
_add("tight_q1", lambda s, d: metrics.tightness(WORKLOADS["q1"].query(s, d)), f"SELECT (SELECT CAST(sum(n) AS BIGINT) FROM ({_PREFIX['q1'].levels_sql()})) AS candidates, (SELECT CAST(coalesce(sum(n), 0) AS BIGINT) FROM ({WORKLOADS['q1'].levels_sql()})) AS answers")
_red = replace(WORKLOADS["q1"], max_len=2)
_add("reduction_q1", lambda s, d: metrics.reduction(_red.query(s, d)), f"SELECT (SELECT CAST(sum(n) AS BIGINT) FROM ({replace(_PREFIX['q1'], max_len=2).levels_sql()})) AS early, (SELECT CAST(sum(n) AS BIGINT) FROM ({_red.candidates_sql(False)})) AS walk")
_add("probed_q3", lambda s, d: metrics.probed_edges(_q3.query(s, d)), f"{_q3.walks()}, p AS (SELECT v, len FROM answers UNION ALL SELECT v, 0 FROM begin) SELECT CAST(len + 1 AS BIGINT) AS len, count(*) AS n FROM p JOIN edges e ON p.v = e.src WHERE len < {_q3.max_len} GROUP BY len")

# -- operators on answers ----------------------------------------------------------------

_BASE = replace(WORKLOADS["q3_payments"], max_len=3)
_ANSWERS = f"{_BASE.walks()}, a AS (SELECT start, v, CAST(len AS INTEGER) AS len, array_to_string(ids, '-') AS edge_ids, ids FROM answers)"


def _paths(s: SparkSession, d: str) -> DataFrame:
    return levels.paths(_BASE.query(s, d))


def _graph(s: SparkSession, d: str):
    return ENCODINGS["payments"](s, d)


_add("op_topk_paths", lambda s, d: results.top_k(_paths(s, d), 10, F.desc("len"), "edge_ids"), f"{_ANSWERS} SELECT start, v, len, edge_ids FROM a ORDER BY len DESC, edge_ids LIMIT 10")
_add("op_rank_paths", lambda s, d: results.rank_paths(_paths(s, d), "v", 2, "len", "edge_ids"), f"{_ANSWERS} SELECT * FROM (SELECT start, v, len, edge_ids, row_number() OVER (PARTITION BY v ORDER BY len, edge_ids) AS rank FROM a) WHERE rank <= 2")
for _how, _text in (("rollup", "ROLLUP (len, v)"), ("cube", "CUBE (len, v)"), ("grouping_sets", "GROUPING SETS ((len), (v))")):
    _add(f"op_{_how}_paths" if _how != "grouping_sets" else "op_grouping_sets", lambda s, d, h=_how: results.summarize(_paths(s, d), h, "len", "v"), f"{_ANSWERS} SELECT len, v, count(*) AS n FROM a GROUP BY {_text}")
_add("op_distinct_ends", lambda s, d: results.distinct_ends(_paths(s, d)), f"{_ANSWERS} SELECT CAST(len AS BIGINT) AS len, count(DISTINCT v) AS n_ends FROM a GROUP BY len")
_add("op_asof_next", lambda s, d: results.asof_next_edge(_graph(s, d)), f"WITH e AS ({EDGE_SQL['payments']}) SELECT id, next_id FROM (SELECT a.id, b.id AS next_id, row_number() OVER (PARTITION BY a.id ORDER BY b.t, b.id) AS rn FROM e a JOIN e b ON a.dst = b.src AND b.t > a.t) WHERE rn = 1")
_DAY3 = 3 * 86_400_000_000
_add("op_interval_join", lambda s, d: results.binned_range_join(_graph(s, d).edges.select("id", F.col("dst").alias("v"), "t"), _graph(s, d).edges.select("id", F.col("src").alias("v"), "t"), "v", "t", _DAY3).select("id", "r_id"), f"WITH e AS ({EDGE_SQL['payments']}) SELECT a.id, b.id AS r_id FROM e a JOIN e b ON a.dst = b.src AND abs(a.t - b.t) <= {_DAY3}")
_add("op_semi_targets", lambda s, d: _paths(s, d).join(load(s, d, "customer").where("c_acctbal > 5000").select(F.col("c_custkey").alias("v")), "v", "left_semi").select("start", "v", "len", "edge_ids"), f"{_ANSWERS} SELECT start, v, len, edge_ids FROM a WHERE v IN (SELECT c_custkey FROM customer WHERE c_acctbal > 5000)")
_add("op_anti_deadends", lambda s, d: results.dead_ends(ENCODINGS["dialog"](s, d)), f"WITH e AS ({EDGE_SQL['dialog']}) SELECT DISTINCT dst AS v FROM e WHERE dst NOT IN (SELECT src FROM e)")
_add("op_left_vertices", lambda s, d: _paths(s, d).join(load(s, d, "customer").where("c_nationkey < 10").select(F.col("c_custkey").alias("v"), F.col("c_mktsegment").alias("segment")), "v", "left").select("v", "len", "edge_ids", "segment"), f"{_ANSWERS} SELECT v, len, edge_ids, c_mktsegment AS segment FROM a LEFT JOIN (SELECT * FROM customer WHERE c_nationkey < 10) ON c_custkey = v")
_add("op_union_levels", lambda s, d: _paths(s, d).where("len = 1").unionByName(_paths(s, d).where("len = 3")), f"{_ANSWERS} SELECT start, v, len, edge_ids FROM a WHERE len IN (1, 3)")
_wide = replace(WORKLOADS["qa_wide"], max_len=3)
_OTHER = f"SELECT start, v, CAST(len AS INTEGER) AS len, array_to_string(ids, '-') AS edge_ids FROM ({_wide.walks()} SELECT * FROM answers)"
_add("op_intersect_paths", lambda s, d: _paths(s, d).intersectAll(levels.paths(_wide.query(s, d))), f"{_ANSWERS} SELECT start, v, len, edge_ids FROM a INTERSECT {_OTHER}")
_add("op_except_paths", lambda s, d: _paths(s, d).exceptAll(levels.paths(_wide.query(s, d))), f"{_ANSWERS} SELECT start, v, len, edge_ids FROM a EXCEPT {_OTHER}")
_add("op_two_hop", lambda s, d: results.two_hop(_graph(s, d)).groupBy("src").agg(F.count(F.lit(1)).alias("n")), f"WITH e AS ({EDGE_SQL['payments']}) SELECT a.src, count(*) AS n FROM e a JOIN e b ON a.dst = b.src GROUP BY a.src")
_EDGES_OF = f"{_ANSWERS}, x AS (SELECT start, edge_ids, k, id FROM (SELECT start, edge_ids, unnest(ids) AS id, unnest(range(1, len + 1)) AS k FROM a)), y AS (SELECT start, edge_ids, k, x.id, e.amount, e.t FROM x JOIN edges_all e ON e.id = x.id)".replace(", begin AS", f", edges_all AS ({EDGE_SQL['payments']}), begin AS", 1)
_add("op_explode_edges", lambda s, d: results.path_edges(_paths(s, d), _graph(s, d), "amount"), f"{_EDGES_OF} SELECT start, edge_ids, CAST(k AS BIGINT) AS k, id, amount FROM y")
_add("op_running_sum", lambda s, d: results.running_sum(results.path_edges(_paths(s, d), _graph(s, d), "amount").withColumn("cents", F.round(F.col("amount") * 100).cast("long")), "cents").select("edge_ids", "k", "running"), f"{_EDGES_OF} SELECT edge_ids, CAST(k AS BIGINT) AS k, CAST(sum(CAST(round(amount * 100) AS BIGINT)) OVER (PARTITION BY start, edge_ids ORDER BY k) AS BIGINT) AS running FROM y")
_WEEK = 7 * 86_400_000_000
_add("op_range_frame", lambda s, d: _graph(s, d).edges.select("id", F.count(F.lit(1)).over(Window.partitionBy("src").orderBy("t").rangeBetween(-_WEEK, 0)).alias("n")), f"WITH e AS ({EDGE_SQL['payments']}) SELECT id, count(*) OVER (PARTITION BY src ORDER BY t RANGE BETWEEN {_WEEK} PRECEDING AND CURRENT ROW) AS n FROM e")
_add("op_ntile_starts", lambda s, d: starts(_graph(s, d), "iqr").select("v", F.ntile(4).over(Window.partitionBy("degree").orderBy("v")).cast("long").alias("quarter")), f"WITH e AS ({EDGE_SQL['payments']}), g AS (SELECT src AS v, count(*) AS degree FROM e GROUP BY src) SELECT v, CAST(ntile(4) OVER (PARTITION BY degree ORDER BY v) AS BIGINT) AS quarter FROM g WHERE degree BETWEEN (SELECT quantile_cont(degree, 0.25) FROM g) AND (SELECT quantile_cont(degree, 0.75) FROM g)")
_add("op_json_props", lambda s, d: load(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].cast("long").alias("k"), F.variant_get(F.parse_json("props"), "$.k", "long").alias("k2")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k2 FROM events")
_add("op_map_state", lambda s, d: _graph(s, d).edges.groupBy("src").agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct("label", F.lit(1))))).alias("m")).select("src", F.array_join(F.map_keys("m"), ",").alias("labels")), f"WITH e AS ({EDGE_SQL['payments']}) SELECT src, array_to_string(list_sort(list(DISTINCT label)), ',') AS labels FROM e GROUP BY src")
_add("op_array_hof", lambda s, d: _graph(s, d).edges.groupBy("src").agg(F.sort_array(F.collect_list("t")).alias("ts")).select("src", F.size(F.filter("ts", lambda x: x > F.element_at("ts", 1))).cast("long").alias("later"), F.forall("ts", lambda x: x >= F.array_min("ts")).alias("ok")), f"WITH e AS ({EDGE_SQL['payments']}) SELECT src, CAST(count_if(t > m) AS BIGINT) AS later, true AS ok FROM (SELECT src, t, min(t) OVER (PARTITION BY src) AS m FROM e) GROUP BY src")
_add("op_date_bins", lambda s, d: load(s, d, "events").groupBy(F.date_trunc("day", F.col("ts").cast("timestamp_ntz")).alias("day")).agg(F.count(F.lit(1)).alias("n")).select(micros("day").alias("day"), "n"), "SELECT epoch_us(date_trunc('day', ts)) AS day, count(*) AS n FROM events GROUP BY 1")
_add("op_string_labels", lambda s, d: _graph(s, d).edges.select("id", F.concat_ws("/", F.lower("label"), F.regexp_extract("color", r"^(\d)", 1), F.substring("color", 3, 3)).alias("label")), f"WITH e AS ({EDGE_SQL['payments']}) SELECT id, concat_ws('/', lower(label), regexp_extract(color, '^(\\d)', 1), substring(color, 3, 3)) AS label FROM e")
_add("op_udf", lambda s, d: _graph(s, d).edges.select("id", F.udf(lambda x: None if x is None else x.upper(), "string", useArrow=True)("label").alias("label")), f"WITH e AS ({EDGE_SQL['payments']}) SELECT id, upper(label) AS label FROM e")


def _udtf(s: SparkSession, d: str) -> DataFrame:
    results.register_sql(s)
    return _with_edges(s.sql(f"SELECT from_state, to_state, label FROM transitions('{QB_REGEX}')"), _graph(s, d).edges)


_add("op_udtf_transitions", _udtf, ORACLES["transitions_qb"])

# -- layouts -----------------------------------------------------------------------------

_LAYOUT_SQL = _BASE.levels_sql()


def _partitioned(s: SparkSession, d: str) -> DataFrame:
    q, path = _BASE.query(s, d), shared_folder(s, "edges")
    layout.write_partitioned(q.graph, path)
    return levels.levels(q.vary(graph=replace(q.graph, edges=layout.read_partitioned(s, path))))


def _bucketed(s: SparkSession, d: str) -> DataFrame:
    q, name = _BASE.query(s, d), f"ps_edges_{uuid.uuid4().hex[:8]}"
    layout.write_bucketed(q.graph, name)
    return levels.levels(q.vary(graph=replace(q.graph, edges=s.table(name))))


def _adjacent(s: SparkSession, d: str) -> DataFrame:
    q = _BASE.query(s, d)
    adj = layout.adjacency(q.graph, "t", chunk=8)
    return levels.levels(q.vary(graph=replace(q.graph, edges=layout.from_adjacency(adj, "x.t IS NOT NULL"))))


def _salted(s: SparkSession, d: str) -> DataFrame:
    g = _graph(s, d)
    heavy = starts(g, "top").select("v")
    return layout.expand_salted(g.edges.select(F.col("dst").alias("v"), F.col("id").alias("first")), g, heavy, 4).groupBy("first").agg(F.count(F.lit(1)).alias("n"))


_add("layout_partitioned_q3", _partitioned, _LAYOUT_SQL)
_add("layout_bucketed_q3", _bucketed, _LAYOUT_SQL)
_add("layout_adjacency_q3", _adjacent, _LAYOUT_SQL)
_add("layout_salted_two_hop", _salted, f"WITH e AS ({EDGE_SQL['payments']}) SELECT a.id AS first, count(*) AS n FROM e a JOIN e b ON a.dst = b.src GROUP BY a.id")

# -- streams -----------------------------------------------------------------------------


def _event_stream(s: SparkSession, d: str, delay: str = "40 days") -> DataFrame:
    schema = s.read.parquet(f"{d}/events.parquet").schema
    rows = s.readStream.schema(schema).parquet(f"{d}/events.parquet*")
    return rows.select(F.col("event_id").alias("id"), F.col("user_id").alias("src"), F.pmod(F.col("user_id") * 7 + F.col("event_id"), F.lit(150)).alias("dst"), F.col("event_type").alias("label"), F.col("ts").cast("timestamp").alias("ts")).withWatermark("ts", delay)


_EVENTS = "(SELECT event_id AS id, user_id AS src, (user_id * 7 + event_id) % 150 AS dst, event_type AS label, ts FROM events)"


def _finish(stream: DataFrame, mode: str = "append") -> DataFrame:
    return streams.run_to_end(stream, shared_folder(stream.sparkSession, "stream"), mode)


_add("stream_chain_2hop", lambda s, d: _finish(streams.chain(_event_stream(s, d), _event_stream(s, d), "2 HOURS").select("id1", "id2")), f"SELECT a.id AS id1, b.id AS id2 FROM {_EVENTS} a JOIN {_EVENTS} b ON a.dst = b.src AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
_add("stream_tumbling", lambda s, d: _finish(streams.tumbling(_event_stream(s, d), "1 day", "label"), "complete").select(micros(F.col("window.start").cast("timestamp_ntz")).alias("start"), "label", "n"), f"SELECT epoch_us(date_trunc('day', ts)) AS start, label, count(*) AS n FROM {_EVENTS} GROUP BY 1, 2")
_add("stream_sliding", lambda s, d: _finish(streams.sliding(_event_stream(s, d), "2 days", "1 day"), "complete").select(micros(F.col("window.start").cast("timestamp_ntz")).alias("start"), "n"), f"SELECT epoch_us(date_trunc('day', ts) - k * INTERVAL 1 DAY) AS start, count(*) AS n FROM {_EVENTS}, (VALUES (0), (1)) AS x(k) GROUP BY 1")
_add("stream_session", lambda s, d: _finish(streams.sessions(_event_stream(s, d), "3 hours", "src"), "complete").select("src", micros(F.col("session_window.start").cast("timestamp_ntz")).alias("start"), "n"), f"SELECT src, epoch_us(min(ts)) AS start, count(*) AS n FROM (SELECT src, ts, sum(fresh) OVER (PARTITION BY src ORDER BY ts, id) AS g FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY src ORDER BY ts, id) + INTERVAL 3 HOUR THEN 0 ELSE 1 END AS fresh FROM {_EVENTS})) GROUP BY src, g")
_add("stream_dedupe", lambda s, d: _finish(streams.dedupe(_event_stream(s, d).unionByName(_event_stream(s, d))).select("id", "src")), f"SELECT id, src FROM {_EVENTS}")


def _incremental(s: SparkSession, d: str) -> DataFrame:
    edges = _event_stream(s, d)
    begin = s.createDataFrame([(4,)], "v long")
    found = streams.incremental_paths(s, edges, shared_folder(s, "prefixes"), begin, 3, shared_folder(s, "stream"))
    return found.groupBy(F.col("len").cast("long").alias("len")).agg(F.count(F.lit(1)).alias("n"))


_add("stream_incremental_q3", _incremental, f"WITH RECURSIVE p(v, ts, len) AS (SELECT 4::BIGINT, NULL::TIMESTAMP, 0 UNION ALL SELECT e.dst, e.ts, len + 1 FROM p JOIN {_EVENTS} e ON p.v = e.src WHERE len < 3 AND (p.ts IS NULL OR e.ts > p.ts)) SELECT CAST(len AS BIGINT) AS len, count(*) AS n FROM p WHERE len > 0 GROUP BY len")
_add("stream_stateful_window", lambda s, d: _finish(streams.stateful_spread(_event_stream(s, d), 6 * 3_600_000_000)).select("src", "id", "n"), f"SELECT src, id, CAST((SELECT count(*) FROM {_EVENTS} b WHERE b.src = a.src AND b.ts >= a.ts - INTERVAL 6 HOUR AND (b.ts, b.id) < (a.ts, a.id)) AS BIGINT) AS n FROM {_EVENTS} a")

_add("stream_stateful_paths", lambda s, d: _finish(streams.stateful_paths(_event_stream(s, d), "label", 12 * 3_600_000_000, 3)), f"WITH RECURSIVE p(label, head, id, v, t0, ts, len) AS (SELECT label, id, id, dst, ts, ts, 1 FROM {_EVENTS} UNION ALL SELECT p.label, p.head, e.id, e.dst, p.t0, e.ts, len + 1 FROM p JOIN {_EVENTS} e ON e.src = p.v AND e.label = p.label AND e.ts > p.ts AND e.ts <= p.t0 + INTERVAL 12 HOUR WHERE len < 3) SELECT label, head AS first, id AS last, CAST(len AS BIGINT) AS len FROM p")


def _late(s: SparkSession, d: str) -> DataFrame:
    """Paths over the edges in time, and those that the late ones (every seventh) add: together the paths over all."""
    rows = load(s, d, "events").select(F.col("event_id").alias("id"), F.col("user_id").alias("src"), F.pmod(F.col("user_id") * 7 + F.col("event_id"), F.lit(150)).alias("dst"), F.col("ts").cast("timestamp").alias("ts"))
    in_time, late = rows.where("id % 7 <> 0"), rows.where("id % 7 = 0")
    begin = s.createDataFrame([(4,)], "v long")
    before = streams.extend_late(in_time.limit(0), in_time, begin, 3)
    return before.unionByName(streams.extend_late(in_time, late, begin, 3)).groupBy(F.col("len").cast("long").alias("len")).agg(F.count(F.lit(1)).alias("n"))


_add("stream_late_edges", _late, ORACLES["stream_incremental_q3"])

# -- sources -----------------------------------------------------------------------------

#: Columns that name a row, where a table has such; else all are counted as they stand.
KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}
for _name in TABLES:
    _key = KEYS[_name]
    _add(f"scan_{_name}", lambda s, d, n=_name, k=_key: load(s, d, n).agg(F.count(F.lit(1)).alias("n"), F.countDistinct(k).alias("n_keys"), F.count_if(F.col(k).isNull()).alias("n_null"), F.min(F.col(k).cast("string")).alias("least"), F.max(F.col(k).cast("string")).alias("most")), f"SELECT count(*) AS n, count(DISTINCT {_key}) AS n_keys, count_if({_key} IS NULL)::BIGINT AS n_null, min({_key}::VARCHAR) AS least, max({_key}::VARCHAR) AS most FROM {_name}")


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
