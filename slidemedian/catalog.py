"""Driver queries of the engine and their SQL.

``QUERIES`` maps a key to a function of (spark, folder); ``ORACLE_SQL`` gives
the same rows in DuckDB. The relational surroundings are in
``catalog_relational``.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import catalog_relational as relational
from . import measures, sqlapi, verify
from .operators import baselines, filters, reduction, sorting
from .plans.positions import global_positions
from .plans.store import fresh_path
from .plans.tiles import neighbour_summaries
from .sources import generators
from .sources.tables import EVENTS_ORDER, LINEITEM_ORDER, load
from .streaming import sliding

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

EVENTS, LINEITEM = list(EVENTS_ORDER), list(LINEITEM_ORDER)


def query(name: str, sql: str | None = None):
    def keep(run: Query) -> Query:
        QUERIES[name] = run
        if sql is not None:
            ORACLE_SQL[name] = sql
        return run

    return keep


def framed(table: str, item: str, k: int, order: list[str], part: tuple[str, ...] = (), show: tuple[str, ...] = (), out: str = "med", align: str = "leading", where: str = "true", full: bool = True, source: str | None = None) -> str:
    """SQL over a frame of k rows; ``item`` is an aggregate with {w} for its window."""
    before = {"leading": 0, "trailing": k - 1, "centered": k // 2}[align]
    by = f"PARTITION BY {', '.join(part)} " if part else ""
    frame = f"ROWS BETWEEN {before} PRECEDING AND {k - 1 - before} FOLLOWING"
    columns = "".join(f"{c}, " for c in (*part, *show))
    kept = f"WHERE held = {k} AND {where}" if full else f"WHERE {where}"
    return f"""SELECT {columns}pos, {out} FROM (
  SELECT {columns}CAST(row_number() OVER s - 1 AS BIGINT) AS pos, count(*) OVER w AS held, {item.format(w='OVER w')} AS {out}
  FROM {source or table} WINDOW s AS ({by}ORDER BY {', '.join(order)}), w AS ({by}ORDER BY {', '.join(order)} {frame})) {kept}"""


def item_sql(value: str, rank: int) -> str:
    return f"list_sort(array_agg({value}) {{w}})[{rank + 1}]"


def median_query(name: str, table: str, value: str, k: int, order: list[str], part: tuple[str, ...] = (), show: tuple[str, ...] = (), **options) -> None:
    """A query on a median, and its SQL."""
    exact = options.pop("exact_item", False)
    sql = framed(table, item_sql(value, k // 2) if exact else f"median({value}) {{w}}", k, order, part, show, align=options.get("align", "leading"))

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = filters.sliding_median(load(spark, sf_dir, table), value, k, order, list(part), **options)
        return found.select(*part, *show, "pos", "med")

    query(name, sql)(run)


median_query("median_events_global", "events", "value", 25, EVENTS, show=("event_id",))
median_query("median_events_per_user", "events", "value", 5, EVENTS, ("user_id",), ("event_id",))
median_query("median_events_per_type", "events", "value", 101, EVENTS, ("event_type",), ("event_id",))
for _k in (25, 1001, 20001):
    median_query(f"median_lineitem_price_k{_k}", "lineitem", "l_extendedprice", _k, LINEITEM)
median_query("median_lineitem_per_supp", "lineitem", "l_extendedprice", 51, LINEITEM, ("l_suppkey",))
median_query("median_lineitem_per_part", "lineitem", "l_extendedprice", 15, LINEITEM, ("l_partkey",))
median_query("median_quantity_ties", "lineitem", "l_quantity", 9, LINEITEM)
median_query("median_orders_per_cust", "orders", "o_totalprice", 7, ["o_orderdate", "o_orderkey"], ("o_custkey",), ("o_orderkey",))
median_query("median_docs_len", "documents", "n_chars", 11, ["doc_id"], show=("doc_id",), exact_item=True)
median_query("median_docs_len_by_lang", "documents", "n_chars", 11, ["doc_id"], ("lang",), ("doc_id",), exact_item=True)
median_query("majority_labels", "labels", "quality", 5, ["doc_id"], show=("doc_id",), exact_item=True)
median_query("median_centered", "events", "value", 25, EVENTS, show=("event_id",), align="centered")
median_query("median_trailing", "events", "value", 25, EVENTS, show=("event_id",), align="trailing")
median_query("median_wide_route", "events", "value", 1001, EVENTS, show=("event_id",), route="wide")
median_query("median_scalar_kernel", "events", "value", 101, EVENTS, ("event_type",), ("event_id",), kernel="scalar")
median_query("median_rank_ties", "lineitem", "l_quantity", 101, LINEITEM, ("l_returnflag",), kernel="scalar", ties="rank", route="short_series")
median_query("median_radix_sorter", "lineitem", "l_quantity", 101, LINEITEM, sorter="radix")
for _even in ("mean", "lower", "upper"):
    _item = "round(median(value) {w}, 6)" if _even == "mean" else item_sql("value", 4 if _even == "lower" else 5)

    def _even_run(spark, sf_dir, even=_even):
        found = filters.sliding_median(load(spark, sf_dir, "events"), "value", 10, EVENTS, even=even)
        return found.select("event_id", "pos", (F.round("med", 6) if even == "mean" else F.col("med")).alias("med"))

    query(f"median_even_{_even}", framed("events", _item, 10, EVENTS, show=("event_id",)))(_even_run)


@query("median_conv_len", framed("", "list_sort(array_agg(len) {w})[2]", 3, ["turn"], ("conv_id",), ("turn",), source="(SELECT *, length(text) AS len FROM conversations)"))
def median_conv_len(spark, sf_dir):
    rows = load(spark, sf_dir, "conversations").select("conv_id", "turn", F.length("text").cast("long").alias("len"))
    return filters.sliding_median(rows, "len", 3, "turn", "conv_id").select("conv_id", "turn", "pos", "med")


@query("median_edges_partial", framed("events", "round(median(value) {w}, 6)", 9, EVENTS, ("user_id",), ("event_id",), align="trailing", full=False))
def median_edges_partial(spark, sf_dir):
    found = filters.sliding_median(load(spark, sf_dir, "events"), "value", 9, EVENTS, "user_id", align="trailing", edges="partial", even="mean", route="short_series")
    return found.select("user_id", "event_id", "pos", F.round("med", 6).alias("med"))


@query("median_edges_keep", f"SELECT event_id, pos, CASE WHEN held = 9 THEN med ELSE value END AS med FROM (SELECT event_id, value, row_number() OVER s - 1 AS pos, count(*) OVER w AS held, median(value) OVER w AS med FROM events WINDOW s AS (ORDER BY ts, event_id), w AS (ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING))")
def median_edges_keep(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events"), "value", 9, EVENTS, align="centered", edges="keep").select("event_id", "pos", "med")


@query("median_edges_pad", "SELECT event_id, row_number() OVER (ORDER BY ts, event_id) - 1 AS pos, list_sort(list_concat(array_agg(value) OVER w, list_transform(range(9 - count(*) OVER w), lambda i: 0.0)))[5] AS med FROM events WINDOW w AS (ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING)")
def median_edges_pad(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events"), "value", 9, EVENTS, align="centered", edges="pad", constant=0.0).select("event_id", "pos", "med")


@query("median_edges_reflect", "WITH p AS (SELECT event_id, value, row_number() OVER (ORDER BY ts, event_id) - 1 AS pos FROM events), n AS (SELECT count(*) AS n FROM events), e AS (SELECT pos, value FROM p UNION ALL SELECT -pos - 1, value FROM p WHERE pos < 4 UNION ALL SELECT 2 * n - 1 - pos, value FROM p, n WHERE pos >= n - 4), w AS (SELECT pos, median(value) OVER (ORDER BY pos ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING) AS med FROM e) SELECT event_id, pos, med FROM w JOIN p USING (pos)")
def median_edges_reflect(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events"), "value", 9, EVENTS, align="centered", edges="reflect").select("event_id", "pos", "med")


for _edges, _align in (("partial", "trailing"), ("keep", "centered"), ("pad", "centered"), ("reflect", "centered")):

    def _edges_run(spark, sf_dir, edges=_edges, align=_align):
        found = filters.sliding_median(load(spark, sf_dir, "events"), "value", 9, EVENTS, align=align, edges=edges, constant=0.0, route="blocks")
        return found.select("event_id", "pos", F.round("med", 6).alias("med"))

    _whole = framed("events", "round(median(value) {w}, 6)", 9, EVENTS, show=("event_id",), align="trailing", full=False)
    query(f"median_edges_{_edges}_blocks", _whole if _edges == "partial" else f"SELECT event_id, pos, round(med, 6) AS med FROM ({ORACLE_SQL[f'median_edges_{_edges}']})")(_edges_run)


@query("median_stride", framed("events", "median(value) {w}", 25, EVENTS, show=("event_id",), where="pos % 10 = 0"))
def median_stride(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events"), "value", 25, EVENTS, stride=10).select("event_id", "pos", "med")


@query("median_date", framed("", "list_sort(array_agg(d) {w})[6]", 11, ["o_orderkey"], show=("o_orderkey",), source="(SELECT o_orderkey, CAST(o_orderdate AS DATE) AS d FROM orders)"))
def median_date(spark, sf_dir):
    rows = load(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").cast("date").alias("d"))
    return filters.sliding_median(rows, "d", 11, "o_orderkey").select("o_orderkey", "pos", "med")


@query("median_decimal", framed("", "list_sort(array_agg(d) {w})[6]", 11, LINEITEM, source="(SELECT *, CAST(l_extendedprice AS DECIMAL(12,2)) AS d FROM lineitem)"))
def median_decimal(spark, sf_dir):
    rows = load(spark, sf_dir, "lineitem").withColumn("d", F.col("l_extendedprice").cast("decimal(12,2)"))
    return filters.sliding_median(rows, "d", 11, LINEITEM).select("pos", "med")


@query("median_interval", "SELECT user_id, event_id, pos, epoch_us(med) AS med FROM (" + framed("", "list_sort(array_agg(gap) {w})[3]", 5, EVENTS, ("user_id",), ("event_id",), source="(SELECT * FROM (SELECT user_id, event_id, ts, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap FROM events) WHERE gap IS NOT NULL)") + ")")
def median_interval(spark, sf_dir):
    from pyspark.sql import Window

    gap = F.col("ts") - F.lag("ts").over(Window.partitionBy("user_id").orderBy(*EVENTS))
    rows = load(spark, sf_dir, "events").select("user_id", "event_id", "ts", gap.alias("gap"))
    found = filters.sliding_median(rows, "gap", 5, EVENTS, "user_id", nulls="drop")
    return found.select("user_id", "event_id", "pos", F.expr("unix_micros(TIMESTAMP '1970-01-01 00:00:00 UTC' + med)").alias("med"))


@query("median_string", framed("", "list_sort(array_agg(event_type) {w})[4]", 7, EVENTS, show=("event_id",), source="events"))
def median_string(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events"), "event_type", 7, EVENTS, even="lower").select("event_id", "pos", "med")


@query("median_k1", "SELECT event_id, row_number() OVER (ORDER BY ts, event_id) - 1 AS pos, value AS med FROM events")
def median_k1(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events"), "value", 1, EVENTS).select("event_id", "pos", "med")


@query("median_k_eq_n", "SELECT CAST(0 AS BIGINT) AS pos, median(s_acctbal) AS med FROM supplier")
def median_k_eq_n(spark, sf_dir):
    rows = load(spark, sf_dir, "supplier")
    return filters.sliding_median(rows, "s_acctbal", rows.count(), "s_suppkey").select("pos", "med")


@query("median_k_gt_n", "SELECT CAST(0 AS BIGINT) AS pos, s_acctbal AS med FROM supplier WHERE false")
def median_k_gt_n(spark, sf_dir):
    rows = load(spark, sf_dir, "supplier")
    return filters.sliding_median(rows, "s_acctbal", rows.count() + 1, "s_suppkey", even="lower").select("pos", "med")


@query("median_json_value", framed("", "list_sort(array_agg(j) {w})[13]", 25, EVENTS, show=("event_id",), source="(SELECT *, CAST(json_extract_string(props, '$.k') AS BIGINT) AS j FROM events)"))
def median_json_value(spark, sf_dir):
    rows = load(spark, sf_dir, "events").withColumn("j", F.get_json_object("props", "$.k").cast("long"))
    return filters.sliding_median(rows, "j", 25, EVENTS).select("event_id", "pos", "med")


@query("filter_series_key", framed("events", "median(value) {w}", 5, EVENTS, ("user_id",), ("event_id",), where="user_id < 10"))
def filter_series_key(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events").where("user_id < 10"), "value", 5, EVENTS, "user_id").select("user_id", "event_id", "pos", "med")


@query("filter_then_median", framed("", "median(value) {w}", 5, EVENTS, ("user_id",), ("event_id",), source="(SELECT * FROM events WHERE event_type = 'purchase')"))
def filter_then_median(spark, sf_dir):
    return filters.sliding_median(load(spark, sf_dir, "events"), "value", 5, EVENTS, "user_id", pre_filter=F.col("event_type") == "purchase").select("user_id", "event_id", "pos", "med")


@query("median_out_range", framed("events", "median(value) {w}", 25, EVENTS, show=("event_id",), where="pos BETWEEN 1000 AND 1999"))
def median_out_range(spark, sf_dir):
    return filters.median_in_range(load(spark, sf_dir, "events"), "value", 25, EVENTS, 1000, 2000).select("event_id", "pos", "med")


for _name, _rank in (("min", 0), ("max", 20), ("r3", 3)):

    def _stat_run(spark, sf_dir, rank=_rank):
        return filters.sliding_order_stat(load(spark, sf_dir, "events"), "value", 21, rank, EVENTS).select("event_id", "pos", "stat")

    query(f"order_stat_{_name}", framed("events", item_sql("value", _rank), 21, EVENTS, show=("event_id",), out="stat"))(_stat_run)


@query("quantile_p90", framed("events", item_sql("value", 18), 21, EVENTS, show=("event_id",), out="p90"))
def quantile_p90(spark, sf_dir):
    return filters.sliding_quantile(load(spark, sf_dir, "events"), "value", 21, 0.9, EVENTS, out="p90").select("event_id", "pos", "p90")


@query("quantile_interpolated", framed("events", "round(quantile_cont(value, 0.33) {w}, 6)", 21, EVENTS, show=("event_id",), out="p33"))
def quantile_interpolated(spark, sf_dir):
    found = filters.sliding_quantile(load(spark, sf_dir, "events"), "value", 21, 0.33, EVENTS, out="p33", interpolate=True)
    return found.select("event_id", "pos", F.round("p33", 6).alias("p33"))


@query("multi_quantile", "SELECT event_id, pos, l[3] AS p10, l[11] AS p50, l[19] AS p90 FROM (" + framed("events", "list_sort(array_agg(value) {w})", 21, EVENTS, show=("event_id",), out="l") + ")")
def multi_quantile(spark, sf_dir):
    return filters.multi_quantile(load(spark, sf_dir, "events"), "value", 21, {"p10": 0.1, "p50": 0.5, "p90": 0.9}, EVENTS).select("event_id", "pos", "p10", "p50", "p90")


@query("sliding_iqr", "SELECT event_id, pos, round(l[16] - l[6], 6) AS iqr FROM (" + framed("events", "list_sort(array_agg(value) {w})", 21, EVENTS, show=("event_id",), out="l") + ")")
def sliding_iqr(spark, sf_dir):
    return filters.sliding_iqr(load(spark, sf_dir, "events"), "value", 21, EVENTS).select("event_id", "pos", F.round("iqr", 6).alias("iqr"))


_HAMPEL = "WITH f AS (SELECT user_id, event_id, value, count(*) OVER w AS held, array_agg(value) OVER w AS l, median(value) OVER w AS med FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING)), m AS (SELECT user_id, event_id, value, med, list_sort(list_transform(l, lambda x: abs(x - med)))[5] AS mad FROM f WHERE held = 9) "


@query("hampel_flags", _HAMPEL + "SELECT user_id, event_id, round(med, 6) AS med, round(mad, 6) AS mad, abs(value - med) > 3.0 * mad AS outlier FROM m")
def hampel_flags(spark, sf_dir):
    found = filters.hampel(load(spark, sf_dir, "events"), "value", 9, EVENTS, "user_id")
    return found.select("user_id", "event_id", F.round("med", 6).alias("med"), F.round("mad", 6).alias("mad"), "outlier")


@query("hampel_two_pass", "WITH f AS (SELECT user_id, event_id, ts, value, count(*) OVER w AS held, median(value) OVER w AS med FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING)), g AS (SELECT *, abs(value - med) AS gap FROM f WHERE held = 9), m AS (SELECT user_id, event_id, med, gap, count(*) OVER w AS held, median(gap) OVER w AS mad FROM g WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING)) SELECT user_id, event_id, round(med, 6) AS med, round(mad, 6) AS mad, gap > 3.0 * mad AS outlier FROM m WHERE held = 9")
def hampel_two_pass(spark, sf_dir):
    found = filters.hampel_fast(load(spark, sf_dir, "events"), "value", 9, EVENTS, "user_id")
    return found.select("user_id", "event_id", F.round("med", 6).alias("med"), F.round("mad", 6).alias("mad"), "outlier")


@query("despike", _HAMPEL + "SELECT user_id, event_id, CASE WHEN abs(value - med) > 3.0 * mad THEN med ELSE value END AS clean FROM m")
def despike(spark, sf_dir):
    return filters.despike(load(spark, sf_dir, "events"), "value", 9, EVENTS, "user_id").select("user_id", "event_id", "clean")


def _sorted_sql(table: str, value: str, k: int, order: list[str]) -> str:
    return f"WITH p AS (SELECT {value}, row_number() OVER (ORDER BY {', '.join(order)}) - 1 AS pos FROM {table}) SELECT pos // {k} AS blk, row_number() OVER (PARTITION BY pos // {k} ORDER BY {value}, pos) - 1 AS rnk, pos % {k} AS off, {value} FROM p"


for _k in (25, 1001):

    def _sort_run(spark, sf_dir, k=_k):
        return sorting.piecewise_sort(load(spark, sf_dir, "lineitem"), "l_extendedprice", k, LINEITEM)

    query(f"piecewise_sort_k{_k}", _sorted_sql("lineitem", "l_extendedprice", _k, LINEITEM))(_sort_run)
for _sorter in sorting.SORTERS[1:]:

    def _sorter_run(spark, sf_dir, sorter=_sorter):
        return sorting.piecewise_sort(load(spark, sf_dir, "lineitem"), "l_quantity", 101, LINEITEM, sorter=sorter)

    query(f"piecewise_sort_{_sorter}", _sorted_sql("lineitem", "l_quantity", 101, LINEITEM))(_sorter_run)


@query("block_permutation", "SELECT blk, array_to_string(list(off ORDER BY rnk), ',') AS permutation FROM (" + _sorted_sql("events", "value", 16, EVENTS) + ") GROUP BY blk")
def block_permutation(spark, sf_dir):
    held = sorting.block_permutations(load(spark, sf_dir, "events"), "value", 16, EVENTS)
    return held.select("blk", F.array_join(F.col("order").cast("array<string>"), ",").alias("permutation"))


@query("inverse_permutation", "SELECT blk, array_to_string(list(rnk ORDER BY off), ',') AS permutation FROM (" + _sorted_sql("events", "value", 16, EVENTS) + ") GROUP BY blk")
def inverse_permutation(spark, sf_dir):
    held = sorting.block_permutations(load(spark, sf_dir, "events"), "value", 16, EVENTS, inverse=True)
    return held.select("blk", F.array_join(F.col("order").cast("array<string>"), ",").alias("permutation"))


@query("medians_from_sorted", framed("lineitem", "median(l_extendedprice) {w}", 101, LINEITEM))
def medians_from_sorted(spark, sf_dir):
    blocks = sorting.piecewise_sort(load(spark, sf_dir, "lineitem"), "l_extendedprice", 101, LINEITEM, sorter="engine")
    return sorting.medians_from_sorted_blocks(blocks, "l_extendedprice", 101)


for _name, _m, _isolate in (("isolated", 8, True), ("concat", 51, False)):

    def _reduce_run(spark, sf_dir, m=_m, isolate=_isolate):
        return reduction.sort_blocks_by_median(load(spark, sf_dir, "lineitem"), "l_extendedprice", m, LINEITEM, isolate=isolate)

    query(f"sort_by_filter_{_name}", f"SELECT blk, rnk, l_extendedprice FROM ({_sorted_sql('lineitem', 'l_extendedprice', _m, LINEITEM)})")(_reduce_run)

for _method in (*baselines.METHODS, "engine_percentile", "collect_sort", "self_join"):

    def _baseline_run(spark, sf_dir, method=_method):
        return baselines.run(load(spark, sf_dir, "events"), method, "value", 5, EVENTS, "user_id").select("user_id", "event_id", "pos", "med")

    query(f"baseline_{_method}", framed("events", "median(value) {w}", 5, EVENTS, ("user_id",), ("event_id",)))(_baseline_run)


@query("baseline_long_series_double_heap", framed("lineitem", "median(l_extendedprice) {w}", 101, LINEITEM))
def baseline_long_series_double_heap(spark, sf_dir):
    return baselines.run(load(spark, sf_dir, "lineitem"), "double_heap", "l_extendedprice", 101, LINEITEM).select("pos", "med")


@query("baseline_approx")
def baseline_approx(spark, sf_dir):
    return baselines.run(load(spark, sf_dir, "events"), "engine_approx", "value", 101, EVENTS, "event_type").select("event_type", "event_id", "pos", "med")


@query("rank_error_approx")
def rank_error_approx(spark, sf_dir):
    rows = load(spark, sf_dir, "events")
    approx = baselines.run(rows, "engine_approx", "value", 101, EVENTS, "event_type")
    return measures.rank_error(rows, approx, "value", 101, EVENTS, ["event_type"])


@query("moving_average_global", framed("events", "round(avg(value) {w}, 6)", 25, EVENTS, show=("event_id",), out="avg", align="centered"))
def moving_average_global(spark, sf_dir):
    return baselines.moving_average(load(spark, sf_dir, "events"), "value", 25, EVENTS, align="centered").select("event_id", "pos", F.round("avg", 6).alias("avg"))


@query("moving_average_k25", framed("events", "round(avg(value) {w}, 6)", 25, EVENTS, ("user_id",), ("event_id",), out="avg"))
def moving_average_k25(spark, sf_dir):
    return baselines.moving_average(load(spark, sf_dir, "events"), "value", 25, EVENTS, "user_id").select("user_id", "event_id", "pos", F.round("avg", 6).alias("avg"))


def _mix(pos: str, seed: int) -> str:
    return generators.mix_text(pos, seed, "//")


@query(
    "recovery_quality",
    f"WITH p AS (SELECT unnest(range(count(*))) AS pos FROM lineitem), s AS (SELECT pos, 50.0 + abs(pos % 500 - 250) * 0.4 AS clean, {_mix('pos', 1)} % 4 = 0 AS corrupted, ({_mix('pos', 2)} % 21 - 10) / 10.0 AS noise, {_mix('pos', 2)} % 200 AS wrong FROM p), d AS (SELECT pos, CAST(clean AS DOUBLE) AS clean, CAST(CASE WHEN corrupted THEN wrong ELSE clean + noise END AS DOUBLE) AS dirty FROM s), f AS (SELECT clean, count(*) OVER w AS held, median(dirty) OVER w AS med, avg(dirty) OVER w AS mean FROM d WINDOW w AS (ORDER BY pos ROWS BETWEEN 12 PRECEDING AND 12 FOLLOWING)), g AS (SELECT 'median' AS method, abs(med - clean) AS gap FROM f WHERE held = 25 UNION ALL SELECT 'moving_average', abs(mean - clean) FROM f WHERE held = 25) SELECT method, round(avg(gap), 6) AS mae, round(sqrt(avg(gap * gap)), 6) AS rmse, round(max(gap), 6) AS worst, count(*) AS points FROM g GROUP BY method",
)
def recovery_quality(spark, sf_dir):
    signal = generators.corrupted_signal(spark, load(spark, sf_dir, "lineitem").count())
    named = signal.withColumnRenamed("pos", "place")
    median = filters.sliding_median(named, "dirty", 25, "place", align="centered").select("place", F.col("med").alias("estimate"))
    mean = baselines.moving_average(named, "dirty", 25, "place", align="centered").select("place", F.col("avg").alias("estimate"))
    rows = None
    for method, estimates in (("median", median), ("moving_average", mean)):
        both = measures.recovery(named.join(estimates, "place"), "clean", "estimate")
        line = both.select(F.lit(method).alias("method"), F.round("mae", 6).alias("mae"), F.round("rmse", 6).alias("rmse"), F.round("worst", 6).alias("worst"), "points")
        rows = line if rows is None else rows.unionByName(line)
    return rows


for _gen in generators.GENERATORS:
    _vector = f"(SELECT pos, CAST({generators.value_text(_gen, '(SELECT count(*) FROM lineitem)', 1, 32, '//')} AS BIGINT) AS x FROM (SELECT row_number() OVER (ORDER BY {', '.join(LINEITEM)}) - 1 AS pos FROM lineitem))"

    def _generate(spark, sf_dir, gen=_gen):
        return generators.generate(load(spark, sf_dir, "lineitem"), LINEITEM, gen)

    def _generated_median(spark, sf_dir, gen=_gen):
        rows = generators.generate(load(spark, sf_dir, "lineitem"), LINEITEM, gen).withColumnRenamed("pos", "place")
        return filters.sliding_median(rows, "x", 101, "place").select("pos", "med")

    query(f"gen_{_gen}", f"SELECT pos, x FROM {_vector}")(_generate)
    query(f"median_gen_{_gen}", f"SELECT pos, CAST(med AS BIGINT) AS med FROM (SELECT pos, count(*) OVER w AS held, median(x) OVER w AS med FROM {_vector} WINDOW w AS (ORDER BY pos ROWS BETWEEN CURRENT ROW AND 100 FOLLOWING)) WHERE held = 101")(_generated_median)


@query("gen_wide_random_64", f"SELECT pos, CAST({generators.value_text('wide_random', '0', 1, 64, '//')} AS BIGINT) AS x FROM (SELECT row_number() OVER (ORDER BY {', '.join(LINEITEM)}) - 1 AS pos FROM lineitem)")
def gen_wide_random_64(spark, sf_dir):
    return generators.generate(load(spark, sf_dir, "lineitem"), LINEITEM, "wide_random", width=64)


@query("disorder_per_block", f"WITH p AS (SELECT l_extendedprice AS v, row_number() OVER (ORDER BY {', '.join(LINEITEM)}) - 1 AS pos FROM lineitem), d AS (SELECT pos // 101 AS blk, CASE WHEN v < lag(v) OVER (PARTITION BY pos // 101 ORDER BY pos) THEN 1 ELSE 0 END AS down FROM p), i AS (SELECT a.pos // 101 AS blk, count(*) AS inversions FROM p a JOIN p b ON a.pos // 101 = b.pos // 101 AND a.pos < b.pos AND a.v > b.v GROUP BY 1) SELECT d.blk, count(*) AS rows, CAST(sum(down) AS BIGINT) AS descents, CAST(sum(down) AS BIGINT) + 1 AS runs, sum(down) = 0 AS is_sorted, coalesce(any_value(i.inversions), 0) AS inversions FROM d LEFT JOIN i ON d.blk = i.blk GROUP BY d.blk")
def disorder_per_block(spark, sf_dir):
    return sorting.disorder_per_block(load(spark, sf_dir, "lineitem"), "l_extendedprice", 101, LINEITEM)


AGREEING = ("sorted_blocks", *baselines.METHODS, "engine_percentile", "collect_sort", "self_join")
_pairs = [(a, b) for i, a in enumerate(AGREEING) for b in AGREEING[i + 1 :]]


#: Many short series; series with ties, many of them shorter than the window; few long ones.
AGREEMENTS = {"matrix": ("events", "value", 5, EVENTS, "user_id"), "ties": ("lineitem", "l_quantity", 21, LINEITEM, "l_partkey"), "long": ("events", "value", 51, EVENTS, "event_type")}
for _name, (_table, _value, _k, _order, _series) in AGREEMENTS.items():

    def _agree_run(spark, sf_dir, table=_table, value=_value, k=_k, order=_order, series=_series):
        return verify.agree(load(spark, sf_dir, table), AGREEING, value, k, order, series)

    query(f"agreement_{_name}", "SELECT p.method_a, p.method_b, n.rows, CAST(0 AS BIGINT) AS mismatches FROM (VALUES " + ", ".join(f"('{a}', '{b}')" for a, b in _pairs) + f") p(method_a, method_b), (SELECT CAST(sum(greatest(c - {_k - 1}, 0)) AS BIGINT) AS rows FROM (SELECT count(*) AS c FROM {_table} GROUP BY {_series})) n")(_agree_run)


@query("set_except_methods", "SELECT CAST(0 AS BIGINT) AS different, CAST(sum(greatest(c - 4, 0)) AS BIGINT) AS rows FROM (SELECT count(*) AS c FROM events GROUP BY user_id)")
def set_except_methods(spark, sf_dir):
    one, other = (baselines.run(load(spark, sf_dir, "events"), m, "value", 5, EVENTS, "user_id") for m in ("sorted_blocks", "double_heap"))
    return one.exceptAll(other).agg(F.count("*").alias("different")).crossJoin(other.agg(F.count("*").alias("rows")))


@query("median_array_cells", "SELECT vec_id, d - 4 AS pos, med FROM (SELECT vec_id, d, count(*) OVER w AS held, list_sort(array_agg(x) OVER w)[4] AS med FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS d FROM embeddings) WINDOW w AS (PARTITION BY vec_id ORDER BY d ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING)) WHERE held = 7")
def median_array_cells(spark, sf_dir):
    cells = sqlapi.median_cells("embedding", T.FloatType(), 7)
    return load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(cells).alias("pos", "med")).withColumn("pos", F.col("pos").cast("long"))


@query("global_positions", f"SELECT l_orderkey, l_linenumber, row_number() OVER (ORDER BY {', '.join(LINEITEM)}) - 1 AS pos FROM lineitem")
def positions(spark, sf_dir):
    return global_positions(load(spark, sf_dir, "lineitem").select(*LINEITEM), LINEITEM).select("l_orderkey", "l_linenumber", "pos")


@query("median_join_nation", "SELECT n_name, s_suppkey, pos, med FROM (" + framed("supplier", "median(s_acctbal) {w}", 3, ["s_suppkey"], ("s_nationkey",), ("s_suppkey",)) + ") JOIN nation ON s_nationkey = n_nationkey")
def median_join_nation(spark, sf_dir):
    found = filters.sliding_median(load(spark, sf_dir, "supplier"), "s_acctbal", 3, "s_suppkey", "s_nationkey")
    nation = load(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    return found.join(nation, found["s_nationkey"] == nation["n_nationkey"]).select("n_name", "s_suppkey", "pos", "med")


@query("median_join_region_rollup", "SELECT r_name, n_name, count(*) AS windows, max(med) AS highest FROM (" + framed("customer", "median(c_acctbal) {w}", 5, ["c_custkey"], ("c_nationkey",)) + ") JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def median_join_region_rollup(spark, sf_dir):
    found = filters.sliding_median(load(spark, sf_dir, "customer"), "c_acctbal", 5, "c_custkey", "c_nationkey")
    nation, region = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    named = found.join(nation, found["c_nationkey"] == nation["n_nationkey"]).join(region, nation["n_regionkey"] == region["r_regionkey"])
    return named.rollup("r_name", "n_name").agg(F.count("*").alias("windows"), F.max("med").alias("highest"))


@query("udtf_median", framed("events", "median(value) {w}", 25, EVENTS, ("user_id",), ("event_id",)))
def udtf_median(spark, sf_dir):
    sqlapi.register(spark)
    load(spark, sf_dir, "events").createOrReplaceTempView("events_of_filter")
    return spark.sql("SELECT user_id, event_id, pos, med FROM sliding_median(TABLE(events_of_filter) PARTITION BY user_id ORDER BY (ts, event_id), 'value', 25)")


@query("grouped_median", framed("events", "median(value) {w}", 25, EVENTS, ("user_id",), ("event_id",)))
def grouped_median(spark, sf_dir):
    return sqlapi.median_groups(load(spark, sf_dir, "events"), "value", 25, EVENTS, ["user_id"]).select("user_id", "event_id", "pos", "med")


@query("pair_blocks_join", f"WITH p AS (SELECT l_extendedprice AS v, row_number() OVER (ORDER BY {', '.join(LINEITEM)}) - 1 AS pos FROM lineitem), b AS (SELECT pos // 1001 AS blk, min(v) AS low, max(v) AS high FROM p GROUP BY blk) SELECT b.blk, b.low, b.high, a.low AS before_low, a.high AS before_high FROM b JOIN b a ON b.blk = a.blk + 1")
def pair_blocks_join(spark, sf_dir):
    return neighbour_summaries(global_positions(load(spark, sf_dir, "lineitem").select(*LINEITEM), LINEITEM), "l_extendedprice", 1001)


@query("stream_median_replay", framed("events", "median(value) {w}", 25, EVENTS, show=("event_id",)))
def stream_median_replay(spark, sf_dir):
    rows = load(spark, sf_dir, "events").select("event_id", "ts", "value")
    stream = sliding.replay(rows, "ts", "event_id", None, 3, "stream-median")
    found = sliding.run_to_end(sliding.stream_sliding_median(stream, "value", 25, "ts", "event_id"), "stream-median", one_state=True)
    return found.where("id >= 0").select(F.col("id").alias("event_id"), "pos", "med")


_CLOSED = "(SELECT max(ts) FROM events) - INTERVAL 1 HOUR"


def _times(df: DataFrame) -> DataFrame:
    """Timestamps as text, which means the same everywhere."""
    return df.select(*[F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c) if isinstance(df.schema[c].dataType, T.TimestampType) else F.col(c) for c in df.columns])


def _unflushed(spark, sf_dir, label):
    rows = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "value")
    folder = fresh_path(spark, label)
    sliding.slices(rows, "ts", 2, folder)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(folder)


@query("stream_tumbling_median", f"SELECT strftime(d, '%Y-%m-%d %H:%M:%S') AS first, strftime(d + INTERVAL 1 DAY, '%Y-%m-%d %H:%M:%S') AS past, count(value) AS rows, round(median(value), 6) AS med FROM (SELECT date_trunc('day', ts) AS d, value FROM events) GROUP BY d HAVING d + INTERVAL 1 DAY <= {_CLOSED}")
def stream_tumbling_median(spark, sf_dir):
    found = sliding.run_to_end(sliding.time_window_medians(_unflushed(spark, sf_dir, "tumbling"), "ts", "value", "1 day"), "tumbling")
    return _times(found).withColumn("med", F.round("med", 6))


@query("stream_sliding_median", f"SELECT strftime(d, '%Y-%m-%d %H:%M:%S') AS first, strftime(d + INTERVAL 1 DAY, '%Y-%m-%d %H:%M:%S') AS past, count(value) AS rows, round(median(value), 6) AS med FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) - i * INTERVAL 6 HOUR AS d, value FROM events, range(4) r(i)) GROUP BY d HAVING d + INTERVAL 1 DAY <= {_CLOSED}")
def stream_sliding_median(spark, sf_dir):
    found = sliding.run_to_end(sliding.time_window_medians(_unflushed(spark, sf_dir, "sliding"), "ts", "value", "1 day", "6 hours"), "sliding")
    return _times(found).withColumn("med", F.round("med", 6))


@query("stream_session_median", f"WITH g AS (SELECT user_id, ts, event_id, value, CASE WHEN ts - lag(ts) OVER w < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT user_id, ts, value, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM g) SELECT user_id AS series, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS first, count(value) AS rows, round(median(value), 6) AS med FROM s GROUP BY user_id, n HAVING max(ts) + INTERVAL 1 HOUR <= {_CLOSED}")
def stream_session_median(spark, sf_dir):
    found = sliding.run_to_end(sliding.session_medians(_unflushed(spark, sf_dir, "session"), "ts", "value", "user_id", "1 hour"), "session")
    return _times(found).withColumn("med", F.round("med", 6))


@query("stream_dedup_join", "SELECT n_name, count(*) AS rows FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def stream_dedup_join(spark, sf_dir):
    rows = load(spark, sf_dir, "events").select("event_id", "ts", "user_id")
    folder = fresh_path(spark, "dedup")
    sliding.slices(rows, "ts", 2, folder)
    stream = spark.readStream.schema(rows.schema).parquet(folder)
    customers = load(spark, sf_dir, "customer").join(load(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")
    joined = sliding.deduplicated(stream.unionByName(stream), "ts", "event_id").join(customers, F.col("user_id") == F.col("c_custkey"))
    return sliding.run_to_end(joined.select("event_id", "n_name"), "dedup").groupBy("n_name").agg(F.count("*").alias("rows"))


for _key, (_run, _sql) in relational.queries().items():
    QUERIES[_key] = _run
    ORACLE_SQL[_key] = _sql


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Medians of each user's events, and of all events, in one result."""
    per_user = QUERIES["median_events_per_user"](spark, sf_dir).select(F.col("user_id").alias("series"), "event_id", "pos", "med")
    whole = QUERIES["median_events_global"](spark, sf_dir).select(F.lit(None).cast("long").alias("series"), "event_id", "pos", "med")
    return per_user.unionByName(whole)
