"""Relational surroundings of the filters: scans, filters, joins, aggregates, windows, sets and functions.

Most of them are one statement that both engines read; others are DataFrame
code or have a text for each engine.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .operators import filters
from .plans.positions import global_positions
from .sources import generators
from .sources.tables import LINEITEM_ORDER, TABLES, load

Query = Callable[[SparkSession, str], DataFrame]

SCANS = {
    "region": "r_regionkey, r_name",
    "nation": "n_nationkey, n_name, n_regionkey",
    "customer": "c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment",
    "supplier": "s_suppkey, s_name, s_nationkey, s_acctbal",
    "part": "p_partkey, p_name, p_brand, p_type, p_size, p_retailprice",
    "orders": "o_orderkey, o_custkey, o_orderstatus, o_totalprice, o_orderdate, o_orderpriority",
    "lineitem": "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate",
    "events": "event_id, ts, user_id, event_type, value, props",
    "documents": "doc_id, text, lang, source, n_chars",
    "embeddings": "vec_id, CAST(cardinality(embedding) AS BIGINT) AS dims, label",
    "pages": "page_id, url, html",
    "benchmark": "item_id, text",
    "labels": "doc_id, quality, toxic",
    "conversations": "conv_id, turn, role, text",
}

#: One text for both engines.
SHARED = {
    "project_price_net": "SELECT l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) * (1 + l_tax) AS net FROM lineitem",
    "filter_in_between": "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority LIKE '1%' AND o_orderdate IS NOT NULL",
    "case_buckets": "SELECT band, count(*) AS rows FROM (SELECT CASE WHEN o_totalprice < 50000 THEN 'low' WHEN o_totalprice < 150000 THEN 'mid' ELSE 'high' END AS band FROM orders) x GROUP BY band",
    "series_long_semi": "SELECT c_custkey FROM customer LEFT SEMI JOIN (SELECT o_custkey FROM orders GROUP BY o_custkey HAVING count(*) >= 7) o ON c_custkey = o_custkey",
    "series_short_anti": "SELECT c_custkey FROM customer LEFT ANTI JOIN (SELECT o_custkey FROM orders GROUP BY o_custkey HAVING count(*) >= 7) o ON c_custkey = o_custkey",
    "median_global_group": "SELECT event_type, round(median(value), 6) AS med, count(*) AS rows FROM events GROUP BY event_type",
    "cube_flag_status": "SELECT l_returnflag, l_linestatus, count(*) AS rows, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "grouping_sets": "SELECT o_orderstatus, o_orderpriority, count(*) AS rows FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
    "having_filter_agg": "SELECT user_id, count(*) AS rows, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM events GROUP BY user_id HAVING count(*) > 50",
    "win_ranking": "SELECT c_custkey, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rk, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)",
    "win_lag_lead": "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "win_rows_avg": "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 24 PRECEDING AND CURRENT ROW), 6) AS mean FROM events",
    "sort_multi": "SELECT s_nationkey, s_acctbal, s_suppkey FROM supplier ORDER BY s_nationkey ASC, s_acctbal DESC NULLS LAST, s_suppkey",
    "topk_per_user": "SELECT user_id, event_id, value FROM (SELECT user_id, event_id, value, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS rn FROM events) x WHERE rn <= 3",
    "topk_values": "SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 20",
    "distinct_series": "SELECT DISTINCT user_id, event_type FROM events",
    "outer_full": "SELECT c.c_custkey, s.s_suppkey FROM (SELECT c_custkey FROM customer) c FULL OUTER JOIN (SELECT s_suppkey FROM supplier) s ON c.c_custkey = s.s_suppkey",
    "set_operations": "SELECT user_id AS k FROM events UNION SELECT s_suppkey FROM supplier EXCEPT SELECT n_nationkey FROM nation",
    "set_intersect_users": "SELECT user_id AS k FROM events INTERSECT SELECT c_custkey FROM customer",
    "fn_math": "SELECT event_id, abs(value - 100) AS a, round(value, 1) AS r, CAST(floor(value) AS BIGINT) AS f, CAST(ceil(value) AS BIGINT) AS c, CAST(sign(value - 50) AS DOUBLE) AS s, greatest(value, 50.0) AS g, least(value, 50.0) AS l, round(sqrt(value), 6) AS q, round(power(value, 2), 4) AS p, event_id % 7 AS m FROM events",
    "fn_null": "SELECT event_id, coalesce(nullif(event_type, 'view'), 'none') AS t, CASE WHEN isnan(value) THEN 0.0 ELSE value END AS v, nullif(user_id, 3) AS u FROM events",
}

#: Texts for each engine.
PAIRED = {
    "rollup_type_month": (
        "SELECT event_type, month, count(*) AS rows, round(sum(value), 2) AS total FROM (SELECT event_type, CAST(month(ts) AS BIGINT) AS month, value FROM events) GROUP BY ROLLUP (event_type, month)",
        "SELECT event_type, month, count(*) AS rows, round(sum(value), 2) AS total FROM (SELECT event_type, month(ts) AS month, value FROM events) GROUP BY ROLLUP (event_type, month)",
    ),
    "series_to_array": (
        "SELECT conv_id, array_join(transform(array_sort(collect_list(struct(turn, role))), x -> x.role), ',') AS roles FROM conversations GROUP BY conv_id",
        "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id",
    ),
    "win_range_days": (
        "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 6 PRECEDING AND CURRENT ROW), 2) AS week FROM (SELECT o_orderkey, o_custkey, o_totalprice, date_diff(CAST(o_orderdate AS DATE), DATE '1970-01-01') AS day FROM orders)",
        "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 6 PRECEDING AND CURRENT ROW), 2) AS week FROM (SELECT o_orderkey, o_custkey, o_totalprice, date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS day FROM orders)",
    ),
    "interval_join_events": (
        "SELECT e.user_id, count(*) AS pairs FROM events e JOIN events p ON e.user_id = p.user_id AND e.event_type = 'error' AND p.event_type = 'purchase' AND p.ts BETWEEN e.ts - INTERVAL 6 HOURS AND e.ts + INTERVAL 6 HOURS GROUP BY e.user_id",
        "SELECT e.user_id, count(*) AS pairs FROM events e JOIN events p ON e.user_id = p.user_id AND e.event_type = 'error' AND p.event_type = 'purchase' AND p.ts BETWEEN e.ts - INTERVAL 6 HOURS AND e.ts + INTERVAL 6 HOURS GROUP BY e.user_id",
    ),
    "fn_date": (
        "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, date_format(date_trunc('month', o_orderdate), 'yyyy-MM-dd') AS t, CAST(date_diff(CAST(o_orderdate AS DATE), DATE '1990-01-01') AS BIGINT) AS d, unix_micros(CAST(o_orderdate AS TIMESTAMP)) AS u FROM orders",
        "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS t, date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) AS d, epoch_us(o_orderdate) AS u FROM orders",
    ),
    "fn_string": (
        "SELECT doc_id, CAST(length(text) AS BIGINT) AS n, lower(substring(text, 1, 5)) AS head, concat_ws('-', lang, source) AS tag, regexp_extract(source, '([0-9]+)', 1) AS number, CAST(size(split(text, ' ')) AS BIGINT) AS words FROM documents",
        "SELECT doc_id, length(text) AS n, lower(substring(text, 1, 5)) AS head, concat_ws('-', lang, source) AS tag, regexp_extract(source, '([0-9]+)', 1) AS number, len(string_split(text, ' ')) AS words FROM documents",
    ),
    "fn_array": (
        "SELECT vec_id, a[0] AS least_value, element_at(a, -1) AS most, CAST(size(filter(a, x -> x > 0)) AS BIGINT) AS positive, exists(a, x -> x > 0.4) AS large, array_join(transform(slice(sequence(1, 64), 3, 4), x -> x * x), ',') AS squares, CAST(array_position(a, a[3]) AS BIGINT) AS place FROM (SELECT vec_id, array_sort(embedding) AS a FROM embeddings)",
        "SELECT vec_id, a[1] AS least_value, a[-1] AS most, len(list_filter(a, lambda x: x > 0)) AS positive, len(list_filter(a, lambda x: x > 0.4)) > 0 AS large, array_to_string(list_transform(range(3, 7), lambda x: x * x), ',') AS squares, CAST(list_position(a, a[4]) AS BIGINT) AS place FROM (SELECT vec_id, list_sort(embedding) AS a FROM embeddings)",
    ),
    "fn_map": (
        "SELECT user_id, m['purchase'] AS purchases, CAST(size(map_keys(m)) AS BIGINT) AS kinds, transform_values(m, (k, v) -> v * 2)['click'] AS twice FROM (SELECT user_id, map_from_entries(collect_list(struct(event_type, n))) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) GROUP BY user_id)",
        "SELECT user_id, CAST(max(n) FILTER (WHERE event_type = 'purchase') AS BIGINT) AS purchases, count(*) AS kinds, CAST(max(n) FILTER (WHERE event_type = 'click') * 2 AS BIGINT) AS twice FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) GROUP BY user_id",
    ),
    "fn_json": (
        "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k, from_json(props, 'k BIGINT').k + 1 AS after, to_json(named_struct('id', event_id)) AS j FROM events",
        "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS after, '{\"id\":' || event_id || '}' AS j FROM events",
    ),
    "fn_struct": (
        "SELECT s.id AS id, s.of.kind AS kind FROM (SELECT named_struct('id', event_id, 'of', named_struct('kind', event_type)) AS s FROM events)",
        "SELECT s.id AS id, s.inner_part.kind AS kind FROM (SELECT struct_pack(id := event_id, inner_part := struct_pack(kind := event_type)) AS s FROM events)",
    ),
}


def _tables_of(text: str) -> list[str]:
    return [t for t in TABLES if re.search(rf"\b(FROM|JOIN) {t}\b", text)]


def _statement(text: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        for table in _tables_of(text):
            load(spark, sf_dir, table).createOrReplaceTempView(table)
        return spark.sql(text)

    return run


def _duck(text: str) -> str:
    return text.replace("LEFT SEMI JOIN", "SEMI JOIN").replace("LEFT ANTI JOIN", "ANTI JOIN")


EVENT_MEDIANS = "SELECT user_id, event_id, pos, med FROM (SELECT user_id, event_id, CAST(row_number() OVER s - 1 AS BIGINT) AS pos, count(*) OVER w AS held, median(value) OVER w AS med FROM events WINDOW s AS (PARTITION BY user_id ORDER BY ts, event_id), w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN {a} PRECEDING AND {b} FOLLOWING)) WHERE held = 5"


def _user_medians(spark: SparkSession, sf_dir: str, align: str = "leading") -> DataFrame:
    return filters.sliding_median(load(spark, sf_dir, "events"), "value", 5, ["ts", "event_id"], "user_id", align=align)


def join_broadcast_nation(spark, sf_dir):
    supplier, nation = load(spark, sf_dir, "supplier"), load(spark, sf_dir, "nation")
    return supplier.join(F.broadcast(nation), supplier["s_nationkey"] == nation["n_nationkey"]).select("n_name", "s_suppkey", "s_acctbal")


def join_back_payload(spark, sf_dir):
    """Residuals of values against their trailing medians: a join on the row's own key."""
    medians = _user_medians(spark, sf_dir, "trailing").select("event_id", "med")
    rows = load(spark, sf_dir, "events").select("event_id", "user_id", "value")
    return rows.hint("merge").join(medians, "event_id").select("user_id", "event_id", F.round(F.col("value") - F.col("med"), 6).alias("residual"))


def topk_spikes(spark, sf_dir):
    rows = join_back_payload(spark, sf_dir).select("event_id", F.abs("residual").alias("size"))
    return rows.orderBy(F.desc("size"), "event_id").limit(20)


def asof_median_orders(spark, sf_dir):
    """Each order with the latest trailing price median at or before its date, through one sorted union by customer-free days."""
    medians = filters.sliding_median(load(spark, sf_dir, "lineitem"), "l_extendedprice", 25, list(LINEITEM_ORDER), align="trailing")
    # The latest median of a day stands for the day; days are few and bounded by the calendar.
    daily = medians.groupBy(F.col("l_shipdate").cast("date").alias("day")).agg(F.max_by("med", "pos").alias("med"), F.max("pos").alias("pos"))
    orders = load(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").cast("date").alias("day"))
    days = orders.select("day").distinct().withColumn("asked", F.lit(True)).join(daily, "day", "full")
    by_day = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, 0)
    filled = days.select("day", F.last("med", ignorenulls=True).over(by_day).alias("med"), F.last("pos", ignorenulls=True).over(by_day).alias("pos"))
    return orders.join(filled, "day").select("o_orderkey", "pos", "med")


def outer_missing_windows(spark, sf_dir):
    windows = filters.sliding_median(load(spark, sf_dir, "orders"), "o_totalprice", 7, ["o_orderdate", "o_orderkey"], "o_custkey").groupBy("o_custkey").agg(F.count("*").alias("n"))
    customer = load(spark, sf_dir, "customer").select("c_custkey")
    return customer.join(windows, customer["c_custkey"] == windows["o_custkey"], "left").select("c_custkey", F.coalesce("n", F.lit(0)).cast("long").alias("windows"))


def agg_medians_per_user(spark, sf_dir):
    return _user_medians(spark, sf_dir).groupBy("user_id").agg(F.count("*").alias("rows"), F.min("med").alias("low"), F.max("med").alias("high"), F.round(F.avg("med"), 6).alias("mean"))


def distinct_medians(spark, sf_dir):
    found = filters.sliding_median(load(spark, sf_dir, "events"), "value", 101, ["ts", "event_id"], "event_type")
    return found.groupBy("event_type").agg(F.count_distinct("med").alias("different"))


def pivot_type_median(spark, sf_dir):
    kinds = ["click", "error", "login", "purchase", "view"]
    return load(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", kinds).agg(F.round(F.median("value"), 6))


def _vector_sql(name: str) -> str:
    return f"SELECT CAST({generators.value_text(name, '(SELECT count(*) FROM lineitem)', 1, 32, '//')} AS BIGINT) AS x FROM (SELECT row_number() OVER (ORDER BY {', '.join(LINEITEM_ORDER)}) - 1 AS pos FROM lineitem)"


def set_union_generators(spark, sf_dir):
    one, other = (generators.generate(load(spark, sf_dir, "lineitem"), LINEITEM_ORDER, g).select("x") for g in ("ramp_up", "ramp_down"))
    return one.unionAll(other)


def set_intersect(spark, sf_dir):
    one, other = (generators.generate(load(spark, sf_dir, "lineitem"), LINEITEM_ORDER, g).select("x") for g in ("noisy_up", "narrow_random"))
    return one.intersect(other)


def range_join_windows(spark, sf_dir):
    """How many windows of 25 rows each row lies in, by a join on blocks of positions and a range."""
    placed = global_positions(load(spark, sf_dir, "events").select("ts", "event_id"), ["ts", "event_id"]).select("event_id", "pos")
    starts = placed.select(F.col("pos").alias("start"), F.explode(F.array(F.expr("pos div 25"), F.expr("pos div 25 + 1"))).alias("blk"))
    return placed.withColumn("blk", F.expr("pos div 25")).join(starts, "blk").where("pos BETWEEN start AND start + 24").groupBy("event_id").agg(F.count("*").alias("windows"))


CODED: dict[str, tuple[Query, str]] = {
    "join_broadcast_nation": (join_broadcast_nation, "SELECT n_name, s_suppkey, s_acctbal FROM supplier JOIN nation ON s_nationkey = n_nationkey"),
    "join_back_payload": (join_back_payload, f"SELECT e.user_id, e.event_id, round(e.value - m.med, 6) AS residual FROM events e JOIN ({EVENT_MEDIANS.format(a=4, b=0)}) m USING (event_id)"),
    "topk_spikes": (topk_spikes, f"SELECT e.event_id, abs(round(e.value - m.med, 6)) AS size FROM events e JOIN ({EVENT_MEDIANS.format(a=4, b=0)}) m USING (event_id) ORDER BY size DESC, e.event_id LIMIT 20"),
    "asof_median_orders": (
        asof_median_orders,
        f"WITH m AS (SELECT CAST(l_shipdate AS DATE) AS day, row_number() OVER (ORDER BY {', '.join(LINEITEM_ORDER)}) - 1 AS pos, count(*) OVER w AS held, median(l_extendedprice) OVER w AS med FROM lineitem WINDOW w AS (ORDER BY {', '.join(LINEITEM_ORDER)} ROWS BETWEEN 24 PRECEDING AND CURRENT ROW)), d AS (SELECT day, max(pos) AS pos, arg_max(med, pos) AS med FROM m WHERE held = 25 GROUP BY day), o AS (SELECT o_orderkey, CAST(o_orderdate AS DATE) AS day FROM orders) SELECT o.o_orderkey, d.pos, d.med FROM o ASOF LEFT JOIN d ON o.day >= d.day",
    ),
    "outer_missing_windows": (outer_missing_windows, "SELECT c_custkey, CAST(greatest(coalesce(n, 0) - 6, 0) AS BIGINT) AS windows FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) ON c_custkey = o_custkey"),
    "agg_medians_per_user": (agg_medians_per_user, f"SELECT user_id, count(*) AS rows, min(med) AS low, max(med) AS high, round(avg(med), 6) AS mean FROM ({EVENT_MEDIANS.format(a=0, b=4)}) GROUP BY user_id"),
    "distinct_medians": (
        distinct_medians,
        "SELECT event_type, count(DISTINCT med) AS different FROM (SELECT event_type, count(*) OVER w AS held, median(value) OVER w AS med FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN CURRENT ROW AND 100 FOLLOWING)) WHERE held = 101 GROUP BY event_type",
    ),
    "pivot_type_median": (
        pivot_type_median,
        "SELECT user_id, " + ", ".join(f"round(median(value) FILTER (WHERE event_type = '{t}'), 6) AS {t}" for t in ("click", "error", "login", "purchase", "view")) + " FROM events GROUP BY user_id",
    ),
    "set_union_generators": (set_union_generators, f"{_vector_sql('ramp_up')} UNION ALL {_vector_sql('ramp_down')}"),
    "set_intersect": (set_intersect, f"{_vector_sql('noisy_up')} INTERSECT {_vector_sql('narrow_random')}"),
    "range_join_windows": (range_join_windows, "WITH p AS (SELECT event_id, row_number() OVER (ORDER BY ts, event_id) - 1 AS pos FROM events) SELECT event_id, least(pos + 1, 25) AS windows FROM p"),
}


def queries() -> dict[str, tuple[Query, str]]:
    out = {f"scan_{table}": (_statement(f"SELECT {columns} FROM {table}"), f"SELECT {columns.replace('cardinality', 'len')} FROM {table}") for table, columns in SCANS.items()}
    out |= {key: (_statement(text), _duck(text)) for key, text in SHARED.items()}
    out |= {key: (_statement(spark), duck) for key, (spark, duck) in PAIRED.items()}
    return out | CODED
