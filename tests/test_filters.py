"""DataFrame operators against brute force."""

import datetime
import random

import pytest
from pyspark.sql import Row
from pyspark.sql import functions as F

from slidemedian import measures, sqlapi, verify
from slidemedian.operators import baselines, filters, reduction, sorting
from slidemedian.plans import positions, tiles
from slidemedian.plans.planner import choose, explain_plan
from slidemedian.plans.spec import SlidingSpec
from slidemedian.sources import generators, tables


def series(spark, groups, seed=0):
    rng = random.Random(seed)
    rows = [(g, i, rng.choice([rng.randrange(5), rng.randrange(1000)])) for g, n in groups.items() for i in range(n)]
    data = {g: [r[2] for r in rows if r[0] == g] for g in groups}
    rng.shuffle(rows)
    return spark.createDataFrame(rows, "g int, i int, v long").repartition(3), data


def found(df, out="med"):
    result = {}
    for r in df.collect():
        result.setdefault(r["g"], {})[r["pos"]] = r[out]
    return result


GROUPS = {1: 0 + 30, 2: 4, 3: 5, 4: 11, 5: 1}


@pytest.mark.parametrize("route", ["short_series", "blocks", "wide"])
@pytest.mark.parametrize("k", [1, 2, 5, 7])
def test_routes(spark, route, k):
    df, data = series(spark, GROUPS)
    got = found(filters.sliding_median(df, "v", k, "i", "g", even="upper", route=route))
    for g, values in data.items():
        expected = {i: sorted(values[i : i + k])[k // 2] for i in range(len(values) - k + 1)}
        assert got.get(g, {}) == expected


@pytest.mark.parametrize("even,pick", [("lower", lambda w: w[2]), ("upper", lambda w: w[3]), ("mean", lambda w: (w[2] + w[3]) / 2)])
def test_even_windows(spark, even, pick):
    df, data = series(spark, GROUPS)
    got = found(filters.sliding_median(df, "v", 6, "i", "g", even=even))
    assert got[1] == {i: pick(sorted(data[1][i : i + 6])) for i in range(25)}


@pytest.mark.parametrize("align,shift", [("leading", 0), ("trailing", 4), ("centered", 2)])
def test_partial_edges_and_alignment(spark, align, shift):
    df, data = series(spark, GROUPS)
    got = found(filters.sliding_median(df, "v", 5, "i", "g", even="upper", align=align, edges="partial"))
    for g, values in data.items():
        for i in range(len(values)):
            window = sorted(values[max(0, i - shift) : max(0, i - shift + 5)])
            assert got[g][i] == window[len(window) // 2]


def test_pad_reflect_and_keep(spark):
    df, data = series(spark, {1: 9})
    v = data[1]
    padded, mirrored = [0, 0, *v, 0, 0], [v[1], v[0], *v, v[-1], v[-2]]
    options = {"align": "centered"}
    assert found(filters.sliding_median(df, "v", 5, "i", "g", edges="pad", constant=0, **options))[1] == {i: sorted(padded[i : i + 5])[2] for i in range(9)}
    assert found(filters.sliding_median(df, "v", 5, "i", "g", edges="reflect", **options))[1] == {i: sorted(mirrored[i : i + 5])[2] for i in range(9)}
    kept = found(filters.sliding_median(df, "v", 5, "i", "g", edges="keep", **options))[1]
    assert kept == {i: sorted(v[i - 2 : i + 3])[2] if 2 <= i <= 6 else v[i] for i in range(9)}


def test_null_policies(spark):
    rows = [(1, i, None if i == 4 else i) for i in range(9)]
    df = spark.createDataFrame(rows, "g int, i int, v int")
    with pytest.raises(Exception, match="nulls"):
        filters.sliding_median(df, "v", 3, "i", "g").collect()
    assert found(filters.sliding_median(df, "v", 3, "i", "g", nulls="drop"))[1] == {0: 1, 1: 2, 2: 3, 3: 5, 4: 6, 5: 7}
    assert found(filters.sliding_median(df, "v", 3, "i", "g", nulls="poison"))[1] == {0: 1, 1: 2, 2: None, 3: None, 4: None, 5: 6, 6: 7}


def test_order_statistics_and_quantiles(spark):
    df, data = series(spark, GROUPS)
    got = filters.multi_quantile(df, "v", 5, {"low": 0.0, "mid": 0.5, "high": 1.0}, "i", "g")
    for r in got.collect():
        window = sorted(data[r["g"]][r["pos"] : r["pos"] + 5])
        assert (r["low"], r["mid"], r["high"]) == (window[0], window[2], window[4])
    between = filters.sliding_quantile(df, "v", 5, 0.4, "i", "g", interpolate=True)
    for r in between.collect():
        window = sorted(data[r["g"]][r["pos"] : r["pos"] + 5])
        assert r["quantile"] == pytest.approx(window[1] + (window[2] - window[1]) * 0.6)


def test_hampel(spark):
    df, data = series(spark, {1: 40})
    v = data[1]
    for r in filters.hampel(df, "v", 5, "i", "g").collect():
        window = v[r["i"] - 2 : r["i"] + 3]
        med = sorted(window)[2]
        mad = sorted(abs(x - med) for x in window)[2]
        assert (r["med"], r["mad"], r["outlier"]) == (med, mad, abs(v[r["i"]] - med) > 3 * mad)


@pytest.mark.parametrize("sorter", sorting.SORTERS)
def test_piecewise_sort(spark, sorter):
    df, data = series(spark, GROUPS)
    got = {}
    for r in sorting.piecewise_sort(df, "v", 4, "i", "g", sorter=sorter).collect():
        got[(r["g"], r["blk"], r["rnk"])] = (r["v"], r["off"])
    for g, values in data.items():
        for b in range(0, len(values), 4):
            block = sorted((v, o) for o, v in enumerate(values[b : b + 4]))
            for rank, item in enumerate(block):
                assert got.pop((g, b // 4, rank)) == item
    assert not got


def test_both_directions_of_the_equivalence(spark):
    df, data = series(spark, {1: 30, 2: 13})
    blocks = sorting.piecewise_sort(df, "v", 5, "i", "g", sorter="window")
    got = found(sorting.medians_from_sorted_blocks(blocks, "v", 5, partition_by="g"))
    for g, values in data.items():
        assert got[g] == {i: sorted(values[i : i + 5])[2] for i in range(len(values) - 4)}
    for isolate in (True, False):
        back = {(r["g"], r["blk"], r["rnk"]): r["v"] for r in reduction.sort_blocks_by_median(df, "v", 5, "i", "g", isolate=isolate).collect()}
        expected = {(r["g"], r["blk"], r["rnk"]): r["v"] for r in blocks.collect()}
        assert back == expected


@pytest.mark.parametrize("method", baselines.ALL_METHODS)
def test_baselines(spark, method):
    df, data = series(spark, GROUPS)
    if method == "engine_approx":
        return
    got = found(baselines.run(df, method, "v", 5, "i", "g"))
    for g, values in data.items():
        assert got.get(g, {}) == {i: sorted(values[i : i + 5])[2] for i in range(len(values) - 4)}


def test_one_long_series_for_a_contender(spark):
    df = generators.vector(spark, 3000, "narrow_random").withColumnRenamed("pos", "i").withColumn("g", F.lit(1))
    one, other = (baselines.run(df, m, "x", 11, "i").select("pos", "med") for m in ("double_heap", "sorted_blocks"))
    assert verify.differences(one, other).count() == 0 and one.count() == 2990


def test_agreement(spark):
    df, _ = series(spark, GROUPS)
    rows = verify.agree(df, ["sorted_blocks", "two_trees", "collect_sort"], "v", 5, "i", "g").collect()
    assert len(rows) == 3 and all(r["mismatches"] == 0 and r["rows"] == 34 for r in rows)


def test_positions_and_halo(spark):
    df, data = series(spark, GROUPS)
    got = {(r["g"], r["i"]): r["pos"] for r in positions.global_positions(df, ["i"], ["g"], partitions=5).collect()}
    assert all(pos == i for (_, i), pos in got.items()) and len(got) == sum(map(len, data.values()))
    with pytest.raises(ValueError):
        positions.assert_total_order(df, ["g"])
    tiled = tiles.with_halo(spark.range(40).withColumnRenamed("id", "pos"), 3, 4).collect()
    assert len(tiled) == 40 + 9 and sum(r["halo"] for r in tiled) == 9


def test_positions_with_one_leading_key(spark):
    rows = spark.range(30_000).select(F.lit("2024-01-01").cast("date").alias("d"), F.expr("(id * 7919) % 30000").alias("i"), F.lit(None).cast("long").alias("g"))
    placed = positions.global_positions(rows, ["d", "i"], partitions=1100)
    assert placed.count() == 30_000 and placed.where("pos != i").count() == 0
    # One series without a key, over many partitions, and no partition holds much of it.
    keyed = positions.global_positions(rows, ["d", "i"], ["g"], partitions=50)
    assert keyed.count() == 30_000 and keyed.where("pos != i").count() == 0
    ranged = rows.repartitionByRange(50, "d", "i").groupBy(F.spark_partition_id()).count().agg(F.max("count")).first()[0]
    assert ranged < 3 * 30_000 / 50


def test_positions_in_a_range_read_few_partitions(spark):
    rows = spark.range(2000).select(F.expr("(id * 7919) % 2000").alias("i"))
    for low, high in ((0, 5), (990, 1400), (1995, 3000), (2500, 2600), (7, 7)):
        got = positions.positions_in_range(rows, ["i"], low, high, partitions=20)
        assert sorted(r["pos"] for r in got.collect()) == list(range(low, min(high, 2000))) and got.where("pos != i").count() == 0
    plan = positions.positions_in_range(rows, ["i"], 990, 1000, partitions=20)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters" in plan and "GreaterThanOrEqual(__part" in plan


@pytest.mark.parametrize("edges", ["partial", "keep", "pad", "reflect"])
@pytest.mark.parametrize("k", [1, 4, 7])
@pytest.mark.parametrize("align", ["leading", "centered", "trailing"])
def test_edges_on_tiles(spark, monkeypatch, edges, k, align):
    """Series of many tiles, shorter than a window, and of one row."""
    from slidemedian.plans import routes

    monkeypatch.setattr(routes, "blocks_per_tile", lambda k: 4)
    df, data = series(spark, {1: 150, 2: 5, 3: 1, 4: 29})
    options = {"align": align, "edges": edges, "constant": 3 if edges == "pad" else None, "extra": ("v",)}
    for even in ("mean", "lower"):
        one, other = (filters.sliding_median(df, "v", k, "i", "g", route=route, even=even, **options) for route in ("blocks", "short_series"))
        assert one.dtypes == other.dtypes
        assert sorted(map(tuple, one.collect())) == sorted(map(tuple, other.collect()))


def test_edges_of_one_long_series(spark):
    df = spark.range(9000).select(F.col("id").alias("i"), F.expr("(id * 7919) % 1000").alias("v"))
    values = [i * 7919 % 1000 for i in range(9000)]
    got = filters.sliding_median(df, "v", 5, "i", align="centered", edges="reflect")
    assert measures.shuffle_stats(got)["python"] == 1 and "hashpartitioning(tile" in got._jdf.queryExecution().executedPlan().toString()
    around = [values[1], values[0], *values, values[-1], values[-2]]
    assert {r["pos"]: r["med"] for r in got.collect()} == {i: sorted(around[i : i + 5])[2] for i in range(9000)}
    strided = filters.sliding_median(df, "v", 5, "i", align="centered", edges="partial", stride=7)
    whole = filters.sliding_median(df, "v", 5, "i", align="centered", edges="partial")
    assert strided.count() == 1286 and verify.differences(strided, whole.where("pos % 7 = 0")).count() == 0


def test_batches_cut_anywhere(spark):
    df, data = series(spark, GROUPS)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        got = found(filters.sliding_median(df, "v", 5, "i", "g", route="blocks"))
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert got[1] == {i: sorted(data[1][i : i + 5])[2] for i in range(26)}


def test_types(spark):
    day = datetime.date(2024, 1, 1)
    rows = [(1, i, day + datetime.timedelta(days=(i * 7) % 5), f"s{(i * 3) % 7}", i % 3 == 0) for i in range(12)]
    df = spark.createDataFrame(rows, "g int, i int, d date, s string, b boolean").withColumn("m", F.col("i").cast("decimal(10,2)"))
    for column, at in (("d", 2), ("s", 3), ("b", 4)):
        values = [r[at] for r in rows]
        assert found(filters.sliding_median(df, column, 3, "i", "g"))[1] == {i: sorted(values[i : i + 3])[1] for i in range(10)}
    assert float(found(filters.sliding_median(df, "m", 3, "i", "g"))[1][4]) == 5.0


def test_bad_requests(spark):
    df, _ = series(spark, GROUPS)
    for options in ({"k": 0}, {"k": 3, "align": "left"}, {"k": 3, "route": "fast"}, {"k": 3, "edges": "pad"}):
        with pytest.raises(ValueError):
            filters.sliding_median(df, "v", options.pop("k"), "i", "g", **options)
    with pytest.raises(TypeError):
        filters.sliding_median(df.withColumn("s", F.lit("x")), "s", 4, "i", "g")


def test_empty_input(spark):
    df = spark.createDataFrame([], "g int, i int, v long")
    for route in ("short_series", "blocks"):
        assert filters.sliding_median(df, "v", 3, "i", "g", route=route).count() == 0


def test_choice_of_route(spark):
    df, _ = series(spark, GROUPS)
    spec = SlidingSpec("v", 5, ("i",), ("g",), (2,))
    assert choose(spec, {"rows": 10, "series": 2, "longest": 5}) == "short_series"
    assert choose(spec, {"rows": 1 << 30, "series": 2, "longest": 1 << 29}) == "blocks"
    assert choose(SlidingSpec("v", 1 << 24, ("i",), (), (2,)), {"rows": 1 << 30, "series": 1, "longest": 1 << 30}) == "wide"
    assert "short_series" in explain_plan(df, spec)


def test_long_series_need_no_single_partition(spark):
    df = generators.vector(spark, 20_000, "wide_random").withColumnRenamed("pos", "i")
    plan = filters.sliding_median(df, "x", 25, "i", route="blocks")
    assert measures.shuffle_stats(plan)["python"] == 1


def test_median_recovers_better_than_the_mean(spark):
    signal = generators.corrupted_signal(spark).withColumnRenamed("pos", "place")
    med = filters.sliding_median(signal, "dirty", 25, "place", align="centered").select("place", F.col("med").alias("e"))
    avg = baselines.moving_average(signal, "dirty", 25, "place", align="centered").select("place", F.col("avg").alias("e"))
    errors = [measures.recovery(signal.join(e, "place"), "clean", "e").first()["mae"] for e in (med, avg)]
    assert errors[0] < 0.5 * errors[1]


def test_moving_average_on_tiles(spark, monkeypatch):
    monkeypatch.setattr(baselines, "blocks_per_tile", lambda k: 4)
    df = spark.range(500).select(F.col("id").alias("i"), F.expr("(id * 7919) % 1000").alias("v"))
    values = [i * 7919 % 1000 for i in range(500)]
    for align, shift in (("leading", 0), ("centered", 3), ("trailing", 6)):
        got = baselines.moving_average(df, "v", 7, "i", align=align).collect()
        assert {r["pos"]: r["avg"] for r in got} == {i + shift: sum(values[i : i + 7]) / 7 for i in range(494)} and len(got) == 494
        assert all(r["i"] == r["pos"] for r in got)


def test_approximate_medians_miss_few_ranks(spark):
    df, data = series(spark, {1: 60, 2: 5})
    approx = baselines.run(df, "engine_approx", "v", 21, "i", "g")
    row = measures.rank_error(df, approx, "v", 21, ["i"], ["g"]).first()
    wrong = []
    for r in approx.collect():
        window = sorted(data[r["g"]][r["pos"] : r["pos"] + 21])
        ranks = [i for i, x in enumerate(window) if x == r["med"]]
        wrong.append(min(abs(i - 10) for i in ranks))
    assert (row["rows"], row["worst"], row["different"]) == (40, max(wrong), sum(w > 0 for w in wrong))
    assert row["worst"] <= 21 / 20 + 1  # the sketch's accuracy is a twentieth
    exact = baselines.run(df, "sorted_blocks", "v", 21, "i", "g")
    assert measures.rank_error(df, exact, "v", 21, ["i"], ["g"]).first()["worst"] == 0


def test_measures_of_memory_traffic_and_phases(spark):
    import numpy as np

    assert measures.peak_memory(lambda: np.zeros(1 << 20)) >= 8 << 20
    df = generators.vector(spark, 20_000, "wide_random").withColumnRenamed("pos", "i")
    moved = measures.traffic(spark, lambda: filters.sliding_median(df, "x", 25, "i", route="blocks").count())
    assert moved["shuffle_written"] > 20_000 and moved["disk_spilled"] == 0
    ascending, rng = np.arange(60_000), np.random.default_rng(1)
    ordered, mixed = measures.phases(ascending, 501), measures.phases(rng.permutation(60_000), 501)
    assert ordered["sort"] < mixed["sort"] and set(mixed) == {"sort", "walk"}
    assert sorting.inversions([3, 1, 2, 2, 0]) == 7 and sorting.inversions([1, 1, 2]) == 0


def test_sql_functions(spark):
    df, data = series(spark, {1: 12, 2: 3})
    sqlapi.register(spark)
    df.createOrReplaceTempView("rows_to_filter")
    rows = spark.sql("SELECT * FROM sliding_median(TABLE(rows_to_filter) PARTITION BY g ORDER BY (i), 'v', 5)").collect()
    assert {r["pos"]: r["med"] for r in rows} == {i: sorted(data[1][i : i + 5])[2] for i in range(8)}


def test_table_function_holds_few_rows(monkeypatch):
    monkeypatch.setattr(sqlapi, "TABLE_ROWS", 10)
    function, out = sqlapi.SlidingMedianFunction(), []
    values = [i * 7919 % 1000 for i in range(200)]
    for i, v in enumerate(values):
        out += function.eval(Row(i=i, v=v), "v", 5) or ()
        assert len(function.rows) < 20
    out += function.terminate()
    assert out == [(i, values[i], i, sorted(values[i : i + 5])[2]) for i in range(196)]


def test_sinks(spark, tmp_path):
    df, _ = series(spark, GROUPS)
    for fmt in ("parquet", "orc", "json", "csv"):
        tables.save(df, str(tmp_path / fmt), fmt, ["g"], ["i"])
        assert tables.load_as(spark, fmt, str(tmp_path / fmt), df.schema).count() == df.count()
