"""The relational operators, functions and SQL surface that the methods stand on, each over the given tables."""

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import select as sel
from ..plans import sqlapi
from ..sources import tables as tb
from .common import cells_sql, grid, naive, plain, scores_sql


def T(spark, sf, name):
    return tb.load(spark, sf, name)


def _roundtrip(fmt, **options):
    def run(spark, sf):
        path = f"{tb.shared_dir(spark)}/lossband-tables/{fmt}-{uuid.uuid4().hex[:12]}"
        rows = T(spark, sf, "supplier").select("s_suppkey", "s_name", "s_nationkey")
        rows.write.options(**options).format(fmt).save(path)
        return tb.read(spark, fmt, "s_suppkey long, s_name string, s_nationkey int", path, **options)

    return run


def score_store(spark, sf):
    """Scores written by reference and source, and one source read back through partition pruning."""
    path = f"{tb.shared_dir(spark)}/lossband-tables/store-{uuid.uuid4().hex[:12]}"
    tb.store_scores(naive(spark, sf), path)
    return plain(tb.load_scores(spark, path, "seasonal_naive_24").where("source = 'view'"))


def join_broadcast_dims(spark, sf):
    rows = T(spark, sf, "supplier").join(T(spark, sf, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(T(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.select("s_suppkey", "n_name", "r_name")


def join_scores_pair(spark, sf):
    a, b = plain(naive(spark, sf)), plain(naive(spark, sf, "events_hourly", held_out=False)).withColumnRenamed("rfl", "rfl2").drop("m")
    return a.hint("merge").join(b, ["source", "series_id", "origin"]).agg(F.count("*").alias("windows"), F.count_if(F.col("rfl") == F.col("rfl2")).alias("equal"))


def salted_join(left, right, key: str, salts: int = 8):
    """Equality join in which a hot key of ``left`` is spread over ``salts`` tasks and ``right`` is copied to each."""
    a = left.withColumn("salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int"))
    b = right.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "salt"]).drop("salt")


def join_salted(spark, sf):
    a = T(spark, sf, "lineitem").select("l_suppkey", "l_quantity")
    b = T(spark, sf, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    return salted_join(a, b, "l_suppkey").groupBy("s_nationkey").agg(F.sum("l_quantity").cast("long").alias("q"))


def join_range_bucketed(spark, sf):
    """Events inside spans of three hours, by an equality join on six-hour cells and a residual test."""
    spans = spark.range(0, 700, 50).select(F.col("id").alias("lo"), (F.col("id") + 3).alias("hi"))
    rows = T(spark, sf, "events").select("event_id", F.expr("timestampdiff(HOUR, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)").alias("h")).withColumn("cell", F.floor(F.col("h") / 6))
    spans = spans.withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / 6), F.floor(F.col("hi") / 6))))
    return rows.join(spans, "cell").where("h >= lo and h <= hi").groupBy("lo").agg(F.count("*").alias("n"))


def join_asof_events(spark, sf):
    """For every purchase the last view of the same user at or before it: union, then the last view carried on."""
    e = T(spark, sf, "events").where("event_type in ('view', 'purchase')")
    at = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = e.withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(at))
    return seen.where("event_type = 'purchase'").select("event_id", "view_id")


def join_shift(spark, sf):
    """Seasonal differences by a self join on a shifted slot, against lag: differing slots (none)."""
    g = grid(spark, sf)
    lag = g.withColumn("b", F.lag("y", 24).over(Window.partitionBy("source", "series_id").orderBy("t")))
    other = g.select("source", "series_id", (F.col("t") + 24).alias("t"), F.col("y").alias("b2"))
    rows = lag.join(other, ["source", "series_id", "t"])
    return rows.agg(F.count("*").alias("slots"), F.count_if(~F.col("b").eqNullSafe(F.col("b2"))).alias("differing"))


def prefix_frame(spark, sf):
    """Sums of the next 24 slots by running sums and by a sliding frame: differing slots (none)."""
    w = Window.partitionBy("source", "series_id").orderBy("t")
    g = grid(spark, sf).withColumn("p", F.sum(F.coalesce("y", F.lit(0))).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    g = g.withColumns({"a": F.lead("p", 24).over(w) - F.col("p"), "b": F.sum(F.coalesce("y", F.lit(0))).over(w.rowsBetween(1, 24))})
    return g.where("a is not null").agg(F.count("*").alias("slots"), F.count_if(F.col("a") != F.col("b")).alias("differing"))


def group_topk(spark, sf):
    w = Window.partitionBy("source").orderBy(F.desc("rfl"), "series_id", "origin")
    return plain(naive(spark, sf).withColumn("k", F.row_number().over(w)).where("k <= 3"))


def join_lateral(spark, sf):
    naive(spark, sf).createOrReplaceTempView("lateral_scores")
    return spark.sql("""select s.source, x.origin from (select distinct source from lateral_scores) s,
        lateral (select origin from lateral_scores t where t.source = s.source order by rfl desc, origin limit 2) x""")


def udaf_masked_mean(spark, sf):
    import pandas as pd

    tb.ship(spark)

    @F.pandas_udf("double")
    def masked_mean(y: pd.Series) -> float:
        return float(y.dropna().mean()) if y.notna().any() else None

    return grid(spark, sf, "supplier_weekly").groupBy("source").agg(F.round(masked_mean(F.col("y").cast("double")), 6).alias("mean"))


def udf_dot(spark, sf):
    import numpy as np
    import pandas as pd

    tb.ship(spark)

    @F.pandas_udf("double")
    def dot(v: pd.Series) -> pd.Series:
        x = np.stack(v.to_numpy()).astype(float)
        return pd.Series((x * x).sum(axis=1))

    return T(spark, sf, "embeddings").select("vec_id", F.round(dot("embedding"), 5).alias("norm2"))


def vector_mean(spark, sf):
    return T(spark, sf, "embeddings").select("label", F.posexplode("embedding").alias("i", "v")).groupBy("label", "i").agg(F.round(F.avg(F.col("v").cast("double")), 9).alias("mean"))


def agg_kll(spark, sf):
    """Median of a sketch against the exact one, in ranks: within two percent or not."""
    rows = naive(spark, sf).groupBy("source").agg(F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("rfl"), F.lit(0.5)).alias("k"), F.percentile("rfl", F.array(F.lit(0.48), F.lit(0.52))).alias("p"))
    return rows.select("source", F.col("k").between(F.col("p")[0], F.col("p")[1]).alias("near"))


def fn_maps(spark, sf):
    m = F.map_from_entries(F.transform(F.sequence(F.lit(1), F.lit(3)), lambda i: F.struct(i.alias("k"), (i * F.col("n_nationkey")).alias("v"))))
    rows = T(spark, sf, "nation").select("n_nationkey", F.map_filter(F.transform_values(m, lambda k, v: v + k), lambda k, v: v % 2 == 0).alias("m"))
    return rows.select("n_nationkey", F.explode("m").alias("k", "v"))


E = "events"
QUERIES = {
    **{f"scan_{t}": (lambda s, d, t=t: T(s, d, t).agg(F.count("*").alias("n"))) for t in tb.NAMES},
    "csv_roundtrip": _roundtrip("csv", header=True),
    "json_roundtrip": _roundtrip("json"),
    "orc_roundtrip": _roundtrip("orc"),
    "score_store": score_store,
    "project_basic": lambda s, d: T(s, d, E).selectExpr("event_id", "user_id % 10 as bucket", "upper(event_type) as kind"),
    "filter_basic": lambda s, d: T(s, d, E).where(F.col("event_type").isin("view", "click") & F.col("value").between(10, 20) & ~F.col("event_type").like("%ew") | F.col("event_type").rlike("^pur")).select("event_id"),
    "filter_null_safe": lambda s, d: grid(s, d, "supplier_weekly").where(F.col("y").eqNullSafe(F.lit(None).cast("long"))).select("source", "series_id", "t"),
    "case_when": lambda s, d: T(s, d, E).select("event_id", F.when(F.col("value") < 10, "low").when(F.col("value") < 100, "middle").otherwise("high").alias("band"), F.nullif("event_type", F.lit("view")).alias("not_view")),
    "join_broadcast_dims": join_broadcast_dims,
    "join_scores_pair": join_scores_pair,
    "join_left_grid": lambda s, d: T(s, d, "nation").join(T(s, d, "supplier"), F.col("n_nationkey") == F.col("s_nationkey"), "left").groupBy("n_name").agg(F.count("s_suppkey").alias("suppliers")),
    "join_full_overlap": lambda s, d: sel.central(naive(s, d), "2/5").select("source", "series_id", "origin", F.lit(1).alias("a")).join(sel.bottom(naive(s, d), "2/5").select("source", "series_id", "origin", F.lit(1).alias("b")), ["source", "series_id", "origin"], "full").groupBy("a", "b").agg(F.count("*").alias("n")),
    "join_semi_selected": lambda s, d: grid(s, d).join(naive(s, d).where("rfl < 2e8").select("source", F.col("origin").alias("t")).distinct(), ["source", "t"], "left_semi"),
    "join_anti": lambda s, d: T(s, d, "customer").join(T(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"),
    "join_cross_grid": lambda s, d: T(s, d, "region").crossJoin(F.broadcast(s.range(3).withColumnRenamed("id", "k"))).select("r_name", "k"),
    "join_range_bucketed": join_range_bucketed,
    "join_asof_events": join_asof_events,
    "join_lateral_topn": join_lateral,
    "join_shift_equals_lag": join_shift,
    "join_salted": join_salted,
    "agg_slot_sum": lambda s, d: T(s, d, E).groupBy("event_type", F.date_trunc("day", "ts").alias("day")).agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")).withColumn("day", F.col("day").cast("date")),
    "agg_collect_sorted": lambda s, d: T(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), "|").alias("names")),
    "agg_filter": lambda s, d: T(s, d, E).groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("large"), F.sum(F.when(F.col("value") > 50, F.round(F.col("value") * 100).cast("long"))).alias("cents")),
    "agg_count_distinct": lambda s, d: T(s, d, E).groupBy("event_type").agg(F.count_distinct("user_id").alias("users")),
    "agg_hll": lambda s, d: T(s, d, E).groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users")),
    "agg_quantile_exact": lambda s, d: naive(s, d).groupBy("source").agg(*(F.round(F.percentile("rfl", F.lit(q)), 3).alias(f"q{int(q * 100)}") for q in (0.1, 0.5, 0.9))),
    "agg_quantile_kll": agg_kll,
    "agg_moments": lambda s, d: T(s, d, E).groupBy("event_type").agg(F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_pop("value"), 6).alias("sd"), F.round(F.corr("user_id", "value"), 6).alias("r"), F.round(F.covar_pop("user_id", "value"), 3).alias("cov")),
    "agg_regr": lambda s, d: T(s, d, E).groupBy("event_type").agg(F.round(F.regr_slope("value", "user_id"), 6).alias("slope"), F.round(F.regr_intercept("value", "user_id"), 5).alias("icpt")),
    "agg_min_by": lambda s, d: naive(s, d).groupBy("source").agg(F.min_by("origin", F.struct("rfl", "origin")).alias("easiest"), F.max_by("origin", F.struct("rfl", "origin")).alias("hardest")),
    "agg_rollup": lambda s, d: T(s, d, E).withColumn("big", F.col("value") > 50).rollup("event_type", "big").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("g")),
    "agg_cube": lambda s, d: T(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("g")),
    "agg_grouping_sets": lambda s, d: (T(s, d, "orders").createOrReplaceTempView("orders"), s.sql("select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())"))[1],
    "agg_vector_mean": vector_mean,
    "pivot_grid": lambda s, d: T(s, d, E).groupBy((F.col("user_id") % 5).alias("b")).pivot("event_type", ["click", "view"]).agg(F.count("event_id")),
    "unpivot_metrics": lambda s, d: T(s, d, "part").groupBy("p_type").agg(F.min("p_size").alias("least"), F.max("p_size").alias("most")).unpivot(["p_type"], ["least", "most"], "metric", "value"),
    "score_histogram": lambda s, d: naive(s, d).groupBy("source", F.width_bucket("rfl", F.lit(0.0), F.lit(1e9), F.lit(20)).alias("bin")).agg(F.count("*").alias("n")),
    "win_rank_family": lambda s, d: (lambda w: T(s, d, "supplier").select("s_suppkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(w.orderBy("s_nationkey", "s_suppkey")).alias("rn"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.ntile(4).over(w.orderBy("s_nationkey", "s_suppkey")).alias("nt")))(Window.partitionBy((F.col("s_suppkey") % 3)).orderBy("s_nationkey")),
    "win_lag_lead": lambda s, d: (lambda w: grid(s, d).select("source", "t", F.lag("y", 2).over(w).alias("a"), F.lead("y", 3).over(w).alias("b"), F.first("y").over(w).alias("f"), F.nth_value("y", 2).over(w).alias("n2")))(Window.partitionBy("source", "series_id").orderBy("t")),
    "win_ffill": lambda s, d: (lambda w: grid(s, d, "orders_weekly").select("source", "series_id", "t", F.last("y", True).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("y")))(Window.partitionBy("source", "series_id").orderBy("t")),
    "win_rows_future": lambda s, d: (lambda w: grid(s, d).select("source", "t", F.sum("y").over(w).alias("ahead")))(Window.partitionBy("source", "series_id").orderBy("t").rowsBetween(1, 24)),
    "win_range_interval": lambda s, d: (lambda w: T(s, d, E).select("event_id", F.count("*").over(w).alias("n")))(Window.partitionBy("event_type").orderBy(F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)")).rangeBetween(-3600, 0)),
    "win_prefix_equals_frame": prefix_frame,
    "topk_windows": lambda s, d: plain(naive(s, d)).orderBy(F.desc("rfl"), "source", "origin").limit(10),
    "limit_offset": lambda s, d: T(s, d, "nation").orderBy("n_name").offset(5).limit(7).select("n_name"),
    "group_topk": group_topk,
    "set_union_corpora": lambda s, d: grid(s, d).withColumn("corpus", F.lit("events")).unionByName(grid(s, d, "orders_weekly"), allowMissingColumns=True).groupBy("corpus").agg(F.count("*").alias("n")),
    "set_intersect_refs": lambda s, d: sel.central(naive(s, d), "2/5").select("source", "origin").intersect(sel.central(naive(s, d), "2/5", by=None).select("source", "origin")),
    "set_except_holdout": lambda s, d: naive(s, d, held_out=False).select("source", "origin").exceptAll(naive(s, d).select("source", "origin")),
    "distinct_texts": lambda s, d: T(s, d, "documents").groupBy(F.xxhash64("text").alias("h"), "text").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).select("doc_id", "copies"),
    "fn_dates": lambda s, d: T(s, d, E).select("event_id", F.hour("ts").alias("h"), F.dayofweek("ts").alias("dow"), F.last_day("ts").alias("eom"), F.expr("timestampdiff(HOUR, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)").alias("slot"), F.date_format("ts", "yyyy-MM").alias("ym")),
    "fn_math": lambda s, d: T(s, d, E).select("event_id", F.round(F.log(F.col("value") + 1), 6).alias("l"), F.round(F.sqrt("value"), 6).alias("r"), F.pmod(-F.col("user_id"), F.lit(7)).alias("p"), F.greatest(F.col("user_id"), F.lit(20)).alias("g"), F.floor("value").alias("f"), F.round(F.try_divide(F.lit(1.0), F.col("user_id") % 3), 6).alias("q")),
    "fn_strings": lambda s, d: T(s, d, "customer").select("c_custkey", F.concat_ws("-", F.lower("c_name"), "c_mktsegment").alias("a"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("b"), F.length("c_name").alias("n"), F.substring("c_name", 1, 4).alias("c"), F.sha2("c_name", 256).alias("h"), F.levenshtein("c_mktsegment", F.lit("MACHINERY")).alias("d")),
    "fn_arrays": lambda s, d: T(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.array_position(F.transform(F.slice("embedding", 1, 8), lambda x: (x > 0).cast("int")), 1).cast("int").alias("first_pos"), F.exists("embedding", lambda x: x > 0.3).alias("big")),
    "fn_array_dot": lambda s, d: T(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with("embedding", "embedding", lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda a, x: a + x), 6).alias("dot")),
    "fn_maps": fn_maps,
    "fn_json_props": lambda s, d: T(s, d, E).select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.k").cast("int").alias("k2"), F.variant_get(F.parse_json("props"), "$.k", "int").alias("k3")),
    "fn_struct_order": lambda s, d: naive(s, d).groupBy("source").agg(F.min(F.struct("rfl", "series_id", "origin")).alias("m")).select("source", "m.origin"),
    "udf_dot": udf_dot,
    "udaf_masked_mean": udaf_masked_mean,
    "udtf_windows": sqlapi.udtf_windows,
    "sql_select_central": sqlapi.select_central,
}

_N = scores_sql("events_hourly")
_R = f"{_N}, r as (select *, count(*) over (partition by source) as n, row_number() over (partition by source order by rfl, series_id, origin) as k from ok)"
_K = lambda a: f"greatest(1, (2 * {a} * n + 10) // 20)"  # noqa: E731  a tenths
_C = lambda a: f"k > (n - {_K(a)}) // 2 and k <= (n - {_K(a)}) // 2 + {_K(a)}"
_LEN = 720 - 48 - 24
ORACLES = {
    **{f"scan_{t}": f"select count(*) as n from {t}" for t in tb.NAMES},
    **{f"{f}_roundtrip": "select s_suppkey, s_name, s_nationkey from supplier" for f in ("csv", "json", "orc")},
    "score_store": f"with {_N} select * from scores where source = 'view'",
    "project_basic": "select event_id, user_id % 10 as bucket, upper(event_type) as kind from events",
    "filter_basic": "select event_id from events where (event_type in ('view', 'click') and value between 10 and 20 and event_type not like '%ew') or regexp_matches(event_type, '^pur')",
    "filter_null_safe": f"with {cells_sql('supplier_weekly')} select source, series_id, t from cells where y is null",
    "case_when": "select event_id, case when value < 10 then 'low' when value < 100 then 'middle' else 'high' end as band, nullif(event_type, 'view') as not_view from events",
    "join_broadcast_dims": "select s_suppkey, n_name, r_name from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey",
    "join_scores_pair": f"with {_N} select count(*) as windows, count(rfl) as equal from scores",
    "join_left_grid": "select n_name, count(s_suppkey) as suppliers from nation left join supplier on n_nationkey = s_nationkey group by 1",
    "join_full_overlap": f"with {_R}, x as (select case when {_C(4)} then 1 end as a, case when k <= {_K(4)} then 1 end as b from r) select a, b, count(*) as n from x where a is not null or b is not null group by 1, 2",
    "join_semi_selected": f"with {_N} select * from cells c where exists (select 1 from ok where ok.source = c.source and ok.origin = c.t and rfl < 2e8)",
    "join_anti": "select c_custkey from customer where c_custkey not in (select o_custkey from orders)",
    "join_cross_grid": "select r_name, k from region cross join (select unnest(range(0, 3)) as k)",
    "join_range_bucketed": "select lo, count(*) as n from events join (select unnest(range(0, 700, 50)) as lo) on date_diff('hour', timestamp '2024-01-01', ts) between lo and lo + 3 group by 1",
    "join_asof_events": "select p.event_id, arg_max(v.event_id, (v.ts, v.event_id)) as view_id from events p left join events v on v.user_id = p.user_id and v.event_type = 'view' and v.ts <= p.ts where p.event_type = 'purchase' group by 1",
    "join_lateral_topn": f"with {_N} select source, origin from (select source, origin, row_number() over (partition by source order by rfl desc, origin) as k from ok) where k <= 2",
    "join_shift_equals_lag": f"with {cells_sql('events_hourly')} select count(*) as slots, cast(0 as bigint) as differing from cells where t >= 24",
    "join_salted": "select s_nationkey, cast(sum(l_quantity) as bigint) as q from lineitem join supplier on l_suppkey = s_suppkey group by 1",
    "agg_slot_sum": "select event_type, cast(ts as date) as day, cast(sum(cast(round(value * 100) as bigint)) as bigint) as cents from events group by 1, 2",
    "agg_collect_sorted": "select n_regionkey, string_agg(n_name, '|' order by n_name) as names from nation group by 1",
    "agg_filter": "select event_type, count(*) filter (value > 50) as large, cast(sum(cast(round(value * 100) as bigint)) filter (value > 50) as bigint) as cents from events group by 1",
    "agg_count_distinct": "select event_type, count(distinct user_id) as users from events group by 1",
    "agg_quantile_exact": f"with {_N} select source, " + ", ".join(f"round(quantile_cont(rfl, {q / 100}), 3) as q{q}" for q in (10, 50, 90)) + " from ok group by 1",
    "agg_quantile_kll": f"with {_N} select distinct source, true as near from ok",
    "agg_moments": "select event_type, round(avg(value), 6) as mean, round(stddev_pop(value), 6) as sd, round(corr(user_id, value), 6) as r, round(covar_pop(user_id, value), 3) as cov from events group by 1",
    "agg_regr": "select event_type, round(regr_slope(value, user_id), 6) as slope, round(regr_intercept(value, user_id), 5) as icpt from events group by 1",
    "agg_min_by": f"with {_N} select source, arg_min(origin, (rfl, origin)) as easiest, arg_max(origin, (rfl, origin)) as hardest from ok group by 1",
    "agg_rollup": "select event_type, big, count(*) as n, cast(grouping_id(event_type, big) as integer) as g from (select event_type, value > 50 as big from events) group by rollup (event_type, big)",
    "agg_cube": "select o_orderstatus, o_orderpriority, count(*) as n, cast(grouping_id(o_orderstatus, o_orderpriority) as integer) as g from orders group by cube (o_orderstatus, o_orderpriority)",
    "agg_grouping_sets": "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())",
    "agg_vector_mean": "select label, cast(i as integer) as i, round(avg(v), 9) as mean from (select label, unnest(range(0, 64)) as i, cast(unnest(embedding) as double) as v from embeddings) group by 1, 2",
    "pivot_grid": "select user_id % 5 as b, nullif(count(*) filter (event_type = 'click'), 0) as click, nullif(count(*) filter (event_type = 'view'), 0) as view from events group by 1",
    "unpivot_metrics": "select p_type, 'least' as metric, min(p_size) as value from part group by 1 union all select p_type, 'most', max(p_size) from part group by 1",
    "score_histogram": f"with {_N} select source, case when rfl >= 1e9 then 21 else cast(floor(rfl / 5e7) as bigint) + 1 end as bin, count(*) as n from ok group by 1, 2",
    "win_rank_family": "select s_suppkey, rank() over w as r, dense_rank() over w as dr, row_number() over (partition by s_suppkey % 3 order by s_nationkey, s_suppkey) as rn, round(percent_rank() over w, 9) as pr, round(cume_dist() over w, 9) as cd, ntile(4) over (partition by s_suppkey % 3 order by s_nationkey, s_suppkey) as nt from supplier window w as (partition by s_suppkey % 3 order by s_nationkey)",
    "win_lag_lead": f"with {cells_sql('events_hourly')} select source, t, lag(y, 2) over w as a, lead(y, 3) over w as b, first_value(y) over w as f, nth_value(y, 2) over w as n2 from cells window w as (partition by source, series_id order by t)",
    "win_ffill": f"with {cells_sql('orders_weekly')} select source, series_id, t, last_value(y ignore nulls) over (partition by source, series_id order by t rows unbounded preceding) as y from cells",
    "win_rows_future": f"with {cells_sql('events_hourly')} select source, t, cast(sum(y) over (partition by source, series_id order by t rows between 1 following and 24 following) as bigint) as ahead from cells",
    "win_range_interval": "select event_id, count(*) over (partition by event_type order by date_diff('second', timestamp '2024-01-01', date_trunc('second', ts)) range between 3600 preceding and current row) as n from events",
    "win_prefix_equals_frame": f"with {cells_sql('events_hourly')} select count(*) as slots, cast(0 as bigint) as differing from cells where t < 696",
    "topk_windows": f"with {_N} select * from ok order by rfl desc, source, origin limit 10",
    "limit_offset": "select n_name from nation order by n_name limit 7 offset 5",
    "group_topk": f"with {_N} select source, series_id, origin, m, rfl from (select *, row_number() over (partition by source order by rfl desc, series_id, origin) as k from ok) where k <= 3",
    "set_union_corpora": f"select 'events' as corpus, count(*) as n from (with {cells_sql('events_hourly')} select * from cells) union all select null, count(*) from (with {cells_sql('orders_weekly')} select * from cells)",
    "set_intersect_refs": f"with {_N}, r as (select *, count(*) over (partition by source) as n, row_number() over (partition by source order by rfl, series_id, origin) as k from ok), g as (select *, count(*) over () as n, row_number() over (order by rfl, source, series_id, origin) as k from ok) select source, origin from r where {_C(4)} intersect select source, origin from g where {_C(4)}",
    "set_except_holdout": f"with {cells_sql('events_hourly')} select source, unnest(range({_LEN - 24 + 1}, {_LEN + 1})) as origin from series",
    "distinct_texts": "select min(doc_id) as doc_id, count(*) as copies from documents group by text",
    "fn_dates": "select event_id, cast(hour(ts) as integer) as h, cast(dayofweek(ts) + 1 as integer) as dow, last_day(ts) as eom, date_diff('hour', timestamp '2024-01-01', ts) as slot, strftime(ts, '%Y-%m') as ym from events",
    "fn_math": "select event_id, round(ln(value + 1), 6) as l, round(sqrt(value), 6) as r, ((-user_id % 7) + 7) % 7 as p, greatest(user_id, 20) as g, cast(floor(value) as bigint) as f, round(case when user_id % 3 <> 0 then 1.0::double / (user_id % 3) end, 6) as q from events",
    "fn_strings": "select c_custkey, lower(c_name) || '-' || c_mktsegment as a, regexp_extract(c_name, '([0-9]+)', 1) as b, cast(length(c_name) as integer) as n, substring(c_name, 1, 4) as c, sha256(c_name) as h, cast(levenshtein(c_mktsegment, 'MACHINERY') as integer) as d from customer",
    "fn_arrays": "select vec_id, cast(len(list_filter(embedding, lambda x: x > 0)) as integer) as pos, cast(coalesce(list_position(list_transform(embedding[1:8], lambda x: cast(x > 0 as integer)), 1), 0) as integer) as first_pos, len(list_filter(embedding, lambda x: x > 0.3)) > 0 as big from embeddings",
    "fn_array_dot": "select vec_id, round(list_inner_product(cast(embedding as double[]), cast(embedding as double[])), 6) as dot from embeddings",
    "fn_maps": "select n_nationkey, k, v from (select n_nationkey, cast(k as integer) as k, cast(k * n_nationkey + k as integer) as v from nation cross join (select unnest(range(1, 4)) as k)) where v % 2 = 0",
    "fn_json_props": "select event_id, cast(json_extract(props, '$.k') as integer) as k, cast(json_extract(props, '$.k') as integer) as k2, cast(json_extract(props, '$.k') as integer) as k3 from events",
    "fn_struct_order": f"with {_N} select source, arg_min(origin, (rfl, series_id, origin)) as origin from ok group by 1",
    "udf_dot": "select vec_id, round(list_inner_product(cast(embedding as double[]), cast(embedding as double[])), 5) as norm2 from embeddings",
    "udaf_masked_mean": f"with {cells_sql('supplier_weekly')} select source, round(avg(y), 6) as mean from cells group by 1",
    "udtf_windows": "select unnest(range(0, 29, 4)) as origin, 'a' as series_id union all select unnest(range(0, 19, 4)), 'b'",
    "sql_select_central": f"with {_R} select source, series_id, origin from r where {_C(8)}",
}
