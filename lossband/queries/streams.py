"""Streams run to their end, against the same result in batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import select as sel
from ..operators.scoring import SeasonalNaive, score
from ..sources.tables import keep, load
from ..streaming import slots as st
from .common import grid, plain, scores_sql

#: A bound beyond the length of the data: what the stream holds back at its end would otherwise be missing.
LATE = "60 days"


def _ended(df, mode="update"):
    """Update mode gives every group once, for the whole file is one batch."""
    return st.run_once(df, mode)


def stream_tumbling(spark, sf):
    return _ended(st.tumbling(st.events(spark, sf), late=LATE))


def stream_sliding(spark, sf):
    return _ended(st.sliding(st.events(spark, sf), late=LATE))


def stream_session(spark, sf):
    return _ended(st.sessions(st.events(spark, sf), late=LATE), "complete")


def stream_dedup(spark, sf):
    rows = st.events(spark, sf)
    return _ended(st.deduplicated(rows.unionByName(st.events(spark, sf)), late=LATE).select("event_id", "user_id", "event_type"), "append")


def stream_join(spark, sf):
    rows = lambda: st.events(spark, sf)
    return _ended(st.joined(rows().where("event_type = 'view'"), rows().where("event_type = 'purchase'"), late=LATE), "append")


def _slot_stream(spark, sf):
    from ..sources.tables import shared_dir
    import uuid

    path = f"{shared_dir(spark)}/lossband-streams/slots-{uuid.uuid4().hex[:12]}"
    grid(spark, sf).write.parquet(path)
    return spark.readStream.schema("source string, series_id string, t long, y long").parquet(path)


def stream_online_scores(spark, sf):
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return st.run_once(st.online_scores(_slot_stream(spark, sf), 48, 24, 24), "append")
    finally:
        spark.conf.set(name, before) if before else spark.conf.unset(name)


def stream_keep_within(spark, sf):
    """Scores of the stream inside cuts that a batch froze: the stratified selection again, where no score ties a cut."""
    scores = score(grid(spark, sf), SeasonalNaive(24), 48, 24, held_out=False)
    kept = sel.central(scores, "4/5")
    cuts = keep(kept.groupBy("source").agg(F.min("rfl").alias("lo"), F.max("rfl").alias("hi")), "frozen")
    stored = keep(plain(scores), "stream-scores")
    path = stored.inputFiles()[0].rsplit("/", 1)[0]
    rows = spark.readStream.schema(stored.schema).parquet(path)
    return st.run_once(st.keep_within(rows, cuts).select("source", "series_id", "origin"), "append")


def stream_late_rows(spark, sf):
    """Hourly sums where one event in a hundred comes after all others: those whose hour the watermark has closed are left out."""
    rows = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    late = F.col("event_id") % 100 == 0
    got = st.run_in_turns([rows.where(~late), rows.where(late)], lambda r: st.tumbling(r, late="2 hours"))
    last = got.groupBy("source", "start").agg(F.max_by(F.struct("y", "n"), F.struct("turn", "epoch")).alias("x"))
    return last.select("source", "start", "x.y", "x.n")


def stream_cutoff_refresh(spark, sf):
    """Scores that come in two batches; the share of them between the cuts that the merged sketches give, near to four fifths."""
    from ..sources.tables import shared_dir
    import uuid

    scores = keep(plain(score(grid(spark, sf), SeasonalNaive(24), 48, 24)), "refresh")
    refresh = st.CutoffRefresh(0.1, 0.9, f"{shared_dir(spark)}/lossband-streams/cuts-{uuid.uuid4().hex[:12]}")
    for i in (0, 1):
        refresh(scores.where(F.col("origin") % 2 == i), i)
    rows = scores.where("rfl is not null").join(F.broadcast(refresh.cuts(spark)), "source")  # one row a source
    share = F.avg(F.col("rfl").between(F.col("lo"), F.col("hi")).cast("int"))
    return rows.groupBy("source").agg(F.count("*").alias("windows"), F.round(share, 1).alias("share"))


QUERIES = {
    "stream_late_rows": stream_late_rows,
    "stream_cutoff_refresh": stream_cutoff_refresh,
    "stream_tumbling": stream_tumbling,
    "stream_sliding": stream_sliding,
    "stream_session": stream_session,
    "stream_dedup": stream_dedup,
    "stream_join": stream_join,
    "stream_online_scores": stream_online_scores,
    "stream_keep_within": stream_keep_within,
}
ORACLES = {
    "stream_late_rows": """with e as (select *, event_id % 100 = 0 as late, date_trunc('hour', ts) as start from events), w as (select max(ts) - interval 2 hours as mark from e where not late)
        select event_type as source, start, cast(sum(cast(round(value * 100) as bigint)) as bigint) as y, count(*) as n from e, w where not late or start + interval 1 hour > mark group by 1, 2""",
    "stream_cutoff_refresh": f"with {scores_sql('events_hourly')} select source, count(*) as windows, round(avg(case when rfl between lo and hi then 1 else 0 end), 1) as share from ok join (select source as s, quantile_disc(rfl, 0.1) as lo, quantile_disc(rfl, 0.9) as hi from ok group by 1) q on q.s = source group by 1",
    "stream_tumbling": "select event_type as source, date_trunc('hour', ts) as start, cast(sum(cast(round(value * 100) as bigint)) as bigint) as y, count(*) as n from events group by 1, 2",
    "stream_sliding": "select event_type as source, start, count(*) as n from (select event_type, ts, date_trunc('hour', ts) - to_hours(cast(k as integer)) as start from events cross join (select unnest(range(0, 6)) as k)) group by 1, 2",
    "stream_session": """with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as f from events),
        s as (select user_id, ts, sum(f) over (partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, min(ts) as start, count(*) as n from s group by user_id, k""",
    "stream_dedup": "select event_id, user_id, event_type from events",
    "stream_join": "select a.event_id as a, b.event_id as b, a.user_id from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'view' and b.event_type = 'purchase'",
    "stream_online_scores": f"with {scores_sql('events_hourly', 'cast(e as double) * e', held_out=False)} select * from scores",
    "stream_keep_within": f"""with {scores_sql('events_hourly', held_out=False)}, r as (select *, count(*) over (partition by source) as n, row_number() over (partition by source order by rfl, series_id, origin) as k from ok),
        c as (select source, min(rfl) as lo, max(rfl) as hi from r where k > (n - greatest(1, (8 * n + 5) // 10)) // 2 and k <= (n - greatest(1, (8 * n + 5) // 10)) // 2 + greatest(1, (8 * n + 5) // 10) group by 1)
        select o.source, series_id, origin from ok o join c on c.source = o.source and rfl between lo and hi""",
}
