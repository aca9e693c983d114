"""Streaming forms, run over the events table with availableNow; and sources and sinks."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import functions as F

from evsketch.operators import discretize, estimate
from evsketch.operators import registers as rg
from evsketch.sources import tables
from evsketch.spec import SketchSpec
from evsketch.streaming import streams as st
from evsketch.workloads.common import geo, query, regs, seeded
from evsketch.workloads.methods import z6
from evsketch.workloads.scenarios import USERS, dense

SPEC = SketchSpec(k=16)
def _day_window():
    return F.window("ts", "1 day")


def _day(df):
    return df.withColumn("day", F.date_format("window.start", "yyyy-MM-dd")).drop("window")


def _answers(regs_, by):
    return z6(estimate.estimate_geometric(rg.with_seed_draws(regs_, SPEC, by), SPEC, by))


_DAILY = geo(seeded(regs(USERS, "user_id", "day", 16), "day", 16), 16, "day")


@query(_DAILY)
def st_tumbling(spark, sf_dir):
    regs_ = st.stream_registers(tables.stream_events(spark, sf_dir), "user_id", SPEC, _day_window(), "1 hour")
    return _answers(_day(st.run_available(regs_)), ["day"])


_SLIDE = "(select strftime(cast(day as date) - cast(d as integer), '%Y-%m-%d') as day, user_id from " + USERS + " cross join range(7) s(d))"


@query(geo(seeded(regs(_SLIDE, "user_id", "day", 16), "day", 16), 16, "day"))
def st_sliding(spark, sf_dir):
    """Seven-day windows that start every day."""
    regs_ = st.stream_registers(tables.stream_events(spark, sf_dir), "user_id", SPEC, F.window("ts", "7 days", "1 day"), "1 hour")
    return _answers(_day(st.run_available(regs_)), ["day"])


_SESSIONS = "(select event_type, event_id, sum(fresh) over (partition by event_type order by ts rows unbounded preceding) as n from (select event_type, event_id, ts, case when ts - lag(ts) over (partition by event_type order by ts) < interval 2 hours then 0 else 1 end as fresh from events))"


@query(f"select event_type, count(*) as sessions, cast(sum(k) as bigint) as registers from (select event_type, n, count(distinct cast('0x' || substr(md5('s1:' || cast(event_id as varchar)), 17, 8) as bigint) % 16) as k from {_SESSIONS} group by all) group by event_type")
def st_session(spark, sf_dir):
    """Sessions of an event type with a two-hour gap: their number, and their occupied registers."""
    wide = st.session_registers(tables.stream_events(spark, sf_dir), "event_type", "event_id", "2 hours", SPEC, "1 hour")
    rows = st.long_form(st.run_available(wide), SPEC, ["event_type", "window"])
    each = rows.groupBy("event_type", "window").agg(F.count("*").alias("k"))
    return each.groupBy("event_type").agg(F.count("*").alias("sessions"), F.sum("k").alias("registers"))


def _folder(spark) -> str:
    """A new folder in the cluster's shared place; a local one only where the session names none."""
    shared = spark.conf.get("spark.checkpoint.dir", None) or tempfile.gettempdir()
    return f"{shared.rstrip('/')}/evsketch-{uuid.uuid4().hex}"


@query(_DAILY)
def st_update_upsert(spark, sf_dir):
    """Update mode into a sketch table by foreachBatch, answered on reading."""
    path = _folder(spark)
    regs_ = st.stream_registers(tables.stream_events(spark, sf_dir), "user_id", SPEC, _day_window(), "1 hour")
    day = regs_.withColumn("day", F.date_format("window.start", "yyyy-MM-dd"))
    run = day.writeStream.outputMode("update").foreachBatch(st.upsert_into(f"{path}/regs", ["day"])).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    run.awaitTermination()
    return _answers(st.query_state(spark, f"{path}/regs", ["day"]), ["day"])


@query("select cast(0 as bigint) as differing")
def st_late_rows(spark, sf_dir):
    """Registers of the stream in time order and in reverse order, which a state never notices."""
    events = tables.load(spark, sf_dir, "events")
    path = _folder(spark)
    events.orderBy(F.desc("ts")).write.parquet(f"{path}/events.parquet")
    a = st.run_available(st.stream_registers(tables.stream_events(spark, sf_dir), "user_id", SPEC))
    b = st.run_available(st.stream_registers(tables.stream_events(spark, path), "user_id", SPEC))
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").alias("differing"))


@query("select cast(0 as bigint) as differing")
def st_equals_batch(spark, sf_dir):
    """Registers of the stream and of the batch."""
    a = st.run_available(st.stream_registers(tables.stream_events(spark, sf_dir), "user_id", SPEC)).select("reg", "w")
    b = rg.registers(tables.load(spark, sf_dir, "events"), "user_id", spec=SPEC)
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").alias("differing"))


@query("select cast(0 as bigint) as differing, true as mismatch_raises")
def io_sketch_roundtrip(spark, sf_dir):
    """A stored sketch is read back equal, and another spec's is refused."""
    from evsketch.spec import SpecMismatch

    path = _folder(spark)
    q = discretize.shift_round_registers(dense(tables.load(spark, sf_dir, "lineitem"), "l_orderkey", SPEC), SPEC)
    tables.save_sketch(q, SPEC, path)
    back = tables.load_sketch(spark, path, SPEC).select("reg", "q")
    try:
        tables.load_sketch(spark, path, SPEC.with_(k=32))
        raised = False
    except SpecMismatch:
        raised = True
    return q.select("reg", "q").exceptAll(back).union(back.exceptAll(q.select("reg", "q"))).agg(F.count("*").alias("differing")).withColumn("mismatch_raises", F.lit(raised))


def _roundtrip(spark, sf_dir, fmt):
    path = _folder(spark)
    df = tables.load(spark, sf_dir, "customer").select("c_custkey", "c_name", "c_nationkey")
    df.write.format(fmt).save(path)
    back = tables.load_items(spark, path, fmt, "c_custkey long, c_name string, c_nationkey int")
    a, b = (rg.registers(x, ["c_name", "c_nationkey"], spec=SPEC) for x in (df, back))
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").alias("differing"))


@query("select cast(0 as bigint) as differing")
def io_csv_items(spark, sf_dir):
    return _roundtrip(spark, sf_dir, "csv")


@query("select cast(0 as bigint) as differing")
def io_json_items(spark, sf_dir):
    return _roundtrip(spark, sf_dir, "json")


@query("select cast(0 as bigint) as differing")
def io_orc_items(spark, sf_dir):
    return _roundtrip(spark, sf_dir, "orc")
