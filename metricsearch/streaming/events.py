"""Streams over the event and order tables, replayed from files, with batch twins in DuckDB.

Each query runs its stream to the end of the available files and returns what its sink holds. Sinks and checkpoints lie
in the folder all executors share.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import scan, voronoi
from ..operators.relational import _POINTS
from ..plans import index as ix
from ..plans.workloads import DEGREE, LEAF, ORACLES as _METHODS, asked
from ..sources import scratch
from ..sources.objects import objects
from ..sources.tables import load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
DELAY = "2 hours"


def _query(sql: str | None):
    def take(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return take


def replay(spark: SparkSession, sf_dir: str, table: str, files: int = 1) -> DataFrame:
    """A stream over a table written to ``files`` files, one file a trigger."""
    rows, path = load(spark, sf_dir, table), scratch.new_path(spark, f"stream-{table}", "stream")
    for i in range(files):
        part = rows if files == 1 else rows.where(F.pmod(F.col(rows.columns[0]), F.lit(files)) == i)
        part.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _timed(df: DataFrame) -> DataFrame:
    return df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", DELAY)


def drain(stream: DataFrame, mode: str = "append"):
    """Run a stream over what is there; its sink as a table, and the finished query. A complete result is replaced by
    each trigger, others are added to."""
    spark = stream.sparkSession
    out, mark = scratch.new_path(spark, "sink", "stream"), scratch.new_path(spark, "mark", "stream")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(out)

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", mark).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out), query


@_query("select (date_trunc('day', ts)::date)::varchar as day, event_type, count(*) as n from events group by all")
def stream_tumbling_counts(spark, d):
    g = _timed(replay(spark, d, "events")).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return drain(g, "complete")[0].select(F.to_date("window.start").cast("string").alias("day"), "event_type", "n")


@_query("select (day::date)::varchar as day, sum(n)::bigint as n from (select date_trunc('day', ts) as day, count(*) as n from events group by all union all select date_trunc('day', ts) - interval 1 day, count(*) from events group by all) group by day")
def stream_sliding_counts(spark, d):
    g = _timed(replay(spark, d, "events")).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return drain(g, "complete")[0].select(F.to_date("window.start").cast("string").alias("day"), "n")


@_query(
    "with s as (select user_id, ts, round(value * 100)::bigint as c, case when ts < lag(ts) over w + interval 6 hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)), "
    "n as (select user_id, c, sum(fresh) over (partition by user_id order by ts) as k from s) select user_id, count(*) as n, sum(c)::bigint as cents, k::bigint as k from n group by user_id, k"
)
def stream_session_paths(spark, d):
    """Movements closed by a gap of six hours."""
    from pyspark.sql import Window

    g = _timed(replay(spark, d, "events")).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    out = drain(g, "complete")[0]
    return out.select("user_id", "n", "cents", F.row_number().over(Window.partitionBy("user_id").orderBy("session_window.start")).cast("long").alias("k"))


@_query("select event_id from events")
def stream_dedup(spark, d):
    """Events replayed twice, kept once."""
    one = replay(spark, d, "events")
    twice = _timed(one.withColumn("again", F.explode(F.array(F.lit(0), F.lit(1))))).dropDuplicatesWithinWatermark(["event_id"])
    return drain(twice.select("event_id"))[0]


@_query(None)
def stream_late_rows(spark, d):
    """Rows dropped as late when events come in shuffled files and daily counts close two hours after the day."""
    g = _timed(replay(spark, d, "events", 3)).groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    _, query = drain(g, "append")
    late = sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"])
    return spark.createDataFrame([(int(late),)], "late long")


@_query("select user_id, count(*) as units, sum(v)::bigint as cents from (select user_id, round(value * 100)::bigint as v, lag(event_id) over (partition by user_id order by ts, event_id) as p from events) where p is not null group by user_id")
def stream_state_units(spark, d):
    """Open movements as state: each event after a user's first closes a unit."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["us", "event_id"])
        last = state.get[0] if state.exists else None
        starts = [last, *rows["us"].tolist()[:-1]]
        units = pd.DataFrame({"user_id": key[0], "t0": starts, "t1": rows["us"].tolist(), "cents": rows["cents"].tolist()})
        state.update((int(rows["us"].iloc[-1]),))
        yield units[units["t0"].notna()].astype({"t0": "int64"})

    rows = replay(spark, d, "events").select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), F.round(F.col("value") * 100).cast("long").alias("cents"))
    units = rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, t0 long, t1 long, cents long", "last long", "append", GroupStateTimeout.NoTimeout)
    return drain(units)[0].groupBy("user_id").agg(F.count("*").alias("units"), F.sum("cents").alias("cents"))


@_query(_METHODS["assign_cells"])
def stream_static_cells(spark, d):
    """The cell of each new point: centres go out once, the stream is not shuffled."""
    centers = voronoi.pick_centers(objects(spark, d, "order_points"), "euclid", 8, "random")
    days = F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).cast("double")
    points = replay(spark, d, "orders").select(F.col("o_orderkey").alias("obj_id"), F.struct((F.col("o_totalprice") / 1000.0).alias("x"), days.alias("y")).alias("obj"))
    return drain(voronoi.assign(points, centers).select("obj_id", "cell", "cell_dist"))[0].select("obj_id", "cell", F.round("cell_dist", 6).alias("cell_dist"))


@_query("select a.event_id as first_id, b.event_id as second_id from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 6 hour")
def stream_stream_pairs(spark, d):
    """Clicks and purchases of a user within six hours, by two streams with watermarks."""
    a = _timed(replay(spark, d, "events")).where("event_type = 'click'").select(F.col("event_id").alias("first_id"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = _timed(replay(spark, d, "events")).where("event_type = 'purchase'").select(F.col("event_id").alias("second_id"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return drain(a.join(b, F.expr("ua = ub and tb >= ta and tb <= ta + interval 6 hours")).select("first_id", "second_id"))[0]


@_query(f"with p as {_POINTS}, q as (select * from p order by md5(id || '|1'), id limit 5) select q.id as query_id, p.id as obj_id from q, p where sqrt((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y)) <= 25.0000137")
def stream_standing_range(spark, d):
    """Registered queries against each new object."""
    queries = asked(objects(spark, d, "order_points"), r=25.0000137)
    days = F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).cast("double")
    points = replay(spark, d, "orders").select(F.col("o_orderkey").alias("obj_id"), F.struct((F.col("o_totalprice") / 1000.0).alias("x"), days.alias("y")).alias("obj"))
    return drain(scan.range_scan(points, queries, "euclid").select("query_id", "obj_id"))[0]


@_query("select o_orderkey as obj_id from orders where o_orderkey % 4 = 0 or o_orderkey % 40 = 1")
def stream_index_inserts(spark, d):
    """Batches of new objects inserted into the touched parts of an index."""
    objs = objects(spark, d, "order_points")
    return _inserted(spark, objs.where("obj_id % 4 = 0"), objs.where("obj_id % 40 = 1"))


@_query("select o_orderkey as obj_id from orders")
def stream_index_inserts_whole(spark, d):
    objs = objects(spark, d, "order_points")
    return _inserted(spark, objs.where("obj_id % 4 <> 1"), objs.where("obj_id % 4 = 1"))


def _inserted(spark: SparkSession, base: DataFrame, objs: DataFrame) -> DataFrame:
    held = {"index": ix.build(base, "euclid", DEGREE, LEAF)}
    path, mark = scratch.new_path(spark, "stream-points", "stream"), scratch.new_path(spark, "mark", "stream")
    objs.coalesce(1).write.parquet(path)

    def insert(batch: DataFrame, number: int) -> None:
        held["index"] = ix.insert(held["index"], batch)

    query = spark.readStream.schema(objs.schema).parquet(path).writeStream.foreachBatch(insert).option("checkpointLocation", mark).trigger(availableNow=True).start()
    query.awaitTermination()
    return ix.members_table(held["index"]).select("obj_id")
