"""Queries q130 - q139: streams run to their end, against batch results."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor

from cubelens.operators import insert
from cubelens.operators.rank import build_ranks
from cubelens.queries import base as Q
from cubelens.sources import catalog as C
from cubelens.storage import materialize
from cubelens.streaming import streams as S

queries, oracles = {}, {}
FILES = 4


def events(spark, sf):
    e = C.table(spark, sf, "events")
    return e.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("cents", F.round(F.col("value") * 100).cast("long"))


def stream(spark, df, files=FILES, key="event_id"):
    path = Q.once(spark, ("files", df.semanticHash(), files), lambda: S.split_files(df, files, key))
    return S.source(spark, path, df.schema)


def q(sql=None):
    def keep(fn):
        queries[fn.__name__] = fn
        if sql:
            oracles[fn.__name__] = sql
        return fn

    return keep


_CENTS = "CAST(round(value * 100) AS BIGINT)"


@q("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def q130_stream_tumbling(spark, sf):
    s = stream(spark, events(spark, sf)).withWatermark("ts", "400 days")
    out = S.run_append(s.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n")), "complete")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@q("SELECT CAST(to_timestamp(s * 21600) AT TIME ZONE 'UTC' AS TIMESTAMP) AS start, count(*) AS n FROM (SELECT unnest(range(CAST(floor(epoch(ts) / 21600) AS BIGINT) - 3, CAST(floor(epoch(ts) / 21600) AS BIGINT) + 1)) AS s FROM events) GROUP BY 1")
def q131_stream_sliding(spark, sf):
    out = S.run_append(stream(spark, events(spark, sf)).groupBy(F.window("ts", "1 day", "6 hours")).agg(F.count("*").alias("n")), "complete")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@q("WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 12 HOUR THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(f) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def q132_stream_session(spark, sf):
    s = stream(spark, events(spark, sf)).groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count("*").alias("n"))
    return S.run_append(s, "complete").select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@q("SELECT date_trunc('day', ts) AS start, count(*) AS n FROM events, (SELECT quantile_cont(epoch_us(ts), 0.5) AS mid, max(ts) AS last FROM events) WHERE epoch_us(ts) >= mid AND date_trunc('day', ts) + INTERVAL 1 DAY <= last - INTERVAL 1 DAY GROUP BY 1")
def q133_stream_late(spark, sf):
    """The newer half of the events comes first, in two batches; the older half is late, and its rows are dropped; windows behind the watermark are final.

    A batch is held against the watermark that the batch before it began with.
    """
    d = events(spark, sf)
    us = F.unix_micros("ts")
    mid, high = d.agg(F.percentile(us, 0.5), F.percentile(us, 0.75)).first()
    parts = [d.filter(us >= (high or 0)), d.filter((us >= (mid or 0)) & (us < (high or 0))), d.filter(us < (mid or 0))]
    s = S.source(spark, Q.once(spark, ("late", sf), lambda: S.in_order(parts)), d.schema, 2).withWatermark("ts", "1 day")
    out = S.run_append(s.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n")), "append")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@q("SELECT event_id, user_id, event_type FROM events")
def q134_stream_dedup(spark, sf):
    """A third of the events arrives twice; each is kept once."""
    d = events(spark, sf)
    twice = d.unionByName(d.filter("event_id % 3 = 0"))
    s = stream(spark, twice).withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"])
    return S.run_append(s).select("event_id", "user_id", "event_type")


@q(f"SELECT c_mktsegment, count(*) AS n, CAST(sum({_CENTS}) AS BIGINT) AS cents FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def q135_stream_static_join(spark, sf):
    s = stream(spark, events(spark, sf)).join(C.table(spark, sf, "customer"), F.col("user_id") == F.col("c_custkey"))
    return S.run_append(s.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("cents").alias("cents")), "complete")


_SPECS = [C.LOG["value"], C.LOG["user_id"]]
_RANKED = f"WITH r AS (SELECT {', '.join(f'''row_number() OVER (ORDER BY {s.order_sql()}, md5(concat_ws(':', '{s.name}', CAST(event_id AS VARCHAR))), event_id) - 1 AS {s.rank}''' for s in _SPECS)}, greatest(0, CAST(ceil(log2(count(*) OVER ())) AS INT) - 7) AS sh FROM events) "


@q(_RANKED + " UNION ALL ".join(f"SELECT '{s.name}' AS dim, CAST({s.rank} >> sh AS INT) AS bucket, count(*) AS cnt FROM r GROUP BY ALL" for s in _SPECS))
def q136_stream_histogram(spark, sf):
    d = build_ranks(C.table(spark, sf, "events"), _SPECS, C.LOG_KEY)
    d = materialize(d.select("event_id", *[s.rank for s in _SPECS]))
    return S.stream_histogram(stream(spark, d), _SPECS, d.count(), 7)


@q(f"WITH {Q.cube_sql(Q.DIMS, Q.BINS)} SELECT * FROM cube")
def q137_stream_cube(spark, sf):
    d = Q.binned(spark, sf, Q.DIMS, Q.BINS).select("l_orderkey", *[s.bin for s in Q.DIMS])
    return S.stream_cube(stream(spark, d, key="l_orderkey"), Q.DIMS, Q.BINS)


class Totals(StatefulProcessor):
    """Rows and cents of a user so far, kept between batches."""

    def init(self, handle) -> None:
        self.total = handle.getValueState("total", "n long, cents long")

    def handleInputRows(self, key, rows, timerValues):
        import pandas as pd

        n, cents = self.total.get() if self.total.exists() else (0, 0)
        for pdf in rows:
            n, cents = n + len(pdf), cents + int(pdf.cents.sum())
        self.total.update((n, cents))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "cents": [cents]})

    def close(self) -> None:
        pass


@q(f"SELECT user_id, count(*) AS n, CAST(sum({_CENTS}) AS BIGINT) AS cents FROM events GROUP BY 1")
def q138_stream_stateful(spark, sf):
    """Running totals of every user as the stream leaves them: what the last update of each says."""
    key, rocks = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    before = spark.conf.get(key)
    spark.conf.set(key, rocks)  # the only store with typed state; a setting of the query, not of the session's start
    try:
        s = stream(spark, events(spark, sf)).groupBy("user_id").transformWithStateInPandas(Totals(), "user_id long, n long, cents long", "Update", "None")
        out = S.run_append(s, "update")
    finally:
        spark.conf.set(key, before)
    return out.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("cents", "n").alias("cents"))


_NEW = "event_id % 100 = 7"


def _inserted_sql(half: int) -> str:
    new = f"{_NEW} AND (event_id // 100) % 2 = {half}"
    return (
        f"SELECT * FROM (WITH old AS (SELECT event_id, ts, row_number() OVER (ORDER BY ts, md5(concat_ws(':', 'ts', CAST(event_id AS VARCHAR))), event_id) - 1 AS rk FROM events WHERE NOT ({_NEW})), "
        "h AS (SELECT CAST(rk >> greatest(0, CAST(ceil(log2((SELECT count(*) FROM old))) AS INT) - 8) AS INT) AS bucket, count(*) AS cnt, arg_min(ts, rk) AS first_ts FROM old GROUP BY 1), "
        f"new AS (SELECT event_id, ts, coalesce((SELECT max(bucket) FROM h WHERE first_ts <= e.ts), 0) AS bucket FROM events e WHERE {new}), "
        "a AS (SELECT bucket, CAST(sum(c) AS BIGINT) AS cnt FROM (SELECT bucket, cnt AS c FROM h UNION ALL SELECT bucket, count(*) FROM new GROUP BY 1) GROUP BY 1), "
        "p AS (SELECT bucket, coalesce(sum(cnt) OVER (ORDER BY bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // (((SELECT sum(cnt) FROM a) + 15) // 16) AS bin FROM a) "
        "SELECT event_id, CAST(bin AS INT) AS b_ts FROM new JOIN p USING (bucket))"
    )


@q(" UNION ALL ".join(_inserted_sql(half) for half in (0, 1)))
def q139_stream_inserts(spark, sf):
    """Two micro-batches of new rows, each binned by remembered bounds."""
    all_rows, spec = C.table(spark, sf, "events"), C.LOG["ts"]
    old = build_ranks(all_rows.filter(f"NOT ({_NEW})"), [spec], C.LOG_KEY)
    bounds = materialize(insert.capture_bounds(old, spec, old.count(), 8), "bounds")
    new = all_rows.filter(_NEW)
    source = S.source(spark, S.in_order([new.filter(f"(event_id div 100) % 2 = {half}") for half in (0, 1)]), new.schema, 2)
    path = S.scratch(spark, "inserted")

    def one(df, k):
        out, _ = insert.bin_inserts(df, bounds, spec, 16, C.LOG_KEY)
        out.select("event_id", F.col("b_ts").cast("int").alias("b_ts")).write.mode("overwrite").parquet(f"{path}/batch={k}")

    S.run_batches(source, one)
    return spark.read.parquet(path).select("event_id", "b_ts")
