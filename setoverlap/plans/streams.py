"""Stream workloads replayed from the events table, and the same windows on the table itself.

Window ends are compared with SQL over the whole table: every window, the last one too, is emitted.
"""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from setoverlap.operators import mle, pairstats, registers
from setoverlap.plans import sql, workloads as w
from setoverlap.plans.book import query, within
from setoverlap.plans.texts import error_at
from setoverlap.session import shared_folder
from setoverlap.sources.tables import load_table
from setoverlap.streaming import windows

M, SMALL = w.M, 16
STAMP = "yyyy-MM-dd HH:mm:ss"


def _sides():
    return F.col("event_type") == "click", F.col("event_type") == "purchase"


def _closed_stream(spark, d):
    """All events, then the closing row, as two micro-batches."""
    ev = load_table(spark, d, "events")
    return windows.timed(windows.replay(spark, [ev, windows.closing_row(ev, _sides()[0])]))


def _estimates(stats):
    got = mle.mle_intersection(stats)
    return got.select(F.date_format("w.start", STAMP).alias("start"), F.date_format("w.end", STAMP).alias("end"), F.round("card_both", 2).alias("card_both"))


def _from_stream(spark, d, window, m, session=False, over=None):
    regs = windows.windowed_registers(_closed_stream(spark, d), "user_id", *_sides(), window, m, "md5", over)
    return _estimates(windows.run_to_table(windows.windowed_stats(regs, m, "md5", session)))


def _from_table(spark, d, window, m, session=False, over=None):
    ev = load_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return _estimates(windows.windowed_stats(windows.windowed_registers(ev, "user_id", *_sides(), window, m, "md5", over), m, "md5", session))


_TAGGED = "SELECT ts, user_id AS e, event_type = 'click' AS in_a, event_type = 'purchase' AS in_b FROM events WHERE event_type IN ('click', 'purchase')"


def _windows_sql(rows: str, m: int) -> str:
    """start, end, card_both of a query giving start, end, e, in_a, in_b."""
    est = sql.newton(sql.stats(sql.pair_registers(rows, m, '"start", "end"'), m, '"start", "end"'), '"start", "end"')
    return sql.rounded(est, ["card_both"], ('"start"', '"end"'), 2)


def _text(x: str) -> str:
    return f"strftime({x}, '%Y-%m-%d %H:%M:%S')"


_DAILY = _windows_sql(f"""SELECT {_text("date_trunc('day', ts)")} AS "start", {_text("date_trunc('day', ts) + INTERVAL 1 DAY")} AS "end", e, in_a, in_b FROM ({_TAGGED}) t""", M)
_HOURLY = _windows_sql(f"""SELECT {_text("date_trunc('hour', ts)")} AS "start", {_text("date_trunc('hour', ts) + INTERVAL 1 HOUR")} AS "end", e, in_a, in_b FROM ({_TAGGED}) t""", SMALL)
# the seven windows of seven days that start on midnights and hold a row
_SLIDING = _windows_sql(f"""SELECT {_text("date_trunc('day', ts) - INTERVAL 1 DAY * i")} AS "start", {_text("date_trunc('day', ts) - INTERVAL 1 DAY * i + INTERVAL 7 DAY")} AS "end", e, in_a, in_b FROM ({_TAGGED}) t, range(7) r(i)""", M)
# a session ends 30 minutes after its last row
_SESSION = _windows_sql(f"""SELECT {_text("min(ts) OVER (PARTITION BY s)")} AS "start", {_text("max(ts) OVER (PARTITION BY s) + INTERVAL 30 MINUTE")} AS "end", e, in_a, in_b FROM
(SELECT *, sum(fresh) OVER (ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (ORDER BY ts) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS fresh FROM ({_TAGGED}) t) u) v""", SMALL)


_KINDS = {
    "daily": (_DAILY, lambda: F.window("ts", "1 day"), M), "hourly": (_HOURLY, lambda: F.window("ts", "1 hour"), SMALL),
    "sliding": (_SLIDING, lambda: F.window("ts", "1 day"), M), "session": (_SESSION, lambda: F.session_window("ts", "30 minutes"), SMALL),
}
#: Sliding windows out of the panes above.
_OVER = {"sliding": ("7 days", "1 day")}
for _kind, (_sql, _window, _m) in _KINDS.items():
    def _stream(spark, d, window=_window, m=_m, session=_kind == "session", over=_OVER.get(_kind)):
        return _from_stream(spark, d, window(), m, session, over)

    def _table(spark, d, window=_window, m=_m, session=_kind == "session", over=_OVER.get(_kind)):
        return _from_table(spark, d, window(), m, session, over)

    query(_sql, f"window_{_kind}")(_table)
    if _kind != "hourly":
        query(_sql, f"stream_{_kind}")(_stream)


@query(_DAILY)
def stream_late(spark, d):
    """Rows that come after the watermark has passed their day are dropped, rows delivered twice change nothing: the
    result is that of the events alone, though other users' rows of the first week and all events again follow them
    (after one micro-batch more: lateness is judged by the watermark that the batch before began with)."""
    ev = load_table(spark, d, "events")
    early = ev.where(F.dayofmonth("ts") <= 7).withColumn("user_id", F.col("user_id") + 1_000_000)
    stream = windows.timed(windows.replay(spark, [ev, ev.orderBy(F.desc("ts")).limit(1), early.unionByName(ev), windows.closing_row(ev, _sides()[0])]))
    regs = windows.windowed_registers(stream, "user_id", *_sides(), F.window("ts", "1 day"), M, "md5")
    return _estimates(windows.run_to_table(windows.windowed_stats(regs, M, "md5")))


@query(_DAILY)
def stream_deduplicated(spark, d):
    """Dropping repeated events first costs state and changes nothing."""
    ev = load_table(spark, d, "events")
    stream = windows.timed(windows.replay(spark, [ev.unionByName(ev), windows.closing_row(ev, _sides()[0])])).dropDuplicatesWithinWatermark(["event_id"])
    regs = windows.windowed_registers(stream, "user_id", *_sides(), F.window("ts", "1 day"), M, "md5")
    return _estimates(windows.run_to_table(windows.windowed_stats(regs, M, "md5")))


@query(f"SELECT c_mktsegment, k::INTEGER AS k, min({sql.HASH}) AS v FROM (SELECT c_mktsegment, user_id AS e FROM events JOIN customer ON user_id = c_custkey) s, range(8) r(k) GROUP BY 1, 2")
def stream_with_customers(spark, d):
    """A stream joined with a table: running registers of each market segment's users, merged out of the micro-batches' store."""
    people = load_table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    ev = load_table(spark, d, "events")
    stream = windows.replay(spark, [ev.where("event_id % 2 = 0"), ev.where("event_id % 2 = 1")]).join(people, "user_id")
    path = shared_folder(spark, "running")
    windows.running_registers(stream, "user_id", "c_mktsegment", 8, path, shared_folder(spark, "stream"), "md5").awaitTermination()
    return registers.merge_registers(spark.read.parquet(path), ["c_mktsegment"])


@query("SELECT 3::BIGINT AS n_updates, true AS equals_batch")
def stream_running_state(spark, d):
    """Click and purchase users of the whole stream, updated with each of three micro-batches out of registers held as
    state; the last update has the statistics of the table."""
    ev = load_table(spark, d, "events").withColumn("all", F.lit("all"))
    path = shared_folder(spark, "state")
    stream = windows.running_overlap(windows.replay(spark, [ev.where(f"event_id % 3 = {i}") for i in range(3)]), "user_id", "all", *_sides(), 128)
    windows.run_batches(stream, lambda batch, epoch: batch.withColumn("epoch", F.lit(epoch)).write.mode("append").parquet(path))
    seen = spark.read.parquet(path)
    last = seen.orderBy(F.desc("epoch")).limit(1)
    whole = w.stats_of(ev.select(F.col("user_id").alias("e"), *[c.alias(n) for c, n in zip(_sides(), ("in_a", "in_b"), strict=True)]), m=128, family="xxhash64")
    same = F.lit(True)
    for c in ("k_tie", "k_b", "k_a"):
        same = same & (F.col(f"l.{c}") == F.col(f"t.{c}"))
    for c in ("sum_a", "sum_b", "sum_any"):
        same = same & (F.abs(F.col(f"l.{c}") - F.col(f"t.{c}")) <= 1e-9 * F.col(f"t.{c}"))
    return last.alias("l").crossJoin(whole.alias("t")).crossJoin(seen.agg(F.count("*").alias("n"))).select(F.col("n").alias("n_updates"), same.alias("equals_batch"))  # one row each


_FLOWS = "SELECT strftime(ts, '%Y-%m-%d') AS day, user_id AS e, event_type = 'error' AS in_a, event_type = 'click' AS in_b FROM events"
_EST = sql.newton(sql.stats(sql.pair_registers(_FLOWS, M, "day"), M, "day"), "day")
_ERR = f"sqrt(CASE WHEN card_both > 0 THEN ((card_a + card_b - card_both) / {M}) / (1 / card_both + (card_b - card_both) / (card_a * card_a + (card_a - card_both) * (card_b - card_both)) + (card_a - card_both) / (card_b * card_b + (card_a - card_both) * (card_b - card_both))) ELSE 0 END)"


def _alerts(est, days):
    """Each day's jump against the mean of the seven days before it, in its own standard errors: a join of the report's
    days with the days that follow them, no window over the whole table."""
    around = days.withColumn("of", F.explode(F.sequence(F.lit(1), F.lit(7)))).select(F.date_format(F.date_add(F.to_date("day"), F.col("of")), "yyyy-MM-dd").alias("day"), "card_both")
    before = around.groupBy("day").agg(F.avg("card_both").alias("expected"))
    return est.join(before, "day", "left").select("day", F.round("card_both", 2).alias("card_both"), F.round("expected", 2).alias("expected"), F.round(F.try_divide(F.col("card_both") - F.col("expected"), F.col("std_err")), 2).alias("jump"))


@query(f"WITH e AS (SELECT *, {_ERR} AS err FROM ({_EST}) q), p AS (SELECT x.day, avg(y.card_both) AS expected FROM e x JOIN e y ON y.day::DATE < x.day::DATE AND y.day::DATE >= x.day::DATE - 7 GROUP BY 1) SELECT e.day, round(card_both, 2) AS card_both, round(expected, 2) AS expected, round((card_both - expected) / nullif(err, 0), 2) AS jump FROM e LEFT JOIN p ON e.day = p.day")
def alert_flow_jumps(spark, d):
    """Days whose shared error and click users differ from the week before, in standard errors."""
    est = mle.estimate_interval(mle.mle_intersection(w.stats_of(w.shared_flows(spark, d, "error", "click"), ["day"])))
    return _alerts(est, est.select("day", "card_both"))


_RANK = f"SELECT day, round(card_both, 2) AS card_both, row_number() OVER (ORDER BY card_both DESC, day)::INTEGER AS place, ntile(4) OVER (ORDER BY card_both, day)::INTEGER AS quarter, round(card_both - lag(card_both) OVER (ORDER BY day), 2) AS change FROM ({_EST}) q"


@query(_RANK)
def flow_ranks(spark, d):
    """One row a day: its place, quarter and change, by window functions over the 30 rows of the report."""
    est = mle.mle_intersection(w.stats_of(w.shared_flows(spark, d, "error", "click"), ["day"])).select("day", "card_both")
    place, quarter, time = Window.orderBy(F.desc("card_both"), "day"), Window.orderBy("card_both", "day"), Window.orderBy("day")
    return est.select("day", F.round("card_both", 2).alias("card_both"), F.row_number().over(place).alias("place"), F.ntile(4).over(quarter).alias("quarter"), F.round(F.col("card_both") - F.lag("card_both").over(time), 2).alias("change"))


_PAIRS = "SELECT strftime(x.ts, '%Y-%m-%d') AS day, x.event_type AS x, y.event_type AS y, count(DISTINCT x.user_id) AS card_both FROM events x JOIN events y ON x.user_id = y.user_id AND x.ts::DATE = y.ts::DATE AND x.event_type < y.event_type GROUP BY 1, 2, 3"


@query(f"SELECT day, x, y, card_both, true AS close FROM ({_PAIRS}) q")
def ml_type_pairs_daily(spark, d):
    """All pairs of event types on each day: exact overlap, and whether the estimate from 256 functions is close."""
    m = 256
    ev = load_table(spark, d, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type", F.col("user_id").alias("e"))
    regs = registers.build_registers(ev, "e", ["day", "event_type"], m)
    a, b = (registers.pack(regs, ["day", "event_type"], m).withColumnsRenamed({"event_type": t, "regs": v}) for t, v in (("x", "va"), ("y", "vb")))
    both = a.join(b, "day").where("x < y").withColumn("s", pairstats.packed_stats(F.col("va"), F.col("vb"), m))  # few types a day
    est = mle.mle_intersection(both.select("day", "x", "y", F.lit(m).cast("long").alias("m"), "s.*", F.lit(1.0).alias("scale"))).select("day", "x", "y", F.col("card_both").alias("estimate"))
    sets = ev.distinct()
    met = sets.withColumnRenamed("event_type", "x").join(sets.withColumnRenamed("event_type", "y"), ["day", "e"]).where("x < y")
    n = sets.groupBy("day", "event_type").agg(F.count("*").alias("n"))
    true = met.groupBy("day", "x", "y").agg(F.count("*").alias("card_both")).join(n.toDF("day", "x", "card_a"), ["day", "x"]).join(n.toDF("day", "y", "card_b"), ["day", "y"])
    return true.join(est, ["day", "x", "y"]).select("day", "x", "y", "card_both", within(F.col("estimate"), F.col("card_both"), error_at("card_a", "card_b", "card_both", m), slack=2.0).alias("close"))
