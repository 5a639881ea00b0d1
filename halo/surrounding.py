"""Registered queries of the operators around the methods: joins, windows, sets, functions, SQL, sinks and streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from halo import series, sqlapi
from halo.models import moments
from halo.operators import blocks as lay
from halo.operators import grid
from halo.plans.scratch import folder
from halo.registry import COV_E, blocks_e, query
from halo.sources import ingest
from halo.sources.ingest import micros, read
from halo.streaming import stream

HOUR, DAY, JAN = series.HOUR, series.DAY, series.JAN_2024


# ---- windows, sorting

@query("rank_family", f"""WITH {series.SQL_E}, x AS (SELECT idx, dim, v, idx // 24 AS day FROM se)
 SELECT idx, dim, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER v AS INTEGER) AS rk, CAST(dense_rank() OVER v AS INTEGER) AS dr, round(percent_rank() OVER v, 8) AS pr, CAST(ntile(4) OVER w AS INTEGER) AS nt, round(cume_dist() OVER v, 8) AS cd
 FROM x WINDOW w AS (PARTITION BY dim, day ORDER BY v DESC, idx), v AS (PARTITION BY dim, day ORDER BY v DESC)""")
def _(spark, d):
    x = series.events(spark, d).withColumn("day", F.expr("idx div 24"))
    w, v = Window.partitionBy("dim", "day").orderBy(F.desc("v"), "idx"), Window.partitionBy("dim", "day").orderBy(F.desc("v"))
    return x.select("idx", "dim", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.round(F.percent_rank().over(v), 8).alias("pr"), F.ntile(4).over(w).alias("nt"), F.round(F.cume_dist().over(v), 8).alias("cd"))


@query("nth_value_day", f"WITH {series.SQL_E} SELECT DISTINCT dim, idx // 24 AS day, first_value(v) OVER w AS open, nth_value(v, 12) OVER w AS noon, last_value(v) OVER w AS close FROM se WINDOW w AS (PARTITION BY dim, idx // 24 ORDER BY idx ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, d):
    x = series.events(spark, d).withColumn("day", F.expr("idx div 24"))
    w = Window.partitionBy("dim", "day").orderBy("idx").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return x.select("dim", "day", F.first("v").over(w).alias("open"), F.nth_value("v", 12).over(w).alias("noon"), F.last("v").over(w).alias("close")).distinct()


@query("topk_per_dim", COV_E + " SELECT lag, i, j, c / (n - 1) AS value FROM cv WHERE lag > 0 QUALIFY row_number() OVER (PARTITION BY i ORDER BY abs(c / (n - 1)) DESC, lag, j) <= 3")
def _(spark, d):
    from halo.registry import lag_frame, moments_e

    w = Window.partitionBy("i").orderBy(F.desc(F.abs("value")), "lag", "j")
    return lag_frame(spark, moments_e(spark, d).autocov()).where("lag > 0").withColumn("rn", F.row_number().over(w)).where("rn <= 3").drop("rn")


# ---- aggregates

@query("distinct_users", f"SELECT CAST((epoch_us(ts) - {JAN}) // {DAY} AS BIGINT) AS day, count(DISTINCT user_id) AS users, true AS approx_users, true AS approx_median FROM events GROUP BY 1")
def _(spark, d):
    """Exact counts, and whether the sketches are within five of their standard errors."""
    e = read(spark, d, "events", ["ts", "user_id", "value"]).withColumn("day", grid.index(F.col("ts"), DAY, JAN))
    got = e.groupBy("day").agg(
        F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("near"), F.count(F.lit(1)).alias("n"),
        F.percentile_approx("value", 0.5, 10_000).alias("mid"), F.expr("percentile_cont(0.45) WITHIN GROUP (ORDER BY value)").alias("lo"), F.expr("percentile_cont(0.55) WITHIN GROUP (ORDER BY value)").alias("hi"),
    )
    return got.select("day", "users", (F.abs(F.col("near") - F.col("users")) <= F.greatest(F.lit(1.0), 0.1 * F.col("users"))).alias("approx_users"), F.col("mid").between(F.col("lo"), F.col("hi")).alias("approx_median"))


@query("grouping_sets_events", f"SELECT event_type AS kind, CAST((epoch_us(ts) - {JAN}) // {DAY} AS BIGINT) AS day, CAST(GROUPING(kind, day) AS BIGINT) AS level, count(*) AS n FROM events GROUP BY GROUPING SETS ((kind), (day), ())")
def _(spark, d):
    e = read(spark, d, "events", ["ts", "event_type"]).select(F.col("event_type").alias("kind"), grid.index(F.col("ts"), DAY, JAN).alias("day"))
    return e.groupingSets([("kind",), ("day",), ()], "kind", "day").agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"))


@query("collect_by_type", "SELECT event_type, arg_min(event_id, ts) AS first_id, arg_max(event_id, ts) AS last_id, bool_and(value > -1e9) AS sane, CAST(list_sum(list_slice(list_sort(list(event_id)), 1, 5)) AS BIGINT) AS low_five, count(DISTINCT CAST(floor(value) AS BIGINT)) AS bins FROM (SELECT * FROM events QUALIFY count(*) OVER (PARTITION BY event_type, ts) = 1) GROUP BY 1")
def _(spark, d):
    e = read(spark, d, "events", ["event_id", "ts", "event_type", "value"])
    once = e.withColumn("m", F.count(F.lit(1)).over(Window.partitionBy("event_type", "ts"))).where("m = 1")  # ties of the time have no order
    low = F.slice(F.array_sort(F.collect_list("event_id")), 1, 5)
    return once.groupBy("event_type").agg(
        F.min_by("event_id", "ts").alias("first_id"), F.max_by("event_id", "ts").alias("last_id"), F.bool_and(F.col("value") > -1e9).alias("sane"),
        F.aggregate(low, F.lit(0).cast("bigint"), lambda s, x: s + x).alias("low_five"), F.count_distinct(F.floor("value").cast("bigint")).alias("bins"),
    )


# ---- joins

@query("full_outer_types", f"WITH {series.SQL_E} SELECT coalesce(a.idx, b.idx) AS idx, coalesce(a.v, 0) AS clicks, coalesce(b.v, 0) AS errors, a.idx IS NULL AS only_errors, b.idx IS NULL AS only_clicks FROM (SELECT * FROM se0 WHERE dim = 0) a FULL JOIN (SELECT * FROM se0 WHERE dim = 1) b ON a.idx = b.idx")
def _(spark, d):
    e = series.events_long(spark, d)
    a, b = (e.where(f"dim = {k}").select("idx", F.col("v").alias(f"v{k}")) for k in (0, 1))
    both = a.join(b, "idx", "full")
    return both.select("idx", F.coalesce("v0", F.lit(0)).alias("clicks"), F.coalesce("v1", F.lit(0)).alias("errors"), F.col("v0").isNull().alias("only_errors"), F.col("v1").isNull().alias("only_clicks"))


@query("left_outer_lags", f"WITH {series.SQL_O} SELECT a.idx, a.v, b.v AS next FROM so a LEFT JOIN (SELECT * FROM so WHERE v IS NOT NULL) b ON b.idx = a.idx + 1 WHERE a.v IS NOT NULL")
def _(spark, d):
    s = series.orders(spark, d).where("v is not null")
    return s.join(s.select((F.col("idx") - 1).alias("idx"), F.col("v").alias("next")), "idx", "left")


@query("theta_regions", "SELECT CAST(a.r_regionkey AS INTEGER) AS a, CAST(b.r_regionkey AS INTEGER) AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey AND a.r_name <> b.r_name")
def _(spark, d):
    r = read(spark, d, "region", ["r_regionkey", "r_name"])
    a, b = (r.select(F.col("r_regionkey").cast("int").alias(k), F.col("r_name").alias(f"n{k}")) for k in "ab")
    return a.join(b, (F.col("a") < F.col("b")) & (F.col("na") != F.col("nb"))).select("a", "b")


# ---- sets, functions

@query("set_ops_all", f"WITH a AS (SELECT (epoch_us(ts) - {JAN}) // {HOUR} AS h FROM events WHERE event_type = 'click'), b AS (SELECT (epoch_us(ts) - {JAN}) // {HOUR} AS h FROM events WHERE event_type = 'error') SELECT 'both' AS part, CAST(h AS BIGINT) AS h, count(*) AS n FROM (SELECT h FROM a INTERSECT ALL SELECT h FROM b) GROUP BY h UNION ALL SELECT 'more', CAST(h AS BIGINT), count(*) FROM (SELECT h FROM a EXCEPT ALL SELECT h FROM b) GROUP BY h")
def _(spark, d):
    e = read(spark, d, "events", ["ts", "event_type"])
    a, b = (e.where(F.col("event_type") == k).select(grid.index(F.col("ts"), HOUR, JAN).alias("h")) for k in ("click", "error"))
    parts = {"both": a.intersectAll(b), "more": a.exceptAll(b)}
    out = [x.groupBy("h").agg(F.count(F.lit(1)).alias("n")).select(F.lit(k).alias("part"), "h", "n") for k, x in parts.items()]
    return out[0].unionByName(out[1])


@query("string_functions", "SELECT conv_id, turn, upper(trim(role)) AS who, length(text) AS n, len(string_split(text, ' ')) AS parts, regexp_replace(text, '[0-9]+', '#', 'g') = text AS no_digits, concat_ws('-', role, CAST(turn AS VARCHAR)) AS tag, printf('%05d', turn) AS padded, substr(text, 1, 3) AS head FROM conversations")
def _(spark, d):
    c = read(spark, d, "conversations", ["conv_id", "turn", "role", "text"])
    return c.select(
        "conv_id", "turn", F.upper(F.trim("role")).alias("who"), F.length("text").cast("bigint").alias("n"), F.size(F.split("text", " ", -1)).cast("bigint").alias("parts"),
        (F.regexp_replace("text", "[0-9]+", "#") == F.col("text")).alias("no_digits"), F.concat_ws("-", "role", F.col("turn").cast("string")).alias("tag"), F.format_string("%05d", "turn").alias("padded"), F.substring("text", 1, 3).alias("head"),
    )


@query("duplicates_last", f"SELECT CAST((epoch_us(ts) - {JAN}) // {HOUR} AS BIGINT) AS idx, CAST(user_id % 16 AS INTEGER) AS dim, arg_max(CAST(round(value * 100) AS BIGINT), event_id) AS v FROM events GROUP BY 1, 2")
def _(spark, d):
    e = read(spark, d, "events", ["event_id", "ts", "user_id", "value"])
    long = e.select(grid.index(F.col("ts"), HOUR, JAN).alias("idx"), (F.col("user_id") % 16).cast("int").alias("dim"), F.round(F.col("value") * 100).cast("bigint").alias("v"), "event_id")
    return grid.resolve_duplicates(long, "last", "event_id")


# ---- SQL, subqueries, recursion, functions of our own

SUBQUERY = """SELECT n.n_nationkey AS nation, (SELECT count(*) FROM {p}customer c WHERE c.c_nationkey = n.n_nationkey) AS customers,
 n.n_nationkey IN (SELECT s_nationkey FROM {p}supplier) AS supplies, EXISTS (SELECT 1 FROM {p}customer c WHERE c.c_nationkey = n.n_nationkey AND c.c_acctbal < 0) AS in_debt,
 n.n_regionkey = (SELECT max(r_regionkey) FROM {p}region) AS last_region FROM {p}nation n"""


@query("subqueries", SUBQUERY.format(p=""))
def _(spark, d):
    sqlapi.register(spark, folder=d, names=("nation", "region", "customer", "supplier"))
    return spark.sql(SUBQUERY.format(p="halo_"))


# Where the customers of each nation are after each hop of a walk.
RECURSIVE = "WITH RECURSIVE s AS (SELECT CAST(c_nationkey AS INTEGER) AS v, count(*) AS n FROM {p}customer GROUP BY 1), r(start, v, hop, n) AS (SELECT v, v, CAST(0 AS INTEGER), n FROM s UNION ALL SELECT start, CAST((v + 5) % 25 AS INTEGER), hop + 1, n FROM r WHERE hop < 4) SELECT start, v, hop, n FROM r"


@query("recursive_walk", RECURSIVE.format(p=""))
def _(spark, d):
    sqlapi.register(spark, folder=d, names=("customer",))
    return spark.sql(RECURSIVE.format(p="halo_"))


@query("udf_norm", "SELECT vec_id, round(sqrt(list_sum([CAST(x AS DOUBLE) * CAST(x AS DOUBLE) for x in embedding])), 6) AS norm FROM embeddings")
def _(spark, d):
    return read(spark, d, "embeddings", ["vec_id", "embedding"]).select("vec_id", F.round(sqlapi.halo_norm(F.col("embedding").cast("array<double>")), 6).alias("norm"))


@query("udaf_panel_lag", "WITH c AS (SELECT conv_id, turn, CAST(length(text) AS BIGINT) AS n FROM conversations) SELECT a.conv_id, CAST(sum(a.n * coalesce(b.n, 0)) AS BIGINT) AS s FROM c a LEFT JOIN c b ON b.conv_id = a.conv_id AND b.turn = a.turn + 1 GROUP BY 1")
def _(spark, d):
    c = read(spark, d, "conversations", ["conv_id", "turn", "text"]).select("conv_id", "turn", F.length("text").cast("bigint").alias("n"))
    return c.groupBy("conv_id").agg(sqlapi.halo_lag_moment("turn", "n", F.lit(1)).alias("s"))


@query("udtf_psi", "WITH m AS (SELECT s_suppkey, (s_suppkey % 8) / 16.0::DOUBLE AS a, (s_nationkey % 4) / 8.0::DOUBLE AS b FROM supplier) SELECT s_suppkey, CAST(k AS INTEGER) AS k, CASE WHEN k = 0 THEN 1.0 ELSE power(a, k - 1) * (a + b) END::DOUBLE AS psi FROM m, range(13) t(k)")
def _(spark, d):
    """Weights of the model of each supplier; its parameters are sixteenths and eighths, so that powers are exact."""
    sqlapi.register(spark, folder=d, names=("supplier",))
    return spark.sql("""SELECT s.s_suppkey, p.k, p.psi FROM (SELECT s_suppkey, CAST(s_suppkey % 8 AS DOUBLE) / 16D AS a, CAST(s_nationkey % 4 AS DOUBLE) / 8D AS b FROM halo_supplier) s,
        LATERAL halo_psi(s.a, s.b, 12) p""")


@query("sql_surface", "WITH c AS (SELECT conv_id, turn, CAST(length(text) AS DOUBLE) AS n FROM conversations) SELECT a.conv_id, CAST(h.l AS INTEGER) AS lag, sum(a.n * b.n) AS s FROM range(2) h(l) JOIN (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS k FROM c) a ON true JOIN (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS k FROM c) b ON b.conv_id = a.conv_id AND b.k = a.k + h.l GROUP BY 1, 2")
def _(spark, d):
    sqlapi.register(spark, folder=d, names=("conversations",))
    got = spark.sql("""SELECT s.conv_id, l.lag, l.s FROM (SELECT conv_id, transform(array_sort(collect_list(struct(turn, CAST(length(text) AS DOUBLE) AS n))), e -> e.n) AS x FROM halo_conversations GROUP BY conv_id) s,
        LATERAL halo_lags(s.x, 1) l""")
    return got.where("s > 0 or lag = 0")


# ---- sources, sinks, stored layouts

@query("sink_round_trip", "SELECT f.f AS format, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) f(f) GROUP BY 1")
def _(spark, d):
    path, out = folder(spark), None
    for fmt in ("csv", "json", "orc", "parquet"):
        e = read(spark, d, "events", ["event_id", "event_type", "value"])
        ingest.write(e, f"{path}/{fmt}", fmt, ("event_type",))
        got = ingest.read_as(spark, f"{path}/{fmt}", fmt, "event_id bigint, value double, event_type string").agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("ids")).select(F.lit(fmt).alias("format"), "n", "ids")
        out = got if out is None else out.unionByName(got)
    return out


LAYOUT = "SELECT CAST(b AS BIGINT) AS block, idx, idx // 100 = b AS is_core FROM range({lo}, {hi}) x(b) JOIN sz ON idx >= 100 * b - 3 AND idx < 100 * (b + 1) + 2"


@query("append_layout", f"WITH {series.SQL_O} " + LAYOUT.format(lo=0, hi=25))
def _(spark, d):
    """A layout stored in four parts, the last of them in the middle, equals the layout of the whole."""
    rows, path = series.orders(spark, d, 0), folder(spark) + "/layout"
    cuts = [(0, 650), (650, 1203), (1801, series.N_O), (1203, 1801)]
    for k, (a, b) in enumerate(cuts):
        part = rows.where(F.col("idx").between(a, b - 1))
        if k:
            lay.append(part, path, 100, 3, 2, group=4)
        else:
            lay.store(lay.time_blocks(part, 100, 3, 2), path, group=4)
    return lay.stored(spark, path).select("block", "idx", "is_core")


@query("stored_block_range", f"WITH {series.SQL_O} " + LAYOUT.format(lo=6, hi=11))
def _(spark, d):
    path = folder(spark) + "/layout"
    lay.store(lay.time_blocks(series.orders(spark, d, 0), 100, 3, 2), path, group=4)
    return lay.stored(spark, path, (6, 10), group=4).select("block", "idx", "is_core")


# ---- streams

def events_in_order(spark, d, columns, parts: int = 4, repeat: int = 1):
    """The events as a stream of files in order of time, one a micro-batch; `repeat` writes each file several times."""
    path = folder(spark)
    src = read(spark, d, "events", columns).withColumn("ts", F.col("ts").cast("timestamp"))
    ends = src.agg(F.min("ts").cast("double"), F.max("ts").cast("double")).head()
    part = F.least(F.floor((F.col("ts").cast("double") - ends[0]) / max(ends[1] - ends[0], 1e-6) * parts), F.lit(parts - 1))
    for k in range(parts):
        for _ in range(repeat):
            src.where(part == k).coalesce(1).write.mode("append").parquet(f"{path}/in")
    live = spark.readStream.schema(src.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/in")
    return live, path


@query("stream_dedup", "SELECT event_type, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events GROUP BY 1")
def _(spark, d):
    live, path = events_in_order(spark, d, ["event_id", "ts", "event_type"], 2, repeat=2)
    got = stream.run(stream.dedup(live, "event_id", "ts", "60 days"), f"{path}/out", f"{path}/cp")
    return got.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("ids"))


@query("stream_score", "SELECT event_id, CASE event_type WHEN 'click' THEN 1 WHEN 'error' THEN -4 WHEN 'purchase' THEN 16 END AS score FROM events WHERE event_type IN ('click', 'error', 'purchase')")
def _(spark, d):
    live, path = events_in_order(spark, d, ["event_id", "ts", "event_type"], 2)
    model = spark.createDataFrame([("click", 1), ("error", -4), ("purchase", 16)], "event_type string, score int")
    return stream.run(stream.score(live, model, "event_type").select("event_id", "score"), f"{path}/out", f"{path}/cp").select("event_id", "score")


@query("stream_interval_join", f"SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.event_type = 'click' AND b.event_type = 'purchase' AND a.user_id = b.user_id AND epoch_us(b.ts) - epoch_us(a.ts) BETWEEN 0 AND 6 * {HOUR}")
def _(spark, d):
    live, path = events_in_order(spark, d, ["event_id", "ts", "event_type", "user_id"], 2)
    a = live.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("ts").alias("lts"), F.col("user_id").alias("user_l")).withWatermark("lts", "1 hour")
    b = live.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("ts").alias("rts"), F.col("user_id").alias("user_r")).withWatermark("rts", "1 hour")
    got = stream.run(stream.interval_join(a, b, "user", "6 HOURS").select("click", "purchase"), f"{path}/out", f"{path}/cp")
    return got.select("click", "purchase")


@query("stream_late_rows", f"WITH e AS (SELECT epoch_us(ts) AS t FROM events), m AS (SELECT min(t) AS a, max(t) AS b FROM e), p AS (SELECT t, CASE WHEN t >= a + (b - a) / 2 THEN 0 ELSE 1 END AS batch FROM e, m), w AS (SELECT max(t) - {HOUR} AS mark FROM p WHERE batch = 0) SELECT count(*) AS fed, count(*) FILTER (batch = 0 OR (t // {HOUR} + 1) * {HOUR} > mark) AS kept, count(*) FILTER (batch = 1 AND (t // {HOUR} + 1) * {HOUR} <= mark) AS late FROM p, w")
def _(spark, d):
    """The last quarter first, then the third, then the earlier half: its rows come after the watermark and count as late.

    A batch drops what lies under the watermark that the batch before it began with, so the first two lose nothing.
    """
    path = folder(spark)
    src = read(spark, d, "events", ["ts"]).withColumn("ts", F.col("ts").cast("timestamp"))
    a, b = src.agg(F.min("ts").cast("double"), F.max("ts").cast("double")).head()
    at = F.col("ts").cast("double")
    half, late = a + (b - a) / 2, a + (b - a) * 3 / 4
    for part in (src.where(at >= late), src.where((at >= half) & (at < late)), src.where(at < half)):
        part.coalesce(1).write.mode("append").parquet(f"{path}/in")
    live = spark.readStream.schema(src.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/in")
    return stream.late_report(live, "ts", "1 hour", "1 hour", src, f"{path}/out", f"{path}/cp")


@query("stream_complete", "SELECT event_type, count(*) AS v FROM events GROUP BY 1")
def _(spark, d):
    live, path = events_in_order(spark, d, ["ts", "event_type"], 3)
    got = stream.run(live.groupBy("event_type").agg(F.count(F.lit(1)).alias("v")), f"{path}/out", f"{path}/cp", "complete")
    last = got.agg(F.max("batch")).head()[0]
    return got.where(F.col("batch") == last).select("event_type", "v")


@query("stream_append_windows", f"WITH e AS (SELECT epoch_us(ts) AS t FROM events), w AS (SELECT max(t) - {HOUR} AS mark FROM e) SELECT CAST(t // {HOUR} * {HOUR} AS BIGINT) AS start, count(*) AS v FROM e, w WHERE (t // {HOUR} + 1) * {HOUR} <= mark GROUP BY 1")
def _(spark, d):
    """Append mode gives a window once the watermark has passed its end."""
    live, path = events_in_order(spark, d, ["ts"], 3)
    got = stream.run(stream.grid(live, "ts", "1 hour", "1 hour"), f"{path}/out", f"{path}/cp")
    return got.select(micros(F.col("window.start")).alias("start"), "v")


@query("predicates_pushed", "SELECT event_type, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-05' AND ts < TIMESTAMP '2024-01-12' AND event_type IN ('click', 'view') AND event_type LIKE '%i%' GROUP BY 1")
def _(spark, d):
    e = read(spark, d, "events", ["ts", "event_type"], (F.col("ts") >= F.lit("2024-01-05").cast("timestamp_ntz")) & (F.col("ts") < F.lit("2024-01-12").cast("timestamp_ntz")) & F.col("event_type").isin("click", "view") & F.col("event_type").like("%i%"))
    return e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
