"""Queries for the operators, sources, sinks, functions and streams that users of the method need."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.config import RepairConfig
from unscramble.functions import perm
from unscramble.operators import candidates, determine, matching, model, runs
from unscramble.operators.intervals import asof_join, interval_join, overlap_join, regularise
from unscramble.operators.ordinal import with_ordinal
from unscramble.plans import oracle, sqlapi, workloads
from unscramble.plans.queries import Example, query, r6
from unscramble.scratch import scratch_path, stored
from unscramble.sources import inject, panels
from unscramble.sources.tables import read_any, read_table, stream_source, write_result
from unscramble.streaming.online import stream_repair
from unscramble.streaming.ticks import alarm_sessions, stream_ticks


@query("scan_pruned", "SELECT l_orderkey, round(l_quantity, 6) AS l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
def scan_pruned(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem", ["l_orderkey", r6("l_quantity")], (F.col("l_quantity") > 45) & (F.col("l_returnflag") == "R"))


_EVENTS = "event_id long, user_id long, event_type string, value double"


@query("scan_formats", "SELECT fmt, count(*) AS cnt, round(sum(value), 4) AS total FROM events, (VALUES ('csv'), ('json'), ('orc'), ('text')) f(fmt) GROUP BY fmt")
def scan_formats(spark, sf_dir):
    """events written in each format and read back with the schema stated."""
    rows = read_table(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "value"])
    out = None
    for fmt in ("csv", "json", "orc", "text"):
        path = scratch_path(spark, fmt)
        if fmt == "text":
            rows.select(F.to_json(F.struct("*")).alias("value")).write.text(path)
            got = read_any(spark, "text", path, "value string").select(F.from_json("value", _EVENTS).alias("e")).select("e.*")
        else:
            rows.write.format(fmt).save(path)
            got = read_any(spark, fmt, path, _EVENTS)
        one = got.agg(F.lit(fmt).alias("fmt"), F.count("*").alias("cnt"), F.round(F.sum("value"), 4).alias("total"))
        out = one if out is None else out.unionByName(one)
    return out


@query("sink_roundtrip", "SELECT event_type, count(*) AS cnt, round(sum(value), 4) AS total FROM events GROUP BY event_type")
def sink_roundtrip(spark, sf_dir):
    rows, path = read_table(spark, sf_dir, "events", ["event_id", "event_type", "value"]), scratch_path(spark, "sink")
    write_result(rows, path, ["event_type"])
    return spark.read.parquet(path).groupBy("event_type").agg(F.count("*").alias("cnt"), F.round(F.sum("value"), 4).alias("total"))


@query("panel_melt", "SELECT m, count(*) AS cnt, round(sum(x), 3) AS total FROM (SELECT 0 AS m, l_quantity AS x FROM lineitem UNION ALL SELECT 1, l_extendedprice FROM lineitem UNION ALL SELECT 2, l_discount FROM lineitem UNION ALL SELECT 3, l_tax FROM lineitem) GROUP BY m")
def panel_melt(spark, sf_dir):
    wide = read_table(spark, sf_dir, "lineitem", ["l_orderkey", *panels.MEASURES])
    long = wide.unpivot(["l_orderkey"], list(panels.MEASURES), "name", "x").withColumn("m", F.array_position(F.lit(list(panels.MEASURES)), F.col("name")).cast("int") - 1)
    return long.groupBy("m").agg(F.count("*").alias("cnt"), F.round(F.sum("x"), 3).alias("total"))


@query("panel_pivot", "SELECT CAST(user_id % 100 AS BIGINT) AS bucket, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'error') AS error, count(*) FILTER (WHERE event_type = 'view') AS view_ FROM events GROUP BY 1")
def panel_pivot(spark, sf_dir):
    rows = read_table(spark, sf_dir, "events", ["user_id", "event_type"]).withColumn("bucket", F.col("user_id") % 100)
    wide = rows.groupBy("bucket").pivot("event_type", list(panels.CLICKS)).count().fillna(0)
    return wide.select("bucket", "click", "error", F.col("view").alias("view_"))


@query("apply_permutation", "SELECT vec_id, round(embedding[2], 6) AS a, round(embedding[1], 6) AS b, round(embedding[5], 6) AS c FROM embeddings")
def apply_permutation(spark, sf_dir):
    rows = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    moved = rows.select("vec_id", perm.apply_cycles(F.transform("embedding", lambda v: v.cast("double")), perm.parse_notation(F.lit("(1 2)(3 5)"))).alias("x"))
    return moved.select("vec_id", *[F.round(F.col("x")[i], 6).alias(c) for i, c in ((0, "a"), (1, "b"), (2, "c"))])


@query("prefix_filter", "SELECT count(*) AS cnt, round(sum(l_tax), 4) AS total FROM lineitem WHERE l_shipdate BETWEEN '1996-01-01' AND '1997-12-31' AND l_linestatus IN ('O', 'F') AND l_tax IS NOT NULL")
def prefix_filter(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet").filter("l_shipdate BETWEEN '1996-01-01' AND '1997-12-31' AND l_linestatus IN ('O', 'F') AND l_tax IS NOT NULL")
    return rows.agg(F.count("*").alias("cnt"), F.round(F.sum("l_tax"), 4).alias("total"))


@query("ordinal_index", f"SELECT l_orderkey, l_linenumber, row_number() OVER (ORDER BY {oracle.ROW_ORDER}) AS n FROM lineitem")
def ordinal_index(spark, sf_dir):
    return with_ordinal(read_table(spark, sf_dir, "lineitem", list(panels.ROW_ORDER)), panels.ROW_ORDER).select("l_orderkey", "l_linenumber", "n")


@query("score_panel", oracle.with_(oracle.example(), f"SELECT n, m, round({oracle.chebyshev('x')}, 6) AS p FROM bad JOIN models USING (m)"))
def score_panel(spark, sf_dir):
    from unscramble.operators.detect import supports, with_models

    e = Example(spark, sf_dir)
    return with_models(e.bad, model.packed(e.models)).select("n", F.posexplode(supports("chebyshev")).alias("m", "p")).select("n", "m", r6("p"))


@query(
    "native_panel",
    f"SELECT row_number() OVER (ORDER BY {oracle.ROW_ORDER}) AS n, l_returnflag AS regime, round(o_totalprice, 4) AS price, round(p_retailprice, 4) AS retail, round(s_acctbal + c_acctbal, 4) AS balance FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey",
)
def native_panel(spark, sf_dir):
    x = F.col("x")
    return panels.native_panel(spark, sf_dir).select("n", "regime", F.round(x[4], 4).alias("price"), F.round(x[5], 4).alias("retail"), F.round(x[7] + x[8], 4).alias("balance"))


_INTERVALS = "(0, 10, 40), (0, 100, 700), (0, 1000, 1000), (0, 2500, 4999)"


def _few(spark: SparkSession, values: str) -> DataFrame:
    return spark.sql(f"SELECT CAST(e AS LONG) AS eq_id, CAST(l AS LONG) AS l, CAST(r AS LONG) AS r FROM VALUES {values} AS t(e, l, r)")


@query("interval_join", oracle.with_(f"{oracle.panel('p', 2.0)}, i AS (SELECT * FROM (VALUES {_INTERVALS}) t(e, l, r))", "SELECT l, r, count(DISTINCT n) AS points FROM p JOIN i ON n BETWEEN l AND r GROUP BY l, r"))
def interval_join_(spark, sf_dir):
    got = interval_join(panels.calibrated_panel(spark, sf_dir).select("eq_id", "n"), _few(spark, _INTERVALS), "inner")
    return got.groupBy("l", "r").agg(F.count("*").alias("points"))


#: Intervals of the parts: of all of them, and of every third, which are longer and shared.
_PART_A = "SELECT p_partkey * 10 + p_size % 4 AS l, p_partkey * 10 + p_size % 4 + p_size % 30 AS r FROM {}"
_PART_B = "SELECT p_partkey * 10 + 7 AS l, p_partkey * 10 + 7 + 3 * (p_size % 9) AS r FROM {} WHERE p_partkey % 3 = 0"
_PART_AB = f"WITH a AS ({_PART_A.format('part')}), b AS ({_PART_B.format('part')})"


def _part_ab(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    parts = read_table(spark, sf_dir, "part", ["p_partkey", "p_size"])
    a, b = (spark.sql(text.format("{parts}"), parts=parts).select(F.lit(0).cast("long").alias("eq_id"), "l", "r") for text in (_PART_A, _PART_B))
    return a, b


@query("interval_overlap", f"{_PART_AB} SELECT CAST(a.l AS BIGINT) AS a_l, CAST(b.l AS BIGINT) AS b_l, CAST(least(a.r, b.r) - greatest(a.l, b.l) + 1 AS BIGINT) AS shared FROM a JOIN b ON a.l <= b.r AND b.l <= a.r")
def interval_overlap(spark, sf_dir):
    got = overlap_join(*_part_ab(spark, sf_dir))
    return got.select("a_l", "b_l", (F.least("a_r", "b_r") - F.greatest("a_l", "b_l") + 1).alias("shared"))


@query("score_outer", f"{_PART_AB} SELECT CAST(a.l AS BIGINT) AS found_l, CAST(b.l AS BIGINT) AS true_l FROM a FULL JOIN b ON a.l <= b.r AND b.l <= a.r")
def score_outer(spark, sf_dir):
    a, b = _part_ab(spark, sf_dir)
    both = overlap_join(a, b).select("a_l", "b_l")
    left = a.select(F.col("l").alias("found_l")).join(both, F.col("found_l") == F.col("a_l"), "left").select("found_l", F.col("b_l").alias("k"))
    return left.join(b.select(F.col("l").alias("true_l")), F.col("k") == F.col("true_l"), "full").select("found_l", "true_l")


@query(
    "asof_align",
    "WITH t AS (SELECT unnest(generate_series((SELECT min(ts) FROM events), (SELECT max(ts) FROM events), INTERVAL 12 HOUR)) AS ts) SELECT t.ts AS ts, round(e.value, 6) AS value FROM t ASOF LEFT JOIN (SELECT ts, value FROM events WHERE event_type = 'view') e ON t.ts >= e.ts",
)
def asof_align(spark, sf_dir):
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    ticks = events.agg(F.min("ts").alias("lo"), F.max("ts").alias("hi")).select(F.explode(F.expr("sequence(lo, hi, interval 12 hours)")).alias("ts"))
    return asof_join(ticks, events.filter("event_type = 'view'").select("ts", "value"), "value").select("ts", r6("value"))


@query(
    "regularise_daily",
    """WITH d AS (SELECT date_trunc('day', l_shipdate) AS ts, count(*) AS c FROM lineitem GROUP BY 1), g AS (SELECT unnest(generate_series((SELECT min(ts) FROM d)::TIMESTAMP, (SELECT max(ts) FROM d)::TIMESTAMP, INTERVAL 1 DAY)) AS ts)
SELECT count(*) AS days, count(*) FILTER (WHERE d.ts IS NULL) AS filled FROM g LEFT JOIN d ON g.ts = d.ts""",
)
def regularise_daily(spark, sf_dir):
    got = regularise(panels.daily_panel(spark, sf_dir), "1 day", ["x1", "x2"])
    return got.agg(F.count("*").alias("days"), F.count_if("filled").alias("filled"))


@query("fit_moments", "SELECT count(*) AS cnt, round(avg(l_quantity), 6) AS mu, round(stddev_samp(l_quantity), 6) AS sigma FROM lineitem")
def fit_moments(spark, sf_dir):
    return model.fit_moments(panels.native_panel(spark, sf_dir)).filter("m = 0").select("cnt", r6("mu"), r6("sigma"))


@query("fit_robust", "WITH mid AS (SELECT median(l_quantity) AS mu FROM lineitem) SELECT round(any_value(mu), 6) AS mid, round(quantile_cont(l_quantity, 0.25), 6) AS q1, round(median(abs(l_quantity - mu)) * 1.4826, 6) AS sigma FROM lineitem, mid")
def fit_robust(spark, sf_dir):
    return model.fit_robust(panels.native_panel(spark, sf_dir)).filter("m = 0").select(r6("mu", "mid"), r6("q1"), r6("sigma"))


@query("fit_hist", "WITH e AS (SELECT min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem) SELECT CAST(least(floor((l_quantity - lo) / (hi - lo) * 10), 9) AS INTEGER) AS bin, count(*) AS c FROM lineitem, e GROUP BY 1")
def fit_hist(spark, sf_dir):
    fit = model.fit_hist(panels.native_panel(spark, sf_dir), 10).filter("m = 0")
    return fit.select("cnt", F.posexplode("hist").alias("bin", "share")).filter("share > 0").select("bin", F.round(F.col("share") * F.col("cnt")).cast("long").alias("c"))


_REPORT = "WITH s AS (SELECT l_suppkey, l_returnflag, l_linestatus, n_name, r_name FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"


def _hierarchy(spark, sf_dir) -> DataFrame:
    items = read_table(spark, sf_dir, "lineitem", ["l_suppkey", "l_returnflag", "l_linestatus"])
    supplier = read_table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"])
    nation, region = read_table(spark, sf_dir, "nation"), read_table(spark, sf_dir, "region")
    return items.join(supplier, items.l_suppkey == supplier.s_suppkey).join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))


@query("report_rollup", f"{_REPORT} SELECT r_name, n_name, count(*) AS cnt FROM s GROUP BY ROLLUP (r_name, n_name)")
def report_rollup(spark, sf_dir):
    return _hierarchy(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("cnt"))


@query("report_cube", f"{_REPORT} SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM s GROUP BY CUBE (l_returnflag, l_linestatus)")
def report_cube(spark, sf_dir):
    return _hierarchy(spark, sf_dir).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("cnt"))


@query("report_sets", f"{_REPORT} SELECT r_name, l_returnflag, count(*) AS cnt FROM s GROUP BY GROUPING SETS ((r_name), (l_returnflag), ())")
def report_sets(spark, sf_dir):
    _hierarchy(spark, sf_dir).createOrReplaceTempView("hierarchy_rows")
    return spark.sql("SELECT r_name, l_returnflag, count(*) AS cnt FROM hierarchy_rows GROUP BY GROUPING SETS ((r_name), (l_returnflag), ())")


@query("repair_report")
def repair_report(spark, sf_dir):
    """Repaired points by equipment and order of cycle."""
    b = workloads.Workbench(spark, sf_dir, g=3.0)
    from unscramble.plans.methods import repair

    units = repair(b.panel, b.models, RepairConfig()).units
    return units.rollup("eq_id", "order").agg(F.count("*").alias("n_units"), F.sum("points").alias("points"))


@query("rolling_rows", "SELECT event_id, round(avg(value) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 10 PRECEDING AND 1 PRECEDING), 6) AS mean FROM events")
def rolling_rows(spark, sf_dir):
    w = Window.partitionBy("event_type").orderBy("event_id").rowsBetween(-10, -1)
    return read_table(spark, sf_dir, "events", ["event_id", "event_type", "value"]).select("event_id", F.round(F.avg("value").over(w), 6).alias("mean"))


@query("rolling_range", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY ts RANGE BETWEEN INTERVAL 6 HOUR PRECEDING AND CURRENT ROW) AS near FROM events")
def rolling_range(spark, sf_dir):
    rows = read_table(spark, sf_dir, "events", ["event_id", "event_type", "ts"]).withColumn("us", F.unix_micros("ts"))
    w = Window.partitionBy("event_type").orderBy("us").rangeBetween(-6 * 3_600_000_000, 0)
    return rows.select("event_id", F.count("*").over(w).alias("near"))


def _two(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """Points that the complete method changes, and those that candidates alone change."""
    e = Example(spark, sf_dir)
    found = stored(e.candidates(), "candidates")
    full = determine.determine(found, e.last, e.cfg).schemas
    a = full.select("eq_id", F.explode(F.sequence("l", "r")).alias("n")).select("n")
    return a, found.filter("size(cycles) > 0").select("n")


_POINTS = f"{oracle.FULL}, fp AS (SELECT DISTINCT unnest(range(l, r + 1)) AS n FROM intervals), cp AS (SELECT DISTINCT n FROM cyc)"


@query("points_agree", oracle.with_(_POINTS, "SELECT n FROM fp INTERSECT SELECT n FROM cp"))
def points_agree(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.intersect(b)


@query("points_only_full", oracle.with_(_POINTS, "SELECT n FROM fp EXCEPT SELECT n FROM cp"))
def points_only_full(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.exceptAll(b)


@query("perm_map", oracle.with_(f"{oracle.example()}, {oracle.FLAGS}, {oracle.WEIGHTS}, {oracle.MATCH}", "SELECT n, unnest(src) AS u, unnest(dst) AS v FROM matched"))
def perm_map(spark, sf_dir):
    """Permutations as maps from sensor to sensor, taken apart again."""
    got = Example(spark, sf_dir).candidates().filter("size(src) > 0").select("n", F.map_from_arrays("src", "dst").alias("to"))
    return got.select("n", F.explode(F.map_entries("to")).alias("e")).select("n", F.col("e.key").alias("u"), F.col("e.value").alias("v"))


_NOTES = "SELECT p_partkey, p_size % 3 AS kind, p_partkey % 9 AS k FROM {}"


@query(
    "cycle_text",
    f"SELECT p_partkey, CASE kind WHEN 0 THEN concat(k, '>', k + 1, '|', k + 2, '>', k + 4) WHEN 1 THEN concat(k, '>', k + 2, '>', k + 1) ELSE '' END AS key, CAST(CASE kind WHEN 0 THEN 2 WHEN 1 THEN 1 ELSE 0 END AS INTEGER) AS n_cycles FROM ({_NOTES.format('part')})",
)
def cycle_text(spark, sf_dir):
    """A permutation noted down for each part, read, written and read again."""
    parts = read_table(spark, sf_dir, "part", ["p_partkey", "p_size"])
    rows = spark.sql(_NOTES.format("{parts}"), parts=parts)
    text = "CASE kind WHEN 0 THEN concat('(', k + 2, ' ', k + 1, ')(', k + 5, ',', k + 3, ')') WHEN 1 THEN concat('(', k + 3, ' ', k + 2, ' ', k + 1, ')') ELSE '' END"
    phi = perm.parse_notation(F.col("s"))
    return rows.select("p_partkey", F.expr(text).alias("s")).select("p_partkey", perm.cycles_key(perm.parse_cycles(perm.cycles_key(phi))).alias("key"), F.size(phi).alias("n_cycles"))


@query("tick_aggregate", "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS ts, event_type, round(avg(value), 6) AS v, count(*) AS c FROM events GROUP BY 1, 2")
def tick_aggregate(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/events.parquet")
    cells = rows.groupBy(F.window("ts", "6 hours")["start"].alias("ts"), "event_type").agg(F.round(F.avg("value"), 6).alias("v"), F.count("*").alias("c"))
    return cells.select("ts", "event_type", "v", "c")


@query("event_panel", "WITH r AS (SELECT event_type, value, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) AS n FROM events) SELECT n, round(max(value) FILTER (WHERE event_type = 'click'), 6) AS click, round(max(value + 600) FILTER (WHERE event_type = 'view'), 6) AS view_ FROM r GROUP BY n HAVING count(*) = 5")
def event_panel(spark, sf_dir):
    return panels.event_ordinals(spark, sf_dir).select("n", F.round(F.col("x")[0], 6).alias("click"), F.round(F.col("x")[4], 6).alias("view_"))


@query("embedding_panel", "SELECT row_number() OVER (ORDER BY vec_id) AS n, CAST(label AS VARCHAR) AS regime, round(CAST(embedding[1] AS DOUBLE), 6) AS first, round(CAST(embedding[64] AS DOUBLE) + CAST(7.875 AS DOUBLE), 6) AS last FROM embeddings")
def embedding_panel(spark, sf_dir):
    return panels.embedding_panel(spark, sf_dir).select("n", "regime", F.round(F.col("x")[0], 6).alias("first"), F.round(F.col("x")[63], 6).alias("last"))


@query("props_channel", "SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS k, count(*) AS cnt FROM events GROUP BY 1")
def props_channel(spark, sf_dir):
    rows = read_table(spark, sf_dir, "events", ["props"])
    return rows.select(F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(F.count("*").alias("cnt"))


# --- SQL surface ------------------------------------------------------------------------------------------------


@query("sql_match", oracle.with_(f"{oracle.example()}, {oracle.FLAGS}, {oracle.WEIGHTS}, {oracle.MATCH}, {oracle.CYCLES}", "SELECT n, coalesce(string_agg(sigma, '|' ORDER BY walk), '') AS phi FROM matched LEFT JOIN cyc USING (n) GROUP BY n"))
def sql_match(spark, sf_dir):
    sqlapi.register_functions(spark)
    stored(Example(spark, sf_dir).weighted().select("n", "abnormal", "w"), "weighted").createOrReplaceTempView("weighted_points")
    return spark.sql("SELECT n, cycle_text(abnormal, match_exact(w)) AS phi FROM weighted_points")


@query("smooth_labels")
def smooth_labels(spark, sf_dir):
    sqlapi.register_functions(spark)
    with_ordinal(read_table(spark, sf_dir, "labels", ["doc_id", "quality", "toxic"]), ["doc_id"]).createOrReplaceTempView("label_bits")
    return spark.sql("SELECT toxic, smooth_bits(n, quality) AS kept FROM label_bits GROUP BY toxic")


_UDTF_BITS = "CASE WHEN quality = 1 THEN 1 ELSE 0 END"


@query(
    "udtf_runs",
    f"WITH b AS (SELECT doc_id % 7 AS g, row_number() OVER (PARTITION BY doc_id % 7 ORDER BY doc_id) AS n, {_UDTF_BITS} AS bit FROM labels), i AS (SELECT g, bit, n, n - row_number() OVER (PARTITION BY g, bit ORDER BY n) AS k FROM b) SELECT CAST(g AS BIGINT) AS g, bit, min(n) AS l, max(n) AS r FROM i GROUP BY g, bit, k",
)
def udtf_runs(spark, sf_dir):
    sqlapi.register_functions(spark)
    rows = read_table(spark, sf_dir, "labels", ["doc_id", "quality"]).withColumn("g", F.col("doc_id") % 7)
    bits = rows.groupBy("g").agg(F.transform(F.array_sort(F.collect_list(F.struct("doc_id", "quality"))), lambda s: s["quality"]).alias("bits"))
    bits.createOrReplaceTempView("bit_arrays")
    return spark.sql("SELECT g, t.bit, t.l, t.r FROM bit_arrays, LATERAL bit_runs(bits) AS t")


@query("sql_surface", oracle.with_(oracle.example(), f"SELECT n, round(min({oracle.chebyshev('x')}), 6) AS least FROM bad JOIN models USING (m) GROUP BY n"))
def sql_surface(spark, sf_dir):
    sqlapi.register_functions(spark)
    e = Example(spark, sf_dir)
    sqlapi.create_views(panels.to_long(e.bad), e.models)
    return spark.sql("SELECT p.n, round(min(chebyshev_support(p.x, q.mu, q.sigma)), 6) AS least FROM panel p JOIN models q ON p.eq_id = q.eq_id AND p.m = q.m GROUP BY p.n")


@query("greedy_below_exact", "SELECT '1>2>0' AS unused WHERE false")
def greedy_below_exact(spark, sf_dir):
    """Points of the calibrated panel at which the greedy matching weighs more than the exact one: none."""
    b = workloads.Workbench(spark, sf_dir)
    from unscramble.operators import detect

    rows = candidates.gate(detect.flag(b.panel, b.models)).select("n", matching.weights().alias("w"))
    rows = rows.withColumn("e", matching.matched(F.col("w"), "assign")).withColumn("g", matching.greedy(F.col("w")))
    total = lambda to: F.aggregate(F.zip_with("w", to, lambda row, j: row[j]), F.lit(0.0), lambda a, v: a + v)
    return rows.filter(total("g") > total("e") + 1e-9).select(perm.cycle_key(F.col("g")).alias("unused"))


# --- streams ----------------------------------------------------------------------------------------------------


def _files(spark: SparkSession, sf_dir: str, parts: int = 4) -> tuple[str, DataFrame]:
    """events as a folder of files that arrive in order of time: a replay of a stream."""
    rows = read_table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type", "value"])
    path, numbered = scratch_path(spark, "stream"), stored(with_ordinal(rows, ["ts"]), "replay")
    size = -(-numbered.count() // parts) or 1
    for k in range(parts):
        numbered.filter((F.col("n") > k * size) & (F.col("n") <= (k + 1) * size)).drop("n").coalesce(1).write.mode("append").parquet(path)
    return path, rows


def _drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything that is there, through the stream, as a table."""
    spark = stream.sparkSession
    path, check = scratch_path(spark, "sink"), scratch_path(spark, "progress")

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("append").parquet(path)

    run = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", check).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


@query("stream_source", "SELECT event_type, count(*) AS cnt FROM events GROUP BY event_type")
def stream_source_(spark, sf_dir):
    path, rows = _files(spark, sf_dir)
    got = _drain(stream_source(spark, path, rows.schema).select("event_type", "event_id"))
    return got.groupBy("event_type").agg(F.count("*").alias("cnt"))


_CLOSED = "(SELECT max(ts) - INTERVAL 1 DAY FROM events)"


@query("stream_tumbling", f"WITH w AS (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS ts, event_type, value FROM events) SELECT event_type, count(*) AS windows, CAST(sum(c) AS BIGINT) AS total FROM (SELECT ts, event_type, count(*) AS c FROM w GROUP BY 1, 2) WHERE ts + INTERVAL 6 HOUR <= {_CLOSED} GROUP BY event_type")
def stream_tumbling(spark, sf_dir):
    path, rows = _files(spark, sf_dir)
    got = _drain(stream_ticks(stream_source(spark, path, rows.schema)))
    return got.groupBy("event_type").agg(F.count("*").alias("windows"), F.sum("c").alias("total"))


@query("stream_sliding")
def stream_sliding(spark, sf_dir):
    path, rows = _files(spark, sf_dir)
    got = _drain(stream_ticks(stream_source(spark, path, rows.schema), "6 hours", slide="3 hours"))
    return got.groupBy("event_type").agg(F.count("*").alias("windows"), F.sum("c").alias("total"))


@query("stream_session")
def stream_session(spark, sf_dir):
    path, rows = _files(spark, sf_dir)
    got = _drain(alarm_sessions(stream_source(spark, path, rows.schema).filter("value > 150")))
    return got.groupBy("event_type").agg(F.count("*").alias("sessions"), F.sum("n_alarms").alias("alarms"))


@query("stream_late")
def stream_late(spark, sf_dir):
    """Files out of order: windows that the watermark has closed don't come back."""
    path, rows = _files(spark, sf_dir)
    late = scratch_path(spark, "late")
    rows.withColumn("part", F.col("event_id") % 3).repartition(3, "part").drop("part").write.parquet(late)
    a = _drain(stream_ticks(stream_source(spark, path, rows.schema))).agg(F.sum("c").alias("c")).select(F.lit("in order").alias("arrival"), "c")
    b = _drain(stream_ticks(stream_source(spark, late, rows.schema), late="60 days")).agg(F.sum("c").alias("c")).select(F.lit("shuffled").alias("arrival"), "c")
    return a.unionByName(b)


@query("stream_candidates")
def stream_candidates(spark, sf_dir):
    """Ticks of five event channels with one interval of misplaced readings, repaired as a stream."""
    clean = stored(panels.event_ordinals(spark, sf_dir), "clean")
    ends = inject.extent(clean)
    bad = stored(inject.inject(clean, inject.example_plan(ends)), "bad")
    fit = model.packed(model.fit_moments(clean)).first()
    spaced = bad.withColumn("ts", F.timestamp_seconds(F.col("n") * 60)).select("eq_id", "ts", "x")
    path = scratch_path(spark, "panel")
    last = ends.first()["last"]
    for k in range(4):  # files arrive in order of time
        part = (F.unix_seconds("ts") > k * last * 15) & (F.unix_seconds("ts") <= (k + 1) * last * 15)
        spaced.filter(part).coalesce(1).write.mode("append").parquet(path)
    cfg = RepairConfig(theta_m=0.2)
    live = stream_repair(stream_source(spark, path, spaced.schema), list(fit["mu"]), list(fit["sigma"]), cfg, "1 hour")
    return _drain(live).groupBy("kind", "sigma", "status").agg(F.count("*").alias("cnt"), F.min("l").alias("l"), F.max("r").alias("r"))


def check_runs(spark: SparkSession, bits: list[int]) -> DataFrame:
    """Islands of a dense sequence, for notebooks and tests."""
    rows = spark.createDataFrame([(0, "x", i + 1) for i, b in enumerate(bits) if b] or [], "eq_id long, sigma string, n long")
    return runs.islands(rows)
