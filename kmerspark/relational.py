"""Registered queries over the given tables for the parts of the engine's own surface that the sketches lean on."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .operators.store import shared_path, stored
from .plans.workloads import table
from .queries import BASE, BENCH_WORDS, K, docs, passages, query, words
from .sources import reads as R
from .streaming import online

SLOT = 1800


@query("""WITH w AS (SELECT DISTINCT user_id, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 9 HOUR AS a FROM events)
SELECT w.user_id, w.a AS began, count(*) AS n FROM events e JOIN w ON e.user_id = w.user_id AND e.ts >= w.a AND e.ts < w.a + INTERVAL 8 HOUR GROUP BY ALL""")
def range_join_shifts(spark, d):
    """Events within intervals of their user: an interval join whose intervals are cut into slots, so it hashes."""
    events = table(spark, d, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    shifts = events.select("user_id", (F.date_trunc("day", "ts") + F.expr("INTERVAL 9 HOURS")).alias("a")).distinct().withColumn("b", F.col("a") + F.expr("INTERVAL 8 HOURS"))
    return interval_join(events, shifts, "ts", "a", "b", ["user_id"]).groupBy("user_id", F.col("a").cast("timestamp_ntz").alias("began")).agg(F.count("*").alias("n"))


def interval_join(points: DataFrame, intervals: DataFrame, at: str, low: str, high: str, keys: list[str], slot: int = SLOT) -> DataFrame:
    """Points with the intervals [low, high) that hold them, for equal keys: both sides are dealt by slots of time."""
    second = lambda c: F.floor(F.unix_timestamp(c) / slot)
    cut = intervals.withColumn("_slot", F.explode(F.sequence(second(F.col(low)), second(F.col(high)))))
    met = points.withColumn("_slot", second(F.col(at))).join(cut, [*keys, "_slot"])
    return met.filter((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("_slot")


@query("SELECT lang, count_if(source = 'src2')::BIGINT AS src2, count_if(source = 'src4')::BIGINT AS src4, count_if(source = 'src6')::BIGINT AS src6 FROM documents GROUP BY lang")
def pivot_sources(spark, d):
    found = table(spark, d, "documents").groupBy("lang").pivot("source", ["src2", "src4", "src6"]).agg(F.count("doc_id"))
    return found.select("lang", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("src2", "src4", "src6")))


@query("SELECT n_name, count(*) AS n, sum(c_acctbal)::DECIMAL(38, 2)::VARCHAR AS total FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def shuffle_hash_join(spark, d):
    nation = table(spark, d, "nation").hint("shuffle_hash")
    total = F.sum(F.col("c_acctbal").cast("decimal(18,2)")).cast("decimal(38,2)").cast("string")
    return table(spark, d, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"), total.alias("total"))


@query("SELECT o_custkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def sort_merge_join(spark, d):
    return table(spark, d, "orders").join(table(spark, d, "customer").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("o_custkey").agg(F.count("*").alias("n"))


@query(f"{BASE} SELECT kmer, cnt::BIGINT AS cnt FROM counts ORDER BY cnt DESC, kmer LIMIT 20 OFFSET 20")
def repeats_next_page(spark, d):
    return words(spark, d).orderBy(F.desc("cnt"), "kmer").offset(20).limit(20)


@query("SELECT event_type AS item, count(*) AS n FROM events GROUP BY 1 ORDER BY n DESC LIMIT 10")
def approximate_top_k(spark, d):
    """Frequent items from the engine's sketch; with so few different items its counts are exact."""
    top = table(spark, d, "events").agg(F.expr("approx_top_k(event_type, 10, 1024)").alias("t"))
    return top.select(F.explode("t").alias("x")).select(F.col("x.item").alias("item"), F.col("x.count").alias("n"))


@query(f"""{BASE},\n{BENCH_WORDS}, a AS (SELECT w FROM bench_occ) SELECT 'intersect_all' AS op, count(*) AS n FROM (SELECT w FROM occ INTERSECT ALL SELECT w FROM a)
UNION ALL SELECT 'except_all', count(*) FROM (SELECT w FROM a EXCEPT ALL SELECT w FROM occ)""")
def multiset_operations(spark, d):
    from .operators.kmers import explode_kmers

    a = explode_kmers(docs(spark, d), K, with_pos=False)
    b = explode_kmers(R.genome_of(table(spark, d, "benchmark")).select(F.col("contig_id").alias("read_id"), "seq"), K, with_pos=False)
    both = (("intersect_all", a.intersectAll(b)), ("except_all", b.exceptAll(a)))
    one, two = (df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n") for name, df in both)
    return one.unionByName(two)


@query("""SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS lately,
 first_value(event_type) OVER w AS first_type, nth_value(event_type, 2) OVER w AS second_type, round(percent_rank() OVER (PARTITION BY user_id ORDER BY ts, event_id), 6) AS place, round(cume_dist() OVER (PARTITION BY user_id ORDER BY ts, event_id), 6) AS share
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def analytic_windows(spark, d):
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    table(spark, d, "events").select("user_id", "event_id", "event_type", F.col("ts").cast("timestamp").alias("ts")).createOrReplaceTempView("_events_w")
    return spark.table("_events_w").select(
        "event_id", F.expr("count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW)").alias("lately"),
        F.first_value("event_type").over(whole).alias("first_type"), F.nth_value("event_type", 2).over(whole).alias("second_type"),
        F.round(F.percent_rank().over(by), 6).alias("place"), F.round(F.cume_dist().over(by), 6).alias("share"),
    )


@query("""SELECT p_partkey, lpad(p_partkey::VARCHAR, 8, '0') AS code, instr(p_name, ' ') AS first_gap, levenshtein(p_name, p_brand) AS distance, upper(substring(p_name, 1, 3)) AS head,
 reverse(p_brand) AS back, ascii(p_name) AS letter, translate(p_brand, 'Bb', '88') AS mapped, split_part(p_name, ' ', 2) AS second, 'xx' || substring(p_brand, 3) AS overlaid FROM part""")
def scalar_strings(spark, d):
    return table(spark, d, "part").select(
        "p_partkey", F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("code"), F.instr("p_name", " ").cast("long").alias("first_gap"), F.levenshtein("p_name", "p_brand").cast("long").alias("distance"), F.upper(F.substring("p_name", 1, 3)).alias("head"),
        F.reverse("p_brand").alias("back"), F.ascii("p_name").alias("letter"), F.translate("p_brand", "Bb", "88").alias("mapped"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("second"), F.overlay("p_brand", F.lit("xx"), 1, 2).alias("overlaid"),
    )


@query("""SELECT o_orderkey, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS days, year(o_orderdate)::INTEGER AS y, quarter(o_orderdate)::INTEGER AS q, date_trunc('month', o_orderdate)::DATE::VARCHAR AS m,
 (o_orderdate::DATE + INTERVAL 40 DAY)::DATE::VARCHAR AS later, last_day(o_orderdate::DATE)::VARCHAR AS month_end, dayofyear(o_orderdate)::INTEGER AS doy, (o_orderdate::DATE + INTERVAL 2 MONTH)::DATE::VARCHAR AS two_months FROM orders""")
def scalar_dates(spark, d):
    day = F.col("o_orderdate").cast("date")
    return table(spark, d, "orders").select(
        "o_orderkey", F.date_diff(day, F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.year(day).alias("y"), F.quarter(day).alias("q"), F.trunc(day, "month").cast("string").alias("m"),
        F.expr("CAST(o_orderdate AS DATE) + INTERVAL '40' DAY").cast("date").cast("string").alias("later"), F.last_day(day).cast("string").alias("month_end"), F.dayofyear(day).alias("doy"), F.add_months(day, 2).cast("string").alias("two_months"),
    )


@query("""SELECT source, cardinality(map_from_entries(list(DISTINCT (lang, 1)))) AS n_langs, list_max(list(n_chars)) AS longest, len(list_distinct(list(lang))) AS n_distinct,
 list_contains(list(lang), 'en') AS has_en, array_to_string(list_sort(list(DISTINCT lang)), '|') AS joined FROM documents GROUP BY source""")
def maps_and_arrays(spark, d):
    langs = F.sort_array(F.collect_set("lang"))
    own = table(spark, d, "documents").groupBy("source").agg(langs.alias("langs"), F.max("n_chars").alias("longest"))
    as_map = F.map_from_arrays("langs", F.transform("langs", lambda _: F.lit(1)))
    zipped = F.arrays_zip("langs", F.transform("langs", lambda x, i: i).alias("i"))
    return own.select("source", F.size(F.map_keys(F.map_filter(as_map, lambda k, v: v > 0))).cast("long").alias("n_langs"), "longest", F.size(F.array_distinct(F.transform(zipped, lambda z: z["langs"]))).cast("long").alias("n_distinct"), F.array_contains("langs", "en").alias("has_en"), F.array_join("langs", "|").alias("joined"))


@query("SELECT event_id, '{\"id\":' || event_id || ',\"type\":\"' || event_type || '\"}' AS packed, json_valid(props) AS valid, (props->>'k')::BIGINT AS k FROM events")
def json_round_trip(spark, d):
    events = table(spark, d, "events")
    packed = F.to_json(F.struct(F.col("event_id").alias("id"), F.col("event_type").alias("type")))
    shape = F.schema_of_json(F.lit('{"id": 1, "type": "x"}'))
    again = F.from_json(packed, shape)
    return events.filter(again["id"] == F.col("event_id")).select("event_id", packed.alias("packed"), F.get_json_object("props", "$").isNotNull().alias("valid"), F.get_json_object("props", "$.k").cast("long").alias("k"))


def _stream_of(t: DataFrame, order: str, files: int) -> DataFrame:
    """A table as a stream of about `files` micro-batches, in the order of a column: files written one after another."""
    spark, path = t.sparkSession, shared_path(t.sparkSession)
    if "ts" in t.columns:
        t = t.withColumn("ts", F.col("ts").cast("timestamp"))
    t = t.withColumn("_o", F.expr(order).cast("long"))
    cuts = sorted(set(t.approxQuantile("_o", [i / files for i in range(1, files)], 0.001)))
    part = sum((F.when(F.col("_o") > c, 1).otherwise(0) for c in cuts), F.lit(0))
    for i in range(len(cuts) + 1):
        t.filter(part == i).drop("_o").coalesce(1).sortWithinPartitions(F.expr(order)).write.mode("append").parquet(path)
    return spark.readStream.schema(t.drop("_o").schema).option("maxFilesPerTrigger", 1).parquet(path)


def _drain(stream: DataFrame) -> tuple[DataFrame, list]:
    """Run a stream to its end into a table; returns the table and the progress of the batches."""
    out = shared_path(stream.sparkSession)
    run = stream.writeStream.option("checkpointLocation", shared_path(stream.sparkSession)).trigger(availableNow=True).start(out, format="parquet")
    run.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out), run.recentProgress


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, d):
    """Each user and type once, from micro-batches, within a watermark longer than the stream."""
    stream = _stream_of(table(spark, d, "events"), "event_id", 4)
    return _drain(online.dedup_stream(stream, "4000 days", ["user_id", "event_type"]).select("user_id", "event_type"))[0]


@query("SELECT e.event_id, l.toxic FROM events e JOIN labels l ON e.user_id = l.doc_id")
def stream_static_join(spark, d):
    labels = table(spark, d, "labels").select(F.col("doc_id").alias("user_id"), "toxic")
    stream = _stream_of(table(spark, d, "events"), "event_id", 3)
    return _drain(stream.join(labels, "user_id").select("event_id", "toxic"))[0]


@query("""WITH m AS (SELECT max(ts) AS top FROM events), b AS (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS w_start, event_type, count(*) AS n FROM events GROUP BY ALL)
SELECT w_start, event_type, n FROM b, m WHERE w_start + INTERVAL 1 HOUR <= top - INTERVAL 10 MINUTE""")
def late_data(spark, d):
    """Hourly counts of a stream in order of time: only windows that the watermark has passed are out, and they are whole."""
    counts = online.windowed_counts(_stream_of(table(spark, d, "events"), "unix_micros(ts)", 5), "1 hour")
    return _drain(counts)[0].select(F.col("w_start").cast("timestamp_ntz").alias("w_start"), "event_type", "n")


@query("SELECT 0::BIGINT AS in_order, TRUE AS some_late, count(*) AS total FROM events")
def late_rows_metric(spark, d):
    """Rows that streams have dropped as late: none of one in order of time, some of one in reverse."""
    events = table(spark, d, "events")
    dropped = [online.dropped_late(_drain(online.windowed_counts(_stream_of(events, order, 4), "1 hour"))[1]) for order in ("unix_micros(ts)", "-unix_micros(ts)")]
    return events.agg(F.count("*").alias("total")).select(F.lit(dropped[0]).cast("long").alias("in_order"), F.lit(dropped[1] > 0).alias("some_late"), "total")


@query(f"""WITH RECURSIVE {BASE.removeprefix('WITH ')},\n{BENCH_WORDS}, b AS (SELECT DISTINCT read_id, w FROM bench_occ),
e AS (SELECT DISTINCT x.read_id AS a, y.read_id AS b FROM b x JOIN b y USING (w)), reach AS (SELECT read_id, read_id AS c FROM (SELECT DISTINCT read_id FROM b) UNION SELECT r.read_id, e.b FROM reach r JOIN e ON e.a = r.c)
SELECT read_id, min(c) AS component FROM reach GROUP BY read_id""")
def components_of_passages(spark, d):
    """Benchmark passages tied by shared words, directly or over others."""
    from .operators.graph import graph_components

    reads = R.genome_of(table(spark, d, "benchmark")).select(F.col("contig_id").alias("read_id"), "seq")
    return graph_components(reads, K, stored)


@query(f"{BASE},\n{BENCH_WORDS} SELECT count(*) AS n, count(c.kmer) AS n_present FROM q LEFT JOIN counts c USING (kmer)")
def broadcast_hash_join(spark, d):
    asked = passages(spark, d)
    found = words(spark, d).join(F.broadcast(asked.select(F.col("kmer").alias("_k"))), F.col("kmer") == F.col("_k"), "left_semi")  # words of the bounded benchmark
    n = stored(found.agg(F.count("*").alias("n_present")))
    return asked.agg(F.count("*").alias("n")).crossJoin(n)  # one row each
