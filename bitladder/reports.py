"""Queries for the relational operators, functions, sources, sinks and streams around retrieval, and their SQL."""

from __future__ import annotations

import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import workloads as w
from .functions import codes, text
from .operators import baselines, encoder, ladder, match, metrics, relational, retrieve, samples
from .oracles import EXACT, FLOAT, LANE, ROWS, TOP, WIDTH, N, hashed_sum, lane_top, pairs, planes, vector_planes, words
from .plans.index import LadderIndex, LadderModel
from .sources import io
from .streaming import stream

# joins and aggregates ---------------------------------------------------------------


def joined_large(spark: SparkSession, sf: str, how: str = "merge") -> DataFrame:
    """Line items with their orders by a join of two large sides, counted by priority."""
    lines = io.table(spark, sf, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_quantity")
    orders = io.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    return relational.join_large(lines, orders, "o_orderkey", how).groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.sum("l_quantity").cast("long").alias("quantity"))


def join_kinds(spark: SparkSession, sf: str) -> DataFrame:
    """Customers with and without orders: semi and anti join."""
    c = io.table(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    o = io.table(spark, sf, "orders").select(F.col("o_custkey").alias("c_custkey"))
    kinds = [relational.survivors(c, o, "c_custkey").withColumn("kind", F.lit("with")), relational.minus_pairs(c, o, "c_custkey").withColumn("kind", F.lit("without"))]
    return kinds[0].unionByName(kinds[1]).groupBy("kind", "c_mktsegment").agg(F.count("*").alias("customers"))


def price_bands(spark: SparkSession, sf: str) -> DataFrame:
    """Parts in price bands by a theta join with a small side."""
    bands = spark.createDataFrame([("low", 0.0, 1000.0), ("middle", 1000.0, 1500.0), ("high", 1500.0, 1e9)], "band string, lo double, hi double")
    parts = io.table(spark, sf, "part").select("p_retailprice", "p_size")
    return relational.nested_loop(parts, bands, (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("parts"), F.sum("p_size").cast("long").alias("sizes"))


def best_items(spark: SparkSession, sf: str) -> DataFrame:
    """Per user the events of largest and smallest value, the first and the last in time, and the largest (value, event)."""
    e = io.table(spark, sf, "events")
    first = F.struct("ts", "event_id")
    top = F.max(F.struct("value", "event_id"))  # a struct buffer: a sort aggregate
    return e.groupBy("user_id").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("best"), F.min_by("event_id", F.struct("value", "event_id")).alias("worst"), F.min_by("event_type", first).alias("first_type"), F.max_by("event_type", first).alias("last_type"), top["event_id"].alias("sorted_best"))


def sketches(spark: SparkSession, sf: str) -> DataFrame:
    """Sketches of the events' users against exact figures: within their error bounds or not."""
    e = io.table(spark, sf, "events")
    near = io.checkpoint(relational.approx_profile(e, "user_id"), "sketches")
    # the median by its place among the rows: gaps between ids say nothing about a sketch
    median = near.select(F.col("quantiles")[0].alias("median"))
    rows = e.crossJoin(F.broadcast(median)).agg(F.count_distinct("user_id").alias("users"), F.count("user_id").alias("n"), F.count_if(F.col("user_id") < F.col("median")).alias("below"), F.count_if(F.col("user_id") <= F.col("median")).alias("to"))
    rows = rows.crossJoin(F.broadcast(near))
    placed = (F.col("below") <= F.col("n") * 0.51) & (F.col("to") >= F.col("n") * 0.49)
    return rows.select("users", (F.abs(F.col("distinct") - F.col("users")) <= F.col("users") * 0.15).alias("distinct_near"), placed.alias("median_near"), (F.size("top") == F.least(F.lit(5), F.col("users"))).alias("five_items"))


def line_profile(spark: SparkSession, sf: str) -> DataFrame:
    """Exact median, spread and correlation of price and quantity."""
    p = relational.exact_profile(io.table(spark, sf, "lineitem"), "l_extendedprice", "l_quantity")
    return p.select(F.round("median", 6).alias("median"), F.round("spread", 4).alias("spread"), F.round("corr", 6).alias("corr"))


def subtotals(spark: SparkSession, sf: str) -> DataFrame:
    """Orders by year and priority: rollup, and two grouping sets of the same."""
    o = io.table(spark, sf, "orders").select(F.year("o_orderdate").alias("year"), "o_orderpriority")
    rolled = o.rollup("year", "o_orderpriority").agg(F.count("*").alias("orders")).withColumn("kind", F.lit("rollup"))
    sets = o.groupingSets([["year"], ["o_orderpriority"]], "year", "o_orderpriority").agg(F.count("*").alias("orders")).withColumn("kind", F.lit("sets"))
    return rolled.unionByName(sets)


def plane_bits(spark: SparkSession, sf: str) -> DataFrame:
    """For each plane word the bits set in all, in any and in an odd number of codes."""
    c, params = w.coded(spark, sf)
    shown = [F.lpad(F.conv(F.hex(x), 16, 2), 64, "0").alias(x) for x in ("all_set", "any_set", "parity")]
    return metrics.plane_balance(c, params.spec().columns()).select("word", *shown)


def frequent_trigrams(spark: SparkSession, sf: str) -> DataFrame:
    """Trigrams in at least ten documents (having), from one row per document and trigram."""
    grams = relational.explode_trigrams(io.table(spark, sf, "documents"), "doc_id").distinct()
    return grams.groupBy("trigram").agg(F.count("*").alias("documents")).where("documents >= 10")


def term_positions(spark: SparkSession, sf: str) -> DataFrame:
    """Exploded words of benchmark items with their places: how often, first and last."""
    t = relational.explode_terms(io.table(spark, sf, "benchmark"), "item_id")
    return t.groupBy("item_id", "term").agg(F.count("*").alias("n"), F.min("pos").alias("first"), F.max("pos").alias("last"))


# windows, sorts and paging -------------------------------------------------------------


def rank_family(spark: SparkSession, sf: str) -> DataFrame:
    """All ranks of parts by size within their brand."""
    by = Window.partitionBy("p_brand").orderBy("p_size")
    named = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")
    whole = named.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return io.table(spark, sf, "part").select("p_partkey", F.rank().over(by).alias("rank"), F.dense_rank().over(by).alias("dense"), F.round(F.percent_rank().over(by), 9).alias("percent"), F.round(F.cume_dist().over(by), 9).alias("cume"), F.first("p_partkey").over(whole).alias("first"), F.nth_value("p_partkey", 2).over(whole).alias("second"))


def smoothed_volume(spark: SparkSession, sf: str) -> DataFrame:
    """Events a day and their moving average over seven days."""
    days = io.table(spark, sf, "events").groupBy(F.to_date("ts").alias("day")).agg(F.count("*").alias("events"))
    return relational.smoothed(days, "day", "events", 7).withColumn("smooth", F.round("smooth", 9))


def single_query(spark: SparkSession, sf: str) -> DataFrame:
    """One query at run time: a top-k over all keywords without a window."""
    q, k, qs, ks = w.sides(spark, sf)
    one = match.exhaustive(q.where("query_id = 3"), k, qs, ks).where("keyword_id <> 3")
    return one.orderBy(F.desc("rank_key"), "keyword_id").limit(N).select("keyword_id", "rank_key", "dot")


def second_page(spark: SparkSession, sf: str) -> DataFrame:
    """The second page of twenty parts by price."""
    return relational.page(io.table(spark, sf, "part").select("p_partkey", "p_retailprice"), [F.desc("p_retailprice"), "p_partkey"], 20, 1)


# functions -----------------------------------------------------------------------------


def string_functions(spark: SparkSession, sf: str) -> DataFrame:
    """String functions on part names."""
    p = io.table(spark, sf, "part")
    return p.select("p_partkey", F.levenshtein("p_name", "p_type").alias("distance"), F.sha2("p_name", 256).alias("sha"), F.startswith("p_type", F.lit("STANDARD")).alias("standard"), F.contains("p_name", F.lit("re")).alias("has"), F.concat_ws("|", F.trim("p_brand"), F.lower("p_type")).alias("label"), F.regexp_extract("p_brand", r"(\d+)", 1).alias("number"), F.size(F.sentences("p_name")).alias("sentences"))


def term_maps(spark: SparkSession, sf: str) -> DataFrame:
    """Word counts of a user turn and of the answer as maps, and the words they share."""
    def counted(c: str):
        t = text.words(F.col(c))
        return F.map_from_entries(F.transform(F.array_distinct(t), lambda x: F.struct(x.alias("k"), F.size(F.filter(t, lambda y: y == x)).alias("n"))))

    both = samples.turn_pairs(io.table(spark, sf, "conversations")).select("pair_id", counted("q_text").alias("q"), counted("k_text").alias("k"))
    least = F.map_zip_with("q", "k", lambda _, a, b: F.least(F.coalesce(a, F.lit(0)), F.coalesce(b, F.lit(0))))
    return both.select("pair_id", F.size(F.map_keys("q")).alias("q_terms"), F.aggregate(F.map_values(least), F.lit(0), lambda s, x: s + x).alias("common"), F.coalesce(F.element_at("q", F.lit("the")), F.lit(0)).alias("the"))


def json_props(spark: SparkSession, sf: str) -> DataFrame:
    """Event properties parsed and written again."""
    e = io.table(spark, sf, "events")
    kind = e.select(F.schema_of_json(F.lit('{"k": 1}')).alias("s")).limit(1)
    parsed = e.withColumn("p", F.from_json("props", "k long"))
    return parsed.crossJoin(F.broadcast(kind)).groupBy(F.to_json(F.struct((F.col("p.k") % 10).alias("tens"))).alias("tens"), "s").agg(F.count("*").alias("events")).select("tens", F.col("s").alias("schema"), "events")


def attribute_filters(spark: SparkSession, sf: str) -> DataFrame:
    """Filters of retrieval: every kind, on attributes kept with the index."""
    parts = io.table(spark, sf, "part").select(F.col("p_partkey").alias("pos"), "p_brand", "p_size", "p_type", F.split("p_name", " ").alias("tags"))
    kinds = {"compare": "p_size > 25", "in": "p_brand in ('Brand#1', 'Brand#2')", "between": "p_size between 10 and 20", "like": "p_type like 'STANDARD%'", "null": "p_type is not null", "array": "array_contains(tags, 'red')"}
    out = None
    q, k, qs, ks = w.sides(spark, sf)
    index = io.checkpoint(k.join(parts, "pos"), "index")
    for kind, where in kinds.items():
        found = retrieve.top_n(q, index, qs, ks, 3, mode="exact", backend="block", where=where, exclude_self=True)
        one = found.groupBy().agg(F.count("*").alias("found"), F.coalesce(F.sum("rank_key"), F.lit(0)).alias("keys")).select(F.lit(kind).alias("kind"), "found", F.col("keys").cast("decimal(38,0)").cast("string").alias("keys"))
        out = one if out is None else out.unionByName(one)
    return out


def arrow_functions(spark: SparkSession, sf: str) -> DataFrame:
    """Arrow scalar functions: vectors to plane words and back to signs."""
    from .functions import sqlfuncs  # needs a session

    encode = sqlfuncs.encode_vector_udf(ladder.init_hadamard(64, 1))
    coded = w.vectors(spark, sf).select("vec_id", encode(F.col("embedding").cast("array<double>")).alias("words"))
    return coded.select("vec_id", *[F.array_join(F.transform(sqlfuncs.sign_planes(F.col("words")[t]), lambda x: F.when(x > 0, "+").otherwise("-")), "").alias(f"plane{t}") for t in (0, 1)])


def grouped_functions(spark: SparkSession, sf: str) -> DataFrame:
    """Grouped Arrow aggregates: the vector sum of each label, and the area of its first coordinate against the second's sign."""
    from .functions import sqlfuncs  # needs a session

    e = w.vectors(spark, sf)
    v = F.col("embedding").cast("array<double>")
    area = sqlfuncs.auc_agg(F.element_at(v, 1), F.element_at(v, 2) > 0)
    summed = e.groupBy("label").agg(sqlfuncs.vector_sum(v).alias("total"))
    return e.groupBy("label").agg(area.alias("area")).join(summed, "label").select("label", F.round("area", 9).alias("area"), F.round(F.element_at("total", 1), 6).alias("first"), F.round(F.element_at("total", 64), 6).alias("last"))


def table_functions(spark: SparkSession, sf: str) -> DataFrame:
    """Table functions in SQL: plane words of vectors, letter trigrams of part names."""
    from .functions import sqlfuncs  # needs a session

    sqlfuncs.register_functions(spark)
    w.vectors(spark, sf).select("vec_id", F.col("embedding").cast("array<double>").alias("v")).createOrReplaceTempView("w_vectors")
    io.table(spark, sf, "part").select("p_partkey", "p_name").createOrReplaceTempView("w_parts")
    return spark.sql(
        "SELECT 'plane ' || plane AS kind, count(*) AS n, sum(bit_count(value)) AS total FROM w_vectors, LATERAL code_planes(v, 1) GROUP BY plane "
        "UNION ALL SELECT 'trigram ' || trigram, count(*), sum(pos) FROM w_parts, LATERAL letter_trigrams(p_name) GROUP BY trigram"
    )


def query_metrics(spark: SparkSession, sf: str) -> DataFrame:
    """Recall of each query by a cogroup of its exact and its lane results (applyInArrow)."""
    exact, lane = (w.top(spark, sf, mode=m, backend="block").select("query_id", "keyword_id") for m in ("exact", "lane"))

    def measure(a: pa.Table, b: pa.Table) -> pa.Table:
        q = (a if a.num_rows else b).column("query_id")[0].as_py()
        hits = len(set(a.column("keyword_id").to_pylist()) & set(b.column("keyword_id").to_pylist()))
        return pa.table({"query_id": pa.array([q], pa.int64()), "hits": pa.array([hits], pa.int64()), "recall": pa.array([hits / N], pa.float64())})

    return exact.groupBy("query_id").cogroup(lane.groupBy("query_id")).applyInArrow(measure, "query_id long, hits long, recall double")


# sources, sinks and measures --------------------------------------------------------------


def formats(spark: SparkSession, sf: str) -> DataFrame:
    """Customers written and read again as CSV, JSON, ORC and text."""
    c = io.table(spark, sf, "customer").select("c_custkey", "c_mktsegment", "c_acctbal")
    base, out = f"{io.shared_dir(spark).rstrip('/')}/formats-{uuid.uuid4().hex}", None
    for fmt in ("csv", "json", "orc", "text"):
        rows = c if fmt != "text" else c.select(F.concat_ws(",", *c.columns).alias("value"))
        rows.write.format(fmt).save(f"{base}/{fmt}")
        back = io.read_any(spark, f"{base}/{fmt}", fmt, "value string" if fmt == "text" else "c_custkey long, c_mktsegment string, c_acctbal double")
        if fmt == "text":
            cut = F.split("value", ",")
            back = back.select(cut[0].cast("long").alias("c_custkey"), cut[1].alias("c_mktsegment"), cut[2].cast("double").alias("c_acctbal"))
        one = back.groupBy("c_mktsegment").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance")).withColumn("format", F.lit(fmt))
        out = one if out is None else out.unionByName(one)
    return out


def stored_results(spark: SparkSession, sf: str) -> DataFrame:
    """Lane results written to the sink and read back."""
    path = f"{io.shared_dir(spark).rstrip('/')}/results-{uuid.uuid4().hex}"
    io.write_results(w.top(spark, sf, backend="block"), path)
    return spark.read.parquet(path)


def stored_bytes(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes of stored indexes of one, two and three planes against floats: measured and by the model."""
    base, rows = f"{io.shared_dir(spark).rstrip('/')}/bytes-{uuid.uuid4().hex}", []
    made = io.generated_codes(spark, io.table(spark, sf, "lineitem"), 3)
    total = made.count()
    for p in (1, 2, 3):
        made.select(*codes.CodeSpec(64, p).columns()).write.option("compression", "none").parquet(f"{base}/{p}")
        rows.append((p, total, metrics.index_bytes(spark, f"{base}/{p}") / max(total, 1), 8))
    return spark.createDataFrame(rows, "planes int, keywords long, measured double, words int").select("planes", "keywords", F.round("measured", 3).alias("measured_bytes"), (F.col("planes") * F.col("words")).alias("model_bytes"), (F.lit(256) / F.col("measured")).alias("floats_over_codes"))


def candidate_traffic(spark: SparkSession, sf: str) -> DataFrame:
    """Rows that leave each stage of selection: all pairs, lane queues, the merge."""
    q, k, qs, ks = w.sides(spark, sf)
    k = io.checkpoint(k, "keywords")
    left = retrieve.lane_traffic(q, k, LANE, WIDTH, exclude_self=True).first()
    found = {"pairs": left["pairs"], "lanes": left["lanes"]} | metrics.traffic({"merged": retrieve.top_n(q, k, qs, ks, N, LANE, WIDTH, exclude_self=True)})
    return spark.createDataFrame(list(found.items()), "stage string, rows long")


def sampled_floats(spark: SparkSession, sf: str) -> DataFrame:
    """Full-precision brute force over a hash sample of a quarter of the keywords."""
    e = w.vectors(spark, sf)
    found = baselines.float_bruteforce(e, e, 250, 3)
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), "keyword_id", F.round("score", 9).alias("score"))


def vector_codes(spark: SparkSession, sf: str) -> DataFrame:
    """The word-sum layer of benchmark items: planes of their codes."""
    e = encoder.hashed_sum(io.table(spark, sf, "benchmark"), "item_id")
    c = ladder.encode_vectors(e, ladder.init_hadamard(64, 1))
    return c.select(F.col("keyword_id").alias("item_id"), *[F.array_join(F.transform(codes.unpack_expr(F.col(f"p{p}_w0")), lambda x: F.when(x > 0, "+").otherwise("-")), "").alias(f"plane{p}") for p in (0, 1)])


# streams ----------------------------------------------------------------------------------


def rates(spark: SparkSession, sf: str, **options) -> DataFrame:
    """Views and clicks in event-time windows, from files in time order under a one-hour watermark."""
    events = stream.events_stream(spark, w._event_files(spark, sf))
    out = w._streamed(spark, stream.stream_rates(events, lateness="1 hour", **options))
    return out.withColumn("ctr", F.round("ctr", 9)).withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


def late_rows(spark: SparkSession, sf: str) -> DataFrame:
    """A file of old events last: days that the watermark has closed lose them, and they are reported.

    Late rows are judged by the watermark of the batch before, so two files come first.
    """
    path = f"{io.shared_dir(spark).rstrip('/')}/late-{uuid.uuid4().hex}"
    e = io.table(spark, sf, "events")
    for part in (e.where("ts >= '2024-01-10' and ts < '2024-01-20'"), e.where("ts >= '2024-01-20'"), e.where("ts < '2024-01-10'")):
        w.append_file(part.coalesce(1).sortWithinPartitions("ts"), path)
    events = stream.events_stream(spark, path)
    out, cp = w._stream_dirs(spark)
    rated = stream.stream_rates(events, "1 day", lateness="1 hour")
    query = rated.writeStream.outputMode("append").option("checkpointLocation", cp).format("parquet").option("path", out).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.createDataFrame([(stream.late_report(query) > 0,)], "reported boolean").crossJoin(spark.read.parquet(out).agg(F.coalesce(F.sum(F.col("views") + F.col("clicks")), F.lit(0)).alias("kept")))


def index_upserts(spark: SparkSession, sf: str) -> DataFrame:
    """Every vector arrives, a tenth of them again and changed: the newest version of each is what is read."""
    path, (out, cp) = f"{io.shared_dir(spark).rstrip('/')}/upserts-{uuid.uuid4().hex}", w._stream_dirs(spark)
    e = w.vectors(spark, sf).select("vec_id", "embedding")
    changed = e.where("vec_id % 10 = 0").withColumn("embedding", F.transform("embedding", lambda x: -x))
    for part in (e, changed):
        w.append_file(part.coalesce(1), path)
    model = LadderModel(ladder.init_hadamard(64, 2))
    arriving = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
    stream.stream_index_upsert(arriving, model.encode, out, cp).awaitTermination()
    latest = stream.read_latest(spark, out)
    signs = F.array_join(F.transform(codes.unpack_expr(F.col("p0_w0")), lambda x: F.when(x > 0, "+").otherwise("-")), "")
    return latest.select(F.col("keyword_id").alias("vec_id"), signs.alias("plane0"), F.col("version").cast("int").alias("version"))


def running_top(spark: SparkSession, sf: str, stateful: bool = True) -> DataFrame:
    """Events as scored keywords of their user: the running three best, by a stateful operator or by merging batches."""
    path = w._event_files(spark, sf)
    events = stream.events_stream(spark, path).select(F.col("user_id").alias("query_id"), F.col("event_id").alias("keyword_id"), F.col("value").alias("score")).where("score is not null")
    out, cp = w._stream_dirs(spark)
    if stateful:
        stream.run_stateful_top_n(events, 3, out, cp).awaitTermination()
        rows = spark.read.parquet(out)
        newest = Window.partitionBy("query_id")
        rows = rows.withColumn("last", F.max("batch").over(newest)).where("batch = last")
    else:
        stream.stream_keyword_top_n(events, 3, out, cp).awaitTermination()
        rows = spark.read.parquet(stream.last_state(spark, out))
    return rows.select("query_id", F.col("rank").cast("int").alias("rank"), "keyword_id")


def bounded_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Clicks with their views of the last thirty minutes, under ten minutes of lateness: state stays bounded."""
    events = stream.events_stream(spark, w._event_files(spark, sf))
    return w._streamed(spark, stream.stream_pairs(events)).select("click_id", "view_id")


QUERIES = {
    "join_merge": joined_large,
    "join_shuffle_hash": lambda spark, sf: joined_large(spark, sf, "shuffle_hash"),
    "join_kinds": join_kinds,
    "price_bands": price_bands,
    "best_items": best_items,
    "sketches": sketches,
    "line_profile": line_profile,
    "subtotals": subtotals,
    "plane_bits": plane_bits,
    "frequent_trigrams": frequent_trigrams,
    "term_positions": term_positions,
    "rank_family": rank_family,
    "smoothed_volume": smoothed_volume,
    "single_query": single_query,
    "second_page": second_page,
    "string_functions": string_functions,
    "term_maps": term_maps,
    "json_props": json_props,
    "attribute_filters": attribute_filters,
    "arrow_functions": arrow_functions,
    "grouped_functions": grouped_functions,
    "table_functions": table_functions,
    "query_metrics": query_metrics,
    "formats": formats,
    "stored_results": stored_results,
    "stored_bytes": stored_bytes,
    "candidate_traffic": candidate_traffic,
    "sampled_floats": sampled_floats,
    "vector_codes": vector_codes,
    "stream_tumbling": rates,
    "stream_sliding": lambda spark, sf: rates(spark, sf, window="6 hours", slide="3 hours"),
    "stream_sessions": lambda spark, sf: rates(spark, sf, gap="2 hours"),
    "stream_late": late_rows,
    "stream_upserts": index_upserts,
    "stream_running_top": running_top,
    "stream_merged_top": lambda spark, sf: running_top(spark, sf, False),
    "stream_pairs_bounded": bounded_pairs,
}

SIGNS = "array_to_string(list_transform({s}, lambda x: CASE WHEN x > 0 THEN '+' ELSE '-' END), '')"
BITS = "list_transform({s}, lambda x: CASE WHEN x > 0 THEN 1 ELSE 0 END)"


def folded(kind: str) -> str:
    """Bits from high to low of a plane word: set in all, in any, in an odd number of vectors."""
    how = {"all_set": "min(b)", "any_set": "max(b)", "parity": "sum(b) % 2"}[kind]
    return f"SELECT word, string_agg(CAST(CAST(x AS INTEGER) AS VARCHAR), '' ORDER BY i DESC) AS {kind} FROM (SELECT word, i, {how} AS x FROM bits GROUP BY word, i) GROUP BY word"


RATES = "count_if(event_type = 'view') AS views, count_if(event_type = 'click') AS clicks, round(CASE WHEN count_if(event_type = 'view') > 0 THEN count_if(event_type = 'click') / count_if(event_type = 'view') END, 9) AS ctr"
CLOSED = '"end" <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR'
JOINED = "SELECT o_orderpriority, count(*) AS lines, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY 1"
RUNNING = "SELECT user_id AS query_id, CAST(rn AS INTEGER) AS rank, event_id AS keyword_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS rn FROM events WHERE value IS NOT NULL) WHERE rn <= 3"
FILTERS = {"compare": "p_size > 25", "in": "p_brand IN ('Brand#1', 'Brand#2')", "between": "p_size BETWEEN 10 AND 20", "like": "p_type LIKE 'STANDARD%'", "null": "p_type IS NOT NULL", "array": "list_contains(string_split(p_name, ' '), 'red')"}
TURNS = "SELECT conv_id * 16777216 + turn AS pair_id, text AS q_text, k_text FROM (SELECT *, lead(role) OVER w AS nr, lead(text) OVER w AS k_text FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND nr = 'assistant'"

ORACLES = {
    "join_merge": JOINED,
    "join_shuffle_hash": JOINED,
    "join_kinds": "SELECT CASE WHEN EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) THEN 'with' ELSE 'without' END AS kind, c_mktsegment, count(*) AS customers FROM customer GROUP BY ALL",
    "price_bands": "SELECT CASE WHEN p_retailprice < 1000 THEN 'low' WHEN p_retailprice < 1500 THEN 'middle' ELSE 'high' END AS band, count(*) AS parts, CAST(sum(p_size) AS BIGINT) AS sizes FROM part GROUP BY 1",
    "best_items": "SELECT user_id, arg_max(event_id, (value, event_id)) AS best, arg_min(event_id, (value, event_id)) AS worst, arg_min(event_type, (ts, event_id)) AS first_type, arg_max(event_type, (ts, event_id)) AS last_type, arg_max(event_id, (value, event_id)) AS sorted_best FROM events GROUP BY user_id",
    "sketches": "SELECT count(DISTINCT user_id) AS users, true AS distinct_near, true AS median_near, true AS five_items FROM events",
    "line_profile": "SELECT round(quantile_cont(l_extendedprice, 0.5), 6) AS median, round(stddev_samp(l_extendedprice), 4) AS spread, round(corr(l_extendedprice, l_quantity), 6) AS corr FROM lineitem",
    "subtotals": "SELECT year, o_orderpriority, count(*) AS orders, 'rollup' AS kind FROM (SELECT CAST(year(o_orderdate) AS INTEGER) AS year, o_orderpriority FROM orders) GROUP BY ROLLUP (year, o_orderpriority) UNION ALL SELECT year, o_orderpriority, count(*), 'sets' FROM (SELECT CAST(year(o_orderdate) AS INTEGER) AS year, o_orderpriority FROM orders) GROUP BY GROUPING SETS ((year), (o_orderpriority))",
    "plane_bits": f"WITH {planes()}, bits AS (SELECT word, unnest({BITS.format(s='s')}) AS b, unnest(range(64)) AS i FROM (SELECT 'p0_w0' AS word, s0 AS s FROM p2 UNION ALL SELECT 'p1_w0', s1 FROM p2 UNION ALL SELECT 'p2_w0', s2 FROM p2)) SELECT * FROM ({folded('all_set')}) JOIN ({folded('any_set')}) USING (word) JOIN ({folded('parity')}) USING (word)",
    "frequent_trigrams": f"SELECT trigram, count(DISTINCT doc_id) AS documents FROM (SELECT doc_id, substr(w, i, 3) AS trigram FROM (SELECT doc_id, '#' || w || '#' AS w, unnest(range(1, length(w) + 1)) AS i FROM (SELECT doc_id, unnest({words()}) AS w FROM documents))) GROUP BY trigram HAVING count(DISTINCT doc_id) >= 10",
    "term_positions": f"SELECT item_id, w[i] AS term, count(*) AS n, CAST(min(i) - 1 AS INTEGER) AS first, CAST(max(i) - 1 AS INTEGER) AS last FROM (SELECT item_id, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT item_id, {words()} AS w FROM benchmark)) GROUP BY item_id, w[i]",
    "rank_family": "SELECT p_partkey, CAST(rank() OVER b AS INTEGER) AS rank, CAST(dense_rank() OVER b AS INTEGER) AS dense, round(percent_rank() OVER b, 9) AS percent, round(cume_dist() OVER b, 9) AS cume, first_value(p_partkey) OVER n AS first, nth_value(p_partkey, 2) OVER n AS second FROM part WINDOW b AS (PARTITION BY p_brand ORDER BY p_size), n AS (PARTITION BY p_brand ORDER BY p_size, p_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "smoothed_volume": "SELECT day, events, round(avg(events) OVER (ORDER BY day ROWS BETWEEN 6 PRECEDING AND CURRENT ROW), 9) AS smooth FROM (SELECT CAST(ts AS DATE) AS day, count(*) AS events FROM events GROUP BY 1)",
    "single_query": f"{pairs()} SELECT k AS keyword_id, key AS rank_key, CAST(s AS INTEGER) AS dot FROM scored WHERE q = 3 ORDER BY key DESC, k LIMIT {N}",
    "second_page": "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20 OFFSET 20",
    "string_functions": "SELECT p_partkey, CAST(levenshtein(p_name, p_type) AS INTEGER) AS distance, sha256(p_name) AS sha, starts_with(p_type, 'STANDARD') AS standard, contains(p_name, 're') AS has, trim(p_brand) || '|' || lower(p_type) AS label, regexp_extract(p_brand, '(\\d+)', 1) AS number, CAST(1 AS INTEGER) AS sentences FROM part",
    "term_maps": f"""WITH t AS ({TURNS}), q AS (SELECT pair_id, w, count(*) AS n FROM (SELECT pair_id, unnest({words('q_text')}) AS w FROM t) GROUP BY ALL), k AS (SELECT pair_id, w, count(*) AS n FROM (SELECT pair_id, unnest({words('k_text')}) AS w FROM t) GROUP BY ALL)
SELECT t.pair_id, CAST((SELECT count(*) FROM q WHERE q.pair_id = t.pair_id) AS INTEGER) AS q_terms, CAST(coalesce((SELECT sum(least(q.n, k.n)) FROM q JOIN k USING (pair_id, w) WHERE q.pair_id = t.pair_id), 0) AS INTEGER) AS common, CAST(coalesce((SELECT n FROM q WHERE q.pair_id = t.pair_id AND w = 'the'), 0) AS INTEGER) AS the FROM t""",
    "json_props": "SELECT '{\"tens\":' || CAST(CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS VARCHAR) || '}' AS tens, 'STRUCT<k: BIGINT>' AS schema, count(*) AS events FROM events GROUP BY 1",
    "attribute_filters": f"{pairs()}, {', '.join(f'f_{k} AS (SELECT * FROM (SELECT q, key, row_number() OVER (PARTITION BY q ORDER BY key DESC, k) AS rn FROM scored JOIN part ON p_partkey = k WHERE {c}) WHERE rn <= 3)' for k, c in FILTERS.items())} " + " UNION ALL ".join(f"SELECT '{k}' AS kind, count(*) AS found, CAST(CAST(coalesce(sum(key), 0) AS HUGEINT) AS VARCHAR) AS keys FROM f_{k}" for k in FILTERS),
    "arrow_functions": f"WITH {planes()} SELECT vec_id, {SIGNS.format(s='s0')} AS plane0, {SIGNS.format(s='s1')} AS plane1 FROM p2",
    "grouped_functions": """WITH e AS (SELECT label, CAST(embedding[1] AS DOUBLE) AS a, embedding[2] > 0 AS pos, CAST(embedding[64] AS DOUBLE) AS z FROM embeddings)
SELECT x.label, round((sum(CASE WHEN pos THEN r END) - count_if(pos) * (count_if(pos) + 1) / 2.0) / (count_if(pos) * CAST(count_if(NOT pos) AS DOUBLE)), 9) AS area, round(sum(a), 6) AS first, round(sum(z), 6) AS last
FROM (SELECT label, a, z, pos, avg(n) OVER (PARTITION BY label, a) AS r FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY a) AS n FROM e)) x GROUP BY x.label""",
    "table_functions": f"""WITH {planes()}, b AS (SELECT 'plane 0' AS kind, s0 AS s FROM p2 UNION ALL SELECT 'plane 1', s1 FROM p2), g AS (SELECT substr(x, i, 3) AS t, i - 1 AS pos FROM (SELECT '#' || x || '#' AS x, unnest(range(1, length(x) + 1)) AS i FROM (SELECT unnest({words('p_name')}) AS x FROM part)))
SELECT kind, count(*) AS n, CAST(sum(list_sum({BITS.format(s='s')})) AS BIGINT) AS total FROM b GROUP BY kind UNION ALL SELECT 'trigram ' || t, count(*), CAST(sum(pos) AS BIGINT) FROM g GROUP BY t""",
    "query_metrics": f"WITH a AS ({EXACT}), b AS ({lane_top()}) SELECT a.query_id, count(b.query_id) AS hits, count(b.query_id) / {N}.0 AS recall FROM a LEFT JOIN b ON b.query_id = a.query_id AND b.keyword_id = a.keyword_id GROUP BY 1",
    "formats": "SELECT c_mktsegment, count(*) AS customers, round(sum(c_acctbal), 2) AS balance, format FROM customer, (VALUES ('csv'), ('json'), ('orc'), ('text')) t(format) GROUP BY ALL",
    "stored_results": lane_top(),
    "candidate_traffic": f"{pairs()} SELECT 'pairs' AS stage, count(*) AS rows FROM scored UNION ALL SELECT 'lanes', count(*) FROM (SELECT DISTINCT q, k // {LANE * WIDTH} * {WIDTH} + k % {WIDTH} FROM scored) UNION ALL SELECT 'merged', count(*) FROM ({TOP.format(source='scored', n=N)})",
    "vector_codes": f"WITH {ROWS}, qe AS ({hashed_sum('benchmark', 'item_id')}), {vector_planes('qa', 'qe')} SELECT vec_id AS item_id, {SIGNS.format(s='s0')} AS plane0, {SIGNS.format(s='s1')} AS plane1 FROM qa2",
    "sampled_floats": f"""WITH {FLOAT}, every AS (SELECT a.vec_id AS q, b.vec_id AS k, list_dot_product(list_transform(a.v, lambda x: x / sqrt(list_dot_product(a.v, a.v))), list_transform(b.v, lambda x: x / sqrt(list_dot_product(b.v, b.v)))) AS c FROM fl a, fl b WHERE CAST('0x' || substr(md5('0:' || CAST(b.vec_id AS VARCHAR)), 1, 7) AS BIGINT) % 1000 < 250)
SELECT q AS query_id, CAST(rn AS INTEGER) AS rank, k AS keyword_id, round(c, 9) AS score FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY c DESC, k) AS rn FROM every) WHERE rn <= 3""",
    # windows leave when the watermark, one hour behind the last event, has passed their end
    "stream_tumbling": f"SELECT * FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS \"end\", {RATES} FROM events GROUP BY 1, 2) WHERE {CLOSED}",
    "stream_sliding": f"SELECT * FROM (SELECT b AS start, b + INTERVAL 6 HOUR AS \"end\", {RATES} FROM (SELECT *, unnest([time_bucket(INTERVAL 3 HOUR, ts), time_bucket(INTERVAL 3 HOUR, ts) - INTERVAL 3 HOUR]) AS b FROM events) GROUP BY 1, 2) WHERE {CLOSED}",
    "stream_sessions": f"SELECT * FROM (SELECT min(ts) AS start, max(ts) + INTERVAL 2 HOUR AS \"end\", user_id, {RATES} FROM (SELECT *, sum(n) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS n FROM events)) GROUP BY user_id, s) WHERE {CLOSED}",
    "stream_late": f"SELECT true AS reported, count(*) AS kept FROM (SELECT *, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS \"end\" FROM events) WHERE ts >= '2024-01-10' AND event_type IN ('view', 'click') AND {CLOSED}",
    "stream_running_top": RUNNING,
    "stream_merged_top": RUNNING,
    "stream_upserts": f"WITH {planes()} SELECT vec_id, CASE WHEN vec_id % 10 = 0 THEN {SIGNS.format(s='list_transform(s0, lambda x: -x)')} ELSE {SIGNS.format(s='s0')} END AS plane0, CAST(CASE WHEN vec_id % 10 = 0 THEN 1 ELSE 0 END AS INTEGER) AS version FROM p2",
    "stream_pairs_bounded": "SELECT c.event_id AS click_id, v.event_id AS view_id FROM (SELECT *, json_extract_string(props, '$.k') AS item FROM events WHERE event_type = 'click') c JOIN (SELECT *, json_extract_string(props, '$.k') AS item FROM events WHERE event_type = 'view') v ON c.user_id = v.user_id AND c.item = v.item AND v.ts <= c.ts AND v.ts >= c.ts - INTERVAL 30 MINUTE",
}
