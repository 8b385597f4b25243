"""The registered queries of the paper's own methods, and their SQL.

Every query runs over its whole tables.  Vectors come from ``embeddings`` under
the Hadamard ladder, whose planes SQL can rebuild from ±1 lists alone; positions
are vec_id, which is dense, unless a query builds an index.
"""

from __future__ import annotations

import math
import time
import uuid
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import codes, text
from .functions.codes import CodeSpec
from .operators import baselines, cost, encoder, ladder, loss, match, metrics, missprob, relational, retrieve, samples, select, train
from .sources import codes_source, io

#: lanes at the size of these tables
N, LANE, WIDTH = 10, 8, 16
#: events are sparse here: a click counts for views up to so long before
WITHIN = "5 days"
SCALE = math.sqrt(2.0 / (math.pi * 64)) / 8.0


def vectors(spark: SparkSession, sf: str) -> DataFrame:
    return io.table(spark, sf, "embeddings")


def coded(spark: SparkSession, sf: str, depth: int = 2, weighted: bool = True) -> tuple[DataFrame, ladder.LadderParams]:
    params = ladder.init_hadamard(64, depth, weighted=weighted)
    return ladder.encode_vectors(vectors(spark, sf), params), params


def sides(spark: SparkSession, sf: str, u: int = 2, v: int = 1, weighted: bool = True):
    """Queries, keywords and specs of code(u, v): one encoding, fewer planes by column pruning.

    Planes of a weighted or unweighted ladder depend only on earlier planes.
    """
    all_codes, params = coded(spark, sf, max(u, v), weighted)
    qspec, kspec = params.spec(u), params.spec(v)
    queries = match.as_queries(all_codes.drop("norm_sq"), planes=u + 1).withColumn("q_norm_sq", codes.norm_sq_expr(qspec, "q_"))
    keywords = all_codes.select("keyword_id", F.col("keyword_id").alias("pos"), *kspec.columns()).withColumn("norm_sq", codes.norm_sq_expr(kspec))
    return queries, keywords, qspec, kspec


# encoding and similarity ---------------------------------------------------------


def ladder_planes(spark: SparkSession, sf: str) -> DataFrame:
    """Signs of all planes of every vector, and the squared norms from planes."""
    c, params = coded(spark, sf)

    def signs(p: int):
        return F.array_join(F.transform(codes.unpack_expr(F.col(f"p{p}_w0")), lambda x: F.when(x > 0, "+").otherwise("-")), "")

    return c.select(F.col("keyword_id").alias("vec_id"), *[signs(p).alias(f"plane{p}") for p in range(3)], codes.norm_sq_expr(params.spec(1)).alias("norm1"), F.col("norm_sq").alias("norm2"))


def code_dots(spark: SparkSession, sf: str, u: int = 2, v: int = 1, weighted: bool = True) -> DataFrame:
    """Per query over all keywords: sums and extremes of dot, naive dot, rank key and cosine."""
    q, k, qs, ks = sides(spark, sf, u, v, weighted)
    pairs = match.exhaustive(q, k, qs, ks).withColumn("naive", codes.dot_expr(qs, ks, order="naive"))
    return pairs.groupBy("query_id").agg(
        F.count("*").alias("pairs"),
        F.sum("dot").alias("dots"),
        F.sum(F.abs(F.col("dot") - F.col("naive"))).alias("order_gap"),
        F.max("rank_key").alias("best_key"),
        F.round(F.sum("cosine"), 6).alias("cosines"),
        F.round(F.max(F.when(F.col("query_id") != F.col("keyword_id"), F.col("cosine"))), 9).alias("nearest"),
    )


def sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    """The same dots by SQL-defined functions."""
    from .functions import sqlfuncs

    sqlfuncs.register(spark)
    q, k, _, _ = sides(spark, sf)
    q.createOrReplaceTempView("w_queries")
    k.createOrReplaceTempView("w_keywords")
    return spark.sql(
        "SELECT query_id, sum(code_dot_2_1(q_p0_w0, q_p1_w0, q_p2_w0, p0_w0, p1_w0)) AS dots, sum(pm_dot(q_p0_w0, p0_w0)) AS base_dots, "
        "round(sum(code_cosine_2_1(q_p0_w0, q_p1_w0, q_p2_w0, p0_w0, p1_w0)), 6) AS cosines FROM w_keywords CROSS JOIN w_queries GROUP BY query_id"
    )


def top(spark: SparkSession, sf: str, **options) -> DataFrame:
    q, k, qs, ks = sides(spark, sf)
    options = {"lane_size": LANE, "lanes_per_block": WIDTH, "exclude_self": True} | options
    return retrieve.top_n(q, k, qs, ks, N, **options).select("query_id", F.col("rank").cast("int").alias("rank"), F.col("pos").alias("keyword_id"), "rank_key")


def progressive(spark: SparkSession, sf: str) -> DataFrame:
    """Base planes first, the 50 best refined: per query the best refined keyword."""
    q, k, qs, ks = sides(spark, sf)
    out = match.progressive(q, k, qs, ks, keep=50)
    return out.groupBy("query_id").agg(F.count("*").alias("kept"), F.max("rank_key").alias("best_key"), F.min("base_rank").cast("int").alias("first_rank"), F.bool_or("certified").alias("certified"))


def above_threshold(spark: SparkSession, sf: str) -> DataFrame:
    q, k, qs, ks = sides(spark, sf)
    return retrieve.above(q, k, qs, ks, 0.4).where("query_id <> keyword_id").groupBy("query_id").agg(F.count("*").alias("keywords"), F.round(F.max("cosine"), 9).alias("best"))


def index_top_n(spark: SparkSession, sf: str) -> DataFrame:
    """A written index with scattered positions, read back, block backend, exact: equals exact_top_n."""
    from .plans.index import LadderIndex, LadderModel

    params = ladder.init_hadamard(64, 2)
    model = LadderModel(params)
    built = LadderIndex.build(vectors(spark, sf), model, lane_size=LANE, lanes_per_block=WIDTH, seed=1)
    path = f"{io.shared_dir(spark).rstrip('/')}/index-{uuid.uuid4().hex}"
    built.write(path, rows_per_part=512)
    index = LadderIndex.read(spark, path, model, LANE, WIDTH)
    queries = model.encode(vectors(spark, sf), "query")
    found = index.top_n(queries, N + 1, mode="exact", backend="block")
    # equal keys are in the order of scattered positions: rank them by id, without those of the least key
    above = found.withColumn("least", F.min("rank_key").over(Window.partitionBy("query_id"))).where("rank_key > least")
    w = Window.partitionBy("query_id").orderBy(F.desc("rank_key"), "keyword_id")
    return above.select("query_id", F.row_number().over(w).alias("rank"), "keyword_id", "rank_key")


def float_top(spark: SparkSession, sf: str) -> DataFrame:
    """Full-precision ten nearest of every vector (truth T1)."""
    e = vectors(spark, sf)
    return baselines.float_cosine(e, e, N, exclude_self=True).select("query_id", F.col("rank").cast("int").alias("rank"), "keyword_id", F.round("score", 9).alias("score"))


# accuracy ------------------------------------------------------------------------

#: fixed values: the depths of the published comparisons
DEPTHS = ((0, 0), (1, 1), (2, 1), (2, 2))


def truth(spark: SparkSession, sf: str) -> DataFrame:
    return io.checkpoint(float_top(spark, sf).select("query_id", "keyword_id"), "truth")


def code_aucs(spark: SparkSession, sf: str, true: DataFrame, depths, weighted: bool = True, extra: tuple = ()) -> DataFrame:
    """model, auc of each depth: a histogram of all pairs' cosines, and the true pairs scored one by one."""
    all_codes, params = coded(spark, sf, max(max(d) for d in depths), weighted)
    codes_ = io.checkpoint(all_codes.drop("norm_sq"), "codes")
    q = match.as_queries(codes_)
    specs = [(f"code({u},{v})", params.spec(u), params.spec(v)) for u, v in depths]
    return spec_aucs(q, codes_, true, specs)


def spec_aucs(q: DataFrame, k: DataFrame, true: DataFrame, specs: list) -> DataFrame:
    """model, auc of each (model, query spec, keyword spec)."""
    pairs = match.checked_broadcast(true).join(k, "keyword_id").join(q, "query_id").where("query_id <> keyword_id")
    scores = [F.struct(F.lit(name).alias("model"), codes.cosine_expr(codes.dot_expr(qs, ks).cast("long"), codes.norm_sq_expr(qs, "q_").cast("long"), codes.norm_sq_expr(ks).cast("long")).alias("score")) for name, qs, ks in specs]
    qcols, kcols = max((q_.columns("q_") for _, q_, _ in specs), key=len), max((k_.columns() for _, _, k_ in specs), key=len)
    return match.pair_areas(q.select("query_id", *qcols), k.select("keyword_id", *kcols), pairs.select(F.inline(F.array(*scores))), [name for name, _, _ in specs], *match.code_tiles([x[1:] for x in specs]), wave_rows=1 << 16)


def bits_table(spark: SparkSession, sf: str) -> DataFrame:
    """AUC of each depth against float neighbours."""
    return code_aucs(spark, sf, truth(spark, sf), DEPTHS).select("model", F.round("auc", 9).alias("auc"))


def turned(e: DataFrame) -> DataFrame:
    """Vectors in the Hadamard ladder's own dimensions, one product for a batch: query_id, f."""
    h = np.array([[1.0 - 2.0 * ((i & j).bit_count() % 2) for j in range(64)] for i in range(64)])

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                f = ladder.matrix(batch.column(1), 64) @ h.T
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(f), pa.list_(pa.float64()))], ["query_id", "f"])

    return e.select(F.col("vec_id").alias("query_id"), F.col("embedding").cast("array<double>").alias("f")).mapInArrow(run, "query_id long, f array<double>")


def accuracy_table(spark: SparkSession, sf: str) -> DataFrame:
    """AUC and lift of the five models without training, against float neighbours (trained: ``trained_accuracy``)."""
    e, true = vectors(spark, sf), truth(spark, sf)
    params = ladder.init_hadamard(64, 1)
    spec, kept = params.spec(1), baselines.usable(e, "vec_id", "embedding", "keyword_id")
    k1 = io.checkpoint(ladder.encode_vectors(e, params).select("keyword_id", *spec.columns()), "hybrid")
    f = io.checkpoint(turned(kept.select(F.col("keyword_id").alias("vec_id"), F.col("v").alias("embedding"))), "turned")

    def near(q: DataFrame, k: DataFrame, name: str) -> DataFrame:
        """Scores of the true pairs between vectors a and b."""
        def dot(x, y):
            return F.aggregate(F.zip_with(x, y, lambda i, j: i * j), F.lit(0.0), lambda t, i: t + i)

        norm = F.sqrt(dot("a", "a")) * F.sqrt(dot("b", "b"))
        rows = match.checked_broadcast(true).join(k, "keyword_id").join(q, "query_id").where("query_id <> keyword_id")
        return rows.select(F.lit(name).alias("model"), F.round(dot("a", "b") / F.when(norm > 0, norm), match.PLACES).alias("score"))

    own = kept.select(F.col("keyword_id").alias("query_id"), F.col("v").alias("a"))
    flo = match.pair_areas(own, kept, near(own, kept.withColumnRenamed("v", "b"), "float64d"), ["float64d"], *match.vector_tiles(lambda batch: ladder.matrix(batch.column(1))))
    dense = F.zip_with(codes.unpack_expr(F.col("p0_w0")), codes.unpack_expr(F.col("p1_w0")), lambda x, y: x + 0.5 * y)
    hyb = match.pair_areas(f, k1, near(f.withColumnRenamed("f", "a"), k1.select("keyword_id", dense.alias("b")), "hybrid"), ["hybrid"], *match.vector_tiles(lambda batch: match.code_matrix(batch, 1, spec, codes.unpack)))
    real = flo.unionByName(hyb)
    sign = io.checkpoint(ladder.encode_vectors(e, baselines.sign_code(128)).drop("norm_sq"), "signs")
    wide = spec_aucs(match.as_queries(sign), sign, true, [("sign128", CodeSpec(128, 1), CodeSpec(128, 1))])
    auc = io.checkpoint(real.unionByName(wide).unionByName(code_aucs(spark, sf, true, ((0, 0), (2, 1)))), "auc")
    return with_lift(auc, "sign128", "float64d").select("model", F.round("auc", 6).alias("auc"), F.round("auc_lift", 2).alias("auc_lift"))


def with_lift(auc: DataFrame, low: str, high: str, column: str = "auc") -> DataFrame:
    """Adds the lift of each model's area between those of two reference models."""
    ref = auc.agg(F.max(F.when(F.col("model") == high, F.col(column))).alias("_high"), F.max(F.when(F.col("model") == low, F.col(column))).alias("_low"))
    return auc.crossJoin(F.broadcast(ref)).withColumn(f"{column}_lift", F.try_divide((F.col(column) - F.col("_low")) * 100.0, F.col("_high") - F.col("_low"))).drop("_high", "_low")


def weights_table(spark: SparkSession, sf: str) -> DataFrame:
    """AUC with and without residual weights: planes beyond the second are encoded anew."""
    true = truth(spark, sf)
    on, off = (code_aucs(spark, sf, true, DEPTHS[1:], weighted) for weighted in (True, False))
    return on.withColumnRenamed("auc", "auc_weighted").join(off.withColumnRenamed("auc", "auc_plain"), "model").select("model", F.round("auc_weighted", 9).alias("auc_weighted"), F.round("auc_plain", 9).alias("auc_plain"))


def neighbour_groups(spark: SparkSession, sf: str) -> DataFrame:
    """group_id, keyword_id, is_pos: the nearest float neighbour and the next ten ids round the table."""
    e = vectors(spark, sf).select("vec_id")
    count = e.count()
    best = float_top(spark, sf).where("rank = 1").select(F.col("query_id").alias("group_id"), "keyword_id", F.lit(True).alias("is_pos"))
    others = e.select(F.col("vec_id").alias("group_id"), F.explode(F.sequence(F.lit(1), F.lit(10))).alias("k")).select("group_id", F.pmod(F.col("group_id") + F.col("k"), F.lit(count)).alias("keyword_id"), F.lit(False).alias("is_pos"))
    return best.unionByName(others.join(best.select("group_id", "keyword_id"), ["group_id", "keyword_id"], "left_anti"))


def neighbour_scores(spark: SparkSession, sf: str) -> DataFrame:
    q, k, qs, ks = sides(spark, sf)
    g = neighbour_groups(spark, sf)
    return match.scored(g.join(k, "keyword_id").join(q, g["group_id"] == q["query_id"]), qs, ks).select("group_id", "is_pos", "cosine")


def log_loss_table(spark: SparkSession, sf: str) -> DataFrame:
    """Log loss of code(2,1) over gamma, per group and per sample, in one pass."""
    found = train.tune_gamma(neighbour_scores(spark, sf), (1.0, 5.0, 10.0))
    return found.select("gamma", F.round("log_loss", 9).alias("per_group"), F.round("per_sample", 9).alias("per_sample"))


def gamma_search(spark: SparkSession, sf: str) -> DataFrame:
    return train.tune_gamma(neighbour_scores(spark, sf)).select("gamma", F.round("log_loss", 9).alias("log_loss"))


def objective_table(spark: SparkSession, sf: str) -> DataFrame:
    """The training objective and the mean log loss of neighbour groups, which are the same but for the count."""
    scored = neighbour_scores(spark, sf)
    total, mean = loss.objective(scored, 10.0), metrics.log_loss(scored, 10.0)
    return total.crossJoin(F.broadcast(mean)).select(F.round("objective", 6).alias("objective"), F.round("log_loss", 9).alias("log_loss"))


def recall_table(spark: SparkSession, sf: str) -> DataFrame:
    """Measured recall and misses of lane selection beside the exact expectation: one block pass for each lane shape."""
    q, k, qs, ks = sides(spark, sf)
    q, k = io.checkpoint(q, "queries"), io.checkpoint(k, "keywords")
    exact = io.checkpoint(retrieve.top_n(q, k, qs, ks, N, mode="exact", backend="block", exclude_self=True).select("query_id", "pos"), "exact")
    C, out = k.count(), None
    for lane in (4, 8, 16):
        # the 2 N best of queues of two hold the N best lanes, so one pass serves both lengths
        queues = io.checkpoint(retrieve.block_queues(q, k, qs, ks, 2 * N, lane, WIDTH, 2, exclude_self=True), "queues")
        for r in (1, 2):
            got = select.merge_select(select.lane_cut(queues, r), N)
            row = metrics.mean_recall(got, exact, N).select(F.lit(lane).alias("lane_size"), F.lit(r).alias("r"), "queries", F.round("recall", 9).alias("recall"), F.round("mean_missed", 9).alias("mean_missed"))
            row = row.withColumn("theory", F.lit(round(missprob.expected_missed(C - C % lane, N, lane, r), 6)))
            out = row if out is None else out.unionByName(row)
    return out


def md5_codes(rows: DataFrame, keys: list[str], key: str, planes: int) -> DataFrame:
    """``key`` and planes p*_w0 from MD5 digests of ``keys`` and the plane's number."""
    def word(p: int):
        return encoder.digest_bits(F.md5(F.concat_ws(":", *[F.col(c).cast("string") for c in keys], F.lit(str(p)))))

    return rows.select(F.col(key), *[word(p).alias(f"p{p}_w0") for p in range(planes)])


def generated_recall(spark: SparkSession, sf: str) -> DataFrame:
    """Recall at N = 100 with lanes of 64: generated codes of suppliers against those of all line items."""
    qs, ks = CodeSpec(64, 3), CodeSpec(64, 2)
    q = match.as_queries(md5_codes(io.table(spark, sf, "supplier"), ["s_suppkey"], "s_suppkey", 3), "s_suppkey")
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    # one number for each digest: equal rows follow one another, so numbers do not depend on their order
    lines = io.table(spark, sf, "lineitem").select(*keys).withColumn("digest", F.md5(F.concat_ws(":", *[F.col(c).cast("string") for c in keys])))
    numbered = io.dense_pos(lines, "digest")
    k = md5_codes(numbered, keys, "pos", 2).withColumn("norm_sq", codes.norm_sq_expr(ks))
    # parts of whole blocks: a lane in two partitions would have a queue in each
    path = f"{io.shared_dir(spark).rstrip('/')}/generated-{uuid.uuid4().hex}"
    io.write_index(k, ks, path, 1 << 14, 64, 16)
    k, _ = io.read_index(spark, path)
    exact = retrieve.top_n(q, k, qs, ks, 100, mode="exact", backend="block")
    got = retrieve.top_n(q, k, qs, ks, 100, 64, 16, backend="block")
    C = k.count()
    theory = missprob.expected_missed(C - C % 64, 100, 64) if C >= 6400 else None
    return metrics.mean_recall(got, exact, 100).select(F.lit(C).alias("keywords"), "queries", F.round("recall", 9).alias("recall"), F.lit(None if theory is None else round(1 - theory / 100, 4)).cast("double").alias("expected"))


def miss_table(spark: SparkSession, sf: str) -> DataFrame:
    """Chances to miss so many of 100 relevant line items in lanes of 16."""
    C = io.table(spark, sf, "lineitem").agg(F.count("l_orderkey")).first()[0]
    return missprob.table(spark, C - C % 16, 100, 16, 4).select("l", F.round("p", 9).alias("p"), F.round("p_cum", 9).alias("p_cum"))


def miss_simulated(spark: SparkSession, sf: str) -> DataFrame:
    """Monte Carlo with a trial for each customer: 16 relevant among 4096 in lanes of 16."""
    return missprob.simulate(spark, 4096, 16, 16, 1, io.table(spark, sf, "customer").select("c_custkey"), 7)


def memory_table(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes of the codes of all vectors and of the vectors as floats, counted, beside the model."""
    c, params = coded(spark, sf)
    plane = [F.sum(sum(F.octet_length(F.unhex(F.lpad(F.hex(w), 16, "0"))) for w in params.spec(p).columns())).cast("long").alias(f"b{p}") for p in range(3)]
    one = baselines.usable(vectors(spark, sf), "vec_id", "embedding", "keyword_id").agg(F.sum(4 * F.size("v")).alias("float_bytes"))
    both = c.agg(F.count("*").alias("keywords"), *plane).crossJoin(one)
    rows = F.inline(F.array(*[F.struct(F.lit(p + 1).alias("planes"), F.col("keywords"), F.lit(cost.memory_model(64, p + 1)["bytes_per_keyword"]).alias("bytes_per_keyword"), F.coalesce(f"b{p}", F.lit(0)).alias("code_bytes"), F.coalesce("float_bytes", F.lit(0)).alias("float_bytes")) for p in range(3)]))
    return both.select(rows)


def cost_table(spark: SparkSession, sf: str) -> DataFrame:
    """Operations of the exhaustive match of all vectors with each other, by depth."""
    pairs = coded(spark, sf, 0)[0].agg((F.count("*") * F.count("*")).alias("pairs"))
    rows = [F.struct(*[F.lit(x).alias(c) for x, c in ((u, "u"), (v, "v"))], *[(F.col("pairs") * x).alias(c) for x, c in ((cost.popcounts(u, v), "popcounts"), (codes.shift_count(u, v), "horner_shifts"), (codes.shift_count(u, v, "naive"), "naive_shifts"))]) for u, v in DEPTHS]
    return pairs.select(F.inline(F.array(*rows)))


def cardinality_table(spark: SparkSession, sf: str) -> DataFrame:
    """Values that a dimension takes in the codes of all vectors, with and without residual weights."""
    def counted(weighted: bool, name: str) -> DataFrame:
        c, _ = coded(spark, sf, 3, weighted)
        signs = c.select(F.explode(F.arrays_zip(*[codes.unpack_expr(F.col(f"p{t}_w0")).alias(f"s{t}") for t in range(4)])).alias("s")).distinct()
        value = [sum(F.col(f"s.s{t}") * (2 ** (3 - t) if weighted else 1) for t in range(p)) for p in range(1, 5)]
        return signs.select(F.inline(F.array(*[F.struct(F.lit(p + 1).alias("planes"), x.alias("x")) for p, x in enumerate(value)]))).groupBy("planes").agg(F.count_distinct("x").cast("int").alias(name))

    return counted(True, "weighted_values").join(counted(False, "plain_values"), "planes")


def lane_geometry(spark: SparkSession, sf: str) -> DataFrame:
    """Keywords per lane over all line items' positions: each position is in one lane."""
    n = io.table(spark, sf, "lineitem").count()
    pos = spark.range(n).select(F.col("id").alias("pos"))
    return pos.groupBy(select.lane_of(F.col("pos"), LANE, WIDTH).alias("lane")).agg(F.count("*").alias("keywords"), F.min("pos").alias("first"), F.max("pos").alias("last"))


def plane_stats(spark: SparkSession, sf: str) -> DataFrame:
    c, params = coded(spark, sf)
    return metrics.plane_balance(c, params.spec().columns()).select("word", F.round("share", 9).alias("share"))


# generated codes -----------------------------------------------------------------


def generated_codes(spark: SparkSession, sf: str) -> DataFrame:
    """Best keyword of every embedding's code among generated codes of all line items (block backend)."""
    all_codes, params = coded(spark, sf)
    spec_k = CodeSpec(64, 2, True, params.fingerprint)
    made = io.generated_codes(spark, io.table(spark, sf, "lineitem"), 2)
    index = io.dense_pos(made, "keyword_id")
    q = match.as_queries(all_codes)
    return retrieve.top_n(q, index, params.spec(2), spec_k, 1, backend="block", lane_size=256, lanes_per_block=4).select("query_id", "rank", "pos", "rank_key")


def codes_source_table(spark: SparkSession, sf: str) -> DataFrame:
    """Rows of the generated source, per plane: set bits near one half."""
    codes_source.register(spark)
    n = io.table(spark, sf, "orders").count()
    df = spark.read.format("ladder_codes").option("rows", n).option("planes", 2).option("seed", 5).load()
    return df.agg(F.count("*").alias("rows"), F.count_distinct("p0_w0").alias("distinct"), F.round(F.avg(F.bit_count("p0_w0")) / 64.0, 2).alias("share"))


def latency_table(spark: SparkSession, sf: str) -> DataFrame:
    """Milliseconds per query of two codes and of the float model over the same keywords: hashed vectors of all line items."""
    e, keys = vectors(spark, sf), ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    hashed = F.array(*[(F.xxhash64(*keys, F.lit(i)) / F.lit(2.0**63)).alias("x") for i in range(64)])
    made = io.dense_pos(io.table(spark, sf, "lineitem").select(*keys).withColumn("id", F.xxhash64(*keys)), "id")
    made = io.checkpoint(made.select(F.col("pos").alias("vec_id"), hashed.alias("embedding")), "hashed")
    params = ladder.init_hadamard(64, 2)
    queries = ladder.encode_vectors(e, params)
    keywords = io.checkpoint(ladder.encode_vectors(made, params, depth=1).withColumn("pos", F.col("keyword_id")), "keywords")
    total, n, rows = made.count(), e.count(), []

    def code(u: int):
        q = match.as_queries(queries.drop("norm_sq"), planes=u + 1)
        return lambda: retrieve.top_n(q, keywords, params.spec(u), params.spec(1), N, backend="block", lane_size=256, lanes_per_block=4)

    for name, run in (("code(1,1)", code(1)), ("code(2,1)", code(2)), ("float64d", lambda: baselines.float_cosine(e, made, N))):
        t = metrics.latency(run, n, 3)
        rows.append((name, total, t["cold_ms"], t["mean_ms"], t["p95_ms"]))
    base = rows[1][3]
    return spark.createDataFrame([(*r, r[3] / base) for r in rows], "model string, keywords long, cold_ms double, mean_ms double, p95_ms double, ratio double")


# samples and text ----------------------------------------------------------------


def pairs_clicks(spark: SparkSession, sf: str) -> DataFrame:
    return samples.clicked_pairs(io.table(spark, sf, "events")).select("query_id", "keyword_id")


def pairs_turns(spark: SparkSession, sf: str) -> DataFrame:
    return samples.turn_pairs(io.table(spark, sf, "conversations")).select("pair_id", "q_text", "k_text")


def pairs_lines(spark: SparkSession, sf: str) -> DataFrame:
    return samples.line_pairs(io.table(spark, sf, "documents")).select("pair_id", "q_text", F.length("k_text").alias("k_chars"))


def pairs_pages(spark: SparkSession, sf: str) -> DataFrame:
    return samples.page_pairs(io.table(spark, sf, "pages")).select("pair_id", "q_text", F.length("k_text").alias("k_chars"))


def training_samples(spark: SparkSession, sf: str) -> DataFrame:
    """Cross-sampled groups of clicks: per user the positives and negatives."""
    s = samples.cross_sample(samples.clicked_pairs(io.table(spark, sf, "events")), 10)
    return s.groupBy("query_id").agg(F.count_distinct("group_id").alias("groups"), F.count_if("is_pos").alias("positives"), F.count_if(~F.col("is_pos")).alias("negatives"))


def time_split(spark: SparkSession, sf: str) -> DataFrame:
    clicks = io.table(spark, sf, "events").where("event_type = 'click'")
    return samples.split_by_time(clicks, "2024-01-24 00:00:00").groupBy("fold").agg(F.count("*").alias("clicks"))


def trigram_vocab(spark: SparkSession, sf: str) -> DataFrame:
    return text.build_vocab(io.table(spark, sf, "documents"))


def window_counts(spark: SparkSession, sf: str) -> DataFrame:
    """Per conversation turn: windows and trigrams in them."""
    c = io.table(spark, sf, "conversations")
    w = text.word_windows(F.col("text"), 3, 4096)
    counted = c.select("conv_id", "turn", w.alias("w"))
    total = F.aggregate(F.flatten(F.col("w")), F.lit(0.0), lambda s, x: s + x["cnt"].cast("double"))
    return counted.select("conv_id", "turn", F.size("w").alias("windows"), total.alias("trigrams"))


def encoded_turns(spark: SparkSession, sf: str) -> DataFrame:
    """Codes of all conversation turns under an untrained text encoder."""
    c = io.table(spark, sf, "conversations").withColumn("id", samples.turn_id(F.col("conv_id"), F.col("turn")))
    return encoder.encode_texts(c, encoder.init_tower(), "query", "id").select("id", "p0_w0", "p1_w0", "p2_w0", "norm_sq")


#: unrelated documents that each item is judged with
BAD = 20


def judged(spark: SparkSession, sf: str) -> DataFrame:
    """query_id, keyword_id, grade, is_pos: grades of (item, document) by the share of the item's
    word triples in the document; ``bad`` are documents without any, twenty drawn for each item."""
    items, docs = io.table(spark, sf, "benchmark"), io.table(spark, sf, "documents")

    def triples(df: DataFrame, key: str) -> DataFrame:
        w = text.words(F.col("text"))
        grams = F.transform(F.sequence(F.lit(1), F.size("w") - 2), lambda i: F.concat_ws(" ", F.slice("w", i, 3)))
        return df.select(key, w.alias("w")).where(F.size("w") >= 3).select(key, F.explode(grams).alias("g"))

    a = io.checkpoint(triples(items, "item_id").distinct(), "triples")
    size = a.groupBy("item_id").agg(F.count("*").alias("size"))
    # documents' triples meet the items' before anything is shuffled; repeats go afterwards, among hits only
    hit = triples(docs, "doc_id").join(match.checked_broadcast(a, 1_000_000), "g").groupBy("item_id", "doc_id").agg(F.count_distinct("g").alias("hits"))
    c = F.col("hits") / F.col("size")
    graded = hit.join(size, "item_id").select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("keyword_id"), F.when(c >= 0.3, "excellent").when(c >= 0.05, "good").otherwise("fair").alias("grade"))
    graded = io.checkpoint(graded, "graded")
    n = docs.count()
    drawn = items.select(F.col("item_id").alias("query_id"), F.explode(F.sequence(F.lit(1), F.lit(BAD))).alias("j")).select("query_id", F.pmod(F.col("query_id") * 7919 + F.col("j") * 104729, F.lit(max(n, 1))).alias("keyword_id")).distinct()
    bad = drawn.join(docs.select(F.col("doc_id").alias("keyword_id")).distinct(), "keyword_id", "left_semi")
    bad = relational.minus_pairs(bad, graded.select("query_id", "keyword_id"), ["query_id", "keyword_id"]).select("query_id", "keyword_id", F.lit("bad").alias("grade"))
    return graded.unionByName(bad).withColumn("is_pos", F.col("grade") != "bad")


def judge_agreement(spark: SparkSession, sf: str) -> DataFrame:
    """The second judge: judged pairs of each grade whose document ``labels`` calls good, bad and toxic."""
    labels = io.table(spark, sf, "labels").select(F.col("doc_id").alias("keyword_id"), "quality", "toxic")
    rows = judged(spark, sf).join(labels, "keyword_id", "left")
    return rows.groupBy("grade").agg(F.count("*").alias("pairs"), F.count("quality").alias("labelled"), F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("toxic") == 1).alias("toxic"))


def lexical(spark: SparkSession, sf: str, which: str) -> DataFrame:
    """Lexical ranking of all documents for every benchmark item: five best."""
    return lexical_of(*items_and_documents(spark, sf), which)


def items_and_documents(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """query_id, text and keyword_id, text."""
    items, docs = io.table(spark, sf, "benchmark"), io.table(spark, sf, "documents")
    return items.select(F.col("item_id").alias("query_id"), "text"), docs.select(F.col("doc_id").alias("keyword_id"), "text")


def text_top(spark: SparkSession, sf: str, n: int = 5) -> DataFrame:
    """The whole way from text: word-sum vectors, ladder codes, a written index, lanes, the best ``n`` documents of each item."""
    from .plans.index import LadderIndex, LadderModel

    q, k = items_and_documents(spark, sf)
    params = ladder.init_hadamard(64, 2)
    model = LadderModel(params)
    built = model.encode(encoder.hashed_sum(k, "keyword_id")).withColumn("pos", F.col("keyword_id"))
    path = f"{io.shared_dir(spark).rstrip('/')}/index-{uuid.uuid4().hex}"
    io.write_index(built, model.kspec, path, 4096, LANE, WIDTH)
    index = LadderIndex.read(spark, path, model, LANE, WIDTH)
    return index.top_n(model.encode(encoder.hashed_sum(q, "query_id"), "query"), n, backend="block").withColumn("rank", F.col("rank").cast("int"))


def production(spark: SparkSession, sf: str) -> dict[str, DataFrame]:
    """The two settings compared with: BM25 over as many keywords, and over the hash sample that fits the codes' bytes."""
    q, k = items_and_documents(spark, sf)
    listed = k.select("keyword_id", F.size(F.array_distinct(text.words(F.col("text")))).alias("terms"))
    documents, postings = listed.agg(F.count("*"), F.sum("terms")).first()
    # a code has two planes and a norm (20 bytes), a posting a term's number, a document's and a count (12)
    share = 20 * documents * 1000 // max(12 * (postings or 0), 1)
    some = baselines.hash_sample(k, "keyword_id", int(share))
    return {"equal keywords": lexical_of(q, k, "bm25"), "equal memory": lexical_of(q, some, "bm25")}


def lexical_of(q: DataFrame, k: DataFrame, which: str, n: int = 5) -> DataFrame:
    out = {"bm25": baselines.bm25, "tfidf": baselines.tfidf_cosine, "bim": baselines.bim}[which](q, k).withColumn("score", F.round("score", 6))
    return baselines.ranked(out, n).select("query_id", F.col("rank").cast("int").alias("rank"), "keyword_id", "score")


def compared(ours: DataFrame, theirs: dict[str, DataFrame], grades: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Grade counts with their change, and the overlap of good and excellent pairs, for each baseline."""
    known = io.checkpoint(grades.where("is_pos").select("query_id", "keyword_id", "grade"), "grades")

    def graded(df: DataFrame) -> DataFrame:
        return io.checkpoint(df.select("query_id", "keyword_id").join(known, ["query_id", "keyword_id"], "left").withColumn("grade", F.coalesce("grade", F.lit("bad"))), "graded")

    mine, counts, common = graded(ours), None, None
    for name, df in theirs.items():
        other = graded(df)
        one = metrics.grade_change(mine, other).select(F.lit(name).alias("baseline"), "grade", "ours", "theirs", F.round("change", 6).alias("change"))
        two = metrics.overlap(*(x.where("grade in ('good', 'excellent')") for x in (mine, other))).select(F.lit(name).alias("baseline"), F.coalesce("common", F.lit(0)).cast("long").alias("common"), F.round("of_ours", 9).alias("of_ours"), F.round("of_theirs", 9).alias("of_theirs"), F.round("jaccard", 9).alias("jaccard"))
        counts = one if counts is None else counts.unionByName(one)
        common = two if common is None else common.unionByName(two)
    return counts, common


def quality_table(spark: SparkSession, sf: str) -> DataFrame:
    """Grades of the five best by our codes against those of both production settings, with changes."""
    return compared(text_top(spark, sf), production(spark, sf), judged(spark, sf))[0]


def overlap_table(spark: SparkSession, sf: str) -> DataFrame:
    """Common good and excellent pairs of our codes and of both production settings."""
    return compared(text_top(spark, sf), production(spark, sf), judged(spark, sf))[1]


def latent(spark: SparkSession, sf: str, which: str) -> DataFrame:
    q = io.table(spark, sf, "benchmark").select(F.col("item_id").alias("query_id"), "text")
    k = io.table(spark, sf, "documents").select(F.col("doc_id").alias("keyword_id"), "text")
    return {"lsa": baselines.lsa, "lda": baselines.lda, "word_sum": baselines.word_sum}[which](q, k, N=5)


def vector_baseline(spark: SparkSession, sf: str, which: str) -> DataFrame:
    e = vectors(spark, sf)
    return {"lsh": baselines.lsh, "pq": baselines.product_quantizer}[which](e, e, N)


# relational surroundings ----------------------------------------------------------


def attributed_clicks(spark: SparkSession, sf: str) -> DataFrame:
    e = io.table(spark, sf, "events")
    found = samples.attribute(e.where("event_type = 'view'"), e.where("event_type = 'click'"), WITHIN)
    return found.groupBy("click_id").agg(F.count("*").alias("views"), F.max("view_id").alias("last_view"))


def asof_views(spark: SparkSession, sf: str) -> DataFrame:
    e = io.table(spark, sf, "events")
    return samples.asof(e.where("event_type = 'click'"), e.where("event_type = 'view'"))


def rolling_ctr(spark: SparkSession, sf: str) -> DataFrame:
    return relational.rolling_rate(io.table(spark, sf, "events")).withColumn("ctr", F.round("ctr", 9))


def clicks_cube(spark: SparkSession, sf: str) -> DataFrame:
    """Clicks by market segment and nation, with all subtotals."""
    clicks = io.table(spark, sf, "events").where("event_type = 'click'").select((F.col("user_id")).alias("c_custkey"))
    c = io.table(spark, sf, "customer").select("c_custkey", "c_mktsegment", "c_nationkey")
    n = io.table(spark, sf, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name")
    rows = relational.attach(clicks.join(c, "c_custkey"), n, "c_nationkey")
    return rows.cube("c_mktsegment", "n_name").agg(F.count("*").alias("clicks"))


def star_top(spark: SparkSession, sf: str) -> DataFrame:
    """Nearest keywords as parts: revenue of each query's ten nearest parts by brand."""
    winners = top(spark, sf, mode="exact")
    parts = io.table(spark, sf, "part").select((F.col("p_partkey")).alias("keyword_id"), "p_brand")
    revenue = io.table(spark, sf, "lineitem").groupBy(F.col("l_partkey").alias("keyword_id")).agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"))
    return winners.join(parts, "keyword_id").join(revenue, "keyword_id", "left").groupBy("p_brand").agg(F.count("*").alias("winners"), F.round(F.sum(F.coalesce("revenue", F.lit(0.0))), 2).alias("revenue"))


def set_operations(spark: SparkSession, sf: str) -> DataFrame:
    """Kept and lost keywords of lane selection by intersect and except."""
    exact, lane = top(spark, sf, mode="exact").select("query_id", "keyword_id"), top(spark, sf).select("query_id", "keyword_id")
    exact, lane = io.checkpoint(exact, "exact"), io.checkpoint(lane, "lane")
    parts = exact.intersect(lane).withColumn("kind", F.lit("kept")).unionByName(exact.exceptAll(lane).withColumn("kind", F.lit("lost"))).unionByName(lane.exceptAll(exact).withColumn("kind", F.lit("instead")))
    return parts.groupBy("kind").agg(F.count("*").alias("pairs"))


def grade_pivot(spark: SparkSession, sf: str) -> DataFrame:
    return judged(spark, sf).where("is_pos").groupBy("query_id").pivot("grade", ["fair", "good", "excellent"]).agg(F.count(F.lit(1))).na.fill(0, ["fair", "good", "excellent"])


def event_profile(spark: SparkSession, sf: str) -> DataFrame:
    e = io.table(spark, sf, "events")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users"), F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.stddev_samp("value"), 6).alias("spread"))


def user_windows(spark: SparkSession, sf: str) -> DataFrame:
    """Ranks, neighbours and running counts of each user's events."""
    e = io.table(spark, sf, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select("event_id", F.row_number().over(w).alias("rn"), F.dense_rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("dr"), F.lag("event_id").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.ntile(4).over(w).alias("quarter"), F.sum(F.when(F.col("event_type") == "click", 1).otherwise(0)).over(w.rowsBetween(-6, 0)).alias("recent"))


def lateral_top(spark: SparkSession, sf: str) -> DataFrame:
    io.table(spark, sf, "events").createOrReplaceTempView("w_events")
    return relational.per_query_top(spark, "w_events", "user_id", "x.value DESC, x.event_id", 2).select("user_id", "event_id")


# streams ----------------------------------------------------------------------------


def _stream_dirs(spark: SparkSession) -> tuple[str, str]:
    base = f"{io.shared_dir(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    return f"{base}/out", f"{base}/checkpoint"


def append_file(df: DataFrame, path: str) -> None:
    """One more write to ``path``; waits until files of the next write must be newer (the stream reads by time of change)."""
    df.write.mode("append").parquet(path)
    time.sleep(1.1)


def _event_files(spark: SparkSession, sf: str, files: int = 4) -> str:
    """The event table as a few files in time order, written one after the other: the stream's input."""
    path = f"{io.shared_dir(spark).rstrip('/')}/events-{uuid.uuid4().hex}"
    e = io.table(spark, sf, "events")
    cuts = e.select(F.percentile_approx("ts", [i / files for i in range(1, files)])).first()[0] or []
    edges = [None, *sorted(set(cuts)), None]
    for lo, hi in zip(edges[:-1], edges[1:], strict=True):
        part = e if lo is None else e.where(F.col("ts") >= F.lit(lo))
        append_file((part if hi is None else part.where(F.col("ts") < F.lit(hi))).coalesce(1).sortWithinPartitions("ts"), path)
    return path


def _streamed(spark: SparkSession, df: DataFrame, mode: str = "append") -> DataFrame:
    out, cp = _stream_dirs(spark)
    q = df.writeStream.outputMode(mode).option("checkpointLocation", cp).format("parquet").option("path", out).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def stream_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Clicks with their views by a stream-stream join; equals the batch join."""
    from .streaming import stream

    events = stream.events_stream(spark, _event_files(spark, sf))
    found = _streamed(spark, stream.stream_pairs(events, WITHIN, lateness="1 hour"))
    return found.groupBy("click_id").agg(F.count("*").alias("views"), F.max("view_id").alias("last_view"))


def stream_unique(spark: SparkSession, sf: str) -> DataFrame:
    from .streaming import stream

    events = stream.events_stream(spark, _event_files(spark, sf))
    return _streamed(spark, stream.stream_unique_pairs(events, "60 days")).select("query_id", "keyword_id")


def stream_answers(spark: SparkSession, sf: str) -> DataFrame:
    """Every event asks for the vector of its user: ten nearest, answered per micro-batch."""
    from .plans.index import LadderIndex, LadderModel
    from .streaming import stream

    e = vectors(spark, sf)
    n = e.count()
    model = LadderModel(ladder.init_hadamard(64, 2))
    keywords = model.encode(e).withColumn("pos", F.col("keyword_id"))
    lookup = io.checkpoint(model.encode(e, "query"), "lookup")
    index = LadderIndex(io.checkpoint(keywords, "keywords"), model, LANE, WIDTH)
    asked = stream.events_stream(spark, _event_files(spark, sf)).select(F.pmod("user_id", F.lit(n)).alias("query_id"))
    out, cp = _stream_dirs(spark)
    stream.stream_top_n(asked, index, model, N, out, cp, lookup).awaitTermination()
    return spark.read.parquet(out).select("query_id", "rank", "keyword_id", "rank_key").distinct()


QUERIES = {
    "lane_top_n": top,
    "lane_top_n_r2": partial(top, r=2),
    "lane_top_n_tree": partial(top, fan_in=4),
    "lane_top_n_block": partial(top, backend="block"),
    "exact_top_n": partial(top, mode="exact"),
    "exact_top_n_block": partial(top, mode="exact", backend="block"),
    "radix_top_n": partial(top, mode="radix"),
    "index_top_n": index_top_n,
    "float_top_n": float_top,
    "ladder_planes": ladder_planes,
    "code_dots_2_1": code_dots,
    "code_dots_0_0": partial(code_dots, u=0, v=0),
    "code_dots_1_1": partial(code_dots, u=1, v=1),
    "code_dots_2_2": partial(code_dots, u=2, v=2),
    "code_dots_plain_2_1": partial(code_dots, weighted=False),
    "sql_functions": sql_functions,
    "progressive": progressive,
    "above_threshold": above_threshold,
    "bits_table": bits_table,
    "accuracy_table": accuracy_table,
    "weights_table": weights_table,
    "log_loss_table": log_loss_table,
    "gamma_search": gamma_search,
    "recall_table": recall_table,
    "miss_table": miss_table,
    "miss_simulated": miss_simulated,
    "memory_table": memory_table,
    "cost_table": cost_table,
    "cardinality_table": cardinality_table,
    "lane_geometry": lane_geometry,
    "plane_stats": plane_stats,
    "generated_codes": generated_codes,
    "codes_source": codes_source_table,
    "latency_table": latency_table,
    "pairs_clicks": pairs_clicks,
    "pairs_turns": pairs_turns,
    "pairs_lines": pairs_lines,
    "pairs_pages": pairs_pages,
    "training_samples": training_samples,
    "time_split": time_split,
    "trigram_vocab": trigram_vocab,
    "window_counts": window_counts,
    "encoded_turns": encoded_turns,
    "judged_pairs": judged,
    "judge_agreement": judge_agreement,
    "text_top_n": text_top,
    "objective_table": objective_table,
    "generated_recall": generated_recall,
    "lexical_bm25": partial(lexical, which="bm25"),
    "lexical_tfidf": partial(lexical, which="tfidf"),
    "lexical_bim": partial(lexical, which="bim"),
    "quality_table": quality_table,
    "overlap_table": overlap_table,
    "latent_lsa": partial(latent, which="lsa"),
    "latent_lda": partial(latent, which="lda"),
    "latent_word_sum": partial(latent, which="word_sum"),
    "vector_lsh": partial(vector_baseline, which="lsh"),
    "vector_pq": partial(vector_baseline, which="pq"),
    "attributed_clicks": attributed_clicks,
    "asof_views": asof_views,
    "rolling_ctr": rolling_ctr,
    "clicks_cube": clicks_cube,
    "star_top": star_top,
    "set_operations": set_operations,
    "grade_pivot": grade_pivot,
    "event_profile": event_profile,
    "user_windows": user_windows,
    "lateral_top": lateral_top,
    "stream_pairs": stream_pairs,
    "stream_unique": stream_unique,
    "stream_answers": stream_answers,
}
