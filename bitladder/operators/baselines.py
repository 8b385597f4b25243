"""Baselines: full-precision cosine, sign codes, lexical ranking, topic and word models.

All return (query_id, keyword_id, score), or with ``N`` also rank, like retrieval.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import words
from .ladder import LadderParams, hadamard, init_orthogonal, matrix
from .match import checked_broadcast, local_waves, same_ids, wave_by_wave
from .retrieve import Queues, sifted


def ranked(scored: DataFrame, N: int | None) -> DataFrame:
    if N is None:
        return scored
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "keyword_id")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= N).select("query_id", "rank", "keyword_id", "score")


def float_cosine_sql(queries: DataFrame, keywords: DataFrame, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Cosine of every pair by expressions; for sizes at which queries are broadcast."""
    def dot(a, b):
        return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)

    q = queries.select(F.col(key).alias("query_id"), F.col(vector).cast("array<double>").alias("qv"))
    k = keywords.select(F.col(key).alias("keyword_id"), F.col(vector).cast("array<double>").alias("kv"))
    norm = F.sqrt(dot(F.col("qv"), F.col("qv"))) * F.sqrt(dot(F.col("kv"), F.col("kv")))
    return k.crossJoin(checked_broadcast(q)).select("query_id", "keyword_id", (dot(F.col("qv"), F.col("kv")) / F.when(norm > 0, norm)).alias("score"))


def usable(df: DataFrame, key: str, vector: str, as_key: str) -> DataFrame:
    """``as_key`` and ``v`` of the vectors without null components."""
    kept = df.where(F.col(vector).isNotNull() & F.forall(vector, lambda x: x.isNotNull()))
    return kept.select(F.col(key).cast("long").alias(as_key), F.col(vector).cast("array<double>").alias("v"))


def float_cosine(queries: DataFrame, keywords: DataFrame, N: int | None = None, key: str = "vec_id", vector: str = "embedding", exclude_self: bool = False, wave_rows: int = 4096) -> DataFrame:
    """Full-precision cosine of every pair, block products in waves of queries.

    With ``N`` each partition sends its best N of a query; else all pairs leave.
    Vectors with null components take no part; unequal lengths are an error.  A
    zero vector has no cosine: its score is null and it is not ranked.
    """
    spark = keywords.sparkSession
    source = usable(keywords, key, vector, "keyword_id")
    schema, names = "query_id long, keyword_id long, score double", ["query_id", "keyword_id", "score"]

    def unit(x):
        n = np.linalg.norm(x, axis=1, keepdims=True)
        return np.divide(x, n, out=np.full_like(x, np.nan), where=n > 0)

    def wave(rows):
        if len({len(r[1]) for r in rows}) > 1:
            raise ValueError("query vectors of unequal lengths")
        ids, q = np.array([r[0] for r in rows], np.int64), unit(np.array([r[1] for r in rows], np.float64))
        sent = spark.sparkContext.broadcast((ids, q))

        def run(batches):
            qi, qv = sent.value
            kept, by_id = Queues(len(qi), N or 1, N or 1, np.float64), np.argsort(qi)
            for batch in batches:
                for a in range(0, batch.num_rows, 4096):
                    part = batch.slice(a, 4096)
                    k = part.column(0).to_numpy(zero_copy_only=False)
                    x = unit(matrix(part.column(1), qv.shape[1]))
                    if N is not None:  # vectors without a cosine are not ranked
                        real = ~np.isnan(x).any(axis=1)
                        k, x = k[real], x[real]
                    if not len(k):
                        continue
                    row, col = same_ids(k, qi, by_id) if exclude_self else (by_id[:0], by_id[:0])
                    alone = np.arange(len(k))
                    for b in range(0, len(qi), 256):
                        s, mine = qv[b : b + 256] @ x.T, qi[b : b + 256]
                        own = (col >= b) & (col < b + 256)
                        if N is None:
                            keep = np.ones(s.shape, bool)
                            keep[col[own] - b, row[own]] = False
                            at, of = np.nonzero(keep)
                            yield pa.RecordBatch.from_arrays([pa.array(mine[at]), pa.array(k[of]), pa.array(s[at, of], from_pandas=True)], names)
                            continue
                        s[col[own] - b, row[own]] = -np.inf
                        at, of = sifted(s, alone, alone, kept.least[b : b + 256], N, N, 0.0)
                        if len(at):
                            score = s[at, of]
                            kept.add(at + b, of, k[of], score, k[of], score)
                    kept.settle()
            if N is not None:
                i, _, pos, score, _ = kept.all()
                for b in range(0, len(i), 1 << 16):
                    yield pa.RecordBatch.from_arrays([pa.array(x[b : b + (1 << 16)]) for x in (qi[i], pos, score.astype(np.float64))], names)

        return source.mapInArrow(run, schema), sent

    out = wave_by_wave(spark, local_waves(usable(queries, key, vector, "query_id"), wave_rows), wave, schema)
    return ranked(out, N)


def sign_code(n: int, m: int = 64, seed: int = 7) -> LadderParams:
    """One plane of ``n`` signs: Hadamard rows, for n = 2 m also with columns flipped by a bent
    sequence (as far from the first rows as can be); else stacked orthogonal blocks."""
    if m & (m - 1) == 0 and n in (m, 2 * m):
        h, flip = hadamard(m), np.array([(-1.0) ** (j & (j >> 1)).bit_count() for j in range(m)])
        return LadderParams(np.concatenate([h, h * flip])[:n], [], [])
    return init_orthogonal(m, n, 0, seed)


def hash_sample(df: DataFrame, key: str, per_mille: int, seed: int = 0) -> DataFrame:
    """A reproducible share of rows by the MD5 of seed and key."""
    digest = F.md5(F.concat_ws(":", F.lit(seed).cast("string"), F.col(key).cast("string")))
    return df.where(F.conv(F.substring(digest, 1, 7), 16, 10).cast("long") % 1000 < per_mille)


def float_bruteforce(queries: DataFrame, keywords: DataFrame, per_mille: int, N: int, key: str = "vec_id") -> DataFrame:
    """Full-precision brute force on a hash sample of the keywords."""
    return float_cosine(queries, hash_sample(keywords, key, per_mille), N, key)


def checkpoint(df: DataFrame, name: str) -> DataFrame:
    from ..sources import io

    return io.checkpoint(df, name)


def postings(texts: DataFrame, key: str, text: str = "text") -> DataFrame:
    """key, term, tf: one row for each document and distinct word."""
    return texts.select(F.col(key), F.explode(words(F.col(text))).alias("term")).groupBy(key, "term").agg(F.count("*").alias("tf"))


def _terms(queries: DataFrame, text: str) -> DataFrame:
    return checkpoint(postings(queries, "query_id", text).withColumnRenamed("tf", "qtf"), "terms")


def _matched(keywords: DataFrame, terms: DataFrame, text: str) -> tuple[DataFrame, int, int]:
    """Postings (keyword_id, len, term, tf, df) of the queries' terms; documents and all their words.

    Words that no query asks for drop out before the first shuffle; a document's
    length is the size of its word list, so nothing is joined for it.
    """
    asked = terms.select("term").distinct()
    listed = keywords.select("keyword_id", words(F.col(text)).alias("w")).select("keyword_id", "w", F.size("w").cast("long").alias("len"))
    count, total = listed.agg(F.count("*"), F.coalesce(F.sum("len"), F.lit(0))).first()
    hits = listed.select("keyword_id", "len", F.explode("w").alias("term")).join(checked_broadcast(asked), "term", "left_semi")
    post = checkpoint(hits.groupBy("keyword_id", "len", "term").agg(F.count("*").alias("tf")), "postings")
    dfs = post.groupBy("term").agg(F.count("*").alias("df"))
    return post.join(checked_broadcast(dfs), "term"), count, total


def tfidf_cosine(queries: DataFrame, keywords: DataFrame, N: int | None = None, text: str = "text", idf: bool = True) -> DataFrame:
    """Cosine of term frequency (times ln(C/df)) vectors; equi-join on terms.

    A document's norm needs all its terms, so here the whole postings are written once.
    """
    post = checkpoint(postings(keywords, "keyword_id", text), "postings")
    count = keywords.count()
    weight = F.log(F.lit(float(max(count, 1))) / F.col("df")) if idf else F.lit(1.0)
    dfs = checkpoint(post.groupBy("term").agg(F.count("*").alias("df")).select("term", weight.alias("idf")), "idf")
    k = post.join(checked_broadcast(dfs, 1_000_000), "term").select("keyword_id", "term", (F.col("tf") * F.col("idf")).alias("kw"))
    q = checkpoint(_terms(queries, text).join(dfs, "term").select("query_id", "term", (F.col("qtf") * F.col("idf")).alias("qw")), "weights")
    kn = k.groupBy("keyword_id").agg(F.sqrt(F.sum(F.col("kw") * F.col("kw"))).alias("kn"))
    qn = q.groupBy("query_id").agg(F.sqrt(F.sum(F.col("qw") * F.col("qw"))).alias("qn"))
    dots = k.join(checked_broadcast(q, 1_000_000), "term").groupBy("query_id", "keyword_id").agg(F.sum(F.col("qw") * F.col("kw")).alias("dot"))
    out = dots.join(kn, "keyword_id").join(checked_broadcast(qn), "query_id").where("kn > 0 and qn > 0")
    return ranked(out.select("query_id", "keyword_id", (F.col("dot") / (F.col("kn") * F.col("qn"))).alias("score")), N)


def bm25(queries: DataFrame, keywords: DataFrame, N: int | None = None, k1: float = 1.2, b: float = 0.75, text: str = "text") -> DataFrame:
    """BM25 over distinct query words."""
    terms = _terms(queries, text)
    post, count, total = _matched(keywords, terms, text)
    mean = total / max(count, 1) or 1.0
    idf = F.log((F.lit(count) - F.col("df") + 0.5) / (F.col("df") + 0.5) + 1.0)
    part = idf * F.col("tf") * (k1 + 1.0) / (F.col("tf") + k1 * (1.0 - b + b * F.col("len") / F.lit(float(mean))))
    scored = post.select("keyword_id", "term", part.alias("part")).join(checked_broadcast(terms), "term").groupBy("query_id", "keyword_id").agg(F.sum("part").alias("score"))
    return ranked(scored, N)


def bim(queries: DataFrame, keywords: DataFrame, N: int | None = None, text: str = "text") -> DataFrame:
    """Binary independence model without relevance feedback."""
    terms = _terms(queries, text)
    post, count, _ = _matched(keywords, terms, text)
    weight = F.log((F.lit(count) - F.col("df") + 0.5) / (F.col("df") + 0.5))
    scored = post.select("keyword_id", "term", weight.alias("part")).join(checked_broadcast(terms), "term").groupBy("query_id", "keyword_id").agg(F.sum("part").alias("score"))
    return ranked(scored, N)


def _counts(texts: DataFrame, key: str, text: str, dims: int) -> DataFrame:
    from pyspark.ml.feature import HashingTF

    rows = texts.select(F.col(key).cast("long").alias("id"), words(F.col(text)).alias("words"))
    return HashingTF(inputCol="words", outputCol="features", numFeatures=dims).transform(rows)


def principal_vectors(queries: DataFrame, keywords: DataFrame, k: int, text: str = "text", dims: int = 512) -> tuple[DataFrame, DataFrame]:
    """vec_id, embedding of both sides: hashed counts along the keywords' principal directions.

    These directions are the best weights of a linear autoencoder, so this is its code layer too.
    """
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import vector_to_array

    counts = _counts(keywords, "keyword_id", text, dims)
    model = PCA(k=k, inputCol="features", outputCol="z").fit(counts)
    both = (_counts(queries, "query_id", text, dims), counts)
    qv, kv = (model.transform(x).select(F.col("id").alias("vec_id"), vector_to_array("z").alias("embedding")) for x in both)
    return qv, kv


def unit_vectors(df: DataFrame) -> DataFrame:
    """vec_id, embedding scaled to length one; zero vectors are left out."""
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x * x))
    return df.withColumn("norm", norm).where("norm > 0").select("vec_id", F.transform("embedding", lambda x: x / F.col("norm")).alias("embedding"))


def lsa(queries: DataFrame, keywords: DataFrame, k: int = 32, N: int | None = None, text: str = "text", dims: int = 512) -> DataFrame:
    """Latent semantic ranking: principal directions of hashed counts, then cosine."""
    return float_cosine(*principal_vectors(queries, keywords, k, text, dims), N)


def lda(queries: DataFrame, keywords: DataFrame, topics: int = 10, N: int | None = None, text: str = "text", dims: int = 512, iterations: int = 5) -> DataFrame:
    """Topic mixtures, compared by cosine."""
    from pyspark.ml.clustering import LDA
    from pyspark.ml.functions import vector_to_array

    counts = _counts(keywords, "keyword_id", text, dims)
    model = LDA(k=topics, maxIter=iterations, seed=1, featuresCol="features").fit(counts)
    kv = model.transform(counts).select(F.col("id").alias("vec_id"), vector_to_array("topicDistribution").alias("embedding"))
    qv = model.transform(_counts(queries, "query_id", text, dims)).select(F.col("id").alias("vec_id"), vector_to_array("topicDistribution").alias("embedding"))
    return float_cosine(qv, kv, N)


#: words that one part of a skip-gram fit passes through at least
FIT_WORDS = 1 << 20


def word_model(texts: DataFrame, text: str = "text", size: int = 64, iterations: int = 1):
    """Skip-gram vectors of the words of ``texts``.

    Parts of at least ``FIT_WORDS`` words, as many as there are cores at most, go
    side by side from the same vectors in an iteration, which takes their mean.
    """
    from pyspark.ml.feature import Word2Vec

    rows = checkpoint(texts.select(words(F.col(text)).alias("words")).where(F.size("words") > 0), "words")
    total = rows.agg(F.coalesce(F.sum(F.size("words")), F.lit(0))).first()[0]
    parts = min(max(1, total // FIT_WORDS), rows.sparkSession.sparkContext.defaultParallelism)
    return Word2Vec(vectorSize=size, minCount=2, maxIter=iterations, numPartitions=parts, seed=1, inputCol="words", outputCol="z").fit(rows)


def word_vectors(texts: DataFrame, key: str, text: str = "text", size: int = 64, iterations: int = 1, fit_on: DataFrame | None = None, model=None) -> DataFrame:
    """vec_id, embedding: mean word vectors of each text (the sum layer, up to scale), under ``model`` or one fitted for it."""
    from pyspark.ml.functions import vector_to_array

    rows = texts.select(F.col(key).cast("long").alias("vec_id"), words(F.col(text)).alias("words")).where(F.size("words") > 0)
    model = model or word_model(texts if fit_on is None else fit_on, text, size, iterations)
    return model.transform(rows).select("vec_id", vector_to_array("z").alias("embedding"))


def word_sides(queries: DataFrame, keywords: DataFrame, text: str = "text", size: int = 64) -> tuple[DataFrame, DataFrame]:
    """Vectors of both sides under one model, fitted once on the texts of both."""
    model = word_model(queries.select(text).unionByName(keywords.select(text)), text, size)
    return word_vectors(queries, "query_id", text, model=model), word_vectors(keywords, "keyword_id", text, model=model)


def word_sum(queries: DataFrame, keywords: DataFrame, N: int | None = None, text: str = "text", size: int = 64) -> DataFrame:
    return float_cosine(*word_sides(queries, keywords, text, size), N)


def lsh(queries: DataFrame, keywords: DataFrame, N: int, bucket: float = 0.5, tables: int = 8, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Random-projection hashing: candidates share a bucket, then exact distance."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    def rows(df):
        return df.where(F.col(vector).isNotNull()).select(F.col(key).alias("id"), array_to_vector(F.col(vector).cast("array<double>")).alias("features"))

    k = rows(keywords)
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=3).fit(k)
    pairs = model.approxSimilarityJoin(rows(queries), k, 2.0, "dist")
    return ranked(pairs.select(F.col("datasetA.id").alias("query_id"), F.col("datasetB.id").alias("keyword_id"), (1.0 - F.col("dist") * F.col("dist") / 2.0).alias("score")), N)


def product_quantizer(queries: DataFrame, keywords: DataFrame, N: int, parts: int = 8, centers: int = 16, sample: int = 20_000, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Quantised sub-vectors: centers are fitted on a bounded sample, all rows are coded.

    A score is the sum of table lookups, one per part.
    """
    spark = keywords.sparkSession
    fit = np.array([r[0] for r in keywords.where(F.col(vector).isNotNull()).orderBy(F.xxhash64(key)).limit(sample).select(F.col(vector).cast("array<double>")).collect()])
    width, rng, books = fit.shape[1] // parts, np.random.default_rng(0), []
    for p in range(parts):
        x = fit[:, p * width : (p + 1) * width]
        c = x[rng.choice(len(x), min(centers, len(x)), replace=False)]
        for _ in range(10):
            near = ((x[:, None] - c[None]) ** 2).sum(-1).argmin(1)
            c = np.stack([x[near == i].mean(0) if (near == i).any() else c[i] for i in range(len(c))])
        books.append(c)
    sent = spark.sparkContext.broadcast(books)

    def coded(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x = matrix(batch.column(1))
            back = np.concatenate([c[((x[:, p * width : (p + 1) * width][:, None] - c[None]) ** 2).sum(-1).argmin(1)] for p, c in enumerate(sent.value)], axis=1)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(back), pa.list_(pa.float64()))], ["vec_id", "embedding"])

    codes = keywords.where(F.col(vector).isNotNull()).select(F.col(key).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("embedding")).mapInArrow(coded, "vec_id long, embedding array<double>")
    return float_cosine(queries.select(F.col(key).alias("vec_id"), F.col(vector).alias("embedding")), codes, N)
