"""Miss probability, measures, samples, storage, streams and the SQL of the queries."""

import math
from fractions import Fraction

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from bitladder import registry, workloads
from bitladder.operators import baselines, loss, metrics, missprob, samples
from bitladder.sources import codes_source, io


def test_published_miss_table():
    p = missprob.exact(10**9 - 10**9 % 256, 1000, 256, 2)
    total = [float(sum(p[: i + 1])) for i in range(3)]
    for got, want in zip(total, (0.880396, 0.992563, 0.999689), strict=True):
        assert abs(got - want) < 1e-6
    assert abs(missprob.expected_recall(10**9 - 10**9 % 256, 1000, 256) - 0.999873) < 1e-6


@pytest.mark.filterwarnings("ignore")
def test_series_equals_enumeration():
    for C, N, I in ((12, 4, 3), (20, 5, 4), (12, 4, 1)):  # noqa: E741
        p = missprob.exact(C, N, I, N - 1)
        assert sum(p) == 1
        for l, x in enumerate(p):  # noqa: E741
            if N - l >= 1:
                assert x == missprob.enumerated(C, N, I, N - l)
        assert abs(float(sum(l * x for l, x in enumerate(p))) - missprob.expected_missed(C, N, I)) < 1e-9  # noqa: E741
    two = missprob.exact(12, 5, 4, 4, r=2)
    assert sum(two) == 1
    assert abs(float(sum(l * x for l, x in enumerate(two))) - missprob.expected_missed(12, 5, 4, 2)) < 1e-9  # noqa: E741
    assert missprob.exact(12, 4, 3, 0, r=3)[0] == Fraction(1)


@pytest.mark.filterwarnings("ignore")
def test_simulation_is_near_theory(spark):
    rows = missprob.simulate(spark, 4096, 16, 16, 1, 1500, 3).collect()
    mean = sum(r["l"] * r["share"] for r in rows)
    assert abs(mean - missprob.expected_missed(4096, 16, 16)) < 0.05


def test_auc_and_lift(spark):
    rng = np.random.default_rng(1)
    rows = [(float(np.round(s, 1)), bool(b)) for s, b in zip(rng.standard_normal(200), rng.random(200) < 0.3, strict=True)]
    df = spark.createDataFrame(rows, "score double, is_pos boolean")
    pos, neg = [s for s, b in rows if b], [s for s, b in rows if not b]
    want = sum((p > n) + 0.5 * (p == n) for p in pos for n in neg) / (len(pos) * len(neg))
    assert abs(metrics.roc_auc(df).first()["auc"] - want) < 1e-12
    flipped = metrics.roc_auc(df.withColumn("score", -F.col("score"))).first()["auc"]
    assert abs(flipped - (1 - want)) < 1e-12
    assert metrics.roc_auc(df.where("is_pos")).first()["auc"] is None
    assert metrics.roc_auc(df.withColumn("score", F.lit(1.0))).first()["auc"] == 0.5
    assert round(metrics.auc_lift(0.8005, 0.7846, 0.8044), 2) == 80.30


def test_group_loss(spark):
    df = spark.createDataFrame([(1, i == 0, 0.3) for i in range(11)], "group_id int, is_pos boolean, cosine double")
    assert abs(metrics.log_loss(df, 10.0).first()["log_loss"] - math.log(11)) < 1e-12
    assert abs(loss.group_prob(df, 5.0).agg(F.sum("prob")).first()[0] - 1) < 1e-12
    value, g = loss.group_grad(np.full((1, 11), 0.3), 10.0)
    assert abs(value - math.log(11)) < 1e-12 and abs(g.sum()) < 1e-12


def test_grades_recall_and_overlap(spark):
    a = spark.createDataFrame([("good",), ("good",), ("bad",)], "grade string")
    b = spark.createDataFrame([("good",), ("fair",)], "grade string")
    got = {r["grade"]: (r["ours"], r["theirs"], r["change"]) for r in metrics.grade_change(a, b).collect()}
    assert got == {"good": (2, 1, 100.0), "bad": (1, 0, None), "fair": (0, 1, -100.0)}
    t = spark.createDataFrame([(1, 1), (1, 2), (2, 5)], "query_id int, pos int")
    r = spark.createDataFrame([(1, 1), (1, 9)], "query_id int, pos int")
    assert {x["query_id"]: x["recall"] for x in metrics.recall_at(r, t, 2).collect()} == {1: 0.5, 2: 0.0}
    o = metrics.overlap(t, r, ("query_id", "pos")).first()
    assert o["common"] == 1 and o["of_theirs"] == 0.5


def test_cross_sampling(spark):
    pairs = spark.createDataFrame([(i, i, 100 + i) for i in range(50)], "pair_id long, query_id long, keyword_id long")
    out = samples.cross_sample(pairs, 10, block=16).collect()
    for g in range(50):
        mine = [r for r in out if r["group_id"] == g]
        assert sum(r["is_pos"] for r in mine) == 1
        negatives = [r["keyword_id"] for r in mine if not r["is_pos"]]
        assert len(negatives) == len(set(negatives)) and 100 + g not in negatives
    packed = samples.groups(samples.cross_sample(pairs, 3, block=16)).collect()
    assert all(r["members"][0]["is_pos"] for r in packed)
    same = pairs.withColumn("keyword_id", F.lit(7).cast("long"))
    assert samples.cross_sample(same, 3, block=16, drop_false_negatives=True).where("query_id = 0 and not is_pos").count() == 0


def test_index_round_trip(spark, sf, tmp_path):
    from bitladder.operators import ladder
    from bitladder.plans.index import LadderIndex, LadderModel

    model = LadderModel(ladder.init_hadamard(64, 2))
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    index = LadderIndex.build(e, model, lane_size=8, lanes_per_block=4, seed=3, attributes=("label",))
    pos = sorted(r["pos"] for r in index.codes.select("pos").collect())
    assert pos == list(range(e.count()))
    index.write(str(tmp_path / "i"), rows_per_part=64)
    again = LadderIndex.read(spark, str(tmp_path / "i"), model, 8, 4)
    assert again.codes.count() == e.count()
    lanes = again.codes.select("part_id", (F.floor(F.col("pos") / 32) * 4 + F.col("pos") % 4).alias("lane")).distinct()
    assert lanes.count() == lanes.select("lane").distinct().count()  # no lane in two parts
    base, spec = io.read_index(spark, str(tmp_path / "i"), planes=1)
    assert "p1_w0" not in base.columns and spec.planes == 1
    with pytest.raises(ValueError):
        io.read_index(spark, str(tmp_path / "i"), model="other")
    q = model.encode(e, "query").limit(5)
    assert again.top_n(q, 3, where="label < 5").count() == 15
    again.register_sql(model.encode(e, "query"))
    by_sql = spark.sql("SELECT keyword_id FROM top_n(3, 5) ORDER BY rank").collect()
    exact = again.top_n(model.encode(e, "query").where("query_id = 3"), 5, mode="exact").orderBy("rank").collect()
    assert [r[0] for r in by_sql] == [r["keyword_id"] for r in exact]
    model.save(spark, str(tmp_path / "m"))
    assert LadderModel.load(spark, str(tmp_path / "m")).model_id == model.model_id
    assert index.explain_cost(5)["popcounts"] == 6 and index.stats().count() == 2


def test_generated_source_ignores_the_cut(spark):
    codes_source.register(spark)
    one, many = (spark.read.format("ladder_codes").option("rows", 500).option("partitions", p).load().orderBy("keyword_id").collect() for p in (1, 7))
    assert one == many


def test_sql_table_functions(spark):
    from bitladder.functions import sqlfuncs

    sqlfuncs.register_functions(spark)
    assert [r[0] for r in spark.sql("SELECT trigram FROM letter_trigrams('Ab c')").collect()] == ["#ab", "ab#", "#c#"]
    assert abs(spark.sql("SELECT p FROM miss_table(64, 4, 4, 1) WHERE l = 0").first()[0] - float(missprob.exact(64, 4, 4, 0)[0])) < 1e-12
    assert spark.sql("SELECT auc_agg(s, b) FROM VALUES (0.1D, false), (0.9D, true), (0.5D, false) t(s, b)").first()[0] == 1.0
    assert spark.sql("SELECT sign_planes(5L)").first()[0][:4] == [1, -1, 1, -1]


def test_vector_baselines_agree(spark, sf):
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    by_sql = baselines.ranked(baselines.float_cosine_sql(e, e).where("query_id <> keyword_id"), 3)
    by_block = baselines.float_cosine(e, e, 3, exclude_self=True, wave_rows=200)
    a, b = ({(r["query_id"], r["rank"], r["keyword_id"]) for r in x.collect()} for x in (by_sql, by_block))
    assert len(a - b) <= 2  # rounding at near ties


def test_orderings_of_the_models(spark, sf):
    auc = {r["model"]: r["auc"] for r in workloads.bits_table(spark, sf).collect()}
    assert auc["code(0,0)"] < auc["code(1,1)"] < auc["code(2,1)"] < auc["code(2,2)"]
    for r in workloads.weights_table(spark, sf).collect():
        assert r["auc_weighted"] > r["auc_plain"]
    five = {r["model"]: r["auc"] for r in workloads.accuracy_table(spark, sf).collect()}
    assert five["code(0,0)"] < five["sign128"] < five["code(2,1)"] < five["hybrid"] < five["float64d"]


def test_stateful_top_n(spark, tmp_path):
    """Running best by merge equals the batch result."""
    from bitladder.streaming import stream

    rows = [(q, k, float((q * 37 + k * 11) % 23)) for q in range(3) for k in range(40)]
    src = str(tmp_path / "in")
    spark.createDataFrame(rows, "query_id long, keyword_id long, score double").repartition(4).write.parquet(src)
    s = spark.readStream.schema("query_id long, keyword_id long, score double").option("maxFilesPerTrigger", 1).parquet(src)
    stream.stream_keyword_top_n(s, 5, str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    last = max(int(p.name.split("=")[1]) for p in (tmp_path / "out").iterdir() if "=" in p.name)
    got = {(r["query_id"], r["keyword_id"]) for r in spark.read.parquet(str(tmp_path / "out" / f"state={last}")).collect()}
    want = {(q, k) for q in range(3) for _, k in sorted((-s, k) for x, k, s in rows if x == q)[:5]}
    assert got == want


@pytest.mark.parametrize("name", ["lane_top_n", "lane_top_n_block", "radix_top_n", "index_top_n", "ladder_planes", "code_dots_2_1", "code_dots_plain_2_1", "sql_functions", "progressive", "above_threshold", "log_loss_table", "trigram_vocab", "window_counts", "judged_pairs", "lexical_bm25", "lexical_tfidf", "asof_views", "rolling_ctr", "clicks_cube", "set_operations", "grade_pivot", "user_windows", "lateral_top", "stream_pairs", "stream_answers"])
def test_query_equals_its_sql(spark, sf, name):
    con = duckdb.connect()
    for t in io.TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = registry.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    want = con.sql(registry.ORACLES[name])
    assert cols == sorted(want.columns)

    def tidy(rows):
        return sorted(repr(tuple(round(x, 6) if isinstance(x, float) else x for x in r)) for r in rows)

    assert tidy(tuple(r[c] for c in cols) for r in df.collect()) == tidy(want.project(", ".join(f'"{c}"' for c in cols)).fetchall())
