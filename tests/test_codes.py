"""Codes, ladder, matching and selection on literal and random inputs."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from bitladder.functions import codes
from bitladder.functions.codes import CodeSpec
from bitladder.operators import binarize, cost, ladder, match, retrieve, select, theory


def planes_df(spark, q, k, qspec, kspec):
    """One row per pair, packed; q and k are lists of planes (rows x n)."""
    cols = [f"q_{c}" for c in qspec.columns()] + kspec.columns()
    words = np.concatenate([codes.pack(p) for p in [*q, *k]], axis=1)
    return spark.createDataFrame([tuple(int(x) for x in r) for r in words], ", ".join(f"{c} long" for c in cols))


@given(st.integers(-(2**63), 2**63 - 1), st.integers(-(2**63), 2**63 - 1))
@settings(max_examples=50)
def test_popcount_form_equals_list_form(x, y):
    a, b = codes.unpack(np.array([[x]]), 64)[0].astype(int), codes.unpack(np.array([[y]]), 64)[0].astype(int)
    assert int(a @ b) == 64 - 2 * bin((x ^ y) & (2**64 - 1)).count("1")
    assert codes.pack(a[None])[0, 0] == x


def test_dot_of_equal_and_opposite(spark):
    rows = [(x, y) for x in (0, -1, 1 << 62, -(2**63), 123456789) for y in (x, ~x)]
    out = spark.createDataFrame(rows, "x long, y long").select("x", "y", codes.pm_dot(F.col("x"), F.col("y")).alias("d")).collect()
    assert all(r["d"] == (64 if r["x"] == r["y"] else -64) for r in out)


@pytest.mark.parametrize("u,v,n,weighted", [(0, 0, 64, True), (1, 1, 64, True), (2, 1, 64, True), (2, 2, 128, True), (2, 1, 64, False), (3, 2, 64, True)])
def test_dots_norms_and_cosines_equal_dense(spark, u, v, n, weighted):
    rng = np.random.default_rng(u * 10 + v)
    q, k = ([rng.choice([-1.0, 1.0], (30, n)) for _ in range(d + 1)] for d in (u, v))
    qs, ks = CodeSpec(n, u + 1, weighted), CodeSpec(n, v + 1, weighted)
    df = planes_df(spark, q, k, qs, ks)
    out = df.select(
        codes.dot_expr(qs, ks).alias("h"), codes.dot_expr(qs, ks, order="naive").alias("n"), codes.norm_sq_expr(ks).alias("kn"), codes.norm_sq_expr(qs, "q_").alias("qn"),
        codes.cosine_expr(codes.dot_expr(qs, ks), codes.norm_sq_expr(qs, "q_"), codes.norm_sq_expr(ks)).alias("c"), match.rank_key(codes.dot_expr(qs, ks), codes.norm_sq_expr(ks), qs, ks).alias("key"),
    ).collect()
    dq, dk = ladder.dense(q, weighted), ladder.dense(k, weighted)
    for r, a, b in zip(out, dq, dk, strict=True):
        assert r["h"] == r["n"] == a @ b * qs.scale * ks.scale
        assert r["kn"] == b @ b * ks.scale**2 and r["qn"] == a @ a * qs.scale**2
        assert abs(r["c"] - a @ b / np.sqrt((a @ a) * (b @ b))) < 1e-12
    scores = [a @ b / np.sqrt(b @ b) for a, b in zip(dq, dk, strict=True)]
    keys = [r["key"] for r in out]
    for i in range(30):
        for j in range(i):
            if abs(scores[i] - scores[j]) > 1e-9:
                assert (scores[i] > scores[j]) == (keys[i] > keys[j])
            else:
                assert keys[i] == keys[j]


def test_two_planes_with_weight_one(spark):
    """All four plane dots count once in the plain two-plane form."""
    rng = np.random.default_rng(0)
    q, k = ([rng.choice([-1.0, 1.0], (1, 64)) for _ in range(2)] for _ in range(2))
    s = CodeSpec(64, 2, False)
    got = planes_df(spark, q, k, s, s).select(codes.dot_expr(s, s).alias("d")).first()["d"]
    assert got == sum(int(a[0] @ b[0]) for a in q for b in k)


def test_zero_code_has_no_cosine(spark):
    s = CodeSpec(64, 2, False)
    p = np.ones((1, 64))
    df = planes_df(spark, [p, p], [p, -p], s, s)
    r = df.select(codes.norm_sq_expr(s).alias("n"), codes.cosine_expr(codes.dot_expr(s, s), codes.norm_sq_expr(s, "q_"), codes.norm_sq_expr(s)).alias("c"), match.rank_key(codes.dot_expr(s, s), codes.norm_sq_expr(s), s, s).alias("k")).first()
    assert r["n"] == 0 and r["c"] is None and r["k"] is None


def test_sign(spark):
    assert binarize.sign(np.array([-1.0, -0.0, 0.0, 1e-30])).tolist() == [-1, -1, -1, 1]
    with pytest.raises(ValueError):
        binarize.sign(np.array([np.nan]))
    rows = spark.createDataFrame([(-1.0,), (-0.0,), (0.0,), (1e-30,), (None,)], "x double").select(binarize.sign_expr(F.col("x")).alias("s")).collect()
    assert [r["s"] for r in rows] == [-1, -1, -1, 1, None]


def test_values_and_cardinality():
    assert theory.values_per_dim(2) == [-1.5, -0.5, 0.5, 1.5] and theory.values_per_dim(2, False) == [-2, 0, 2]
    assert theory.cardinality(2, 5) == 4**5 and theory.cardinality(2, 5, False) == 3**5
    assert theory.cardinality(3, 4) == 8**4 and theory.cardinality(3, 4, False) == 4**4
    assert round(theory.edge_fraction(0.05, 128), 3) == 0.977


def test_memory_and_operations():
    m = cost.memory_model(64, 2)
    assert round(m["gib"], 2) == 14.90 and round(m["float_gib"], 2) == 238.42
    assert cost.memory_model(64, 3)["gib"] / m["gib"] == 1.5
    assert cost.ops(2, 1) == {"popcounts": 6, "shifts": 3}


def test_gradients_by_differences():
    """The backward pass with sign replaced by tanh."""
    rng = np.random.default_rng(3)
    p = ladder.LadderParams(rng.standard_normal((6, 4)), [rng.standard_normal((4, 6)) for _ in range(2)], [rng.standard_normal((6, 4)) for _ in range(2)])
    f, g = rng.standard_normal((3, 4)), rng.standard_normal((3, 6))
    act, d_act = np.tanh, lambda z: 1 - np.tanh(z) ** 2
    value = lambda: float((ladder.forward(f, p, act)[0] * g).sum())
    _, tape = ladder.forward(f, p, act)
    grads, gf = ladder.backward(g, tape, p, d_act)
    for x, dx in ((p.W, grads["W"]), (p.B[0], grads["B"][0]), (p.B[1], grads["B"][1]), (p.R[0], grads["R"][0]), (p.R[1], grads["R"][1]), (f, gf)):
        for _ in range(4):
            i = tuple(rng.integers(0, s) for s in x.shape)
            keep = x[i]
            x[i] = keep + 1e-6
            up = value()
            x[i] = keep - 1e-6
            down = value()
            x[i] = keep
            assert abs((up - down) / 2e-6 - dx[i]) < 1e-5


def test_ladder_sql_planes_equal_numpy(spark):
    h = ladder.hadamard(8)
    p = ladder.LadderParams(h, [0.1 * h.T] * 2, [h] * 2)
    x = np.random.default_rng(5).standard_normal((20, 8)) / np.sqrt(8)
    df = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "i int, v array<double>").orderBy("i")
    got = df.select("i", *[c.alias(f"s{t}") for t, c in enumerate(ladder.planes_sql(F.col("v"), p, 2))]).orderBy("i").collect()
    want = ladder.encode(x, p, 2)
    for t in range(3):
        assert [r[f"s{t}"] for r in got] == want[t].astype(int).tolist()


def test_shared_parameters_and_fingerprints():
    a, b = ladder.init_hadamard(64, 2), ladder.init_hadamard(64, 2, scale=0.5)
    assert a.fingerprint != b.fingerprint and not a.spec().matches(b.spec())
    shared = ladder.LadderParams(a.W, a.B[:1], a.R[:1], shared=True)
    x = np.random.default_rng(6).standard_normal((5, 64))
    assert all((p == q).all() for p, q in zip(ladder.encode(x, a, 2), ladder.encode(x, shared, 2), strict=True))


def test_dense_view(spark):
    p = ladder.init_hadamard(64, 2)
    x = np.random.default_rng(9).standard_normal((4, 64))
    words = [codes.pack(q)[:, 0].tolist() for q in ladder.encode(x, p)]
    df = spark.createDataFrame(list(zip(range(4), *words, strict=True)), "i int, p0_w0 long, p1_w0 long, p2_w0 long")
    got = [r[0] for r in df.orderBy("i").select(codes.dense_expr(CodeSpec(64, 3))).collect()]
    assert np.allclose(got, ladder.dense(ladder.encode(x, p)))


def test_windows_keep_positions(spark):
    from bitladder.functions import text

    df = spark.createDataFrame([("ab cd ef",), (None,), ("",)], "t string")
    bag, at = ([r[0] for r in df.select(text.word_windows(F.col("t"), 3, 512, m)).collect()] for m in ("bag", "positions"))
    assert [len(x) for x in bag] == [3, 0, 0]
    first = {x["idx"] for x in at[0][0]}
    assert all(512 <= i < 1536 for i in first)  # nothing before the first word
    assert sum(x["cnt"] for x in bag[0][1]) == sum(x["cnt"] for x in at[0][1]) == 6


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(8)
    ks = CodeSpec(64, 2)
    k = codes.pack(rng.choice([-1.0, 1.0], (96, 64))), codes.pack(rng.choice([-1.0, 1.0], (96, 64)))
    rows = [(i, i, int(a[0]), int(b[0])) for i, (a, b) in enumerate(zip(*k, strict=True))]
    index = spark.createDataFrame(rows, "keyword_id long, pos long, p0_w0 long, p1_w0 long").withColumn("norm_sq", codes.norm_sq_expr(ks)).repartition(3)
    queries = match.as_queries(index.where("keyword_id < 7"))
    return queries, index, ks


def result(df):
    return sorted(tuple(r) for r in df.select("query_id", "rank", "pos", "rank_key").collect())


@pytest.mark.parametrize("r", [1, 2])
def test_lane_selection(small, r):
    queries, index, s = small
    exact = result(retrieve.exact_top_n(queries, index, s, s, 10))
    for backend in ("expr", "block"):
        one = result(retrieve.top_n(queries, index, s, s, 10, 1, 4, r, "lane", backend))
        assert one == exact  # lanes of one keyword lose nothing
        full = result(retrieve.top_n(queries, index, s, s, 10, 8, 4, 8, "lane", backend))
        assert backend == "block" or full == exact
    assert result(retrieve.top_n(queries, index, s, s, 10, mode="radix")) == exact
    assert result(retrieve.top_n(queries, index, s, s, 10, mode="exact", backend="block")) == exact
    lane = result(retrieve.top_n(queries, index.coalesce(1), s, s, 10, 8, 4, r))
    assert lane == result(retrieve.top_n(queries, index.coalesce(1), s, s, 10, 8, 4, r, backend="block"))
    best = {x[0]: x for x in exact if x[1] == 1}
    assert {x[0]: x for x in lane if x[1] == 1} == best  # the first is never lost
    assert lane == result(retrieve.top_n(queries, index.coalesce(1), s, s, 10, 8, 4, r, fan_in=3))


def test_lanes_partition_positions(spark):
    df = spark.range(1000).select("id", select.lane_of(F.col("id"), 8, 4).alias("lane"), select.place_in_lane(F.col("id"), 8, 4).alias("place"))
    rows = df.select("id", "lane", "place", select.pos_of(F.col("lane"), F.col("place"), 8, 4).alias("back")).collect()
    assert all(r["id"] == r["back"] for r in rows)
    assert len({(r["lane"], r["place"]) for r in rows}) == 1000


def test_ties_go_to_the_smaller_position(spark):
    s = CodeSpec(64, 1)
    index = spark.createDataFrame([(i, i, 5) for i in range(20)], "keyword_id long, pos long, p0_w0 long").withColumn("norm_sq", codes.norm_sq_expr(s))
    q = match.as_queries(index.limit(1))
    assert [x[2] for x in result(retrieve.exact_top_n(q, index, s, s, 3))] == [0, 1, 2]
    assert [x[2] for x in result(retrieve.top_n(q, index, s, s, 3, 4, 2))] == [0, 1, 8]
    assert retrieve.top_n(q.where("false"), index, s, s, 3).count() == 0
    assert retrieve.top_n(q, index, s, s, 99, mode="exact").count() == 20


def test_broadcast_is_checked(spark):
    """Up to the limit a side is broadcast; beyond it the same rows come without the hint."""
    few, many = spark.range(5), spark.range(50)
    shown = [match.checked_broadcast(df, 10)._jdf.queryExecution().logical().toString() for df in (few, many)]
    assert "broadcast" in shown[0].lower() and "broadcast" not in shown[1].lower()
    assert match.checked_broadcast(many, 10).count() == 50
