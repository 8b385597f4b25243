"""At and beyond the limits of the engine: deep codes, many queries, small tables, odd inputs; encoder and training."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitladder.functions import codes, text
from bitladder.functions.codes import CodeSpec
from bitladder.operators import baselines, encoder, ladder, match, missprob, retrieve, samples, train
from bitladder.plans.index import LadderIndex, TextModel
from bitladder.sources import io


def coded(spark, depth, rows=40, seed=0):
    rng = np.random.default_rng(seed)
    v = rng.standard_normal((rows, 64))
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<double>")
    params = ladder.init_hadamard(64, depth)
    dense = (ladder.dense(ladder.encode(v, params)) * 2**depth).astype(object)
    return ladder.encode_vectors(df, params), params.spec(), [[int(x) for x in row] for row in dense]


@pytest.mark.parametrize("depth", range(9))
def test_every_depth_ranks_exactly(spark, depth):
    c, spec, dense = coded(spark, depth)
    q = match.as_queries(c)

    def squared(i, k):
        from fractions import Fraction

        s, n = sum(a * b for a, b in zip(dense[i], dense[k], strict=True)), sum(a * a for a in dense[k])
        return Fraction(s * abs(s), n)

    want = {(i, r + 1, k) for i in range(40) for r, k in enumerate(sorted((k for k in range(40) if k != i), key=lambda k: (-squared(i, k), k))[:5])}
    backends = ("expr",) if match.wide(spec, spec) else ("expr", "block")
    assert ("block" in backends) == (depth <= 6)
    for backend in backends:
        for mode in ("exact", "lane"):  # lanes of one keyword lose nothing
            got = retrieve.top_n(q, c, spec, spec, 5, 1, 4, mode=mode, backend=backend, exclude_self=True).collect()
            assert {(r["query_id"], r["rank"], r["pos"]) for r in got} == want
    if "block" not in backends:
        with pytest.raises(Exception, match="too deep"):
            retrieve.top_n(q, c, spec, spec, 5, backend="block").collect()


def test_waves_beyond_a_broadcast(spark, monkeypatch):
    c, spec, _ = coded(spark, 2)
    q = match.as_queries(c)
    want = sorted(tuple(r) for r in retrieve.top_n(q, c, spec, spec, 3, mode="exact").collect())
    real = match.few
    monkeypatch.setattr(match, "few", lambda df, max_rows=match.MAX_BROADCAST_ROWS: real(df, 10))
    assert sorted(tuple(r) for r in match.in_waves(q, lambda w: retrieve.exact_select(retrieve.scored_pairs(w, c, spec, spec), 3), 10).collect()) == want
    assert sorted(tuple(r) for r in retrieve.top_n(q, c, spec, spec, 3, mode="exact").collect()) == want
    assert sorted(tuple(r)[:4] for r in retrieve.top_n(q, c, spec, spec, 3, mode="exact", backend="block").collect()) == want
    f = spark.createDataFrame([(i, [1.0 + i] * 64) for i in range(25)], "query_id long, f array<double>")
    k1 = CodeSpec(64, 3)
    one, many = (match.hybrid(f, c, k1, max_rows=n).count() for n in (100, 7))
    assert one == many == 25 * 40


def test_histogram_counts_every_pair(spark):
    c, spec, _ = coded(spark, 2)
    q = match.as_queries(c)
    got = {(r["model"], round(r["score"], 9)): r["n"] for r in match.score_histogram(q, c, [("a", spec, spec)], exclude_self=True).collect()}
    want: dict = {}
    for r in match.exhaustive(q, c, spec, spec).where("query_id <> keyword_id").collect():
        want["a", round(r["cosine"], 9)] = want.get(("a", round(r["cosine"], 9)), 0) + 1
    assert got == want


@pytest.mark.parametrize("pairs,block", [(11, 4), (50, 4), (300, 16), (3000, 8)])
def test_every_pair_gets_all_its_negatives(spark, pairs, block):
    p = spark.range(pairs).select(F.col("id").alias("pair_id"), F.col("id").alias("query_id"), (F.col("id") + 10_000).alias("keyword_id"))
    per = samples.cross_sample(p, 10, block=block).groupBy("group_id").agg(F.count_if(~F.col("is_pos")).alias("n"), F.count_distinct("keyword_id").alias("k"))
    assert per.count() == pairs and per.where("n <> 10 or k <> 11").count() == 0
    with pytest.raises(ValueError):
        samples.cross_sample(p.limit(10), 10)


def test_ragged_and_null_vectors(spark):
    rows = [(0, [1.0] * 63), (1, [1.0] * 65)]
    ragged = spark.createDataFrame(rows, "vec_id long, embedding array<double>").coalesce(1)
    whole = spark.createDataFrame([(2, [1.0] * 64), (3, None), (4, [None] * 64)], "vec_id long, embedding array<double>")
    for broken in (lambda: ladder.encode_vectors(ragged, ladder.init_hadamard()).collect(), lambda: baselines.float_cosine(whole, ragged, 2).collect(), lambda: baselines.float_cosine(ragged, whole, 2).collect()):
        with pytest.raises(Exception, match="length"):
            broken()
    assert [r["keyword_id"] for r in ladder.encode_vectors(whole, ladder.init_hadamard()).collect()] == [2]
    assert [(r["query_id"], r["keyword_id"]) for r in baselines.float_cosine(whole, whole, 2).collect()] == [(2, 2)]


def test_turn_ids_do_not_clash(spark):
    df = spark.createDataFrame([(0, 10_000), (1, 0), (0, (1 << 24) - 2), (-1, 5), (None, 1), (2, None)], "c long, t long")
    ids = [r[0] for r in df.select(samples.turn_id(F.col("c"), F.col("t"))).collect()]
    assert len({i for i in ids if i is not None}) == 4 and ids.count(None) == 2
    with pytest.raises(Exception, match="out of range"):
        spark.createDataFrame([(0, 1 << 24)], "c long, t long").select(samples.turn_id(F.col("c"), F.col("t"))).collect()


@pytest.mark.filterwarnings("ignore")
def test_simulation_where_nearly_all_are_relevant(spark):
    rows = missprob.simulate(spark, 64, 60, 4, 1, 50, 1).collect()
    assert sum(r["trials"] for r in rows) == 50 and {r["l"] for r in rows} <= set(range(44, 46))  # 15 or 16 lanes are hit


@pytest.mark.parametrize("mode", ["bag", "positions"])
def test_word_convolution_equals_sparse_windows(spark, mode):
    texts = ["The quick brown fox's den", "", "one", "Ab ab AB straße 12", "naïve tests of words " * 7]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "id long, text string")
    tower = encoder.init_tower(512, 16, 64, 1, mode=mode)
    windows = {r["id"]: r["w"] for r in df.select("id", text.word_windows(F.col("text"), 3, 512, mode).alias("w")).collect()}
    got = {r["id"]: r["f"] for r in encoder.encode_texts(df, tower, "query", "id", vectors=True, keep_empty=True).collect()}
    for i in range(len(texts)):
        assert np.allclose(got[i], encoder.max_pool(encoder.convolve(windows[i], tower.query.conv))[0])
    vocab = {"#th": 0, "the": 1, "he#": 2, "fox": 7}
    ids = encoder.WordIds(8, vocab)
    assert ids["the"].tolist() == [0, 1, 2] and ids["zzz"].tolist() == []


@pytest.mark.parametrize("mode,hidden", [("bag", 0), ("positions", 0), ("bag", 1)])
def test_gradients_of_the_whole_tower(mode, hidden):
    """Finite differences through real-valued towers: convolution, pooling, hidden layers, cosine and softmax."""
    tower = encoder.init_tower(64, 8, 8, 0, mode=mode, hidden=hidden, floats=(True, True))
    words = "alpha beta gamma delta epsilon zeta eta theta".split()
    rng = np.random.default_rng(3)
    draw = lambda n: [words[i] for i in rng.integers(0, 8, n)]
    qs, ks, cfg = [draw(4), draw(6)], [[draw(5), draw(3), []], [draw(2), draw(7), draw(1)]], train.Config(gamma=3.0)
    _, grads = train.batch_gradient(tower, qs, ks, cfg, 0)
    for side in ("query", "keyword"):
        for key, x in tower.side(side).arrays().items():
            g = grads[side][key]
            if isinstance(g, tuple):
                whole = np.zeros_like(x)
                whole[g[0]] = g[1]
                g = whole
            for at in [tuple(rng.integers(0, n) for n in x.shape) for _ in range(12)]:
                kept, h = x[at], 1e-6
                x[at] = kept + h
                up = train.batch_gradient(tower, qs, ks, cfg, 0)[0]
                x[at] = kept - h
                down = train.batch_gradient(tower, qs, ks, cfg, 0)[0]
                x[at] = kept
                assert abs((up - down) / (2 * h) - g[at]) < 1e-4


def test_training_lowers_held_out_loss_and_towers_are_kept(spark, tmp_path):
    """Two languages: the answer is in the question's; trained text retrieval finds it."""
    rng = np.random.default_rng(4)
    tongues = [["kara", "mono", "tilu", "sepa", "roka"], ["blim", "drax", "frop", "grun", "skey"]]
    say = lambda i: " ".join(rng.choice(tongues[i % 2], 8))
    rows = [(i, say(i), say(i)) for i in range(60)]
    df = spark.createDataFrame(rows, "i long, q string, k string")
    pairs = df.select(F.col("i").alias("pair_id"), F.col("i").alias("query_id"), F.col("i").alias("keyword_id"))
    q, k = (df.select(F.col("i").alias(c), text.words(F.col(x)).alias("x")) for c, x in (("query_id", "q"), ("keyword_id", "k")))
    groups = train.packed_groups(samples.cross_sample(pairs, 3), q, k)
    fold = F.pmod("group_id", F.lit(4)) == 0
    cfg = train.Config(epochs=8, rate=0.02, optimizer="adam", clip=1e9)
    done = train.fit(groups.where(~fold), encoder.init_tower(256, 32, 64, 2, k_depth=1), cfg, path=str(tmp_path / "p"))
    assert done.converged and len(done.history) == 8
    held = train.tune_gamma(train.group_scores(groups.where(fold), {"m": done.model}), by=("model",)).agg(F.min("log_loss")).first()[0]
    assert held < np.log(4) * 0.9  # half of the negatives are of the same language
    again = io.load_tower(spark, str(tmp_path / "p" / "model"))
    for side in ("query", "keyword"):
        for key, x in done.model.side(side).arrays().items():
            assert np.array_equal(again.side(side).arrays()[key], x)
    model = TextModel(done.model)
    index = LadderIndex.build(df, model, "k", "i", 4, 4)
    top = index.top_n(model.encode(df, "query", "q", "i"), 5, mode="exact", backend="block").collect()
    assert np.mean([r["query_id"] % 2 == r["keyword_id"] % 2 for r in top]) > 0.9
    model.save(spark, str(tmp_path / "m"))
    assert TextModel.load(spark, str(tmp_path / "m")).model_id == model.model_id


def test_stochastic_surrogate_draws():
    tower = encoder.init_tower(64, 8, 64, 1)
    qs, ks = [["ab"], ["cd"]], [[["ab"], ["ef"]], [["cd"], ["gh"]]]
    a, b = (train.batch_gradient(tower, qs, ks, train.Config(surrogate=s), 0)[0] for s in ("clipped", "stochastic"))
    c = train.batch_gradient(tower, qs, ks, train.Config(surrogate="stochastic"), 0)[0]
    assert a != b and b == c


def test_words_of_codes_pack(spark):
    x = np.random.default_rng(0).choice([-1.0, 1.0], (7, 128))
    assert np.array_equal(codes.unpack(codes.pack(x), 128), x.astype(np.int8))
