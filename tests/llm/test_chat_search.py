"""Preference formatting, exact search, the pipeline and the SQL of the queries."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from bitladder.llm import chat, queries, search


def test_preferences(spark):
    c = [(1, 0, "user", "Hi"), (1, 1, "assistant", "Hello"), (1, 2, "user", "Bye"), (1, 3, "assistant", "Good")]
    r = [(1, 0, "user", "Hi"), (1, 1, "assistant", "Hello"), (1, 2, "user", "Bye"), (1, 3, "assistant", "Bad"), (1, 3, "assistant", "Bad"), (2, None, None, None)]
    schema = "pair_id long, turn long, role string, text string"
    out = {(x["pair_id"], x["part"]): x for x in chat.format_preferences(spark.createDataFrame(c, schema), spark.createDataFrame(r, schema)).collect()}
    prompt = out[1, "prompt"]
    assert prompt["n_turns"] == 3 and prompt["loss_spans"] == "" and prompt["text"].startswith("<|user|>\nHi<|end|>\n<|assistant|>\nHello")
    for part, text in (("chosen", "Good"), ("rejected", "Bad")):
        x = out[1, part]
        a, b = map(int, x["loss_spans"].split("-"))
        assert x["text"][a:b] == text + "<|end|>\n"
    assert (2, "rejected") in out and (2, "chosen") not in out


def test_preferences_equal_sides_and_segments(spark):
    schema = "pair_id long, turn long, role string, text string"
    same = spark.createDataFrame([(1, t, "user", f"x{t}") for t in range(600)], schema)
    rows = chat.format_preferences(same, same).collect()
    assert {r["part"] for r in rows} == {"prompt"} and sorted(r["segment"] for r in rows) == [0, 1, 2]
    assert chat.format_preferences(same.where("false"), same.where("false")).count() == 0


def brute_top(rows, k, wanted):
    whole = {}
    for i, v in rows:
        if i is not None and v and all(x is not None and np.isfinite(x) for x in v):
            whole.setdefault(i, [int(np.floor(256.0 * float(x))) for x in v])
    out = set()
    for q in whole:
        if q in wanted:
            s = sorted((-sum(a * b for a, b in zip(whole[q], v, strict=True)), i) for i, v in whole.items() if i != q and len(v) == len(whole[q]))[:k]
            out |= {(q, r + 1, i, max(-(2**63), min(2**63 - 1, -x))) for r, (x, i) in enumerate(s)}
    return out


@pytest.mark.parametrize("lists", [1, 2, 3])
def test_top_k(spark, lists):
    rng = np.random.default_rng(5)
    rows = [(i, rng.standard_normal(6).tolist()) for i in range(80)]
    rows += [(200 + i, rows[3][1]) for i in range(30)]  # many equal vectors
    rows += [(300, None), (301, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (302, [float("nan")] * 6), (303, []), (304, [1.0, 2.0]), (305, [3.0, 4.0]), (306, [3e7] * 6), (None, [1.0] * 6), rows[0], (307, [1e15, -1e15, 0.5, 0.0, 0.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("score", F.lit("clash")).repartition(3)
    wanted = {r[0] for r in rows if r[0] is not None and r[0] % 2 == 0}
    for wave in (7, 4096):
        got = {tuple(r) for r in search.top_k(df, df.where("vec_id % 2 = 0"), 5, lists, wave).collect()}
        assert got == brute_top(rows, 5, wanted)
    assert search.top_k(df.where("false"), df.where("false")).count() == 0


def test_top_k_of_repeated_rows(spark):
    """Copies of one row, and one id with many vectors of equal score, hold one place."""
    rng = np.random.default_rng(6)
    rows = [(i, rng.integers(-8, 8, 6).astype(float).tolist()) for i in range(1, 205)] + [(0, [1.0, 0.0, 0.0, 0.0, 0.0, 0.0])]
    for id_, many in ((500, [[90.0] + [0.0] * 5] * 50), (500, [[90.0, float(i), 0.0, 0.0, 0.0, 0.0] for i in range(60)])):
        both = [*rows, *((id_, v) for v in many)]
        for scale in (1.0, 1e5):
            df = spark.createDataFrame([(i, [x * scale for x in v]) for i, v in both], "vec_id long, embedding array<double>").coalesce(1)
            got = {(r["rank"], r["vec_id"], r["score"]) for r in search.top_k(df, df.where("vec_id = 0"), 5).collect()}
            scores = sorted({(-int(65536 * scale * scale) * int(v[0]), i) for i, v in both if i})[:5]
            assert got == {(n + 1, i, -s) for n, (s, i) in enumerate(scores)}


def test_queries_equal_their_sql(spark, sf):
    con = duckdb.connect()
    for t in ("documents", "conversations", "embeddings"):
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    for name, sql in queries.ORACLES.items():
        df = queries.QUERIES[name](spark, sf)
        want = con.sql(sql)
        cols = sorted(df.columns)
        assert cols == sorted(want.columns), name
        a = sorted(repr(tuple(r[c] for c in cols)) for r in df.collect())
        b = sorted(repr(r) for r in want.project(", ".join(cols)).fetchall())
        assert a == b, name


def test_pipeline(spark, sf):
    import corpus_pipeline
    from bitladder.llm.common import written

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    ids, rows = None, None
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = written(stage(spark, docs, sf), name)
        assert out.columns == docs.columns
        kept = {r["doc_id"] for r in out.collect()}
        assert ids is None or kept <= ids
        assert kept
        if name == "mix":
            assert kept == ids and out.count() == rows
        ids, rows, docs = kept, out.count(), out
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert {r["doc_id"] for r in pieces.select("doc_id").distinct().collect()} == ids
    assert corpus_pipeline.run(spark, sf).count() == pieces.count()


def plain_quality(text):
    """The quality rules once more, on strings, by other means than the library: (kept, cleaned text)."""
    import collections
    import re

    from bitladder.llm.quality import NOTICES

    space = " \t\n\r\x0b\x0c"
    words = [w for w in re.split(f"[{space}]+", text) if w]
    runs = collections.Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    hit = {i + k for i in range(len(words) - 7) if runs[tuple(words[i : i + 8])] > 1 for k in range(8)}
    good, lost, size = [], 0, 0
    for line in text.split("\n"):
        ws = [w for w in re.split(f"[{space}]+", line) if w]
        n = sum(len(w.encode()) for w in ws)
        bars = sum(w in ("|", "»", "›", "·", "•") for w in ws)
        low = "".join(c.lower() if c.isascii() else c for c in line)
        bad = bool(ws) and (
            (bars >= 2 and bars * 8 >= len(ws))
            or re.search(NOTICES, low) is not None
            or (len(ws) >= 4 and (ws[-1][-1] not in ".!?…\"'”’»):;。！？" or sum(c in "!?#*$%&<>" for c in line) * 2 > len(ws)))
        )
        size += n
        lost += n if bad else 0
        if not bad:
            good.append(line)
    return len(words) >= 20 and 100 * len(hit) <= 30 * len(words) and 2 * lost <= size, "\n".join(good)


def test_pipeline_brute_force(spark, sf):
    """Every stage against brute force, on what the one before kept."""
    import collections

    import corpus_pipeline
    from bitladder.llm.queries import vocabulary
    from tests.llm.test_documents import brute_classes, brute_lines, brute_slots, sha
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r["doc_id"], r["text"] or "") for r in docs.collect()]
    want = {i: text for i, t in rows for kept, text in (plain_quality(t),) if kept}
    one = corpus_pipeline.quality_rules(spark, docs, sf)
    assert {r["doc_id"]: r["text"] for r in one.collect()} == want
    two = corpus_pipeline.line_dedup(spark, one, sf)
    brute = brute_lines(sorted(want.items()))
    got = {r["doc_id"]: r["text"] for r in two.collect()}
    assert all(sha(t.encode()) == brute[i][2] for i, t in got.items())
    assert all(i in got or brute[i][1] > 0 for i in want)
    three = corpus_pipeline.written(corpus_pipeline.near_dedup(spark, two, sf), "three")
    classes = brute_classes(sorted(got.items()))
    kept = three.collect()
    assert {r["doc_id"] for r in kept} == {i for i, c in classes.items() if i == c}
    # the mixture: brute-force slots over documents in the order of their ids' hashes
    hashes = {r["doc_id"]: r["h"] for r in three.select("doc_id", F.xxhash64("doc_id").alias("h")).collect()}
    mine = collections.defaultdict(list)
    for r in sorted(kept, key=lambda r: hashes[r["doc_id"]]):
        mine[r["source"]].append(r["doc_id"])
    names = sorted(mine, key=lambda s: (s is not None, s or ""))
    order = [d for i, block, _ in brute_slots([-(-len(mine[s]) // 8) for s in names], [float(len(mine[s])) ** 0.5 for s in names]) for d in mine[names[i]][8 * block : 8 * block + 8]]
    four = corpus_pipeline.mix_sources(spark, three, sf)
    assert [r["doc_id"] for r in four.collect()] == order
    # packing: a round trip of every document's ids, and sequences that rise with the mixture
    library = Tokenizer.from_file(vocabulary())
    pieces = corpus_pipeline.pack_sequences(spark, corpus_pipeline.written(four, "four"), sf).collect()
    texts = {r["doc_id"]: r["text"] for r in kept}
    total = collections.Counter()
    for p in pieces:
        total[p["doc_id"]] += p["length"]
    assert total == {i: len(library.encode(t, add_special_tokens=False).ids) + 1 for i, t in texts.items()}
    place, first = {d: k for k, d in enumerate(order)}, {}
    for p in pieces:
        first.setdefault(p["sequence_id"], []).append(place[p["doc_id"]])
    means = [sum(x) / len(x) for _, x in sorted(first.items())]
    assert all(x < y + corpus_pipeline.POOL_DOCS for x, y in zip(means, means[1:], strict=False))


def test_stages_on_awkward_rows(spark):
    """Nulls in every column, empty and long texts, repeated rows, clashing names, and an empty table, through all stages."""
    import corpus_pipeline

    good = "A plain sentence of many words stands right here, and it ends as it should. " * 4
    texts = [None, "", " \n ", good, good, good + "And one more.", "x" * 50000, " ".join(f"w{i}" for i in range(30000)) + ".", "© 2020 x\n" + "\n".join(f"Line number {i} of this text says {i * i} things, and ends." for i in range(30))]
    rows = [(i if i != 4 else None, t, None if i == 5 else "en", None if i % 2 else "s", None if i == 3 else len(t or ""), True, "clash", 1) for i, t in enumerate(texts)]
    rows += [rows[3], rows[8], (None, None, None, None, None, None, None, None)]
    wide = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, _text string, n_words long"
    for df in (spark.createDataFrame(rows, wide).repartition(3), spark.createDataFrame([], wide)):
        docs, empty = df, df.isEmpty()
        for name, stage in corpus_pipeline.STAGES:
            alone = stage(spark, df, "")  # each stage on the rows as they are
            assert (alone.count() == 0) == empty
            docs = corpus_pipeline.written(stage(spark, docs, ""), name)
            assert name == "pack" or docs.columns == list(corpus_pipeline.COLUMNS)
        assert (docs.count() == 0) == empty


def test_near_stage_of_rows_without_id(spark):
    import corpus_pipeline
    from bitladder.llm import near

    a, b, c, d = (" ".join(f"{x}{i}" for i in range(60)) for x in "abcd")
    texts = [(None, a), (5, a), (6, a + " end"), (None, b), (7, b), (None, c), (None, c), (None, c + " end"), (8, d), (None, ""), (None, ""), (9, None)]
    df = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in texts], "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    kept = [(r["doc_id"], r["text"]) for r in corpus_pipeline.near_dedup(spark, df, "").collect()]
    third = [x for x in kept if x[1] and x[1].startswith("c")]
    assert len(third) == 1 and third[0][1] in (c, c + " end")
    kept.remove(third[0])
    assert sorted(kept, key=repr) == sorted([(None, a), (None, b), (8, d), (None, ""), (None, ""), (9, None)], key=repr)
    got = sorted(((r["doc_id"], r["class_id"], r["in_class"]) for r in near.near_duplicates(df).collect()), key=repr)
    want = [(None, None, True)] * 5 + [(i, None, True) for i in (5, 6, 7)] + [(None, None, False)] * 2 + [(8, 8, False), (9, 9, False)]
    assert got == sorted(want, key=repr)
