"""Document operators against brute force, on awkward rows."""

import collections
import hashlib
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitladder.llm import common, lines, mixing, near, packing, quality, suffix, tokens, windows
from bitladder.llm.queries import vocabulary

BASE = "the quick brown fox jumps over the lazy dog while seven wizards brew a very potent potion near old stone bridges and " * 3
LONG = " ".join(f"w{i % 977}x{i // 7}" for i in range(6000))
TEXTS = [
    None,
    "",
    " \t\n ",
    "one",
    BASE,
    BASE,
    BASE + "tail words here.",
    "head " + BASE,
    LONG,
    "x" * 700,
    "x" * 700 + "y",
    "Common line of text.\nUnique alpha line here.\n  COMMON line of text.  \nshort",
    "common LINE of text.\nanother line, not shared\n\n",
    "a | b | c | d\nHome | About | Contact",
    "naïve Straße 東京 it's <|endoftext|> \x01 \x1c odd space x",
    "ab " * 300,
    "é" * 60 + " " + "é" * 60,
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "src0" if i % 3 else None, len(t or ""), "clash", i) for i, t in enumerate(TEXTS)]
    rows.append((None, "a document without an id, long enough to hold a window of fifty bytes", "en", "s", 1, "clash", 0))
    rows.append(rows[4])  # a repeated row
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, tag string, pos long").repartition(3)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("false")


def sha(b: bytes) -> str:
    return hashlib.sha256(b).hexdigest()


def by_id(df):
    out = collections.defaultdict(list)
    for r in df.collect():
        out[r[0]].append(tuple(r[1:]))
    return {k: sorted(v, key=repr) for k, v in out.items()}


def order(i):
    return -(2**63) if i is None else i


def distinct_rows(docs):
    return sorted({(r["doc_id"], r["text"] or "") for r in docs.select("doc_id", "text").collect()}, key=lambda r: order(r[0]))


def test_token_counts(docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(vocabulary())
    got = by_id(tokens.count_tokens(docs, vocabulary()))
    for i, text in distinct_rows(docs):
        n = len(t.encode(text, add_special_tokens=False).ids)
        assert set(got[i]) == {(len(text.encode()), n, n > 2048)}
    assert len(got[4]) == 2


def test_quick_pieces_equal_the_library():
    m = tokens.PairMerger(vocabulary())
    for c in [*range(0x21, 0x250), 0x3A3, 0x130, 0x1F600, 0x4E2D]:
        s = f"a{chr(c)}1{chr(c)}'s"
        assert m.count(s.encode()) == len(m.library.encode(s, add_special_tokens=False).ids)


def test_pair_merger_on_a_byte_vocabulary():
    m = tokens.PairMerger(vocabulary("byte_bpe_50k.json"))
    for s in ("Hello  world", "a\n\nb", "naïve 東京", ""):
        assert m.count(s.encode()) == len(m.library.encode(s, add_special_tokens=False).ids)


def test_packing_round_trip(docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(vocabulary())
    pieces = packing.pack(docs, vocabulary(), pool_docs=4).collect()
    want = collections.Counter()
    for r in docs.collect():
        want[(r["doc_id"], tuple([*t.encode(r["text"] or "", add_special_tokens=False).ids, 1]))] += 1
    by_doc = collections.defaultdict(list)
    for p in pieces:
        by_doc[p["doc_id"]].append(p)
    for (i, ids), n in want.items():
        total = sum(p["length"] for p in by_doc[i])
        assert total == n * len(ids) and all(p["doc_tokens"] == len(ids) for p in by_doc[i])
        for p in by_doc[i]:
            assert np.frombuffer(p["ids"], "<u4").tolist() == list(ids[p["start"] : p["start"] + p["length"]])
    sequences = collections.defaultdict(list)
    for p in pieces:
        sequences[p["sequence_id"]].append(p)
    for seq in sequences.values():
        at = 0
        for p in sorted(seq, key=lambda p: p["offset"]):
            assert p["offset"] == at
            at += p["length"]
        assert at <= 2048
    short = [s for s in sequences.values() if sum(p["length"] for p in s) < 2048]
    assert len(short) <= docs.rdd.getNumPartitions()


def test_best_fill_is_the_best():
    rng = np.random.default_rng(0)
    for _ in range(200):
        lengths = collections.Counter(rng.integers(1, 40, 6).tolist())
        room = int(rng.integers(1, 90))
        sums = {0}
        for k, n in lengths.items():
            for _ in range(n):
                sums |= {s + k for s in sums if s + k <= room}
        got = packing.best_fill(sorted(((k, n) for k, n in lengths.items() if k <= room), reverse=True), room)
        assert sum(k * n for k, n in got.items()) == max(sums) and all(n <= lengths[k] for k, n in got.items())


def brute_lines(rows):
    keys = collections.defaultdict(set)
    split = {}
    for i, text in rows:
        ls = [(x, x.strip(lines.SPACE).lower()) for x in text.encode().split(b"\n")]
        split[i, text] = ls
        for _, k in ls:
            if len(k.decode()) >= 10:
                keys[k].add(order(i))
    out = {}
    for (i, text), ls in split.items():
        kept = [x for x, k in ls if not (len(k.decode()) >= 10 and len(keys[k]) > 1 and min(keys[k]) < order(i))]
        out[i] = (len(ls), len(ls) - len(kept), sha(b"\n".join(kept)))
    return out


def test_line_dedup(docs):
    got = by_id(lines.dedup_lines(docs, keep=("tag", "pos")).select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256)))
    assert {i: set(v) for i, v in got.items()} == {i: {v} for i, v in brute_lines(distinct_rows(docs)).items()}


def test_stream_first_across_batches():
    import pyarrow as pa

    h, d = [1, 1, 1, 2, 2, 3], [5, 5, 7, 1, 2, 9]
    whole = pa.RecordBatch.from_pydict({"h1": h, "h2": h, "doc": d})
    flags = [f for n in range(6) for _, x in lines.stream_first([whole.slice(n, 1)]) for f in x]
    assert not any(flags)  # one row alone is always first
    flags = [f for _, x in lines.stream_first([whole.slice(0, 2), whole.slice(2, 2), whole.slice(4, 2)]) for f in x]
    assert flags == [False, False, True, False, True, False]


def brute_spans(rows, w=50):
    first = {}
    for i, text in rows:
        b = text.encode()
        for k in range(len(b) - w + 1):
            first.setdefault(b[k : k + w], order(i))
    out = {}
    for i, text in rows:
        b = text.encode()
        gone = bytearray(len(b))
        for k in range(len(b) - w + 1):
            if first[b[k : k + w]] != order(i):
                gone[k : k + w] = b"\1" * w
        runs = sum(1 for k, x in enumerate(gone) if x and (k == 0 or not gone[k - 1]))
        out[i] = (len(b), sum(gone), runs, sha(bytes(c for c, x in zip(b, gone, strict=True) if not x)))
    return out


def test_span_dedup(docs):
    out = suffix.dedup_spans(docs)
    got = by_id(out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256)))
    assert {i: set(v) for i, v in got.items()} == {i: {v} for i, v in brute_spans(distinct_rows(docs)).items()}
    for r in out.collect():
        assert r["n_removed"] == sum(b - a for a, b in zip(r["span_starts"], r["span_ends"], strict=True))


def test_difference_cover_and_suffix_order():
    for p in (3, 7, 13):
        d = suffix.difference_cover(p)
        assert {(a - b) % p for a in d for b in d} == set(range(p))
    rng = np.random.default_rng(1)
    for alphabet, n in ((2, 900), (26, 300), (1, 200)):
        text = rng.integers(97, 97 + alphabet, n).astype(np.uint8)
        text[n // 2 : n // 2 + 90] = text[:90]
        data = np.concatenate([text, np.zeros(66, np.uint8)])
        starts = np.arange(n - 50)
        ranks = suffix.CoverRanks(data, 50)
        seen = []
        for block in suffix.leading_blocks(data, starts, 64):
            order, number = suffix.sorted_ties(data, block, ranks)
            tails = [data[i : i + 50].tobytes() for i in order]
            assert tails == sorted(tails)
            new = suffix.prefix_classes(data, order, number, 50)
            assert [t != u for t, u in zip(tails[1:], tails, strict=False)] == new[1:].tolist()
            seen += block.tolist()
        assert sorted(seen) == starts.tolist()


def brute_windows(rows, w=20):
    first, out = {}, {}
    for i, text in rows:
        ws = text.encode().split()
        for k in range(len(ws) - w + 1):
            first.setdefault(tuple(ws[k : k + w]), (order(i), k))
    for i, text in rows:
        ws = text.encode().split()
        gone = [False] * len(ws)
        for k in range(len(ws) - w + 1):
            if first[tuple(ws[k : k + w])] != (order(i), k):
                gone[k : k + w] = [True] * w
        out[i] = (len(ws), sum(gone), sha(b" ".join(x for x, g in zip(ws, gone, strict=True) if not g)))
    return out


@pytest.mark.parametrize("start", [None, 5, 20])
def test_window_dedup(docs, start):
    got = by_id(windows.dedup_windows(docs, 20, start).select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256)))
    assert {i: set(v) for i, v in got.items()} == {i: {v} for i, v in brute_windows(distinct_rows(docs)).items()}


def brute_classes(rows, threshold=0.8):
    bags = {}
    for i, text in rows:
        w = text.encode().split()
        bags[i] = collections.Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else collections.Counter()
    n = len(rows)
    df = collections.Counter(s for b in bags.values() for s in b)
    idf = {s: 1 + math.log((1 + n) / (1 + c)) / math.log(1 + n) for s, c in df.items()}
    up = {i: i for i, _ in rows}

    def root(x):
        return x if up[x] == x else root(up[x])

    ids = [i for i, _ in rows]
    for p, a in enumerate(ids):
        for b in ids[:p]:
            common = sum(min(bags[a][s], bags[b][s]) * idf[s] for s in bags[a] if s in bags[b])
            whole = sum(max(bags[a][s], bags[b][s]) * idf[s] for s in bags[a] | bags[b])
            if whole and common / whole >= threshold:
                x, y = sorted((root(a), root(b)), key=order)
                up[y] = x
    return {i: root(i) for i in ids}


def test_near_duplicates(docs, spark):
    once = docs.dropDuplicates(["doc_id"])
    got = {r["doc_id"]: r["class_id"] for r in near.near_duplicates(once).collect()}
    assert got == brute_classes(distinct_rows(docs))
    again = near.near_duplicates(docs).collect()
    assert len(again) == docs.count() and {r["doc_id"]: r["class_id"] for r in again} == got


def test_samples_do_not_depend_on_tiles():
    rng = np.random.default_rng(7)
    heads = np.array([0, 1, 40, 41, 300, 700])
    key = rng.integers(0, 2**64, 900, np.uint64)
    key[300:400], weight = key[500:600], rng.integers(1, 4, 900) * (1.0 + rng.random(900))
    whole = near.signatures(key, weight, heads)
    for tile in (1, 64, 300, 899):
        assert (near.signatures(key, weight, heads, tile) == whole).all()
    ends = [*heads[1:], 900]
    alone = [near.signatures(key[a:b], weight[a:b], np.array([0]))[0] for a, b in zip(heads, ends, strict=True)]
    assert (np.stack(alone) == whole).all()
    # equal draws agree as often as the weighted similarity says
    k, w = np.arange(1, 401, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15), np.ones(400)
    draws = [[near.sample(x, np.zeros(360), np.array([0]), np.array([360]), d)[0] for d in range(600)] for x in (k[:360], k[40:])]
    assert abs(np.mean([a == b for a, b in zip(*draws, strict=True)]) - 320 / 400) < 0.06
    assert (near.signatures(k, w, np.array([0])) == near.signatures(k[::-1].copy(), w, np.array([0]))).all()


def test_shingles_by_document():
    texts = ["a b c d e f a b c d e", "one two", "", "a b c d e f", "z " * 30, "one two three"]
    lens = np.array([len(t) for t in texts], np.int64)
    blob = "".join(texts).encode()
    ids = np.array([9, 3, 5, -4, 7, 1], np.int64)
    import pyarrow as pa

    row = {"chunk_id": 0, "ids": ids.tobytes(), "lens": lens.tobytes(), "blob": pa.compress(blob, codec="zstd", asbytes=True), "n_bytes": len(blob)}
    s = near.Shingles(common.Chunk(row), 5)
    for i, t in zip(ids, texts, strict=True):
        w = t.split()
        of = collections.Counter(tuple(w[j : j + 5]) for j in range(max(len(w) - 4, min(len(w), 1))))
        assert sorted(s.tf[s.ids == i].tolist()) == sorted(of.values())
        assert len(set(s.key[s.ids == i].tolist())) == len(of)
    assert (np.diff(np.flatnonzero(np.diff(s.ids, prepend=2**62))) > 0).all() and len(set(s.ids.tolist())) == 1 + np.count_nonzero(np.diff(s.ids))
    assert sorted(s.df.tolist(), reverse=True)[:2] == [2, 2]


def test_near_duplicates_in_a_group_of_several_blocks(spark, monkeypatch):
    monkeypatch.setattr(near, "GROUP", 4)
    rng = np.random.default_rng(2)
    base = [f"t{i}" for i in range(120)]
    rows = []
    for i in range(30):
        words = list(base)
        for k in rng.integers(0, 120, i % 4):
            words[k] = f"e{i}_{k}"
        rows.append((i, " ".join(words)))
    got = {r["doc_id"]: r["class_id"] for r in near.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute_classes(rows)


def test_near_duplicates_of_a_large_group_in_several_parts(spark, monkeypatch):
    """Two families and loners that a popular band ties: blocks, heads, and what is left."""
    monkeypatch.setattr(near, "GROUP", 4)
    rng, rows = np.random.default_rng(5), []
    for family in range(2):
        base = [f"f{family if k >= 40 else 0}t{k}" for k in range(120)]
        for i in range(20):
            text = list(base)
            for k in rng.integers(60, 120, i % 5):
                text[k] = f"e{family}_{i}_{k}"
            rows.append((100 * family + i, " ".join(text)))
    rows += [(300 + i, " ".join(f"f0t{k}" if k < 50 else f"l{i}_{k}" for k in range(120))) for i in range(6)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    rows_, _ = near.keyed(df)
    store = near.written(near.vectors(rows_, 5, 0.1), "store")
    groups = store.select("doc", F.lit(0).cast("long").alias("class"))  # one candidate group of all
    assert groups.count() > 40
    found = {r["doc"]: r["class"] for r in near.with_roots(near.components(near.linked(groups, store, 0.8))).collect()}
    want = brute_classes(rows)
    assert {i: found.get(i, i) for i in want} == want


def test_near_duplicates_of_ids_with_several_texts(spark):
    """Every text of a repeated id is looked at, wherever its rows lie."""
    a, b, c = (" ".join(f"{x}{k}" for k in range(60)) for x in "abc")
    rows = [(1, a), (1, b), (2, a + " more"), (3, b), (3, b), (4, c), (None, c), (None, a + " end")]
    for parts in (1, 8):
        df = spark.createDataFrame(rows, "doc_id long, text string").repartition(parts)
        got = {(r["doc_id"], r["class_id"], r["in_class"]) for r in near.near_duplicates(df).collect()}
        assert got == {(1, None, True), (2, None, True), (3, None, True), (4, None, True), (None, None, True)}
        got = {(r["doc_id"], r["class_id"]) for r in near.near_duplicates(df.where("doc_id is not null")).collect()}
        assert got == {(1, 1), (2, 1), (3, 1), (4, 4)}


def test_hot_keys_are_looked_up_like_others(spark, monkeypatch):
    monkeypatch.setattr(near, "HOT", 4)
    monkeypatch.setattr(near, "GROUP", 8)
    rows = spark.range(100).select(F.col("id").alias("x"), F.when(F.col("id") < 60, 0).otherwise(F.col("id") % 30).alias("k"))
    found = rows.groupBy("k").agg(F.min("x").alias("least"), F.count("*").alias("n")).where("n > 1")
    got = sorted(tuple(r) for r in near.looked_up(rows, found, "k", 100).select("x", "k", "least").collect())
    assert got == sorted(tuple(r) for r in rows.join(found, "k").select("x", "k", "least").collect())


def test_components_go_on_until_nothing_changes(spark, monkeypatch):
    """Steps that are held back for more than 30 rounds."""
    real, calls = near.written, []
    held = [spark.createDataFrame(e, "a long, b long").coalesce(1) for e in ([(1, 0), (2, 1), (3, 2)], [(1, 0), (2, 1), (3, 1)])]

    def slow(df, name):
        calls.append(name)
        return held[len(calls) % 2] if len(calls) <= 34 else real(df, name)

    monkeypatch.setattr(near, "written", slow)
    assert {(r["doc"], r["class"]) for r in near.components(held[0]).collect()} == {(1, 0), (2, 0), (3, 0)}
    assert len(calls) > 34


def test_similar_pairs_counts_repeats():
    def vec(counts):
        keys = np.array(sorted(counts), np.uint64)
        return keys.tobytes(), np.array([counts[int(k)] for k in keys], np.uint32).tobytes(), np.ones(len(keys), np.float32).tobytes()

    a, b, c = vec({1: 4, 2: 1}), vec({1: 3, 2: 1}), vec({1: 1, 3: 1})
    k, t, i = zip(a, b, c, strict=True)
    assert list(near.similar_pairs(list(k), list(t), list(i), 0.8)) == [(0, 1)]


def test_quality_rules(docs):
    got = {r["doc_id"]: r for r in quality.clean(docs, keep=("tag", "pos")).collect()}
    assert got[0]["base_failed"] and got[0]["n_words"] == 0 and got[1]["clean_text"] == ""
    assert not got[8]["base_failed"] and not got[8]["kept"]  # one line without an ending
    assert got[13]["n_symbols"] == 5 and got[13]["n_failed_lines"] == 2
    assert got[15]["base_failed"] and got[15]["n_repeat_words"] == 300
    assert got[11]["n_dup_lines"] == 0
    good = "A plain sentence of ten words stands here, and it ends well.\n" * 1 + "Another one follows it directly, with quite different words in it.\nWe use cookies."
    r = quality.judge(good.encode())
    assert r[6] and r[7] == 1 and b"cookies" not in r[9]


def test_repeat_words_brute():
    rng = np.random.default_rng(3)
    for _ in range(60):
        ws = [b"%d" % x for x in rng.integers(0, 3, 40)]
        seen = collections.Counter(tuple(ws[k : k + 8]) for k in range(33))
        hit = {k + j for k in range(33) if seen[tuple(ws[k : k + 8])] > 1 for j in range(8)}
        assert quality.repeat_words(ws) == len(hit)


def test_schedule_is_fair():
    from fractions import Fraction

    rng = np.random.default_rng(4)
    for _ in range(20):
        parts = rng.integers(1, 30, int(rng.integers(1, 9))).tolist()
        length = sum(parts)
        seq = mixing.period_schedule(parts, length)
        assert collections.Counter(seq) == collections.Counter(dict(enumerate(parts)))
        assert mixing.lag_bound(seq * 2, [Fraction(p, length) for p in parts]) < 1


def test_long_schedules_keep_their_exact_targets():
    """Against the weights as given, which no short period holds."""
    from fractions import Fraction

    for weights, blocks in (([n**0.5 for n in range(1, 21)], [4000 + 40 * n for n in range(20)]), ([1e-5, 0.3, 0.69999], [2, 9000, 21000])):
        parts = mixing.whole_parts(weights)
        assert all(p * Fraction(weights[0]) == parts[0] * Fraction(w) for p, w in zip(parts, weights, strict=True))
        got = list(mixing.slots(blocks, parts))
        assert [x[3] for x in got] == list(range(sum(blocks)))
        assert all(release <= slot < deadline for _, _, _, slot, release, deadline in got)
        assert collections.Counter(x[0] for x in got) == collections.Counter(dict(enumerate(blocks)))
        done, have, start, live, phase = [0] * len(blocks), [0] * len(blocks), 0, sum(parts), 0
        for s, block, ph, slot, _, _ in got:
            if ph != phase:
                phase, start, have = ph, slot, [0] * len(blocks)
                live = sum(p for p, d, b in zip(parts, done, blocks, strict=True) if d < b)
            assert block == done[s]
            done[s] += 1
            have[s] += 1
            t = slot + 1 - start
            assert all(abs(h * live - p * t) < live for h, p, d, b in zip(have, parts, done, blocks, strict=True) if d < b or h)


def test_mixing_keeps_targets_over_many_blocks(spark):
    d = spark.range(60000).select(F.concat(F.lit("s"), F.col("id") % 3).alias("source"), F.col("id").alias("doc_id"))
    target = {"s0": 0.33321, "s1": 0.33337, "s2": 0.33342}  # less than a 4096th apart
    out = mixing.schedule(d, weights=target, block_docs=1).where("phase = 0").select("source", "slot").orderBy("slot").collect()
    names = sorted(target)
    whole = mixing.whole_parts([target[s] for s in names])
    from fractions import Fraction

    assert len(out) > 50000 and mixing.lag_bound([names.index(r["source"]) for r in out], [Fraction(p, sum(whole)) for p in whole]) < 1


def brute_slots(blocks, weights):
    """Every slot by looking at all sources: earliest deadline among the released, with fractions."""
    from fractions import Fraction

    w, out, done, slot = [Fraction(x) for x in weights], [], [0] * len(blocks), 0
    while any(d < b for d, b in zip(done, blocks, strict=True)):
        live = [i for i, b in enumerate(blocks) if done[i] < b]
        share = {i: w[i] / sum(w[j] for j in live) for i in live}
        have, start = dict.fromkeys(live, 0), slot
        while all(done[i] < blocks[i] for i in live):
            ready = [(math.ceil((have[i] + 1) / share[i]), -w[i], i) for i in live if math.floor(have[i] / share[i]) <= slot - start]
            i = min(ready)[2]
            out.append((i, done[i], slot))
            have[i], done[i], slot = have[i] + 1, done[i] + 1, slot + 1
    return out


def test_slots_equal_brute_force():
    rng = np.random.default_rng(7)
    for _ in range(12):
        n = int(rng.integers(1, 8))
        weights, blocks = (rng.random(n) + 0.01).tolist(), rng.integers(0, 60, n).tolist()
        got = [(s, b, t) for s, b, _, t, _, _ in mixing.slots(blocks, mixing.whole_parts(weights))]
        assert got == brute_slots(blocks, weights)


def test_mixing_query_equals_brute_force(spark, sf):
    """The registered query, with its unequal weights, against brute-force slots and an order of its own."""
    from bitladder.llm import queries

    rows = spark.read.parquet(f"{sf}/documents.parquet").select("source", "doc_id", F.xxhash64("doc_id").alias("h")).collect()
    names = sorted({r["source"] for r in rows}, key=lambda s: (s is not None, s or ""))
    mine = {s: sorted(((r["h"], r["doc_id"]) for r in rows if r["source"] == s)) for s in names}
    weights = mixing.falling(names)
    blocks = [-(-len(mine[s]) // 8) for s in names]
    want = {}
    for i, block, slot in brute_slots(blocks, [weights[s] for s in names]):
        for k, (_, doc) in enumerate(mine[names[i]][8 * block : 8 * block + 8]):
            want[doc] = (names[i], 8 * block + k, block, slot, 8 * slot + k)
    got = {r["doc_id"]: (r["source"], r["seq"], r["block"], r["slot"], r["position"]) for r in queries.op1_mix_sources(spark, sf).collect()}
    assert got == want and len({weights[s] for s in names}) > 1


def test_kept_columns_of_clashing_names(spark):
    text = "A plain sentence of many words stands right here, and it ends well. " * 3
    df = spark.createDataFrame([(1, text, 7, "x", True, "y", 3, "z")], "doc_id long, text string, n_words long, _text string, kept boolean, kept_text string, n_lines long, _doc string")
    r = quality.clean(df, keep=("n_words", "_text", "kept", "clean_text") if "clean_text" in df.columns else ("n_words", "_text", "kept")).first()
    assert (r["in_n_words"], r["_text"], r["in_kept"]) == (7, "x", True) and r["n_words"] == 39
    r = lines.dedup_lines(df, keep=("kept_text", "n_lines", "_doc", "_text")).first()
    assert (r["in_kept_text"], r["in_n_lines"], r["_doc"], r["_text"]) == ("y", 3, "z", "x") and r["kept_text"] == text


def test_long_texts(spark):
    """A hundred thousand words, with passages that repeat inside and elsewhere."""
    rng = np.random.default_rng(8)
    words = [f"v{x}" for x in rng.integers(0, 50000, 100_000)]
    words[70_000:70_100] = words[10_000:10_100]
    rows = [(1, " ".join(words)), (2, " ".join(words[500:700])), (3, " ".join(words[99_000:]))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = by_id(suffix.dedup_spans(df).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256)))
    assert {i: set(v) for i, v in got.items()} == {i: {v} for i, v in brute_spans(rows).items()}
    got = by_id(windows.dedup_windows(df, 20).select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256)))
    assert {i: set(v) for i, v in got.items()} == {i: {v} for i, v in brute_windows(rows).items()}


def test_notices_in_any_language():
    for line in ("© 2021 Firma", "(c) 1999 someone", "Alle Rechte vorbehalten", "Conditions d'utilisation", "Todos los derechos reservados", "See https://x.org/license here"):
        assert quality.line_fails(line.encode()) == "boilerplate"
    assert not quality.line_fails("Die Katze sitzt auf der Matte und schläft.".encode())


def test_mixing_of_more_than_4096_sources(spark):
    d = spark.range(12000).select(F.concat(F.lit("host"), F.col("id") % 5000).alias("source"), F.col("id").alias("doc_id"))
    out = mixing.schedule(d, block_docs=2).collect()
    assert sorted(r["doc_id"] for r in out) == list(range(12000)) and len({r["position"] for r in out}) == 12000
    assert sorted({(r["slot"], r["source"], r["block"]) for r in out}) == sorted((n, s, b) for n, (s, b) in enumerate(x[1:] for x in sorted({(r["slot"], r["source"], r["block"]) for r in out})))
    assert all(r["release"] <= r["slot"] < r["deadline"] for r in out)


def test_mixing(docs, spark):
    rows = [(f"s{i % 7 % 3}", i) for i in range(400)] + [(None, 1000), (None, 1000)]
    d = spark.createDataFrame(rows, "source string, doc_id long").withColumn("text", F.lit("t"))
    out = mixing.schedule(d, block_docs=2, resolution=64).collect()
    assert len(out) == len(rows)
    assert len({r["position"] for r in out}) == len(rows)
    blocks = {}
    for r in out:
        blocks.setdefault((r["source"], r["block"]), r)
        assert r["release"] <= r["slot"] < r["deadline"]
    assert sorted(b["slot"] for b in blocks.values()) == list(range(len(blocks)))
    for s in {r["source"] for r in out}:
        mine = sorted((r for r in out if r["source"] == s), key=lambda r: r["position"])
        assert [r["seq"] for r in mine] == list(range(len(mine)))
    assert mixing.mixed_documents(docs).count() == docs.count()
    assert mixing.mixed_documents(docs).columns == docs.columns
    weighted = mixing.schedule(d, weights={"s0": 0.9}, block_docs=1, resolution=100)
    first = weighted.where("slot < 50").groupBy("source").count().collect()
    assert {r["source"]: r["count"] for r in first}["s0"] in (44, 45, 46)


def test_empty_tables(empty, spark):
    assert tokens.count_tokens(empty, vocabulary()).count() == 0
    assert packing.pack(empty, vocabulary()).count() == 0
    assert quality.clean(empty).count() == 0
    assert lines.dedup_lines(empty).count() == 0
    assert suffix.dedup_spans(empty).count() == 0
    assert windows.dedup_windows(empty).count() == 0
    assert near.near_duplicates(empty).count() == 0
    assert mixing.schedule(empty).count() == 0
    assert mixing.mixed_documents(empty).count() == 0


@pytest.fixture
def two_steps(monkeypatch):
    """Four coarse buckets, blocks of a few rows: what large inputs do."""
    monkeypatch.setattr(common, "DIRECT_BITS", 2)
    monkeypatch.setattr(common, "DEAL_BYTES", 5_000)


def test_numbered_parts_round_trip():
    for parts in ([], [(7, b"")], [(-3, b"abc"), (2**40, b""), (5, b"\0" * 9)]):
        assert list(common.unpacked(common.packed(parts))) == parts


def test_exchange_in_two_steps(docs, two_steps):
    many = docs.repartition(7).cache()  # one chunk for each
    got = by_id(suffix.dedup_spans(many).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256)))
    assert {i: set(v) for i, v in got.items()} == {i: {v} for i, v in brute_spans(distinct_rows(docs)).items()}
    for start in (None, 5):
        got = by_id(windows.dedup_windows(many, 20, start).select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256)))
        assert {i: set(v) for i, v in got.items()} == {i: {v} for i, v in brute_windows(distinct_rows(docs)).items()}
    once = docs.dropDuplicates(["doc_id"]).repartition(7)
    assert {r["doc_id"]: r["class_id"] for r in near.near_duplicates(once).collect()} == brute_classes(distinct_rows(docs))


def test_one_answer_for_each_chunk_and_coarse_bucket(spark, two_steps):
    rows = spark.range(40, numPartitions=5)

    def ask(batches):
        for batch in batches:
            for chunk in batch.column(0).to_pylist():
                yield common.requests_batch([(b, chunk, b"%d:%d" % (b, chunk)) for b in range(chunk % 3, 32, 3)], 3)

    answers = common.answered(rows.mapInArrow(ask, common.REQUEST), lambda blobs: [b"re " + b for b in blobs], 3)
    seen = [(r["chunk_id"], r["bucket"], list(common.unpacked(bytes(r["data"])))) for r in answers.collect()]
    assert len(seen) == len({s[:2] for s in seen}) == 40 * 4
    assert all(coarse < 0 and {b >> 3 for b, _ in own} == {-1 - coarse} for _, coarse, own in seen)
    assert {(chunk, b): d for chunk, _, own in seen for b, d in own} == {(c, b): b"re %d:%d" % (b, c) for c in range(40) for b in range(c % 3, 32, 3)}
