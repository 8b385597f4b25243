"""Two-sided convolutional text encoder: windows, affine map, tanh, max-pool.

A window's counts are the sum of its words' counts, so the affine map is taken
once for each distinct word and summed over the windows: the same values as on
sparse window vectors (``text.word_windows``), at a fraction of the work.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import norm_sq_expr, pack
from ..functions.text import words
from . import ladder


@dataclass
class SideParams:
    """One side: convolution (dims x m; None for vector inputs), hidden layers, ladder (None: real vectors)."""

    conv: np.ndarray | None
    ladder: ladder.LadderParams | None
    hidden: list[np.ndarray] = field(default_factory=list)

    def arrays(self) -> dict[tuple[str, int], np.ndarray]:
        """All parameters by (name, number)."""
        out = {} if self.conv is None else {("conv", 0): self.conv}
        out |= {("hidden", t): w for t, w in enumerate(self.hidden)}
        if self.ladder is not None:
            out["W", 0] = self.ladder.W
            out |= {("B", t): b for t, b in enumerate(self.ladder.B)} | {("R", t): r for t, r in enumerate(self.ladder.R)}
        return out


@dataclass
class TwoTower:
    """Separate parameters for the query side and the keyword side.

    ``vocab`` maps trigrams to ids below ``dims``; without one ids are hashes.
    """

    query: SideParams
    keyword: SideParams
    dims: int = 4096
    width: int = 3
    mode: str = "bag"
    vocab: dict[str, int] | None = None

    def side(self, name: str) -> SideParams:
        return getattr(self, name)


def init_tower(dims: int = 4096, m: int = 64, n: int = 64, depth: int = 2, seed: int = 0, width: int = 3, mode: str = "bag", k_depth: int | None = None, weighted: bool = True, hidden: int = 0, floats: tuple[bool, bool] = (False, False), vocab: dict[str, int] | None = None) -> TwoTower:
    """Random towers with equal sides; ``floats`` leaves out a side's ladder for one tanh layer of n."""
    rng = np.random.default_rng(seed)
    rows = dims * width if mode == "positions" else dims
    conv = rng.standard_normal((rows, m)) / np.sqrt(24.0)  # about as many trigrams in a window
    layers = [np.linalg.qr(rng.standard_normal((m, m)))[0] for _ in range(hidden)]
    depths = (depth, depth if k_depth is None else k_depth)
    base = ladder.init_orthogonal(m, n, max(depths), seed + 1, weighted=weighted)
    made = []
    for d, real in zip(depths, floats, strict=True):
        own = None if real else ladder.LadderParams(base.W.copy(), [b.copy() for b in base.B[:d]], [r.copy() for r in base.R[:d]], weighted)
        made.append(SideParams(conv.copy(), own, [w.copy() for w in layers] + ([base.W.copy()] if real else [])))
    return TwoTower(*made, dims, width, mode, vocab)


class WordIds(dict):
    """Word to the ids of its letter trigrams, as ``text.hash_ids`` gives them or by a vocabulary.

    Trigrams that a vocabulary lacks are left out.  Forgets everything when it
    grows too large.
    """

    def __init__(self, dims: int, vocab: dict[str, int] | None = None, limit: int = 200_000):
        self.dims, self.vocab, self.limit = dims, vocab, limit

    def __missing__(self, word: str) -> np.ndarray:
        from xxhash import xxh64_intdigest

        w = f"#{word}#"
        grams = [w[i : i + 3] for i in range(max(len(w) - 2, 1))]
        if self.vocab is not None:
            found = [self.vocab[g] for g in grams if self.vocab.get(g, self.dims) < self.dims]
        else:
            found = []
            for g in grams:
                h = xxh64_intdigest(g.encode(), 42)
                found.append((h - 2**64 if h >= 2**63 else h) % self.dims)
        ids = np.array(found, dtype=np.int64)
        if len(self) >= self.limit:
            self.clear()
        self[word] = ids
        return ids


@dataclass
class Words:
    """Texts as numbers of their distinct words, with the words' trigram ids under each setting (dims, vocabulary)."""

    lens: np.ndarray
    word: np.ndarray
    #: by the setting's number: trigram ids of all words, ids of each word, and the order of ids with their words
    ids: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)
    #: what all models of a block have in common, made at its first use
    plans: dict = field(default_factory=dict)

    def plan(self, setting: int) -> Runs:
        """How the trigrams of each word are added up."""
        if ("on", setting) not in self.plans:
            self.plans["on", setting] = Runs.of(*self.ids[setting][:2])
        return self.plans["on", setting]

    def plan_back(self, setting: int) -> tuple[np.ndarray, Runs]:
        """The trigram ids that occur, and how the words of each are added up."""
        if ("back", setting) not in self.plans:
            flat, sizes, order = self.ids[setting]
            ordered = flat[order]
            heads = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
            owner = np.repeat(np.arange(len(sizes), dtype=np.int32), sizes)[order]
            self.plans["back", setting] = ordered[heads].astype(np.int64), Runs.of(owner, np.diff(np.append(heads, len(owner))))
        return self.plans["back", setting]

    @classmethod
    def of(cls, texts: list, settings: list[WordIds]) -> Words:
        number: dict[str, int] = {}
        lens = np.array([len(t) for t in texts], dtype=np.int64)
        word = np.fromiter((number.setdefault(w, len(number)) for t in texts for w in t), np.int32, int(lens.sum()))
        return cls(lens, word, [trigrams(list(number), own) for own in settings])


def trigrams(names: list[str], ids: WordIds) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Trigram ids of words, how many each has, and the order of the ids by value."""
    lists = [ids[w] for w in names]
    flat = np.concatenate(lists).astype(np.int32) if lists else np.empty(0, np.int32)
    return flat, np.array([len(x) for x in lists], dtype=np.int32), np.argsort(flat, kind="stable").astype(np.int32)


@dataclass
class ConvTape:
    """What the way back through the convolution needs."""

    texts: Words
    setting: int
    at: np.ndarray
    pooled: np.ndarray


def segments(sizes: np.ndarray) -> np.ndarray:
    return np.cumsum(sizes) - sizes


def segment_sums(x: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Sums of consecutive runs of rows; runs may be empty."""
    out = np.zeros((len(sizes), *x.shape[1:]))
    some = sizes > 0
    if some.any():
        out[some] = np.add.reduceat(x, segments(sizes)[some], axis=0)
    return out


#: words whose windows are added up at once, and runs of rows and rows of one, so that the arrays stay in the cache
STRIP_WORDS, STRIP_RUNS, PIECE = 2048, 512, 32


@dataclass
class Runs:
    """Consecutive runs of row numbers, cut into pieces that lie in order of their lengths."""

    index: np.ndarray
    pieces: np.ndarray
    order: np.ndarray
    owner: np.ndarray
    length: np.ndarray
    begin: np.ndarray

    @classmethod
    def of(cls, index: np.ndarray, sizes: np.ndarray) -> Runs:
        sizes = sizes.astype(np.int64)
        pieces = -(-sizes // PIECE)
        owner = np.repeat(np.arange(len(sizes)), pieces)
        skip = PIECE * (np.arange(len(owner)) - segments(pieces)[owner])
        length = np.minimum(PIECE, sizes[owner] - skip)
        order = np.argsort(-length, kind="stable")
        return cls(index, pieces, order, owner[order], length[order], (segments(sizes)[owner] + skip)[order])


def run_sums(x: np.ndarray, runs: Runs, more: int = 0) -> np.ndarray:
    """Sums of the rows of ``x`` that runs name, added up side by side; empty runs, and ``more`` rows at the end, are zero."""
    m = x.shape[1]
    found, spare = np.empty((len(runs.order), m)), np.empty((STRIP_RUNS, m))
    for a in range(0, len(found), STRIP_RUNS):
        n, at, mine = runs.length[a : a + STRIP_RUNS], runs.begin[a : a + STRIP_RUNS], found[a : a + STRIP_RUNS]
        np.take(x, runs.index[at], axis=0, out=mine, mode="clip")
        for j in range(1, int(n[0])):
            k = int(np.searchsorted(-n, -j))  # pieces longer than j
            np.take(x, runs.index[at[:k] + j], axis=0, out=spare[:k], mode="clip")
            mine[:k] += spare[:k]
    out = np.zeros((len(runs.pieces) + more, m))
    if len(runs.pieces) and runs.pieces.max() > 1:
        whole = np.empty_like(found)
        whole[runs.order] = found
        out[: len(runs.pieces)] = segment_sums(whole, runs.pieces)
    else:
        out[runs.owner] = found
    return out


def text_strips(lens: np.ndarray):
    """Ranges of neighbouring texts of about ``STRIP_WORDS`` words."""
    start, ends = 0, np.cumsum(lens)
    while start < len(lens):
        end = max(start + 1, int(np.searchsorted(ends, (ends[start - 1] if start else 0) + STRIP_WORDS, "right")))
        yield start, end
        start = end


def conv_words(texts: Words, conv: np.ndarray, dims: int, width: int = 3, mode: str = "bag", setting: int = 0, taped: bool = True) -> tuple[np.ndarray, ConvTape | None]:
    """Max-pooled tanh windows of every text (zero for a text without words), and the tape.

    tanh rises, so it is taken of the largest window only.  Texts lie side by side
    with gaps of no word between them, so that a window's sum is a sum of slices.
    """
    sizes = texts.ids[setting][1]
    lens, m, half = texts.lens, conv.shape[1], width // 2
    by_place = [run_sums(conv[p * dims :], texts.plan(setting), 1) for p in (range(width) if mode == "positions" else (0,))]  # the last row: no word
    top, at, begin = np.zeros((len(lens), m)), np.zeros((len(lens), m), np.int64), segments(lens)
    for a, b in text_strips(lens):
        some = np.flatnonzero(lens[a:b] > 0) + a
        if not len(some):
            continue
        n, lo = lens[some], begin[some[0]]
        starts, text = segments(n + half), np.repeat(np.arange(len(some)), n)
        place = np.arange(len(text)) + half * text  # of each word among the windows
        padded = np.full(int(n.sum()) + half * (len(some) + 1), len(sizes))
        padded[place + half] = texts.word[lo : lo + len(text)]
        z = np.zeros((len(padded) - 2 * half, m))
        if mode != "positions":
            x = by_place[0][padded]
        for p in range(width):
            z += (by_place[p][padded[p : p + len(z)]] if mode == "positions" else x[p : p + len(z)])
        gap = np.ones(len(z), bool)
        gap[place] = False
        z[gap] = -np.inf
        top[some] = best = np.maximum.reduceat(z, starts, axis=0)
        if taped:
            row, dim = np.divmod(np.flatnonzero(z == np.repeat(best, n + half, axis=0)[: len(z)]), m)
            mine = np.repeat(np.arange(len(some)), n + half)[row]
            word = row - starts[mine] + begin[some][mine]
            at[some[mine][::-1], dim[::-1]] = word[::-1]  # the first of equal windows
    top = np.tanh(top)
    return top, ConvTape(texts, setting, at, top) if taped else None


def conv_forward(texts: list[list[str]], conv: np.ndarray, ids: WordIds, width: int = 3, mode: str = "bag", taped: bool = True) -> tuple[np.ndarray, ConvTape | None]:
    """``conv_words`` of texts given as lists of words."""
    return conv_words(Words.of(texts, [ids]), conv, ids.dims, width, mode, 0, taped)


def conv_backward(g: np.ndarray, tape: ConvTape, shape: tuple[int, int], dims: int, width: int = 3, mode: str = "bag") -> tuple[np.ndarray, np.ndarray]:
    """Rows of the convolution that have a gradient, and their gradients."""
    texts, (flat, sizes, _) = tape.texts, tape.texts.ids[tape.setting]
    some = texts.lens > 0
    if not some.any() or not len(flat):
        return np.empty(0, np.int64), np.empty((0, shape[1]))
    m, half = shape[1], width // 2
    begin, at = segments(texts.lens)[some], tape.at[some]
    end = begin + texts.lens[some]
    value = (g * (1.0 - tape.pooled**2))[some]
    dim = np.broadcast_to(np.arange(m), at.shape)
    ids, runs = texts.plan_back(tape.setting)
    rows, grads = [], []
    by_word = np.zeros(len(sizes) * m)
    for p in range(width):
        place = at + p - half
        inside = (place >= begin[:, None]) & (place < end[:, None])
        by_word += np.bincount(texts.word[place[inside]].astype(np.int64) * m + dim[inside], weights=value[inside], minlength=len(by_word))
        if mode == "positions" or p == width - 1:
            rows.append(ids + (p * dims if mode == "positions" else 0))
            grads.append(run_sums(by_word.reshape(-1, m), runs))
            by_word = np.zeros_like(by_word)
    return np.concatenate(rows), np.concatenate(grads)


def convolve(windows: list[list[dict]], conv: np.ndarray) -> np.ndarray:
    """tanh of every window's sparse counts times ``conv``: windows x m."""
    if not windows:
        return np.zeros((0, conv.shape[1]))
    idx = np.array([c["idx"] for w in windows for c in w], dtype=np.int64)
    cnt = np.array([c["cnt"] for w in windows for c in w])
    at = np.repeat(np.arange(len(windows)), [len(w) for w in windows])
    out = np.zeros((len(windows), conv.shape[1]))
    np.add.at(out, at, conv[idx] * cnt[:, None])
    return np.tanh(out)


def max_pool(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Largest value of each dimension over positions, and its position; zero if none."""
    if not len(x):
        return np.zeros(x.shape[1]), np.zeros(x.shape[1], dtype=np.int64)
    at = x.argmax(0)
    return x[at, np.arange(x.shape[1])], at


def dense_layers(f: np.ndarray, layers: list[np.ndarray]) -> np.ndarray:
    for w in layers:
        f = np.tanh(f @ w.T)
    return f


def text_vectors(texts: list[list[str]], side: SideParams, ids: WordIds, width: int = 3, mode: str = "bag") -> np.ndarray:
    """Pooled (and hidden-layer) vectors of texts given as lists of words."""
    return dense_layers(conv_forward(texts, side.conv, ids, width, mode, taped=False)[0], side.hidden)


#: words that one convolution takes at once; a longer text is a block of its own
BLOCK_WORDS = 1 << 16


def word_blocks(lists: list):
    """Ranges of neighbouring texts of about ``BLOCK_WORDS`` words."""
    start, size = 0, 0
    for i, t in enumerate(lists):
        if i > start and size + len(t) > BLOCK_WORDS:
            yield start, i
            start, size = i, 0
        size += len(t)
    if start < len(lists):
        yield start, len(lists)


def encode_texts(df: DataFrame, model: TwoTower, side: str, key: str, text: str = "text", depth: int | None = None, vectors: bool = False, keep_empty: bool = False) -> DataFrame:
    """Codes (or vectors ``f``) of texts: key, planes, norm_sq, is_empty.

    Words are cut by expressions, the dense part runs in one Arrow pass with the
    parameters broadcast.  Texts without words are left out unless ``keep_empty``.
    A side without a ladder gives vectors only.
    """
    spark = df.sparkSession
    params = model.side(side)
    if params.ladder is None and not vectors:
        raise ValueError("this side has no ladder: ask for vectors")
    sent = spark.sparkContext.broadcast((params, model.dims, model.vocab))
    width, mode = model.width, model.mode
    spec = None if params.ladder is None else params.ladder.spec(depth)
    source = df.select(F.col(key).cast("long").alias(key), words(F.col(text)).alias("w"))
    source = source if keep_empty else source.where(F.size("w") > 0)

    def run(batches):
        p, dims, vocab = sent.value
        ids = WordIds(dims, vocab)
        for batch in batches:
            for lo in range(0, batch.num_rows, 2048):
                part = batch.slice(lo, 2048)
                texts = [t or [] for t in part.column(1).to_pylist()]
                for a, b in word_blocks(texts):
                    f = text_vectors(texts[a:b], p, ids, width, mode)
                    own, empty = part.column(0).slice(a, b - a), pa.array([not t for t in texts[a:b]])
                    if vectors:
                        yield pa.RecordBatch.from_arrays([own, pa.array(list(f), pa.list_(pa.float64())), empty], [key, "f", "is_empty"])
                    else:
                        planes = [w for x in ladder.encode(f, p.ladder, depth) for w in pack(x).T]
                        yield pa.RecordBatch.from_arrays([own, *[pa.array(np.ascontiguousarray(w), pa.int64()) for w in planes], empty], [key, *spec.columns(), "is_empty"])

    if vectors:
        return source.mapInArrow(run, f"{key} long, f array<double>, is_empty boolean")
    out = source.mapInArrow(run, ", ".join([f"{key} long", *[f"{c} long" for c in spec.columns()], "is_empty boolean"]))
    return out.withColumn("norm_sq", norm_sq_expr(spec))


def encode_dense(df: DataFrame, models: dict[str, TwoTower], side: str, key: str, text: str = "text") -> DataFrame:
    """model, key, v: the real vectors (a ladder's code as real numbers) of texts under many models, in one pass."""
    sent = df.sparkSession.sparkContext.broadcast(models)
    source = df.select(F.col(key).cast("long").alias(key), words(F.col(text)).alias("w")).where(F.size("w") > 0)

    def run(batches):
        ids: dict = {}
        for batch in batches:
            for lo in range(0, batch.num_rows, 2048):
                part = batch.slice(lo, 2048)
                texts = part.column(1).to_pylist()
                for a, b in word_blocks(texts):
                    mine: dict = {}  # words of the block once for each setting
                    for name, model in sent.value.items():
                        at = (model.dims, id(model.vocab))
                        if at not in mine:
                            mine[at] = Words.of(texts[a:b], [ids.setdefault(at, WordIds(model.dims, model.vocab))])
                        p = model.side(side)
                        f = dense_layers(conv_words(mine[at], p.conv, model.dims, model.width, model.mode, taped=False)[0], p.hidden)
                        v = f if p.ladder is None else ladder.dense(ladder.encode(f, p.ladder), p.ladder.weighted)
                        yield pa.RecordBatch.from_arrays([pa.array([name] * (b - a)), part.column(0).slice(a, b - a), pa.array(list(v.astype(np.float64)), pa.list_(pa.float64()))], ["model", key, "v"])

    return source.mapInArrow(run, f"model string, {key} long, v array<double>")


def hashed_sum(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    """vec_id, embedding: the word-sum layer with fixed random word vectors, scaled to length one.

    A word's vector has a sign for each of 64 bits of its MD5; a text's vector is
    the sum over its words, so it needs no training, and SQL can compute it.
    """
    rows = df.select(F.col(key).cast("long").alias("vec_id"), words(F.col(text)).alias("w")).where(F.size("w") > 0)
    each = rows.select("vec_id", F.size("w").alias("n"), F.explode("w").alias("x")).select("vec_id", "n", digest_bits(F.md5("x")).alias("bits"))
    sums = each.groupBy("vec_id", "n").agg(*[F.sum(F.getbit("bits", F.lit(i)).cast("long")).alias(f"s{i}") for i in range(64)])
    v = F.array(*[(2 * F.col(f"s{i}") - F.col("n")).cast("double") for i in range(64)])
    unit = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    return sums.select("vec_id", v.alias("v")).withColumn("norm", unit).where("norm > 0").select("vec_id", F.transform("v", lambda x: x / F.col("norm")).alias("embedding"))


def digest_bits(digest):
    """The first 16 hex digits of a digest as a BIGINT."""
    high, low = (F.conv(F.substring(digest, at, 8), 16, 10).cast("long") for at in (1, 9))
    return F.shiftleft(high, 32).bitwiseOR(low)
