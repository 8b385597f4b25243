"""Joint training of encoder and ladder with a stand-in gradient for sign.

Each round is one job for any number of models: parameters are broadcast, every
partition sums the gradients of its groups, blocks of parameter rows are summed
by key, and the driver takes a step.  Sample groups arrive packed: ``q`` (one
input) and ``ks`` (positive first).  Inputs are real vectors (array<double>), or
lists of words when there is a convolution.  The driver holds parameters and one
gradient of their size, never samples.
"""

from __future__ import annotations

import copy
import itertools
import pickle
import tempfile
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import binarize, encoder, ladder, loss

#: parameter rows in one block of a gradient
BLOCK_ROWS = 1024
SCHEMA = "model string, side string, name string, t int, block int, data binary"


@dataclass
class Config:
    gamma: float = 10.0
    epochs: int = 5
    rate: float = 0.05
    surrogate: str = "clipped"
    growth: float = 1.05
    clip: float = 5.0
    optimizer: str = "sgd"
    seed: int = 0
    #: factor on pre-activations inside the stand-in gradient, where clipping acts
    reach: float = 1.0


@dataclass
class Fit:
    model: encoder.TwoTower
    history: list[dict] = field(default_factory=list)

    @property
    def converged(self) -> bool:
        """Finite throughout, and the mean of the last third below that of the first third by a fiftieth."""
        losses = [h["loss"] for h in self.history]
        third = max(1, len(losses) // 3)
        if not losses or not np.isfinite(losses).all():
            return False
        return float(np.mean(losses[-third:])) < 0.98 * float(np.mean(losses[:third]))

    @property
    def unsteady(self) -> float:
        """Largest rise from one epoch to the next, as a share of the first loss."""
        losses = [h["loss"] for h in self.history]
        rises = np.diff(losses)
        return float(max(0.0, rises.max(initial=0.0)) / losses[0]) if losses else 0.0


#: words of distinct texts, and groups, of one block
BLOCK_WORDS, BLOCK_GROUPS = 1 << 16, 4096


@dataclass
class Block:
    """Sample groups whose inputs are listed once: both sides' inputs, and each group's numbers in them.

    ``groups`` has for each number of keywords (queries, keywords, places in the block).
    """

    query: encoder.Words | np.ndarray
    keyword: encoder.Words | np.ndarray
    groups: list[tuple[np.ndarray, np.ndarray, np.ndarray]]
    #: tells blocks apart in what they draw
    key: int = 0


def block_of(qs: list, ks: list[list], settings: list, key: int = 0) -> Block:
    """A block of groups; ``settings`` are the word ids that models need (none: inputs are vectors)."""
    kind = pa.list_(pa.string() if settings else pa.float64())
    q, k = pa.array([list(x or ()) for x in qs], kind), pa.array([[list(x or ()) for x in group] for group in ks], pa.list_(kind))
    return block_of_arrays(q, k, settings, key)


def listed(lists: pa.Array, settings: list) -> tuple[encoder.Words | np.ndarray, np.ndarray]:
    """Distinct inputs of a column of lists, and each row's number among them."""
    lens, flat = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), lists.flatten()
    if settings:
        coded = flat.dictionary_encode()
        flat, names = coded.indices, coded.dictionary.to_pylist()
    x, ends, number = flat.to_numpy(zero_copy_only=False), np.cumsum(lens).tolist(), {}
    at = np.array([number.setdefault(x[a:b].tobytes(), len(number)) for a, b in zip([0, *ends[:-1]], ends, strict=True)], dtype=np.int64)
    parts = [np.frombuffer(k, x.dtype) for k in number]
    if not settings:
        return np.array(parts, dtype=np.float64), at
    sizes = np.array([len(p) for p in parts], dtype=np.int64)
    return encoder.Words(sizes, np.concatenate([*parts, x[:0]]).astype(np.int32), [encoder.trigrams(names, own) for own in settings]), at


def block_of_arrays(q: pa.Array, ks: pa.Array, settings: list, key: int = 0) -> Block:
    """``block_of`` from columns q (lists) and ks (lists of lists)."""
    (queries, qn), (keywords, kn) = listed(q, settings), listed(ks.flatten(), settings)
    sizes = ks.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    begin, groups = encoder.segments(sizes), []
    for m in np.unique(sizes).tolist():
        at = np.flatnonzero(sizes == m)
        groups.append((qn[at], kn[begin[at][:, None] + np.arange(m)], at))
    return Block(queries, keywords, groups, key)


def settings_of(models) -> tuple[list[tuple[int, dict | None]], dict[str, int]]:
    """The distinct (dims, vocabulary) of models with a convolution, and each model's number among them."""
    found, number = [], {}
    for name, model in models.items():
        if model.query.conv is not None:
            at = next((i for i, (dims, vocab) in enumerate(found) if dims == model.dims and vocab is model.vocab), None)
            number[name] = len(found) if at is None else at
            if at is None:
                found.append((model.dims, model.vocab))
    return found, number


def blocks_in(batches, settings: list):
    """Groups' ids and blocks of about ``BLOCK_WORDS`` words, or ``BLOCK_GROUPS`` groups, from batches of group_id, q and ks.

    Neighbours share keywords, so a group counts with its query and one keyword.
    """
    ids = [encoder.WordIds(*x) for x in settings]
    for batch in batches:
        key, q, ks = (batch.column(batch.schema.get_field_index(c)) for c in ("group_id", "q", "ks"))
        inner, sizes = ks.flatten().value_lengths().fill_null(0).to_numpy(zero_copy_only=False), ks.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        mean = encoder.segment_sums(inner[:, None].astype(np.float64), sizes)[:, 0] / np.maximum(sizes, 1)
        words = np.cumsum(q.value_lengths().fill_null(0).to_numpy(zero_copy_only=False) + mean)
        a = 0
        while a < batch.num_rows:
            b = int(np.searchsorted(words, (words[a - 1] if a else 0) + BLOCK_WORDS, "right"))
            n = min(max(b - a, 1), BLOCK_GROUPS)
            keys = key.slice(a, n).to_numpy(zero_copy_only=False)
            yield keys, block_of_arrays(q.slice(a, n), ks.slice(a, n), ids, int(keys[0]))
            a += n


def spread(groups: DataFrame) -> DataFrame:
    """Packed groups over all cores; those with a place stay beside their neighbours."""
    cores = groups.sparkSession.sparkContext.defaultParallelism
    if groups.rdd.getNumPartitions() >= cores:
        return groups
    return in_place(groups, cores) if "place" in groups.columns else groups.repartition(cores, "group_id")


def in_place(groups: DataFrame, parts: int) -> DataFrame:
    """Runs of 128 neighbouring groups dealt to ``parts`` partitions, in order there."""
    return groups.repartition(parts, F.shiftright("place", 7)).sortWithinPartitions("place")


def side_forward(inputs: encoder.Words | np.ndarray, side: encoder.SideParams, model: encoder.TwoTower, setting: int = 0, taped: bool = True):
    """Output of the layers under the ladder for all inputs, and what the way back needs."""
    if side.conv is None:
        f, tape = inputs, None
    else:
        f, tape = encoder.conv_words(inputs, side.conv, model.dims, model.width, model.mode, setting, taped)
    layers = [f]
    for w in side.hidden:
        layers.append(np.tanh(layers[-1] @ w.T))
    return layers[-1], (tape, layers)


def side_backward(g: np.ndarray, side: encoder.SideParams, model: encoder.TwoTower, tapes, into: dict) -> None:
    """Gradients of hidden layers and of the convolution's rows, by (name, number)."""
    tape, layers = tapes
    for t in range(len(side.hidden) - 1, -1, -1):
        gz = g * (1.0 - layers[t + 1] ** 2)
        into["hidden", t] = gz.T @ layers[t]
        g = gz @ side.hidden[t]
    if tape is not None:
        into["conv", 0] = encoder.conv_backward(g, tape, side.conv.shape, model.dims, model.width, model.mode)


def batch_gradient(model: encoder.TwoTower, qs: list, ks: list[list], cfg: Config, epoch: int, ids=None):
    """Loss and gradients, by side and (name, number), of groups."""
    settings = [] if model.query.conv is None else [ids if ids is not None else encoder.WordIds(model.dims, model.vocab)]
    return block_gradient(model, block_of(qs, ks, settings), cfg, epoch)


def sums_by(number: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    """Rows of ``x`` summed by their number below ``n``."""
    order = np.argsort(number, kind="stable")
    return encoder.segment_sums(x[order], np.bincount(number, minlength=n))


def block_gradient(model: encoder.TwoTower, block: Block, cfg: Config, epoch: int, setting: int = 0):
    """Loss and gradients, by side and (name, number), of a block's groups; layers run once for each distinct input.

    Drawn signs are drawn anew wherever an input occurs.
    """
    slope, kind = binarize.slope_at(epoch, cfg.growth), cfg.surrogate
    drawn, value = kind == "stochastic", 0.0
    rng = np.random.default_rng((cfg.seed, epoch, block.key & (2**63 - 1), len(block.groups)))
    act = (lambda z: binarize.stochastic_sign(z * cfg.reach, rng)) if drawn else binarize.sign

    def surrogate(z):
        return binarize.grad(kind, z * cfg.reach, slope) * cfg.reach

    found = []
    for name, inputs in (("query", block.query), ("keyword", block.keyword)):
        side = model.side(name)
        f, tapes = side_forward(inputs, side, model, setting)
        numbers = np.concatenate([x[name == "keyword"].ravel() for x in block.groups])
        out, tape = (f, None) if side.ladder is None else ladder.forward(f[numbers] if drawn else f, side.ladder, act)
        spread = out if drawn and tape is not None else out[numbers]
        found.append((name, side, tapes, tape, numbers, spread, len(f)))
    bq, bk = found[0][5], found[1][5]
    grads, lo, klo = (np.empty_like(bq), np.empty_like(bk)), 0, 0
    for q, k, _ in block.groups:
        g, m = k.shape
        cos, dq, dk = loss.cosine_grad(bq[lo : lo + g, None, :], bk[klo : klo + g * m].reshape(g, m, -1))
        one, gc = loss.group_grad(cos, cfg.gamma)
        value += one
        grads[0][lo : lo + g], grads[1][klo : klo + g * m] = (gc[..., None] * dq).sum(1), (gc[..., None] * dk).reshape(g * m, -1)
        lo, klo = lo + g, klo + g * m
    out = {}
    for grad, (name, side, tapes, tape, numbers, _, n) in zip(grads, found, strict=True):
        mine: dict = {}
        late = drawn and tape is not None
        grad = grad if late else sums_by(numbers, grad, n)
        if tape is not None:
            by_name, grad = ladder.backward(grad, tape, side.ladder, surrogate)
            mine["W", 0] = by_name["W"]
            mine |= {("B", t): x for t, x in enumerate(by_name["B"])} | {("R", t): x for t, x in enumerate(by_name["R"])}
        side_backward(sums_by(numbers, grad, n) if late else grad, side, model, tapes, mine)
        out[name] = mine
    return value, out


def add_gradients(total: dict, model: encoder.TwoTower, sides: dict) -> None:
    """Adds one block's gradients to (side, name, number) -> sum."""
    for side, grads in sides.items():
        for key, g in grads.items():
            at = (side, *key)
            if isinstance(g, tuple):
                if at not in total:
                    total[at] = np.zeros_like(model.side(side).conv)
                total[at][g[0]] += g[1]
            elif at in total:
                total[at] += g
            else:
                total[at] = g


def prepared(groups: DataFrame, settings: list) -> DataFrame:
    """data: packed groups as blocks, cut into words and numbered once for all epochs."""
    sent = groups.sparkSession.sparkContext.broadcast(settings)

    def run(batches):
        for _, block in blocks_in(batches, sent.value):
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(block, 5)], pa.binary())], ["data"])

    return groups.select("group_id", "q", "ks").mapInArrow(run, "data binary")


def gradients(blocks: DataFrame, models: dict[str, tuple[encoder.TwoTower, Config]], epoch: int, settings: dict[str, int]) -> DataFrame:
    """model, side, name, t, block, data: gradient blocks summed over all ``prepared`` groups (doubles, little-endian)."""
    sent = blocks.sparkSession.sparkContext.broadcast(models)

    def run(batches):
        totals: dict[str, dict] = {m: {} for m in sent.value}
        value = dict.fromkeys(sent.value, 0.0)
        count = 0
        for batch in batches:
            for data in batch.column(0):
                block = pickle.loads(data.as_buffer())
                count += sum(len(q) for q, _, _ in block.groups)
                for name, (model, cfg) in sent.value.items():
                    v, sides = block_gradient(model, block, cfg, epoch, settings.get(name, 0))
                    value[name] += v
                    add_gradients(totals[name], model, sides)
        rows = [(m, "", "loss", 0, 0, np.array([v, float(count)]).tobytes()) for m, v in value.items()]
        for m, total in totals.items():
            for (side, name, t), g in total.items():
                for b in range(0, len(g), BLOCK_ROWS):
                    piece = g[b : b + BLOCK_ROWS]
                    if piece.any():
                        rows.append((m, side, name, t, b // BLOCK_ROWS, np.ascontiguousarray(piece).tobytes()))
        kinds = [pa.string(), pa.string(), pa.string(), pa.int32(), pa.int32(), pa.binary()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], SCHEMA.replace(",", "").split()[::2])

    def added(table: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x, np.float64) for x in table.column("data").to_pylist())
        first = table.slice(0, 1)
        return first.set_column(first.schema.get_field_index("data"), "data", pa.array([total.tobytes()], pa.binary()))

    return blocks.mapInArrow(run, SCHEMA).groupBy("model", "side", "name", "t", "block").applyInArrow(added, SCHEMA)


class Optimizer:
    """Plain steps or Adam, on a model's parameters in place."""

    def __init__(self, cfg: Config):
        self.cfg, self.seen, self.state = cfg, 0, {}

    def step(self, model: encoder.TwoTower, grads: dict, count: float) -> None:
        """One step down the mean gradient, clipped by its norm."""
        self.seen += 1
        norm = np.sqrt(sum(float(np.square(g).sum()) for g in grads.values())) / count
        scale = min(1.0, self.cfg.clip / max(norm, 1e-12)) / count
        for (side, *key), g in grads.items():
            target, g = model.side(side).arrays()[tuple(key)], g * scale
            if self.cfg.optimizer == "adam":
                m, v = self.state.get((side, *key), (0.0, 0.0))
                m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
                self.state[side, *key] = m, v
                g = m / (1 - 0.9**self.seen) / (np.sqrt(v / (1 - 0.999**self.seen)) + 1e-8)
            target -= self.cfg.rate * g


def collected(rows: list, models: dict) -> tuple[dict, dict]:
    """Loss (sum, count) and gradients by model, from collected blocks."""
    losses, grads = {}, {m: {} for m in models}
    for r in rows:
        x = np.frombuffer(r["data"], np.float64)
        if r["name"] == "loss":
            losses[r["model"]] = x
            continue
        at = (r["side"], r["name"], r["t"])
        target = models[r["model"]][0].side(r["side"]).arrays()[at[1:]]
        whole = grads[r["model"]].setdefault(at, np.zeros_like(target, dtype=np.float64))
        lo = r["block"] * BLOCK_ROWS
        whole[lo : lo + BLOCK_ROWS] = x.reshape(-1, target.shape[1])
    return losses, grads


def fit_many(groups: DataFrame, models: dict[str, tuple[encoder.TwoTower, Config]], path: str | None = None) -> dict[str, Fit]:
    """Trains all models together, one job a round; each for its own number of epochs.

    The given models stay as they are.  With ``path`` the parameters are written
    after every round, so training can go on where a lost driver stopped.
    """
    from ..sources import io

    cores = groups.sparkSession.sparkContext.defaultParallelism
    known, settings = settings_of({m: model for m, (model, _) in models.items()})
    groups = spread(groups)
    blocks = prepared(groups, known)
    blocks = io.pin(blocks.repartition(cores) if groups.rdd.getNumPartitions() < 4 * cores else blocks)
    live = {m: (copy.deepcopy(model), cfg) for m, (model, cfg) in models.items()}
    out = {m: Fit(model) for m, (model, _) in live.items()}
    steps = {m: Optimizer(cfg) for m, (_, cfg) in live.items()}
    epoch = 0
    while live:
        live = {m: x for m, x in live.items() if epoch < x[1].epochs}
        if not live:
            break
        losses, grads = collected(gradients(blocks, live, epoch, settings).collect(), live)
        for m, (model, cfg) in list(live.items()):
            value, count = losses[m]
            mean = float(value / max(count, 1.0))
            out[m].history.append({"epoch": epoch, "loss": mean, "slope": binarize.slope_at(epoch, cfg.growth)})
            if not np.isfinite(mean):
                del live[m]
                continue
            steps[m].step(model, grads[m], max(count, 1.0))
            if path is not None:
                io.save_tower(groups.sparkSession, model, f"{path}/{m}")
        epoch += 1
    blocks.unpersist()
    return out


def fit(groups: DataFrame, model: encoder.TwoTower, cfg: Config | None = None, path: str | None = None) -> Fit:
    """Trains one model for ``cfg.epochs`` rounds."""
    return fit_many(groups, {"model": (model, cfg or Config())}, path)["model"]


def group_scores(groups: DataFrame, models: dict[str, encoder.TwoTower]) -> DataFrame:
    """model, group_id, is_pos, cosine of every member of packed groups (held-out measures)."""
    known, settings = settings_of(models)
    sent = groups.sparkSession.sparkContext.broadcast((models, known))
    names = ["model", "group_id", "is_pos", "cosine"]

    def run(batches):
        towers, known = sent.value
        for keys, block in blocks_in(batches, known):
            for name, model in towers.items():
                both = []
                for inputs, side in ((block.query, model.query), (block.keyword, model.keyword)):
                    f, _ = side_forward(inputs, side, model, settings.get(name, 0), taped=False)
                    both.append(f if side.ladder is None else ladder.dense(ladder.encode(f, side.ladder), side.ladder.weighted))
                norms = [np.linalg.norm(x, axis=1) for x in both]
                for qs, ks, at in block.groups:
                    m = ks.shape[1]
                    for a in range(0, len(qs), 1024):
                        q, k = np.repeat(qs[a : a + 1024], m), ks[a : a + 1024].ravel()
                        norm = norms[0][q] * norms[1][k]
                        cos = np.divide((both[0][q] * both[1][k]).sum(1), norm, out=np.full(len(q), np.nan), where=norm > 0)
                        first = np.arange(len(q)) % m == 0
                        yield pa.RecordBatch.from_arrays([pa.array([name] * len(cos)), pa.array(np.repeat(keys[at[a : a + 1024]], m)), pa.array(first), pa.array(cos, from_pandas=True)], names)

    return spread(groups).select("group_id", "q", "ks").mapInArrow(run, "model string, group_id long, is_pos boolean, cosine double")


def packed_groups(samples: DataFrame, queries: DataFrame, keywords: DataFrame) -> DataFrame:
    """group_id, q and ks (positive first) of each group, from samples and (id, x) inputs; and their place, if samples have one."""
    place = [F.any_value("place").alias("place")] if "place" in samples.columns else []
    rows = samples.join(queries.select(F.col("query_id"), F.col("x").alias("q")), "query_id").join(keywords.select("keyword_id", F.col("x").alias("k")), "keyword_id")
    member = F.struct((~F.col("is_pos")).alias("neg"), "keyword_id", "k")
    packed = rows.groupBy("group_id").agg(*place, F.any_value("q").alias("q"), F.sort_array(F.collect_list(member)).alias("m"))
    return packed.where(F.size("m") > 1).where(~F.col("m")[0]["neg"]).select("group_id", *(["place"] if place else []), "q", F.transform("m", lambda x: x["k"]).alias("ks"))


def local_fit(groups: DataFrame, model: encoder.TwoTower, cfg: Config, parts: int = 4) -> DataFrame:
    """part, epoch, loss: an independent run of plain steps in each of ``parts`` hash parts.

    An alternative to summed gradients: every part trains on its own groups; the
    part of least loss, or an average, can go on.  A part's blocks lie in a file of
    its task's own and pass one by one, so memory does not grow with the part.
    """
    known, settings = settings_of({"model": model})
    sent = groups.sparkSession.sparkContext.broadcast((model, cfg, known))
    at = settings.get("model", 0)

    def by_part(batches):
        """(part, its batches), parts following one another."""
        rows = (piece for b in batches for piece in split(b))
        for part, pieces in itertools.groupby(rows, key=lambda x: x[0]):
            yield part, (x[1] for x in pieces)

    def split(batch):
        part = batch.column(0).to_numpy(zero_copy_only=False)
        heads = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(part)]
        return [(int(part[a]), batch.slice(a, b - a)) for a, b in itertools.pairwise(heads) if b > a]

    def run(batches):
        first, cfg_, known = sent.value
        for part, mine in by_part(batches):
            own, step, losses = copy.deepcopy(first), Optimizer(cfg_), []
            with tempfile.TemporaryFile() as kept:
                ends, count = [0], 0
                for keys, block in blocks_in(mine, known):
                    pickle.dump(block, kept, 5)
                    ends.append(kept.tell())
                    count += len(keys)
                for epoch in range(cfg_.epochs):
                    value, total = 0.0, {}
                    for lo in ends[:-1]:
                        kept.seek(lo)
                        one, sides = block_gradient(own, pickle.load(kept), cfg_, epoch, at)
                        value += one
                        add_gradients(total, own, sides)
                    step.step(own, total, float(count))
                    losses.append(value / count)
            n = len(losses)
            yield pa.RecordBatch.from_arrays([pa.array([part] * n, pa.int32()), pa.array(range(n), pa.int32()), pa.array(losses, pa.float64())], ["part", "epoch", "loss"])

    dealt = groups.select(F.pmod(F.xxhash64("group_id"), F.lit(parts)).cast("int").alias("part"), "group_id", "q", "ks")
    return dealt.repartitionByRange(parts, "part").sortWithinPartitions("part").mapInArrow(run, "part int, epoch int, loss double")


def tune_gamma(scored: DataFrame, grid=(1.0, 2.0, 5.0, 10.0, 20.0), score: str = "cosine", by: tuple[str, ...] = ()) -> DataFrame:
    """gamma, log_loss (per group) and per_sample: on held-out samples, all values in one job."""
    spark = scored.sparkSession
    g = spark.createDataFrame([(float(x),) for x in grid], "gamma double")
    s = F.col("gamma") * F.col(score)
    from pyspark.sql import Window

    w = Window.partitionBy(*by, "gamma", "group_id")
    e = F.exp(s - F.max(s).over(w))
    rows = scored.crossJoin(F.broadcast(g)).withColumn("p", e / F.sum(e).over(w))
    lost = F.sum(F.when(F.col("is_pos"), -F.log("p")))
    return rows.groupBy(*by, "gamma").agg((lost / F.count_if("is_pos")).alias("log_loss"), (lost / F.count("*")).alias("per_sample"))
