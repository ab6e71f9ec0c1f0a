"""Deterministic mini-batch training of stages, with bit-exact checkpoints.

Batches are slices of a keyed permutation, a pure function of (seed, epoch, cursor), so a
stage that resumes from a checkpoint sees exactly what an uninterrupted run would see.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.functions.hpfunc import Piece
from stagewise.store import Scratch


def affine(epoch: int, n: int, seed: int) -> tuple[int, int]:
    """(a, b) of the permutation i -> (a i + b) mod n of an epoch; a has no factor in common with n."""
    a = (seed * 7919 + epoch * 104729 + 1) % n if n > 1 else 0
    while math.gcd(a, n) != 1 and n > 1:
        a = (a + 1) % n
    return a, (seed * 31 + epoch * 17) % n


def rows_at(epoch: int, cursor: int, size: int, n: int, seed: int) -> np.ndarray:
    a, b = affine(epoch, n, seed)
    return (a * np.arange(cursor, min(n, cursor + size)) + b) % n


@dataclass
class State:
    """A checkpoint: parameters, optimizer state, position in the data, steps done."""

    params: np.ndarray
    moments: list[np.ndarray] = field(default_factory=list)
    epoch: int = 0
    cursor: int = 0
    step: int = 0

    def dump(self) -> bytes:
        head = np.array([self.epoch, self.cursor, self.step, len(self.moments), *self.params.shape], dtype="<i8")
        return b"".join([np.array([len(head)], dtype="<i8").tobytes(), head.tobytes(), self.params.astype("<f8").tobytes(), *[m.astype("<f8").tobytes() for m in self.moments]])

    @staticmethod
    def load(raw: bytes) -> State:
        n = int(np.frombuffer(raw, "<i8", 1)[0])
        head = np.frombuffer(raw, "<i8", n, 8)
        shape = tuple(head[4:].tolist())
        flat = np.frombuffer(raw, "<f8", offset=8 * (n + 1)).reshape((1 + int(head[3]), *shape)).copy()
        return State(flat[0], list(flat[1:]), *map(int, head[:3]))


class Learner:
    """Mini-batch descent with momentum or adam, weight decay, and cutout of a window of inputs; ``gradient`` is the model's."""

    def __init__(self, x: np.ndarray, y: np.ndarray, classes: int, seed: int = 1):
        self.x, self.y, self.classes, self.seed = x, y, classes, seed

    def inputs(self, rows: np.ndarray, s: State, hp: dict[str, float]) -> np.ndarray:
        x = self.with_one(self.x[rows])
        cut = int(hp.get("cutout", 0))
        if cut:
            at = (self.seed * 13 + s.step * 7) % (x.shape[1] - 1)
            x[:, at : min(at + cut, x.shape[1] - 1)] = 0
        return x

    def step(self, s: State, hp: dict[str, float]) -> None:
        n = len(self.x)
        size = int(hp.get("bs", 32))
        if s.cursor >= n:
            s.epoch, s.cursor = s.epoch + 1, 0
        rows = rows_at(s.epoch, s.cursor, size, n, self.seed)
        s.cursor += size
        g = self.gradient(self.inputs(rows, s, hp), self.y[rows], s.params) + hp.get("decay", 0.0) * s.params
        s.step += 1
        momentum = hp.get("momentum", 0.0)
        if momentum < 0:  # adam
            if len(s.moments) < 2:
                s.moments = [np.zeros_like(g), np.zeros_like(g)]
            s.moments[0] = 0.9 * s.moments[0] + 0.1 * g
            s.moments[1] = 0.999 * s.moments[1] + 0.001 * g * g
            s.params = s.params - hp["lr"] * (s.moments[0] / (1 - 0.9**s.step)) / (np.sqrt(s.moments[1] / (1 - 0.999**s.step)) + 1e-8)
        else:
            if not s.moments:
                s.moments = [np.zeros_like(g)]
            s.moments[0] = momentum * s.moments[0] + g
            s.params = s.params - hp["lr"] * s.moments[0]

    @staticmethod
    def matrix(rows: pd.Series) -> np.ndarray:
        """Held-out rows as ``predict`` takes them."""
        return np.array(rows.tolist(), dtype=np.float64)

    @staticmethod
    def with_one(x: np.ndarray) -> np.ndarray:
        return np.hstack([x, np.ones((len(x), 1))])

    @staticmethod
    def miss(z: np.ndarray, y: np.ndarray) -> np.ndarray:
        """The loss's slope by the outputs z: probabilities less the truth, per row."""
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        p[np.arange(len(y)), y] -= 1
        return p / len(y)


class Softmax(Learner):
    """Multinomial logistic regression."""

    def fresh(self) -> State:
        return State(np.zeros((self.x.shape[1] + 1, self.classes)))

    def gradient(self, x: np.ndarray, y: np.ndarray, w: np.ndarray) -> np.ndarray:
        return x.T @ self.miss(x @ w, y)

    @classmethod
    def predict(cls, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        return (cls.with_one(x) @ w).argmax(axis=1)


class OneHidden(Learner):
    """A net of one hidden layer; the parameters are one matrix: the weights into the units, then, transposed, those out of them."""

    UNITS = 32

    def fresh(self) -> State:
        rng, d = np.random.default_rng(self.seed), self.x.shape[1] + 1
        w = rng.standard_normal((d + self.classes, self.UNITS))  # inputs are of about unit length
        w[d:] /= np.sqrt(self.UNITS)
        return State(w)

    def gradient(self, x: np.ndarray, y: np.ndarray, w: np.ndarray) -> np.ndarray:
        d = x.shape[1]
        hidden = np.maximum(x @ w[:d], 0)
        miss = self.miss(hidden @ w[d:].T, y)
        return np.vstack([x.T @ ((miss @ w[d:]) * (hidden > 0)), miss.T @ hidden])

    @classmethod
    def predict(cls, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        d = x.shape[1] + 1
        return (np.maximum(cls.with_one(x) @ w[:d], 0) @ w[d:].T).argmax(axis=1)


class WordBag(Softmax):
    """Softmax over hashed words, as bucket numbers (-1: none); training reads as many of a text's words as the setting ``length`` says, evaluation all."""

    BUCKETS, RATE = 256, 1e4  # the published rates are for another kind of model: they are taken times RATE

    def fresh(self) -> State:
        return State(np.zeros((self.BUCKETS + 1, self.classes)))

    @classmethod
    def counts(cls, words: np.ndarray, length: int) -> np.ndarray:
        words = words[:, :length].astype(np.int64)
        row, at = np.nonzero(words >= 0)
        out = np.bincount(row * cls.BUCKETS + words[row, at], minlength=len(words) * cls.BUCKETS).reshape(len(words), cls.BUCKETS).astype(np.float64)
        return out / np.maximum(np.sqrt((out * out).sum(axis=1, keepdims=True)), 1)

    def inputs(self, rows: np.ndarray, s: State, hp: dict[str, float]) -> np.ndarray:
        return self.with_one(self.counts(self.x[rows], int(hp["length"])))

    def step(self, s: State, hp: dict[str, float]) -> None:
        super().step(s, hp | {"lr": hp["lr"] * self.RATE})

    @classmethod
    def matrix(cls, rows: pd.Series) -> np.ndarray:
        out = np.stack([np.bincount(np.asarray(r, dtype=np.int64), minlength=cls.BUCKETS) for r in rows]).astype(np.float64)
        return out / np.maximum(np.sqrt((out * out).sum(axis=1, keepdims=True)), 1)


def parsed(text: str) -> Piece:
    """One setting's canonical text as a function of the steps of its segment."""
    fn, rest = text.split("(", 1)
    args, clock = rest.split(")", 1)
    return Piece(1, fn, tuple(float(a) for a in args.split(",")), int(clock[1:]) if clock else 0)


def parse_value(text: str, t: int) -> float:
    """The value of one setting's canonical text ``t`` steps into its segment."""
    return parsed(text).value(t)


def functions(cfg: str) -> dict[str, Piece]:
    return {k: parsed(v) for k, v in (x.split("=", 1) for x in cfg.split(";"))}


def settings(cfg: str, t: int) -> dict[str, float]:
    return {k: f.value(t) for k, f in functions(cfg).items()}


class Trainer:
    """What a user of a study overrides: a model's training, step by step; states are the user's own.

    ``setup`` is called with the settings that have another value than at the step before (None: no longer set), ``iterate``
    trains one step of the engine, which may be several mini-batches (``ITERATION``).  A state resumes from its
    bytes exactly where it was.
    """

    ITERATION = 1

    def fresh(self):
        raise NotImplementedError

    def setup(self, changed: dict[str, float | None]) -> None:
        raise NotImplementedError

    def iterate(self, state) -> None:
        raise NotImplementedError

    def dump(self, state) -> bytes:
        raise NotImplementedError

    def restore(self, raw: bytes):
        raise NotImplementedError


class LearnerTrainer(Trainer):
    """The learners of this module as a user would write them."""

    def __init__(self, learner: Learner, iteration: int = 1):
        self.learner, self.hp, self.ITERATION, self.told = learner, {}, iteration, []

    def fresh(self) -> State:
        return self.learner.fresh()

    def setup(self, changed: dict[str, float | None]) -> None:
        self.told.append(changed)
        self.hp = {k: v for k, v in (self.hp | changed).items() if v is not None}

    def iterate(self, state: State) -> None:
        for _ in range(self.ITERATION):
            self.learner.step(state, self.hp)

    def dump(self, state: State) -> bytes:
        return state.dump()

    def restore(self, raw: bytes) -> State:
        return State.load(raw)


def drive(trainer: Trainer, state, cfg: str, age: int, steps: int, last: dict[str, float]) -> dict[str, float]:
    """Trains ``steps`` steps under a configuration whose node began ``age`` steps before; ``last`` are the settings the trainer has, those of the end are returned."""
    own = functions(cfg)
    moving = [k for k, f in own.items() if f.fn != "constant"]
    for t in range(age, age + steps):
        now = {k: f.value(t) for k, f in own.items()} if t == age else last | {k: own[k].value(t) for k in moving}
        changed = {k: v for k, v in now.items() if last.get(k) != v} | {k: None for k in last if k not in now}
        if changed:
            trainer.setup(changed)
            last = now
        trainer.iterate(state)
    return last


def train_trials(segments: pd.DataFrame, trainer: Trainer, shared: bool, lo: int = 0, hi: int | None = None) -> tuple[list[tuple], int]:
    """Trains the steps lo..hi of trials that all stand at lo; a trial's ``ckpt`` is its state there (null: fresh).

    shared: a stage of a node is trained once, and every trial through it resumes from the state
    at its end.  States are kept at ends of stages only.  Returns ((study, trial, step, state), ..) and the number of steps trained.
    """
    segments = segments.assign(lo=segments["start"].clip(lower=lo), hi=segments["end"] if hi is None else segments["end"].clip(upper=hi))
    segments = segments[segments["lo"] < segments["hi"]]
    cuts = {path: sorted(set(own)) for path, own in segments.groupby("path")["hi"]}
    for path, parent, start in set(zip(segments["path"], segments["parent"], segments["lo"])):
        if parent in cuts and start > lo:
            cuts[parent] = sorted({*cuts[parent], start})
    states: dict[tuple, bytes] = {}
    hp_names = {k for cfg in segments["cfg"].unique() for k in functions(cfg)}
    steps, out = 0, []
    for (study, trial), own in segments.sort_values(["study", "trial", "k"]).groupby(["study", "trial"], sort=True):
        first = own["ckpt"].iloc[0]
        s, last = trainer.fresh() if first is None else trainer.restore(first), {}
        trainer.setup(dict.fromkeys(hp_names, None))
        for row in own.itertuples():
            ends = [c for c in cuts[row.path] if row.lo < c <= row.hi]
            known = [c for c in ends if (row.path, c) in states] if shared else []
            at = row.lo
            if known:
                at = known[-1]
                s = trainer.restore(states[row.path, at])
            for end in ends[len(known) :]:
                last = drive(trainer, s, row.cfg, at - row.start, end - at, last)
                steps += end - at
                at = end
                if shared:
                    states[row.path, end] = trainer.dump(s)
        out.append((study, int(trial), int(own["hi"].max()), trainer.dump(s)))
    return out, steps


FIT_ROWS = 2_000


def fit_sample(rows: DataFrame, most: int = FIT_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """At most ``most`` of rows(id, x, y) to learn from, in a seeded order that doesn't depend on where rows lie."""
    t = rows.orderBy(F.xxhash64("id"), "id").limit(most).toPandas().sort_values("id")
    return np.array(t["x"].tolist(), dtype=np.float64).reshape(len(t), -1), t["y"].to_numpy(dtype=np.int64)


def train(segments: DataFrame, data: tuple[np.ndarray, np.ndarray], classes: int, shared: bool, lo: int = 0, hi: int | None = None, seed: int = 1, model: type = Softmax, iteration: int = 1) -> DataFrame:
    """segments(.., ckpt binary) -> (study, trial, step, ckpt, steps_run): the trials' states at ``hi``.

    A task trains one tree of the forest (shared) or one trial; nothing is shared between
    trees.  The sample is broadcast: its size is bounded by ``fit_sample``.  ``steps_run`` is told once per tree, at its first trial.
    """
    held = segments.sparkSession.sparkContext.broadcast(data)

    def one(group: pd.DataFrame) -> pd.DataFrame:
        out, steps = train_trials(group, LearnerTrainer(model(*held.value, classes, seed), iteration), shared, lo, hi)
        return pd.DataFrame([(*r, steps if not k else 0) for k, r in enumerate(out)], columns=["study", "trial", "step", "ckpt", "steps_run"])

    own = ["root"] if shared else ["study", "trial"]
    return segments.groupBy(*own).applyInPandas(one, "study string, trial long, step long, ckpt binary, steps_run long")


def scores(models: DataFrame, rows: DataFrame, model: type = Softmax) -> DataFrame:
    """models(study, trial, ckpt), rows(x, y) -> (study, trial, value, f1): the share of rows that each model gets right, and F1 of class 0.

    All rows are read, each once for all models; only counts per task and model are shuffled.
    The models are a client's trials: refused beyond 100,000.
    """
    known = models.select("study", "trial", "ckpt").limit(100_001).toPandas()
    if len(known) > 100_000:
        raise ValueError("too many models for one pass")
    names = list(zip(known["study"], known["trial"].tolist()))
    held = models.sparkSession.sparkContext.broadcast([State.load(x).params for x in known["ckpt"]])

    def run(batches):
        told = np.zeros((len(names), 3), dtype=np.int64)  # right, right in class 0, said to be class 0
        n = zeros = 0
        for b in batches:
            if len(b):
                x, y = model.matrix(b["x"]), b["y"].to_numpy()
                n, zeros = n + len(b), zeros + int((y == 0).sum())
                for k, w in enumerate(held.value):
                    said = model.predict(w, x)
                    told[k] += ((said == y).sum(), ((said == y) & (y == 0)).sum(), (said == 0).sum())
        if n:
            yield pd.DataFrame({"study": [a for a, _ in names], "trial": [b for _, b in names], "right": told[:, 0], "hit": told[:, 1], "said": told[:, 2], "zeros": zeros, "n": n})

    told = rows.select("x", "y").mapInPandas(run, "study string, trial long, right long, hit long, said long, zeros long, n long")
    f1 = F.try_divide(2 * F.sum("hit"), F.sum("said") + F.sum("zeros"))
    return told.groupBy("study", "trial").agg((F.sum("right") / F.sum("n")).alias("value"), F.coalesce(f1, F.lit(0.0)).alias("f1"))


def run_chains(placed: DataFrame, data: tuple[np.ndarray, np.ndarray], classes: int, model: type = Softmax, seed: int = 1, iteration: int = 1, every: int | None = None) -> DataFrame:
    """placed(leaf, path, lo, hi, start, cfg, ckpt binary) -> checkpoints(leaf, path, step, ckpt) at the end of each stage, and at all multiples of ``every``.

    A task runs a whole chain on one worker; only its first stage reads a checkpoint (null: a fresh model).  The
    sample is broadcast: its size is bounded by ``fit_sample``.
    """
    held = placed.sparkSession.sparkContext.broadcast(data)

    def one(group: pd.DataFrame) -> pd.DataFrame:
        trainer = LearnerTrainer(model(*held.value, classes, seed), iteration)
        group = group.sort_values("lo")
        first, last, out = group["ckpt"].iloc[0], {}, []
        s = trainer.restore(first) if first is not None else trainer.fresh()
        for r in group.itertuples():
            at = r.lo
            while at < r.hi:
                end = min(r.hi, (at // every + 1) * every) if every else r.hi
                last = drive(trainer, s, r.cfg, at - r.start, end - at, last)
                out.append((r.leaf, r.path, end, trainer.dump(s)))
                at = end
        return pd.DataFrame(out, columns=["leaf", "path", "step", "ckpt"])

    return placed.groupBy("leaf").applyInPandas(one, "leaf string, path string, step long, ckpt binary")


def numbered(rows: DataFrame, key: str) -> tuple[DataFrame, int]:
    """(key, row_no) with the rows numbered from 0 in the key's order, nulls first, and how many there are.

    The key's ranges are sorted apart and written; a range begins where those before it end, so no task sees all rows.
    """
    scratch = Scratch(rows.sparkSession, "numbered")
    ranged = rows.select(key).repartitionByRange(F.col(key).asc_nulls_first()).sortWithinPartitions(F.col(key).asc_nulls_first())
    at = F.monotonically_increasing_id()
    saved = scratch.save(ranged.select(key, F.shiftright(at, 33).alias("part"), at.bitwiseAND((1 << 33) - 1).alias("within")), "ranges")
    begins, n = [], 0
    for r in saved.groupBy("part").count().orderBy("part").collect():
        begins.append((r["part"], n))
        n += r["count"]
    begins = rows.sparkSession.createDataFrame(begins, "part long, begin long")
    return saved.join(F.broadcast(begins), "part").select(key, (F.col("begin") + F.col("within")).alias("row_no")), n


def batch_slices(rows: DataFrame, key: str, sizes: list[int], seed: int, epoch: int = 0) -> DataFrame:
    """(batch, row_no, key): the batch of each row in one epoch, in closed form; the last of the sizes holds to the epoch's end.

    A row's place in the epoch's permutation is found from its number by the inverse of :func:`affine`; places stay exact for up to 3 * 10^9 rows.
    """
    own, n = numbered(rows, key)
    a, b = affine(epoch, n, seed) if n else (0, 0)
    back, starts = pow(a, -1, n) if n > 1 else 0, np.concatenate([[0], np.cumsum(sizes[:-1])]).tolist()
    at = own.withColumn("i", F.pmod(F.lit(back) * (F.col("row_no") - b), F.lit(max(n, 1))))
    batch = F.lit(len(sizes) - 1) + F.expr(f"(i - {starts[-1]}) div {sizes[-1]}")
    for k in reversed(range(len(sizes) - 1)):
        batch = F.when(F.col("i") < starts[k + 1], F.lit(k)).otherwise(batch)
    return at.select(batch.cast("long").alias("batch"), "row_no", key)
