"""Document quality by a byte-level convolutional network in numpy.

Filters over consecutive bytes are learned; their responses are max-pooled over overlapping
chunks that cover the whole document.  The mean and the maximum of the chunks' pooled responses
go through one small dense layer to one probability.

The net is fitted where the sample lies: in each round every task passes once over the whole texts of
its shard, a few documents at a time, and the tasks' weights are averaged.  So neither the driver nor
a task ever holds the sample.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.llm import texthash
from stagewise.llm.labelled import SHARDS, fit_sample, held_out
from stagewise.store import Scratch

WIDTH, FILTERS, HIDDEN = 6, 16, 16
CELL, CELLS, STEP = 64, 4, 3  # a chunk is 4 cells of 64 bytes; the next begins 3 cells on
FIT_ROWS = 6000
ROUNDS = 8  # passes over a full sample; a smaller one is passed over more often, up to MOST_ROUNDS
MOST_ROUNDS = 24
RATE, DECAY, MINIBATCH = 0.02, 1e-4, 16
BATCH = 256 << 10


class ByteNet:
    """table: (WIDTH, 257, FILTERS), the weight of each byte (256: past the end) at each place of each filter."""

    def __init__(self, seed: int = 11):
        rng = np.random.default_rng(seed)
        self.p = {
            "table": rng.standard_normal((WIDTH, 257, FILTERS)).astype(np.float32) * 0.1,
            "b0": np.zeros(FILTERS, dtype=np.float32),
            "w1": (rng.standard_normal((2 * FILTERS, HIDDEN)) / np.sqrt(2 * FILTERS)).astype(np.float32),
            "b1": np.zeros(HIDDEN, dtype=np.float32),
            "w2": (rng.standard_normal(HIDDEN) / np.sqrt(HIDDEN)).astype(np.float32),
            "b2": np.zeros(1, dtype=np.float32),
        }
        self.p["table"][:, 256] = 0
        self.pairs: list[np.ndarray] | None = None

    def top(self, mean: np.ndarray, most: np.ndarray) -> tuple:
        x = np.concatenate([mean, most], axis=1)
        h = np.maximum(x @ self.p["w1"] + self.p["b1"], 0)
        z = h @ self.p["w2"] + self.p["b2"][0]
        return x, h, 1 / (1 + np.exp(-np.clip(z, -30, 30)))

    def responses(self, raw: np.ndarray) -> np.ndarray:
        """(bytes, FILTERS) of one run of bytes; two bytes are looked up at once."""
        if self.pairs is None:
            t = self.p["table"]
            self.pairs = [(t[k][:256, None, :] + t[k + 1][None, :256, :]).reshape(-1, FILTERS) for k in range(0, WIDTH, 2)]
        code = raw[:-1].astype(np.int32) << 8 | raw[1:]
        n = len(raw) - WIDTH + 1
        out = self.pairs[0][code[:n]]
        for k in range(2, WIDTH, 2):
            out += self.pairs[k // 2][code[k : k + n]]
        return out

    def single_responses(self, raw: np.ndarray) -> np.ndarray:
        """The same byte by byte: quicker while the weights change."""
        n = len(raw) - WIDTH + 1
        out = self.p["table"][0][raw[:n]]
        for k in range(1, WIDTH):
            out += self.p["table"][k][raw[k : k + n]]
        return out

    def score(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Probability of each document; raw and offsets as of an Arrow text column."""
        if len(offsets) < 2:
            return np.zeros(0)
        lay = Layout(raw, offsets)
        chunk, _ = lay.pooled(self.responses, False)
        mean, most = lay.by_document(np.maximum(chunk + self.p["b0"], 0))
        return self.top(mean, most)[2].astype(np.float64)

    def gradients(self, raw: np.ndarray, offsets: np.ndarray, labels: np.ndarray) -> dict[str, np.ndarray]:
        """Of the mean log loss over some whole documents; a maximum passes its share on to the bytes that made it."""
        lay = Layout(raw, offsets)
        peak, place = lay.pooled(self.single_responses, True)
        peak = peak + self.p["b0"]
        act = np.maximum(peak, 0)
        mean, most = lay.by_document(act)
        x, h, prob = self.top(mean, most)
        dz = (prob - labels).astype(np.float32) / len(labels)
        g = {"w2": h.T @ dz, "b2": np.array([dz.sum()], dtype=np.float32)}
        dh = dz[:, None] * self.p["w2"] * (h > 0)
        g["w1"], g["b1"] = x.T @ dh, dh.sum(axis=0)
        dx = dh @ self.p["w1"].T
        top = act == most[lay.doc]  # chunks alike share a maximum
        shared = dx[:, FILTERS:] / np.add.reduceat(top, lay.starts, axis=0, dtype=np.float32)
        dact = dx[lay.doc, :FILTERS] / lay.counts[lay.doc][:, None] + shared[lay.doc] * top
        dpeak = dact * (peak > 0)
        g["b0"] = dpeak.sum(axis=0)
        rows, f = np.nonzero(dpeak)
        at, share = place[rows, f], dpeak[rows, f]
        g["table"] = np.stack([
            np.bincount(lay.laid[at + k].astype(np.int64) * FILTERS + f, weights=share, minlength=257 * FILTERS).reshape(257, FILTERS) for k in range(WIDTH)
        ]).astype(np.float32)
        return g


class Layout:
    """Documents laid out in whole cells, with blanks after the end, so that no cell holds bytes of two of them."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray):
        size = np.diff(offsets)
        self.cells = np.maximum(1, -(-size // CELL))
        self.first = np.concatenate([[0], np.cumsum(self.cells)])
        self.laid = np.full(int(self.first[-1]) * CELL + WIDTH, 32, dtype=np.uint8)
        for i in np.flatnonzero(size).tolist():
            at = int(self.first[i]) * CELL
            self.laid[at : at + size[i]] = raw[offsets[i] : offsets[i + 1]]
        # chunks of each document; the last one may be shorter
        self.counts = np.maximum(1, -(-np.maximum(self.cells - (CELLS - STEP), 1) // STEP))
        self.doc = np.repeat(np.arange(len(size)), self.counts)
        self.starts = np.cumsum(self.counts) - self.counts
        self.begin = self.first[self.doc] + STEP * (np.arange(len(self.doc)) - self.starts[self.doc])
        self.last = self.first[self.doc + 1] - 1

    def pooled(self, responses, placed: bool) -> tuple[np.ndarray, np.ndarray | None]:
        """(chunks, FILTERS): each filter's largest response in each chunk and, if asked, the byte it begins at."""
        total = int(self.first[-1])
        most = np.empty((total, FILTERS), dtype=np.float32)
        place = np.empty((total, FILTERS), dtype=np.int32) if placed else None
        for a in range(0, total, BATCH // CELL):
            b = min(total, a + BATCH // CELL)
            r = responses(self.laid[a * CELL : b * CELL + WIDTH - 1]).reshape(b - a, CELL, FILTERS)
            if placed:
                best = r.argmax(axis=1)
                most[a:b] = np.take_along_axis(r, best[:, None, :], axis=1)[:, 0]
                place[a:b] = best + (np.arange(a, b, dtype=np.int32) * CELL)[:, None]
            else:
                most[a:b] = r.max(axis=1)
        chunk, where = most[self.begin], place[self.begin] if placed else None
        for k in range(1, CELLS):
            other = np.minimum(self.begin + k, self.last)
            if placed:
                where = np.where(most[other] > chunk, place[other], where)
            chunk = np.maximum(chunk, most[other])
        return chunk, where

    def by_document(self, act: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        mean = np.add.reduceat(act, self.starts, axis=0) / self.counts[:, None]
        return mean.astype(np.float32), np.maximum.reduceat(act, self.starts, axis=0)


class Trainer:
    """Adam with a warm-up and a rate that falls to a tenth; ``step`` counts the steps of all rounds."""

    def __init__(self, net: ByteNet, moments: tuple[dict, dict], step: int, total: int):
        self.net, self.step, self.total = net, step, total
        self.m, self.s = ({k: v.copy() for k, v in own.items()} for own in moments)

    def update(self, raw: np.ndarray, offsets: np.ndarray, labels: np.ndarray) -> None:
        g = self.net.gradients(raw, offsets, labels)
        self.step += 1
        speed = RATE * min(1.0, self.step / 20) * max(0.1, 1 - 0.9 * self.step / self.total)
        for k, v in self.net.p.items():
            gk = g[k] + DECAY * v
            self.m[k] = 0.9 * self.m[k] + 0.1 * gk
            self.s[k] = 0.99 * self.s[k] + 0.01 * gk * gk
            self.net.p[k] = v - speed * (self.m[k] / (1 - 0.9**self.step)) / (np.sqrt(self.s[k] / (1 - 0.99**self.step)) + 1e-7)


def _minibatches(batches: Iterator[pa.RecordBatch], docs: int = MINIBATCH, most: int = 4 << 20) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(shard, bytes, offsets, labels) of a few neighbouring documents of one shard; a longer text is one of its own."""
    for batch in batches:
        shard, label = batch.column("shard").to_numpy(), batch.column("label").to_numpy()
        raw, offsets = texthash.text_bytes(batch.column("text"))
        at = 0
        while at < batch.num_rows:
            same = np.flatnonzero(shard[at : at + docs] != shard[at])
            end = at + int(same[0]) if len(same) else min(at + docs, batch.num_rows)
            end = max(at + 1, min(end, int(np.searchsorted(offsets, offsets[at] + most, side="right")) - 1))
            yield int(shard[at]), raw[offsets[at] : offsets[end]], offsets[at : end + 1] - offsets[at], label[at:end].astype(np.float32)
            at = end


def train_shards(batches: Iterator[pa.RecordBatch], state: dict) -> Iterator[tuple[int, int, dict, tuple[dict, dict], int]]:
    """One pass over rows that lie shard by shard: (shard, documents, weights, moments, steps) of each."""
    now, net, trainer, n = None, None, None, 0
    for shard, raw, offsets, labels in _minibatches(batches):
        if shard != now:
            if trainer is not None:
                yield now, n, net.p, (trainer.m, trainer.s), trainer.step
            now, n, net = shard, 0, ByteNet()
            net.p = {k: v.copy() for k, v in state["p"].items()}
            trainer = Trainer(net, state["moments"], state["step"], state["total"])
        trainer.update(raw, offsets, labels)
        n += len(labels)
    if trainer is not None:
        yield now, n, net.p, (trainer.m, trainer.s), trainer.step


def fit(sample: DataFrame, rounds: int | None = None, seed: int = 11) -> ByteNet:
    """sample(label, shard, text), rows of a shard side by side -> a net; without both labels it gives the (only) label's share."""
    net = ByteNet(seed)
    told = sample.agg(F.count("*").alias("n"), F.avg("label").alias("share")).first()
    share = float(np.clip(told.share if told.n else 0.5, 0.01, 0.99))
    net.p["b2"][:] = np.log(share / (1 - share))
    if not told.n or told.share in (0, 1):
        net.p["w2"][:] = 0
        return net
    rounds = rounds or int(np.clip(ROUNDS * FIT_ROWS / told.n, ROUNDS, MOST_ROUNDS))
    zeros = {k: np.zeros_like(v) for k, v in net.p.items()}
    each = -(-told.n // (MINIBATCH * max(1, sample.select("shard").distinct().count())))
    state = {"p": net.p, "moments": (zeros, zeros), "step": 0, "total": rounds * each}
    spark = sample.sparkSession
    for _ in range(rounds):
        held = spark.sparkContext.broadcast(state)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for shard, n, *learned in train_shards(batches, held.value):
                yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "n": pa.array([n], pa.int64()), "learned": pa.array([pickle.dumps(learned)], pa.binary())})

        # one row a shard
        parts = sorted(sample.select("label", "shard", "text").mapInArrow(run, "shard int, n long, learned binary").collect(), key=lambda r: (r["shard"], r["n"], r["learned"]))
        held.destroy()
        share = [r["n"] / told.n for r in parts]
        learned = [pickle.loads(r["learned"]) for r in parts]
        mean = lambda pick: {k: sum(w * pick(x)[k] for w, x in zip(share, learned)).astype(np.float32) for k in net.p}
        state |= {"p": mean(lambda x: x[0]), "moments": (mean(lambda x: x[1][0]), mean(lambda x: x[1][1])), "step": max(x[2] for x in learned)}
    net.p = state["p"]
    return net


def score(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, threshold: float = 0.7) -> DataFrame:
    """docs(doc_id, text, ...), labels(doc_id, quality) -> (doc_id, held_out, score, predicted), one row per input row.

    Only the text is an input of a score.  At most ``fit_rows`` labelled rows that are not held out are
    learned from.  Null and empty texts are scored as one blank cell.  Without labels all scores are 0.5.
    """
    sample = fit_sample(docs, labels, "quality", fit_rows)
    sample = Scratch(docs.sparkSession, "quality").save(sample.repartition(SHARDS, "shard").sortWithinPartitions("shard", F.xxhash64("doc_id"), "doc_id"), "sample")
    net = docs.sparkSession.sparkContext.broadcast(fit(sample).p)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = ByteNet()
        own.p = net.value
        for batch in batches:
            for part in texthash.slices(batch, "text", 1 << 20):
                got = own.score(*texthash.text_bytes(part.column("text")))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(got)], names=["doc_id", "held_out", "score"])

    kind = dict(docs.dtypes)["doc_id"]
    rows = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text")
    scored = rows.mapInArrow(run, f"doc_id {kind}, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
