"""Near-duplicate vectors: dense groups exactly, the rest by a forest of random-projection trees.

Around the sample vectors with many near ones lie balls.  A vector within the linking angle of a ball's centre has its
home there, and all vectors that it can link with lie within twice that angle (its halo), so a ball's own vectors are
compared with each other and with the halo, and no link of theirs is lost.  Only vectors without a home go to the trees.

The split directions and thresholds of every tree are fitted on a bounded sample, to a depth
that follows the number of vectors; every vector then goes down all trees, at each split into both halves when it lies near the threshold
(spill).  Vectors of one leaf are compared in double precision.  A pair that meets in several
leaves is counted in the first one only, so links are counted without a table of pairs: a
leaf gives each vector its number of new links, and spanning edges of its linked vectors.
Equal vectors are merged first and stand for all their copies.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.llm.components import connected_components
from stagewise.store import Scratch

SAMPLE = 20_000
TREES, SPILL, LEAF = 8, 0.15, 48
DENSE = 12  # sample vectors near each other, from which on they get a ball
_TREE_BITS = 26  # a leaf code is its tree times 2**26 and its node


def _usable(column: pa.Array, dim: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(vectors of the usable rows in double precision, their row numbers)."""
    sizes = pa.compute.fill_null(pa.compute.list_value_length(column), 0).to_numpy(zero_copy_only=False)
    if dim is not None and len(column) and (sizes == dim).all() and not column.null_count and not column.flatten().null_count:
        x, at = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim), np.arange(len(column))
    else:
        rows = [(v, i) for i, v in enumerate(column.to_pylist()) if v and len(v) == (dim or len(v)) and not any(y is None for y in v)]
        x, at = np.array([v for v, _ in rows], dtype=np.float64).reshape(len(rows), dim or (len(rows[0][0]) if rows else 0)), np.array([i for _, i in rows], dtype=np.int64)
    good = np.isfinite(x).all(axis=1) & (x != 0).any(axis=1)
    return x[good], at[good]


def _unit_rows(x: np.ndarray) -> np.ndarray:
    """Vectors of length 1; very large and very small ones are first scaled by a power of two."""
    if not x.size:
        return x
    x = np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1])
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _units(raw: list[bytes], kind: str, dim: int) -> np.ndarray:
    """Unit vectors in double precision from stored values of the column's own precision."""
    return _unit_rows(np.frombuffer(b"".join(raw), dtype=kind).reshape(-1, dim).astype(np.float64))


class Forest:
    """Trees as arrays: of node k of tree t, a direction, a threshold and a margin; its halves are 2 k and 2 k + 1.

    These upper levels end where few sample vectors are left in a node, a cell.  A table too large
    for that gets further levels: all cells of a tree share one direction a level, and each has a
    threshold and margin of its own from the sample vectors that it holds.  The model's
    size thus follows the sample, and the depth the table.
    """

    def __init__(self, sample: np.ndarray, trees: int, leaf: int, spill: float, seed: int, least_depth: int = 0):
        rng = np.random.default_rng(seed)
        self.upper = max(0, int(np.ceil(np.log2(max(1, len(sample) / leaf)))))
        self.depth = min(max(self.upper, least_depth), _TREE_BITS - 1)
        dim, cells = sample.shape[1], 1 << self.upper
        self.directions = rng.standard_normal((trees, cells, dim))
        self.directions /= np.linalg.norm(self.directions, axis=2, keepdims=True)
        self.threshold = np.zeros((trees, cells))
        self.margin = np.zeros((trees, cells))
        self.lower = rng.standard_normal((trees, self.depth - self.upper, dim))
        self.lower /= np.linalg.norm(self.lower, axis=2, keepdims=True)
        self.lower_threshold = np.zeros((trees, self.depth - self.upper, cells))
        self.lower_margin = np.zeros((trees, self.depth - self.upper, cells))
        for t in range(trees):
            held = {1: np.arange(len(sample))}
            for _ in range(self.upper):
                below = {}
                for k, rows in held.items():
                    p = sample[rows] @ self.directions[t, k]
                    if len(p):
                        self.threshold[t, k] = np.median(p)
                        self.margin[t, k] = spill * p.std()
                    below[2 * k], below[2 * k + 1] = rows[p <= self.threshold[t, k]], rows[p > self.threshold[t, k]]
                held = below
            if self.depth > self.upper:
                for k, rows in held.items():
                    p = sample[rows] @ self.lower[t].T if len(rows) else np.zeros((1, self.depth - self.upper))
                    self.lower_threshold[t, :, k - cells] = np.median(p, axis=0)
                    self.lower_margin[t, :, k - cells] = spill * p.std(axis=0)

    def leaves(self, vectors: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf) of each vector, in one or more leaves of tree t."""
        row, node = np.arange(len(vectors)), np.ones(len(vectors), dtype=np.int64)
        for level in range(self.depth):
            if level < self.upper:
                gap = np.einsum("ij,ij->i", vectors[row], self.directions[t, node]) - self.threshold[t, node]
                margin = self.margin[t, node]
            else:
                k = level - self.upper
                cell = (node >> k) - (1 << self.upper)
                gap, margin = (vectors @ self.lower[t, k])[row] - self.lower_threshold[t, k, cell], self.lower_margin[t, k, cell]
            low, high = gap <= margin, gap > -margin
            row, node = np.concatenate([row[low], row[high]]), np.concatenate([2 * node[low], 2 * node[high] + 1])
        return row, node


def _centres(unit: np.ndarray, least: float, dense: int) -> tuple[np.ndarray, np.ndarray]:
    """(centres of the balls, the sample vectors that are in none): the densest first, until fewer than ``dense`` near vectors are left anywhere."""
    n, x = len(unit), unit.astype(np.float32)
    near = np.zeros((n, (n + 7) // 8), dtype=np.uint8)  # bits
    count = np.zeros(n, dtype=np.int64)
    for k in range(0, n, 500):
        some = x[k : k + 500] @ x.T >= least
        near[k : k + 500], count[k : k + 500] = np.packbits(some, axis=1), some.sum(axis=1)
    free, found = np.ones(n, dtype=bool), []
    while n and count.max() >= dense:
        found.append(int(count.argmax()))
        own = np.unpackbits(near[found[-1]], count=n).astype(bool) & free
        own[found[-1]] |= free[found[-1]]
        free &= ~own
        at = np.flatnonzero(own)
        for k in range(0, len(at), 500):
            count -= np.unpackbits(near[at[k : k + 500]], axis=1, count=n).sum(axis=0, dtype=np.int64)
        count[found[-1]] = 0
    return unit[found], unit[free]


def _place(forest, balls, least: float, trees: int, kind: str, dim: int):
    """Rows (vid, weight, raw) -> one row per vector and leaf, with the codes of all its leaves, or per vector and ball (leaf -1, -2, ..)."""
    # within twice the linking angle of the centre, and a little more for rounding
    wide = 2 * least * least - 1 - 1e-9 if least > 0 else -2.0

    def in_balls(part: pa.RecordBatch, unit: np.ndarray) -> tuple[pa.RecordBatch | None, np.ndarray]:
        """(rows of the vectors in balls and halos, which vectors have no home)."""
        centres = balls.value
        if not len(centres):
            return None, np.ones(len(unit), dtype=bool)
        cosine = unit @ centres.T
        inside = cosine >= least
        home = np.where(inside.any(axis=1), inside.argmax(axis=1), len(centres))
        # a pair of two homes is found in the first of them
        row, ball = np.nonzero((cosine >= wide) & (np.arange(len(centres)) <= home[:, None]))
        at = pa.array(row)
        rows = pa.RecordBatch.from_arrays(
            [pa.array((-1 - ball).astype(np.int32)), part.column("vid").take(at), part.column("weight").take(at), part.column("raw").take(at),
             pa.array([b""] * len(row), type=pa.binary()), pa.array(ball < home[row])],
            names=["leaf", "vid", "weight", "raw", "codes", "halo"],
        )
        return rows, home == len(centres)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = forest.value
        for batch in batches:
            for k in range(0, batch.num_rows, 2000):
                part = batch.slice(k, 2000)
                if not part.num_rows:
                    continue
                unit = _units(part.column("raw").to_pylist(), kind, dim)
                held, free = in_balls(part, unit)
                if held is not None and held.num_rows:
                    yield held
                part, unit = part.filter(pa.array(free)), unit[free]
                if not part.num_rows:
                    continue
                rows, codes = [], []
                for t in range(trees):
                    r, n = f.leaves(unit, t)
                    rows.append(r)
                    codes.append((n + (t << _TREE_BITS)).astype(np.int32))
                row, code = np.concatenate(rows), np.concatenate(codes)
                order = np.lexsort((code, row))
                row, code = row[order], code[order]
                counts = np.bincount(row, minlength=part.num_rows)
                ends = np.cumsum(counts)
                own = [code[e - c : e].tobytes() for c, e in zip(counts, ends)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(code), part.column("vid").take(pa.array(row)), part.column("weight").take(pa.array(row)),
                     part.column("raw").take(pa.array(row)), pa.array([own[i] for i in row], type=pa.binary()), pa.array(np.zeros(len(row), dtype=bool))],
                    names=["leaf", "vid", "weight", "raw", "codes", "halo"],
                )

    return run


def _earlier(codes: list[np.ndarray], leaf: int) -> np.ndarray:
    """(vectors, leaves): membership in the leaves before this one that several of the vectors share."""
    flat = np.concatenate(codes)
    row = np.repeat(np.arange(len(codes)), [len(c) for c in codes])
    row, flat = row[flat < leaf], flat[flat < leaf]
    _, column, count = np.unique(flat, return_inverse=True, return_counts=True)
    number = np.cumsum(count > 1) - 1
    some = count[column] > 1
    out = np.zeros((len(codes), int((count > 1).sum())), dtype=np.float32)
    out[row[some], number[column[some]]] = 1
    return out


def _compare(kind: str, dim: int, least: float):
    """One part of a leaf against another (or itself): new links per vector and spanning edges."""

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        group = group.drop_duplicates(["vid", "side"])
        side = group.side.to_numpy()
        unit = _units(list(group.raw), kind, dim)
        ids, weight = group.vid.to_numpy(), group.weight.to_numpy()
        xs, ys = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        same = key[1] == key[2]
        ys = xs if same else ys
        product = unit[xs] @ unit[ys].T
        near = product >= least
        # the blocked product may differ in its last bits: near the threshold a plain sum decides
        for i, j in zip(*np.nonzero(np.abs(product - least) < 1e-12)):
            near[i, j] = float(np.dot(unit[xs[i]], unit[ys[j]])) >= least
        if same:
            np.fill_diagonal(near, False)
        xs_some, ys_some = np.flatnonzero(near.any(axis=1)), np.flatnonzero(near.any(axis=0))
        if not len(xs_some):
            return pd.DataFrame({"a": [], "n": [], "b": []}).astype("int64")
        near, xs, ys = near[np.ix_(xs_some, ys_some)], xs[xs_some], ys[ys_some]
        both = np.union1d(xs, ys)
        met = _earlier([np.frombuffer(c, dtype=np.int32) for c in group.codes.iloc[both]], key[0])
        near &= ~(met[np.searchsorted(both, xs)] @ met[np.searchsorted(both, ys)].T > 0)
        links = np.zeros(len(unit), dtype=np.int64)
        links[xs] += near @ weight[ys]
        if not same:
            links[ys] += weight[xs] @ near
        # labels fall to the least id of each group of linked vectors
        label = ids.copy()
        while True:
            before = label.copy()
            label[xs] = np.minimum(label[xs], np.where(near, label[ys], np.iinfo(np.int64).max).min(axis=1))
            label[ys] = np.minimum(label[ys], np.where(near, label[xs][:, None], np.iinfo(np.int64).max).min(axis=0))
            if (label == before).all():
                break
        some = links > 0
        return pd.DataFrame({"a": ids[some], "n": links[some], "b": label[some]})

    return run


def near_vectors(vectors: DataFrame, least: float = 0.9, trees: int = TREES, spill: float = SPILL, leaf: int = LEAF, dense: int = DENSE, sample: int = SAMPLE, part: int = 1500, seed: int = 7) -> DataFrame:
    """vectors(vec_id, embedding, ...) -> (vec_id, n_links, component_id, kept), one row per input row.

    Rows are linked when the cosine of their vectors is >= ``least`` and one of them has its home in a ball (around ``dense``
    or more sample vectors) or the forest brings them together (the recall is measured in the tests).  ``n_links`` counts other rows; ``component_id`` is the
    smallest vec_id reachable.  Null, zero, empty, non-finite vectors, and those of another
    length than most of the sample, link with nothing.  The splits are fitted on at most ``sample`` rows; every
    row is indexed.  The trees are so deep that a leaf has about half of ``part`` vectors or less, whatever the
    table's size; leaves and balls of more than ``part`` vectors are compared in parts, all against all.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "forest")
    kind = "<f4" if dict(vectors.dtypes)["embedding"] == "array<float>" else "<f8"
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    fit = rows.where(F.size("embedding") > 0).orderBy(F.xxhash64("vec_id")).limit(sample).select("embedding").toArrow().column(0)
    fit = fit.combine_chunks() if fit.num_chunks != 1 else fit.chunk(0)
    dims = pa.compute.list_value_length(fit).to_pylist()
    if not dims:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.col("vec_id").isNotNull().alias("kept"))
    dim = max(set(dims), key=lambda d: (dims.count(d), d))
    seen = _usable(fit, dim)[0]
    seen = np.unique(seen, axis=0)

    def stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, at = _usable(batch.column("embedding"), dim)
            own: list = [None] * batch.num_rows
            for i, v in zip(at.tolist(), (x + 0.0).astype(kind)):  # -0 and 0 are equal
                own[i] = v.tobytes()
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(own, type=pa.binary())], names=["vec_id", "raw"])

    keyed = scratch.save(rows.mapInArrow(stored, "vec_id long, raw binary"), "rows")
    distinct = scratch.save(
        keyed.where("raw is not null and vec_id is not null").groupBy("raw").agg(F.min("vec_id").alias("first"), F.count("*").alias("weight")).withColumn("vid", F.monotonically_increasing_id()), "distinct"
    )
    centres, free = _centres(_unit_rows(seen), least, dense)
    least_depth = int(np.ceil(np.log2(max(1, 2 * distinct.count() * len(free) / max(1, len(seen)) / part))))
    forest, balls = spark.sparkContext.broadcast(Forest(free, trees, leaf, spill, seed, least_depth)), spark.sparkContext.broadcast(centres)
    placed = scratch.save(
        distinct.select("vid", "weight", "raw").mapInArrow(_place(forest, balls, least, trees, kind, dim), "leaf int, vid long, weight long, raw binary, codes binary, halo boolean"), "placed"
    )
    # a leaf of many vectors is cut into parts; each pair of its parts is a group of its own, but for two parts of a halo
    sizes = placed.groupBy("leaf").agg(F.count("*").alias("c"), F.count_if(~F.col("halo")).alias("own")).where("c > 1 and own > 0")
    sizes = sizes.select("leaf", F.ceil(F.col("own") / part).cast("int").alias("parts"), F.ceil((F.col("c") - F.col("own")) / part).cast("int").alias("outer"))
    p = F.when(F.col("halo"), F.expr("parts + pmod(xxhash64(vid), outer)")).otherwise(F.expr("pmod(xxhash64(vid), parts)")).cast("int")
    last = F.when(F.col("halo"), F.col("parts")).otherwise(F.col("parts") + F.col("outer")) - 1
    cut = placed.join(sizes, "leaf").withColumn("p", p)
    met = cut.withColumn("q", F.explode(F.sequence(F.lit(0), last))).select(
        "leaf", F.least("p", "q").alias("p"), F.greatest("p", "q").alias("q"), (F.col("p") > F.col("q")).cast("int").alias("side"), "vid", "weight", "raw", "codes"
    )
    found = scratch.save(met.groupBy("leaf", "p", "q").applyInPandas(_compare(kind, dim, least), "a long, n long, b long"), "found")
    scratch.drop("placed")
    roots = connected_components(found.where("a <> b").select("a", "b"), scratch)
    counts = found.where("n > 0").groupBy("a").agg(F.sum("n").alias("n"))
    named = distinct.select("vid", "first", "weight").join(roots, F.col("vid") == F.col("id"), "left").withColumn("root", F.coalesce("root", "vid"))
    least_id = named.groupBy("root").agg(F.min("first").alias("component"))
    of_vid = named.join(least_id, "root").join(counts, F.col("vid") == F.col("a"), "left")
    of_vid = scratch.save(of_vid.select("vid", "component", (F.coalesce("n", F.lit(0)) + F.col("weight") - 1).alias("links")), "of_vid")
    of_raw = distinct.select("raw", "vid").join(of_vid, "vid").select("raw", "component", "links")
    out = keyed.join(of_raw, "raw", "left")
    own = F.when(F.col("vec_id").isNotNull(), F.coalesce("component", "vec_id"))
    linked = F.when(F.col("vec_id").isNotNull(), F.col("links"))
    out = out.select("vec_id", F.coalesce(linked, F.lit(0)).cast("long").alias("n_links"), own.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))
