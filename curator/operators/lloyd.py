"""K-means on the unit sphere: one scan per iteration serves all numbers of clusters at once.

A task multiplies its Arrow batches with the stacked centres of every resolution and sends back one partial sum per
centre; only centres, and of each resolution the one sample farthest from its centre, reach the driver.  Ties go to the
lowest cluster number.  ``metric`` 'l2' takes plain distances and means instead.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.functions.keyed import SEED, draw, key32

Centres = dict[int, np.ndarray]


def matrix(column: pa.Array) -> np.ndarray:
    """Rows of a list column of equal lengths."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def probe_sample(feats: DataFrame, fraction: float = 0.2, seed: int = SEED, cap: int | None = None) -> DataFrame:
    """A keyed share of the samples: the same on any partitioning.  ``cap`` bounds the rows by lowering the share."""
    if cap is not None:
        n = feats.count()
        fraction = min(fraction, cap / n) if n else fraction
    return feats.where(draw("doc_id", seed, "probe") < fraction)


def seed_rows(probe: DataFrame, k: int, seed: int = SEED, how: str = "hash", rounds: int = 4) -> np.ndarray:
    """k starting centres: the k smallest keyed hashes, or spread out by oversampling far samples ('parallel')."""
    first = probe.select("emb", key32("doc_id", seed, "seeds").alias("h"), "doc_id").orderBy("h", "doc_id").limit(k)
    rows = [r["emb"] for r in first.collect()]  # k vectors
    if how == "hash" or len(rows) < 2:
        return np.array(rows)
    chosen = np.array(rows[:1])
    for step in range(rounds):
        scored = assign(probe, chosen, keep=("emb",)).withColumn("cost", F.col("dist") * F.col("dist"))
        total = scored.agg(F.sum("cost")).first()[0] or 0.0
        if total <= 0:
            break
        chance = F.col("cost") * F.lit(2.0 * k / rounds / total)
        u = draw("doc_id", seed + 1 + step, "seeds")
        picked = scored.where(u < chance).select("emb", u.alias("u")).orderBy("u").limit(4 * k)
        more = [r["emb"] for r in picked.collect()]
        chosen = np.concatenate([chosen, np.array(more)]) if more else chosen
    if len(chosen) < k:
        return np.array(rows)
    # the candidates, weighted by what they attract, come down to k by greedy spreading
    attracted = {r["k"]: r["count"] for r in assign(probe, chosen).groupBy("k").count().collect()}
    weight = np.array([attracted.get(i, 0) for i in range(len(chosen))], dtype=float)
    take = [int(np.argmax(weight))]
    far = 2 - 2 * chosen @ chosen[take[0]]
    while len(take) < k:
        far[take] = 0
        at = int(np.argmax(far * weight)) if (far * weight).max() > 0 else next(i for i in range(len(chosen)) if i not in take)
        take.append(at)
        far = np.minimum(far, 2 - 2 * chosen @ chosen[at])
    return chosen[take]


def _nearest(x: np.ndarray, mu: np.ndarray, metric: str = "cosine") -> tuple[np.ndarray, np.ndarray]:
    """Nearest centre (highest cosine or least distance, lowest number on ties) and the distance to it, by differences."""
    k = np.empty(len(x), dtype=np.int32)
    d = np.empty(len(x))
    handicap = np.zeros(len(mu)) if metric == "cosine" else (mu * mu).sum(axis=1) / 2
    for a in range(0, len(x), 4096):
        part = x[a : a + 4096]
        k[a : a + 4096] = np.argmax(np.round(part @ mu.T - handicap, 12), axis=1)
        d[a : a + 4096] = np.sqrt(((part - mu[k[a : a + 4096]]) ** 2).sum(axis=1))
    return k, d


#: Tasks that add up the partial sums of all others.
MERGERS = 8
#: A resolution's stacked (sum, number, distance) of each centre, and its farthest sample.
PARTIAL = "resolution int, sums binary, d double, far binary"
Partial = dict[int, tuple[np.ndarray, float, bytes]]


def _add(to: Partial, resolution: int, sums: np.ndarray, d: float, far: bytes) -> None:
    if resolution not in to:
        to[resolution] = sums.copy(), d, far
    else:
        have, most, v = to[resolution]
        have += sums
        to[resolution] = (have, d, far) if d > most else (have, most, v)


def _rows_of(parts: Partial) -> pa.RecordBatch:
    cols = [list(parts), [s.tobytes() for s, _, _ in parts.values()], [d for _, d, _ in parts.values()], [v for _, _, v in parts.values()]]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.binary(), pa.float64(), pa.binary()), strict=True)], names=["resolution", "sums", "d", "far"])


def _partial_sums(shared, metric: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centres: Centres = shared.value
        parts: Partial = {}
        for batch in batches:
            x = matrix(batch.column(0))
            if not len(x):
                continue
            for r, mu in centres.items():
                k, d = _nearest(x, mu, metric)
                order = np.argsort(k, kind="stable")
                ks, at = np.unique(k[order], return_index=True)
                sums = np.zeros((len(mu), mu.shape[1] + 2))
                sums[ks, :-2] = np.add.reduceat(x[order], at, axis=0)
                sums[:, -2] = np.bincount(k, minlength=len(mu))
                sums[:, -1] = np.bincount(k, weights=d, minlength=len(mu))
                _add(parts, r, sums, float(d.max()), x[int(np.argmax(d))].tobytes())
        yield _rows_of(parts)

    return run


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts: Partial = {}
    for batch in batches:
        for row in batch.to_pylist():
            _add(parts, row["resolution"], np.frombuffer(row["sums"]), row["d"], row["far"])
    yield _rows_of(parts)


def step(probe: DataFrame, centres: Centres, metric: str = "cosine") -> tuple[Centres, dict[int, float]]:
    """One iteration for all resolutions: new centres and the mean distance of each.

    The first empty cluster moves to the sample farthest from its centre; others wait, and keep theirs.
    """
    shared = probe.sparkSession.sparkContext.broadcast(centres)
    parts = probe.select("emb").mapInArrow(_partial_sums(shared, metric), PARTIAL)
    total: Partial = {}
    for row in parts.repartition(MERGERS).mapInArrow(_merged, PARTIAL).collect():  # a matrix for each merger and resolution
        _add(total, row["resolution"], np.frombuffer(row["sums"]), row["d"], bytes(row["far"]))
    new = {r: mu.copy() for r, mu in centres.items()}
    cost = dict.fromkeys(centres, 0.0)
    for r, (sums, _, far) in total.items():
        sums = sums.reshape(len(new[r]), -1)
        n = sums[:, -2]
        full = np.flatnonzero(n)
        v = sums[full, :-2] / n[full, None]
        length = np.linalg.norm(v, axis=1, keepdims=True) if metric == "cosine" else np.ones((len(v), 1))
        new[r][full] = np.where(length > 0, v / np.where(length > 0, length, 1.0), new[r][full])
        empty = np.flatnonzero(n == 0)
        if len(empty):
            new[r][empty[0]] = np.frombuffer(far)
        cost[r] = float(sums[:, -1].sum() / n.sum())
    return new, cost


def sweep(probe: DataFrame, grid: list[int], iters: int = 20, tol: float = 1e-4, seed: int = SEED, how: str = "hash", metric: str = "cosine") -> Centres:
    """Centres for every K of the grid.  A K beyond the number of samples is left out."""
    probe = probe.select("doc_id", "emb").persist()
    try:
        start = seed_rows(probe, max(grid), seed)
        centres = {k: start[:k] if how == "hash" else seed_rows(probe, k, seed, how) for k in sorted(set(grid)) if k <= len(start)}
        last: dict[int, float] = {}
        for _ in range(iters):
            centres, now = step(probe, centres, metric)
            if last and all(abs(last[r] - now[r]) <= tol * max(last[r], 1e-12) for r in now):
                break
            last = now
        return centres
    finally:
        probe.unpersist()


def fit(probe: DataFrame, k: int, iters: int = 20, tol: float = 1e-4, seed: int = SEED, how: str = "hash", metric: str = "cosine") -> np.ndarray:
    return sweep(probe, [k], iters, tol, seed, how, metric)[k]


def assign(feats: DataFrame, centres: np.ndarray, keep: tuple[str, ...] = (), k: str = "k", dist: str = "dist", metric: str = "cosine") -> DataFrame:
    """(doc_id, kept columns, k, dist): nearest centre of every sample; map-only, centres broadcast (K x d numbers)."""
    # a stream's plan outlives the broadcasts of the call that made it: its centres travel in the function
    shared = None if feats.isStreaming else feats.sparkSession.sparkContext.broadcast(centres)
    columns = ["doc_id", *[c for c in keep if c != "doc_id"]]
    source = feats.select(*columns, F.col("emb").alias("__emb"))
    own = centres if shared is None else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mu = own if shared is None else shared.value
        for batch in batches:
            x = matrix(batch.column(batch.num_columns - 1))
            ks, ds = _nearest(x, mu, metric) if len(x) else (np.zeros(0, dtype=np.int32), np.zeros(0))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(ks, pa.int32()), pa.array(ds, pa.float64())], names=[*columns, k, dist])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[:-1])
    return source.mapInArrow(run, f"{fields}, `{k}` int, `{dist}` double")


def assign_all(feats: DataFrame, centres: Centres, keep: tuple[str, ...] = ()) -> DataFrame:
    """(kept columns, resolution, k, dist): the nearest centre at every resolution, out of one scan."""
    shared = feats.sparkSession.sparkContext.broadcast(centres)
    source = feats.select(*keep, F.col("emb").alias("__emb"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column(batch.num_columns - 1))
            for r, mu in shared.value.items() if batch.num_rows else ():
                ks, ds = _nearest(x, mu)
                yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(np.full(len(x), r, dtype=np.int32)), pa.array(ks), pa.array(ds)], names=[*keep, "resolution", "k", "dist"])

    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in source.schema.fields[:-1])
    return source.mapInArrow(run, f"{fields}resolution int, k int, dist double")


def frame(spark, centres: Centres) -> DataFrame:
    """Centres as a table (resolution, k, mu)."""
    rows = [(r, i, mu[i].tolist()) for r, mu in centres.items() for i in range(len(mu))]
    return spark.createDataFrame(rows, "resolution int, k int, mu array<double>")


def fit_mllib(probe: DataFrame, k: int, seed: int = SEED, iters: int = 20) -> np.ndarray:
    """The library's K-means with cosine distance."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = probe.select(array_to_vector("emb").alias("features"))
    return np.array(KMeans(k=k, seed=seed, maxIter=iters, distanceMeasure="cosine").fit(rows).clusterCenters())
