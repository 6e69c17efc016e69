"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

The model is fitted on at most ``MAX_TRAIN`` labelled rows (chosen by a hash of doc_id, whole texts, until they have
``MAX_FEATURES`` features), one pass after another over examples in hash order, so a re-run gives the same weights.  Per-coordinate rates and the L1 term leave a few
thousand non-zero weights of 2^20, which are what scoring ships to the tasks; scoring reads every whole text once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from curator.llm import flat

_U = np.uint64
BITS = 20
#: Bounds on the labelled rows that the model is fitted on, and on their features (four bytes each in the fitting task).
MAX_TRAIN, MAX_FEATURES = 20_000, 48_000_000
#: The setting of least log loss in ``compare_settings``, on the two largest tables it was run on.
EPOCHS = 4
ALPHA, BETA, L1, L2 = 2.0, 1.0, 8.0, 0.5
THRESHOLD = 0.3


def features(words: flat.Words) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features of each text (with repeats) and the text each belongs to: words, pairs, triples, skip-pairs."""
    h, n = words.hashes, len(words.hashes)
    owner = words.owners()
    parts, owners = [flat.mix(h, 1)], [owner]
    for name, lags in ((2, (0, 1)), (3, (0, 1, 2)), (4, (0, 2)), (5, (0, 3))):
        far = lags[-1]
        if n <= far:
            continue
        m = n - far
        v = h[:m]
        for k, lag in enumerate(lags[1:], 1):
            v = v * _U(0x9E3779B97F4A7C15) + flat.mix(h[lag : lag + m], k)
        same = owner[:m] == owner[far:]
        parts.append(flat.mix(v[same], name))
        owners.append(owner[:m][same])
    return (np.concatenate(parts) >> _U(64 - BITS)).astype(np.int64), np.concatenate(owners)


def _distinct(index: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    both = np.unique(owner << BITS | index)
    return both & ((1 << BITS) - 1), both >> BITS


def fit(examples: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS, alpha: float = ALPHA, l1: float = L1) -> tuple[np.ndarray, np.ndarray, float]:
    """Indexes and values of the non-zero weights, and the bias."""
    z, n = np.zeros(1 << BITS), np.zeros(1 << BITS)
    bz = bn = bias = 0.0
    for _ in range(epochs):
        for x, y in zip(examples, labels, strict=True):
            zx, nx = z[x], n[x]
            root = np.sqrt(nx)
            w = np.where(np.abs(zx) <= l1, 0.0, -(zx - np.sign(zx) * l1) / ((BETA + root) / alpha + L2))
            bias = -bz / ((BETA + np.sqrt(bn)) / alpha)
            g = 1 / (1 + np.exp(-np.clip(w.sum() + bias, -35, 35))) - y
            after = nx + g * g
            z[x] = zx + g - (np.sqrt(after) - root) / alpha * w
            n[x] = after
            bz += g - (np.sqrt(bn + g * g) - np.sqrt(bn)) / alpha * bias
            bn += g * g
    w = np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((BETA + np.sqrt(n)) / alpha + L2))
    at = np.flatnonzero(w)
    return at, w[at], float(-bz / ((BETA + np.sqrt(bn)) / alpha))


def _examples(texts: pa.Array) -> list[np.ndarray]:
    """Distinct features of each text."""
    out: list[np.ndarray] = []
    for i, j, words in flat.word_runs(texts, "alnum", True, 1 << 20):
        index, owner = _distinct(*features(words))
        index = index.astype(np.int32)
        at = np.searchsorted(owner, np.arange(j - i + 1))
        out += [index[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]
    return out


def _fit_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    examples, labels, held = [], [], 0
    for batch in batches:
        if held > MAX_FEATURES:  # the input is read to its end
            continue
        for a in range(0, batch.num_rows, 256):
            part = batch.slice(a, 256)
            if held <= MAX_FEATURES:
                examples += _examples(part.column(0))
                labels.append(part.column(1).to_numpy())
                held += sum(map(len, examples[-part.num_rows :]))
    at, w, bias = fit(examples, np.concatenate(labels) if labels else np.zeros(0))
    yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(w, bias))], names=["at", "weight"])


def _learnable(docs: DataFrame, labels: DataFrame, may_learn: Column, most: int) -> DataFrame:
    """(doc_id, text, y, place) of at most ``most`` labelled rows, chosen and placed by a hash of doc_id."""
    given = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & may_learn)
    given = given.groupBy("doc_id").agg(F.max(F.col("toxic").cast("double")).alias("y")).withColumn("place", F.xxhash64("doc_id"))
    n = given.count()
    if n > most:  # a keyed share, then the exact bound
        cut = int((2**64) * min(1.0, 1.1 * most / n)) - 2**63
        given = given.where(F.col("place") <= F.lit(min(cut, 2**63 - 1)).cast("long"))
    given = F.broadcast(given.orderBy("place", "doc_id").limit(most))
    return docs.select("doc_id", "text").join(given, "doc_id")


def train(docs: DataFrame, labels: DataFrame, may_learn: Column, most: int = MAX_TRAIN) -> tuple[np.ndarray, np.ndarray, float]:
    """Weights learned from labelled documents for which ``may_learn`` (on doc_id) holds.

    Labels that are null, or of documents that aren't there, are not used; a document with several is toxic if one says so.
    """
    texts = _learnable(docs, labels, may_learn, most)
    ordered = texts.repartition(1).sortWithinPartitions("place", F.xxhash64("text"))
    rows = ordered.select("text", "y").mapInArrow(_fit_task, "at long, weight double").toPandas()
    at, w = rows["at"].to_numpy(), rows["weight"].to_numpy()
    return at[at >= 0], w[at >= 0], float(w[at < 0].sum())


def _compare_task(table: pa.Table) -> pa.Table:
    table = table.sort_by("place").combine_chunks()
    alpha, l1, epochs = (table[c][0].as_py() for c in ("alpha", "l1", "epochs"))
    x, y, inner = _examples(table["text"].combine_chunks()), table["y"].to_numpy(), table["inner"].to_numpy()
    at, w, bias = fit([x[i] for i in np.flatnonzero(~inner)], y[~inner], epochs, alpha, l1)
    dense = np.zeros(1 << BITS)
    dense[at] = w
    total = np.array([dense[x[i]].sum() for i in np.flatnonzero(inner)]) + bias
    p, truth = 1 / (1 + np.exp(-np.clip(total, -35, 35))), y[inner] > 0
    loss = -np.log(np.clip(np.where(truth, p, 1 - p), 1e-9, 1))
    hits = (p >= THRESHOLD) & truth
    row = (alpha, l1, epochs, len(at), loss.mean() if len(loss) else None, hits.sum() / max(1, (p >= THRESHOLD).sum()), hits.sum() / max(1, truth.sum()))
    return pa.table({name: [value] for name, value in zip(("alpha", "l1", "epochs", "n_weights", "log_loss", "precision", "recall"), row, strict=True)})


def compare_settings(docs: DataFrame, labels: DataFrame, settings: list[tuple[float, float, int]], most: int = MAX_TRAIN) -> DataFrame:
    """(alpha, l1, epochs) settings -> a row each with log loss, precision and recall on an inner fold.

    Only rows that may be learned from are read: those whose crc32(doc_id) mod 4 is 3 judge, 0 and 1 are fitted
    on, and the held-out fold (2) takes no part.  A task fits one setting on at most ``most`` rows.
    """
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4
    rows = _learnable(_typed(docs), labels.select(F.col("doc_id").cast("long").alias("doc_id"), "toxic"), fold != 2, most)
    grid = F.array(*[F.struct(F.lit(float(a)).alias("alpha"), F.lit(float(b)).alias("l1"), F.lit(int(e)).alias("epochs")) for a, b, e in settings])
    rows = rows.select("text", "y", "place", (fold == 3).alias("inner"), F.explode(grid).alias("s")).select("text", "y", "place", "inner", "s.*")
    kinds = "alpha double, l1 double, epochs long, n_weights long, log_loss double, precision double, recall double"
    return rows.groupBy("alpha", "l1", "epochs").applyInArrow(_compare_task, kinds)


def _score_task(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, w, bias = shared.value
        table = np.zeros(1 << BITS, dtype=np.float32)
        table[at] = w
        for batch in batches:
            for i, j, words in flat.word_runs(batch.column(1), "alnum", True):
                index, owner = features(words)
                live = np.flatnonzero(table[index])
                index, owner = _distinct(index[live], owner[live])
                total = np.bincount(owner, weights=table[index], minlength=j - i) + bias
                score = 1 / (1 + np.exp(-np.clip(total, -35, 35)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(score)], names=["doc_id", "score"])

    return run


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray, float]) -> DataFrame:
    """(doc_id, score) of every row from its text alone; null and empty texts get the bias's score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # at most 2^20 weights
    return docs.select("doc_id", "text").mapInArrow(_score_task(shared), "doc_id long, score double")


def _typed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """documents, labels -> (doc_id, held_out, score, predicted) for every row.

    Rows whose crc32(doc_id) mod 4 is 2 are never learned from.  A null doc_id is not held out.  Rows are scored one by
    one, repeated ones alike; a repeated labelled row is learned from as often as it stands in ``docs``.
    """
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4
    docs = _typed(docs)
    model = train(docs, labels.select(F.col("doc_id").cast("long").alias("doc_id"), "toxic"), fold != 2)
    out = score(docs, model)
    return out.select("doc_id", F.coalesce(fold == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def clean_documents(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that score under the threshold, with all their columns; null and empty texts have the bias's score."""
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4
    typed = _typed(docs)
    shared = docs.sparkSession.sparkContext.broadcast(train(typed, labels.select(F.col("doc_id").cast("long").alias("doc_id"), "toxic"), fold != 2))
    names = docs.columns
    at = names.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pair = pa.RecordBatch.from_arrays([pa.array(range(batch.num_rows), pa.int64()), batch.column(at)], names=["doc_id", "text"])
            for scored in _score_task(shared)(iter([pair])):
                yield batch.take(scored.column(0).filter(pa.array(scored.column(1).to_numpy() < threshold)))

    return docs.mapInArrow(run, docs.schema)
