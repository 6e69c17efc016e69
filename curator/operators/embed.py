"""Vectors for texts: a given column, hashed character n-grams, or a user's model."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.functions.vectors import unit


def from_column(df: DataFrame, column: str = "embedding", d: int = 64) -> DataFrame:
    """``emb``: the column as unit vectors; another length is an error."""
    v = F.col(column).cast("array<double>")
    checked = F.when(F.size(v) == d, v).otherwise(F.raise_error(F.lit(f"vectors of {d} numbers are expected")).cast("array<double>"))
    return df.withColumn("emb", unit(checked, d))


#: Bytes of text hashed at once.
SLICE = 1 << 20


def _hashed(d: int, ngram: tuple[int, int], seed: int):
    odd = [int(x) | 1 for x in np.random.default_rng(seed).integers(1, 1 << 62, ngram[1])]

    def vectors(data: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Unnormalised vectors of the texts at data[at[i] : at[i + 1]]."""
        rows = len(at) - 1
        out = np.zeros(rows * d)
        b, owner = data.astype(np.uint64), np.repeat(np.arange(rows), np.diff(at))
        raw = np.zeros(len(b), dtype=np.uint64)
        for n in range(1, ngram[1] + 1):
            if len(b) < n:
                break
            # the hash of n bytes goes on from that of n - 1
            raw = (raw[: len(b) - n + 1] + b[n - 1 :] + np.uint64(1)) * np.uint64(odd[n - 1])
            if n < ngram[0]:
                continue
            h = raw ^ (raw >> np.uint64(29))
            h *= np.uint64(0xBF58476D1CE4E5B9)
            h ^= h >> np.uint64(32)
            who = owner[: len(h)]
            inside = who == owner[n - 1 :]
            h, who = h[inside], who[inside]
            # texts stand in order: each one's hashes are sorted in place, much faster than all by two keys
            ends = np.searchsorted(who, np.arange(rows + 1)).tolist()
            for a, z in zip(ends[:-1], ends[1:], strict=True):
                h[a:z].sort()
            first = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (who[1:] != who[:-1])])) if len(h) else np.zeros(0, dtype=np.int64)
            counts = np.diff(np.append(first, len(h)))
            h, who = h[first], who[first]
            sign = np.where(h >> np.uint64(63), 1.0, -1.0)
            out += np.bincount(who * d + (h % np.uint64(d)).astype(np.int64), weights=sign * np.log1p(counts), minlength=rows * d)
        return out.reshape(rows, d)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = pc.utf8_lower(pc.fill_null(batch.column(batch.num_columns - 1), ""))
            lengths = np.concatenate([[0], np.cumsum(np.asarray(pc.binary_length(texts)).astype(np.int64))])
            i = 0
            while i < batch.num_rows:
                j = max(i + 1, int(np.searchsorted(lengths, lengths[i] + SLICE, side="right")) - 1)
                part = np.frombuffer(b"".join(texts.slice(i, j - i).cast(pa.binary()).to_pylist()), dtype=np.uint8)
                out = vectors(part, lengths[i : j + 1] - lengths[i])
                length = np.linalg.norm(out, axis=1, keepdims=True)
                out = np.divide(out, length, out=np.zeros_like(out), where=length > 0)
                embedded = pa.ListArray.from_arrays(pa.array(np.arange(0, out.size + 1, d, dtype=np.int32)), pa.array(out.reshape(-1)))
                yield pa.RecordBatch.from_arrays([*[c.slice(i, j - i) for c in batch.columns[:-1]], embedded], names=[*batch.schema.names[:-1], "emb"])
                i = j

    return run


def hashed_text(df: DataFrame, d: int = 64, ngram: tuple[int, int] = (3, 5), seed: int = 42, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Signed feature hashing of character n-grams with log-scaled counts, scaled to length one; empty texts give zeros."""
    source = df.select(*keep, "text")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[:-1])
    return source.mapInArrow(_hashed(d, ngram, seed), f"{fields}, emb array<double>")


def with_model(df: DataFrame, load: Callable[[], Callable[[list[str]], np.ndarray]], keep: tuple[str, ...] = ("doc_id",), batch: int = 256) -> DataFrame:
    """Vectors of a user's model: ``load`` runs once per task and returns texts -> matrix."""
    source = df.select(*keep, "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = load()
        for whole in batches:
            for a in range(0, whole.num_rows, batch):
                part = whole.slice(a, batch)
                x = np.asarray(model([t or "" for t in part.column(part.num_columns - 1).to_pylist()]), dtype=float)
                length = np.linalg.norm(x, axis=1, keepdims=True)
                x = np.divide(x, length, out=np.zeros_like(x), where=length > 0)
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(x.tolist(), pa.list_(pa.float64()))], names=[*part.schema.names[:-1], "emb"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[:-1])
    return source.mapInArrow(run, f"{fields}, emb array<double>")


