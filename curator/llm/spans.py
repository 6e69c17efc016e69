"""Substring dedup: repeated windows of words, found by rolling hashes and removed after their first place.

Every window of ``size`` words has a rolling hash (of 128 bits where windows of the whole corpus meet).  Most windows occur once, and shuffling them all would move
several times the input.  So each window is first known by the smallest hash among its short grams: equal
windows have equal smallest grams, and runs of neighbouring windows share one.  Only the distinct smallest grams
are counted over the corpus; a window is counted itself if its gram is in another document too, or if its hash
occurs twice in its own document.  No window that repeats is missed by this.

Of equal windows the first by (key, position) stays.  The others' words are removed; overlapping windows merge
into maximal intervals.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.joins import BROADCAST_BYTES, spread
from curator.functions.workspace import release, stash
from curator.llm import flat
from curator.llm.rows import keyed, per_row

_U = np.uint64
WINDOW_WORDS = 20
#: Words of the short grams; a window of w words has w - GRAM + 1 of them.
GRAM = 5


def _sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each ``width`` consecutive values, by doubling."""
    out, have = values, 1
    while have < width:
        step = min(have, width - have)
        out = np.minimum(out[:-step], out[step:]) if len(out) > step else out[:0]
        have += step
    return out


def _windows(words: flat.Words, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each window: its row, first word (in the row) and smallest gram."""
    at = flat.gram_starts(words.first, size)
    owner = words.owners()[at]
    if not len(at):
        return owner, at, np.zeros(0, dtype=_U)
    short = min(GRAM, size)
    least = _sliding_min(flat.grams(words.hashes, short), size - short + 1)[at]
    return owner, at - words.first[owner], least


def _identity(words: flat.Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Two hashes of each window, in the order of :func:`_windows`."""
    at = flat.gram_starts(words.first, size)
    if not len(at):
        return np.zeros(0, dtype=_U), np.zeros(0, dtype=_U)
    return flat.grams(words.hashes, size)[at], flat.grams(flat.mix(words.hashes, 17), size)[at]


def _distinct_grams(owner: np.ndarray, least: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Each text's distinct smallest grams in hash order: their texts, values and numbers, and the number for each window."""
    order = np.lexsort((least, owner))
    new = np.ones(len(order), dtype=bool)
    new[1:] = (least[order][1:] != least[order][:-1]) | (owner[order][1:] != owner[order][:-1])
    heads = order[new]
    who = owner[heads]
    number = np.arange(len(heads)) - np.searchsorted(who, np.arange(rows))[who] if len(heads) else heads
    of_window = np.empty(len(order), dtype=np.int64)
    of_window[order] = number[np.cumsum(new) - 1] if len(heads) else 0
    return who, least[heads], number, of_window


def _anchors(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column(0).to_numpy()
            for i, j, words in flat.word_runs(batch.column(1), "space", False):
                owner, _, least = _windows(words, size)
                who, value, number, _ = _distinct_grams(owner, least, j - i)
                yield pa.RecordBatch.from_arrays([pa.array(flat.signed(value)), pa.array(keys[i + who]), pa.array(number.astype(np.int32))], names=["anchor", "key", "number"])

    return run


def _candidates(size: int):
    """Windows whose smallest gram is marked for the text, or whose hash repeats within it.

    Of equal windows in a slice only the first has to meet the rest of the corpus: the others are known to repeat
    (place -1 - at, under a hash of their own).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column(0).to_numpy()
            masks = batch.column(2)
            n_masks = np.asarray(masks.value_lengths().fill_null(0)).astype(np.int64)
            mask_at = np.concatenate([[0], np.cumsum(n_masks)])
            entries = masks.flatten()
            chunk = entries.field("chunk").to_numpy(zero_copy_only=False).astype(np.int64)
            bits = entries.field("bits").to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            for i, j, words in flat.word_runs(batch.column(1), "space", False):
                rows = j - i
                owner, at, least = _windows(words, size)
                if not len(owner):
                    continue
                whole, check = _identity(words, size)
                _, _, number, of_window = _distinct_grams(owner, least, rows)
                width = np.zeros(rows, dtype=np.int64)
                np.maximum.at(width, owner, of_window // 64 + 1)
                base = np.concatenate([[0], np.cumsum(width)])
                marked = np.zeros(int(base[-1]), dtype=_U)
                mine = slice(int(mask_at[i]), int(mask_at[j]))
                marked[base[np.repeat(np.arange(rows), n_masks[i:j])] + chunk[mine]] = bits[mine]
                take = (marked[base[owner] + of_window // 64] >> (of_window % 64).astype(_U)) & _U(1) > 0
                tag = flat.mix(whole ^ flat.mix(owner.astype(_U), 9))
                order = np.argsort(tag, kind="stable")
                same = tag[order][1:] == tag[order][:-1]
                take[order[1:][same]] = True
                take[order[:-1][same]] = True
                h, g, key, place = flat.signed(whole[take]), flat.signed(check[take]), keys[i + owner[take]], at[take]
                order = np.lexsort((place, key, g, h))
                h, g, key, place = h[order], g[order], key[order], place[order]
                again = np.zeros(len(h), dtype=bool)
                again[1:] = (h[1:] == h[:-1]) & (g[1:] == g[:-1])
                place = np.where(again, -1 - place, place)
                own = flat.signed(flat.mix(key.astype(_U) ^ flat.mix(place.astype(_U), 13)))
                yield pa.RecordBatch.from_arrays([pa.array(np.where(again, own, h)), pa.array(g), pa.array(key), pa.array(place.astype(np.int32))], names=["h", "g", "key", "at"])

    return run


def _merged(size: int):
    """Starts of repeated windows -> maximal intervals of words (first, stop)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans = []
            for at in batch.column(1):
                s = np.sort(np.asarray(at.values.to_numpy(zero_copy_only=False), dtype=np.int64))
                cut = np.flatnonzero(s[1:] > s[:-1] + size) + 1
                first, last = s[np.concatenate([[0], cut])], s[np.concatenate([cut - 1, [len(s) - 1]])]
                spans.append(np.stack([first, last + size], axis=1).reshape(-1).tolist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(spans, pa.list_(pa.int32()))], names=["key", "spans"])

    return run


def _few(df: DataFrame, bytes_each: str) -> DataFrame:
    """A written table, marked for broadcast if its measured bytes allow it."""
    n, width = df.agg(F.count(F.lit(1)), F.sum(F.expr(bytes_each))).first()
    return F.broadcast(df) if n and width <= BROADCAST_BYTES else df


def repeated_spans(docs: DataFrame, size: int = WINDOW_WORDS) -> DataFrame:
    """(key, text) -> (key, spans): flat (first, stop) word intervals covered by windows that start earlier elsewhere."""
    grams = stash(docs.select("key", "text").mapInArrow(_anchors(size), "anchor long, key long, number int"), "anchors")
    often = stash(grams.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "often")
    marked = spread(grams, often, ["anchor"]).groupBy("key", F.expr("number div 64").cast("int").alias("chunk")).agg(F.expr("bit_or(shiftleft(1L, number % 64))").alias("bits"))
    marked = stash(marked.groupBy("key").agg(F.collect_list(F.struct("chunk", "bits")).alias("masks")), "marked")
    for used in (grams, often):
        release(used)
    found = docs.select("key", "text").join(_few(marked, "40 + 16 * size(masks)"), "key", "left").select("key", "text", "masks").mapInArrow(_candidates(size), "h long, g long, key long, at int")
    # equal windows are known by 128 bits; a window has one row for each slice of the corpus at most, so its rows fit one sorted run
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("h", "g").orderBy("key", "at")))
    again = ranked.where("rank > 1 or at < 0").select("key", F.expr("if(at < 0, -1 - at, at)").alias("at"))
    out = stash(again.groupBy("key").agg(F.collect_list("at").alias("at")).mapInArrow(_merged(size), "key long, spans array<int>"), "spans")
    release(marked)
    return out


def _cut(with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans_of = batch.column(2)
            for i, j, words in flat.word_runs(batch.column(1), "space", False):
                n_words = words.counts
                removed, digests, texts, spans = [], [], [], []
                raw = words.data.tobytes()
                for d in range(i, j):
                    lo, n = int(words.first[d - i]), int(n_words[d - i])
                    s, e = words.starts[lo : lo + n], words.ends[lo : lo + n]
                    at = spans_of[d]
                    gone = np.zeros(n, dtype=bool)
                    if at.is_valid:
                        edges = np.asarray(at.values.to_numpy(zero_copy_only=False), dtype=np.int64)
                        gone[flat.spread(edges[::2], edges[1::2] - edges[::2])] = True
                    kept = b" ".join([raw[a:b] for a, b in zip(s[~gone].tolist(), e[~gone].tolist(), strict=True)])
                    removed.append(int(gone.sum()))
                    digests.append(hashlib.sha256(kept).hexdigest())
                    if with_text:
                        turn = np.flatnonzero(np.diff(np.concatenate([[0], gone.astype(np.int8), [0]])))
                        texts.append(kept.decode("utf-8", "replace"))
                        spans.append([{"first": int(a), "stop": int(b)} for a, b in zip(turn[::2], turn[1::2], strict=True)])
                cols = [batch.column(0).slice(i, j - i), pa.array(n_words.astype(np.int64)), pa.array(removed, type=pa.int64()), pa.array(digests, type=pa.string())]
                names = ["key", "n_words", "n_removed", "kept_sha256"]
                if with_text:
                    cols += [pa.array(texts, type=pa.string()), pa.array(spans, type=pa.list_(pa.struct([("first", pa.int32()), ("stop", pa.int32())])))]
                    names += ["kept_text", "removed"]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def substring_dedup(docs: DataFrame, size: int = WINDOW_WORDS, with_text: bool = True) -> DataFrame:
    """documents -> (doc_id, n_words, n_removed, kept_sha256[, kept_text, removed intervals]) for every row.

    Words are runs of non-blank bytes, as they stand.  Null and blank texts have no words.  Windows are judged
    on the input.  Rows that repeat an id and its text are one document; rows that share only the id stand in
    the order of their texts' hashes.
    """
    base, rows = keyed(docs)
    repeats = _few(repeated_spans(base, size), "40 + 4 * size(spans)")
    schema = "key long, n_words long, n_removed long, kept_sha256 string" + ", kept_text string, removed array<struct<first:int,stop:int>>" * with_text
    out = base.join(repeats, "key", "left").select("key", "text", "spans").mapInArrow(_cut(with_text), schema)
    return per_row(out, rows)
