"""Token counts of a unigram vocabulary by Viterbi, without making the tokens.

An Aho-Corasick automaton lists the vocabulary pieces that end at each character.  Dynamic programming keeps the
best score and its piece count at each place and nothing else.  Ties follow the public tokenizers: of equally good
ways to reach a place the one whose last piece starts first stays.  A character that is no piece costs the lowest
piece score less ``UNKNOWN_PENALTY`` and counts as its UTF-8 bytes.

Texts are cut into segments that no piece can straddle, and each distinct segment is solved once per slice (and
remembered by the worker, within a bound).  Scores of the vocabulary used here are whole numbers, so sums over
segments are exact and ties in a segment are ties in the text.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.llm import flat
from curator.llm.pieces import _SPACE, _segments, model_path, vocabulary

UNKNOWN_PENALTY = 10.0
#: Segments that a worker remembers at most.
MEMO = 400_000


class Unigram:
    """Pieces and scores of a vocabulary file, as an automaton."""

    def __init__(self, path: str):
        import ahocorasick

        v = vocabulary(path)
        lib = v.lib
        self.v = v
        self.scores = {lib.id_to_piece(i): lib.get_score(i) for i in range(v.size) if not (lib.is_control(i) or lib.is_unknown(i) or lib.is_byte(i) or lib.is_unused(i))}
        self.singles = {p for p in self.scores if len(p) == 1}
        self.unknown = min(self.scores.values()) - UNKNOWN_PENALTY
        self.automaton = ahocorasick.Automaton()
        for p, s in self.scores.items():
            self.automaton.add_word(p, (len(p), s))
        self.automaton.make_automaton()
        self.memo: dict[int, tuple[float, int, int]] = {}

    def solve(self, text: str) -> tuple[float, int, int]:
        """Best score, pieces and unknown characters of a text of any length."""
        n = len(text)
        best, pieces, odd = [None] * (n + 1), [0] * (n + 1), [0] * (n + 1)
        best[0] = 0.0
        matches = self.automaton.iter(text)
        one = next(matches, None)
        singles = self.singles
        for end in range(1, n + 1):
            top = at = None
            while one is not None and one[0] == end - 1:  # longest first
                length, score = one[1]
                value = best[end - length] + score
                if top is None or value > top:
                    top, at = value, end - length
                one = next(matches, None)
            if text[end - 1] not in singles:
                value = best[end - 1] + self.unknown
                if top is None or value > top:
                    best[end], pieces[end], odd[end] = value, pieces[end - 1] + len(text[end - 1].encode("utf-8", "surrogatepass")), odd[end - 1] + 1
                    continue
            best[end], pieces[end], odd[end] = top, pieces[at] + 1, odd[at]
        return best[n], pieces[n], odd[n]


@lru_cache(maxsize=2)
def unigram(path: str) -> Unigram:
    return Unigram(path)


def count_flat(u: Unigram, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Score, pieces and unknown characters of each text."""
    data, offsets = data[int(offsets[0]) : int(offsets[-1])], offsets - offsets[0]
    full = np.diff(offsets) > 0
    data = np.insert(data, offsets[:-1][full], np.uint8(0x20))
    offsets = offsets + np.concatenate([[0], np.cumsum(full)])
    begins, first = _segments(u.v, data, offsets)
    rows = len(offsets) - 1
    if not len(begins):
        return np.zeros(rows), np.zeros(rows, dtype=np.int64), np.zeros(rows, dtype=np.int64)
    stops = np.append(begins[1:], len(data))
    hashes, one, which = np.unique(flat.hash_ranges(data, begins, stops), return_index=True, return_inverse=True)
    raw, memo = data.tobytes(), u.memo
    solved = np.empty((len(one), 3))
    for k, (h, a, b) in enumerate(zip(hashes.tolist(), begins[one].tolist(), stops[one].tolist(), strict=True)):
        got = memo.get(h)
        if got is None:
            got = u.solve(raw[a:b].decode("utf-8", "replace").replace(" ", _SPACE))
            if len(memo) >= MEMO:
                memo.clear()
            memo[h] = got
        solved[k] = got
    sums = np.concatenate([np.zeros((1, 3)), np.cumsum(solved[which], axis=0)])
    each = sums[first[1:]] - sums[first[:-1]]
    return each[:, 0], each[:, 1].astype(np.int64), each[:, 2].astype(np.int64)


def _run(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        u = unigram(path)
        for batch in batches:
            data, offsets = flat.buffers(batch.column(1))
            for i, j in flat.slices(offsets):
                score, pieces, odd = count_flat(u, data, offsets[i : j + 1])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(pieces), pa.array(odd), pa.array(score)], names=["doc_id", "n_tokens", "n_unknown", "best_score"])

    return run


def token_counts(docs: DataFrame, path: str | None = None) -> DataFrame:
    """documents -> (doc_id, n_tokens, n_unknown, best_score) for every row, map-only.

    A blank is put before each text that isn't empty and blanks are written as the vocabulary writes them.  Null
    and empty texts have no token and score 0.  A literal blank mark in a text reads as a blank.  Rows are counted one by
    one, repeated ones alike; other columns are ignored.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.replace(F.col("text").cast("string"), F.lit(_SPACE), F.lit(" ")).alias("text"))
    return rows.mapInArrow(_run(path or model_path()), "doc_id long, n_tokens long, n_unknown long, best_score double")
