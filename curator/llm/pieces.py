"""SentencePiece BPE in merge rounds over flat arrays, and decoding by one gather.

Texts fall into segments that no vocabulary piece can straddle (a run of blanks with the word behind it, or a
character that is in no longer piece).  Each distinct segment of a slice is encoded once: its characters become
a flat symbol array with all other segments'; every round finds the smallest pair rank of each segment, merges
its leftmost occurrences together, compacts, and goes on until no pair is left.  Merging several occurrences at
once gives what one-at-a-time merging gives, unless a merged piece can at once be part of a better pair; for such
pieces (known from the vocabulary) only the leftmost one is merged in a round.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from curator.llm import flat

MODEL = "piece_bpe_32k.model"
_SPACE = "▁"
#: Bytes of text coded at once.
SLICE = 1 << 20
_NEVER = np.int32(2**31 - 1)


def model_path(name: str = MODEL) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Vocabulary:
    """Lookup arrays of one BPE model with byte fallback and a blank put before each text."""

    def __init__(self, path: str):
        import sentencepiece

        lib = self.lib = sentencepiece.SentencePieceProcessor(model_file=path)
        n = self.size = lib.vocab_size()
        names = [lib.id_to_piece(i) for i in range(n)]
        plain = [i for i in range(n) if not (lib.is_control(i) or lib.is_unknown(i) or lib.is_byte(i) or lib.is_unused(i))]
        ids = {names[i]: i for i in plain}
        scores = sorted({lib.get_score(i) for i in plain}, reverse=True)
        rank_of = {s: r for r, s in enumerate(scores)}
        self.begin, self.end = lib.bos_id(), lib.eos_id()
        self.byte_ids = np.array([lib.piece_to_id(f"<0x{b:02X}>") for b in range(256)], dtype=np.int64)
        self.char = np.full(0x110000, -1, dtype=np.int32)
        for p, i in ids.items():
            if len(p) == 1:
                self.char[ord(p)] = i
        joined = {c for p in ids if len(p) > 1 for c in p}
        if any(self.char[ord(c)] < 0 for c in joined) or any(_SPACE in p.lstrip(_SPACE) for p in ids):
            raise ValueError("this vocabulary needs another segmentation")
        #: ASCII characters that never merge with another
        self.alone = np.array([b < 128 and chr(b) not in joined and b != 0x20 for b in range(256)])
        self.char[0x20] = self.char[ord(_SPACE)]
        rank = {p: rank_of[lib.get_score(i)] for p, i in ids.items()}
        pairs, unsafe = {}, set()
        for p, i in ids.items():
            for cut in range(1, len(p)):
                a, b = p[:cut], p[cut:]
                if a in ids and b in ids:
                    pairs[(ids[a], ids[b])] = i
                    unsafe.update(ids[q] for q in (a, b) if rank[p] <= rank[q])
        self.rank = np.full(n, _NEVER, dtype=np.int32)
        for p, i in ids.items():
            self.rank[i] = rank[p]
        self.alone_only = np.zeros(n, dtype=bool)
        self.alone_only[list(unsafe)] = True
        bits = int(np.ceil(np.log2(max(4, 4 * len(pairs)))))
        self.shift = np.uint64(64 - bits)
        self.slots = np.full((1 << bits) + 64, -1, dtype=np.int64)
        self.made = np.full((1 << bits) + 64, -1, dtype=np.int32)
        self.probes = 1
        for (a, b), i in pairs.items():
            key = a << 32 | b
            at = int(((key * 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF) >> int(self.shift))
            start = at
            while self.slots[at] >= 0:
                at += 1
            self.slots[at], self.made[at] = key, i
            self.probes = max(self.probes, at - start + 1)
        blobs = []
        for i in range(n):
            if lib.is_byte(i):
                blobs.append(bytes([int(names[i][3:5], 16)]))
            elif lib.is_control(i):
                blobs.append(b"")
            elif lib.is_unknown(i):
                blobs.append(lib.decode([i]).encode())
            else:
                blobs.append(names[i].replace(_SPACE, " ").encode())
        self.blob = np.frombuffer(b"".join(blobs), dtype=np.uint8)
        self.blob_at = np.concatenate([[0], np.cumsum([len(b) for b in blobs])]).astype(np.int64)
        self.silent = np.array([lib.is_control(i) for i in range(n)])

    def merged(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Piece that two symbols make, or -1."""
        key = left.astype(np.int64) << 32 | right.astype(np.int64)
        at = ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)
        out = np.where(self.slots[at] == key, self.made[at], np.int32(-1))
        open_ = np.flatnonzero((out < 0) & (self.slots[at] >= 0))
        for step in range(1, self.probes):
            if not len(open_):
                break
            spot = at[open_] + step
            there = self.slots[spot]
            hit = there == key[open_]
            out[open_[hit]] = self.made[spot[hit]]
            open_ = open_[~hit & (there >= 0)]
        return out


@lru_cache(maxsize=4)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


def merge_rounds(v: Vocabulary, symbols: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of many segments (bounds ``first``, n+1; none empty) merged until no pair is left."""
    n = len(first) - 1
    counts_out = np.zeros(n, dtype=np.int64)
    done: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    seg = np.arange(n)
    sym, starts = symbols.astype(np.int32), first[:-1].astype(np.int64)

    def ranks(left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        ok = (left < v.size) & (right < v.size)
        made = np.full(len(left), -1, dtype=np.int32)
        made[ok] = v.merged(left[ok], right[ok])
        return made, np.where(made >= 0, v.rank[made], _NEVER)

    made, pr = np.full(len(sym), -1, dtype=np.int32), np.full(len(sym), _NEVER, dtype=np.int32)
    if len(sym) > 1:
        made[:-1], pr[:-1] = ranks(sym[:-1], sym[1:])
    ends = np.append(starts[1:], len(sym)) - 1
    pr[ends] = _NEVER
    while len(starts):
        least = np.minimum.reduceat(pr, starts)
        lengths = np.append(starts[1:], len(sym)) - starts
        over = least == _NEVER
        if over.any():  # finished segments leave
            at = np.repeat(over, lengths)
            done.append((seg[over], lengths[over], sym[at]))
            sym, pr, made = sym[~at], pr[~at], made[~at]
            seg, lengths, least = seg[~over], lengths[~over], least[~over]
            starts = np.cumsum(lengths) - lengths
            if not len(starts):
                break
        hit = pr == np.repeat(least, lengths)
        spots = np.flatnonzero(hit)
        owner = np.searchsorted(starts, spots, side="right") - 1
        # overlapping hits: every other one from the left of their run
        run = np.ones(len(spots), dtype=bool)
        run[1:] = (spots[1:] != spots[:-1] + 1) | (owner[1:] != owner[:-1])
        heads = np.flatnonzero(run)
        place = np.arange(len(spots)) - np.repeat(heads, np.diff(np.append(heads, len(spots))))
        take = place % 2 == 0
        lone = v.alone_only[made[spots]]
        if lone.any():
            leftmost = np.ones(len(spots), dtype=bool)
            leftmost[1:] = owner[1:] != owner[:-1]
            take &= ~lone | leftmost
        spots, owner = spots[take], owner[take]
        sym[spots] = made[spots]
        keep = np.ones(len(sym), dtype=bool)
        keep[spots + 1] = False
        fresh = np.zeros(len(sym), dtype=bool)
        fresh[spots] = True
        sym, pr, made, fresh = sym[keep], pr[keep], made[keep], fresh[keep]
        lengths = lengths - np.bincount(owner, minlength=len(starts))
        starts = np.cumsum(lengths) - lengths
        last = np.append(starts[1:], len(sym)) - 1
        again = fresh.copy()
        again[:-1] |= fresh[1:]
        again[last] = False
        at = np.flatnonzero(again)
        made[at], pr[at] = ranks(sym[at], sym[at + 1])
        pr[last] = _NEVER
    for s, lengths, _ in done:
        counts_out[s] = lengths
    bounds = np.concatenate([[0], np.cumsum(counts_out)])
    out = np.empty(int(bounds[-1]), dtype=np.int32)
    for s, lengths, values in done:
        out[flat.spread(bounds[s], lengths)] = values
    return out, bounds


def _segments(v: Vocabulary, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First byte of each segment, and the first segment of each text (n+1)."""
    n = len(data)
    start = np.zeros(n + 1, dtype=bool)
    blank, alone = data == 0x20, v.alone[data]
    start[:n] = alone
    start[1 : n + 1] |= alone
    start[1:n] |= blank[1:] & ~blank[:-1]
    start[offsets] = True
    start[n] = False
    at = np.flatnonzero(start)
    return at, np.searchsorted(at, offsets)


def encode_flat(v: Vocabulary, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids of each text, with begin and end ids, and the bounds (n+1)."""
    data, offsets = data[int(offsets[0]) : int(offsets[-1])], offsets - offsets[0]
    raw = data.tobytes()
    if _SPACE.encode() in raw:  # reads as a blank
        parts = [raw[a:b].replace(_SPACE.encode(), b" ") for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
        data = np.frombuffer(b"".join(parts), dtype=np.uint8)
        offsets = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
    full = np.diff(offsets) > 0
    data = np.insert(data, offsets[:-1][full], np.uint8(0x20))
    offsets = offsets + np.concatenate([[0], np.cumsum(full)])
    begins, first = _segments(v, data, offsets)
    stops = np.append(begins[1:], len(data))
    _, one, which = np.unique(flat.hash_ranges(data, begins, stops), return_index=True, return_inverse=True)
    seg_a, seg_n = begins[one], (stops - begins)[one]
    text = data[flat.spread(seg_a, seg_n)]
    code = np.frombuffer(text.tobytes().decode("utf-8", "replace").encode("utf-32-le"), dtype=np.uint32).astype(np.int64)
    byte_at = np.concatenate([[0], np.cumsum(seg_n)])
    chars = np.concatenate([[0], np.cumsum((text & 0xC0) != 0x80)])
    bounds = chars[byte_at]
    known = v.char[code]
    symbols = np.where(known >= 0, known, v.size + code)
    if len(one):
        made, at = merge_rounds(v, symbols, bounds)
    else:
        made, at = np.zeros(0, dtype=np.int32), np.zeros(1, dtype=np.int64)
    odd = np.flatnonzero(made >= v.size)
    if len(odd):  # characters outside the vocabulary: their bytes
        spelled = [v.byte_ids[list(chr(int(c) - v.size).encode("utf-8", "surrogatepass"))] for c in made[odd]]
        width = np.ones(len(made), dtype=np.int64)
        width[odd] = [len(s) for s in spelled]
        places = np.concatenate([[0], np.cumsum(width)])
        wide = np.empty(int(places[-1]), dtype=np.int64)
        wide[places[:-1][width == 1]] = made[width == 1]
        wide[flat.spread(places[odd], width[odd])] = np.concatenate(spelled)
        made, at = wide, places[at]
    each = np.diff(at)[which]
    run = np.concatenate([[0], np.cumsum(each)])
    inner = run[first]
    out = np.empty(int(inner[-1]) + 2 * (len(offsets) - 1), dtype=np.int64)
    ids = made[flat.spread(at[:-1][which], each)] if len(which) else np.zeros(0, dtype=np.int64)
    bounds = inner + 2 * np.arange(len(offsets))
    body = np.ones(len(out), dtype=bool)
    body[bounds[:-1]] = body[bounds[1:] - 1] = False
    out[bounds[:-1]], out[bounds[1:] - 1] = v.begin, v.end
    out[body] = ids
    return out, bounds


def decode_flat(v: Vocabulary, ids: np.ndarray, bounds: np.ndarray) -> list[bytes]:
    """Text of each id sequence, as UTF-8."""
    width = (v.blob_at[1:] - v.blob_at[:-1])[ids]
    text = v.blob[flat.spread(v.blob_at[:-1][ids], width)]
    at = np.concatenate([[0], np.cumsum(width)])[bounds]
    raw, out = text.tobytes(), []
    for d in range(len(bounds) - 1):
        piece = raw[at[d] : at[d + 1]]
        loud = ids[bounds[d] : bounds[d + 1]]
        loud = loud[~v.silent[loud[:16]]] if len(loud) <= 16 else loud[:16][~v.silent[loud[:16]]]
        if piece[:1] == b" " and len(loud) and v.blob[v.blob_at[loud[0]]] == 0x20 and loud[0] != v.byte_ids[0x20]:
            piece = piece[1:]  # the blank that encoding put first
        try:
            piece.decode("utf-8")
        except UnicodeDecodeError:  # byte pieces that make no character: the library's own replacement
            piece = v.lib.decode(ids[bounds[d] : bounds[d + 1]].tolist()).encode()
        out.append(piece)
    return out


def _run(path: str, with_values: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = vocabulary(path)
        for batch in batches:
            data, offsets = flat.buffers(batch.column(1))
            for i, j in flat.slices(offsets, SLICE):
                ids, bounds = encode_flat(v, data, offsets[i : j + 1])
                texts = decode_flat(v, ids, bounds)
                raw = ids.astype("<u4").tobytes()
                shas = [hashlib.sha256(raw[4 * a : 4 * b]).hexdigest() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                cols = [batch.column(0).slice(i, j - i), pa.array(np.diff(bounds)), pa.array(shas, pa.string()), pa.array([hashlib.sha256(t).hexdigest() for t in texts], pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_values:
                    cols += [pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids.astype(np.int32))), pa.array([t.decode() for t in texts], pa.string())]
                    names += ["ids", "decoded"]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def encode_decode(docs: DataFrame, path: str | None = None, with_values: bool = True) -> DataFrame:
    """documents -> (doc_id, n_tokens, ids_sha256, decoded_sha256[, ids, decoded]) for every row, map-only.

    Null reads as empty: begin and end ids only.  ``path`` names the model file on every worker.  Rows are coded one by
    one, repeated ones alike; other columns are ignored.
    """
    from pyspark.sql import functions as F

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * with_values
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_run(path or model_path(), with_values), schema)
