"""Pattern packing of token sequences by non-negative least squares.

Documents are cut into pieces of at most ``capacity`` tokens, the first one taking the remainder. Only
the histogram of piece lengths (at most ``capacity`` rows) reaches the driver. There, patterns of few
lengths that fill a sequence are enumerated, repeat counts are fitted to the histogram by non-negative
least squares, rounded down to what is there, and the residual histogram is packed best-fit with the
longest lengths first, again as patterns with counts. Pieces are ranked within their length by a
salted two-level count and take the slot that the pattern table gives to their rank.

Null text counts as empty, which is a piece of the end id alone. Repeated rows are packed one by one. An
empty table gives an empty result. Further columns are not touched.
"""

from __future__ import annotations

import json
import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxprune.llm.bpe import MEMO, _numbered, cut_chunks
from boxprune.llm.shared import stored

CAPACITY = 1024
END_ID = 2
#: Pieces of one length in a salted group, about.
GROUP_ROWS = 100_000
SWEEPS = 60


# ---------------------------------------------------------------- tokens


def _byte_letters() -> dict[str, int]:
    """The printable letters that byte-level vocabularies write for bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class ChunkEncoder:
    """Ids of a byte-level vocabulary file of the tokenizers library, memoised by chunk.

    Chunks that are new are encoded by tiktoken from the file's own vocabulary, which gives the same
    ids as the tokenizers library several times as fast (the tests hold both together). ``library_ids``
    first cuts the file's added tokens out of a text, as the library does; what lies between is encoded apart.
    """

    def __init__(self, path: str, pattern: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.added = {t["content"]: np.array([t["id"]], "<u4").tobytes() for t in spec.get("added_tokens", [])}
        for t in spec.get("added_tokens", []):
            if t.get("single_word") or t.get("lstrip") or t.get("rstrip"):
                raise ValueError(f"added token {t['content']!r} takes or needs what stands beside it; that is not supported")
        self.split = re.compile("(" + "|".join(map(re.escape, sorted(self.added, key=len, reverse=True))) + ")").split if self.added else None
        byte = _byte_letters()
        ranks = {bytes(byte[c] for c in piece): i for piece, i in spec["model"]["vocab"].items() if piece not in self.added}
        self.encode = tiktoken.Encoding("vocabulary", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.first: dict[str, bytes] = {}
        self.later: dict[str, bytes] = {}

    def library_ids(self, text: str) -> bytes:
        """What the library gives at its default setting, as little-endian unsigned 32-bit ids: added tokens count."""
        parts = self.split(text) if self.split else [text]
        if len(parts) == 1:
            return self.ids(text)
        return b"".join(self.added[t] if i % 2 else self.ids(t) for i, t in enumerate(parts) if t)

    def ids(self, text: str) -> bytes:
        """Little-endian unsigned 32-bit ids, added tokens as ordinary text."""
        first, *rest = cut_chunks(text)
        later = self.later
        for c in set(rest).difference(later):
            later[c] = np.array(self.encode(" " + c), "<u4").tobytes()
        lead = self.first.get(first)
        if lead is None:
            lead = self.first[first] = np.array(self.encode(first), "<u4").tobytes()
        out = b"".join([lead, *map(later.__getitem__, rest)])
        if len(later) > MEMO:
            later.clear()
        if len(self.first) > MEMO:
            self.first.clear()
        return out


@lru_cache(maxsize=2)
def chunk_encoder(path: str, pattern: str) -> ChunkEncoder:
    return ChunkEncoder(path, pattern)


PIECES = "piece int, start long, length long, ids_crc32 long"


def cut_pieces(docs: DataFrame, path: str, pattern: str, capacity: int = CAPACITY, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row for each piece of a document; with_ids also gives its ids."""
    kind = docs.schema[id_col].dataType.simpleString()
    tail = np.array([end_id], "<u4").tobytes()

    def job(batches):
        enc = chunk_encoder(path, pattern)
        for b in batches:
            for at, part in _numbered([t or "" for t in b.column(1).to_pylist()]):
                own, piece, start, length, crc, ids = [], [], [], [], [], []
                for i, t in enumerate(part):
                    data = enc.library_ids(t) + tail
                    n = len(data) // 4
                    begin, end, k = 0, n % capacity or capacity, 0
                    while begin < n:
                        cut = data[4 * begin : 4 * end]
                        own.append(at + i), piece.append(k), start.append(begin), length.append(end - begin), crc.append(zlib.crc32(cut))
                        if with_ids:
                            ids.append(np.frombuffer(cut, "<u4").astype(np.int32))
                        begin, end, k = end, end + capacity, k + 1
                cols = [b.column(0).take(pa.array(own, pa.int64())), pa.array(piece, pa.int32()), *[pa.array(x, pa.int64()) for x in (start, length, crc)]]
                yield pa.RecordBatch.from_arrays(cols + [pa.array(ids, pa.list_(pa.int32()))] * with_ids, names=[id_col, "piece", "start", "length", "ids_crc32", *["ids"] * with_ids])

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(job, f"`{id_col}` {kind}, {PIECES}" + ", ids array<int>" * with_ids)


# ---------------------------------------------------------------- patterns (driver, histogram only)


def enumerate_patterns(left: np.ndarray, capacity: int, most: int = 4) -> list[tuple[int, ...]]:
    """Few-document patterns: all pairs of present lengths that fill a sequence exactly, and the
    patterns of at most ``most`` pieces that a best-fit trial on the histogram opens."""
    here = {int(x) for x in np.flatnonzero(left)}
    pairs = {(a, capacity - a) for a in here if capacity - a in here and 2 * a >= capacity}
    trial = {p for p, _ in best_fit(left, capacity) if len(p) <= most}
    return sorted(pairs | trial, reverse=True)


def fit_counts(patterns: list[tuple[int, ...]], hist: np.ndarray, capacity: int, sweeps: int = SWEEPS) -> np.ndarray:
    """Non-negative least squares of pattern counts against the histogram, by cyclic coordinate descent.

    Waste is penalised lightly, so that among equal fits the fuller pattern is taken.
    """
    used = [np.unique(p, return_counts=True) for p in patterns]
    x = np.zeros(len(patterns))
    resid = hist.astype(float).copy()
    norm = [float((m * m).sum()) for _, m in used]
    waste = np.array([(capacity - sum(p)) / capacity for p in patterns]) * max(1.0, hist.sum() / max(1, (hist > 0).sum()))
    for _ in range(sweeps):
        moved = 0.0
        for i, (at, m) in enumerate(used):
            new = max(0.0, x[i] + (float((resid[at] * m).sum()) - waste[i]) / norm[i])
            if new != x[i]:
                resid[at] -= (new - x[i]) * m
                moved = max(moved, abs(new - x[i]))
                x[i] = new
        if moved < 0.25:
            break
    return x


def best_fit(hist: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit with the longest first on a histogram: groups of equal sequences are filled together."""
    open_: dict[int, list[list]] = {}
    free = np.zeros(capacity + 1, bool)
    for length in range(capacity, 0, -1):
        todo = int(hist[length])
        fresh: list[tuple[int, list]] = []
        while todo:
            fits = np.flatnonzero(free[length:])
            if not len(fits):
                each = capacity // length
                full, rest = divmod(todo, each)
                if full:
                    fresh.append((capacity - each * length, [(length,) * each, full]))
                if rest:
                    fresh.append((capacity - rest * length, [(length,) * rest, 1]))
                break
            room = length + int(fits[0])
            group = open_[room][-1]
            each = min(room // length, todo)
            n = min(group[1], todo // each)
            fresh.append((room - each * length, [group[0] + (length,) * each, n]))
            todo -= n * each
            group[1] -= n
            if not group[1]:
                open_[room].pop()
                free[room] = bool(open_[room])
        for room, group in fresh:
            open_.setdefault(room, []).append(group)
            free[room] = room > 0
    return [(tuple(sorted(g[0], reverse=True)), g[1]) for groups in open_.values() for g in groups if g[1]]


def plan_patterns(hist: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """(pattern, repeats) that together hold each length as often as the histogram says."""
    left = np.zeros(capacity + 1, np.int64)
    for length, n in hist.items():
        left[length] = n
    plan: list[tuple[tuple[int, ...], int]] = []
    if left[capacity]:
        plan.append(((capacity,), int(left[capacity])))
        left[capacity] = 0
    if left.any():
        patterns = enumerate_patterns(left, capacity)
        fitted = fit_counts(patterns, left, capacity)
        for i in sorted(range(len(patterns)), key=lambda i: (sum(patterns[i]) != capacity, -fitted[i])):
            at, m = np.unique(patterns[i], return_counts=True)
            n = min(int(fitted[i] + 0.5), int((left[at] // m).min()))
            if n > 0:
                left[at] -= n * m
                plan.append((patterns[i], n))
        plan += best_fit(left, capacity)
    return plan


def slot_table(plan: list[tuple[tuple[int, ...], int]]) -> np.ndarray:
    """Rows (length, first rank, first sequence, pieces of the length in the pattern, offset of the first)."""
    rows, taken, sequence = [], {}, 0
    for pattern, n in plan:
        offset = 0
        for length in sorted(set(pattern), reverse=True):
            m = pattern.count(length)
            rows.append((length, taken.get(length, 0), sequence, m, offset))
            taken[length] = taken.get(length, 0) + m * n
            offset += m * length
        sequence += n
    return np.array(sorted(rows), np.int64).reshape(-1, 5)


# ---------------------------------------------------------------- placing


def place(pieces: DataFrame, capacity: int = CAPACITY, id_col: str = "doc_id") -> DataFrame:
    """Add sequence_id and offset to stored pieces."""
    hist = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    slots = slot_table(plan_patterns(hist, capacity))
    salts = max(1, -(-sum(hist.values()) // GROUP_ROWS))
    salted = pieces.withColumn("_salt", F.pmod(F.xxhash64(id_col, "piece"), F.lit(salts)))
    groups = salted.groupBy("length", "_salt").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    groups = groups.select(F.col("length").alias("_l"), F.col("_salt").alias("_s"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    inner = Window.partitionBy("length", "_salt").orderBy(id_col, "piece", "start", "ids_crc32")
    ranked = salted.withColumn("_r", F.row_number().over(inner).cast("long")).join(groups, (F.col("length") == F.col("_l")) & (F.col("_salt") == F.col("_s"))).withColumn("_rank", F.col("_before") + F.col("_r") - 1)
    ranked = ranked.drop("_salt", "_l", "_s", "_before", "_r")
    keys = slots[:, 0] << 44 | slots[:, 1]

    def job(batches):
        for b in batches:
            length, rank = (b.column(c).to_numpy() for c in ("length", "_rank"))
            s = slots[np.searchsorted(keys, length << 44 | rank, side="right") - 1] if len(slots) else np.zeros((0, 5), np.int64)
            inside = rank - s[:, 1]
            rest = [n for n in b.schema.names if n != "_rank"]
            cols = [b.column(n) for n in rest] + [pa.array(s[:, 2] + inside // s[:, 3]), pa.array(s[:, 4] + inside % s[:, 3] * length)]
            yield pa.RecordBatch.from_arrays(cols, names=[*rest, "sequence_id", "offset"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema)
    return ranked.select(*pieces.columns, "_rank").mapInArrow(job, f"{schema}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, path: str, pattern: str, capacity: int = CAPACITY, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of all documents with their places."""
    return place(stored(cut_pieces(docs, path, pattern, capacity, end_id, id_col, text_col)), capacity, id_col)
