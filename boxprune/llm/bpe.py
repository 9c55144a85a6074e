"""Byte-level BPE by a segment tree, and its inverse.

The tree stands over byte positions; the leaf of a live position holds (rank of the pair that starts
there, position), so the root is the leftmost pair of least rank. A merge makes three point updates:
the pair that begins at the merged part, the one that ends there, and the part that is gone; each
costs the tree's height. Many short pieces of equal width are merged together in numpy,
a long piece alone in plain lists, both by the same tree.

Text is cut by the tokenizer's pattern; each match is encoded separately, a match that is itself a
token at once. Results of space-separated chunks are memoised, which changes nothing, since no match
reaches over a boundary between a non-space character and a space.

Null text counts as empty and gives no ids. Repeated rows are encoded one by one. An empty table gives an
empty result. Further columns are not touched.
"""

from __future__ import annotations

import base64
import hashlib
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NONE = np.iinfo(np.int64).max
#: Bits for a position in a leaf's key of pieces that are merged together (WIDE bytes at most).
POS_BITS = 26
#: The same for a piece that is merged alone, in integers of any size.
LONG_BITS = 48
LONG_NONE = 1 << 80
#: Pieces longer than this are merged alone.
WIDE = 64
#: Chunks memoised by a worker before the memo starts anew.
MEMO = 250_000

_BOUNDARY = re.compile(r"(?<=\S) (?=\S)")
_ODD = re.compile(r"\s ")


def cut_chunks(text: str) -> list[str]:
    """Chunks that stand for themselves under the pattern; all but the first lack their leading space."""
    return _BOUNDARY.split(text) if _ODD.search(text) else text.split(" ")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class SegmentTreeBPE:
    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.pieces = [b""] * (max(ranks.values()) + 1)
        for piece, rank in ranks.items():
            self.pieces[rank] = piece
        self.pairs: dict[int, int] = {}
        for piece, rank in ranks.items():
            for i in range(1, len(piece)):
                a, b = ranks.get(piece[:i]), ranks.get(piece[i:])
                if a is not None and b is not None:
                    self.pairs[a << 20 | b] = rank
        self.keys = np.array(sorted(self.pairs), np.int64)
        self.values = np.array([self.pairs[k] for k in self.keys.tolist()], np.int64)
        self.of_byte = np.array([ranks[bytes([i])] for i in range(256)], np.int64)

    def decode(self, ids) -> bytes:
        return b"".join([self.pieces[i] for i in ids])

    def encode_pieces(self, pieces: list[bytes]) -> list[list[int]]:
        out: list = [None] * len(pieces)
        by_width: dict[int, list[int]] = {}
        for i, p in enumerate(pieces):
            whole = self.ranks.get(p)
            if whole is not None:
                out[i] = [whole]
            elif not p:
                out[i] = []
            elif len(p) > WIDE:
                out[i] = self._merge_long(p)
            else:
                by_width.setdefault(max(2, 1 << (len(p) - 1).bit_length()), []).append(i)
        for width, rows in by_width.items():
            for at in range(0, len(rows), 20_000):
                part = rows[at : at + 20_000]
                for i, ids in zip(part, self._merge_many([pieces[i] for i in part], width), strict=True):
                    out[i] = ids
        return out

    def _pair_keys(self, left, right, pos):
        """Leaf keys of pairs; right < 0 means that there is none."""
        k = left << 20 | right
        at = np.minimum(np.searchsorted(self.keys, k), len(self.keys) - 1)
        hit = (right >= 0) & (left >= 0) & (self.keys[at] == k)
        return np.where(hit, self.values[at] << POS_BITS | pos, NONE)

    def _merge_many(self, pieces: list[bytes], w: int) -> list[list[int]]:
        n = len(pieces)
        lens = np.fromiter(map(len, pieces), np.int64, n)
        raw = np.frombuffer(b"".join(p.ljust(w, b"\0") for p in pieces), np.uint8).reshape(n, w)
        col = np.arange(w)
        ids = np.where(col < lens[:, None], self.of_byte[raw], -1)
        nxt = np.where(col + 1 < lens[:, None], col + 1, w)
        prv = np.broadcast_to(col - 1, (n, w)).copy()
        tree = np.full((n, 2 * w), NONE, np.int64)
        right = np.full((n, w), -1, np.int64)
        right[:, :-1] = ids[:, 1:]
        tree[:, w:] = self._pair_keys(ids, right, col)
        level = w
        while level > 1:
            tree[:, level // 2 : level] = np.minimum(tree[:, level : 2 * level : 2], tree[:, level + 1 : 2 * level : 2])
            level //= 2

        def put(rows, pos, key):
            node = pos + w
            tree[rows, node] = key
            while w > 1 and node[0] > 1:  # all nodes are on one level
                node = node >> 1
                tree[rows, node] = np.minimum(tree[rows, 2 * node], tree[rows, 2 * node + 1])

        live = np.flatnonzero(tree[:, 1] != NONE)
        while len(live):
            best = tree[live, 1]
            i = best & ((1 << POS_BITS) - 1)
            j = nxt[live, i]
            after = nxt[live, j]
            ids[live, i] = best >> POS_BITS
            ids[live, j] = -1
            nxt[live, i] = after
            has = after < w
            prv[live[has], after[has]] = i[has]
            put(live, j, np.full(len(live), NONE))
            own = ids[live, i]
            put(live, i, self._pair_keys(own, np.where(has, ids[live, np.minimum(after, w - 1)], -1), i))
            before = prv[live, i]
            has = before >= 0
            if has.any():
                rows, b = live[has], before[has]
                put(rows, b, self._pair_keys(ids[rows, b], own[has], b))
            live = live[tree[live, 1] != NONE]
        flat, keep = ids.ravel(), (ids >= 0)
        counts = keep.sum(axis=1)
        kept = flat[keep.ravel()].tolist()
        ends = np.cumsum(counts).tolist()
        return [kept[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)]

    def _merge_long(self, piece: bytes) -> list[int]:
        n = len(piece)
        w = 1 << (n - 1).bit_length()
        ids = [int(x) for x in self.of_byte[np.frombuffer(piece, np.uint8)]]
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        get, none = self.pairs.get, LONG_NONE
        tree = [none] * (2 * w)
        for i in range(n - 1):
            r = get(ids[i] << 20 | ids[i + 1])
            if r is not None:
                tree[w + i] = r << LONG_BITS | i
        for v in range(w - 1, 0, -1):
            a, b = tree[2 * v], tree[2 * v + 1]
            tree[v] = a if a < b else b

        def put(v, key):
            v += w
            tree[v] = key
            while v > 1:
                v >>= 1
                a, b = tree[2 * v], tree[2 * v + 1]
                m = a if a < b else b
                if tree[v] == m:
                    return
                tree[v] = m

        while tree[1] != none:
            best = tree[1]
            i = best & ((1 << LONG_BITS) - 1)
            j = nxt[i]
            after = nxt[j]
            ids[i], ids[j] = best >> LONG_BITS, -1
            nxt[i] = after
            put(j, none)
            r = None
            if after < n:
                prv[after] = i
                r = get(ids[i] << 20 | ids[after])
            put(i, none if r is None else r << LONG_BITS | i)
            if prv[i] >= 0:
                r = get(ids[prv[i]] << 20 | ids[i])
                put(prv[i], none if r is None else r << LONG_BITS | prv[i])
        return [x for x in ids if x >= 0]


class TextCodec:
    """Whole texts to ids and back, with a bounded memo of chunks."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.bpe, self.match = SegmentTreeBPE(ranks), regex.compile(pattern).findall
        self.first: dict[str, tuple] = {}
        self.later: dict[str, tuple] = {}

    def learn(self, memo: dict, chunks: list[str], lead: str) -> None:
        found = [self.match(lead + c) for c in chunks]
        pieces = list({p for f in found for p in f})
        ids = dict(zip(pieces, self.bpe.encode_pieces([p.encode() for p in pieces]), strict=True))
        for c, f in zip(chunks, found, strict=True):
            own = [i for p in f for i in ids[p]]
            memo[c] = (np.array(own, "<u4").tobytes(), b"".join([b" %d" % i for i in own]), self.bpe.decode(own))

    def encode(self, texts: list[str]) -> list[list[tuple]]:
        """The (ids, printed ids, decoded bytes) of the chunks of each text."""
        if len(self.later) > MEMO:
            self.later.clear()
        if len(self.first) > MEMO:
            self.first.clear()
        cut = [cut_chunks(t) for t in texts]
        fresh_first = {c[0] for c in cut}.difference(self.first)
        fresh = set().union(*[c[1:] for c in cut]).difference(self.later)
        self.learn(self.first, list(fresh_first), "")
        self.learn(self.later, list(fresh), " ")
        get = self.later.__getitem__
        return [[self.first[c[0]], *map(get, c[1:])] for c in cut]


@lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> TextCodec:
    """One codec for each vocabulary in a worker process."""
    return TextCodec(load_ranks(path), pattern)


#: Characters encoded at once.
STEP_CHARS = 2_000_000


def text_steps(texts: list[str]):
    """Runs of texts of about STEP_CHARS."""
    at, size = 0, 0
    for i, t in enumerate(texts):
        size += len(t)
        if size >= STEP_CHARS:
            yield texts[at : i + 1]
            at, size = i + 1, 0
    if at < len(texts):
        yield texts[at:]


def encode_documents(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, ids (array of int) of each whole text."""
    kind = docs.schema[id_col].dataType.simpleString()

    def job(batches):
        c = codec(path, pattern)
        for b in batches:
            for at, part in _numbered([t or "" for t in b.column(1).to_pylist()]):
                ids = [np.frombuffer(b"".join([x[0] for x in chunks]), "<u4").astype(np.int32) for chunks in c.encode(part)]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(part)), pa.array(ids, pa.list_(pa.int32()))], names=[id_col, "ids"])

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(job, f"`{id_col}` {kind}, ids array<int>")


def decode_documents(encoded: DataFrame, path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """id, text (bytes, as ids may cut characters) of each array of ids; null ids give null."""
    kind = encoded.schema[id_col].dataType.simpleString()

    def job(batches):
        bpe = codec(path, pattern).bpe
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([None if i is None else bpe.decode(i) for i in b.column(1).to_pylist()], pa.binary())], names=[id_col, "decoded"])

    return encoded.select(F.col(id_col), F.col(ids_col)).mapInArrow(job, f"`{id_col}` {kind}, decoded binary")


def _numbered(texts: list[str]):
    at = 0
    for part in text_steps(texts):
        yield at, part
        at += len(part)


def round_trip_digests(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode, print and decode in one pass: n_tokens and digests of printed ids and decoded bytes."""
    kind = docs.schema[id_col].dataType.simpleString()

    def job(batches):
        c = codec(path, pattern)
        for b in batches:
            for at, part in _numbered([t or "" for t in b.column(1).to_pylist()]):
                n, ids, back = [], [], []
                for chunks in c.encode(part):
                    printed = b"".join([x[1] for x in chunks])
                    n.append(printed.count(b" "))
                    ids.append(hashlib.sha256(printed[1:]).hexdigest())
                    back.append(hashlib.sha256(b"".join([x[2] for x in chunks])).hexdigest())
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(part)), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(back, pa.string())], names=[id_col, "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(job, f"`{id_col}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
