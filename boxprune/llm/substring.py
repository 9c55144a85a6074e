"""Repeated passages by a compressed FM-index per shard.

Texts with the same word sequence are one node, standing at its smallest id. Every window of ``width`` words has
one anchor, the position of the least hash among its short word runs, so equal windows have equal anchors. Only anchors found in two
nodes or more go on; the words around each are its context, and equal contexts are sent once with their
smallest id. Contexts are dealt to shards by anchor, so all occurrences of a window meet in one shard. An anchor of more than
``hot`` places, which might fill a shard, is split: its windows are grouped by their distance to the anchor, and the words that
all windows of a group hold are a new anchor. A group that is still hot is split into single windows, whose anchor is all their
words, so that only equal windows share it. Equal windows lie equally far from their anchor and stay together.

A shard numbers its words and joins its contexts to one text with separators, whose suffixes are sorted by their first 64
symbols. Of the index it keeps the transformed text as a wavelet matrix of packed bits with counts a machine word. Contexts
are streamed against it by backward search, all in step: the matching statistic of each position is the longest run of
words, up to ``width``, that the interval still holds; positions that reach the threshold are reported with the
smallest id in their interval. A context's next window reuses the interval: its last word is dropped by moving to the
surrounding interval of width - 1 words, and one step to the left follows.

Windows are judged on the input. A word goes if a window that covers it also starts in a document with a
smaller id; occurrences in the same document don't count. Null text has no words. Repeated rows with one id count as one document.
An empty table gives an empty result. Further columns are not touched.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxprune.llm.kernels import _LANES, U, Texts, as_long, mix, slices
from boxprune.llm.shared import small_side, stored

WIDTH = 50
#: Words hashed for an anchor.
GRAM = 8
#: Words of contexts in a shard, about.
SHARD_WORDS = 1_000_000
#: Symbols by which suffixes are sorted; at least the width.
SORTED = 64
#: Places of an anchor beyond which it is split: about a fifth of a shard's words.
HOT = 2_000
#: Distances to a hot anchor in a group.
GROUP = 8
#: Hot anchors, and hot groups, that each task is told (1.6 MB); more are joined to the documents that hold them.
LISTED = 200_000
#: Contexts a task holds back to send each once.
HELD = 50_000


# ---------------------------------------------------------------- the index of a shard


class WaveletMatrix:
    """Ranks of symbols in a sequence, from bit levels packed into machine words."""

    def __init__(self, seq: np.ndarray, symbols: int):
        self.n, self.bits = len(seq), max(1, int(symbols - 1).bit_length())
        self.levels = []
        cur = seq.astype(np.int64)
        for b in range(self.bits - 1, -1, -1):
            bit = (cur >> b & 1).astype(bool)
            packed = np.packbits(bit, bitorder="little")
            packed = np.concatenate([packed, np.zeros(16 - len(packed) % 8, np.uint8)]).view(np.uint64)
            counts = np.zeros(len(packed) + 1, np.int64)
            np.cumsum(np.bitwise_count(packed), out=counts[1:])
            self.levels.append((packed, counts, self.n - int(bit.sum())))
            cur = np.concatenate([cur[~bit], cur[bit]])

    def descend(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Where position at of the sequence goes on the way of its symbol; differences are ranks."""
        at = at.copy()
        for level, (packed, counts, zeros) in enumerate(self.levels):
            word = at >> 6
            ones = counts[word] + np.bitwise_count(packed[word] & ((U(1) << (at & 63).astype(np.uint64)) - U(1)))
            bit = symbol >> (self.bits - 1 - level) & 1
            at = np.where(bit == 1, zeros + ones, at - ones)
        return at


class ShardIndex:
    """FM-index over contexts of word numbers (1 and up); 0 separates them."""

    def __init__(self, contexts: list[np.ndarray], least: np.ndarray, width: int):
        text = np.concatenate([np.append(c, 0) for c in contexts])
        owner = np.repeat(np.arange(len(contexts)), [len(c) + 1 for c in contexts])
        n, self.width = len(text), width
        _, rank = np.unique(text, return_inverse=True)
        ranks, step = {1: rank}, 1
        while step < max(SORTED, width):
            nxt = np.full(n, -1, np.int64)
            nxt[: n - step] = rank[step:]
            key = rank * (n + 1) + nxt + 1
            order = np.argsort(key, kind="stable")
            k = key[order]
            rank = np.empty(n, np.int64)
            rank[order] = np.cumsum(np.concatenate([[False], k[1:] != k[:-1]]))
            step *= 2
            ranks[step] = rank
        self.symbols = int(text.max()) + 1
        before = np.cumsum(np.bincount(text, minlength=self.symbols))
        self.first = np.concatenate([[0], before])[:-1]
        self.matrix = WaveletMatrix(text[order - 1], self.symbols)
        self.root = self.matrix.descend(np.arange(self.symbols), np.zeros(self.symbols, np.int64))
        # suffixes that agree on width and on width - 1 symbols stand together
        self.full, self.shorter = (self._groups(order, ranks, m) for m in (width, width - 1))
        self.least = np.minimum.reduceat(least[owner[order]], self.full[0])
        self.n = n

    @staticmethod
    def _groups(order: np.ndarray, ranks: dict[int, np.ndarray], m: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n, same, at = len(order), np.ones(len(order) - 1, bool), 0
        for power in sorted(ranks, reverse=True):
            if m & power:
                r = np.full(n, -1, np.int64)
                where = order + at
                r[where < n] = ranks[power][where[where < n]]
                r[where >= n] = -1 - np.flatnonzero(where >= n)
                same &= r[1:] == r[:-1]
                at += power
        starts = np.flatnonzero(np.concatenate([[True], ~same]))
        return starts, np.append(starts[1:], n), np.cumsum(np.concatenate([[False], ~same]))

    def step(self, symbol, lo, hi):
        """The interval of symbol followed by what the interval holds."""
        base = self.first[symbol] - self.root[symbol]
        return base + self.matrix.descend(symbol, lo), base + self.matrix.descend(symbol, hi)

    def windows(self, contexts: list[np.ndarray]) -> list[np.ndarray]:
        """For each context, the smallest id of each of its windows by start; backward search of all in step."""
        w, n = self.width, len(contexts)
        lens = np.array([len(c) for c in contexts])
        flat = np.concatenate(contexts)
        ends = np.cumsum(lens)
        lo, hi = np.zeros(n, np.int64), np.full(n, self.n, np.int64)
        matched = np.zeros(n, np.int64)
        out = [np.full(k - w + 1, np.iinfo(np.int64).max) for k in lens]
        live = np.arange(n)
        for back in range(int(lens.max())):
            live = live[lens[live] > back]
            full = live[matched[live] == w]
            if len(full):
                g = self.shorter[2][lo[full]]
                lo[full], hi[full] = self.shorter[0][g], self.shorter[1][g]
                matched[full] = w - 1
            lo[live], hi[live] = self.step(flat[ends[live] - 1 - back], lo[live], hi[live])
            matched[live] += 1
            hit = live[(matched[live] == w) & (hi[live] > lo[live])]
            for i, v in zip(hit.tolist(), self.least[self.full[2][lo[hit]]].tolist(), strict=True):
                out[i][lens[i] - 1 - back] = v
        return out


# ---------------------------------------------------------------- anchors and contexts


def anchors(t: Texts, width: int = WIDTH, gram: int = GRAM):
    """Words' owners and hashes; then for each anchor its text, hash, place, and first and last window (by word number)."""
    _, _, of, h = t.words()
    n = len(of) - width + 1
    none = np.zeros(0, np.int64)
    if n <= 0:
        return of, h, none, none.view(np.uint64), none, none, none
    grams = np.zeros(len(of) - gram + 1, np.uint64)
    for j in range(gram):
        grams += h[j : j + len(grams)] * _LANES[j]
    grams = mix(grams)
    bits = U(max(1, int(len(grams)).bit_length()))
    low = (grams >> bits << bits) | np.arange(len(grams), dtype=np.uint64)
    span, reach = width - gram + 1, 1
    while reach * 2 <= span:
        low = np.minimum(low[:-reach], low[reach:])
        reach *= 2
    if reach < span:
        low = np.minimum(low[: len(low) - (span - reach)], low[span - reach :])
    at = (low[:n] & ((U(1) << bits) - U(1))).astype(np.int64)
    ok = np.flatnonzero(of[:n] == of[width - 1 :])
    if not len(ok):
        return of, h, none, none.view(np.uint64), none, none, none
    at = at[ok]
    new = np.concatenate([[True], (at[1:] != at[:-1]) | (ok[1:] != ok[:-1] + 1)])
    begin = np.flatnonzero(new)
    last = np.append(begin[1:], len(ok)) - 1
    return of, h, of[ok[begin]], grams[at[begin]], at[begin], ok[begin], ok[last]


_SPREAD = np.random.Generator(np.random.PCG64(99)).integers(1, 2**63, 4 * WIDTH, dtype=np.uint64) * U(2) + U(1)


def _key(words: np.ndarray, anchor: np.uint64) -> np.uint64:
    """A hash of word hashes in their order and of an anchor."""
    spread = (words * _LANES[0] + mix(np.arange(len(words), dtype=np.uint64))) * _SPREAD[: len(words)]
    return mix(np.array([spread.sum(dtype=np.uint64) ^ anchor], np.uint64))[0]


def parts(h: np.ndarray, anchor: np.uint64, at: int, lo: int, hi: int, width: int, group: int):
    """New anchor, first and last window of the windows lo to hi of an anchor at word ``at``, by groups of distances to it."""
    for g in range((at - hi) // group, (at - lo) // group + 1):
        latest = at - g * group
        core = h[latest : latest - group + 1 + width]  # held by each window of the group
        yield _key(core, anchor ^ U(g + 1)), max(lo, latest - group + 1), min(hi, latest)


#: What a text without its spaces is known by.
_NODE = ["node", "more", "n_words"]


def _base(docs: DataFrame, kind: str) -> DataFrame:
    """id, n_words, two hashes of the words (they and the count stand for the text), and the digest of the words joined by one space."""

    def job(batches):
        for b in batches:
            ids, texts = b.column(0), b.column(1)
            for at, t in slices(texts):
                _, _, of, h = t.words()
                n = np.bincount(of, minlength=t.n)
                first = np.concatenate([[0], np.cumsum(n)])[:-1]
                place = (np.arange(len(of)) - first[of]).astype(np.uint64)
                total = np.zeros(len(of) + 1, np.uint64)
                np.cumsum(mix(h + mix(place)), out=total[1:])
                node = mix(total[first + n] - total[first] + n.astype(np.uint64))
                np.cumsum(mix((h ^ U(0x8EBC6AF09C88C6E3)) + mix(place + U(0x589965CC75374CC3))), out=total[1:])
                more = mix(total[first + n] - total[first])
                raw = t.data.tobytes()
                sha = [hashlib.sha256(b" ".join(raw[t.offsets[i] : t.offsets[i + 1]].split())).hexdigest() for i in range(t.n)]
                yield pa.RecordBatch.from_arrays([ids.slice(at, t.n), pa.array(n.astype(np.int64)), pa.array(as_long(node)), pa.array(as_long(more)), pa.array(sha)], names=["id", "n_words", "node", "more", "sha"])

    return docs.mapInArrow(job, f"id {kind}, n_words long, node long, more long, sha string")


def _anchor_rows(firsts: DataFrame, width: int) -> DataFrame:
    """anchor, rep of each anchor of the given (rep, text)."""

    def job(batches):
        for b in batches:
            rep = b.column(0).to_numpy()
            for at, t in slices(b.column(1)):
                _, _, own, a, _, _, _ = anchors(t, width)
                yield pa.RecordBatch.from_arrays([pa.array(as_long(a)), pa.array(rep[at + own])], names=["anchor", "rep"])

    return firsts.mapInArrow(job, "anchor long, rep long")


def _group_rows(texts: DataFrame, width: int, told: np.ndarray, by_rep: bool) -> DataFrame:
    """anchor, rep, n: places of each group of windows of the hot anchors, which are told or, with (rep, text, hot anchors), the text's own;
    added up in a task, rep 0, unless by rep."""

    def batch(counts):
        keys = list(counts)
        return pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int64()), pa.array(list(counts.values()), pa.int64())], names=["anchor", "rep", "n"])

    def job(batches):
        counts: dict[tuple[int, int], int] = {}
        for b in batches:
            rep, lists = b.column(0).to_numpy(), b.column(2)
            for at, t in slices(b.column(1)):
                _, h, own, a, place, lo, hi = anchors(t, width)
                is_told, bounds = np.isin(a, told), np.searchsorted(own, np.arange(t.n + 1))
                for i in range(t.n):
                    s = slice(bounds[i], bounds[i + 1])
                    for j in np.flatnonzero(is_told[s] | np.isin(a[s], lists[at + i].values.to_numpy().view(np.uint64))) + s.start:
                        for key, _, _ in parts(h, a[j], int(place[j]), int(lo[j]), int(hi[j]), width, GROUP):
                            k = (int(key.view(np.int64)), int(rep[at + i]) if by_rep else 0)
                            counts[k] = counts.get(k, 0) + 1
                if len(counts) > HELD:
                    yield batch(counts)
                    counts.clear()
        yield batch(counts)

    return texts.mapInArrow(job, "anchor long, rep long, n long")


def _context_rows(joined: DataFrame, width: int, told: np.ndarray, listed: np.ndarray) -> DataFrame:
    """Two kinds of rows of (rep, text, shared anchors, hot ones that are not told, hot groups that are not listed): contexts (words set, once a
    task, smallest rep) and occurrences."""
    names = ["anchor", "context", "rep", "start", "words"]

    def batch(rows):
        types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(types)], names=names)

    def job(batches):
        held: dict[tuple[int, int], list] = {}
        known_hot, known_groups = set(told.tolist()), set(listed.tolist())
        for b in batches:
            rep = b.column(0).to_numpy()
            for at, t in slices(b.column(1)):
                of, h, own, a, place, lo, hi = anchors(t, width)
                begin = np.searchsorted(of, np.arange(t.n))
                bounds = np.searchsorted(own, np.arange(t.n + 1))
                rows = []
                for i in range(t.n):
                    s, r = slice(bounds[i], bounds[i + 1]), int(rep[at + i])
                    shared, hot, groups = (set(b.column(c)[at + i].values.to_numpy().view(np.uint64).tolist()) for c in (2, 3, 4))
                    found = []
                    for j in range(s.start, s.stop):
                        if int(a[j]) in known_hot or int(a[j]) in hot:
                            for key, first, last in parts(h, a[j], int(place[j]), int(lo[j]), int(hi[j]), width, GROUP):
                                found += parts(h, a[j], int(place[j]), first, last, width, 1) if int(key) in known_groups or int(key) in groups else [(key, first, last)]
                        elif int(a[j]) in shared:
                            found.append((a[j], int(lo[j]), int(hi[j])))
                    for anchor, first, last in found:
                        words = h[first : last + width]
                        key = (int(anchor.view(np.int64)), int(_key(words, anchor).view(np.int64)))
                        rows.append((*key, r, int(first - begin[i]), None))
                        known = held.get(key)
                        if known is None:
                            held[key] = [*key, r, None, words.tobytes()]
                        elif r < known[2]:
                            known[2] = r
                if rows:
                    yield batch(rows)
                if len(held) > HELD:
                    yield batch(list(held.values()))
                    held.clear()
        if held:
            yield batch(list(held.values()))

    return joined.mapInArrow(job, "anchor long, context long, rep long, start long, words binary")


def _shard_runs(contexts: DataFrame, shards: int, width: int) -> DataFrame:
    """anchor, context (together they stand for the context's words), first, count, least: runs of windows with their smallest id."""

    def job(table: pa.Table) -> pa.Table:
        best: dict[tuple[int, int], list] = {}
        for *c, r, w in zip(*[table.column(k).to_pylist() for k in ("anchor", "context", "rep", "words")], strict=True):
            c = tuple(c)
            known = best.get(c)
            if known is None:
                best[c] = [r, w]
            elif r < known[0]:
                known[0] = r
        keys = list(best)
        words = [np.frombuffer(best[k][1], np.uint64) for k in keys]
        _, numbers = np.unique(np.concatenate(words), return_inverse=True)
        contexts_ = np.split(numbers + 1, np.cumsum([len(w) for w in words])[:-1])
        index = ShardIndex(contexts_, np.array([best[k][0] for k in keys], np.int64), width)
        out: list[tuple] = []
        for k, least in zip(keys, index.windows(contexts_), strict=True):
            cut = np.flatnonzero(np.concatenate([[True], least[1:] != least[:-1]]))
            out += [(*k, int(a), int(b - a), int(least[a])) for a, b in zip(cut, np.append(cut[1:], len(least)), strict=True)]
        return pa.table({n: pa.array([o[i] for o in out], pa.int64()) for i, n in enumerate(("anchor", "context", "first", "count", "least"))})

    dealt = contexts.withColumn("shard", F.pmod("anchor", F.lit(shards)).cast("int"))
    return dealt.groupBy("shard").applyInArrow(job, "anchor long, context long, first long, count long, least long")


def _cut(texts: DataFrame, width: int) -> DataFrame:
    """rep, n_removed, sha of (rep, text, runs of window starts)."""

    def job(batches):
        for b in batches:
            reps, texts, runs = b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()
            removed, shas = [], []
            for text, run in zip(texts, runs, strict=True):
                words = text.encode().split()
                edge = np.zeros(len(words) + 1, np.int64)
                for r in run:
                    edge[r["from"]] += 1
                    edge[r["to"]] -= 1
                gone = np.cumsum(edge[:-1]) > 0
                removed.append(int(gone.sum()))
                shas.append(hashlib.sha256(b" ".join([w for w, g in zip(words, gone.tolist(), strict=True) if not g])).hexdigest())
            yield pa.RecordBatch.from_arrays([pa.array(reps, pa.int64()), pa.array(removed, pa.int64()), pa.array(shas)], names=["rep", "n_removed", "cut_sha"])

    return texts.mapInArrow(job, "rep long, n_removed long, cut_sha string")


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, hot: int = HOT) -> DataFrame:
    """id, n_words, n_removed, kept_sha256 (of the kept words joined by one space). Ids are longs; ``hot`` moves work only."""
    if width > 4 * WIDTH // 2:
        raise ValueError(f"windows of at most {2 * WIDTH} words")
    docs = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    base = stored(_base(docs, "bigint"))
    reps = base.where(F.col("n_words") >= width).groupBy(*_NODE).agg(F.min("id").alias("rep"))
    firsts = small_side(stored(base.join(reps, _NODE).where(F.col("id") == F.col("rep")).select("id").distinct()))
    mine = docs.join(firsts, "id", "left_semi").select(F.col("id").alias("rep"), "text")

    found = stored(_anchor_rows(mine, width))
    shared = found.groupBy("anchor").agg(F.min("rep").alias("lo"), F.max("rep").alias("hi"), F.count(F.lit(1)).alias("n")).where("lo <> hi")
    shared = stored(shared.select("anchor", (F.col("n") > hot).alias("hot")))  # a table of its own, so that the joins below can split a hot anchor
    none, known = F.array().cast("array<bigint>"), lambda df: np.array([r["anchor"] for r in df.select("anchor").collect()], np.int64).view(np.uint64)
    hot_anchors = shared.where("hot")
    told, listed, n_hot = np.zeros(0, np.uint64), np.zeros(0, np.uint64), hot_anchors.count()
    own_hot = none
    if n_hot <= LISTED:
        told = known(hot_anchors)  # at most LISTED
    else:
        own_hot = F.collect_set(F.when(F.col("hot"), F.col("anchor")))
    wanted = found.join(shared, "anchor").groupBy("rep").agg(F.collect_set("anchor").alias("anchors"), own_hot.alias("hot"))  # at most a document's own anchors
    wanted = stored(wanted).withColumn("groups", none)
    if n_hot:
        # tasks that are told the hot anchors read the texts where they lie
        split = mine.select("rep", "text", none.alias("hot")) if len(told) else mine.join(wanted.where(F.size("hot") > 0), "rep").select("rep", "text", "hot")
        groups = stored(_group_rows(split, width, told, False).groupBy("anchor").agg(F.sum("n").alias("n")).where(F.col("n") > hot).select("anchor"))
        if groups.count() <= LISTED:
            listed = known(groups)  # at most LISTED
        else:
            own = stored(_group_rows(split, width, told, True).join(groups, "anchor", "left_semi").groupBy("rep").agg(F.collect_set("anchor").alias("own")))  # at most a document's groups
            wanted = wanted.join(own, "rep", "left").withColumn("groups", F.coalesce("own", "groups")).drop("own")
    joined = mine.join(wanted, "rep").select("rep", "text", "anchors", "hot", "groups")
    rows = stored(_context_rows(joined, width, told, listed))
    contexts, places = rows.where("words IS NOT NULL"), rows.where("words IS NULL").select("anchor", "context", "rep", "start")
    total = contexts.agg(F.coalesce(F.sum(F.length("words") / 8), F.lit(0)).alias("t")).first()["t"]
    runs = stored(_shard_runs(contexts.select("anchor", "context", "rep", "words"), max(1, int(total // SHARD_WORDS) + 1), width))

    gone = places.join(runs, ["anchor", "context"]).where(F.col("least") < F.col("rep"))
    gone = gone.select("rep", F.struct((F.col("start") + F.col("first")).alias("from"), (F.col("start") + F.col("first") + F.col("count") - 1 + width).alias("to")).alias("run"))
    gone = stored(gone.groupBy("rep").agg(F.collect_set("run").alias("runs")))  # at most a document's own windows
    hit = mine.join(small_side(stored(gone.select("rep"))), "rep", "left_semi")  # only texts that lose words are sent
    cut = stored(_cut(hit.join(gone, "rep").select("rep", "text", "runs"), width).dropDuplicates(["rep"]))

    whole = hashlib.sha256(b"").hexdigest()
    out = base.join(reps.withColumnRenamed("rep", "first_id"), _NODE, "left").join(cut, F.col("id") == F.col("rep"), "left")
    copy = F.col("first_id") < F.col("id")
    return out.select(
        F.col("id").alias(id_col), "n_words",
        F.when(copy, F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(copy, F.lit(whole)).otherwise(F.coalesce("cut_sha", "sha")).alias("kept_sha256"),
    )
