"""Exact Jaccard join of word-shingle sets by token-combination prefixes.

Texts with equal sets become one node. The tokens of a set are put in a global order: rare ones first, then
frequent ones, then very frequent ones. A set's prefix is extended until it can't lose all its signatures by the edits
that the threshold allows: a rare token is a signature by itself, frequent tokens are indexed in combinations of two or three
within small hash buckets. A set too small to be similar enough to any other one has no signatures; if a
low threshold uses up all tokens of a set, each of them becomes a signature as well.
Every signature also carries how many tokens its set must have lost if nothing before it matched; two
sets meet only if neither has lost more than their sizes allow (this loses no link).

Within a signature's list, every set is first compared with the member that has lost least. Lists that still hold two
components take further members as hubs, up to 256 times as many in each round, one for each hash class, and compare them with the
members of other components only. So a large group of near copies costs a few comparisons a member, the rounds are as many as
the logarithm of the longest list, no list is joined with itself, none is capped, and no pair that may link is left out.

A node is known by 64 bits of its set's hash. Nodes that the set's size or 64 further bits tell apart are
listed and get another name, so different sets are not merged (128 bits stand for a set).

Null or wordless text has the empty set and is linked with nothing. Rows are told apart by id and text, so an id may be null
or repeat: a null id counts as the largest. An empty table gives an empty result. Further columns are not touched.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxprune.llm.graph import components
from boxprune.llm.kernels import U, as_long, mix, release, shingle_sets, slices
from boxprune.llm.shared import BROADCAST_ROWS, discard, stored

#: At most so many frequent tokens are broadcast (9 bytes each). Beyond, the border rises and the least frequent of them become
#: signatures by themselves, which makes longer lists but the same links.
HOT_TOKENS = 1 << 19
#: Tokens in fewer sets than this are always single signatures.
MIN_HOT = 24
#: Tokens in this many times more sets than the border are combined by three.
TRIPLE = 32
#: Tokens in one counting bucket, about.
BUCKET_TOKENS = 2_000_000
#: Hubs of a list grow by this factor in each round.
HUBS = 256
#: Nodes whose 64 bits stand for several sets, at most; about 70 are expected among 5e10 sets.
CLASHES = 1 << 20

#: Words of a set's parity bitmap, of 64 bits each.
_WORDS = [f"b{i}" for i in range(16)]
#: Nodes that a task remembers as sent.
_NO_NODES = 250_000
_NONE = np.zeros(0, np.uint64)

def _fingerprints(own: np.ndarray, sh: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Size and two 64-bit fingerprints of each of n sets."""
    size = np.bincount(own, minlength=n)
    ends = np.cumsum(size)
    out = []
    for salt, step in ((0xA0761D6478BD642F, 0xE7037ED1A0B428DB), (0x8EBC6AF09C88C6E3, 0x589965CC75374CC3)):
        total = np.zeros(len(sh) + 1, np.uint64)
        np.cumsum(mix(sh ^ U(salt)), out=total[1:])
        out.append(mix(total[ends] - total[ends - size] + size.astype(np.uint64) * U(step)))
    return size, *out


def _sets(column, k, folded, clashes=_NONE):
    """For each run of texts: first row, count, and for its nonempty sets the size, node, second hash, bounds, tokens."""
    for at, t in slices(column):
        own, sh = shingle_sets(t, k, folded)
        size, node, more = _fingerprints(own, sh, t.n)
        if len(clashes):
            node = np.where(np.isin(node, clashes), mix(node ^ more), node)
        yield at, t.n, size, node, more, np.cumsum(size) - size, sh


def _nodes(docs: DataFrame, k: int, folded: bool, clashes: np.ndarray) -> DataFrame:
    """key, n, node, second hash and the words of the parity bitmap of each text's set."""

    def job(batches):
        for b in batches:
            for at, n, size, node, more, _, sh in _sets(b.column(1), k, folded, clashes):
                # the tokens of a set are sorted, so those of one bitmap word stand together
                slot = np.repeat(np.arange(n, dtype=np.int64) << 4, size) | (sh >> U(60)).astype(np.int64)
                words = np.zeros(n << 4, np.uint64)
                if len(sh):
                    starts = np.flatnonzero(np.concatenate([[True], slot[1:] != slot[:-1]]))
                    words[slot[starts]] = np.bitwise_xor.reduceat(U(1) << (sh >> U(54) & U(63)), starts)
                words = words.view(np.int64).reshape(n, -1)
                cols = [b.column(0).slice(at, n), pa.array(size.astype(np.int64)), pa.array(as_long(node)), pa.array(as_long(more)), *[pa.array(np.ascontiguousarray(words[:, i])) for i in range(len(_WORDS))]]
                yield pa.RecordBatch.from_arrays(cols, names=["key", "n", "node", "more", *_WORDS])
        release()

    return docs.mapInArrow(job, f"key {docs.schema['key'].dataType.simpleString()}, n long, node long, more long, " + ", ".join(f"{w} long" for w in _WORDS))


def _blob(x: np.ndarray) -> bytes:
    return x.tobytes()


def _frequent(docs: DataFrame, k: int, folded: bool, clashes: np.ndarray, total: int) -> DataFrame:
    """key, df of the tokens that are in MIN_HOT sets or more.

    A token is counted under its bucket (its leading bits) and the next 32 bits, so tokens
    may share a count, which only moves them to another class. Sorted runs of keys travel as blobs; a token is
    sent once for each run of texts, so a token of every set costs one row a run.
    """
    bits = max(0, total // BUCKET_TOKENS).bit_length()

    def send(batches):
        seen: set[int] = set()
        for b in batches:
            for _, n, size, node, _, first, sh in _sets(b.column(0), k, folded, clashes):
                fresh = _fresh(size, node, seen)
                if not len(fresh):
                    continue
                tokens = np.concatenate([sh[first[i] : first[i] + size[i]] for i in fresh])
                keys, c = np.unique(_count_key(tokens, bits), return_counts=True)
                one = c == 1
                runs = []
                for part, counts in ((keys[one], None), (keys[~one], c[~one].astype(np.uint32))):
                    bucket = (part >> U(32)).astype(np.int64)
                    cuts = np.searchsorted(bucket, np.arange((1 << bits) + 1))
                    for i in np.flatnonzero(cuts[1:] > cuts[:-1]):
                        at = slice(cuts[i], cuts[i + 1])
                        runs.append((i, part[at].astype(np.uint32).tobytes(), None if counts is None else counts[at].tobytes()))
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in runs], pa.int32()), pa.array([r[1] for r in runs], pa.binary()), pa.array([r[2] for r in runs], pa.binary())], names=["bucket", "keys", "counts"])

    def count(key, table):
        ks, cs = [], []
        for x, c in zip(table.column("keys").to_pylist(), table.column("counts").to_pylist(), strict=True):
            ks.append(np.frombuffer(x, np.uint32))
            cs.append(np.ones(len(ks[-1]), np.uint32) if c is None else np.frombuffer(c, np.uint32))
        x, c = np.concatenate(ks), np.concatenate(cs)
        order = np.argsort(x)
        x, c = x[order], c[order]
        at = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]]))
        df = np.add.reduceat(c.astype(np.int64), at)
        hot = df >= MIN_HOT
        return pa.table({"key": x[at][hot].astype(np.int64) | int(key[0].as_py()) << 32, "df": df[hot]})

    counted = docs.mapInArrow(send, "bucket int, keys binary, counts binary").groupBy("bucket").applyInArrow(count, "key long, df long")
    return counted.withColumn("bits", F.lit(bits))


def _count_key(h: np.ndarray, bits: int) -> np.ndarray:
    """Bucket and the next 32 bits of hashes."""
    return h >> U(32 - bits)


def _fresh(size: np.ndarray, node: np.ndarray, seen: set[int]) -> np.ndarray:
    """Nonempty sets that this task has not seen; forgetting some only repeats rows."""
    out = []
    for i in np.flatnonzero(size):
        x = int(node[i])
        if x not in seen:
            if len(seen) >= _NO_NODES:
                seen.clear()
            seen.add(x)
            out.append(i)
    return np.array(out, np.int64)


def _hot_classes(frequent: DataFrame) -> tuple[np.ndarray, np.ndarray, int]:
    """Sorted keys of frequent tokens and their combination size, at most HOT_TOKENS of them, and the key's bucket bits."""
    by_power = {int(r["p"]): int(r["c"]) for r in frequent.groupBy(F.floor(F.log2("df")).alias("p")).agg(F.count(F.lit(1)).alias("c")).collect()}  # at most 63 rows
    border, held = MIN_HOT, 0
    for p in sorted(by_power, reverse=True):
        held += by_power[p]
        if held > HOT_TOKENS:
            border = 2 ** (p + 1)
            break
    rows = frequent.where(F.col("df") >= border).toPandas().sort_values("key")
    return rows["key"].to_numpy(np.int64).astype(np.uint64), np.where(rows["df"].to_numpy() >= border * TRIPLE, 3, 2), int(rows["bits"].max()) if len(rows) else 0


def _signatures(docs: DataFrame, k: int, folded: bool, clashes: np.ndarray, hot: tuple[np.ndarray, np.ndarray, int], num: int, den: int) -> DataFrame:
    """sig, node, n, lost."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(hot)

    def combined(sh, cls, n, tau):
        """Signatures of a set that has frequent tokens in its prefix."""
        out: dict[int, int] = {}
        for group in range(max(1, n * num // den).bit_length(), (n * den // num).bit_length() + 1):
            buckets = max(1, (1 << group - 1) // 16)
            held: dict[tuple[int, int], list[int]] = {}
            run = 0
            for t, c in zip(sh, cls, strict=True):
                if run > tau:
                    break
                if c == 1:
                    out[t] = min(out.get(t, run), run)  # bounds differ by size class; only the least loses no link
                    run += 1
                    continue
                mates = held.setdefault((c, t % buckets), [])
                if len(mates) >= c - 1:
                    for combo in combinations(mates, c - 1):
                        h = 0x9E3779B97F4A7C15 + group * 8 + c
                        for x in (*combo, t):
                            h = (h * 0xBF58476D1CE4E5B9 + x) & 0xFFFFFFFFFFFFFFFF
                            h ^= h >> 29
                        out.setdefault(h, run)
                    run += 1
                mates.append(t)
            if run <= tau:
                out.update(dict.fromkeys(sh, 0))
        return out

    def job(batches):
        keys, sizes, bits = shared.value
        seen: set[int] = set()
        for b in batches:
            for _, n, size, node, _, first, sh in _sets(b.column(0), k, folded, clashes):
                fresh = _fresh(size, node, seen)
                fresh = fresh[size[fresh] * den >= num * (size[fresh] + 1)]  # no other set is like a smaller one
                if not len(fresh):
                    continue
                mine = np.zeros(n, bool)
                mine[fresh] = True
                own = np.repeat(np.arange(n), size)
                pick = mine[own]
                own, sh = own[pick], sh[pick]
                cls = np.ones(len(sh), np.int8)
                if len(keys):
                    mine_keys = _count_key(sh, bits)
                    at = np.minimum(np.searchsorted(keys, mine_keys), len(keys) - 1)
                    hit = keys[at] == mine_keys
                    cls[hit] = sizes[at[hit]]
                order = np.lexsort((sh, cls, own))
                own, sh, cls = own[order], sh[order], cls[order]
                count = np.where(mine, size, 0)
                begin = np.cumsum(count) - count
                place = np.arange(len(sh)) - begin[own]
                tau = count - -(-count * num // den)
                inside = place <= tau[own]
                slow = np.zeros(n, bool)
                slow[own[inside & (cls > 1)]] = True
                fast = inside & ~slow[own]
                sigs, nodes, ns, lost = [sh[fast]], [node[own[fast]]], [count[own[fast]]], [place[fast]]
                for i in np.flatnonzero(slow):
                    s = slice(begin[i], begin[i] + count[i])
                    got = combined(sh[s].tolist(), cls[s].tolist(), int(count[i]), int(tau[i]))
                    sigs.append(np.fromiter(got, np.uint64, len(got)))
                    lost.append(np.fromiter(got.values(), np.int64, len(got)))
                    nodes.append(np.full(len(got), node[i]))
                    ns.append(np.full(len(got), count[i]))
                cols = [pa.array(as_long(np.concatenate(sigs))), pa.array(as_long(np.concatenate(nodes))), pa.array(np.concatenate(ns).astype(np.int32)), pa.array(np.concatenate(lost).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(cols, names=["sig", "node", "n", "lost"])

    return docs.mapInArrow(job, "sig long, node long, n int, lost int")


def _may_link(a: str, b: str, num: int, den: int):
    """Both sets can still share the overlap that the threshold needs."""
    need = num * (F.col(f"{a}.n") + F.col(f"{b}.n"))
    return (((num + den) * (F.col(f"{a}.n") - F.col(f"{a}.lost"))) >= need) & (((num + den) * (F.col(f"{b}.n") - F.col(f"{b}.lost"))) >= need)


def _close(p: str, q: str, num: int, den: int):
    """Sets differ in at least as many tokens as their parity bitmaps differ in bits; the overlap that is left must do."""
    apart = sum((F.bit_count(F.col(f"{p}.{w}").bitwiseXOR(F.col(f"{q}.{w}"))) for w in _WORDS), F.lit(0))
    total = F.col(f"{p}.n") + F.col(f"{q}.n")
    return (num + den) * (total - apart) >= 2 * num * total


def _verified(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """The pairs (a, b) whose sets are similar enough."""

    def job(batches):
        for b in batches:
            keep = []
            for x, y in zip(b.column("x").to_pylist(), b.column("y").to_pylist(), strict=True):
                both = np.concatenate([np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)])
                both.sort()
                shared = int((both[1:] == both[:-1]).sum())
                keep.append(den * shared >= num * (len(both) - shared))
            yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = sets.select(F.col("node").alias("a"), F.col("tokens").alias("x"))
    right = sets.select(F.col("node").alias("b"), F.col("tokens").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(job, "a long, b long")


def _token_sets(docs: DataFrame, marks: DataFrame, pairs: DataFrame, k: int, folded: bool, clashes: np.ndarray) -> DataFrame:
    """node, tokens (sorted hashes) of the nodes in pairs."""

    def job(batches):
        for b in batches:
            for _, n, size, node, _, first, sh in _sets(b.column(1), k, folded, clashes):
                yield pa.RecordBatch.from_arrays([pa.array(as_long(node)), pa.array([_blob(sh[first[i] : first[i] + size[i]]) for i in range(n)], pa.binary())], names=["node", "tokens"])
        release()

    nodes = pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct()
    wanted = stored(marks.join(nodes, "node", "left_semi").select("key"))
    side = F.broadcast(wanted) if wanted.count() <= BROADCAST_ROWS else wanted
    return docs.join(side, "key", "left_semi").select("key", "text").mapInArrow(job, "node long, tokens binary").dropDuplicates(["node"])


def _named_apart(base: DataFrame) -> np.ndarray:
    """Nodes whose 64 bits stand for more than one set."""
    apart = base.where("n > 0").groupBy("node").agg(F.min("more").alias("m0"), F.max("more").alias("m1"), F.min("n").alias("n0"), F.max("n").alias("n1")).where("m0 <> m1 OR n0 <> n1")
    found = apart.select("node").limit(CLASHES + 1).toPandas()["node"].to_numpy(np.int64)  # as many as chance makes equal, or an error
    if len(found) > CLASHES:
        raise ValueError("too many sets share their 64-bit fingerprint")
    return np.sort(found.view(np.uint64))


def jaccard_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 3, num: int = 90, den: int = 100, folded: bool = True) -> DataFrame:
    """key, n, least: for each row its key (see row_key), the size of its set, and the least key of its class."""
    docs = docs.select(row_key(id_col, text_col).alias("key"), F.col(text_col).alias("text"))
    base = stored(_nodes(docs, k, folded, _NONE))
    clashes = _named_apart(base)
    if len(clashes):
        base = stored(_nodes(docs, k, folded, clashes))
    total = base.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("t")).first()["t"]
    texts = docs.select("text")
    hot = _hot_classes(stored(_frequent(texts, k, folded, clashes, total)))
    signatures = stored(_signatures(texts, k, folded, clashes, hot, num, den))

    # a list counts once for each task that saw a copy of its node, so lists of one node are only sorted out below
    met = signatures.groupBy("sig").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("sig")
    lists = stored(signatures.join(met, "sig").distinct())
    discard(signatures)
    first = base.where("n > 0").groupBy("node").agg(F.min("key").alias("key"))
    marks = stored(base.join(first, ["node", "key"]).join(lists.select("node").distinct(), "node", "left_semi").dropDuplicates(["node"]))

    def linked(pairs: DataFrame) -> DataFrame:
        """The links among pairs: those that the bitmaps leave are verified on whole sets."""
        near = pairs.join(marks.alias("p"), F.col("a") == F.col("p.node")).join(marks.alias("q"), F.col("b") == F.col("q.node")).where(_close("p", "q", num, den))
        near = stored(near.select("a", "b"))
        if near.isEmpty():
            return near
        return stored(_verified(near, stored(_token_sets(docs, marks, near, k, folded, clashes)), num, den))

    hubs = lists.groupBy("sig").agg(F.min(F.struct("lost", "node", "n")).alias("hub"), F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo <> hi").select("sig", "hub")
    tested = stored(_met(lists, hubs, num, den))
    comps = components(linked(tested))
    left = stored(_open(lists.join(hubs.select("sig", F.col("hub.node").alias("node")), ["sig", "node"], "left_anti"), comps))
    width = 1
    while not left.isEmpty():
        width *= HUBS
        hubs = left.groupBy("sig", F.pmod(F.xxhash64("node"), F.lit(width)).alias("class")).agg(F.min(F.struct("lost", "node", "n", "comp")).alias("hub")).drop("class")
        hubs = stored(hubs)
        pairs = stored(_met(left, hubs, num, den).join(tested, ["a", "b"], "left_anti"))
        if not pairs.isEmpty():
            tested = tested.union(pairs)
            named = linked(pairs).join(comps.withColumnRenamed("node", "a").withColumnRenamed("comp", "ca"), "a", "left").join(comps.withColumnRenamed("node", "b").withColumnRenamed("comp", "cb"), "b", "left")
            edges = stored(named.select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b"), F.col("a").alias("na"), F.col("b").alias("nb")))
            if not edges.isEmpty():
                merged = components(edges.select("a", "b"))
                ends = edges.select(F.col("na").alias("node"), F.col("a").alias("comp")).union(edges.select("nb", "b"))
                comps = comps.unionByName(ends.join(comps, "node", "left_anti").distinct())
                comps = stored(comps.join(merged.select(F.col("node").alias("comp"), F.col("comp").alias("to")), "comp", "left").select("node", F.coalesce("to", "comp").alias("comp")))
        left = stored(_open(left.drop("comp").join(hubs.select("sig", F.col("hub.node").alias("node")), ["sig", "node"], "left_anti"), comps))

    classed = base.join(comps, "node", "left").select("key", "n", F.coalesce("comp", "node").alias("comp"))
    smallest = classed.where("n > 0").groupBy("comp").agg(F.min("key").alias("least"))
    return classed.join(smallest, "comp", "left").select("key", "n", F.when(F.col("n") > 0, F.col("least")).otherwise(F.col("key")).alias("least"))


def row_key(id_col: str = "doc_id", text_col: str = "text"):
    """What tells rows apart: the id, null ids last, then a hash of the text."""
    return F.struct(F.col(id_col).isNull().alias("z"), F.col(id_col).alias("id"), F.xxhash64(F.col(text_col)).alias("h"))


def _met(lists: DataFrame, hubs: DataFrame, num: int, den: int) -> DataFrame:
    """Distinct pairs (a, b) of hubs with members of their lists that may still link; in later rounds, of other components only."""
    member, hub = F.col("m.node"), F.col("h.hub.node")
    apart = (F.col("m.comp") != F.col("h.hub.comp")) if "comp" in lists.columns else (member != hub)
    met = lists.alias("m").join(hubs.alias("h"), "sig").where(apart)
    met = met.select(F.struct("m.n", "m.lost").alias("p"), F.struct(F.col("h.hub.n").alias("n"), F.col("h.hub.lost").alias("lost")).alias("q"), F.least(member, hub).alias("a"), F.greatest(member, hub).alias("b"))
    return met.where(_may_link("p", "q", num, den)).select("a", "b").distinct()


def _open(lists: DataFrame, comps: DataFrame) -> DataFrame:
    """The members of lists that hold two components or more, with their components."""
    labelled = lists.join(comps, "node", "left").select("sig", "node", "n", "lost", F.coalesce("comp", "node").alias("comp"))
    split = labelled.groupBy("sig").agg(F.min("comp").alias("c0"), F.max("comp").alias("c1")).where("c0 <> c1").select("sig")
    return labelled.join(split, "sig", "left_semi")


def jaccard_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 3, num: int = 90, den: int = 100, folded: bool = True) -> DataFrame:
    """id, n_shingles, component_id: classes of documents linked at Jaccard >= num/den, by their smallest id."""
    found = jaccard_classes(docs, id_col, text_col, k, num, den, folded)
    return found.select(F.col("key.id").alias(id_col), F.col("n").alias("n_shingles"), F.col("least.id").alias("component_id"))
