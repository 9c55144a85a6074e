"""Quality rules with host-level verdicts.

Each text gets counts over its words and lines and fails or passes some rules. Failures of each rule are
summed by host; the hosts' failure rates are shrunk towards a beta prior that is fitted to all hosts by moments, one prior a
rule, and documents of hosts with a shrunk rate above ``host_limit`` under any rule are rejected as well.

Null or empty text has no words and fails the base rule. A null host is a host of its own. Repeated
rows are judged one by one. An empty table gives an empty result. Further columns are not touched.
"""

from __future__ import annotations

from functools import reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxprune.llm.kernels import U, mix, slices, windows
from boxprune.llm.shared import small_side, stored

#: Fixed values of the base rule.
SYMBOLS = "#*$%&|<>"
MIN_WORDS = 10
REPEAT_PERCENT = 20
REPEAT_WINDOW = 5

#: A host is rejected if its shrunk failure rate is above this.
HOST_LIMIT = 0.5

COUNTS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


def _repeats(of: np.ndarray, h: np.ndarray) -> np.ndarray:
    """True for members of (of, h) groups with two or more members."""
    key = mix(h + of.astype(np.uint64) * U(0xD6E8FEB86659FD93))
    order = np.argsort(key, kind="stable")
    k = key[order]
    same = np.zeros(len(k), bool)
    same[1:] = k[1:] == k[:-1]
    same[:-1] |= k[1:] == k[:-1]
    out = np.zeros(len(k), bool)
    out[order] = same
    return out


def text_counts(column: pa.Array) -> list[np.ndarray]:
    """The five counts of each text of an Arrow string column."""
    symbol = np.zeros(256, bool)
    symbol[list(SYMBOLS.encode())] = True
    parts: list[list[np.ndarray]] = [[] for _ in range(5)]
    for _, t in slices(column):
        start, end, of, h = t.words()
        parts[0].append(np.bincount(of, minlength=t.n))
        leads = np.zeros(len(t.data) + 1, np.int64)
        np.cumsum((t.data & 0xC0) != 0x80, out=leads[1:])
        parts[1].append(np.bincount(of, weights=leads[end] - leads[start], minlength=t.n).astype(np.int64))
        parts[2].append(t.count(symbol[t.data]))
        # lines: cut at text borders and line feeds, keep those that hold a word
        feeds = np.flatnonzero(t.data == 10)
        begin = np.unique(np.concatenate([t.offsets[:-1], feeds + 1]))
        begin = begin[begin < len(t.data)]
        stop = np.minimum(np.append(feeds, len(t.data))[np.searchsorted(feeds, begin)], t.offsets[np.minimum(np.searchsorted(t.offsets, begin, side="right"), t.n)])
        worded = np.searchsorted(start, stop) > np.searchsorted(start, begin)
        begin, stop = begin[worded], stop[worded]
        own = np.searchsorted(t.offsets, begin, side="right") - 1
        key = mix(t.span_hash(begin, stop) + own.astype(np.uint64) * U(0xD6E8FEB86659FD93))
        _, first = np.unique(key, return_index=True)
        again = np.ones(len(begin), bool)
        again[first] = False
        parts[3].append(np.bincount(own[again], minlength=t.n))
        at, w = windows(of, h, REPEAT_WINDOW)
        hit = at[_repeats(of[at], w)]
        edge = np.zeros(len(of) + 1, np.int64)
        np.add.at(edge, hit, 1)
        np.add.at(edge, hit + REPEAT_WINDOW, -1)
        parts[4].append(np.bincount(of[np.cumsum(edge[:-1]) > 0], minlength=t.n))
    return [np.concatenate(p).astype(np.int64) if p else np.zeros(0, np.int64) for p in parts]


def document_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """doc_id, host and the counts of each text."""
    kinds = {f.name: f.dataType.simpleString() for f in docs.schema}

    def job(batches):
        for b in batches:
            counts = text_counts(b.column(2))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *map(pa.array, counts)], names=["doc_id", "host", *[c.split()[0] for c in COUNTS.split(", ")]])

    picked = docs.select(F.col(id_col).alias("doc_id"), F.col(host_col).cast("string").alias("host"), F.col(text_col).alias("text"))
    return picked.mapInArrow(job, f"doc_id {kinds[id_col]}, host string, {COUNTS}")


def base_failed():
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))


#: The rule of a document's own verdict.
BASE = {"base": base_failed}
#: Rules whose failures count for hosts: beside the base rule, a tenth of symbols, words shorter than two characters on
#: average, and a repeated line for each ten words.
HOST_RULES = BASE | {
    "symbols": lambda: 10 * F.col("n_symbols") > F.col("word_chars"),
    "short_words": lambda: F.col("word_chars") < 2 * F.col("n_words"),
    "repeated_lines": lambda: 10 * F.col("n_dup_lines") > F.col("n_words"),
}

#: Hosts that may be broadcast (a name and a verdict each).
BROADCAST_HOSTS = 200_000


def host_rates(counted: DataFrame, host_limit: float = HOST_LIMIT, rules: dict = BASE) -> DataFrame:
    """One row a host: documents, and for each rule its failures and shrunk failure rate; and the verdict.

    Prior of a rule by moments over hosts: mean m and variance v of the raw rates give the strength
    s = m(1-m)/v - 1, kept within 1 to 1e6; a = m s, b = (1-m) s. Sums are partial before the shuffle, so a host of any
    size costs a row a task.
    """
    sums = [F.sum(rule().cast("long")).alias(f"failed_{name}") for name, rule in rules.items()]
    hosts = counted.groupBy("host").agg(F.count(F.lit(1)).alias("host_docs"), *sums)
    moments = []
    for name in rules:
        rate = F.col(f"failed_{name}") / F.col("host_docs")
        m, v = F.avg(rate), F.var_pop(rate)
        strength = F.when(v > 0, F.least(F.greatest(m * (1 - m) / v - 1, F.lit(1.0)), F.lit(1e6))).otherwise(F.lit(1e6))
        moments += [m.alias(f"m_{name}"), strength.alias(f"s_{name}")]
    out = hosts.crossJoin(F.broadcast(hosts.agg(*moments)))  # one row of priors
    rates = {f"rate_{n}": (F.col(f"failed_{n}") + F.col(f"m_{n}") * F.col(f"s_{n}")) / (F.col("host_docs") + F.col(f"s_{n}")) for n in rules}
    out = out.withColumns(rates).withColumn("host_rejected", reduce(or_, [F.col(c) > host_limit for c in rates]))
    return out.drop(*[f"{x}_{n}" for n in rules for x in "ms"])


def quality_verdicts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", host_limit: float = HOST_LIMIT, rules: dict = BASE) -> DataFrame:
    """One row a document: its counts, base_failed, what its host's rates are and the final verdict."""
    judged = stored(document_counts(docs, id_col, text_col, host_col).withColumn("base_failed", base_failed()))
    hosts = small_side(stored(host_rates(judged, host_limit, rules)), BROADCAST_HOSTS)
    out = judged.join(hosts, judged["host"].eqNullSafe(hosts["host"]), "left").drop(hosts["host"])
    return out.withColumn("kept", ~F.col("base_failed") & ~F.coalesce(F.col("host_rejected"), F.lit(False)))


def keep_good(docs: DataFrame, text_col: str = "text", host_col: str = "source", host_limit: float = HOST_LIMIT, rules: dict = HOST_RULES) -> DataFrame:
    """The rows of docs that pass, with all of their columns. Each row carries its own verdict, so ids play no part."""
    counted = document_counts(docs.withColumn("__boxprune_id", F.lit(0)), "__boxprune_id", text_col, host_col)
    hosts = host_rates(counted, host_limit, rules).select(F.col("host").alias("__boxprune_host"), F.col("host_rejected").alias("__boxprune_rejected"))
    hosts = small_side(stored(hosts.where("__boxprune_rejected")), BROADCAST_HOSTS)
    at = docs.columns.index(text_col)

    def job(batches):
        for b in batches:
            words, *_, repeats = text_counts(b.column(at))
            failed = (words < MIN_WORDS) | (100 * repeats > REPEAT_PERCENT * words)
            yield b.filter(pa.array(~failed))

    passed = docs.mapInArrow(job, docs.schema)
    return passed.join(hosts, passed[host_col].cast("string").eqNullSafe(hosts["__boxprune_host"]), "left_anti")
