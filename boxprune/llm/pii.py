"""Personal data and credentials with DataFrame functions only.

Fixed patterns give the base spans (email, ip, card, phone), each checked as its kind asks. Beside
them a high-recall generator proposes every run of 10 or more key characters that holds a digit; the proposals
may overlap base spans. Each has format features (length, share of digits, letters, alphabet) and context
features (what stands before it). Their joint counts over all documents, a table of at most
``CELLS`` rows, train boosted trees on the driver; labels come from strict key formats and from credential
words before the run, which are not features. The threshold is the least score at which the calibrated
precision reaches ``PRECISION``; proposals above it become spans of kind secret.

Null text counts as empty and has no spans. Repeated rows are searched one by one. An empty table gives an empty
result. Further columns pass through.
"""

from __future__ import annotations

import math
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from boxprune.llm.shared import blank_text

#: The base kinds in the order in which they are listed, and their patterns.
KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: The same matches without backtracking: possessive, and started only where a run starts or the last match ended.
_FAST = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_NEEDS = {"email": "@", "ip": "[0-9][.][0-9]", "card": "[0-9][0-9 -]{12,}", "phone": "\\+[0-9]"}

SECRET = "secret"
#: Key characters; the run must hold a digit.
_PROPOSE = r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*+[0-9])[A-Za-z0-9+/_-]{10,}+"
_STRICT = r"^(AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9]{20,}|xox[abp]-[A-Za-z0-9-]{10,})$"
_CREDENTIAL = r"(?i)(password|passwd|pwd|token|secret|api[_-]?key|access[_-]?key)[\"']?\s{0,2}[=:]\s{0,2}[\"']?$"
#: Characters looked at before a proposal.
BEFORE = 24

PRECISION = 0.9
TREES = 24
RATE = 0.4

_OPEN, _CLOSE, _OTHER = "\x02", "\x03", "\x04"


# ---------------------------------------------------------------- spans of a pattern


def let(value: Column, body) -> Column:
    """body(value) with the value computed once, even if a lambda in the body uses it for each element."""
    return F.transform(F.array(value), body)[0]


def exclusive_scan(values: Column, total: str = "sum") -> Column:
    """For each element, the sum (or maximum) of those before it, 0 at first.

    Two levels of blocks of the square root of the size keep the work far from its square.
    """
    zero = F.lit(0).cast("long")
    join = (lambda a, x: a + x) if total == "sum" else (lambda a, x: F.greatest(a, x))

    def fold(arr):
        return F.aggregate(arr, zero, join)

    def blocks(v):
        width = F.greatest(F.ceil(F.sqrt(F.size(v))).cast("int"), F.lit(1))
        return F.transform(F.sequence(F.lit(0), width - 1), lambda b: F.slice(v, b * width + 1, width))

    def inside(x, start):
        return F.transform(x, lambda _, i: join(start, fold(F.slice(x, F.lit(1), i))))

    def over(bs):
        return let(F.transform(bs, fold), lambda sums: F.flatten(F.transform(bs, lambda x, i: inside(x, fold(F.slice(sums, F.lit(1), i))))))

    return let(values, lambda v: let(blocks(v), over))


MATCH = "array<struct<start:bigint,match:string,before:string>>"


def _matches(text: Column, pattern: str, needs: str, before: int = 0) -> Column:
    """array of (start, match, before) in code points for the leftmost non-overlapping matches."""
    marked = F.regexp_replace(F.translate(text, _OPEN + _CLOSE, _OTHER + _OTHER), pattern, f"{_OPEN}$0{_CLOSE}")

    def rows(pieces):
        starts = exclusive_scan(F.transform(pieces, lambda p, i: F.length(p).cast("long") - F.when(i > 0, 1).otherwise(0)))
        ahead = F.transform(pieces, lambda p: F.right(F.translate(p, _CLOSE, ""), F.lit(before)) if before else F.lit(""))
        shifted = F.concat(F.array(F.lit("")), ahead)
        zipped = F.filter(F.arrays_zip(starts.alias("start"), pieces.alias("piece"), shifted.alias("last")), lambda z, i: (i > 0) & z["piece"].isNotNull())
        return F.transform(zipped, lambda z: F.struct(z["start"].alias("start"), F.substring_index(z["piece"], _CLOSE, 1).alias("match"), z["last"].alias("before")))

    return F.when(text.rlike(needs), let(F.split(marked, _OPEN), rows)).otherwise(F.array().cast(MATCH))


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(x: Column) -> Column:
    d = _digits(x)
    n = F.length(d)
    each = F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.substr(d, n - i + 1, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1))
    total = F.aggregate(each, F.lit(0), lambda a, v: a + F.when(v > 9, v - 9).otherwise(v))
    return F.when(n.between(14, 19), total % 10 == 0).otherwise(F.lit(False))


def _valid(kind: str, x: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(x, "\\."), lambda p: p.rlike("^0*([0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$"))
    if kind == "card":
        return _luhn(x)
    if kind == "phone":
        return F.length(_digits(x)).between(10, 15)
    return F.lit(True)


def _as_spans(rows: Column, kind: str, order: int) -> Column:
    return F.transform(rows, lambda m: F.struct(m["start"].alias("start"), F.lit(order).alias("order"), (m["start"] + F.length(m["match"])).alias("end"), F.lit(kind).alias("kind")))


def base_spans(text: Column) -> Column:
    """array of (start, order, end, kind), by start and kind."""

    def of(kind: str, order: int) -> Column:
        return _as_spans(F.filter(_matches(text, _FAST[kind], _NEEDS[kind]), lambda m: _valid(kind, m["match"])), kind, order)

    return F.concat(*[of(k, i) for i, k in enumerate(KINDS)])


# ---------------------------------------------------------------- boosted trees over feature cells


def features(m: Column) -> dict[str, Column]:
    """Small integers from a proposal's format and from what stands before it."""
    x, before = m["match"], m["before"]
    n = F.length(x)
    share = F.length(_digits(x)) / n
    return {
        "length": F.when(n < 14, 0).when(n < 18, 1).when(n < 28, 2).otherwise(3),
        "digits": F.when(share < 0.2, 0).when(share < 0.5, 1).when(share < 1, 2).otherwise(3),
        "letters": F.when(x.rlike("[a-z]"), 1).otherwise(0) + F.when(x.rlike("[A-Z]"), 2).otherwise(0),
        "alphabet": F.when(x.rlike("^[0-9a-fA-F]+$"), 0).when(x.rlike("^[A-Za-z0-9]+$"), 1).otherwise(2),
        "opened": F.when(before.rlike("[=:]\\s{0,2}[\"']?$"), 1).otherwise(0),
    }


LEVELS = {"length": 4, "digits": 4, "letters": 4, "alphabet": 3, "opened": 2}
CELLS = math.prod(LEVELS.values())


def weak_label(m: Column) -> Column:
    return m["match"].rlike(_STRICT) | m["before"].rlike(_CREDENTIAL)


def boost(cells: dict[tuple[int, ...], tuple[int, int]], trees: int = TREES, rate: float = RATE) -> tuple[float, list[tuple]]:
    """Depth-two trees of logistic loss on (negatives, positives) by cell; names index LEVELS.

    Gives the bias and trees ((feature, cut), then twice ((feature, cut), low, high)).
    """
    names = list(LEVELS)
    total = [sum(c[i] for c in cells.values()) for i in (0, 1)]
    bias = math.log((total[1] + 0.5) / (total[0] + 0.5))
    score = dict.fromkeys(cells, bias)
    cuts = [(f, c) for f in range(len(names)) for c in range(LEVELS[names[f]] - 1)]

    def grads(some):
        g = h = 0.0
        for k in some:
            n, p = cells[k]
            q = 1 / (1 + math.exp(-score[k]))
            g += p - (n + p) * q
            h += (n + p) * q * (1 - q)
        return g, h

    def best(some):
        top = None
        for f, c in cuts:
            sides = [grads([k for k in some if k[f] <= c]), grads([k for k in some if k[f] > c])]
            gain = sum(g * g / (h + 1) for g, h in sides)
            if top is None or gain > top[0] + 1e-12:
                top = (gain, (f, c), [rate * g / (h + 1) for g, h in sides])
        return top

    out = []
    for _ in range(trees):
        keys = list(cells)
        if not keys:
            break
        _, (f, c), _ = best(keys)
        sides = [[k for k in keys if k[f] <= c], [k for k in keys if k[f] > c]]
        leaves = [best(s) for s in sides]
        out.append(((f, c), *[(x[1], *x[2]) for x in leaves]))
        for side, (_, (g, d), (low, high)) in zip(sides, leaves, strict=True):
            for k in side:
                score[k] += low if k[g] <= d else high
    return bias, out


def tree_score(model: tuple[float, list[tuple]], values: list):
    """The score of feature values, numbers or Columns."""
    bias, trees = model
    pick = (lambda cond, a, b: F.when(cond, a).otherwise(b)) if isinstance(values[0], Column) else (lambda cond, a, b: a if cond else b)
    total = F.lit(bias) if isinstance(values[0], Column) else bias
    for (f, c), (lo, la, lb), (hi, ha, hb) in trees:
        total = total + pick(values[f] <= c, pick(values[lo[0]] <= lo[1], la, lb), pick(values[hi[0]] <= hi[1], ha, hb))
    return total


def calibrate(cells: dict[tuple[int, ...], tuple[int, int]], model, precision: float = PRECISION) -> float:
    """The least score above which smoothed precision, from the top down, stays at the target."""
    scored = sorted(((tree_score(model, list(k)), n, p) for k, (n, p) in cells.items()), reverse=True)
    best, neg, pos = math.inf, 0, 0
    for s, n, p in scored:
        neg, pos = neg + n, pos + p
        if pos and (pos + 0.5) / (pos + neg + 1) >= precision * (pos / (pos + 1)) and p >= n:
            best = s
        else:
            break
    return best


def train(proposed: DataFrame) -> tuple[tuple[float, list[tuple]], float, dict]:
    """Fit on the counts of all proposals; proposed has an array column ``proposals``."""
    rows = proposed.where(F.size("proposals") > 0).select(F.explode("proposals").alias("m"))
    rows = rows.select(*[c.alias(k) for k, c in features(F.col("m")).items()], weak_label(F.col("m")).cast("int").alias("label"))
    counts = rows.groupBy(*LEVELS).agg(F.count(F.lit(1)).alias("n"), F.sum("label").alias("p")).collect()  # at most CELLS rows
    cells = {tuple(r[k] for k in LEVELS): (r["n"] - r["p"], r["p"]) for r in counts}
    cells = {k: cells[k] for k in product(*[range(v) for v in LEVELS.values()]) if k in cells}
    model = boost(cells)
    return model, calibrate(cells, model), cells


def find_spans(docs: DataFrame, text_col: str = "text", spans_col: str = "spans") -> DataFrame:
    """All columns and ``spans_col`` (which replaces one of that name): array of (start, order, end, kind), by start and kind; code points, end exclusive."""
    text = blank_text(text_col)
    proposals = _matches(text, _PROPOSE, "[0-9]", BEFORE)
    model, limit, cells = train(docs.select(proposals.alias("proposals")))
    spans = base_spans(text)
    if limit < math.inf:
        # the trees see a proposal only through its cell, so cells that reach the threshold are listed once
        chosen = sorted("".join(map(str, k)) for k in cells if tree_score(model, list(k)) >= limit)
        secret = F.filter(proposals, lambda m: F.concat(*[c.cast("string") for c in features(m).values()]).isin(chosen))
        spans = F.concat(spans, _as_spans(secret, SECRET, len(KINDS)))
    return docs.withColumn(spans_col, F.array_sort(spans))


def span_digest(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The documents with each run of overlapping spans replaced by its first kind in brackets."""
    spans = "__boxprune_spans"
    found = find_spans(docs, text_col, spans)
    text = F.col(text_col)

    def part(start, end):
        return F.substr(text, (start + 1).cast("int"), (end - start).cast("int"))

    def cleaned(spans):
        reach = exclusive_scan(F.transform(spans, lambda s: s["end"]), "max")
        pieces = F.transform(F.arrays_zip(spans.alias("s"), reach.alias("r")), lambda z: F.when(z["s"]["start"] >= z["r"], F.concat(part(z["r"], z["s"]["start"]), F.lit("["), F.upper(z["s"]["kind"]), F.lit("]"))).otherwise(F.lit("")))
        end = F.array_max(F.transform(spans, lambda s: s["end"]))
        return F.concat(F.array_join(pieces, ""), part(end, F.length(text).cast("long")))

    new = F.when(F.size(spans) > 0, let(F.col(spans), cleaned)).otherwise(text)
    return found.select(*[new.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns])
