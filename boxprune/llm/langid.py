"""Language of texts by a linear-chain conditional random field over their words.

A word's features are hashed: its prefixes and suffixes, byte n-grams with borders, and the word itself (a learned
lexicon). Labels of neighbouring words are tied by learned transitions, so words of code-switched text may
change language. The field is fitted by adaptive gradient steps on sequences spliced from short runs of labelled texts in
different languages. A text's prediction is the label with the greatest mean of word marginals, found by
forward-backward over all of its words; that mean is the score.

The fit takes at most ``TRAIN_DOCS`` labelled texts, dealt evenly to the languages, those with the least hash of their id, and
from each at most ``TEXT_RUNS`` runs of words at places drawn over its whole length; predictions cover every whole text. Null text, and text without letters, is ``und`` with score 0, as is everything if there is no labelled text.
Repeated rows are predicted one by one. An empty table gives an empty result. Further columns are not touched.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Bound of the labelled sample, in documents.
TRAIN_DOCS = 1500
#: Runs of words taken from one training text and their length; spliced sequences, their length, sizes of the runs in each.
TEXT_RUNS, RUN_WORDS = 24, 24
SEQUENCES, LENGTH, RUNS = 3000, 48, (4, 24)
BUCKETS = 1 << 18
EPOCHS, BATCH, RATE, RIDGE = 4, 64, 0.3, 1e-6
#: Words memoised by a worker before the memo starts anew; words of texts run in step.
MEMO, STEP_WORDS = 300_000, 400_000

UNKNOWN = "und"
_LETTER = regex.compile(r"\p{L}")


def split_words(text: str) -> list[bytes]:
    return text.lower().encode("utf-8", "replace").split()


def lettered(text: str) -> list[bytes]:
    return [w for w in split_words(text) if _LETTER.search(w.decode("utf-8", "replace"))]


def text_runs(text: str, runs: int = TEXT_RUNS, size: int = RUN_WORDS) -> list[str]:
    """Runs of lettered words at places that a hash of the text draws over all of it; a short text is one run."""
    words = lettered(text)
    if len(words) <= runs * size:
        return [b" ".join(words).decode("utf-8", "replace")] if words else []
    at = np.random.Generator(np.random.PCG64(zlib.crc32(text.encode("utf-8", "replace")))).integers(0, len(words) - size + 1, runs)
    return [b" ".join(words[i : i + size]).decode("utf-8", "replace") for i in at.tolist()]


def word_features(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features of all words in a row, and where each word's begin."""
    n = len(words)
    raw = np.frombuffer(b"".join([b"\x02" + w + b"\x03" for w in words]), np.uint8).astype(np.uint64)
    lens = np.fromiter(map(len, words), np.int64, n) + 2
    ends = np.cumsum(lens)
    begins = ends - lens
    of = np.repeat(np.arange(n), lens)
    owners, feats = [], []

    def add(own, h, salt):
        h = (h ^ np.uint64(salt * 0x9E3779B97F4A7C15 & (2**64 - 1))) * np.uint64(0xBF58476D1CE4E5B9)
        owners.append(own)
        feats.append((h >> np.uint64(46)).astype(np.int64) % BUCKETS)

    run = raw.copy()
    for size in (2, 3, 4, 5):
        run = run[:-1] * np.uint64(257) + raw[size - 1 :]
        if len(run) == 0:
            break
        ok = np.flatnonzero(of[: len(run)] == of[size - 1 :])
        if size < 5:
            add(of[ok], run[ok], size)  # n-grams
        first = ok[ok == begins[of[ok]]]
        add(of[first], run[first], 10 + size)  # prefix after the border
        last = ok[ok + size == ends[of[ok]]]
        add(of[last], run[last], 20 + size)  # suffix before the border
    powers = np.multiply.accumulate(np.full(int(lens.max()) + 1, 1099511628211, np.uint64))
    whole = np.add.reduceat(raw * powers[np.arange(len(raw)) - begins[of]], begins)
    add(np.arange(n), whole, 40)  # lexicon
    own, f = np.concatenate(owners), np.concatenate(feats)
    order = np.argsort(own, kind="stable")
    return f[order], np.searchsorted(own[order], np.arange(n))


def marginals(scores: np.ndarray, lens: np.ndarray, trans: np.ndarray, pairs: bool = False):
    """Forward-backward over padded sequences: scores (batch, length, labels) gives word marginals, and with
    pairs also the expected transitions and the log normaliser."""
    b, t, k = scores.shape
    top = scores.max(axis=2, keepdims=True)
    e = np.exp(scores - top)
    m = np.exp(trans)
    alpha, scale = np.empty_like(e), np.ones((b, t), e.dtype)
    a = e[:, 0] / k
    for i in range(t):
        if i:
            a = (a @ m) * e[:, i]
        s = a.sum(axis=1)
        a = a / s[:, None]
        alpha[:, i], scale[:, i] = a, s
    beta = np.ones((b, k), e.dtype)
    out = np.empty_like(e)
    expected = np.zeros_like(m)
    for i in range(t - 1, -1, -1):
        done = (lens - 1 <= i)[:, None]
        if i + 1 < t:
            ahead = e[:, i + 1] * beta
            if pairs:
                w = np.where(i + 1 < lens, 1.0, 0.0)
                joint = alpha[:, i, :, None] * m * ahead[:, None, :]
                expected += (joint * (w / np.maximum(joint.sum(axis=(1, 2)), 1e-300))[:, None, None]).sum(axis=0)
            beta = ahead @ m.T
            beta /= beta.sum(axis=1, keepdims=True)
        beta = np.where(done, 1.0, beta)
        p = alpha[:, i] * beta
        out[:, i] = p / p.sum(axis=1, keepdims=True)
    return (out, expected, scale, top) if pairs else out


class Field:
    """Weights of hashed features by label, and transitions."""

    def __init__(self, labels: list[str]):
        self.labels = labels
        self.w = np.zeros((BUCKETS, len(labels)), np.float32)
        self.trans = np.zeros((len(labels), len(labels)))

    def emissions(self, words: list[bytes]) -> np.ndarray:
        f, at = word_features(words)
        return np.add.reduceat(self.w[f], at, axis=0)

    def fit(self, texts: list[str], langs: list[str], seed: int = 11) -> None:
        rng = np.random.Generator(np.random.PCG64(seed))
        by = {x: [w for t, own in zip(texts, langs, strict=True) if own == x and len(w := lettered(t)) > 1] for x in self.labels}
        usable = [i for i, x in enumerate(self.labels) if by[x]]
        if not usable:
            return
        k = len(self.labels)
        sequences = []
        for _ in range(SEQUENCES):
            words, tags = [], []
            while len(words) < LENGTH:
                y = usable[rng.integers(len(usable))]
                doc = by[self.labels[y]][rng.integers(len(by[self.labels[y]]))]
                size = int(rng.integers(*RUNS))
                at = int(rng.integers(max(1, len(doc) - size)))
                part = doc[at : at + size]
                words += part
                tags += [y] * len(part)
            sequences.append((words[:LENGTH], tags[:LENGTH]))
        vocabulary = sorted({w for s, _ in sequences for w in s})
        number = {w: i for i, w in enumerate(vocabulary)}
        feats, begin = word_features(vocabulary)
        stop = np.append(begin[1:], len(feats))
        x = np.array([[number[w] for w in s] for s, _ in sequences])
        y = np.array([t for _, t in sequences])
        g2, t2 = np.full(self.w.shape, 1e-2, np.float32), np.full(self.trans.shape, 1.0)
        lens = np.full(BATCH, LENGTH)
        for _ in range(EPOCHS):
            order = rng.permutation(len(x))
            for at in range(0, len(x) - BATCH + 1, BATCH):
                rows = order[at : at + BATCH]
                words, place = np.unique(x[rows], return_inverse=True)
                size = stop[words] - begin[words]
                heads = np.cumsum(size) - size
                f = feats[np.repeat(begin[words] - heads, size) + np.arange(size.sum())]
                e = np.add.reduceat(self.w[f], heads, axis=0)[place.reshape(BATCH, LENGTH)].astype(float)
                p, expected, _, _ = marginals(e, lens, self.trans, pairs=True)
                target = np.eye(k)[y[rows]]
                by_word = np.zeros((len(words), k))
                np.add.at(by_word, place.ravel(), (target - p).reshape(-1, k))
                touched, slot = np.unique(f, return_inverse=True)
                grad = np.zeros((len(touched), k))
                spread = np.repeat(by_word, size, axis=0)
                for c in range(k):
                    grad[:, c] = np.bincount(slot, weights=spread[:, c], minlength=len(touched))
                grad = (grad / BATCH - RIDGE * self.w[touched]).astype(np.float32)
                g2[touched] += grad * grad
                self.w[touched] += RATE * grad / np.sqrt(g2[touched])
                seen = np.zeros((k, k))
                np.add.at(seen, (y[rows][:, :-1].ravel(), y[rows][:, 1:].ravel()), 1)
                tg = (seen - expected) / BATCH
                t2 += tg * tg
                self.trans += RATE * tg / np.sqrt(t2)


class Predictor:
    def __init__(self, field: Field):
        self.field = field
        self.memo: dict[bytes, int] = {}
        self.rows = np.zeros((0, len(field.labels)), np.float32)
        self.letters = np.zeros(0, bool)

    def learn(self, fresh: list[bytes]) -> None:
        start = len(self.memo)
        self.memo.update(zip(fresh, range(start, start + len(fresh)), strict=True))
        self.rows = np.concatenate([self.rows[:start], self.field.emissions(fresh)])
        self.letters = np.concatenate([self.letters[:start], [_LETTER.search(w.decode("utf-8", "replace")) is not None for w in fresh]])

    def numbers(self, texts: list[str]) -> list[np.ndarray]:
        """Memo numbers of the lettered words of each text."""
        if len(self.memo) > MEMO:
            self.memo, self.rows, self.letters = {}, self.rows[:0], self.letters[:0]
        cut = [split_words(t) for t in texts]
        if fresh := list(set().union(*cut).difference(self.memo)):
            self.learn(fresh)
        get = self.memo.__getitem__
        out = []
        for words in cut:
            ids = np.fromiter(map(get, words), np.int64, len(words))
            out.append(ids[self.letters[ids]] if len(ids) else ids)
        return out

    def predict(self, texts: list[str]) -> tuple[list[str], list[float]]:
        labels = self.field.labels
        langs, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
        if not labels:
            return langs, scores
        words = self.numbers(texts)
        lens = np.array([len(w) for w in words])
        order = np.argsort(lens, kind="stable")
        order = order[lens[order] > 0]
        at = 0
        while at < len(order):
            # texts of like lengths run in step, so that padding stays small
            to = at + 1
            while to < len(order) and (to - at + 1) * lens[order[to]] <= STEP_WORDS and to - at < 512:
                to += 1
            rows = order[at:to]
            own = lens[rows]
            x = np.zeros((len(rows), int(own.max())), np.int64)
            mask = np.arange(x.shape[1]) < own[:, None]
            x[mask] = np.concatenate([words[i] for i in rows])
            p = marginals(self.rows[x].astype(np.float64), own, self.field.trans)
            mean = (p * mask[:, :, None]).sum(axis=1) / own[:, None]
            best = mean.argmax(axis=1)
            for i, c, s in zip(rows.tolist(), best.tolist(), mean.max(axis=1).tolist(), strict=True):
                langs[i], scores[i] = labels[c], min(1.0, s)
            at = to
        return langs, scores

    def label_words(self, text: str) -> list[tuple[str, str, float]]:
        """Each lettered word of a text with its label and marginal."""
        words = lettered(text)
        if not words or not self.field.labels:
            return []
        p = marginals(self.field.emissions(words)[None].astype(float), np.array([len(words)]), self.field.trans)[0]
        return [(w.decode("utf-8", "replace"), self.field.labels[c], float(v)) for w, c, v in zip(words, p.argmax(axis=1), p.max(axis=1), strict=True)]


def train_field(docs: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", train_docs: int = TRAIN_DOCS) -> Field:
    """Fit on at most train_docs of the documents that ``learn`` picks, as many of each language, by the least hash of the id.

    A hash threshold leaves about twice that many before they are ordered, so what tasks send does not grow with their number;
    what reaches the driver is bounded by train_docs * TEXT_RUNS runs of RUN_WORDS words.
    """
    picked = docs.where(learn & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    totals = {r["lang"]: r["n"] for r in picked.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row a language
    if not totals:
        return Field([])
    share = max(1, train_docs // len(totals))
    limits = docs.sparkSession.createDataFrame([(x, (1 << 40) * min(2 * share, n) // n) for x, n in totals.items()], "lang string, least long")
    near = picked.withColumn("rank", F.pmod(F.xxhash64("id"), F.lit(1 << 40))).join(F.broadcast(limits), "lang").where(F.col("rank") < F.col("least"))  # one row a language
    first = near.withColumn("nth", F.row_number().over(Window.partitionBy("lang").orderBy("rank", "id", "text"))).where(F.col("nth") <= share)

    def job(batches):
        for b in batches:
            for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                runs = text_runs(text)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(runs), pa.string()), pa.array(runs, pa.string())], names=["lang", "run"])

    rows = first.select("lang", "text").mapInArrow(job, "lang string, run string").collect()
    rows = sorted((r["lang"], r["run"]) for r in rows)
    field = Field(sorted(totals))
    field.fit([r[1] for r in rows], [r[0] for r in rows])
    return field


def predict_languages(docs: DataFrame, field: Field, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, lang_pred, score of every whole text."""
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(field)  # BUCKETS weights a label

    def job(batches):
        predictor = Predictor(shared.value)
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            at, size, langs, scores = 0, 0, [], []
            for i, t in enumerate(texts):
                size += len(t)
                if size > 8_000_000 or i + 1 == len(texts):
                    x, y = predictor.predict(texts[at : i + 1])
                    langs += x
                    scores += y
                    at, size = i + 1, 0
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[id_col, "lang_pred", "score"])

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(job, f"`{id_col}` {kind}, lang_pred string, score double")
