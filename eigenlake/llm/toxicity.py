"""Toxicity by weak supervision.

Voters: words and word beginnings that mark toxic rows of a labelled sample (a
lexicon chosen by those labels), and patterns of writing. A generative model,
fitted to the votes alone, estimates how often each voter is right; voters
whose votes go together within a class form one family, which votes once. Its
posterior labels train a logistic regression over words, word beginnings and
patterns, and that scores texts.

Features are taken and counted in the executors. The driver sees counts of the
most telling ones and which rows hold them, so the length of a text does not
matter there.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packed, textnum

#: Bound of the sample that the model is fitted on: labelled rows of each class.
SAMPLE_ROWS = 4000
#: Lengths in bytes of the word beginnings that count as features besides the word.
STEMS = (4, 5, 6, 8)
#: Most lexicon voters, and most features of the classifier.
VOTERS, FEATURES = 400, 800
#: Marked documents that a further lexicon word or feature must find.
LEAST = 2
#: Within a class, voters that correlate above this are one family.
ALIKE = 0.5

_PATTERNS = 5
_U = np.uint64
_LETTER = np.zeros(256, bool)
_LETTER[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100)]] = True


def _features(raw: np.ndarray, off: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(documents, features): each word's hash, then its beginnings', for words of letters and digits."""
    at = 0
    while at < len(off) - 1:
        to = max(at + 1, int(np.searchsorted(off, off[at] + textnum.CHUNK, "right")) - 1)
        part, first = raw[off[at] : off[to]], off[at : to + 1] - off[at]
        w = textnum._words(part, first, True, ~_LETTER)
        doc = np.repeat(np.arange(at, to), w.counts)
        view = textnum.lanes(textnum._LOWER[part])
        yield doc, w.hashes
        for n in STEMS:
            long = np.flatnonzero(w.ends - w.starts > n)
            yield doc[long], textnum.mix(textnum.lane(view, w.starts[long], np.full(len(long), n)) + _U(n) * textnum._MASK[7])
        at = to


def _patterns(raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Patterns of writing by document: shouting, exclamation, symbols, digits, lines."""
    parts = [_patterns_of(raw[off[a] : off[b]], off[a : b + 1] - off[a]) for a, b in _runs(off)]
    return np.concatenate([np.zeros((0, _PATTERNS), bool), *parts])


def _patterns_of(raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    def share(mask: np.ndarray, of: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(mask, dtype=np.int32)])
        return (total[off[1:]] - total[off[:-1]]) / np.maximum(1, of)

    n = np.diff(off)
    upper = (raw >= 0x41) & (raw <= 0x5A)
    letters = upper | ((raw >= 0x61) & (raw <= 0x7A))
    count = np.concatenate([[0], np.cumsum(letters, dtype=np.int32)])
    return np.stack(
        [
            share(upper, count[off[1:]] - count[off[:-1]]) > 0.5,
            share(raw == 0x21, n) > 0.02,
            share(np.isin(raw, [0x23, 0x24, 0x25, 0x26, 0x2A]), n) > 0.05,
            share((raw >= 0x30) & (raw <= 0x39), n) > 0.05,
            share(raw == 0x7C, n) > 0.02,
        ],
        1,
    )


class _Found:
    """Sorted features with a bitmap in front that turns most words away."""

    def __init__(self, features: np.ndarray):
        self.features = np.sort(features)
        self.seen = np.zeros(1 << 16, bool)
        self.seen[self.features >> _U(48)] = True

    def __call__(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places in h that are features, and which."""
        at = np.flatnonzero(self.seen[h >> _U(48)])
        if not len(self.features) or not len(at):
            return at[:0], at[:0]
        k = np.minimum(np.searchsorted(self.features, h[at]), len(self.features) - 1)
        hit = self.features[k] == h[at]
        return at[hit], k[hit]


def _present(found: _Found, raw: np.ndarray, off: np.ndarray) -> Iterator[np.ndarray]:
    """Distinct (document * features + feature) numbers of the features present; no number comes twice."""
    wide = max(1, len(found.features))
    for doc, h in _features(raw, off):
        at, k = found(h)
        yield np.unique(doc[at] * wide + k)


def _presence(found: _Found, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    return np.concatenate([np.zeros(0, np.int64), *_present(found, raw, off)])


class Sample:
    """The labelled rows as features and patterns: a table in the shared folder, its keys and patterns on the driver."""

    def __init__(self, rows: DataFrame):
        self.rows = packed.cut(rows)
        got = self.rows.select("id", "y", "patterns").toArrow().sort_by([("id", "ascending"), ("y", "ascending")])
        self.id, self.y = got.column("id").to_numpy(), got.column("y").to_numpy()
        bits = got.column("patterns").to_numpy()
        self.patterns = (bits[:, None] >> np.arange(_PATTERNS) & 1).astype(np.float32)
        self.place = {key: k for k, key in enumerate(zip(self.id.tolist(), self.y.tolist()))}

    def marked(self, weight: np.ndarray) -> DataFrame:
        """(h, mark): every feature of every row, and whether the row's weight is above a half."""
        marks = [(i, y, int(w > 0.5)) for i, y, w in zip(self.id.tolist(), self.y.tolist(), weight.tolist())]
        marks = self.rows.sparkSession.createDataFrame(marks, "id long, y int, mark int")
        return self.rows.join(F.broadcast(marks), ["id", "y"]).select("mark", F.explode("features").alias("h"))

    def table(self, features: np.ndarray) -> np.ndarray:
        """Rows by features: 1 where present."""
        out = np.zeros((len(self.id), len(features)), np.float32)
        if len(features):
            asked = self.rows.sparkSession.createDataFrame([(int(h), k) for k, h in enumerate(features.view(np.int64))], "h long, k short")
            held = self.rows.select("id", "y", F.explode("features").alias("h")).join(F.broadcast(asked), "h").groupBy("id", "y").agg(F.collect_list("k").alias("k"))
            for i, y, k in (tuple(r) for r in held.collect()):
                out[self.place[i, y], k] = 1
        return out


def _telling(sample: Sample, weight: np.ndarray, most: int, odds: float, cover: int) -> tuple[np.ndarray, np.ndarray]:
    """Features whose share among rows of weight 1 is `odds` times that among the others, and which rows hold them.

    Of the most telling ones those stay that are needed to find each marked
    row `cover` times, picked greedily: features that only repeat what
    others say, or that a few copies of one document share, fall away.
    """
    n, marked = len(weight), int((weight > 0.5).sum())
    counts = sample.marked(weight).groupBy("h").agg(F.sum("mark").alias("df"), F.count(F.lit(1)).alias("n"))
    ratio = (F.col("df") + 0.5) / (marked + 1) / ((F.col("n") - F.col("df") + 0.5) / (n - marked + 1))
    best = counts.where("df >= 3").withColumn("ratio", ratio).where(F.col("ratio") >= odds).orderBy(F.desc(F.col("df") * F.log("ratio")), "h").limit(most)
    features = np.sort(np.array([r["h"] for r in best.collect()], np.int64).view(_U))
    held = sample.table(features)
    left = np.where(weight > 0.5, float(cover), 0.0)
    cost, chosen = held[weight <= 0.5].sum(0), []
    while len(chosen) < held.shape[1]:
        gain = np.minimum(left, 1) @ held - 4 * cost
        gain[chosen] = -1
        best = int(np.argmax(gain))
        if gain[best] < LEAST:
            break
        chosen.append(best)
        left = np.maximum(left - held[:, best], 0)
    chosen.sort()
    return features[chosen], held[:, chosen]


def _families(votes: np.ndarray, post: np.ndarray) -> np.ndarray:
    """Family number of each voter: those whose votes correlate within a class are together."""
    m = votes.shape[1]
    tie = np.eye(m, dtype=bool)
    for weight in (post, 1 - post):
        total = weight.sum()
        if total < 2:
            continue
        centred = (votes - (weight @ votes) / total) * np.sqrt(weight)[:, None]
        cov = centred.T @ centred
        scale = np.sqrt(np.maximum(np.diag(cov), 1e-9))
        tie |= cov / scale[:, None] / scale[None, :] > ALIKE
    label = np.arange(m)
    while True:
        new = np.where(tie, label[None, :], m).min(1)
        if (new == label).all():
            return np.unique(label, return_inverse=True)[1]
        label = new


def label_model(votes: np.ndarray, lexicon: int, rounds: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Posterior of label 1, each family's accuracy, and the family of each voter; no labels are given.

    Expectation maximisation that starts from how many of the `lexicon` last
    voters fire, so that a voter's accuracy is how far others agree with it;
    further rounds feed on themselves and make every voter certain. A voter that fires says label 1 and is right as often as its
    accuracy; one that does not abstains. A family fires if one of its voters
    does. Silence of the whole lexicon is a voter of its own, the last one,
    whose accuracy is learnt alike. To abstain says nothing, so toxic rows of
    many kinds, each with voters of its own, stay one class.
    """
    votes = votes.astype(np.float64)
    spoken = votes[:, votes.shape[1] - lexicon :].sum(1)
    post = np.clip(spoken / 3, 0.02, 0.98)
    family = _families(votes, post)
    fired = np.zeros((len(votes), family.max(initial=-1) + 2))
    for j, f in enumerate(family):
        fired[:, f] = np.maximum(fired[:, f], votes[:, j])
    fired[:, -1] = spoken == 0
    accuracy = np.zeros(fired.shape[1])
    for _ in range(rounds):
        prior = np.clip(post.mean(), 0.01, 0.99)
        accuracy = (post @ fired + prior) / (fired.sum(0) + 1)
        base = np.log(prior / (1 - prior))
        say = np.log(accuracy / (1 - accuracy)) - base
        new = 1 / (1 + np.exp(-np.clip(base + fired @ say, -30, 30)))
        if np.abs(new - post).max(initial=0) < 1e-6:
            break
        post = new
    return post, accuracy, family


def _regression(x: np.ndarray, y: np.ndarray, l2: float = 0.1, rounds: int = 40) -> np.ndarray:
    """Weights (the last is the constant) of a logistic regression on soft labels, by damped Newton steps."""
    x = np.concatenate([x, np.ones((len(x), 1), x.dtype)], 1)
    w = np.zeros(x.shape[1])
    ridge = np.full(x.shape[1], l2)
    ridge[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        weight = np.maximum(p * (1 - p), 1e-6).astype(x.dtype)
        slope = x.T @ (y - p) - ridge * w
        step = np.linalg.solve((x.T @ (x * weight[:, None])).astype(np.float64) + np.diag(ridge), slope)
        w = w + step * min(1.0, 3 / max(1e-12, np.abs(step).max()))
        if np.abs(step).max() < 1e-4:
            break
    return w


def _middle(z: np.ndarray, marked: np.ndarray) -> float:
    """The cut between scores with the fewest on the wrong side; of equals, the middle of the widest gap."""
    order = np.argsort(z, kind="stable")
    z, marked = z[order], marked[order]
    wrong = np.cumsum(marked)[:-1] + np.cumsum((~marked)[::-1])[::-1][1:]
    gap = np.diff(z)
    if not (gap > 0).any():
        return 0.0
    best = wrong == wrong[gap > 0].min()
    k = int(np.argmax(np.where(best, gap, -1)))
    return float((z[k] + z[k + 1]) / 2)


@dataclass
class Model:
    """A fitted linear classifier: sorted features, their weights, pattern weights, constant.

    `fitted` tells whether rows of both classes were there to learn from.
    """

    features: np.ndarray
    weights: np.ndarray
    patterns: np.ndarray
    constant: float
    fitted: bool = True

    def scores(self, raw: np.ndarray, off: np.ndarray, found: _Found) -> np.ndarray:
        n = len(off) - 1
        total = np.full(n, self.constant) + _patterns(raw, off) @ self.patterns
        if len(self.features):
            there = _presence(found, raw, off)
            total += np.bincount(there // len(self.features), self.weights[there % len(self.features)], n)
        return 1 / (1 + np.exp(-np.clip(total, -30, 30)))


def train(sample: Sample) -> Model:
    """Lexicon, label model and classifier from the sample."""
    y = sample.y
    if not len(y) or y.min() == y.max():
        return Model(np.zeros(0, _U), np.zeros(0), np.zeros(_PATTERNS), 8.0 if len(y) and y.max() else -8.0, False)
    _, lexicon = _telling(sample, y.astype(float), VOTERS, 20.0, 3)
    post, *_ = label_model(np.concatenate([sample.patterns, lexicon], 1), lexicon.shape[1])
    if post.min() > 0.5 or post.max() <= 0.5:  # no voter tells the classes apart
        post = y.astype(float)
    features, held = _telling(sample, post, FEATURES, 10.0, 6)
    x = np.concatenate([sample.patterns, held], 1)
    w = _regression(x, post)
    w[-1] -= _middle(x @ w[:-1] + w[-1], post > 0.5)
    return Model(features, w[_PATTERNS:-1], w[:_PATTERNS], float(w[-1]))


def fit(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", rows: int = SAMPLE_ROWS) -> Model:
    """Fit on at most `rows` labelled ids of each class, chosen by a hash of the id; their texts count whole.

    Labels other than 0 and 1 and ids without a document are left out; an id
    with both labels has a row for each, and of the texts under one id the one
    with the smallest hash counts. Columns of labels and documents may clash.
    Without rows of both classes the model gives one score to all and is not
    `fitted`.
    """
    asked = labels.select(F.col(key).alias("id"), F.col(label).cast("int").alias("y")).where("id is not null and y in (0, 1)").distinct()
    chosen = [asked.where(F.col("y") == y).orderBy(F.xxhash64("id"), "id").limit(rows) for y in (0, 1)]
    texts = docs.select(F.col(key).alias("id"), F.col(text).alias("text")).join(F.broadcast(chosen[0].unionByName(chosen[1])), "id")

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        textnum.settle()
        for batch in batches:
            raw, off = textnum.buffers(batch.column(2))
            for k in range(batch.num_rows):
                part, own = raw[off[k] : off[k + 1]], off[k : k + 2] - off[k]
                held = [np.unique(h) for _, h in _features(part, own)]
                held = np.unique(np.concatenate(held)) if held else np.zeros(0, _U)
                bits = int(_patterns(part, own)[0] @ (1 << np.arange(_PATTERNS)))
                yield pa.record_batch([batch.column(0).slice(k, 1), batch.column(1).slice(k, 1), pa.array([bits], pa.int32()), pa.array([held.view(np.int64)], pa.list_(pa.int64()))], names=["id", "y", "patterns", "features"])

    one = texts.select(F.col("id").cast("long").alias("id"), "y", "text").groupBy("id", "y").agg(F.min_by("text", F.xxhash64("text")).alias("text"))
    return train(Sample(one.mapInArrow(features, "id long, y int, patterns int, features array<long>")))


def score(docs: DataFrame, model: Model, key: str = "doc_id", text: str = "text", also: tuple[str, ...] = (), name: str = "toxicity") -> DataFrame:
    """(key, `also` columns, `name`) of every row: 0 to 1, higher if label 1 is likelier.

    Null and empty texts get the score of a text without words. Repeated rows
    score alike. One pass, no shuffle; only the named columns are read.
    """
    names = [key, *also]
    chosen = docs.select(*names) if text in names else docs.select(*names, F.col(text).alias("__text"))
    place = names.index(text) if text in names else len(names)
    schema = docs.select(*names, F.lit(0.0).alias(name)).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        textnum.settle()
        found = _Found(model.features)
        for batch in batches:
            raw, off = textnum.buffers(batch.column(place))
            got = np.concatenate([np.zeros(0), *(model.scores(raw[off[a] : off[b]], off[a : b + 1] - off[a], found) for a, b in _runs(off))])
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(got, pa.float64())], [*names, name])
            del batch, raw, off, got
            textnum.settle()

    return chosen.mapInArrow(run, schema)


def _runs(off: np.ndarray) -> Iterator[tuple[int, int]]:
    at = 0
    while at < len(off) - 1:
        to = max(at + 1, int(np.searchsorted(off, off[at] + (4 << 20), "right")) - 1)
        yield at, to
        at = to
