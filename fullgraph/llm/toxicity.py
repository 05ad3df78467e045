"""Toxicity by a classifier chain of logistic models.

The chain predicts categories in a fixed order.  A link's features are selected
words (present or not) and word beginnings (how much of the text they make up,
full at one word in ``1 / FULL``), plus the probabilities of the earlier
categories; while a link is fitted those probabilities are out-of-fold
predictions, so it sees the kind of input it will meet in use.

Categories: the features that set toxic from clean training texts apart are
split by how they are used there into ``CATEGORIES - 1`` weak categories (a
feature goes to the category whose features it shares most toxic texts with);
the last category is the label ``toxic`` itself and gives the verdict.

Fitting uses a bounded sample: of the labelled documents those with the smallest
hashes, about ``MAX_TRAIN``; only the words of the sample reach the driver, not
its texts.  The fitted chain is a dictionary of at most ``MAX_WORDS`` words and a
few weights each; it is broadcast, and every whole text is scored with it.

Defined results: null or empty text has no words and the base rate's
probabilities; without both classes among the labels nothing is toxic;
repeated rows are scored row by row; repeated labels of one document count as
toxic when one of them says so; extra columns pass unread; an empty table gives
an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import ship, slices, spread, unit_hash

MAX_TRAIN = 8_000
MAX_WORDS = 256
MIN_TEXTS = 3
CATEGORIES = ("weak_a", "weak_b", "toxic")
FOLDS = 5
_WORD = re.compile(r"[^\W\d_]+")


FULL = 40
STEMS = (5, 6, 7)


def parts_of(word: str) -> tuple[str, ...]:
    """The features a word can give: itself and its beginnings (marked ``*``)."""
    return (word, *(word[:k] + "*" for k in STEMS if len(word) > k))


def features(text: str | None, table: dict[str, tuple[str, ...]] | None = None) -> dict[str, float]:
    """Feature to value in (0, 1]; ``table`` maps a word to the features to look at (default: all)."""
    words = _WORD.findall((text or "").lower())
    if table is None:
        hits = Counter(f for w in words for f in parts_of(w))
    else:
        hits = Counter(f for w in words for f in table[w])
    n = max(len(words), FULL // 2)
    return {f: min(1.0, c * FULL / n) if f[-1] == "*" else 1.0 for f, c in hits.items()}


class Chosen(dict):
    """Word to its chosen features; emptied when it outgrows its bound."""

    def __init__(self, chosen: set[str]):
        super().__init__()
        self.chosen = chosen

    def __missing__(self, word: str) -> tuple[str, ...]:
        if len(self) > 300_000:
            self.clear()
        found = tuple(f for f in parts_of(word) if f in self.chosen)
        self[word] = found
        return found


@dataclass
class Chain:
    """Features and, per category, weights over (features, earlier probabilities, 1)."""

    categories: tuple[str, ...]
    words: list[str] = field(default_factory=list)
    weights: list[np.ndarray] = field(default_factory=list)
    threshold: float = 0.5

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        """One column per category."""
        p = np.zeros((len(x), len(self.categories)))
        for k, w in enumerate(self.weights):
            p[:, k] = _sigmoid(np.hstack([x, p[:, :k]]) @ w[:-1] + w[-1])
        return p


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 25) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the last weight is the constant."""
    x = np.hstack([x, np.ones((len(x), 1))])
    penalty = np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = _sigmoid(x @ w)
        step = np.linalg.solve((x.T * (p * (1 - p) + 1e-9)) @ x + np.diag(penalty), x.T @ (y - p) - penalty * w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return w


def fit_chain(rows: list[dict[str, float]], toxic: np.ndarray, keys: list | None = None, folds: int = FOLDS) -> Chain:
    """Fit on feature values and 0/1 labels; rows of one key (default: equal rows) count once."""
    seen: dict = {}
    for i, r in enumerate(rows):
        seen.setdefault(keys[i] if keys else tuple(sorted(r.items())), i)
    use = sorted(seen.values())
    rows, toxic = [rows[i] for i in use], np.asarray(toxic, dtype=float)[use]
    n_toxic = int(toxic.sum())
    if not n_toxic or n_toxic == len(toxic):
        return Chain(CATEGORIES, [], [np.array([0.0] * k + [-40.0]) for k in range(len(CATEGORIES))])
    with_t, with_c = Counter(), Counter()
    for r, t in zip(rows, toxic):
        (with_t if t else with_c).update([f for f, v in r.items() if v >= 0.5])
    n_clean = len(toxic) - n_toxic
    # G statistic of feature against label, for features that stand out in toxic texts
    gain = {}
    for w, a in with_t.items():
        b = with_c.get(w, 0)
        if a >= MIN_TEXTS and a / n_toxic > 3 * (b + 0.5) / n_clean:
            e = (a + b) * n_toxic / len(toxic)
            gain[w] = a * np.log(a / e) + (b * np.log(b / (a + b - e)) if b else 0)
    words = sorted(sorted(gain, key=lambda w: (-gain[w], w))[:MAX_WORDS])
    place = {w: i for i, w in enumerate(words)}
    x = np.zeros((len(rows), len(words)))
    for i, r in enumerate(rows):
        for w, v in r.items():
            if w in place:
                x[i, place[w]] = v
    labels = _categories(x, toxic, [gain[w] for w in words])
    fold = np.arange(len(toxic)) % folds
    chain = Chain(CATEGORIES, words)
    earlier = np.zeros((len(toxic), 0))
    for y in labels:
        inputs = np.hstack([x, earlier])
        out = np.zeros(len(toxic))
        for f in range(folds):
            w = fit_logistic(inputs[fold != f], y[fold != f])
            out[fold == f] = _sigmoid(inputs[fold == f] @ w[:-1] + w[-1])
        chain.weights.append(fit_logistic(inputs, y))
        earlier = np.hstack([earlier, out[:, None]])
    return chain


def _categories(x: np.ndarray, toxic: np.ndarray, gain: list[float]) -> list[np.ndarray]:
    """Weak labels of the early categories, then the label itself."""
    weak = len(CATEGORIES) - 1
    together = x[toxic > 0].T @ x[toxic > 0]
    order = np.argsort(-np.asarray(gain), kind="stable")
    groups: list[list[int]] = [[int(i)] for i in order[:weak]]
    for i in order[weak : 8 * weak]:
        best = min(range(len(groups)), key=lambda g: (len(groups[g]) > 4, -together[i, groups[g]].mean(), g))
        groups[best].append(int(i))
    out = [np.where(x[:, g].max(axis=1) >= 0.5, toxic, 0.0) if g else np.zeros(len(toxic)) for g in groups]
    return out + [np.zeros(len(toxic))] * (weak - len(groups)) + [toxic]


def train(spark: SparkSession, docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN) -> Chain:
    ship(spark)
    marks = labels.filter("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    total = marks.count()
    share = min(1.0, max_train / max(1, total))
    chosen = marks.filter(unit_hash(F.col("doc_id"), 10) < share).withColumnRenamed("doc_id", "label_id")
    sample = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text")).join(chosen, F.col("doc_id") == F.col("label_id")).select("doc_id", "text", "toxic")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", 1 << 20):
            rows = [sorted(f for f, v in features(t).items() if v >= 0.5) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.string())), batch.column(2)], names=["doc_id", "found", "toxic"])

    found = sample.mapInArrow(count, "doc_id long, found array<string>, toxic int")
    common = found.select(F.explode("found").alias("feature"), "toxic").groupBy("feature").agg(F.sum("toxic").alias("t"), F.count(F.lit(1)).alias("n"))
    # A feature can only be chosen if enough toxic texts hold it and they are a fair part of its texts.
    wanted = common.filter((F.col("t") >= MIN_TEXTS) & (F.col("t") * 5 >= F.col("n"))).orderBy(F.desc(F.col("t") * F.col("t") / F.col("n")), "feature").limit(4 * MAX_WORDS)
    shared = spark.sparkContext.broadcast({r.feature for r in wanted.collect()})

    def slim(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = Chosen(shared.value)
        for batch in slices(batches, "text", 1 << 20):
            texts = batch.column(1).to_pylist()
            rows = [features(t, table) for t in texts]
            keys = [hashlib.blake2b((t or "").encode("utf-8", "surrogatepass"), digest_size=8).digest() for t in texts]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([list(r) for r in rows], pa.list_(pa.string())), pa.array([list(r.values()) for r in rows], pa.list_(pa.float64())), batch.column(2), pa.array(keys, pa.binary())],
                names=["doc_id", "found", "value", "toxic", "key"],
            )

    schema = "doc_id long, found array<string>, value array<double>, toxic int, key binary"
    rows = [(r.doc_id, bytes(r.key), dict(zip(r.found, r.value)), r.toxic) for r in sample.mapInArrow(slim, schema).collect()]  # about max_train short rows
    rows.sort(key=lambda r: r[:2])
    return fit_chain([r[2] for r in rows], np.array([r[3] for r in rows], dtype=float), [r[1] for r in rows])


def score(spark: SparkSession, docs: DataFrame, chain: Chain, passed: list[str] | None = None) -> DataFrame:
    """doc_id, one probability per category, is_toxic; ``passed`` columns are carried along."""
    ship(spark)
    shared = spark.sparkContext.broadcast(chain)
    names = [f"p_{c}" for c in chain.categories]
    carried = passed or []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        place = {w: i for i, w in enumerate(model.words)}
        table = Chosen(set(place))
        for batch in slices(batches, "text", 1 << 20):
            at = batch.schema.get_field_index("text")
            texts = batch.column(at).to_pylist()
            x = np.zeros((len(texts), len(place)))
            for i, t in enumerate(texts):
                for w, v in features(t, table).items():
                    x[i, place[w]] = v
            p = model.probabilities(x)
            rest = [i for i in range(batch.num_columns) if i != at or "text" in carried]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in rest), *(pa.array(p[:, k]) for k in range(p.shape[1])), pa.array(p[:, -1] >= model.threshold)], names=[*(batch.schema.names[i] for i in rest), *names, "is_toxic"])

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"), *[docs[c] for c in carried if c != "text"])
    fields = ["doc_id long", *["text string"] * ("text" in carried), *[f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in carried if c != "text"], *[f"{n} double" for n in names], "is_toxic boolean"]
    return spread(rows).mapInArrow(run, ", ".join(fields))


def classify(spark: SparkSession, docs: DataFrame, labels: DataFrame) -> DataFrame:
    return score(spark, docs, train(spark, docs, labels))


def keep_clean(spark: SparkSession, docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that the chain does not reject, all columns."""
    chain = train(spark, docs, labels)
    # columns travel under names of their own, so none can clash with a result's
    own = {c: c if c in ("doc_id", "text") else f"_c{i}" for i, c in enumerate(docs.columns)}
    flat = docs.select(*[docs[c].alias(n) for c, n in own.items()])
    kept = score(spark, flat, chain, [n for n in own.values() if n != "doc_id"]).filter("not is_toxic")
    return kept.select(*[F.col(n).cast(docs.schema[c].dataType).alias(c) for c, n in own.items()])
