"""Quality classifier by Bradley-Terry pairwise ranking.

Each document has features of its text alone. Preference pairs (a document labelled good, one labelled bad) are drawn from the
training labels, and a Bradley-Terry model, P(good preferred) = sigmoid(w . (x_good - x_bad)), is fitted by Newton's method on
the logistic loss of feature differences. The model's value of a document is w . x; the threshold is the quantile of the
training documents' values that the share of bad labels sets. Scores are sigmoid(value - threshold + logit(cut)), so a document is
accepted (score >= cut) exactly if its value reaches the quantile.

Training uses at most `max_rows` labelled documents, the least under a hash of their ids: a bounded sample of labels.
Features, scores and decisions cover all documents and whole texts. Labels, language, source and ids are no features.

Edge cases. Null or empty text: features of an empty text. Labels without both classes, or none: weights of zero, and all documents
get the score `cut`, so all are accepted. Several labels of one id: their mean decides (0.5: not used). Rows that repeat an id: one row each. Null ids: held_out is null
for them, and they are not trained on. Empty tables: empty result.
"""

from __future__ import annotations

import operator
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NAMES = ("distinct", "repeat", "upper", "odd_end", "symbol", "bar", "bang", "digit", "short_line", "line_copy", "mean_word", "capital", "stop", "comma", "top_word", "log_words")
_SYMBOLS = "#$%&*@^~<>{}[]\\_=+"


def features(text: str) -> list[float]:
    """Numbers in about [0, 1] that say how a text is written, not what about."""
    words = text.split()
    n = len(words)
    if not n:
        return [0.0] * len(NAMES)
    chars = len(text)
    low = text.lower().split()
    lines = [x for x in text.split("\n") if x.strip()]
    repeat = sum(map(operator.eq, low, low[1:])) / n
    count = text.count
    symbols = sum(map(count, _SYMBOLS))
    counts = Counter(low)
    return [
        min(1.0, len(counts) / n**0.9),
        repeat,
        sum(map(str.isupper, words)) / n,
        sum(1 for w in words if not w[-1].isalnum() and w[-1] not in ".,;:!?\"')") / n,
        min(1.0, 8 * symbols / chars),
        min(1.0, 4 * count("|") / n),
        min(1.0, 2 * count("!") / n),
        min(1.0, 8 * sum(map(count, "0123456789")) / chars),
        sum(1 for x in lines if len(x) < 25) / len(lines),
        1 - len(set(lines)) / len(lines),
        min(1.0, chars / n / 16),
        sum(map(str.istitle, words)) / n,
        min(1.0, 4 * count(". ") / n),
        min(1.0, 4 * count(",") / n),
        max(counts.values()) / n,
        min(1.0, np.log1p(n) / 12),
    ]


def feature_rows(texts: pd.Series) -> np.ndarray:
    x = np.array([features(t or "") for t in texts], np.float64).reshape(len(texts), len(NAMES))
    return np.hstack([x, np.sqrt(np.maximum(x, 0)), x**2])


@dataclass(frozen=True)
class Model:
    weights: tuple[float, ...]
    threshold: float
    cut: float = 0.7

    def score(self, x: np.ndarray) -> np.ndarray:
        z = x @ np.array(self.weights) - self.threshold + np.log(self.cut / (1 - self.cut))
        s = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
        return np.where(z >= np.log(self.cut / (1 - self.cut)), np.maximum(s, self.cut), np.minimum(s, np.nextafter(self.cut, 0)))


def fit(x: np.ndarray, good: np.ndarray, cut: float = 0.7, pairs: int = 60_000, ridge: float = 1e-3, rounds: int = 25, seed: int = 5) -> Model:
    """Bradley-Terry weights and the quantile threshold from feature rows and labels."""
    if not good.any() or good.all():
        return Model((0.0,) * x.shape[1] if x.ndim == 2 else (), 0.0, cut)
    mean, scale = x.mean(0), x.std(0) + 1e-6
    z = (x - mean) / scale
    rng = np.random.default_rng(seed)
    a, b = np.flatnonzero(good), np.flatnonzero(~good)
    n = min(pairs, 20 * max(len(a), len(b)))
    d = z[rng.choice(a, n)] - z[rng.choice(b, n)]
    w = np.zeros(d.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(d @ w, -30, 30)))
        grad = d.T @ (p - 1) / n + ridge * w
        hess = (d * (p * (1 - p))[:, None]).T @ d / n + ridge * np.eye(len(w))
        step = np.linalg.solve(hess, grad)
        w -= step / max(1.0, np.abs(step).max() / 2)
        if np.abs(step).max() < 1e-7:
            break
    weights = w / scale
    value = np.sort(x @ weights)
    k = int((~good).sum())  # the quantile of the share of bad labels; halfway between its two neighbours
    return Model(tuple(weights.tolist()), float((value[k - 1] + value[k]) / 2), cut)


def train(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000, cut: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """Fit on at most max_rows labelled documents outside the held-out quarter."""
    known = labels.select(F.col("doc_id").alias("_id"), F.col("quality").cast("double").alias("q")).where("_id is not null and q is not null")
    known = known.where(~held_out(F.col("_id"))).groupBy("_id").agg(F.avg("q").alias("q")).where("q != 0.5")
    picked = known.orderBy(F.xxhash64("_id"), "_id").limit(max_rows)
    rows = docs.select(F.col(id_col).alias("_doc"), F.col(text_col).alias("_text"))
    joined = rows.join(F.broadcast(picked), rows["_doc"] == F.col("_id"))  # at most max_rows small rows
    width = 3 * len(NAMES)

    def rows_of(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            x = feature_rows(f["_text"])
            yield pd.DataFrame({"id": f["_id"], "q": f["q"], "x": list(x)})

    got = joined.select("_id", "q", "_text").mapInPandas(rows_of, "id long, q double, x array<double>").orderBy("id").toPandas()
    if not len(got):
        return Model((0.0,) * width, 0.0, cut)
    return fit(np.array(got["x"].tolist()), (got["q"] > 0.5).to_numpy(), cut)


def held_out(doc_id):
    return F.crc32(doc_id.cast("string")) % 4 == 2


def scored(docs: DataFrame, model: Model, text_col: str = "text", name: str = "score") -> DataFrame:
    """docs with one more column: the score of each row's text."""

    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            yield pd.Series(model.score(feature_rows(s)) if len(s) else [], dtype="float64")

    from pyspark.sql.pandas.functions import PandasUDFType

    return docs.withColumn(name, F.pandas_udf(score, "double", PandasUDFType.SCALAR_ITER)(F.col(text_col)))


def accepted(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs that the classifier accepts. Columns of docs may have any names."""
    model = train(docs, labels, id_col=id_col, text_col=text_col, **options)
    name = "_score"
    while name in docs.columns:
        name += "_"
    return scored(docs, model, text_col, name).where(F.col(name) >= model.cut).drop(name)
