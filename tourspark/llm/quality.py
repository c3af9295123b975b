"""Quality scores by Naive Bayes support vectors.

A text becomes the set of its n-grams: words and marks (1 and 2 in a row), and the shapes of
words and marks (1 to 3 in a row). Each n-gram's indicator is scaled by its log-count ratio
between the classes, and a linear model with hinge loss (squared as an option) is fitted to
the scaled indicators by dual coordinate descent. The weights are then drawn towards their
mean magnitude, as the method proposes, and a logistic curve through the training margins
makes a score of 0 to 1.

The fit uses at most ``sample`` labelled rows, those first in hash order, and of them as many
as ``sample_chars`` allows; n-grams are those of the sample that at least two of its texts
have. Every text is scored whole.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tourspark.llm.rows import Packed, in_one_task, named, text_rows
from tourspark.session import ship

#: Most bytes of words whose shapes a task remembers.
MOST_CACHED = 64 << 20
TOKEN = re.compile(r"\w+|\n+|[^\w\s]+")


def shape(token: str) -> str:
    """A word's case, or digits, or the marks of a run, each once."""
    if token.isalpha():
        return "x" if token.islower() else "X" if token.isupper() and len(token) > 1 else "T" if token[0].isupper() else "m"
    return "9" if token.isdigit() else "/" if token[0] == "\n" else "".join(dict.fromkeys(token))


def grams(text: str | None, shapes: dict[str, str]) -> list[set]:
    """The n-grams of a whole text, each once, by kind: words, pairs of words, and the shapes
    of one, two and three in a row. ``shapes`` is a cache for the caller to keep."""
    if not text:
        return [set() for _ in range(5)]
    tokens = TOKEN.findall(text)
    words = set(tokens)
    for t in words:
        if t not in shapes:
            shapes[t] = shape(t)
    form = list(map(shapes.__getitem__, tokens))
    return [words, set(zip(tokens, tokens[1:], strict=False)), {(f,) for f in set(form)}, set(zip(form, form[1:], strict=False)), set(zip(form, form[1:], form[2:], strict=False))]


def _code(kind: int, gram) -> int:
    return xxhash.xxh64_intdigest(gram if kind == 0 else "\t".join(gram), kind)


@dataclass
class Model:
    """Weights of the n-grams by kind, and the logistic curve over their sum."""

    weights: list[dict]
    bias: float
    slope: float
    shift: float

    def score(self, text: str | None, shapes: dict[str, str]) -> float:
        # exact sums: sets differ in order from process to process
        margin = self.bias + math.fsum(math.fsum([w[x] for x in g if x in w]) for g, w in zip(grams(text, shapes), self.weights, strict=True))
        return 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, self.slope * margin + self.shift))))


def fit(texts: list[str | None], labels: list[int], least: int = 2, smooth: float = 1.0, c: float = 0.1, blend: float = 0.25, rounds: int = 30, seed: int = 11, loss: str = "hinge") -> Model:
    """Fit on texts and labels of 0 or 1. With one class or none the score is constant."""
    y = np.where(np.array(labels, int) == 1, 1.0, -1.0)
    pos, neg = int((y > 0).sum()), int((y < 0).sum())
    if not pos or not neg:
        return Model([{} for _ in range(5)], 0.0, 0.0, 2.0 if pos else -2.0 if neg else 0.0)
    shapes: dict[str, str] = {}
    # n-grams as digests first, so that those of one text only never stay in memory
    coded = [np.fromiter((_code(k, g) for k, kind in enumerate(grams(t, shapes)) for g in kind), np.uint64) for t in texts]
    found, seen = np.unique(np.concatenate(coded), return_counts=True)
    found = found[seen >= least]
    rows = []
    for own in coded:
        at = np.minimum(np.searchsorted(found, own), max(0, len(found) - 1))
        rows.append(np.sort(at[found[at] == own]) if len(found) else at[:0])
    del coded
    index = range(len(found))
    p = np.full(len(index), smooth)
    q = np.full(len(index), smooth)
    for r, t in zip(rows, y, strict=True):
        (p if t > 0 else q)[r] += 1
    ratio = np.log(p / (pos + 2 * smooth)) - np.log(q / (neg + 2 * smooth))
    # Dual coordinate descent; the classes weigh alike. The dual variables of plain hinge loss
    # lie between 0 and a row's cost; those of squared hinge have a ridge instead of that top.
    if loss not in ("hinge", "squared"):
        raise ValueError(f"unknown loss {loss}")
    cost = np.where(y > 0, c * len(y) / (2 * pos), c * len(y) / (2 * neg))
    ridge, ceiling = (1.0 / (2 * cost), np.full(len(y), np.inf)) if loss == "squared" else (np.zeros(len(y)), cost)
    w, bias, alpha = np.zeros(len(index)), 0.0, np.zeros(len(y))
    own = [ratio[r] for r in rows]
    norm = np.array([float(x @ x) for x in own]) + 1.0 + ridge
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        most = 0.0
        for i in rng.permutation(len(y)):
            slope = y[i] * (float(w[rows[i]] @ own[i]) + bias) - 1.0 + alpha[i] * ridge[i]
            step = min(max(alpha[i] - slope / norm[i], 0.0), ceiling[i]) - alpha[i]
            if step == 0.0:
                continue
            most = max(most, abs(slope))
            alpha[i] += step
            w[rows[i]] += step * y[i] * own[i]
            bias += step * y[i]
        if most < 1e-3:
            break
    w = blend * np.abs(w).mean() + (1 - blend) * w if blend and len(w) else w
    scaled = ratio * w
    margin = np.array([float(scaled[r].sum()) for r in rows]) + bias
    slope, shift = _logistic(margin, y)
    weights: list[dict] = [{} for _ in range(5)]
    at = {int(h): float(s) for h, s in zip(found, scaled, strict=True) if abs(s) > 1e-9}
    for t in texts:
        for k, kind in enumerate(grams(t, shapes)):
            for g in kind:
                if g not in weights[k] and (s := at.get(_code(k, g))) is not None:
                    weights[k][g] = s
    return Model(weights, float(bias), slope, shift)


def _logistic(margin: np.ndarray, y: np.ndarray, rounds: int = 100) -> tuple[float, float]:
    """A rising logistic curve through margins, with targets short of 0 and 1 and both
    classes weighed alike, so that 0.5 lies between them; Newton steps."""
    pos, neg = (y > 0).sum(), (y < 0).sum()
    target = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    mass = np.where(y > 0, 0.5 / pos, 0.5 / neg)
    middle, spread = float(np.average(margin, weights=mass)), float(margin.std()) or 1.0
    x = (margin - middle) / spread
    a, b = 1.0, 0.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a * x + b, -30, 30)))
        g, h = mass * (p - target), mass * p * (1 - p)
        ga, gb = float(g @ x) + 1e-3 * a, float(g.sum())
        haa, hab, hbb = float(h @ (x * x)) + 1e-3, float(h @ x), float(h.sum()) + 1e-9
        det = haa * hbb - hab * hab
        if det <= 1e-18:
            break
        da, db = (hbb * ga - hab * gb) / det, (haa * gb - hab * ga) / det
        a, b = max(1e-3, a - da), b - db
        if abs(da) + abs(db) < 1e-9:
            break
    return a / spread, b - a * middle / spread


def held_out(doc_id: Column, parts: int, part: int) -> Column:
    """Whether a row's id keeps it out of any fit."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(parts)) == part, F.lit(False))


def _sample(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "quality", sample: int = 5000, sample_chars: int = 50_000_000) -> DataFrame:
    """(id, y, t): the rows that ``train`` fits on, in one partition."""
    wanted = (
        labels.where(F.col(label).isin(0, 1) & F.col(id_col).isNotNull() & ~held_out(F.col(id_col), 3, 1))
        .select(F.col(id_col).alias("id"), F.col(label).cast("int").alias("y"))
    )
    # at most `sample` rows: its size is bounded by that parameter
    chosen = F.broadcast(wanted.orderBy(F.xxhash64("id"), "id", "y").limit(sample))
    place = ["h", "id", "y", "t"]
    rows = docs.select(F.col(id_col).alias("id"), F.col(text).alias("t")).join(chosen, "id").withColumn("h", F.xxhash64("id")).orderBy(*place).limit(sample)
    # one window over these few rows, for the sum of their lengths
    before = Window.partitionBy(F.lit(0)).orderBy(*place).rowsBetween(Window.unboundedPreceding, -1)
    return rows.withColumn("before", F.coalesce(F.sum(F.coalesce(F.length("t"), F.lit(0))).over(before), F.lit(0))).where(F.col("before") < sample_chars).select("id", "y", "t")


def train(docs: DataFrame, labels: DataFrame, **options) -> Model:
    """Fit on the ``sample`` labelled rows first in hash order of their ids that are not held
    out, or on those of them that begin within the first ``sample_chars`` characters.

    Null labels and ids are left out. An id that is repeated on either side gives that many
    rows, which count towards both bounds, so they bound what comes to the driver. With an
    empty table the score is constant.
    """
    bounds = {k: options.pop(k) for k in ("id_col", "text", "label", "sample", "sample_chars") if k in options}
    found = _sample(docs, labels, **bounds).orderBy("id", "y", "t").select("t", "y").collect()
    return fit([r["t"] for r in found], [r["y"] for r in found], **options)


def train_away(docs: DataFrame, labels: DataFrame, **bounds) -> Packed | Model:
    """The same model for ``score`` and ``keep_good``, fitted in a task: the driver gets neither
    the sample's texts nor the n-grams as objects, whose memory it would keep."""
    ship(docs.sparkSession)
    rows = _sample(docs, labels, **bounds).coalesce(1).sortWithinPartitions("id", "y", "t").select("t", "y")
    return in_one_task(rows, lambda found: fit(found["t"].tolist(), found["y"].tolist())) or fit([], [])


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, held_out, score, predicted) of every row; null and empty texts get the score of
    no n-grams. Texts are read whole, however long; equal texts score alike. Repeated rows
    come back repeated, an empty table empty; other columns are ignored."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the sample
    rows_in = text_rows(docs, id_col, text, held_out(F.col(id_col), 3, 1).alias("held_out"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own, shapes = shared.value, {}
        for rows in batches:
            made = np.array([own.score(t, shapes) for t in rows["t"]], float)
            if sum(map(len, shapes)) + 120 * len(shapes) > MOST_CACHED:
                shapes.clear()
            rows = rows.drop(columns="t")
            rows["score"], rows["predicted"] = made, (made >= 0.5).astype(int)
            yield rows

    return named(rows_in.mapInPandas(run, "id string, held_out boolean, score double, predicted int"), docs, id_col)


def keep_good(docs: DataFrame, model: Model, text: str = "text", least: float = 0.5) -> DataFrame:
    """The rows of ``docs`` whose score is ``least`` or more, with their columns.

    A null text is judged like an empty one; repeated rows are judged alike and all stay or
    all go; an empty table stays empty.
    """
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def of(texts: pd.Series) -> pd.Series:
        shapes: dict[str, str] = {}
        return pd.Series([shared.value.score(t, shapes) for t in texts], dtype=float)

    return docs.where(of(F.col(text)) >= least)
