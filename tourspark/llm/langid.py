"""Language of a text by words first, with back-off to shorter and shorter character n-grams.

A word that the model knows scores by its log frequency in each language. An unseen word is
covered by its longest known character n-grams: all its n-grams of the longest order that
has any known one, scored by their log frequencies; without one the next shorter order is
tried. A word that even single letters don't cover says nothing.

What a language hasn't got weighs alike in all of them: one floor, half a count of the
largest language's sample. And a small sample's frequencies are drawn down (by ``DRAWN``
counts), so a language of a few words doesn't outbid the others where it has one by chance.

The model is fitted on a bounded sample of labelled rows: about ``sample`` a language, those
with the least hashes, and holds all their words and n-grams; every text is scored whole.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.llm.quality import held_out
from tourspark.llm.rows import Packed, in_one_task, named, text_rows
from tourspark.session import ship

WORD = re.compile(r"[^\W\d_]+")
UNKNOWN = "und"
#: Counts by which a language's total is raised before frequencies are taken.
DRAWN = 500
#: Most bytes of unseen words that a task remembers.
MOST_CACHED = 32 << 20


@dataclass
class Model:
    """``word`` and ``gram`` give the row of ``table``: log frequencies by language."""

    langs: list[str]
    word: dict[str, int]
    gram: dict[str, int]
    table: np.ndarray
    longest: int

    def unseen(self, word: str) -> np.ndarray:
        padded = f" {word} "
        for n in range(min(self.longest, len(padded)), 0, -1):
            own = [g for i in range(len(padded) - n + 1) if (g := self.gram.get(padded[i : i + n] if n > 1 else padded[i])) is not None]
            if own:
                # an unseen word weighs no more than one word
                return self.table[own].mean(axis=0)
        return np.zeros(len(self.langs))

    def predict(self, text: str | None, cache: dict[str, np.ndarray]) -> tuple[str, float]:
        return self.judge(text, cache)[:2]

    def judge(self, text: str | None, cache: dict[str, np.ndarray]) -> tuple[str, float, float]:
        """Language, score, and the share of the text's words that the model knows as words.

        Ties go to the language that is first by name. The score is a share of likelihoods
        over the whole text and so near 1 for any longer text; the share of known words
        doesn't saturate with length. One word more counts as known, so a few unseen words
        alone say little.
        """
        counts = Counter(WORD.findall(text.lower())) if text and self.langs else {}
        rows, times, rest = [], [], np.zeros(len(self.langs))
        get, words = self.word.get, 0
        for w, n in counts.items():
            if (at := get(w)) is not None:
                rows.append(at)
                times.append(n)
                continue
            own = cache.get(w)
            if own is None:
                own = cache[w] = self.unseen(w) if any(map(str.isalpha, w)) else np.full(len(self.langs), np.nan)
            if own[:1] == own[:1]:
                rest += n * own
                words += n
        known = sum(times)
        words += known
        if not words or not self.langs:
            return UNKNOWN, 0.0, 0.0
        total = rest + (np.array(times, float) @ self.table[rows] if rows else 0.0)
        top = int(np.argmax(total))
        return self.langs[top], float(1.0 / np.exp(total - total[top]).sum()), (known + 1) / (words + 1)


def grams_of(word: str, longest: int) -> Iterator[str]:
    """Character n-grams of a word between two spaces, all orders; the space alone isn't one."""
    padded = f" {word} "
    yield from word
    for n in range(2, longest + 1):
        for i in range(len(padded) - n + 1):
            yield padded[i : i + n]


def fit(words: dict[str, Counter], grams: dict[str, Counter] | None = None, longest: int = 4) -> Model:
    """From counts of words by language, and of their n-grams if they were counted before."""
    langs = sorted(words)
    if grams is None:
        grams = {l: Counter() for l in langs}
        for l in langs:
            for w, n in words[l].items():
                for g in grams_of(w, longest):
                    grams[l][g] += n
    table: list[np.ndarray] = []

    def rows_of(sets: dict[str, dict[str, int]]) -> dict[str, int]:
        names = sorted({g for s in sets.values() for g in s})
        total = {l: sum(sets[l].values()) for l in langs}
        floor = 0.5 / (max(total.values(), default=0) + DRAWN)
        share = np.array([[sets[l].get(g, 0) / (total[l] + DRAWN) for l in langs] for g in names]).reshape(-1, len(langs))
        first = sum(map(len, table))
        table.append(np.log(np.maximum(share, floor)))
        return {g: first + i for i, g in enumerate(names)}

    word = rows_of({l: {w: n for w, n in words[l].items() if any(map(str.isalpha, w))} for l in langs})
    gram: dict[str, int] = {}
    for n in range(1, longest + 1):
        gram |= rows_of({l: {g: k for g, k in grams[l].items() if len(g) == n} for l in langs})
    return Model(langs, word, gram, np.concatenate(table), longest)


def _counts(docs: DataFrame, id_col: str, text: str, lang: str, sample: int, longest: int) -> tuple[list[str], DataFrame | None]:
    """The languages, and (l, gram, w, n): counts of the sample's words and n-grams."""
    labelled = docs.where(F.col(lang).isNotNull() & F.col(id_col).isNotNull() & ~held_out(F.col(id_col), 4, 2)).select(F.col(id_col).alias("id"), F.col(text).alias("t"), F.col(lang).cast("string").alias("l"))
    sizes = {r["l"]: r["count"] for r in labelled.groupBy("l").count().collect()}  # a row a language
    if not sizes:
        return [], None
    share = F.create_map(*[F.lit(x) for l, n in sizes.items() for x in (l, min(1.0, sample / n))])
    place = F.pmod(F.xxhash64("id"), F.lit(1 << 30)) / F.lit(float(1 << 30))

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            own: dict[str, Counter] = {}
            for l, t in zip(rows["l"], rows["t"], strict=True):
                own.setdefault(l, Counter()).update(WORD.findall(t.lower()) if t else ())
            for l, c in own.items():
                parts: Counter = Counter()
                for w, n in c.items():
                    for g in grams_of(w, longest):
                        parts[g] += n
                for gram, found in ((False, c), (True, parts)):
                    yield pd.DataFrame({"l": l, "gram": gram, "w": list(found), "n": list(found.values())}, columns=["l", "gram", "w", "n"]).astype({"n": "int64", "gram": "bool"})

    ship(docs.sparkSession)
    chosen = labelled.where(place < share[F.col("l")])
    return list(sizes), chosen.mapInPandas(count, "l string, gram boolean, w string, n long").groupBy("l", "gram", "w").agg(F.sum("n").alias("n"))


def _fitted(langs: list[str], rows: Iterable[tuple], longest: int) -> Model:
    """The model of rows (l, gram, w, n)."""
    words, grams = ({l: Counter() for l in langs} for _ in range(2))
    for l, gram, w, n in rows:
        (grams if gram else words)[l][w] = n
    return fit(words, grams, longest)


def _none() -> Model:
    return Model([], {}, {}, np.zeros((0, 0)), 1)


def train(docs: DataFrame, id_col: str = "doc_id", text: str = "text", lang: str = "lang", sample: int = 1500, longest: int = 4) -> Model:
    """Fit on rows with a language and an id that are not held out.

    Of each language about ``sample`` rows, those below a threshold of the hash of their id,
    are counted where they lie; the counts of all their words and n-grams come to the driver,
    so the sample alone bounds the model. Nothing of the sample is left out.
    """
    langs, counted = _counts(docs, id_col, text, lang, sample, longest)
    if counted is None:
        return _none()
    found = counted.toArrow()
    return _fitted(langs, zip(*(found[c].to_pylist() for c in ("l", "gram", "w", "n")), strict=True), longest)


def train_away(docs: DataFrame, id_col: str = "doc_id", text: str = "text", lang: str = "lang", sample: int = 1500, longest: int = 4) -> Packed | Model:
    """The same model for ``identify`` and ``keep_known``, fitted in a task: the counts don't
    come to the driver, which would keep their memory."""
    langs, counted = _counts(docs, id_col, text, lang, sample, longest)
    if counted is None:
        return _none()
    made = in_one_task(counted.repartition(1), lambda found: _fitted(langs, zip(*(found[c] for c in ("l", "gram", "w", "n")), strict=True), longest))
    return made or _fitted(langs, [], longest)


def _predict(batches: Iterator[pd.DataFrame], model: Model) -> Iterator[pd.DataFrame]:
    cache: dict[str, np.ndarray] = {}
    for rows in batches:
        made = [model.predict(t, cache) for t in rows["t"]]
        if sum(map(len, cache)) + 200 * len(cache) > MOST_CACHED:
            cache.clear()
        rows = rows.drop(columns="t")
        rows["lang_pred"], rows["score"] = [m[0] for m in made], np.array([m[1] for m in made], float)
        yield rows


def identify(docs: DataFrame, model: Model, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, held_out, lang_pred, score) of every row: null texts and texts without a letter
    are ``und`` with score 0. Texts are read whole, however long. Repeated rows come back
    repeated, an empty table empty; other columns are ignored."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the sample
    rows = text_rows(docs, id_col, text, held_out(F.col(id_col), 4, 2).alias("held_out"))
    made = rows.mapInPandas(lambda b: _predict(b, shared.value), "id string, held_out boolean, lang_pred string, score double")
    return named(made, docs, id_col)


def keep_known(docs: DataFrame, model: Model, text: str = "text", least: float = 0.5, known: float = 0.05) -> DataFrame:
    """The rows of ``docs`` with a language found at a score of ``least`` or more, and with a
    share of at least ``known`` of their words known to the model.

    Null texts and texts without a letter go; repeated rows are judged alike; an empty table
    stays empty, and with a model of no language every row goes.
    """
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("boolean")
    def stays(texts: pd.Series) -> pd.Series:
        cache: dict[str, np.ndarray] = {}
        made = [shared.value.judge(t, cache) for t in texts]
        return pd.Series([l != UNKNOWN and s >= least and k >= known for l, s, k in made], dtype=bool)

    return docs.where(stays(F.col(text)))
