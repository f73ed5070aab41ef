"""Toxicity by a counterfactually regularised linear classifier.

Besides the logistic loss on labelled texts the fit pays for every change of score
that swapping identity terms causes: for a labelled text that names a group, copies
with each other group's term in its place are made, and the squared differences of
the logits are penalised.  The weights of identity terms are so drawn together and
lose their own pull, which is what makes a neutral mention of a group look toxic.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle

#: The classifier is fitted on at most this many labelled rows, and has at most this many features.
TRAIN_ROWS, MAX_FEATURES, LEAST_ROWS, PREFIX = 10_000, 4096, 3, 6
#: Groups of interchangeable identity terms, in English, German, French and Spanish: fixed values.
IDENTITY_TERMS = [
    ["women", "men"],
    ["woman", "man"],
    ["muslim", "christian", "jewish", "hindu", "buddhist", "atheist"],
    ["muslims", "christians", "jews", "hindus", "buddhists", "atheists"],
    ["black", "white", "asian", "latino", "indigenous"],
    ["gay", "lesbian", "bisexual", "straight", "transgender"],
    ["immigrants", "refugees", "citizens", "tourists"],
    ["deaf", "blind", "disabled", "autistic"],
    ["frauen", "männer"],
    ["frau", "mann"],
    ["muslime", "christen", "juden", "hindus", "buddhisten", "atheisten"],
    ["muslimisch", "christlich", "jüdisch", "hinduistisch", "buddhistisch", "atheistisch"],
    ["schwule", "lesben", "bisexuelle", "heterosexuelle"],
    ["einwanderer", "flüchtlinge", "bürger", "touristen"],
    ["femmes", "hommes"],
    ["femme", "homme"],
    ["musulmans", "chrétiens", "juifs", "hindous", "bouddhistes", "athées"],
    ["musulman", "chrétien", "juif", "hindou", "bouddhiste", "athée"],
    ["homosexuels", "hétérosexuels", "bisexuels"],
    ["immigrés", "réfugiés", "citoyens", "touristes"],
    ["mujeres", "hombres"],
    ["mujer", "hombre"],
    ["musulmanes", "cristianos", "judíos", "hindúes", "budistas", "ateos"],
    ["judío", "cristiano", "hindú", "budista", "ateo"],
    ["homosexuales", "heterosexuales", "bisexuales"],
    ["inmigrantes", "refugiados", "ciudadanos", "turistas"],
]
_WORD = re.compile(r"\w+")


def _flat(terms: list[list[str]]) -> frozenset[str]:
    return frozenset(t.lower() for g in terms for t in g)


_TERMS = _flat(IDENTITY_TERMS)


def features(text: str, terms: frozenset[str] = _TERMS) -> dict[str, float]:
    """Distinct lower-cased words of the whole text, and for each prefix of six
    letters the logarithm of how many distinct longer words have it.  Identity terms
    have no prefixes: a swap changes the terms alone."""
    found = set(_WORD.findall(text.lower()))
    out = dict.fromkeys(found, 1.0)
    heads: dict[str, int] = {}
    for w in found:
        if len(w) > PREFIX and w not in terms:
            heads[w[:PREFIX]] = heads.get(w[:PREFIX], 0) + 1
    for head, n in heads.items():
        out["^" + head] = float(np.log2(1 + n))
    return out


@dataclass
class Classifier:
    names: list[str]
    weights: np.ndarray
    bias: float
    terms: frozenset[str] = _TERMS
    index: dict[str, int] = field(init=False)

    def __post_init__(self):
        self.index = {n: i for i, n in enumerate(self.names)}

    @classmethod
    def fit(cls, names: list[str], rows: list[dict[str, float]], toxic: list[int], terms=IDENTITY_TERMS, swap_penalty: float = 1.0, steps: int = 300) -> Classifier:
        """Nesterov steps on logistic loss + ridge + swap penalty.  The swapped copies
        are pairs of feature differences, one per text, term and replacement."""
        model = cls(names, np.zeros(len(names)), 0.0, _flat(terms))
        if not rows or not names:
            model.bias = -4.0
            return model
        at = model.index
        x = np.zeros((len(rows), len(names)), np.float32)
        for i, row in enumerate(rows):
            for n, v in row.items():
                if n in at:
                    x[i, at[n]] = v
        groups: dict[str, list[str]] = {}
        for g in terms:
            for t in g:  # a word may be in groups of several languages
                groups[t.lower()] = [*groups.get(t.lower(), []), *(x.lower() for x in g)]
        pulls: dict[tuple[int, int], int] = {}
        for row in rows:
            for t in row.keys() & groups.keys():
                for other in groups[t]:
                    if other != t and (t in at or other in at):
                        key = (at.get(t, -1), at.get(other, -1))
                        pulls[key] = pulls.get(key, 0) + 1
        y = np.asarray(toxic, np.float32) * 2 - 1
        pos = max((y > 0).mean(), 1e-6)
        c = np.where(y > 0, min(0.5 / pos, 4.0), 1.0).astype(np.float32)
        c /= c.sum()
        w, b = np.zeros(len(names), np.float32), np.float32(0)
        pw, pb = w, b
        n = np.float32(len(rows))
        # a step of one over a bound of the curvature: of the loss, and of the penalty at its most pulled term
        pull = np.zeros(len(names) + 1)
        for (i, j), k in pulls.items():
            pull[i] += swap_penalty * k / n
            pull[j] += swap_penalty * k / n
        rate = np.float32(1.0 / (0.25 * np.average((x * x).sum(1), weights=c) + 2 * pull.max() + 1e-3))
        for t in range(steps):
            m = np.float32(t / (t + 3))
            vw, vb = w + m * (w - pw), b + m * (b - pb)
            g = -y * c / (1 + np.exp(np.clip(y * (x @ vw + vb), -30, 30)))
            grad = x.T @ g + np.float32(2e-5) * vw
            for (i, j), k in pulls.items():
                d = (vw[i] if i >= 0 else 0) - (vw[j] if j >= 0 else 0)
                for f, sign in ((i, 1), (j, -1)):
                    if f >= 0:
                        grad[f] += np.float32(sign * swap_penalty * k / n) * d
            pw, pb = w, b
            w, b = vw - rate * grad, vb - rate * g.sum()
        model.weights, model.bias = w.astype(float), float(b)
        return model

    def score(self, text: str) -> float:
        at, w = self.index, self.weights
        z = self.bias
        for n, v in features(text, self.terms).items():
            i = at.get(n)
            if i is not None:
                z += w[i] * v
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def held_out() -> Column:
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(5)) == 0


def train(docs: DataFrame, labels: DataFrame, swap_penalty: float = 1.0, terms: list[list[str]] = IDENTITY_TERMS) -> Classifier:
    """Fit on labelled rows that are not held out: the TRAIN_ROWS first in a seeded
    order; of texts that share a doc_id one, by its hash.  The features are the words and prefixes whose share among toxic and
    other rows differs most, by a chi-square count in Spark; the driver gets the
    chosen features of the chosen rows."""
    known = labels.where(F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = known.where(~held_out()).orderBy(F.xxhash64("doc_id", F.lit(5)), "doc_id").limit(TRAIN_ROWS)
    rows = docs.select("doc_id", "text").where("text IS NOT NULL").join(F.broadcast(known), "doc_id")
    rows = rows.groupBy("doc_id", "toxic").agg(F.min(F.struct(F.xxhash64("text").alias("h"), "text")).alias("x"))
    flat = _flat(terms)

    @F.pandas_udf("map<string, double>")
    def extract(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: features(t, flat))

    rows = settle(rows.select("doc_id", "toxic", extract("x.text").alias("f")), "toxicity-features")
    total = rows.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("toxic"), F.lit(0)).alias("t")).first()
    n, t = float(total["n"]), float(total["t"])
    if not n or t in (0.0, n):
        return Classifier.fit([], [], [])
    a, k = F.col("toxic_rows").cast("double"), F.col("rows").cast("double")
    chi = (a * n - k * t) * (a * n - k * t) / (k * F.greatest(n - k, F.lit(1.0)))
    words = rows.select("toxic", F.explode(F.map_keys("f")).alias("name"))
    best = (words.groupBy("name").agg(F.sum("toxic").alias("toxic_rows"), F.count(F.lit(1)).alias("rows"))
                 .where(F.col("rows") >= LEAST_ROWS).orderBy(F.desc(chi), "name").limit(MAX_FEATURES))
    names = sorted({r["name"] for r in best.collect()} | flat)
    few = _narrow(rows, names).toPandas().sort_values("doc_id")
    return Classifier.fit(names, [dict(x) for x in few["f"]], few["toxic"].tolist(), terms, swap_penalty)


def _narrow(rows: DataFrame, names: list[str]) -> DataFrame:
    """The rows with the named features alone."""
    shared = rows.sparkSession.sparkContext.broadcast(frozenset(names))

    @F.pandas_udf("map<string, double>")
    def keep(maps: pd.Series) -> pd.Series:
        return maps.map(lambda f: {k: v for k, v in (f.items() if isinstance(f, dict) else f) if k in shared.value})

    return rows.select("doc_id", "toxic", keep("f").alias("f"))


def score(docs: DataFrame, model: Classifier) -> DataFrame:
    """Adds score (0 to 1; the bias alone for null and empty texts) to ``docs`` (text)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def rate(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            yield pd.Series([shared.value.score(t or "") for t in texts], dtype=float)

    return docs.withColumn("score", rate("text"))


def score_documents(docs: DataFrame, labels: DataFrame, swap_penalty: float = 1.0, terms: list[list[str]] = IDENTITY_TERMS) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, held_out, score, predicted.

    Without usable labels all scores are low.  Repeated rows score alike; long texts
    are read whole."""
    out = score(docs.select("doc_id", "text"), train(docs, labels, swap_penalty, terms))
    return out.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
