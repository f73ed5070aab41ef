"""Language identification by error-correcting output codes.

Each language has a codeword; each bit of the code has one binary classifier over
byte n-grams.  A text's margins on all bits are decoded to the language whose
codeword has the least weighted loss, each classifier weighing in by how well it
separates that language; a small gap to the runner-up flags ambiguity.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import settle, unit

#: The classifiers are fitted on at most this many rows of each language, and in all on so many, shared evenly, but one of each.
TRAIN_ROWS, TRAIN_TOTAL = 700, 44_800
BITS_OF_HASH = 12
DIM = 1 << BITS_OF_HASH
UNDEFINED = "und"
_LETTER = re.compile(r"[^\W\d_]")
_PLAIN = bytes(b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
_GROUP_BYTES = 1 << 21
#: A label is overruled from this score on.
CONFIDENT = 0.9


def histograms(texts: list[str]) -> np.ndarray:
    """One row per text: hashed counts of the byte bi- and trigrams of the whole
    lower-cased text, square-rooted and scaled to length one."""
    data = [b" " + re.sub(rb" +", b" ", t.lower().encode("utf-8", "replace").translate(_PLAIN)) + b" " for t in texts]
    out = np.zeros((len(texts), DIM), np.float32)
    lo = 0
    while lo < len(data):
        hi, size = lo, 0
        while hi < len(data) and (hi == lo or size + len(data[hi]) <= _GROUP_BYTES):
            size += len(data[hi])
            hi += 1
        b = np.frombuffer(b"".join(data[lo:hi]), np.uint8).astype(np.uint32)
        row = np.repeat(np.arange(hi - lo, dtype=np.int64), [len(x) for x in data[lo:hi]])
        counts = np.zeros((hi - lo) * DIM)
        for n in (2, 3):
            k = len(b) - n + 1
            if k <= 0:
                continue
            code = b[:k].copy()
            for i in range(1, n):
                code = code * np.uint32(257) + b[i: k + i]
            code = (code * np.uint32(2654435761) + np.uint32(n * 40503)) >> np.uint32(32 - BITS_OF_HASH)
            own = row[:k] == row[n - 1: k + n - 1]
            counts += np.bincount((row[:k] * DIM + code)[own], minlength=len(counts))
        out[lo:hi] = np.sqrt(counts).reshape(hi - lo, DIM)
        lo = hi
    return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)


def codewords(k: int, seed: int = 11) -> np.ndarray:
    """+1/-1 codewords of ``k`` languages: all splits for few, else seeded random columns."""
    if k == 1:
        return np.ones((1, 1))
    if k <= 5:
        bits = [[1 if i == 0 or not (c >> (i - 1)) & 1 else -1 for i in range(k)] for c in range(1, 1 << (k - 1))]
    else:
        rng, bits = np.random.default_rng(seed), []
        while len(bits) < int(np.ceil(8 * np.log2(k))):
            column = rng.permutation(np.arange(k) % 2 * 2 - 1)
            bits.append(list(column))
    return np.array(bits, float).T


@dataclass
class Codes:
    languages: list[str]
    code: np.ndarray  # languages x bits
    trust: np.ndarray  # languages x bits, rows sum to 1
    weights: np.ndarray  # DIM x bits
    bias: np.ndarray
    #: Texts with a higher loss than this are in no learned language.
    cutoff: float = np.inf

    @classmethod
    def fit(cls, texts: list[str], langs: list[str], steps: int = 150) -> Codes:
        """From texts, see ``fit_histograms``."""
        return cls.fit_histograms(histograms(texts), langs, steps)

    @classmethod
    def fit_histograms(cls, x: np.ndarray, langs: list[str], steps: int = 150) -> Codes:
        """Logistic regression for every bit at once (Nesterov steps, ridge)."""
        names = sorted(set(langs))
        if not names:
            return cls([], np.zeros((0, 1)), np.zeros((0, 1)), np.zeros((DIM, 1), np.float32), np.zeros(1, np.float32))
        code = codewords(len(names))
        place = {v: i for i, v in enumerate(names)}
        own = np.array([place[v] for v in langs])
        y = code[own].astype(np.float32)
        share = 1.0 / np.maximum(np.bincount(own, minlength=len(names)), 1)
        weigh = (share[own] / len(names)).astype(np.float32)[:, None]
        w, b = np.zeros((DIM, code.shape[1]), np.float32), np.zeros(code.shape[1], np.float32)
        pw, pb = w, b
        for t in range(steps):
            m = np.float32(t / (t + 3))
            vw, vb = w + m * (w - pw), b + m * (b - pb)
            g = -y * weigh / (1 + np.exp(np.clip(y * (x @ vw + vb), -30, 30)))
            pw, pb = w, b
            w, b = vw - np.float32(6) * (x.T @ g + np.float32(1e-5) * vw), vb - np.float32(6) * g.sum(0)
        margin = x @ w + b
        right = margin * code[own] > 0
        trust = np.array([right[own == i].mean(0) for i in range(len(names))]) + 1e-6
        out = cls(names, code, trust / trust.sum(1, keepdims=True), w, b)
        # halfway from the worst labelled row to a text that tells the bits nothing; no labelled row is above
        worst = float(out.losses(margin).min(1).max())
        out.cutoff = max(worst, (worst + np.log(2)) / 2)
        return out

    def losses(self, margin: np.ndarray) -> np.ndarray:
        """One column per language: the loss on each side of a bit once, then two products."""
        margin = np.clip(margin.astype(float), -30, 30)
        return np.log1p(np.exp(-margin)) @ (self.trust * (self.code > 0)).T + np.log1p(np.exp(margin)) @ (self.trust * (self.code < 0)).T

    def decode(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        """Languages, scores in 0..1, whether the runner-up is near, and whether the text
        is in a learned language at all (with none learned, any may be)."""
        if not self.languages:
            return [UNDEFINED] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool), np.ones(len(texts), bool)
        loss = self.losses(histograms(texts) @ self.weights + self.bias)
        fit = np.exp(-4 * (loss - loss.min(1, keepdims=True)))
        fit /= fit.sum(1, keepdims=True)
        best = loss.argmin(1)
        score = fit[np.arange(len(best)), best]
        second = np.sort(fit, 1)[:, -2] if fit.shape[1] > 1 else np.zeros(len(best))
        return [self.languages[i] for i in best], score, second > 0.5 * score, loss.min(1) <= self.cutoff


def held_out() -> Column:
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(4)) == 2


@F.pandas_udf(T.BinaryType())
def packed(texts: pd.Series) -> pd.Series:
    """Histograms, mostly zeros, as compressed bytes."""
    texts = texts.tolist()
    return pd.Series([zlib.compress(h.tobytes(), 1) for lo in range(0, len(texts), 256) for h in histograms(texts[lo: lo + 256])], dtype=object)


def train(docs: DataFrame) -> Codes:
    """Fit on rows of ``docs`` (doc_id, text, lang) that are not held out and have a
    language: for each language, however rare, the TRAIN_ROWS first in a seeded order,
    or its even share of TRAIN_TOTAL where there are many.  Rows that repeat id and text count
    once.  The first ones are among those with a low enough draw, so a language's rows
    never meet: only twice as many as are wanted go on.  Whole texts are counted by
    the executors; the driver gets their histograms, of one size."""
    rows = docs.where(~held_out() & F.col("lang").isNotNull() & F.col("text").rlike(r"\p{L}")).select("doc_id", "lang", "text", F.xxhash64("text").alias("h"))
    draw = unit(F.col("doc_id"), F.col("h"), F.lit(6))
    sizes = settle(rows.groupBy("lang").agg(F.approx_count_distinct(draw, 0.02).alias("n")), "languages")
    each = max(1, min(TRAIN_ROWS, TRAIN_TOTAL // max(sizes.count(), 1)))
    # twice the share, and 50 more, is missed by fewer than ``each`` rows with odds below 1e-12
    low = sizes.select(F.col("lang").alias("__l"), ((2.0 * each + 50) / F.col("n")).alias("upto"))
    ids = rows.select("doc_id", "lang", "h", draw.alias("draw")).join(F.broadcast(low), F.col("lang") == F.col("__l")).where(F.col("draw") < F.col("upto"))
    ids = ids.select("doc_id", "lang", "h", "draw").distinct()
    order = W.partitionBy("lang").orderBy("draw", "doc_id", "h")
    ids = ids.withColumn("k", F.row_number().over(order)).where(F.col("k") <= each)
    ids = ids.select(F.col("doc_id").alias("i"), F.col("lang").alias("l"), F.col("h").alias("g"))
    few = rows.join(F.broadcast(ids), F.col("doc_id").eqNullSafe(F.col("i")) & (F.col("lang") == F.col("l")) & (F.col("h") == F.col("g")), "left_semi")
    few = few.select("doc_id", "lang", "h", packed("text").alias("x")).dropDuplicates(["doc_id", "lang", "h"]).toPandas()
    few = few.sort_values(["doc_id", "h"])
    x = np.empty((len(few), DIM), np.float32)
    for i, b in enumerate(few["x"]):
        x[i] = np.frombuffer(zlib.decompress(b), np.float32)
    return Codes.fit_histograms(x, few["lang"].tolist())


def predict(docs: DataFrame, codes: Codes) -> DataFrame:
    """Adds lang_pred, score, ambiguous and told to ``docs`` (text), whose other columns pass
    through; told is whether the text is in a learned language.  Texts that are null or without a letter are ``und`` with score 0; long
    texts are counted whole.  The model has a fixed size, whatever the data."""
    shared = docs.sparkSession.sparkContext.broadcast(codes)

    @F.pandas_udf("struct<lang_pred string, score double, ambiguous boolean, told boolean>")
    def decode(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for column in batches:
            texts = [t or "" for t in column]
            out = pd.DataFrame({"lang_pred": UNDEFINED, "score": 0.0, "ambiguous": True, "told": False}, index=range(len(texts)))
            rows = [i for i, t in enumerate(texts) if _LETTER.search(t)]
            for lo in range(0, len(rows), 256):
                part = rows[lo: lo + 256]
                names, score, near, told = shared.value.decode([texts[i] for i in part])
                out.loc[part, "lang_pred"], out.loc[part, "score"], out.loc[part, "ambiguous"], out.loc[part, "told"] = names, score, near, told
            yield out

    # not to be pushed into a later filter, which would decode every text again
    decode = decode.asNondeterministic()
    return docs.drop("lang_pred", "score", "ambiguous", "told").withColumn("__p", decode("text")).select("*", "__p.lang_pred", "__p.score", "__p.ambiguous", "__p.told").drop("__p")


def identify(docs: DataFrame) -> DataFrame:
    """Per row of ``docs`` (doc_id, text, lang): doc_id, held_out, lang_pred, score, ambiguous."""
    rows = docs.select("doc_id", "text", "lang")
    out = predict(rows.select("doc_id", "text"), train(rows))
    return out.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "ambiguous")


def keep_identified(docs: DataFrame) -> DataFrame:
    """``docs`` with their language told, without the rows whose language cannot be.

    Rejected are texts without a letter, texts whose loss lies past the cutoff, and ambiguous
    ones that have no label to decide.  ``lang`` becomes the prediction where it is null,
    or where another is predicted with a score of CONFIDENT or more; all other columns stay
    as they are.  With no label to learn from, all texts with a letter stay as they are; with
    one language the code has no bit that could reject."""
    codes = train(docs.select("doc_id", "text", "lang"))
    # a column of docs may have a name that predict adds
    told = predict(docs.select(F.struct(*docs.columns).alias("__d"), F.col("text")), codes).where("told")
    if not codes.languages:
        return told.select("__d.*")
    label = F.col("__d.lang")
    firm = ~F.col("ambiguous") & (label.isNull() | (F.col("score") >= CONFIDENT))
    lang = F.when(firm, F.col("lang_pred")).otherwise(label)
    return told.where(label.isNotNull() | ~F.col("ambiguous")).select(*[lang.alias(c) if c == "lang" else F.col("__d").getField(c).alias(c) for c in docs.columns])
