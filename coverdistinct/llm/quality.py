"""Quality rules whose cutoffs carry a guarantee, in DataFrame expressions only.

A rule rejects a document when a measure exceeds its cutoff.  The cutoffs are
chosen on labelled rows: for each stratum (language) and rule the grid is walked
from the loosest cutoff to the strictest, and a cutoff stands while the exact
binomial test rejects "the rule rejects more than its share of ``risk`` of the good documents".
Walking in a fixed order needs no correction inside a grid; over strata and rules
the level is divided by their number (Bonferroni).  So, with a probability of 1 - ``level``, in
every stratum all rules together reject at most ``risk`` of the good documents that pass the
base rules.  A stratum with too few good labels to prove anything keeps all its documents
(at zero rejections a cutoff takes ``log(level / rules / strata) / log(1 - risk / rules)`` of them).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, settle, words

SYMBOLS = "#*$%&|<>"
#: measure -> cutoffs from loose to strict: fixed values.
GRID = {
    "symbols_per_word": [8.0, 5.0, 3.0, 2.0, 1.5, 1.0, 0.7, 0.5, 0.3],
    "dup_lines_per_word": [0.3, 0.2, 0.1, 0.07, 0.05, 0.03],
    "repeat_share": [0.28, 0.25, 0.22, 0.2, 0.17, 0.15],
    "word_length": [25.0, 20.0, 17.0, 15.0, 13.0, 12.0],
}
RISK, LEVEL, WINDOW = 0.016, 0.05, 8


def _with_window_hashes(df: DataFrame, w: str = "w", out: str = "h", n: int = WINDOW) -> DataFrame:
    """Adds the hashes of all ``n``-word windows of array ``w`` (n a power of two), by
    doubling; null for arrays no longer than one window.  One projection a step, so
    that no step is evaluated twice."""
    if n & (n - 1):
        raise ValueError("the window is a power of two")
    df = df.withColumn("__h1", F.when(F.size(w) > n, F.transform(w, lambda x: F.xxhash64(x))))
    step = 1
    while step < n:
        h = F.col(f"__h{step}")
        later = F.slice(h, step + 1, F.size(h))
        df = df.withColumn(f"__h{2 * step}", F.zip_with(h, later, lambda a, b: F.xxhash64(a, b))).drop(f"__h{step}")
        step *= 2
    return df.withColumn(out, F.slice(f"__h{n}", 1, F.size(w) - (n - 1))).drop(f"__h{n}")


def measures(docs: DataFrame) -> DataFrame:
    """Per row of ``docs`` (doc_id, text, lang): n_words, word_chars, n_symbols,
    n_dup_lines, n_repeat_words.  A null text has no words.  Everything is computed
    inside its row: no shuffle, and a text is never cut."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: F.trim(F.translate(x, SPACE, " " * len(SPACE))) != "")
    df = docs.select("doc_id", "lang", text.alias("text")).select(
        "doc_id", "lang",
        words(F.col("text")).alias("w"),
        F.length(F.translate("text", SPACE, "")).cast("long").alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        lines.alias("lines"),
    )
    df = _with_window_hashes(df).select(
        "doc_id", "lang", "word_chars", "n_symbols", "h",
        F.size("w").cast("long").alias("n_words"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"))
    # sorted (hash, place) only for rows with a repeated window; the others stop here
    df = df.withColumn("s", F.when(F.size(F.array_distinct("h")) < F.size("h"),
                                   F.array_sort(F.transform("h", lambda x, i: F.struct(x.alias("h"), i.alias("i"))))))
    again = F.expr("""array_sort(transform(filter(transform(s, (x, k) -> struct(x.i AS i,
        coalesce(x.h = get(s, k - 1).h, false) OR coalesce(x.h = get(s, k + 1).h, false) AS twice)), x -> x.twice), x -> x.i))""")
    df = df.withColumn("starts", again)
    covered = F.aggregate("starts", F.struct(F.lit(0).alias("end"), F.lit(0).alias("n")),
                          lambda a, x: F.struct((x + WINDOW).alias("end"), (a["n"] + x + WINDOW - F.greatest(x, a["end"])).alias("n")),
                          lambda a: a["n"])
    return df.select("doc_id", "lang", "n_words", "word_chars", "n_symbols", "n_dup_lines",
                     F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"))


def _with_rates(df: DataFrame) -> DataFrame:
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return (df.withColumn("symbols_per_word", F.col("n_symbols") / n)
              .withColumn("dup_lines_per_word", F.col("n_dup_lines") / n)
              .withColumn("repeat_share", F.col("n_repeat_words") / n)
              .withColumn("word_length", F.col("word_chars") / n))


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def binomial_tail(k: Column, n: Column, p: float) -> Column:
    """P(Bin(n, p) <= k) exactly, for k <= n p (1.0 above): the k-th term times the
    sum of the ratios down to term 0."""
    k, n = k.cast("double"), n.cast("double")
    small = (k <= n * p) & (n > 0)
    upto = F.when(small & (k >= 1), F.sequence(F.lit(1), k.cast("int"))).otherwise(F.array().cast("array<int>"))
    log_c = F.aggregate(upto, F.lit(0.0), lambda s, i: s + F.log((n - k + i) / i))
    down = F.aggregate(F.reverse(upto), F.struct(F.lit(1.0).alias("t"), F.lit(1.0).alias("s")),
                       lambda a, i: F.struct((a["t"] * i * (1 - p) / ((n - i + 1) * p)).alias("t"),
                                             (a["s"] + a["t"] * i * (1 - p) / ((n - i + 1) * p)).alias("s")),
                       lambda a: a["s"])
    term = F.exp(log_c + k * F.log(F.lit(p)) + (n - k) * F.log(F.lit(1 - p)))
    return F.when(small, F.least(term * down, F.lit(1.0))).otherwise(1.0)


def cutoffs(measured: DataFrame, labels: DataFrame, risk: float = RISK, level: float = LEVEL) -> DataFrame:
    """One row per stratum and rule with a proven cutoff: lang, rule, cutoff, n, k, tail.

    Labels: doc_id, quality (1: good); of repeated labels the best counts, null
    ones none.  Documents that fail the base rules are no evidence.  The counts
    are one partial aggregate over all labelled rows."""
    good = labels.groupBy("doc_id").agg(F.max("quality").alias("__q")).where("__q = 1").select("doc_id")
    rows = _with_rates(measured.where(~base_failed())).join(good, "doc_id", "left_semi")
    counts = [F.count_if(F.col(rule) > cut).alias(f"{rule}__{i}") for rule, grid in GRID.items() for i, cut in enumerate(grid)]
    wide = rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), *counts)
    steps = F.array(*[F.struct(F.lit(rule).alias("rule"), F.lit(i).alias("i"), F.lit(cut).alias("cutoff"), F.col(f"{rule}__{i}").alias("k"))
                      for rule, grid in GRID.items() for i, cut in enumerate(grid)])
    tests = wide.select("lang", "n", F.explode(steps).alias("t")).select("lang", "n", "t.*")
    strata = wide.agg(F.greatest(F.count(F.lit(1)), F.lit(1)).alias("strata"))
    tests = tests.withColumn("tail", binomial_tail(F.col("k"), F.col("n"), risk / len(GRID))).crossJoin(F.broadcast(strata))
    tests = tests.withColumn("passes", F.col("tail") <= level / (len(GRID) * F.col("strata")))
    stop = F.coalesce(F.min(F.when(~F.col("passes"), F.col("i"))), F.lit(1 << 30))
    firm = tests.groupBy("lang", "rule").agg(stop.alias("stop"), F.collect_list(F.struct("i", "cutoff", "n", "k", "tail")).alias("g"))
    won = F.array_max(F.filter("g", lambda x: x["i"] < F.col("stop")))
    return firm.withColumn("won", won).where("won is not null").select("lang", "rule", "won.cutoff", "won.n", "won.k", "won.tail")


def judge(measured: DataFrame, proven: DataFrame) -> DataFrame:
    """Adds base_failed and kept.  ``proven`` has at most one row per stratum and rule."""
    limits = proven.groupBy("lang").agg(*[F.min(F.when(F.col("rule") == rule, F.col("cutoff"))).alias(f"max_{rule}") for rule in GRID])
    limits = limits.withColumnRenamed("lang", "__lang")
    df = _with_rates(measured).join(limits, F.col("lang").eqNullSafe(F.col("__lang")), "left")
    rejected = F.lit(False)
    for rule in GRID:
        rejected = rejected | F.coalesce(F.col(rule) > F.col(f"max_{rule}"), F.lit(False))
    return df.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & ~rejected)


def rule_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """All documents with their measures and verdict.  The measures are settled
    once (numbers only, no texts); calibration and verdicts read them."""
    measured = settle(measures(docs), "quality")
    return judge(measured, cutoffs(measured, labels)).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
