"""Personal data: fixed patterns first, then bootstrapped contextual extraction.

The fixed patterns find emails, IP addresses, card and phone numbers.  They, and a
few shapes of credentials, are the seeds.  A word between blanks may hold many
identifier-like values (runs of value characters with a digit, ``=`` at their end
being padding); around each stands a lexical pattern: what is glued to its front, back
to the value before it, and up to two words or values before, identifiers blurred, and
the class of the value.  In scripts without spaces the last two and four characters
before the value stand for words.  Patterns and instances form a bipartite graph that Spark scores in turns:
a pattern is as good as the mean score of its instances, shrunk by its support;
an instance is as good as its best pattern, seeds staying at 1.  Instances of
patterns above the bar become spans of kind ``secret``.

Texts are read once; the graph holds identifier-like values alone.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import UNSPACED, settle

KINDS = ["email", "ip", "card", "phone"]
LEARNED = "secret"
ROUNDS, BAR, LEAST_SUPPORT, PRIOR = 3, 0.6, 5, 2.0

_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# a match cannot start inside a run of digits whose start did not match
_IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
#: Shapes of credentials that seed the bootstrap: fixed values.
_SEED = re.compile(r"(?:AKIA|ghp_|sk-)[0-9A-Za-z]{16,}\Z|(?=[0-9]*[a-f])(?:[a-f]*[0-9]){4}[0-9a-f]{12,}\Z")
# a match starts where its run does, so that runs without a digit are passed once
_TOKEN = re.compile(r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D0-9]*+[0-9][^\x20\x09-\x0D]*")
_VALUE = re.compile(r"(?<![A-Za-z0-9+/_.-])[A-Za-z+/_.-]*+[0-9][A-Za-z0-9+/_.-]*")
_PADDING = re.compile(r"=++(?![A-Za-z0-9+/_.(\[{<$-])")
_QUOTE = re.compile(r"""\\*(["'`])""")
_NO_SPACES = re.compile(f"[{UNSPACED}]+(?=[^{UNSPACED}]*\\Z)")


def _emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches of local part, @ and dotted domain, each character looked at
    a bounded number of times: the local part is the run that ends at an @."""
    out, at, done = [], text.find("@"), 0
    while at >= 0:
        start = at
        while start > done and (text[start - 1].isascii() and (text[start - 1].isalnum() or text[start - 1] in "._%+-")):
            start -= 1
        m = _DOMAIN.match(text, at) if start < at else None
        if m:
            out.append((start, m.end()))
            done = m.end()
        else:
            done = max(done, at)
        at = text.find("@", max(at + 1, done))
    return out


def _luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = ord(c) - 48
        if i % 2:
            n = n * 2 - 9 if n > 4 else n * 2
        total += n
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """``(start, end, kind)`` in code points, sorted by start, then kind as listed."""
    out = [(a, b, "email") for a, b in _emails(text)]
    if _DIGIT.search(text):
        out += [(m.start(), m.end(), "ip") for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m[0].split("."))]
        for m in _CARD.finditer(text):
            d = _digits(m[0])
            if 12 <= len(d) <= 19 and _luhn(d):
                out.append((m.start(), m.end(), "card"))
        out += [(m.start(), m.end(), "phone") for m in _PHONE.finditer(text) if 9 <= len(_digits(m[0])) <= 15]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def _class(value: str) -> str:
    """What may stand in for an identifier: any mix of letters and digits, or digits
    and marks of like length."""
    if "@" in value:
        return "mail"
    if re.search("[A-Za-z]", value):
        return "mixed"
    return f"digits{'+' if re.search('[^0-9]', value) else ''}{min(len(value), 32)}"


def _blur(word: str, keep: int = 24) -> str:
    """A word of the context: identifiers become one mark, the rest stays, in lower case,
    its first ``keep`` characters or its last ``-keep``."""
    return "<id>" if _DIGIT.search(word) or "@" in word else word.lower()[:keep] if keep > 0 else word.lower()[keep:]


def _padded(text: str, start: int, end: int, stop: int) -> int:
    """Where the value ends with its padding: ``=`` that no value, bracket or opening quote follows."""
    m = _PADDING.match(text, end, stop)
    if not m:
        return end
    quote = _QUOTE.match(text, m.end(), stop)
    return m.end() if not quote or text[start - 1: start] == quote[1] else end


def _contexts(glued: str, near: list[str]) -> list[str]:
    """What a pattern may say of the front of a value."""
    tail = _blur(glued, -24)
    out = [tail] if re.search("[a-z]", tail) else []
    run = _NO_SPACES.search(glued)
    if run:
        out += [run[0][-k:] + _blur(glued[run.end():], -24) for k in (2, 4) if k == 2 or len(run[0]) > 2]
    out += [" ".join([*near[-k:], tail]) for k in range(1, len(near) + 1)]
    return out or [f"^ {tail}"]


def candidates(text: str, base: list[tuple[int, int, str]]) -> list[tuple[int, int, str, str, bool]]:
    """Identifier-like values as ``(start, end, pattern, instance, seed)``, once for each
    of their patterns: what is glued to the front, that and one word, and two; all
    values of a word count, and the start of the text where nothing stands before."""
    out = []
    #: of the base spans, and of the emails among them: starts, and the furthest end so far
    known, mails = (([x for x, _, _ in part], list(accumulate((y for _, y, _ in part), max))) for part in (base, [s for s in base if s[2] == "email"]))

    def meets(spans: tuple[list[int], list[int]], start: int, end: int) -> bool:
        n = bisect_left(spans[0], end)
        return n > 0 and spans[1][n - 1] > start

    for m in _TOKEN.finditer(text):
        a, b = m.span()
        near, last = [_blur(w) for w in text[max(0, a - 80): a].split()[-2:]], a
        for v in _VALUE.finditer(text, a, b):
            start, bare = v.span()
            end = _padded(text, start, bare, b)
            if end == bare:
                while end > start and text[end - 1] in ".-":
                    end -= 1
                bare = end
            value, glued, before = text[start:end], text[last:start], near
            near, last = [*near, "<id>"][-2:], end
            kind = "mail" if meets(mails, start, end) else _class(text[start:bare])
            if kind == "mixed" and bare - start < 6:
                continue
            seed = meets(known, start, end) or bool(_SEED.match(text, start, bare))
            out += [(start, end, f"{kind} {c}", value, seed) for c in _contexts(glued, before)]
    return out


_SPAN = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.string())])
_CANDIDATE = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("pattern", pa.string()), ("instance", pa.string()), ("seed", pa.bool_())])
_SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, base array<struct<start:int,end:int,kind:string>>, found array<struct<start:int,end:int,pattern:string,instance:string,seed:boolean>>"


def join_spans(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        counts, shas, bases, found = [[], [], [], []], [], [], []
        for text in batch.column("text").to_pylist():
            text = text or ""
            base = base_spans(text)
            for i, k in enumerate(KINDS):
                counts[i].append(sum(s[2] == k for s in base))
            shas.append(hashlib.sha256(join_spans(base).encode()).hexdigest())
            bases.append([{"start": a, "end": b, "kind": k} for a, b, k in base])
            found.append([dict(zip(("start", "end", "pattern", "instance", "seed"), c)) for c in (candidates(text, base) if _DIGIT.search(text) else [])])
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in counts), pa.array(shas), pa.array(bases, pa.list_(_SPAN)), pa.array(found, pa.list_(_CANDIDATE))],
            ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "base", "found"])


def score_graph(edges: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """``(pattern, confidence, support)`` from ``edges`` (pattern, instance, seed, n), one
    row per pair.  Each round is two partial aggregates over the edges; a pattern
    that a third of all edges share is summed before it is shuffled."""
    seeds = edges.groupBy("instance").agg(F.max(F.col("seed").cast("double")).alias("score"))
    instances = settle(seeds.withColumn("seed_score", F.col("score")), "instances")
    patterns = None
    for _ in range(rounds):
        scored = edges.join(instances.hint("merge"), "instance")
        patterns = scored.groupBy("pattern").agg(F.sum("score").alias("won"), F.count(F.lit(1)).alias("support"))
        patterns = settle(patterns.select("pattern", (F.col("won") / (F.col("support") + PRIOR)).alias("confidence"), "support"), "patterns")
        best = edges.join(patterns.where(F.col("support") >= LEAST_SUPPORT).hint("merge"), "pattern").groupBy("instance").agg(F.max("confidence").alias("best"))
        instances = settle(instances.join(best.hint("merge"), "instance", "left").select("instance", "seed_score", F.greatest("seed_score", F.coalesce("best", F.lit(0.0))).alias("score")), "instances")
    return patterns


def find_personal_data(docs: DataFrame) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, the counts of the base kinds,
    base_sha256, spans, n_secret.

    Null and empty texts have no spans; very long texts and runs of one character are
    read in time proportional to their length; repeated rows get equal results."""
    rows = docs.select("doc_id", "text").mapInArrow(_read, _SCHEMA)
    # a row's own key, so that rows that repeat an id stay rows of their own; it is fixed by the table
    rows = settle(rows.withColumn("row", F.monotonically_increasing_id()), "personal")
    found = rows.select("row", F.explode("found").alias("c")).select("row", "c.*")
    edges = settle(found.groupBy("pattern", "instance").agg(F.max("seed").alias("seed"), F.count(F.lit(1)).alias("n")), "edges")
    good = score_graph(edges).where((F.col("confidence") >= BAR) & (F.col("support") >= LEAST_SUPPORT)).select("pattern")
    new = found.join(good.hint("merge"), "pattern", "left_semi").select("row", F.struct("start", "end", F.lit(LEARNED).alias("kind")).alias("s"))
    seeds = found.where("seed").select("row", F.struct("start", "end", F.lit(LEARNED).alias("kind")).alias("s"))
    new = new.union(seeds).groupBy("row").agg(F.collect_set("s").alias("learned"))
    out = rows.drop("found").join(new.hint("merge"), "row", "left")
    none = F.array().cast("array<struct<start:int,end:int,kind:string>>")
    fresh = F.filter(F.coalesce("learned", none), lambda s: ~F.exists("base", lambda b: (b["start"] < s["end"]) & (s["start"] < b["end"])))
    out = out.withColumn("fresh", fresh)
    rank = F.create_map(*[x for i, k in enumerate([*KINDS, LEARNED]) for x in (F.lit(k), F.lit(i))])
    ordered = F.array_sort(F.transform(F.concat("base", "fresh"), lambda s: F.struct(s["start"].alias("start"), rank[s["kind"]].alias("rank"), s["end"].alias("end"), s["kind"].alias("kind"))))
    spans = F.concat_ws(",", F.transform(ordered, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])))
    return out.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", spans.alias("spans"), F.size("fresh").cast("long").alias("n_secret"))
