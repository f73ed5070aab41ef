"""DuckDB SQL of the methods, written apart from the Spark plans: the test oracle.

Every function returns a query string over the test tables' names.
"""

from __future__ import annotations

from ..functions import theory
from ..functions.hashing import threshold
from ..sources.streams import STREAMS


def text(x: str) -> str:
    return f"CAST({x} AS VARCHAR)"


def encode(parts: tuple[str, ...]) -> str:
    if len(parts) == 1:
        return text(parts[0])
    return "concat_ws(',', " + ", ".join(f"coalesce(length({text(p)}) || ':' || {text(p)}, '~')" for p in parts) + ")"


def h60(x: str) -> str:
    return f"CAST('0x' || substr(md5({x}), 9, 15) AS BIGINT)"


def h32(x: str) -> str:
    return f"CAST('0x' || substr(md5({x}), 1, 8) AS BIGINT)"


def rank(x: str) -> str:
    return f"(CASE WHEN {h60(x)} = 0 THEN 61 ELSE 61 - length(bin({h60(x)})) END)"


TOKENS = r"(SELECT {ids}, unnest(range(len(parts))) AS pos, unnest(parts) AS token FROM (SELECT {ids}, regexp_split_to_array(lower(text), '[^\p{{L}}]+') AS parts FROM {table}))"


def stream(name: str, groups: dict[str, str] | None = None) -> str:
    s = STREAMS[name]
    source, more = s.table, ""
    if name == "word":
        source, more = TOKENS.format(ids="doc_id", table="documents"), " AND token <> ''"
    elif name == "talk_word":
        source, more = TOKENS.format(ids="conv_id, turn", table="conversations"), " AND token <> ''"
    elif name == "host":
        source = "(SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages)"
    g = "".join(f"{v} AS {k}, " for k, v in (groups or {}).items())
    return f"SELECT {g}{encode(s.element)} AS element, {encode(s.occ)} AS occ FROM {source} WHERE {s.element[0]} IS NOT NULL{more}"


def sample(x: str, rate: float, seed: int | str = 42) -> str:
    return x if rate == 1 else f"SELECT * FROM ({x}) WHERE {h60(f'occ || ' + repr(f'|s{seed}'))} < {threshold(rate)}"


def cols(g: list[str], prefix: str = "") -> str:
    return "".join(f"{prefix}{c}, " for c in g)


def counts(y: str, g: list[str] = ()) -> str:
    return f"SELECT {cols(g)}element, count(*) AS f FROM ({y}) GROUP BY ALL"


HEADS = "CAST(coalesce(sum(f), 0) AS BIGINT) AS l, count(*) AS ns, count(*) FILTER (f = 1) AS e1, count(*) FILTER (f = 2) AS e2"


def heads(y: str, g: list[str] = ()) -> str:
    return f"SELECT {cols(g)}{HEADS} FROM ({counts(y, g)}) GROUP BY ALL"


def hll_formula(m: int, used: str = "used", z: str = "z") -> str:
    raw = f"({theory.alpha(m)!r} * {float(m)} * {float(m)} / (coalesce({z}, 0) + ({float(m)} - {used})))"
    return f"CASE WHEN {raw} <= {2.5 * m} AND {m} - {used} > 0 THEN {float(m)} * ln({float(m)} / ({float(m)} - {used})) ELSE {raw} END"


def registers(y: str, m: int, g: list[str] = (), seed: int = 42) -> str:
    v = f"element || '|v{seed}'"
    return f"SELECT {cols(g)}{h32(v)} % {m} AS bucket, max({rank(v)}) AS rank FROM ({y}) GROUP BY ALL"


def hll(y: str, m: int, g: list[str] = (), seed: int = 42) -> str:
    return f"SELECT {cols(g)}{hll_formula(m)} AS ns_hat FROM (SELECT {cols(g)}count(*) AS used, sum(pow(2.0, -rank)) AS z FROM ({registers(y, m, g, seed)}) GROUP BY ALL)"


def exact(y: str, g: list[str] = ()) -> str:
    return f"SELECT {cols(g)}CAST(count(DISTINCT element) AS DOUBLE) AS ns_hat FROM ({y}) GROUP BY ALL"


def bottom_m(y: str, m: int, seed: int = 42) -> str:
    v = f"element || '|v{seed}'"
    return (f"SELECT CASE WHEN count(*) < {m} THEN CAST(count(*) AS DOUBLE) ELSE {float(m - 1)} / (CAST(max(hash) AS DOUBLE) / {float(1 << 60)}) END AS ns_hat "
            f"FROM (SELECT DISTINCT {h60(v)} AS hash FROM ({y}) ORDER BY hash LIMIT {m})")


def linear(y: str, m: int, seed: int = 42) -> str:
    v = f"element || '|v{seed}'"
    return f"SELECT CASE WHEN {m} - b > 0 THEN {m} * ln({float(m)} / ({m} - b)) END AS ns_hat FROM (SELECT count(DISTINCT {h32(v)} % {m}) AS b FROM ({y}))"


COUNTERS = {"exact": lambda y, m, g: exact(y, g), "hll": hll, "bottom_m": lambda y, m, g: bottom_m(y, m), "linear": lambda y, m, g: linear(y, m)}


def probe(y: str, u: int, mode: str, g: list[str] = (), seed: int = 42, boundary: str = "keep") -> str:
    order = "vh, oh" if mode == "value_hash" else "oh, vh"
    over = f"PARTITION BY {', '.join(g)} " if g else ""
    whole = f"SELECT *, {h60(f'element || ' + repr(f'|v{seed}'))} AS vh, {h60(f'occ || ' + repr(f'|u{seed}'))} AS oh FROM ({y})"
    sub = f"SELECT * FROM (SELECT *, row_number() OVER ({over}ORDER BY {order}) AS k FROM ({whole})) WHERE k <= {u}"
    if mode == "in_sample":
        same = " AND ".join(f"a.{c} IS NOT DISTINCT FROM b.{c}" for c in [*g, "element"])
        per = f"SELECT {cols(g, 'a.')}a.n, b.f FROM (SELECT {cols(g)}element, count(*) AS n FROM ({sub}) GROUP BY ALL) a JOIN ({counts(y, g)}) b ON {same}"
        return (f"SELECT {cols(g)}u, u1, u2, u1 / u AS p0, u2 / u AS p1 FROM (SELECT {cols(g)}CAST(coalesce(sum(n), 0) AS BIGINT) AS u, CAST(coalesce(sum(n) FILTER (f = 1), 0) AS BIGINT) AS u1, "
                f"CAST(coalesce(sum(n) FILTER (f = 2), 0) AS BIGINT) AS u2 FROM ({per}) GROUP BY ALL)")
    if mode == "value_hash" and boundary == "drop":
        w = f"OVER ({over})"
        sub = f"SELECT * FROM (SELECT *, max(vh) {w} AS last, count(*) {w} AS n FROM ({sub})) WHERE n < {u} OR vh < last"
    per = f"SELECT {cols(g)}element, count(*) AS f FROM ({sub}) GROUP BY ALL"
    return (f"SELECT {cols(g)}u, u1, u2, u1 / u AS p0, 2 * u2 / u AS p1 FROM (SELECT {cols(g)}CAST(coalesce(sum(f), 0) AS BIGINT) AS u, count(*) FILTER (f = 1) AS u1, count(*) FILTER (f = 2) AS u2 "
            f"FROM ({per}) GROUP BY ALL)")


def _join(parts: list[tuple[str, str]], g: list[str]) -> str:
    first = parts[0][1]
    out = f"({parts[0][0]}) {first}"
    for q, a in parts[1:]:
        out += f" JOIN ({q}) {a} ON " + (" AND ".join(f"{first}.{c} IS NOT DISTINCT FROM {a}.{c}" for c in g) if g else "true")
    return out


def row(parts: str, method: str, name: str, m: int | None, rate: float | None, g: list[str], are: float | None, group_from: str) -> str:
    """The estimate row over ``parts`` with l, ns, e1, e2, u, p0_, p1_, ns_hat_."""
    whole = rate == 1
    sketch = "0.0" if are is None or m is None else repr(1 / (are * m))
    cover = "p0 * (1 - p0) + p1" if method == "sampled" else "2 * p0 * (1 - p0) + p1"
    size = "l" if method == "sampled" else "u"
    noise = "0.0" if whole else f"(({cover}) / nullif({size}, 0) / ((1 - p0) * (1 - p0)))"
    singles = "false" if whole else "p0 >= 1"
    units = "CAST(ns_hat_ AS BIGINT)" if m is None else str(m)
    extra = "0" if whole else size
    actual = "0" if whole else ("coalesce(ns, l)" if method == "sampled" else "u")
    inner = f"SELECT {cols(g, group_from + '.')}*  EXCLUDE ({', '.join(g)}), " if g else "SELECT *, "
    p0, p1 = ("0.0", "0.0") if whole else ("p0_", "p1_")
    base = f"{inner}CAST({p0} AS DOUBLE) AS p0, CAST({p1} AS DOUBLE) AS p1 FROM {parts}"
    st = f"SELECT *, CASE WHEN l = 0 THEN 'empty_sample' WHEN {singles} THEN 'all_singletons' ELSE 'ok' END AS status, CASE WHEN l > 0 AND p0 <> 1 THEN 1.0 / (1 - p0) END AS ratio FROM ({base})"
    rv = f"SELECT *, CASE WHEN status = 'ok' THEN {noise} + {sketch} END AS rel_var FROM ({st})"
    r = "CAST(NULL AS DOUBLE)" if rate is None else repr(float(rate))
    return f"""SELECT {cols(g)}'{method}' AS method, '{name}' AS procedure, {r} AS rate, CAST({'NULL' if m is None else m} AS BIGINT) AS m, CAST(u AS BIGINT) AS u, CAST(l AS BIGINT) AS l,
 CAST(e1 AS BIGINT) AS e1, CAST(e2 AS BIGINT) AS e2, round(p0, 6) AS p0, round(p1, 6) AS p1, round(CASE WHEN l > 0 THEN ns_hat_ END, 6) AS ns_hat, round(ratio, 6) AS ratio,
 round(CASE WHEN status = 'ok' THEN ns_hat_ * ratio END, 6) AS n_hat, round(rel_var, 6) AS rel_var,
 round(CASE WHEN status = 'ok' THEN greatest(ns_hat_ * ratio * (1 - 1.96 * sqrt(rel_var)), CAST(coalesce(ns, 0) AS DOUBLE)) END, 6) AS ci_lo,
 round(CASE WHEN status = 'ok' THEN ns_hat_ * ratio * (1 + 1.96 * sqrt(rel_var)) END, 6) AS ci_hi,
 CAST({units} + {extra} AS BIGINT) AS storage_units, CAST({units} + {actual} AS BIGINT) AS storage_actual, status FROM ({rv})"""


def m1(y: str, m: int | None = 200, rate: float | None = None, g: list[str] = (), name: str = "hll", are: float | None = 1 / 1.08) -> str:
    g = list(g)
    parts = _join([(f"SELECT {cols(g)}l, ns, e1, e2, e1 / nullif(l, 0) AS p0_, 2 * e2 / nullif(l, 0) AS p1_, 0 AS u FROM ({heads(y, g)})", "a"),
                   (f"SELECT {cols(g)}ns_hat AS ns_hat_ FROM ({COUNTERS[name](y, m, g)})", "b")], g)
    if g:
        parts = f"(SELECT a.*, b.ns_hat_ FROM {parts}) a"
    return row(parts, "sampled", name, m, rate, g, are, "a")


def m2(y: str, m: int | None, u: int, mode: str, rate: float | None = None, g: list[str] = (), boundary: str = "keep", are: float | None = 1 / 1.08, name: str = "hll") -> str:
    g = list(g)
    parts = _join([(f"SELECT {cols(g)}count(*) AS l FROM ({y}) GROUP BY ALL", "a"), (f"SELECT {cols(g)}ns_hat AS ns_hat_ FROM ({COUNTERS[name](y, m, g)})", "b"),
                   (f"SELECT {cols(g)}u, p0 AS p0_, p1 AS p1_ FROM ({probe(y, u, mode, g, boundary=boundary)})", "c")], g)
    parts = f"(SELECT a.*, b.ns_hat_, c.u, c.p0_, c.p1_, NULL AS ns, NULL AS e1, NULL AS e2 FROM {parts}) a"
    return row(parts, "subsampled", name, m, rate, g, are, "a")


# --- replicated runs ---

def runs(x: str, rates: list[float], n: int) -> str:
    """``(rate, run, element, occ)``."""
    grid = " UNION ALL ".join(f"SELECT CAST({r!r} AS DOUBLE) AS rate, {threshold(r)} AS t" for r in rates)
    hashed = f"SELECT run, element, occ, {h60(chr(39).join(['occ || ', '|s', ' || run']))} AS h FROM ({x}), range({n}) q(run)"
    return f"SELECT rate, run, element, occ FROM ({hashed}) JOIN ({grid}) ON h < t"


def run_hll(values: str, ms: list[int]) -> str:
    """``(rate, run, m, l, ns, e1, e2, ns_hat)`` from ``(rate, run, element, k)``."""
    v = "element || '|v' || run"
    regs = (f"SELECT rate, run, m, {h32(v)} % m AS b, max({rank(v)}) AS r, sum(k) AS l, count(*) AS ns, count(*) FILTER (k = 1) AS e1, count(*) FILTER (k = 2) AS e2 "
            f"FROM ({values}), (SELECT unnest({list(ms)}) AS m) GROUP BY ALL")
    sums = f"SELECT rate, run, m, count(*) AS used, sum(pow(2.0, -r)) AS z, sum(l) AS l, sum(ns) AS ns, sum(e1) AS e1, sum(e2) AS e2 FROM ({regs}) GROUP BY ALL"
    est = " ".join(f"WHEN m = {m} THEN {hll_formula(m)}" for m in ms)
    return f"SELECT rate, run, m, l, ns, e1, e2, CASE {est} END AS ns_hat FROM ({sums})"


def run_m1(x: str, rates: list[float], ms: list[int], n: int) -> str:
    values = f"SELECT rate, run, element, count(*) AS k FROM ({runs(x, rates, n)}) GROUP BY ALL"
    return f"SELECT *, ns_hat AS n_naive, ns_hat / nullif(1 - CASE WHEN rate = 1 THEN 0 ELSE e1 / l END, 0) AS n_hat FROM ({run_hll(values, ms)})"


def run_m2(x: str, rates: list[float], splits: list[tuple[int, int]], n: int, mode: str) -> str:
    y = runs(x, rates, n)
    values = f"SELECT rate, run, element, count(*) AS k FROM ({y}) GROUP BY ALL"
    us = sorted({u for _, u in splits})
    order = "vh, oh" if mode == "value_hash" else "oh, vh"
    hashed = f"SELECT rate, run, element, {h60(chr(39).join(['element || ', '|v', ' || run']))} AS vh, {h60(chr(39).join(['occ || ', '|u', ' || run']))} AS oh FROM ({y})"
    sub = f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY rate, run ORDER BY {order}) AS j FROM ({hashed})) JOIN (SELECT unnest({us}) AS u) ON j <= u"
    per = f"SELECT rate, run, u, element, count(*) AS c FROM ({sub}) GROUP BY ALL"
    if mode == "in_sample":
        per = f"SELECT p.*, CASE WHEN v.k = 1 THEN c ELSE 0 END AS hit FROM ({per}) p JOIN ({values}) v USING (rate, run, element)"
    else:
        per = f"SELECT *, CASE WHEN c = 1 THEN 1 ELSE 0 END AS hit FROM ({per})"
    probes = f"SELECT rate, run, u, sum(hit) / sum(c) AS p0_hat FROM ({per}) GROUP BY ALL"
    pairs = ", ".join(f"({m}, {u})" for m, u in splits)
    return f"SELECT *, ns_hat / nullif(1 - p0_hat, 0) AS n_hat FROM ({run_hll(values, sorted({m for m, _ in splits}))}) JOIN ({probes}) USING (rate, run) WHERE (m, u) IN ({pairs})"


def accuracy(est: str, n: str, config: str, column: str = "n_hat") -> str:
    return (f"SELECT {config}, round(avg({column} / n) - 1, 6) AS bias, round(abs(avg({column} / n) - 1), 6) AS abs_bias, round(var_samp({column} / n), 6) AS variance, count({column}) AS runs, round(avg(l), 6) AS mean_l "
            f"FROM ({est}), (SELECT CAST(count(DISTINCT element) AS DOUBLE) AS n FROM ({n})) GROUP BY ALL")


def moments_of(freqs: str, rate: float, form: str = "exact") -> str:
    none = f"exp(-{rate!r} * f)" if form == "exp" else f"pow({1 - rate!r}, f)"
    once = f"{rate!r} * f * exp(-{rate!r} * f)" if form == "exp" else f"f * {rate!r} * pow({1 - rate!r}, f - 1)"
    return (f"SELECT count(*) AS n, CAST(sum(f) AS BIGINT) AS length, avg({none}) AS p0, avg({once}) AS p1, sum(f * {none}) / sum(f) AS p0_mass, sum(f * {once}) / sum(f) AS p1_mass, "
            f"sum({rate!r} * f * (1 - {rate!r}) + {rate!r} * f * {rate!r} * f) / ({rate!r} * sum(f)) AS square FROM ({freqs})")


def moments(x: str, rate: float) -> str:
    return (f"SELECT count(*) AS n, CAST(sum(f) AS BIGINT) AS length, avg(pow({1 - rate!r}, f)) AS p0, avg(f * {rate!r} * pow({1 - rate!r}, f - 1)) AS p1, "
            f"sum(f * pow({1 - rate!r}, f)) / sum(f) AS p0_mass, sum(f * f * {rate!r} * pow({1 - rate!r}, f - 1)) / sum(f) AS p1_mass FROM ({counts(x)})")
