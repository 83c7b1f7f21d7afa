"""Where queries register, and pieces of SQL that several of them share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from ..spec import SketchSpec

QUERIES: dict[str, Callable[..., DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Registers a function of (spark, sf_dir), with the SQL that gives the same rows."""

    def put(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return put


def portable(m: int, b: int | None = 8, seed: int = 0) -> SketchSpec:
    return SketchSpec(m=m, b=b, seed=seed, hash="portable")


# SQL of the portable hash and what is built on it -------------------------------


def bits(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 13))::BIGINT"


def uniform(x: str, j: str, seed: int = 0) -> str:
    return f"(({bits(f"'{seed}:' || {x} || ':' || {j}")} + 0.5) / 4503599627370496.0)"


def route(x: str, m: int, seed: int = 0) -> str:
    return f"({bits(f"'g{seed}:' || {x}")} % {m} + 1)"


def value(x: str, w: str, j: str, seed: int = 0) -> str:
    return f"(-ln({uniform(x, j, seed)}) / {w})"


def bucket(r: str, spec: SketchSpec) -> str:
    y = f"floor(-log2({r}))"
    return f"{y}::INT" if spec.b is None else f"least(greatest({y}, {spec.low}), {spec.high})::INT"


def element(*cols: str) -> str:
    return " || ".join(f"length({c}::VARCHAR) || ':' || {c}::VARCHAR" for c in cols)


PARTS = "SELECT l_partkey::VARCHAR AS x, p_retailprice AS w, l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem JOIN part ON l_partkey = p_partkey"
RATINGS = "SELECT o_custkey AS stream, l_partkey::VARCHAR AS x, max(l_quantity) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL"
VECTORS = "SELECT * FROM (SELECT vec_id AS stream, (unnest(generate_series(1, len(embedding))) - 1)::VARCHAR AS x, unnest(embedding)::DOUBLE AS w FROM embeddings) WHERE w > 0"
VOTES = "SELECT o_orderpriority AS stream, o_custkey::VARCHAR AS x, c_acctbal AS w FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_acctbal > 0"
DAILY = "SELECT strftime(ts, '%Y-%m-%d') AS stream, user_id::VARCHAR AS x, c_acctbal AS w, ts, event_id FROM events JOIN customer ON user_id = c_custkey WHERE c_acctbal > 0"
LINKS = f"SELECT {element('c_nationkey', 's_nationkey')} AS x, 1.0::DOUBLE AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"
TEXTS = "SELECT text AS x, n_chars::DOUBLE AS w FROM documents"
LAWS = {"uniform": uniform("event_id", "1", 7919), "gamma": f"-2.0 * ln({uniform('event_id', '1', 7919)})"}
_DRAW = "1 + sqrt(0.1) * sqrt(-2 * ln({a})) * cos(2 * pi() * {b})"
_DRAWS = [_DRAW.format(a=uniform("event_id", str(2 * k + 1), 7919), b=uniform("event_id", str(2 * k + 2), 7919)) for k in range(8)]
LAWS["gauss"] = "CASE " + " ".join(f"WHEN {x} > 0 THEN {x}" for x in _DRAWS) + " ELSE 1.0 END"
_EDGE = element("o_custkey", "l_suppkey")
EDGES = f"SELECT *, {uniform('x', "'0'", 17)} AS w FROM (SELECT {_EDGE} AS x, l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"
MONITORING = "SELECT event_type AS stream, event_id::VARCHAR AS x, value AS w, ts, event_id FROM events"


def tfidf(docs: str) -> str:
    """SQL of (stream, x, w) from a query of (by, text)."""
    return f"""(WITH d AS ({docs}), t AS (SELECT stream, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS x FROM d), tf AS (SELECT stream, x, count(*) AS tf FROM t GROUP BY ALL),
      df AS (SELECT x, count(*) AS df FROM tf GROUP BY x), n AS (SELECT count(*) AS n FROM d)
      SELECT stream, x, tf * ln(n / df) AS w FROM tf JOIN df USING (x), n WHERE df < n)"""


ENGLISH, OTHER = (tfidf(f"SELECT doc_id AS stream, text FROM documents WHERE lang {sign} 'en'") for sign in ("=", "<>"))
DOCUMENTS = tfidf("SELECT doc_id AS stream, text FROM documents")
CONVERSATIONS = tfidf("SELECT conv_id AS stream, array_to_string(list_sort(list(text)), ' ') AS text FROM conversations GROUP BY conv_id")
PAGES = tfidf("SELECT page_id AS stream, regexp_replace(html, '<[^>]*>', ' ', 'g') AS text FROM pages")


def once(stream: str, by: bool = False) -> str:
    key = "stream, x" if by else "x"
    return f"(SELECT {key}, max(w) AS w FROM ({stream}) GROUP BY {key})"


def dense(stream: str, spec: SketchSpec, by: bool = False) -> str:
    """SQL of (by, j, r)."""
    key = "stream, " if by else ""
    return f"(SELECT {key}j, min({value('x', 'w', 'j', spec.seed)}) AS r FROM {once(stream, by)}, (SELECT unnest(range(1, {spec.m + 1})) AS j) GROUP BY {key}j)"


def integers(stream: str, spec: SketchSpec, by: bool = False) -> str:
    """SQL of (by, j, y) above the lowest value."""
    key = "stream, " if by else ""
    return f"(SELECT {key}j::INT AS j, max({bucket(value('x', 'w', 'j', spec.seed), spec)}) AS y FROM {once(stream, by)}, (SELECT unnest(range(1, {spec.m + 1})) AS j) GROUP BY {key}j HAVING max({bucket(value('x', 'w', 'j', spec.seed), spec)}) > {spec.low})"


def routed(stream: str, spec: SketchSpec, by: bool = False) -> str:
    key = "stream, " if by else ""
    r = value("x", "w", "j", spec.seed)
    return f"(SELECT {key}j::INT AS j, max({bucket(r, spec)}) AS y FROM (SELECT *, {route('x', spec.m, spec.seed)} AS j FROM {once(stream, by)}) GROUP BY {key}j HAVING max({bucket(r, spec)}) > {spec.low})"


def hist(registers: str, spec: SketchSpec, by: str = "") -> str:
    """SQL of (by, y, n), registers without a row at the lowest."""
    k = f"{by}, " if by else ""
    g = f"GROUP BY {by}" if by else ""
    return f"(SELECT {k}y, count(*)::BIGINT AS n FROM {registers} GROUP BY {k}y UNION ALL SELECT {k}{spec.low} AS y, {spec.m} - count(*) AS n FROM {registers} {g} HAVING count(*) < {spec.m})"


def term(kind: str, spec: SketchSpec, c: str = "c") -> str:
    """SQL of one histogram entry's part of the log-likelihood, score or curvature; y and n in scope."""
    a, two = "pow(2.0, -(y + 1))", "pow(2.0, -y)"
    if kind == "loglik":
        low, mid, high = f"-{c} * {a}", f"-{c} * {a} + ln(1 - exp(-{c} * {a}))", f"ln(1 - exp(-{c} * {two}))"
    elif kind == "score":
        low, mid, high = f"-{a}", f"{a} * (1 / (exp({c} * {a}) - 1) - 1)", f"{two} / (exp({c} * {two}) - 1)"
    else:
        low, mid, high = "0", *(f"-{v} * {v} / ((exp({c} * {v}) - 1) * (1 - exp(-{c} * {v})))" for v in (a, two))
    if spec.b is None:
        return f"n * ({mid})"
    return f"n * (CASE WHEN y <= {spec.low} THEN {low} WHEN y >= {spec.high} THEN {high} ELSE {mid} END)"


def start(spec: SketchSpec) -> str:
    return f"(CASE WHEN sum(CASE WHEN y > {spec.low} THEN n ELSE 0 END) < sum(n) THEN sum(CASE WHEN y > {spec.low} THEN n ELSE 0 END) ELSE sum(n) - 1 END / sum(n * pow(2.0, -y)))"


def mle(histogram: str, spec: SketchSpec, by: str = "", steps: int = 25) -> str:
    """SQL of (by, c) by Newton's method, every step a grouped sum."""
    k = f"{by}, " if by else ""
    on = " AND ".join(f"h.{x.strip()} = e.{x.strip()}" for x in by.split(",")) if by else "true"
    keys = ", ".join(f"h.{x.strip()}" for x in by.split(",")) + ", " if by else ""
    parts = [f"h AS MATERIALIZED {histogram}", f"e0 AS MATERIALIZED (SELECT {k}{start(spec)} AS c FROM h {f'GROUP BY {by}' if by else ''})"]
    for i in range(steps):
        parts.append(f"e{i + 1} AS MATERIALIZED (SELECT {keys}any_value(e.c) - sum({term('score', spec, 'e.c')}) / sum({term('curve', spec, 'e.c')}) AS c FROM h JOIN e{i} e ON {on} {f'GROUP BY {keys[:-2]}' if by else ''})")
    return f"(WITH {', '.join(parts)} SELECT {k}c FROM e{steps})"


def routed_estimate(stream: str, spec: SketchSpec, by: bool = False) -> str:
    """SQL of (stream, est): the rate of one register times those that any element reached."""
    key = "stream, " if by else ""
    h = f"(SELECT {key}y, count(*)::BIGINT AS n FROM {routed(stream, spec, by)} GROUP BY {key}y)"
    k = f"(SELECT {key}sum(n) AS k FROM {h} {'GROUP BY stream' if by else ''})"
    return f"(SELECT {key}k * c AS est FROM {mle(h, spec, 'stream' if by else '')} {f'JOIN {k} USING (stream)' if by else f', {k}'})"


def live_steps(stream: str, order: str, spec: SketchSpec, by: str = "", timing: str = "pre", begin: str = "full") -> str:
    """SQL of (by, rise, j, y, before, w, q, est, var and the order's columns): the running estimate's fold, relationally."""
    k = f"{by}, " if by else ""
    part = f"PARTITION BY {by}" if by else ""
    same = f"b.{by} = a.{by} AND " if by else ""
    r = value("x", "w", "j", spec.seed)
    held = "b.rise < a.rise" if timing == "pre" else "b.rise <= a.rise"
    return f"""(WITH z AS (SELECT *, {bucket(r, spec)} AS y FROM (SELECT *, {route('x', spec.m, spec.seed)}::INT AS j FROM ({stream}))),
      u AS (SELECT *, coalesce(max(y) OVER (PARTITION BY {k}j ORDER BY {order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), {spec.low}) AS before FROM z),
      a AS MATERIALIZED (SELECT *, row_number() OVER ({part} ORDER BY {order}) AS rise FROM u WHERE y > before),
      s AS (SELECT {', '.join(f'a.{x}' for x in ([by] if by else []) + ['rise'])}, b.j, max(b.y) AS y FROM a JOIN a b ON {same}{held} GROUP BY ALL),
      q AS (SELECT {k}rise, count(*) AS touched, sum(CASE WHEN s.y < {spec.high} THEN 1 - exp(-a.w * pow(2.0, -(s.y + 1))) ELSE 0 END) AS up FROM s JOIN a USING ({k}rise) GROUP BY ALL),
      p AS (SELECT a.*, (coalesce(up, 0) + ({spec.m} - coalesce(touched, 0)) * {f'(1 - exp(-a.w * pow(2.0, {-(spec.low + 1)})))' if begin == 'full' else '1'}) / {spec.m} AS q FROM a LEFT JOIN q USING ({k}rise))
      SELECT *, sum(w / q) OVER ({part} ORDER BY rise) AS est, sum(w * w * (1 - q) / (q * q)) OVER ({part} ORDER BY rise) AS var FROM p)"""
