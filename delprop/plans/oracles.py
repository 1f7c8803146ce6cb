"""Independent SQL for the registered queries: recursive queries over list state, run by DuckDB on the same tables."""

from __future__ import annotations

from delprop.functions.hashing import uniform_sql as u

ID = (
    "('0x' || substr(md5(concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity::BIGINT, "
    "round(l_extendedprice * 100)::BIGINT, epoch(l_shipdate)::BIGINT)), 1, 15))::BIGINT"
)
SMALL = ["(l_quantity - 25.0) / 15.0", "(l_discount - 0.05) / 0.03", "(l_tax - 0.04) / 0.03"]


def teacher(m: int, cls: int = 0) -> str:
    return "[" + ", ".join(f"2 * {u(repr(str(j)), repr(f'teacher{cls}'))} - 1" for j in range(m)) + "]"


def clipped(key: str, salt: str) -> str:
    return f"least(greatest({u(key, repr(salt))}, 1e-9), 1 - 1e-9)"


def label(kind: str, m: int, q: int = 1, key: str = "sample_id") -> str:
    if kind == "linear":
        gauss = " + ".join(u(key, f"'n{k}'") for k in range(12))
        return f"list_dot_product(x, {teacher(m)}) + 0.1 * ({gauss} - 6.0)"
    if kind == "binary":
        p = clipped(key, "logit")
        return f"CASE WHEN list_dot_product(x, {teacher(m)}) + ln({p} / (1.0 - {p})) >= 0 THEN 1.0 ELSE -1.0 END"
    scores = ", ".join(f"list_dot_product(x, {teacher(m, c)}) - ln(-ln({clipped(key, f'gumbel{c}')}))" for c in range(q))
    return f"(list_position([{scores}], list_max([{scores}])) - 1)::DOUBLE"


def small(columns: int = 3, kind: str = "linear", q: int = 1) -> str:
    """CTE ``fx``: sample_id, x, y, is_valid of the small fixture."""
    x = ", ".join([*SMALL[:columns], "1.0"])
    return f"""raw AS MATERIALIZED (SELECT {ID} AS sample_id, [{x}]::DOUBLE[] AS x FROM lineitem),
fx AS MATERIALIZED (SELECT sample_id, x, ({label(kind, columns + 1, q)})::DOUBLE AS y, {u('sample_id', "'split'")} < 0.1 AS is_valid FROM raw)"""


def blocked(schedule: str, tau: int, parts: int | None, source: str = "fx") -> str:
    """CTEs ``size`` (n, k) and ``bl`` (all rows of ``fx`` with block b) and the number of blocks as ``nb``; a batch is one of ``parts`` equal parts of the rows."""
    k = f"ceil(count(*) / ceil(count(*) / {parts}.0))::INT" if parts else "1"
    size = f"size AS MATERIALIZED (SELECT count(*) AS n, {k} AS k FROM fx)"
    rows = {
        "full": f"SELECT f.*, 0 AS b FROM {source} f",
        "cyclic": f"SELECT f.*, floor({u('sample_id', repr('batch'))} * k)::INT AS b FROM {source} f, size",
        "reshuffle": f"SELECT f.*, (p * k + floor({u('sample_id', chr(39) + 'batch' + chr(39) + ' || p')} * k))::INT AS b FROM {source} f, size, range({tau}) t(p) WHERE p * k < {tau}",
        "sampled": f"SELECT f.*, p::INT AS b FROM {source} f, size, range({tau}) t(p) WHERE {u('sample_id', chr(39) + 'batch' + chr(39) + ' || p')} < ceil(n / {parts}.0) / n",
        "single": f"SELECT * FROM (SELECT f.*, (row_number() OVER (ORDER BY {u('sample_id', repr('batch'))}, sample_id) - 1)::INT AS b FROM {source} f) WHERE b < {tau}",
    }[schedule]
    nb = {"full": "1", "cyclic": "(SELECT k FROM size)", "reshuffle": "1000000", "sampled": "1000000", "single": f"least({tau}, (SELECT n FROM size))"}[schedule]
    return f"{size}, bl AS MATERIALIZED ({rows}), blocks_of AS MATERIALIZED (SELECT {nb} AS nb)"


def grams(source: str, m: int) -> str:
    """CTE ``gs`` (b, cnt, g, n): Gram rows and cross sums of ``source`` by b."""
    return f"""cell AS MATERIALIZED (SELECT b, i, j, sum(x[i] * x[j]) AS v FROM {source}, range(1, {m + 1}) s(i), range(1, {m + 1}) t(j) GROUP BY b, i, j),
grow AS (SELECT b, i, list(v ORDER BY j) AS r FROM cell GROUP BY b, i),
gmat AS (SELECT b, list(r ORDER BY i) AS g FROM grow GROUP BY b),
cr AS (SELECT b, i, sum(x[i] * y) AS v FROM {source}, range(1, {m + 1}) s(i) GROUP BY b, i),
crow AS (SELECT b, list(v ORDER BY i) AS n FROM cr GROUP BY b),
cn AS (SELECT b, count(*) AS cnt FROM {source} GROUP BY b),
gs AS MATERIALIZED (SELECT gmat.b, cnt, g, n FROM gmat JOIN crow ON gmat.b = crow.b JOIN cn ON gmat.b = cn.b)"""


def linear(schedule: str, tau: int, parts: int | None, eta: float | str, lam: float, columns: int = 3, keep: str | None = None, digits: int = 6, tail: str | None = None) -> str:
    """Linear descent on the rows that ``keep`` admits, blocks chosen before; ``eta`` may be an expression of the iteration ``t``."""
    m = columns + 1
    shrink, twice = (f"(1 - ({eta}) * {lam})", f"2 * ({eta})") if isinstance(eta, str) else (1 - eta * lam, 2 * eta)
    kept = f"kept AS MATERIALIZED (SELECT * FROM bl WHERE {keep or 'true'})"
    zero = "[" + ", ".join(["0.0"] * m) + "]::DOUBLE[]"
    step = f"""CASE WHEN cnt IS NULL THEN [{shrink} * w[i] for i in range(1, {m + 1})]
      ELSE [{shrink} * w[i] - {twice} / cnt * (list_dot_product(g[i], w) - n[i]) for i in range(1, {m + 1})] END"""
    final = tail or f"SELECT pos::INT AS pos, round(w[pos + 1], {digits}) + 0.0 AS value FROM it, range({m}) p(pos) WHERE t = {tau}"
    return f"""WITH RECURSIVE {small(columns, 'linear')}, {blocked(schedule, tau, parts)}, {kept}, {grams('kept', m)},
it(t, w) AS (
  SELECT 0, {zero}
  UNION ALL
  SELECT t + 1, {step} FROM it CROSS JOIN blocks_of LEFT JOIN gs ON gs.b = it.t % nb WHERE t < {tau}
)
{final}"""


def piece(z: str, h: str = "4e-5") -> tuple[str, str]:
    """Slope and offset of the interpolant at margin ``z``."""
    low = f"(floor(({z} + 20) / {h}) * {h} - 20)"
    f = lambda x: f"(1 / (1 + exp({x})))"
    slope = f"(({f(low + ' + ' + h)} - {f(low)}) / {h})"
    return f"CASE WHEN abs({z}) < 20 THEN {slope} ELSE 0.0 END", f"CASE WHEN abs({z}) < 20 THEN {f(low)} - {slope} * {low} ELSE {f(f'greatest(least({z}, 20.0), -20.0)')} END"


def binary(schedule: str, tau: int, parts: int | None, eta: float, lam: float, columns: int = 2, keep: str | None = None, linearized: bool = False, replay: bool = False, tail: str | None = None) -> str:
    """Binary descent; ``linearized`` takes pieces at the current parameters, ``replay`` at the full run's."""
    m = columns + 1
    zero = "[" + ", ".join(["0.0"] * m) + "]::DOUBLE[]"

    def recursion(name: str, rows: str, factor: str, path: str = "") -> str:
        sums = ", ".join(f"{1 - eta * lam} * any_value({name}.w)[{i}] + {eta} / count(*) * sum({factor} * y * x[{i}])" for i in range(1, m + 1))
        return f"""{name}(t, w) AS (
  SELECT 0, {zero}
  UNION ALL
  SELECT {name}.t + 1, [{sums}] FROM {name} CROSS JOIN blocks_of JOIN {rows} ON {rows}.b = {name}.t % nb {path} WHERE {name}.t < {tau} GROUP BY {name}.t
)"""

    exact = lambda name: f"(1 / (1 + exp(y * list_dot_product(x, {name}.w))))"

    def chord(at: str, now: str) -> str:
        a, b = piece(f"(y * list_dot_product(x, {at}.w))")
        return f"(({a}) * (y * list_dot_product(x, {now}.w)) + ({b}))"

    kept = f"kept AS MATERIALIZED (SELECT * FROM bl WHERE {keep or 'true'})"
    if replay:
        runs = recursion("full_run", "bl", exact("full_run")) + ", " + recursion("it", "kept", chord("path", "it"), "JOIN full_run path ON path.t = it.t")
    else:
        runs = recursion("it", "kept", chord("it", "it") if linearized else exact("it"))
    final = tail or f"SELECT pos::INT AS pos, round(w[pos + 1], 6) + 0.0 AS value FROM it, range({m}) p(pos) WHERE t = {tau}"
    return f"WITH RECURSIVE {small(columns, 'binary')}, {blocked(schedule, tau, parts)}, {kept}, {runs}\n{final}"


def softmax(tau: int, eta: float, lam: float, columns: int = 2, q: int = 3, keep: str | None = None, replay: bool = False, digits: int = 6, extra: str = "") -> str:
    """Full-batch softmax descent; ``replay`` takes tangents at the full run's parameters."""
    m = columns + 1
    zero = "[" + ", ".join(["0.0"] * (m * q)) + "]::DOUBLE[]"

    def logits(w: str) -> str:
        return "[" + ", ".join(f"list_dot_product(x, {w}[{c * m + 1}:{(c + 1) * m}])" for c in range(q)) + "]"

    def recursion(name: str, rows: str, path: str | None = None) -> str:
        at = path or name
        join = f"JOIN {path} ON {path}.t = {name}.t" if path else ""
        inner = f"SELECT {name}.t, {name}.w, x, y, {logits(f'{at}.w')} AS l0, {logits(f'{name}.w')} AS l FROM {name} CROSS JOIN {rows} {join} WHERE {name}.t < {tau}"
        p = [f"exp(l0[{c}]) / (" + " + ".join(f"exp(l0[{d}])" for d in range(1, q + 1)) + ")" for c in range(1, q + 1)]
        middle = f"SELECT t, w, x, y, l0, l, [{', '.join(p)}] AS p FROM ({inner})"
        moved = " + ".join(f"p[{d}] * (l[{d}] - l0[{d}])" for d in range(1, q + 1))
        sums = ", ".join(
            f"{1 - eta * lam} * any_value(w)[{c * m + i}] - {eta} / count(*) * sum((p[{c + 1}] + p[{c + 1}] * (l[{c + 1}] - l0[{c + 1}] - ({moved})) - CASE WHEN y = {c} THEN 1 ELSE 0 END) * x[{i}])" for c in range(q) for i in range(1, m + 1)
        )
        return f"""{name}(t, w) AS (
  SELECT 0, {zero}
  UNION ALL
  SELECT t + 1, [{sums}] FROM ({middle}) GROUP BY t
)"""

    kept = f"kept AS MATERIALIZED (SELECT * FROM fx WHERE {keep or 'true'})"
    runs = f"{recursion('full_run', 'fx')}, {recursion('it', 'kept', 'full_run')}" if replay else recursion("it", "kept")
    final = f"SELECT pos::INT AS pos, round(w[pos + 1], {digits}) + 0.0 AS value{extra} FROM it, range({m * q}) p(pos) WHERE t = {tau}"
    return f"WITH RECURSIVE {small(columns, 'softmax', q)}, {kept}, {runs}\n{final}"


def sparse(tau: int, parts: int, eta: float, lam: float, rate: float, buckets: int = 47236) -> str:
    """Sparse binary runs in the dual: a model is a list of one factor a sample, and margins come from the samples' inner products."""
    f = lambda z: f"(1 / (1 + exp({z})))"

    def recursion(name: str, kept: str, path: str | None = None) -> str:
        z, at = f"list_dot_product(k[i], {name}.al)", f"(y[i] * list_dot_product(k[i], {path}.al))" if path else ""
        factor = f"({piece(at)[0]}) * {z} + ({piece(at)[1]}) * y[i]" if path else f"y[i] * {f(f'(y[i] * {z})')}"
        held = f"len(list_filter(range(1, n + 1), lambda j: blk[j] = {name}.t % nb AND {kept}[j]))"
        join = f"JOIN {path} ON {path}.t = {name}.t" if path else ""
        return f"""{name}(t, al) AS (
  SELECT 0, (SELECT list_transform(y, lambda v: 0.0::DOUBLE) FROM d)
  UNION ALL
  SELECT {name}.t + 1, list_transform(range(1, n + 1), lambda i: {1 - eta * lam} * {name}.al[i] + CASE WHEN blk[i] = {name}.t % nb AND {kept}[i] THEN {eta} / {held} * ({factor}) ELSE 0.0 END)
  FROM {name} CROSS JOIN d {join} WHERE {name}.t < {tau}
)"""

    norm = lambda a, b: f"list_dot_product({a}, list_transform(k, lambda r: list_dot_product(r, {b})))"
    return f"""WITH RECURSIVE w AS (SELECT doc_id, quality, unnest(string_split_regex(lower(text), '[^\\p{{L}}]+')) AS word FROM documents JOIN labels USING (doc_id) WHERE {u('doc_id', "'split'")} >= 0.1),
c AS (SELECT doc_id, any_value(quality) AS quality, ('0x' || substr(md5(word), 1, 8))::BIGINT % {buckets} AS ix, count(*)::DOUBLE AS v FROM w WHERE word <> '' GROUP BY doc_id, ix),
docs AS (SELECT doc_id, row_number() OVER (ORDER BY doc_id) AS r, CASE WHEN any_value(quality) = 1 THEN 1.0 ELSE -1.0 END AS y, sqrt(sum(v * v)) AS size FROM c GROUP BY doc_id),
cell AS MATERIALIZED (SELECT r, ix, v / size AS v FROM c JOIN docs USING (doc_id)),
pair AS (SELECT a.r AS i, b.r AS j, sum(a.v * b.v) AS v FROM cell a JOIN cell b ON a.ix = b.ix GROUP BY a.r, b.r),
krow AS (SELECT a.r AS i, list(coalesce(v, 0.0) ORDER BY b.r) AS row FROM docs a CROSS JOIN docs b LEFT JOIN pair p ON p.i = a.r AND p.j = b.r GROUP BY a.r),
sizes AS (SELECT count(*) AS n, ceil(count(*) / ceil(count(*) / {parts}.0))::INT AS nb FROM docs),
rows_ AS (SELECT list(y ORDER BY r) AS y, list(floor({u('doc_id', "'batch'")} * nb)::INT ORDER BY r) AS blk, list({u('doc_id', "'rm'")} >= {rate} ORDER BY r) AS kept, list(true ORDER BY r) AS whole FROM docs, sizes),
d AS MATERIALIZED (SELECT *, (SELECT list(row ORDER BY i) FROM krow) AS k FROM rows_, sizes),
{recursion('full_run', 'whole')},
{recursion('old', 'kept')},
{recursion('it', 'kept', 'full_run')},
last_ AS (SELECT k, n, len(list_filter(kept, lambda v: NOT v)) AS removed, a.al AS w, b.al AS truth, c.al AS new FROM d, full_run a, old b, it c WHERE a.t = {tau} AND b.t = {tau} AND c.t = {tau}),
gaps AS (SELECT *, list_transform(range(1, n + 1), lambda i: new[i] - truth[i]) AS e, list_transform(range(1, n + 1), lambda i: w[i] - truth[i]) AS g FROM last_)
SELECT n::BIGINT AS n, removed::BIGINT AS removed, round(sqrt(greatest({norm('e', 'e')}, 0)), 5) AS distance, round({norm('new', 'truth')} / sqrt({norm('new', 'new')} * {norm('truth', 'truth')}), 5) AS cosine, round(sqrt(greatest({norm('g', 'g')}, 0)), 5) AS stale_distance FROM gaps"""


def gone(rate: float, salt: str = "rm") -> str:
    return f"{u('sample_id', repr(salt))} < {rate}"


STAR = """lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey
  JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey"""


def star_columns() -> list[str]:
    from delprop.sources.features import FIXED

    def z(name: str, value: str | None = None) -> str:
        centre, spread = FIXED[name]
        return f"(({value or name})::DOUBLE - {centre}) / {spread}"

    flag = lambda c, v: f"CASE WHEN {c} = '{v}' THEN 1.0 ELSE 0.0 END"
    return [
        z("l_quantity"), z("l_extendedprice"), z("l_discount"), z("l_tax"), z("l_linenumber"), flag("l_returnflag", "A"), flag("l_returnflag", "R"), flag("l_linestatus", "O"),
        z("ship_year", "year(l_shipdate)"), z("ship_month", "month(l_shipdate)"), z("ship_day", "day(l_shipdate)"), z("p_size"), z("p_retailprice"), z("s_acctbal"), z("o_totalprice"), z("c_acctbal"),
        flag("o_orderstatus", "P"), flag("o_orderstatus", "F"),
    ]


def star54_columns() -> list[str]:
    from delprop.sources.features import BRANDS, FIXED, SEGMENTS, STATUSES, TYPES

    z = [f"(({c})::DOUBLE - {FIXED[c][0]}) / {FIXED[c][1]}" for c in ("l_quantity", "l_discount", "l_tax", "o_totalprice", "p_retailprice", "p_size", "s_acctbal", "c_acctbal", "l_extendedprice")]
    z.append("date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::DOUBLE / 60.0 - 1.0")
    flag = lambda c, v: f"CASE WHEN {c} = '{v}' THEN 1.0 ELSE 0.0 END"
    z += [flag("p_brand", b) for b in BRANDS] + [flag("split_part(p_type, ' ', 1)", t) for t in TYPES] + [flag("c_mktsegment", s) for s in SEGMENTS]
    return z + [flag("substr(o_orderpriority, 1, 1)", str(k)) for k in range(1, 6)] + [flag("o_orderstatus", s) for s in STATUSES]


def star(columns: list[str]) -> str:
    return f"fx AS (SELECT {ID} AS sample_id, [{', '.join(columns)}]::DOUBLE[] AS x FROM {STAR})"


def summary(m: int, source: str = "fx", digits: int = 3) -> str:
    """Per-coordinate count, sum, least and greatest."""
    return f"SELECT (i - 1)::INT AS pos, count(*) AS cnt, round(sum(x[i]), {digits}) + 0.0 AS total, round(min(x[i]), 6) + 0.0 AS low, round(max(x[i]), 6) + 0.0 AS high FROM {source}, range(1, {m + 1}) r(i) GROUP BY i"
