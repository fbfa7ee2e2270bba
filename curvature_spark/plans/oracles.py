"""DuckDB SQL for whole training runs in three dimensions, built round by round.

Every round is a chain of materialised common table expressions: oracles per client by aggregation, the
difference to the shift in long form (client, position, multiplicity, value), the compressor by ranking, the new
shifts, the means, and a 3 x 3 solve by cofactors. Nothing here is shared with the engine but the portable
draw, so equal results check the engine's mathematics.
"""

from __future__ import annotations

from ..functions.prng import draw_sql

D, W, LAM = 3, 6, 1e-3
#: Packed positions (column by column) as (row, column).
ENTRIES = [(0, 0), (0, 1), (1, 1), (0, 2), (1, 2), (2, 2)]
MULT = [1 if i == j else 2 for i, j in ENTRIES]

LINE_KEY = (
    "concat_ws(':', CAST(l_orderkey AS VARCHAR), CAST(l_linenumber AS VARCHAR), CAST(l_partkey AS VARCHAR), "
    "CAST(l_suppkey AS VARCHAR), CAST(CAST(round(l_extendedprice * 100) AS BIGINT) AS VARCHAR))"
)
TINY = f"""data AS MATERIALIZED (
  SELECT {draw_sql("7", "k")} % 5 AS client, y * a1 AS z1, y * a2 AS z2, y AS z3
  FROM (SELECT {LINE_KEY} AS k, CASE WHEN l_returnflag = 'R' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y, l_discount * 10 AS a1, l_tax * 12.5 AS a2 FROM lineitem)
)"""


def solve3(a: list[str], b: list[str]) -> list[str]:
    """x of A x = b for a packed symmetric A given as six SQL expressions."""
    m = {(i, j): a[ENTRIES.index((min(i, j), max(i, j)))] for i in range(3) for j in range(3)}

    def minor(i, j):
        r, c = [k for k in range(3) if k != i], [k for k in range(3) if k != j]
        return f"({m[r[0], c[0]]} * {m[r[1], c[1]]} - {m[r[0], c[1]]} * {m[r[1], c[0]]})"

    det = f"({m[0, 0]} * {minor(0, 0)} - {m[0, 1]} * {minor(0, 1)} + {m[0, 2]} * {minor(0, 2)})"
    return ["(" + " + ".join(f"({'-' if (i + j) % 2 else ''}{minor(j, i)}) * {b[j]}" for j in range(3)) + f") / {det}" for i in range(3)]


def oracle_ctes(k: int, where: str = "") -> list[str]:
    """o{k}: per client value, gradient g1..g3 and Hessian h0..h5 at x{k}; d{k}: its difference to the shift in long form."""
    m = "(z1 * x1 + z2 * x2 + z3 * x3)"
    hess = ", ".join(f"avg(s * (1 - s) * z{i + 1} * z{j + 1}) + {LAM if i == j else 0.0} AS h{p}" for p, (i, j) in enumerate(ENTRIES))
    grads = ", ".join(f"avg(-s * z{i + 1}) + {LAM} * any_value(x{i + 1}) AS g{i + 1}" for i in range(3))
    rows = ", ".join(f"{{'pos': {p}, 'm': {MULT[p]}, 'h': h{p}}}" for p in range(W))
    return [
        f"""o{k} AS MATERIALIZED (
  SELECT client, avg(greatest(-m, 0) + ln(1 + exp(-abs(m)))) + {LAM / 2} * any_value(x1 * x1 + x2 * x2 + x3 * x3) AS f, {grads}, {hess}
  FROM (SELECT *, {m} AS m, 1 / (1 + exp({m})) AS s FROM data, x{k}{where}) GROUP BY client
)""",
        f"""d{k} AS MATERIALIZED (
  SELECT e.client, e.r.pos AS pos, e.r.m AS m, e.r.h AS hess, t.h AS shift, e.r.h - t.h AS v
  FROM (SELECT client, unnest([{rows}]) AS r FROM o{k}) e JOIN t{k} t ON t.client = e.client AND t.pos = e.r.pos
)""",
    ]


def compress_cte(k: int, kind: str, size: int, seed: int = 7) -> str:
    """c{k}: client, pos, sent."""
    step = str(k)
    rank = f"row_number() OVER (PARTITION BY client ORDER BY round(abs(v) * sqrt(m), 12) DESC, pos)"
    if kind == "identity":
        body = f"SELECT client, pos, v AS sent FROM d{k}"
    elif kind == "topk":
        body = f"SELECT client, pos, v AS sent FROM (SELECT *, {rank} AS r FROM d{k}) WHERE r <= {size}"
    elif kind == "randk":
        body = f"SELECT client, pos, v * {W / size} AS sent FROM (SELECT *, row_number() OVER (PARTITION BY client ORDER BY {draw_sql(str(seed), step, 'client', 'pos')}, pos) AS r FROM d{k}) WHERE r <= {size}"
    elif kind == "windowk":
        body = f"SELECT client, pos, v * {W / size} AS sent FROM d{k} WHERE (pos - {draw_sql(str(seed), step, 'client')} % {W} + {W}) % {W} < {size}"
    elif kind == "tight":
        body = f"""SELECT client, pos, v AS sent FROM (
    SELECT *, min(CASE WHEN upto / total >= {size / W} - 1e-15 THEN r END) OVER (PARTITION BY client) AS least FROM (
      SELECT *, sum(m * v * v) OVER (PARTITION BY client ORDER BY r ROWS UNBOUNDED PRECEDING) AS upto, sum(m * v * v) OVER (PARTITION BY client) AS total
      FROM (SELECT *, {rank} AS r FROM d{k}) WHERE true) WHERE total > 0
  ) p JOIN (
    SELECT client AS c2, least AS k2, (reach - {size / W}) / (reach - prev) AS chance FROM (
      SELECT client, least, max(CASE WHEN r = least THEN upto / total END) AS reach, coalesce(max(CASE WHEN r = least - 1 THEN upto / total END), 0) AS prev
      FROM (SELECT *, min(CASE WHEN upto / total >= {size / W} - 1e-15 THEN r END) OVER (PARTITION BY client) AS least FROM (
        SELECT *, sum(m * v * v) OVER (PARTITION BY client ORDER BY r ROWS UNBOUNDED PRECEDING) AS upto, sum(m * v * v) OVER (PARTITION BY client) AS total
        FROM (SELECT *, {rank} AS r FROM d{k})) WHERE total > 0) GROUP BY client, least)
  ) q ON p.client = q.c2 WHERE p.r <= q.k2 - CASE WHEN {draw_sql(str(seed), step, 'client')} / 4294967296.0 < chance THEN 1 ELSE 0 END"""
    elif kind == "natural":
        up = f"CASE WHEN {draw_sql(str(seed), step, 'client', 'pos')} / 4294967296.0 < abs(v) / pow(2, e) - 1 THEN 1 ELSE 0 END"
        body = f"SELECT client, pos, CASE WHEN v = 0 THEN 0 ELSE sign(v) * pow(2, e + {up}) END AS sent FROM (SELECT *, CASE WHEN v = 0 THEN 0 ELSE floor(log2(abs(v))) END AS e FROM d{k})"
    else:
        raise KeyError(kind)
    return f"c{k} AS MATERIALIZED ({body})"


def shifts_run(kind: str, size: int, rounds: int, option: str = "shift", init: str = "zero", alpha: float = 1.0, line_search: tuple[float, float] | None = None, data: str = TINY) -> str:
    """Rows round, x1, x2, x3, f, grad_norm (6 decimals) of a run in which every client takes part."""
    ctes = [data, "x0 AS (SELECT 0.0::DOUBLE AS x1, 0.0::DOUBLE AS x2, 0.0::DOUBLE AS x3)"]
    if init == "zero":
        ctes.append(f"t0 AS MATERIALIZED (SELECT client, unnest(range({W})) AS pos, 0.0::DOUBLE AS h FROM (SELECT DISTINCT client FROM data))")
    else:
        ctes.append("u0 AS MATERIALIZED (" + oracle_ctes(0)[0].split("(", 1)[1].rsplit(")", 1)[0] + ")")
        ctes.append("t0 AS MATERIALIZED (SELECT client, r.pos AS pos, r.h AS h FROM (SELECT client, unnest([" + ", ".join(f"{{'pos': {p}, 'h': h{p}}}" for p in range(W)) + "]) AS r FROM u0))")
    for k in range(rounds):
        ctes += oracle_ctes(k)
        ctes.append(compress_cte(k, kind, size))
        ctes.append(f"t{k + 1} AS MATERIALIZED (SELECT d.client, d.pos, d.shift + {alpha} * coalesce(c.sent, 0) AS h FROM d{k} d LEFT JOIN c{k} c ON c.client = d.client AND c.pos = d.pos)")
        ctes.append(f"l{k} AS MATERIALIZED (SELECT avg(l) AS l FROM (SELECT client, sqrt(sum(m * v * v)) AS l FROM d{k} GROUP BY client))")
        means = ", ".join(f"avg(g{i}) AS g{i}" for i in (1, 2, 3))
        pos = ", ".join(f"(SELECT avg(h) FROM t{k} WHERE pos = {p}) AS h{p}" for p in range(W))
        ctes.append(f"a{k} AS MATERIALIZED (SELECT avg(f) AS f, {means}, (SELECT l FROM l{k}) AS l, {pos} FROM o{k})")
        diag = [f"(h{p} + {'l' if option == 'shift' and i == j else '0'})" for p, (i, j) in enumerate(ENTRIES)]
        p = solve3(diag, ["g1", "g2", "g3"])
        ctes.append(f"p{k} AS MATERIALIZED (SELECT x.*, a.f, a.g1, a.g2, a.g3, -({p[0]}) AS p1, -({p[1]}) AS p2, -({p[2]}) AS p3 FROM a{k} a, x{k} x)")
        if line_search:
            c, shrink = line_search
            m = "(z1 * (x1 + t * p1) + z2 * (x2 + t * p2) + z3 * (x3 + t * p3))"
            ctes.append(
                f"""v{k} AS MATERIALIZED (
  SELECT s, t, avg(f) AS value FROM (
    SELECT client, s, t, avg(greatest(-{m}, 0) + ln(1 + exp(-abs({m})))) + {LAM / 2} * any_value(pow(x1 + t * p1, 2) + pow(x2 + t * p2, 2) + pow(x3 + t * p3, 2)) AS f
    FROM data, p{k}, (SELECT s, pow({shrink}, s) AS t FROM range(6) r(s)) GROUP BY client, s, t) GROUP BY s, t
), s{k} AS MATERIALIZED (SELECT min(s) AS s, pow({shrink}, min(s)) AS t FROM v{k}, p{k} WHERE value <= f + {c} * t * (g1 * p1 + g2 * p2 + g3 * p3))"""
            )
            ctes.append(f"x{k + 1} AS MATERIALIZED (SELECT x1 + t * p1 AS x1, x2 + t * p2 AS x2, x3 + t * p3 AS x3 FROM p{k}, s{k})")
        else:
            ctes.append(f"x{k + 1} AS MATERIALIZED (SELECT x1 + p1 AS x1, x2 + p2 AS x2, x3 + p3 AS x3 FROM p{k})")
    rows = " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS round, x1, x2, x3, f, sqrt(g1 * g1 + g2 * g2 + g3 * g3) AS grad_norm FROM p{k}" for k in range(rounds))
    rounded = ", ".join(f"round({c}, 6) + 0.0 AS {c}" for c in ("x1", "x2", "x3", "f", "grad_norm"))
    return "WITH " + ",\n".join(ctes) + f"\nSELECT round, {rounded} FROM ({rows})"


def partial_run(size: int, rounds: int, tau: int, seed: int = 7, clients: int = 5, data: str = TINY) -> str:
    """Rows round, x1, x2, x3, l of a run with tau clients a round, top-k messages and Hessians at 0 as first shifts."""
    entries = ", ".join(f"{{'pos': {p}, 'm': {MULT[p]}, 'h': h{p}}}" for p in range(W))
    ctes = [data, "x0 AS (SELECT 0.0::DOUBLE AS x1, 0.0::DOUBLE AS x2, 0.0::DOUBLE AS x3)"]
    ctes.append("u0 AS MATERIALIZED (" + oracle_ctes(0)[0].split("(", 1)[1].rsplit(")", 1)[0] + ")")
    ctes.append(f"t0 AS MATERIALIZED (SELECT client, r.pos AS pos, r.h AS h FROM (SELECT client, unnest([{entries}]) AS r FROM u0))")
    # Per client: error norm l and corrected gradient q1..q3; at x = 0 that is minus the gradient.
    ctes.append("y0 AS MATERIALIZED (SELECT client, 0.0::DOUBLE AS l, -g1 AS q1, -g2 AS q2, -g3 AS q3 FROM u0)")
    for k in range(rounds):
        pos = ", ".join(f"(SELECT avg(h) FROM t{k} WHERE pos = {p}) AS h{p}" for p in range(W))
        ctes.append(f"a{k} AS MATERIALIZED (SELECT avg(l) AS l, avg(q1) AS q1, avg(q2) AS q2, avg(q3) AS q3, {pos} FROM y{k})")
        s = solve3([f"(h{p} + {'l' if i == j else '0'})" for p, (i, j) in enumerate(ENTRIES)], ["q1", "q2", "q3"])
        ctes.append(f"w{k} AS MATERIALIZED (SELECT {s[0]} AS x1, {s[1]} AS x2, {s[2]} AS x3, l FROM a{k})")
        ctes.append(f"n{k} AS MATERIALIZED (SELECT c AS client FROM (SELECT c, row_number() OVER (ORDER BY {draw_sql(str(seed), str(k), 'c')}, c) AS r FROM range({clients}) t(c)) WHERE r <= {tau})")
        made = [c.replace(f"data, x{k}", f"data, w{k}") for c in oracle_ctes(k, f" WHERE client IN (SELECT client FROM n{k})")]
        ctes += made
        ctes.append(compress_cte(k, "topk", size))
        ctes.append(
            f"""e{k} AS MATERIALIZED (SELECT d.client, d.pos, d.m, d.hess, d.shift + coalesce(c.sent, 0) AS h FROM d{k} d LEFT JOIN c{k} c ON c.client = d.client AND c.pos = d.pos),
b{k} AS MATERIALIZED (SELECT client, sqrt(sum(m * pow(h - hess, 2))) AS l, {", ".join(f"max(CASE WHEN pos = {p} THEN h END) AS h{p}" for p in range(W))} FROM e{k} GROUP BY client)"""
        )
        full = [[ENTRIES.index((min(i, j), max(i, j))) for j in range(3)] for i in range(3)]
        q = ", ".join(f"{' + '.join(f'b.h{full[i][j]} * w.x{j + 1}' for j in range(3))} + b.l * w.x{i + 1} - o.g{i + 1} AS q{i + 1}" for i in range(3))
        ctes.append(f"y{k + 1} AS MATERIALIZED (SELECT b.client, b.l, {q} FROM b{k} b JOIN o{k} o ON b.client = o.client, w{k} w UNION ALL SELECT * FROM y{k} WHERE client NOT IN (SELECT client FROM n{k}))")
        ctes.append(f"t{k + 1} AS MATERIALIZED (SELECT client, pos, h FROM e{k} UNION ALL SELECT * FROM t{k} WHERE client NOT IN (SELECT client FROM n{k}))")
    rows = " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS round, x1, x2, x3 FROM w{k}" for k in range(rounds))
    return "WITH " + ",\n".join(ctes) + f"\nSELECT round, {', '.join(f'round({c}, 6) + 0.0 AS {c}' for c in ('x1', 'x2', 'x3'))} FROM ({rows})"


#: Long form (sample_key, y, j, v) of the wide workloads; y is the label, j counts features from 1, v is the feature.
LONG = {
    "dense": """v AS (SELECT CAST(vec_id AS VARCHAR) AS sample_key, CASE WHEN label = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings WHERE embedding IS NOT NULL),
cells AS (SELECT sample_key, y, unnest(range(1, 70)) AS j, unnest(list_concat(e, [sqrt(list_sum(list_transform(e, lambda x: x * x))), list_max(e), list_min(e), list_sum(list_transform(e, lambda x: abs(x))) / 8, 1.0])) AS v FROM v)""",
    "sparse": """t AS (SELECT doc_id, lang, list_distinct(list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\\s+'), lambda x: x <> '')) AS w FROM documents),
cells AS (
  SELECT CAST(doc_id AS VARCHAR) AS sample_key, CASE WHEN lang = 'en' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y,
    1 + unnest(list_append(list_distinct(list_transform(w, lambda x: CAST('0x' || substr(md5(x), 1, 8) AS BIGINT) % 300)), 300)) AS j, 1.0::DOUBLE AS v FROM t
)""",
}


def minimiser(cells: str, clients: int, d: int, largest: float, rounds: int, equal: bool = False, lam: float = LAM) -> str:
    """CTE `least(j, x, f)`: coordinates and value of the one minimiser of the mean of the clients' functions.

    Accelerated gradient steps as a recursion over vectors, from the largest curvature; nothing of the engine's methods. With
    `equal` clients are ranks of the draw in equal parts, the remainder dropped; otherwise the draw modulo `clients`.
    """
    ratio = (largest / lam) ** 0.5
    momentum = round((ratio - 1) / (ratio + 1), 6)
    draw = draw_sql("7", "sample_key")
    if equal:
        dealt = f"SELECT sample_key, y, n // per AS client FROM (SELECT sample_key, y, row_number() OVER (ORDER BY {draw}, sample_key) - 1 AS n, count(*) OVER () // {clients} AS per FROM k) WHERE n < per * {clients}"
    else:
        dealt = f"SELECT sample_key, y, {draw} % {clients} AS client FROM k"
    zeros = f"list_transform(range({d}), lambda i: 0.0::DOUBLE)"
    margins = f"SELECT i, sum(v * p[j]) AS m FROM lines, walk WHERE k < {rounds} GROUP BY i"
    return f"""WITH RECURSIVE {cells},
k AS MATERIALIZED (SELECT DISTINCT sample_key, y FROM cells), dealt AS MATERIALIZED ({dealt}),
r AS MATERIALIZED (SELECT sample_key, row_number() OVER () AS i, 1.0::DOUBLE / count(*) OVER (PARTITION BY client) / (SELECT count(DISTINCT client) FROM dealt) AS q FROM dealt),
lines AS MATERIALIZED (SELECT i, q, CAST(j AS INTEGER) AS j, y * v AS v FROM cells JOIN r USING (sample_key)),
walk AS (
  SELECT 0 AS k, {zeros} AS x, {zeros} AS p
  UNION ALL
  SELECT k + 1, nx, list_transform(range(1, {d} + 1), lambda i: nx[i] + {momentum} * (nx[i] - x[i])) FROM (
    SELECT any_value(k) AS k, any_value(x) AS x, list(p[j] - (coalesce(g, 0) + {lam} * p[j]) / {largest} ORDER BY j) AS nx
    FROM (SELECT * FROM walk WHERE k < {rounds}), (SELECT unnest(range(1, {d} + 1)) AS j) LEFT JOIN (
      SELECT j, sum(-q * v / (1 + exp(m))) AS g FROM lines JOIN ({margins}) USING (i) GROUP BY j) USING (j)
    HAVING count(*) > 0)
),
last AS MATERIALIZED (SELECT x FROM walk WHERE k = {rounds}),
least AS (
  SELECT unnest(range(1, {d} + 1)) AS j, unnest(x) AS x,
    (SELECT sum(q * (greatest(-m, 0) + ln(1 + exp(-abs(m))))) FROM (SELECT i, any_value(q) AS q, sum(v * x[j]) AS m FROM lines, last GROUP BY i)) + {lam / 2} * list_sum(list_transform(x, lambda a: a * a)) AS f FROM last
)
"""
