"""SQL twins: the same results from Gram matrices and recursive views, for another engine."""

from __future__ import annotations

TOKENS = "regexp_extract_all(lower({0}), '[a-z]+')"
BRAND = "SELECT o_custkey AS r, p_brand AS c, sum(l_quantity) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY ALL"
MONTH = "SELECT strftime(date_trunc('month', l_shipdate), '%Y-%m-%d') AS r, {0} AS c, sum(l_quantity) AS v FROM lineitem GROUP BY ALL"
DAY = "SELECT strftime(ts, '%Y-%m-%d') AS r, user_id AS c, count(*)::DOUBLE AS v FROM events GROUP BY ALL"


def counts(table: str, key: str, text: str, least: int) -> str:
    return f"""SELECT r, c, v FROM (SELECT *, count(*) OVER (PARTITION BY r) AS df FROM (SELECT c, r, count(*)::DOUBLE AS v FROM (SELECT {key} AS c, unnest({TOKENS.format(text)}) AS r FROM {table}) GROUP BY ALL)) WHERE df >= {least}"""


DOC = counts("documents", "doc_id", "text", 50)
PAGE = counts("pages", "page_id", r"regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g')", 20)
CONV = counts("conversations", "conv_id", "text", 10)


def md5_number(*parts: str) -> str:
    return "('0x' || substr(md5(concat_ws(':', " + ", ".join(parts) + ")), 1, 8))::BIGINT"


def law(kind: str, h: str, s: int = 3) -> str:
    return f"({h} % 2 * 2 - 1)" if kind == "sign" else f"(CASE {h} % {2 * s} WHEN 0 THEN 1 WHEN 1 THEN -1 ELSE 0 END)"


def sketch(cells: str, r: int, kind: str, seed: int = 0) -> str:
    """(r, k, v) over cells with column ids i."""
    return f"SELECT r, k, sum(v * w) AS v FROM ({cells}) JOIN (SELECT i, k, {law(kind, md5_number(str(seed), 'i', 'k'))} AS w FROM (SELECT DISTINCT i FROM ({cells})), range(1, {r + 1}) t(k)) USING (i) WHERE w != 0 GROUP BY ALL"


def greedy(cells: str, l: int, score: str = "energy", start: str | None = None, target: str | None = None) -> str:
    """(step, key, score, residual_sq) of a greedy choice on the Gram matrix, unrolled.

    score: 'energy' for the selection criterion, 'norm' for pivoting by residual
    norm.  start: the key of a forced first step.  target: cells (r, k, v) of
    another matrix, whose cross products take the Gram matrix's part in the score.
    """
    out = [
        f"c AS MATERIALIZED ({cells})",
        "n AS (SELECT DISTINCT c FROM c)",
        "x0 AS MATERIALIZED (SELECT a.c AS p, b.c AS q, coalesce(g.v, 0) AS v FROM n a, n b LEFT JOIN (SELECT s.c AS p, t.c AS q, sum(s.v * t.v) AS v FROM c s JOIN c t USING (r) GROUP BY ALL) g ON g.p = a.c AND g.q = b.c)",
        "e0 AS (SELECT p, v FROM x0 WHERE p = q)",
    ]
    if target:
        out += [f"b AS MATERIALIZED ({target})", "h0 AS MATERIALIZED (SELECT k AS p, c.c AS q, sum(b.v * c.v) AS v FROM b JOIN c USING (r) GROUP BY ALL)", "t0 AS (SELECT sum(v * v) AS v FROM b)"]
    else:
        out += ["t0 AS (SELECT sum(v) AS v FROM e0)"]
    for t in range(1, l + 1):
        g = f"x{t - 1}"
        top = f"(SELECT q, sum(v * v) AS s FROM {'h' + str(t - 1) if target else g} GROUP BY q)" if score == "energy" else f"(SELECT q, v AS s FROM {g} WHERE p = q)"
        value = "s / d.v" if score == "energy" else "s"
        forced = f"AND d.p = {start}" if start and t == 1 else ""
        taken = "".join(f" AND d.p != (SELECT p FROM s{i})" for i in range(1, t))
        out.append(f"s{t} AS MATERIALIZED (SELECT d.p, {value} AS s, d.v AS d FROM {g} d JOIN {top} u ON u.q = d.p JOIN e0 ON e0.p = d.p WHERE d.p = d.q AND d.v > 1e-10 * e0.v {forced}{taken} ORDER BY 2 DESC, 1 LIMIT 1)")
        out.append(f"x{t} AS MATERIALIZED (SELECT g.p, g.q, g.v - a.v * b.v / s.d AS v FROM {g} g JOIN s{t} s ON true JOIN {g} a ON a.p = g.p AND a.q = s.p JOIN {g} b ON b.p = g.q AND b.q = s.p)")
        if target:
            out.append(f"h{t} AS MATERIALIZED (SELECT h.p, h.q, h.v - a.v * b.v / s.d AS v FROM h{t - 1} h JOIN s{t} s ON true JOIN h{t - 1} a ON a.p = h.p AND a.q = s.p JOIN {g} b ON b.p = h.q AND b.q = s.p)")
    left = "(SELECT v FROM t0)"
    rows = []
    for t in range(1, l + 1):
        left = f"{left} - (SELECT s FROM s{t})"
        residual = left if score == "energy" else "NULL::DOUBLE"
        rows.append(f"SELECT {t} AS step, p AS key, round(s, 3) AS score, round({residual}, 3) AS residual_sq FROM s{t}")
    return "WITH " + ",\n".join(out) + "\n" + " UNION ALL ".join(rows)


def greedy_rows(cells: str, l: int, target: str | None = None) -> str:
    """The result of :func:`greedy` for more columns than a Gram matrix of SQL rows allows.

    In the space of the matrix's rows: an orthonormal direction a step, and the
    target's products of rows, from which every column's numbers follow.
    """
    out = [
        f"c AS MATERIALIZED ({cells})",
        "rws AS (SELECT DISTINCT r FROM c)",
        f"b AS MATERIALIZED ({target or 'SELECT r, c AS k, v FROM c'})",
        "mid AS MATERIALIZED (SELECT x.r AS p, y.r AS q, sum(x.v * y.v) AS v FROM b x JOIN b y USING (k) GROUP BY ALL)",
        "h AS (SELECT c.c AS i, mid.p AS r, sum(mid.v * c.v) AS v FROM c JOIN mid ON mid.q = c.r GROUP BY ALL)",
        "t0 AS (SELECT sum(v * v) AS v FROM b)",
        "st0 AS MATERIALIZED (SELECT c.c AS i, coalesce(sum(c.v * h.v), 0) AS f, sum(c.v * c.v) AS g, sum(c.v * c.v) AS g0 FROM c LEFT JOIN h ON h.i = c.c AND h.r = c.r GROUP BY 1)",
    ]
    for t in range(1, l + 1):
        taken = "".join(f" AND i != (SELECT i FROM p{q})" for q in range(1, t))
        out.append(f"y{t} AS MATERIALIZED (SELECT i, f / g AS s, g FROM st{t - 1} WHERE g > 1e-10 * g0 AND g > 0{taken})")
        out.append(f"p{t} AS MATERIALIZED (SELECT * FROM y{t} WHERE s >= (SELECT max(s) FROM y{t}) * (1 - 1e-9) ORDER BY i LIMIT 1)")  # equal to nine digits is a tie
        out.append(f"raw{t} AS MATERIALIZED (SELECT rws.r, coalesce(a.v, 0) AS v FROM rws LEFT JOIN (SELECT r, v FROM c WHERE c = (SELECT i FROM p{t})) a USING (r))")
        less = "".join(f" - u{q}.v * (SELECT sum(x.v * y.v) FROM raw{t} x JOIN u{q} y USING (r))" for q in range(1, t))
        joins = "".join(f" JOIN u{q} ON u{q}.r = a.r" for q in range(1, t))
        out.append(f"u{t} AS MATERIALIZED (SELECT a.r, (a.v{less}) / sqrt((SELECT g FROM p{t})) AS v FROM raw{t} a{joins})")
        out.append(f"m{t} AS MATERIALIZED (SELECT u.r, coalesce(sum(mid.v * o.v), 0) AS v FROM u{t} u LEFT JOIN mid ON mid.p = u.r LEFT JOIN u{t} o ON o.r = mid.q GROUP BY 1)")
        less = "".join(f" - u{q}.v * (SELECT sum(x.v * y.v) FROM m{t} x JOIN u{q} y USING (r))" for q in range(1, t))
        joins = joins.replace("a.r", "m.r")
        out.append(f"e{t} AS MATERIALIZED (SELECT m.r, m.v{less} AS v FROM m{t} m{joins})")
        inner = f"(SELECT sum(x.v * y.v) FROM m{t} x JOIN u{t} y USING (r))"
        parts = f"(SELECT c.c AS i, sum(c.v * u.v) AS w, sum(c.v * e.v) AS e FROM c JOIN u{t} u USING (r) JOIN e{t} e USING (r) GROUP BY 1)"
        out.append(f"st{t} AS MATERIALIZED (SELECT i, greatest(f - 2 * w * e + {inner} * w * w, 0) AS f, greatest(g - w * w, 0) AS g, g0 FROM st{t - 1} JOIN {parts} USING (i))")
    left, rows = "(SELECT v FROM t0)", []
    for t in range(1, l + 1):
        left = f"{left} - (SELECT s FROM p{t})"
        rows.append(f"SELECT {t} AS step, i AS key, round(s, 3) AS score, round({left}, 3) AS residual_sq FROM p{t}")
    return "WITH " + ",\n".join(out) + "\n" + " UNION ALL ".join(rows)


EMB = "SELECT vec_id AS c, generate_subscripts(embedding, 1) - 1 AS r, unnest(embedding)::DOUBLE AS v FROM embeddings"
EMB_I = EMB.replace("AS c,", "AS c, vec_id AS i,")


def ranked(cells: str) -> str:
    """Cells with the dense rank of their column as its id i."""
    return f"SELECT r, c, v, dense_rank() OVER (ORDER BY c) - 1 AS i FROM ({cells})"


def in_block(n: int, k: int) -> str:
    return f"{md5_number('i')} % {n} = {k}"


def block_choices(cells: str, n: int, l_b: int, target: str | None, form=greedy) -> list[str]:
    """CTEs blk0 ... of the choices in hash blocks of ``cells`` (r, c, v, i), a CTE or table, and cand_ of all of them."""
    out = [f"blk{k} AS MATERIALIZED ({form(f'SELECT r, c, v FROM {cells} WHERE {in_block(n, k)}', l_b, target=target)})" for k in range(n)]
    return [*out, "cand_ AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT {k} AS block, step, key, score FROM blk{k}" for k in range(n)) + ")"]


def two_stage(cells: str, l: int, r: int, kind: str, n: int, l_b: int, form=greedy) -> str:
    """The two-pass selector over hash blocks of cells (r, c, v, i), for a sketch drawn from hashes."""
    ctes = [f"cells_ AS MATERIALIZED ({cells})", f"sk_ AS MATERIALIZED ({sketch('SELECT r, v, i FROM cells_', r, kind)})", *block_choices("cells_", n, l_b, "SELECT r, k, v FROM sk_", form)]
    last = form("SELECT r, c, v FROM cells_ WHERE c IN (SELECT key FROM cand_)", l, target="SELECT r, k, v FROM sk_")
    return "WITH " + ",\n".join(ctes) + f"\nSELECT * FROM ({last})"


def local_union(cells: str, l: int, n: int, l_b: int, refine: bool) -> str:
    """Local choices of hash blocks, one step of each at a time, or the choice among them."""
    ctes = [f"cells_ AS MATERIALIZED ({cells})", *block_choices("cells_", n, l_b, None)]
    if refine:
        return "WITH " + ",\n".join(ctes) + "\nSELECT * FROM (" + greedy("SELECT r, c, v FROM cells_ WHERE c IN (SELECT key FROM cand_)", l) + ")"
    return "WITH " + ",\n".join(ctes) + f"\nSELECT row_number() OVER (ORDER BY step, score DESC, key) AS step, key, score FROM cand_ ORDER BY 1 LIMIT {l}"


def top_value(gram: str, squarings: int = 6) -> list[str]:
    """CTEs ending in lam(share): the largest eigenvalue of a Gram matrix (p, q, v) as a share of its trace, by squaring."""
    out = [f"q0 AS MATERIALIZED (SELECT p, q, v / (SELECT sum(v) FROM {gram} WHERE p = q) AS v FROM {gram})"]
    for k in range(1, squarings + 1):
        out.append(f"q{k} AS MATERIALIZED (SELECT a.p, b.q, sum(a.v * b.v) AS v FROM q{k - 1} a JOIN q{k - 1} b ON a.q = b.p GROUP BY ALL)")
    return [*out, f"lam AS (SELECT pow((SELECT sum(v) FROM q{squarings} WHERE p = q), 1.0 / {1 << squarings}) AS share)"]
