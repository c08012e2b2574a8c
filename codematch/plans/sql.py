"""The same computations as SQL for an independent engine: common table expressions to put together."""

from __future__ import annotations

from codematch.operators.vectors import DIMENSIONS, NUMERIC, PAGE_LANGUAGE, PAGE_PATTERNS, TURNS, numeric_sql

_TEXT = {
    "documents": ("documents", "doc_id", "text", "lang"),
    "benchmark": ("benchmark", "item_id", "text", "NULL"),
    "turns": ("conversations", f"conv_id * {TURNS} + turn", "text", "role"),
}


def shown(html: str) -> str:
    for p in PAGE_PATTERNS:
        flags = p[2 : p.index(")")] if p.startswith("(?") else ""
        body = p[p.index(")") + 1 :] if flags else p
        html = f"regexp_replace({html}, '{body}', ' ', 'g{flags}')"
    return html


def vec(view: str) -> str:
    """SELECT of (id, vec, grp)."""
    if view == "embeddings":
        return "SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS vec, CAST(label AS VARCHAR) AS grp FROM embeddings"
    if view in NUMERIC:
        z = ", ".join(f"z_{n}" for n, _ in NUMERIC[view][3])
        tables = {t: t for t in ("part", "lineitem", "customer", "orders", "events")}
        return f"SELECT CAST(id AS BIGINT) AS id, [{z}] AS vec, CAST(grp AS VARCHAR) AS grp FROM ({numeric_sql(view).format(**tables)})"
    if view == "pages":
        table, id_, text, grp = "pages", "page_id", shown("html"), f"regexp_extract(html, '{PAGE_LANGUAGE}', 1)"
    else:
        table, id_, text, grp = _TEXT[view]
    d = DIMENSIONS[view]
    return f"""WITH tx AS (SELECT {id_} AS id, CAST({grp} AS VARCHAR) AS grp, {text} AS text FROM {table}),
tw AS (SELECT id, unnest(string_split_regex(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+')) AS w FROM tx),
tb AS (SELECT id, CAST('0x' || left(md5(w), 8) AS BIGINT) % {d} AS b, count(*) AS n FROM tw WHERE w <> '' GROUP BY 1, 2),
tn AS (SELECT id, sqrt(CAST(sum(n * n) AS DOUBLE)) AS norm FROM tb GROUP BY 1)
SELECT tx.id, list(coalesce(tb.n / tn.norm, 0.0) ORDER BY j.b) AS vec, any_value(tx.grp) AS grp
FROM tx CROSS JOIN (SELECT unnest(range({d})) AS b) j LEFT JOIN tb ON tb.id = tx.id AND tb.b = j.b LEFT JOIN tn ON tn.id = tx.id GROUP BY tx.id"""


def square(a: str, b: str, n: int) -> str:
    return f"list_sum([({a}[i] - {b}[i]) * ({a}[i] - {b}[i]) for i in range(1, {n + 1})])"


def codes(view: str, K: int, m: int, k: int, halves: int = 2, probes: int = 1, rotate: bool = False, local: bool = False, where: str = "", p: str = "") -> str:
    """CTEs of the anchor model: {p}v, {p}cd (all half distances), {p}fc (fine codes by block), {p}codes (id, c1, c2, fine).

    With probes > 1, fc has the codes of each of the nearest clusters (rn). model rows come
    from the whole view; `where` (on id, grp, r) restricts the rows that are encoded.
    """
    d = DIMENSIONS[view]
    dh, per, w = d // halves, m // halves, d // m
    step = 3 if dh % 3 else 5
    res = f"[x.hv[i] - cv[i] for i in range(1, {dh + 1})]"
    if rotate:
        res = f"[(CASE WHEN i % 2 = 0 THEN 1 ELSE -1 END) * (x.hv[({step} * i + 1) % {dh} + 1] - cv[({step} * i + 1) % {dh} + 1]) for i in range({dh})]"
    if local:
        sub = f"SELECT h, c, b, j, part AS sp FROM (SELECT h, c, b, part, row_number() OVER (PARTITION BY h, c, b ORDER BY id) - 1 AS j FROM {p}bk WHERE rn = 1) WHERE j < {k}"
        join = f"{p}sb.h = {p}bk.h AND {p}sb.b = {p}bk.b AND {p}sb.c = {p}bk.c"
    else:
        sub = f"SELECT h, b, r - {K} AS j, part AS sp FROM {p}bk WHERE rn = 1 AND r >= {K} AND r < {K + k}"
        join = f"{p}sb.h = {p}bk.h AND {p}sb.b = {p}bk.b"
    keep = f"WHERE {where}" if where else ""
    second = f"max(c) FILTER (WHERE h = 1)" if halves == 2 else "CAST(NULL AS INTEGER)"  # noqa: F541
    return f"""{p}v AS (SELECT id, vec, grp, row_number() OVER (ORDER BY id) - 1 AS r FROM ({vec(view)})),
{p}hv AS (SELECT id, r, grp, h, vec[h * {dh} + 1 : (h + 1) * {dh}] AS hv FROM {p}v CROSS JOIN (SELECT unnest(range({halves})) AS h)),
{p}cc AS (SELECT h, r AS c, hv AS cv FROM {p}hv WHERE r < {K}),
{p}cd AS (SELECT x.id, x.r, x.h, y.c, {square('x.hv', 'y.cv', dh)} AS d FROM {p}hv x JOIN {p}cc y ON x.h = y.h),
{p}cr AS (SELECT *, row_number() OVER (PARTITION BY id, h ORDER BY d, c) AS rn FROM {p}cd),
{p}rs AS (SELECT x.id, x.r, x.h, y.c, y.d, y.rn, {res} AS res FROM {p}hv x JOIN {p}cr y ON x.id = y.id AND x.h = y.h JOIN {p}cc z ON z.h = y.h AND z.c = y.c WHERE y.rn <= {probes}),
{p}bk AS (SELECT id, r, h, c, d, rn, b, res[b * {w} + 1 : (b + 1) * {w}] AS part FROM {p}rs CROSS JOIN (SELECT unnest(range({per})) AS b)),
{p}sb AS ({sub}),
{p}sd AS (SELECT {p}bk.id, {p}bk.r, {p}bk.h, {p}bk.c, {p}bk.d, {p}bk.rn, {p}bk.b, j, {square(f'{p}bk.part', f'{p}sb.sp', w)} AS e FROM {p}bk JOIN {p}sb ON {join}),
{p}fc AS (SELECT id, r, h, c, d, rn, b, h * {per} + b AS pos, j FROM (SELECT *, row_number() OVER (PARTITION BY id, h, rn, b ORDER BY e, j) AS best FROM {p}sd) WHERE best = 1),
{p}enc AS (SELECT id, any_value(r) AS r, CAST(max(c) FILTER (WHERE h = 0) AS INTEGER) AS c1, CAST({second} AS INTEGER) AS c2, list(CAST(j AS SMALLINT) ORDER BY pos) AS fine FROM {p}fc WHERE rn = 1 GROUP BY id),
{p}codes AS (SELECT a.id, a.c1, a.c2, a.fine, v.grp, v.r FROM {p}enc a JOIN {p}v v ON v.id = a.id {keep.replace('id', 'a.id').replace('grp', 'v.grp') if keep else ''})"""


def tokens(m: int, p: str = "") -> str:
    """CTE {p}tokens (id, grp, token) from {p}codes."""
    return f"""{p}tokens AS (SELECT id, grp, (CAST(CASE WHEN c2 IS NULL OR pos < {m // 2} THEN c1 ELSE c2 END AS BIGINT) << 32) | (CAST(pos AS BIGINT) << 16) | f AS token
FROM (SELECT id, grp, c1, c2, unnest(fine) AS f, unnest(range(len(fine))) AS pos FROM {p}codes))"""


def pairs(p: str = "", name: str = "pairs") -> str:
    return f"{name} AS (SELECT a.id AS a, b.id AS b, count(*) AS hits FROM {p}tokens a JOIN {p}tokens b ON a.token = b.token AND a.id < b.id GROUP BY 1, 2)"


def stoplist(lo: int, hi: int, p: str = "", q: str = "s_") -> str:
    return f"{q}tokens AS (SELECT t.* FROM {p}tokens t JOIN (SELECT token FROM {p}tokens GROUP BY token HAVING count(DISTINCT id) BETWEEN {lo} AND {hi}) k ON k.token = t.token)"


def components(edges: str, nodes: str = "", name: str = "comp") -> str:
    """CTE {name}(id, component) of an edge relation (a, b); WITH RECURSIVE is needed."""
    base = nodes or f"SELECT a AS id FROM {edges} UNION SELECT b FROM {edges}"
    return f"""{name}_e AS (SELECT a, b FROM {edges} UNION ALL SELECT b, a FROM {edges}),
{name}_r(id, seen) AS (SELECT id, id FROM ({base}) UNION SELECT r.id, e.b FROM {name}_r r JOIN {name}_e e ON r.seen = e.a),
{name} AS (SELECT id, min(seen) AS component FROM {name}_r GROUP BY id)"""


def visited(quota: int, queries: str, p: str = "", name: str = "vis") -> str:
    """CTE {name}(qid, ord, c1, c2, d, n, seen): cells of database codes {p}db for the queries (a condition on id)."""
    return f"""{name}_n AS (SELECT c1, c2, count(*) AS n FROM {p}db GROUP BY 1, 2),
{name}_p AS (SELECT a.id AS qid, CAST(a.c AS INTEGER) AS c1, CAST(b.c AS INTEGER) AS c2, a.d + b.d AS d FROM {p}cd a JOIN {p}cd b ON a.id = b.id AND a.h = 0 AND b.h = 1 WHERE {queries.replace('id', 'a.id')}),
{name}_s AS (SELECT x.*, y.n, CAST(sum(n) OVER (PARTITION BY qid ORDER BY d, x.c1, x.c2 ROWS UNBOUNDED PRECEDING) AS BIGINT) AS seen, CAST(row_number() OVER (PARTITION BY qid ORDER BY d, x.c1, x.c2) AS INTEGER) AS ord FROM {name}_p x JOIN {name}_n y ON x.c1 = y.c1 AND x.c2 = y.c2),
{name} AS (SELECT qid, ord, c1, c2, d, n, seen FROM {name}_s WHERE seen - n < {quota})"""


def hits(a: str, b: str, m: int) -> str:
    return " + ".join(f"CAST({a}[{i}] = {b}[{i}] AS INTEGER)" for i in range(1, m + 1))


def hits_pair(x: str, y: str, m: int) -> str:
    one, two = (" + ".join(f"CAST({x}.fine[{i}] = {y}.fine[{i}] AS INTEGER)" for i in r) for r in (range(1, m // 2 + 1), range(m // 2 + 1, m + 1)))
    return f"(CASE WHEN {x}.c1 = {y}.c1 THEN {one} ELSE 0 END + CASE WHEN {x}.c2 = {y}.c2 THEN {two} ELSE 0 END)"
