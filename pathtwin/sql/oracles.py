"""Pieces of DuckDB SQL. They restate definitions on whole tables and are never part of a Spark plan."""

from __future__ import annotations

LINES = (
    "list_filter(list_transform(string_split(coalesce(text, ''), chr(10)), lambda x: trim(regexp_replace(lower(x), '[ \\t]+', ' ', 'g'))), lambda x: x <> '')"
)


def abstracted(mode: str, col: str = "l") -> str:
    blind = "CAST(CAST(floor(len(string_split(x, ' ')) / 4) AS BIGINT) AS VARCHAR) || ' ' || regexp_replace(x, '[\\p{L}\\p{N} ]', '', 'g')"
    if mode == "exact":
        return col
    return f"list_transform({col}, lambda x: {blind})" if mode == "blind" else f"list_transform({col}, lambda x: string_split(x, ' ')[1] || ' ' || {blind})"


def fragments(min_lines: int, mode: str = "exact") -> str:
    """CTE ``f(id, s, n)``."""
    return f"f AS (SELECT doc_id AS id, {abstracted(mode)} AS s, len(l) AS n FROM (SELECT doc_id, {LINES} AS l FROM documents) WHERE len(l) >= {min_lines})"


def every(source: str = "f") -> str:
    """CTE ``p(x, y)``: all pairs."""
    return f"p AS (SELECT a.id AS x, b.id AS y FROM {source} a JOIN {source} b ON a.id < b.id)"


def shared(source: str = "f") -> str:
    """CTE ``p(x, y)``: pairs with a common symbol, for metrics that are one without."""
    return (
        f"u AS (SELECT DISTINCT id, unnest(s) AS v FROM {source}), p AS (SELECT DISTINCT a.id AS x, b.id AS y FROM u a JOIN u b ON a.v = b.v AND a.id < b.id)"
    )


def likely(tau: float, source: str = "c") -> str:
    """CTE ``p(x, y)`` of ``source(id, s, n)``: pairs whose bags of symbols have enough in common for a common subsequence of the needed length.

    A common subsequence is never longer than what the bags share, and every metric it is used for is at least the longer
    length less that, or looks for nine tenths of the shorter.
    """
    return (
        f"bag AS (SELECT id, v, count(*) AS k FROM (SELECT id, unnest(s) AS v FROM {source}) GROUP BY ALL), both_bags AS (SELECT a.id AS x, b.id AS y, sum(least(a.k, b.k)) AS o FROM bag a JOIN bag b ON a.v = b.v AND a.id < b.id GROUP BY ALL), "
        f"p AS (SELECT x, y FROM both_bags JOIN {source} a ON a.id = x JOIN {source} b ON b.id = y WHERE o > {1 - tau} * greatest(len(a.s), len(b.s)) - 1e-6 OR 100 * o >= 90 * least(len(a.s), len(b.s)))"
    )


def characters(a: str, b: str, which: str) -> str:
    """One of the lists ``a`` and ``b`` with a character for each symbol that occurs in either."""
    return f"array_to_string(list_transform({which}, lambda x: chr(CAST(list_position(list_distinct(list_concat({a}, {b})), x) AS INTEGER))), '')"


def lcs(a: str, b: str) -> str:
    """Length of the longest common subsequence, by rows of running maxima."""
    step = "list_transform(range(1, len(r) + 1), lambda j: list_max(list_transform(range(1, j + 1), lambda i: CASE WHEN r[i] = 1 THEN greatest(q[i], 1 + CASE WHEN i > 1 THEN q[i - 1] ELSE 0 END) ELSE q[i] END)))"
    rows = f"list_transform({a}, lambda x: list_transform({b}, lambda y: CASE WHEN x = y THEN CAST(1 AS BIGINT) ELSE 0 END))"
    return f"coalesce(list_max(list_reduce({rows}, lambda q, r: {step}, list_transform({b}, lambda y: CAST(0 AS BIGINT)))), 0)"


def mismatches(a: str, b: str) -> str:
    return f"coalesce(list_sum(list_transform(range(1, least(len({a}), len({b})) + 1), lambda i: CASE WHEN {a}[i] = {b}[i] THEN 0 ELSE 1 END)), 0)"


def times(s: str, x: str) -> str:
    return f"len(list_filter({s}, lambda z: z = {x}))"


def distance(metric: str, a: str = "a.s", b: str = "b.s", ta: str = "", tb: str = "", tau: float = 0.3, cap: int | None = None) -> str:
    """Normalised distance of two lists; the string metrics read the character columns. ``cap`` is the greatest difference of lengths."""
    if cap is not None and metric != "lcs_mod":
        return f"CASE WHEN abs(len({a}) - len({b})) > {cap} THEN 1 ELSE {distance(metric, a, b, ta, tb, tau)} END"
    ta, tb = ta or characters(a, b, a), tb or characters(a, b, b)
    longer, shorter = f"greatest(len({a}), len({b}))", f"least(len({a}), len({b}))"
    if metric == "hamming":
        return f"({mismatches(a, b)} + abs(len({a}) - len({b}))) / {longer}"
    if metric == "hamming_free":
        return f"{mismatches(a, b)} / {longer}"
    if metric in ("levenshtein", "damerau"):
        return f"{'levenshtein' if metric == 'levenshtein' else 'damerau_levenshtein'}({ta}, {tb}) / {longer}"
    if metric in ("lcs", "alignment"):
        return f"({longer} - z) / {longer}"
    if metric == "lcs_mod":
        plain = f"({longer} - z) / {longer}"
        if cap is not None:
            plain = f"CASE WHEN {longer} - {shorter} > {cap} THEN 1 ELSE {plain} END"
        return f"CASE WHEN {plain} >= {tau} AND {shorter} >= 10 AND 100 * z >= 90 * {shorter} THEN ({shorter} - z) / {shorter} ELSE {plain} END"
    if metric == "jaccard":
        return f"1 - len(list_intersect(list_distinct({a}), list_distinct({b}))) / len(list_distinct(list_concat({a}, {b})))"
    if metric == "cosine":
        dot = f"list_sum(list_transform(list_distinct({a}), lambda k: {times(a, 'k')} * {times(b, 'k')}))"
        square = lambda s: f"list_sum(list_transform(list_distinct({s}), lambda k: {times(s, 'k')} * {times(s, 'k')}))"
        return f"1 - {dot} / sqrt({square(a)} * {square(b)})"
    if metric == "ngram":
        grams = lambda s: f"list_transform(range(1, len({s})), lambda i: {s}[i] || chr(1) || {s}[i + 1])"
        ga, gb = grams(a), grams(b)
        common = f"coalesce(list_sum(list_transform(list_distinct({ga}), lambda k: least({times(ga, 'k')}, {times(gb, 'k')}))), 0)"
        return f"1 - 2 * {common} / (len({a}) + len({b}) - 2)"
    if metric == "jaro_winkler":
        return f"1 - jaro_winkler_similarity({ta}, {tb})"
    raise ValueError(metric)


def needs_lcs(metric: str) -> bool:
    return metric in ("lcs", "lcs_mod", "alignment")


def clones(metric: str, min_lines: int = 15, mode: str = "exact", tau: float = 0.3, cap: int | None = None, source: str = "", by_class: bool = False) -> str:
    """Clone pairs of single-path documents by one metric; ``source`` makes ``f(id, s, n)`` otherwise than from the documents' lines.

    With ``by_class`` documents of equal paths are one, the first of them, and rows of its other members follow.
    """
    z = f", {lcs('a.s', 'b.s')} AS z" if needs_lcs(metric) else ""
    f = source or fragments(min_lines, mode)
    one = "c AS (SELECT min(id) AS id, s, n FROM f GROUP BY s, n)" if by_class else "c AS (SELECT id, s, n FROM f)"
    near = every("c") if metric == "hamming_free" else likely(tau) if metric in ("lcs", "lcs_mod", "alignment", "hamming", "levenshtein", "damerau") else shared("c")
    inner = f"SELECT p.x, p.y, a.s AS sa, b.s AS sb{z} FROM p JOIN c a ON a.id = p.x JOIN c b ON b.id = p.y"
    d = distance(metric, "sa", "sb", tau=tau, cap=cap)
    found = f"SELECT x AS left_id, y AS right_id, round(CAST({d} AS DOUBLE), 6) AS distance FROM m WHERE round({d}, 6) < {tau}"
    if not by_class:
        return f"WITH {f}, {one}, {near}, m AS ({inner}) {found}"
    rest = "SELECT 'member' AS \"row\", c.id AS left_id, f.id AS right_id, CAST(0 AS DOUBLE) AS distance FROM f JOIN c ON f.s = c.s WHERE f.id <> c.id"
    return f"WITH {f}, {one}, {near}, m AS ({inner}) SELECT 'pair' AS \"row\", * FROM ({found}) UNION ALL {rest}"


def set_clones(paths: str, metric: str, cap: int | None = None, tau: float = 0.3, factor: float | None = 1.7) -> str:
    """Clone pairs of sets of paths; ``paths`` makes ``w(id, q, mult)``. Distinct paths are compared once; the smaller set's mean decides, on ties the smaller mean."""
    size = f" AND greatest(tx.size, ty.size) <= {factor} * least(tx.size, ty.size)" if factor else ""
    return f"""{paths}, t AS (SELECT id, sum(mult) AS size FROM w GROUP BY id),
p2 AS (SELECT tx.id AS x, ty.id AS y, tx.size AS nx, ty.size AS ny FROM t tx JOIN t ty ON tx.id < ty.id{size}),
u AS (SELECT row_number() OVER () AS no, q FROM (SELECT DISTINCT q FROM w)), wu AS (SELECT id, no, mult FROM w JOIN u ON w.q = u.q),
v AS (SELECT DISTINCT no, unnest(q) AS c FROM u), e AS (SELECT DISTINCT a.no AS i, b.no AS j FROM v a JOIN v b ON a.c = b.c AND a.no <= b.no),
z AS (SELECT i, j, a.q AS qa, b.q AS qb, {lcs('a.q', 'b.q')} AS z FROM e JOIN u a ON a.no = i JOIN u b ON b.no = j),
d0 AS (SELECT i, j, {distance(metric, 'qa', 'qb', tau=tau, cap=cap)} AS d FROM z), d1 AS (SELECT i, j, d FROM d0 WHERE d < 1 UNION SELECT j, i, d FROM d0 WHERE d < 1),
near AS (SELECT a.id AS x, a.no, b.id AS y, min(d) AS d FROM wu a JOIN d1 ON d1.i = a.no JOIN wu b ON b.no = d1.j AND b.id <> a.id GROUP BY ALL),
part AS (SELECT near.x, near.y, sum(wu.mult * (1 - near.d)) AS got FROM near JOIN wu ON wu.id = near.x AND wu.no = near.no GROUP BY ALL),
r AS (SELECT p2.x, p2.y, 1 - coalesce(fwd.got, 0) / nx AS f, 1 - coalesce(bwd.got, 0) / ny AS b, nx, ny FROM p2 LEFT JOIN part fwd ON fwd.x = p2.x AND fwd.y = p2.y LEFT JOIN part bwd ON bwd.x = p2.y AND bwd.y = p2.x),
o AS (SELECT x, y, round(CAST(CASE WHEN nx < ny THEN f WHEN ny < nx THEN b ELSE least(f, b) END AS DOUBLE), 6) AS v FROM r)
SELECT x AS left_id, y AS right_id, v AS distance FROM o WHERE v < {tau}"""
