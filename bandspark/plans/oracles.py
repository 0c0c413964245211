"""DuckDB SQL that computes components, roots, levels, labels and measures on its own, by recursion over an edge list."""

from __future__ import annotations

from bandspark.sources.workloads import duck_sql

#: Searches unrolled for a root; a search that no longer grows repeats itself.
SEARCHES = 6
#: Fewer where the graph is deep and two searches reach its ends.
SEARCHES_OF = {"w6": 3}


def _levels(name: str, roots: str) -> str:
    return f"""{name}(v, c, l) USING KEY (v) AS (SELECT root, c, 0 FROM {roots}
 UNION SELECT e.dst, min({name}.c), min({name}.l) + 1 FROM {name} JOIN e ON e.src = {name}.v WHERE NOT EXISTS (SELECT 1 FROM recurring.{name} AS k WHERE k.v = e.dst) GROUP BY e.dst)"""


def _graph(w: str) -> list[str]:
    return [
        f"raw AS (SELECT a::BIGINT AS a, b::BIGINT AS b FROM ({duck_sql(w)}) AS z WHERE a IS NOT NULL AND b IS NOT NULL AND a <> b)",
        "e AS MATERIALIZED (SELECT a AS src, b AS dst FROM raw UNION SELECT b, a FROM raw)",
        "deg AS MATERIALIZED (SELECT src AS v, count(*) AS deg FROM e GROUP BY src)",
        "cc(v, c) USING KEY (v) AS (SELECT v, v FROM deg UNION SELECT e.dst, min(cc.c) FROM cc JOIN e ON e.src = cc.v JOIN recurring.cc AS k ON k.v = e.dst WHERE cc.c < k.c GROUP BY e.dst)",
    ]


def _search(root: str | int = "classic", searches: int = SEARCHES, shrink: str = "deg, ") -> list[str]:
    out = ["r1 AS (SELECT DISTINCT c, c AS root FROM cc)"]
    if isinstance(root, int):
        return [f"rt AS (SELECT c, {root} AS root FROM cc WHERE v = {root})", _levels("lv", "rt")]
    if root == "first":
        return [*out, _levels("lv", "r1"), "rt AS (SELECT c, root FROM r1)"]
    for j in range(1, searches + 1):
        out.append(_levels(f"l{j}", f"r{j}"))
        out.append(f"x{j} AS (SELECT c, max(l) AS ecc FROM l{j} GROUP BY c)")
        out.append(f"h{j} AS (SELECT c, v AS hop FROM (SELECT l{j}.c, l{j}.v, row_number() OVER (PARTITION BY l{j}.c ORDER BY {shrink}l{j}.v) AS n FROM l{j} JOIN x{j} ON x{j}.c = l{j}.c AND x{j}.ecc = l{j}.l JOIN deg ON deg.v = l{j}.v) AS q WHERE n = 1)")
        before = "true AS grew, 1 AS runs" if j == 1 else f"(s{j - 1}.grew AND x{j}.ecc > s{j - 1}.ecc) AS grew, s{j - 1}.runs + s{j - 1}.grew::INT AS runs"
        join = "" if j == 1 else f" JOIN s{j - 1} ON s{j - 1}.c = r{j}.c"
        out.append(f"s{j} AS (SELECT r{j}.c, r{j}.root, x{j}.ecc, h{j}.hop, {before} FROM r{j} JOIN x{j} ON x{j}.c = r{j}.c JOIN h{j} ON h{j}.c = r{j}.c{join})")
        out.append(f"r{j + 1} AS (SELECT c, CASE WHEN grew THEN hop ELSE root END AS root FROM s{j})")
    if root == "algebraic":
        return [*out, f"rt AS (SELECT c, hop AS root FROM s{searches})", _levels("lv", "rt")]
    return [*out, f"rt AS (SELECT c, root FROM s{searches})", f"lv AS MATERIALIZED (SELECT * FROM l{searches})"]


def _labels(sort: str = "degree", reverse: bool = True) -> list[str]:
    keys = {"degree": "p, deg, v", "parent": "p, v", "level": "v", "end": "deg, v"}[sort]
    sign = "(SELECT count(*) FROM cc) - 1 - (b + x)" if reverse else "b + x"
    return [
        "sz AS (SELECT c, l, count(*) AS n FROM lv GROUP BY c, l)",
        "st AS MATERIALIZED (SELECT c, l, coalesce(sum(n) OVER (PARTITION BY c ORDER BY l ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start FROM sz)",
        "bs AS (SELECT c, coalesce(sum(n) OVER (ORDER BY c ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS b FROM (SELECT c, sum(n) AS n FROM sz GROUP BY c) AS q)",
        "dn AS MATERIALIZED (SELECT e.src, e.dst, y.l FROM e JOIN lv AS x ON x.v = e.src JOIN lv AS y ON y.v = e.dst WHERE y.l = x.l + 1)",
        f"""lab(k, v, c, x) AS (SELECT 0, root, c, 0::BIGINT FROM rt UNION ALL
 SELECT k + 1, q.v, q.c, (st.start + row_number() OVER (PARTITION BY q.c ORDER BY {keys.replace('v', 'q.v')}) - 1)::BIGINT
 FROM (SELECT lab.k, dn.dst AS v, lab.c, min(lab.x) AS p FROM lab JOIN dn ON dn.src = lab.v AND dn.l = lab.k + 1 GROUP BY lab.k, dn.dst, lab.c) AS q JOIN deg ON deg.v = q.v JOIN st ON st.c = q.c AND st.l = q.k + 1)""",
        f"o AS MATERIALIZED (SELECT lab.v, ({sign})::BIGINT AS label FROM lab JOIN bs USING (c))",
    ]


def _beta(name: str, labels: str) -> str:
    return f"{name} AS (SELECT x.label AS i, x.label - least(x.label, coalesce(min(y.label), x.label)) AS beta FROM {labels} AS x LEFT JOIN e ON e.src = x.v LEFT JOIN {labels} AS y ON y.v = e.dst GROUP BY x.label)"


def _with(parts: list[str], tail: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + tail


def _n(w: str) -> int:
    return SEARCHES_OF.get(w, SEARCHES)


def components(w: str) -> str:
    return _with(_graph(w), "SELECT v, c AS comp FROM cc")


def roots(w: str) -> str:
    return _with(_graph(w) + _search("classic", _n(w)), f"SELECT c AS comp, root AS classic, ecc AS depth, runs AS searches, hop AS algebraic FROM s{_n(w)}")


def levels(w: str, root: str = "classic") -> str:
    return _with(_graph(w) + _search(root, _n(w)), "SELECT c AS comp, v, l AS level FROM lv")


def order(w: str, root: str | int = "classic", sort: str = "degree", reverse: bool = True, tail: str = "SELECT v, label FROM o", shrink: str = "deg, ") -> str:
    return _with(_graph(w) + _search(root, _n(w), shrink) + _labels(sort, reverse), tail)


def structure(names) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({metrics(w)}) AS {w}" for w in names)


def off_blocks(w: str, scramble: str, blocks: tuple[int, ...]) -> str:
    """Entries across blocks in natural, scrambled and frontier order; ``scramble``: a label from v and c.n."""
    parts = _graph(w) + _search("classic", _n(w)) + _labels()
    parts += [f"k AS (SELECT 'natural' AS ordering, v, row_number() OVER (ORDER BY v) - 1 AS label FROM deg UNION ALL SELECT 'scrambled', v, {scramble} FROM deg, (SELECT count(*) AS n FROM deg) c UNION ALL SELECT 'frontier', v, label FROM o)"]
    tail = " UNION ALL ".join(f"SELECT x.ordering, {b} AS block, count(*) AS off_block FROM e JOIN k x ON x.v = e.src JOIN k y ON y.v = e.dst AND y.ordering = x.ordering WHERE x.label // {b} <> y.label // {b} GROUP BY 1" for b in blocks)
    return _with(parts, tail)


def metrics(w: str) -> str:
    parts = _graph(w) + _search("classic", _n(w)) + _labels()
    parts += ["nat AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS label FROM deg)", _beta("b0", "nat"), _beta("b1", "o")]
    return _with(parts, metrics_tail(w))


def metrics_tail(w: str) -> str:
    return f"""SELECT '{w}' AS graph, (SELECT count(*) FROM deg) AS n, (SELECT count(*) FROM e) AS nnz, (SELECT count(*) FROM rt) AS comps,
 (SELECT max(beta) FROM b0) AS bw_before, (SELECT max(beta) FROM b1) AS bw_after, (SELECT sum(beta) FROM b0)::BIGINT AS profile_before, (SELECT sum(beta) FROM b1)::BIGINT AS profile_after,
 (SELECT max(l) FROM lv) AS pseudo_diameter, (SELECT max(n) FROM sz) AS width"""


def row_bandwidths(w: str) -> str:
    return _with(_graph(w) + _search("classic", _n(w)) + _labels() + [_beta("b1", "o")], "SELECT i, beta FROM b1")
