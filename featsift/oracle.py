"""SQL texts (DuckDB) that compute the queries' results independently: counts by joins, selection as an unrolled chain."""

from __future__ import annotations

from collections.abc import Sequence

from .sources.workloads import EVENTS, GATE, STAR

_LINE = {
    "qty": "CAST(floor(l_quantity) - 1 AS INT)",
    "qty_band": "CAST(floor((l_quantity - 1) / 10) AS INT)",
    "disc": "CAST(round(l_discount * 100) AS INT)",
    "disc_hi": "CASE WHEN round(l_discount * 100) >= 5 THEN 1 ELSE 0 END",
    "tax": "CAST(round(l_tax * 100) AS INT)",
    "rf": "CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 WHEN 'R' THEN 2 END",
    "ls": "CASE l_linestatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 END",
    "ln": "CAST(l_linenumber - 1 AS INT)",
    "ship_month": "CAST(month(l_shipdate) - 1 AS INT)",
    "ship_quarter": "CAST(quarter(l_shipdate) - 1 AS INT)",
}
_GATE = "CASE WHEN (round(l_discount * 100) >= 5 AND round(l_tax * 100) >= 4) OR l_quantity >= 46 THEN 1 ELSE 0 END"
_HI = "(CASE WHEN round(l_discount * 100) >= 5 THEN 1 ELSE 0 END)"
_TARGET = {
    "gate": _GATE,
    "xor": f"CASE WHEN l_quantity <= 15 THEN {_HI} ELSE xor({_HI}, CAST(round(l_tax * 100) AS INT) % 2) END",
    "rare": "CASE WHEN l_quantity = 50 THEN 1 ELSE 0 END",
    "noisy": f"CASE WHEN ((l_orderkey * 16807 + l_partkey * 69621 + l_suppkey) % 2147483647) % 100 < 10 THEN 1 - ({_GATE}) ELSE {_GATE} END",
}


def bucket(key: str, buckets: int = 100, multiplier: int = 48_271, shift: int = 11) -> str:
    return f"((({key}) * {multiplier} + {shift}) % 2147483647) % {buckets}"


def lines(target: str = "gate", where: str = "true") -> str:
    """rid, the ten codes, y and l_orderkey."""
    return f"SELECT row_number() OVER () AS rid, {', '.join(f'{e} AS {f}' for f, e in _LINE.items())}, {_TARGET[target]} AS y, l_orderkey FROM lineitem WHERE {where}"


def star() -> str:
    priorities = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
    segments = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
    code = lambda col, values: f"CASE {col} {' '.join(f'WHEN {v!r} THEN {i}' for i, v in enumerate(values))} END"
    extra = {
        "ship_year": "CAST(year(l_shipdate) - 1995 AS INT)", "ostatus": code("o_orderstatus", ["F", "O", "P"]), "oprio": code("o_orderpriority", priorities),
        "oyear": "CAST(year(o_orderdate) - 1995 AS INT)", "omonth": "CAST(month(o_orderdate) - 1 AS INT)", "oprice": "CAST(floor(o_totalprice / 50000) AS INT)",
        "seg": code("c_mktsegment", segments), "cnation": "c_nationkey", "cregion": "n_regionkey",
        "brand": "bcode", "ptype": "tcode", "psize": "CAST(floor((p_size - 1) / 5.0) AS INT)", "pprice": "CAST(floor((p_retailprice - 900) / 10) AS INT)", "snation": "s_nationkey",
    }
    every = {**_LINE, **extra}
    return f"""SELECT row_number() OVER () AS rid, {', '.join(f'{every[f]} AS {f}' for f in STAR)}, {_GATE} AS y FROM lineitem
        JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey
        JOIN (SELECT *, dense_rank() OVER (ORDER BY p_brand) - 1 AS bcode, dense_rank() OVER (ORDER BY p_type) - 1 AS tcode FROM part) ON l_partkey = p_partkey
        JOIN supplier ON l_suppkey = s_suppkey"""


def embed(size: int = 64, bins: int = 4, binary: bool = False) -> str:
    lo = ", ".join(f"min(embedding[{i + 1}]::DOUBLE) AS lo{i}, max(embedding[{i + 1}]::DOUBLE) AS hi{i}" for i in range(size))
    codes = ", ".join(f"CAST(greatest(least(floor((embedding[{i + 1}]::DOUBLE - lo{i}) / (hi{i} - lo{i}) * {bins}), {bins - 1}), 0) AS INT) AS e{i}" for i in range(size))
    return f"SELECT vec_id AS rid, {codes}, {'CASE WHEN label < 5 THEN 1 ELSE 0 END' if binary else 'label'} AS y FROM embeddings, (SELECT {lo} FROM embeddings)"


def events() -> str:
    return """SELECT event_id AS rid, hour(ts) AS hour, isodow(ts) - 1 AS weekday, user_id % 16 AS user_bucket, CAST(least(floor(value / 10), 31) AS INT) AS value_band,
        CAST(floor(CAST(json_extract_string(props, '$.k') AS INT) / 10.0) AS INT) AS props_band, dense_rank() OVER (ORDER BY event_type) - 1 AS y FROM events"""


def unpivoted(base: str, features: Sequence[str]) -> str:
    """base and long(rid, feature, x, y)."""
    return f"base AS MATERIALIZED ({base}), long AS ({' UNION ALL '.join(f'SELECT rid, {i} AS feature, {f} AS x, y FROM base' for i, f in enumerate(features))})"


def sparse_rows(classes: str, tokens: str) -> str:
    """classes(rid, y), posts(rid, feature, y), vocab(feature, name) from the classes and the distinct (rid, name)."""
    return f"""classes AS MATERIALIZED ({classes}), tok AS MATERIALIZED ({tokens}),
        vocab AS MATERIALIZED (SELECT name, row_number() OVER (ORDER BY name) - 1 AS feature FROM (SELECT DISTINCT name FROM tok)),
        posts AS MATERIALIZED (SELECT rid, feature, y FROM tok JOIN vocab USING (name) JOIN classes USING (rid))"""


def token_rows(target: str = "toxic", ngram: int = 1) -> str:
    if target == "lang":
        classes = "SELECT doc_id AS rid, CASE WHEN lang = 'en' THEN 1 ELSE 0 END AS y FROM documents"
    else:
        classes = f"SELECT doc_id AS rid, {target} AS y FROM labels SEMI JOIN documents USING (doc_id)"
    words = "regexp_extract_all(lower(text), '[a-z]+')"
    if ngram == 2:
        tokens = f"SELECT DISTINCT rid, unnest(list_transform(range(1, greatest(len(w), 1)), lambda i: w[i] || ' ' || w[i + 1])) AS name FROM (SELECT doc_id AS rid, {words} AS w FROM documents SEMI JOIN classes ON rid = doc_id)"
    else:
        tokens = f"SELECT DISTINCT doc_id AS rid, unnest({words}) AS name FROM documents SEMI JOIN classes ON rid = doc_id"
    return sparse_rows(classes, tokens)


def page_rows() -> str:
    classes = """SELECT page_id AS rid, CASE WHEN regexp_extract(html, 'lang="([a-z]+)"', 1) = 'en' THEN 1 ELSE 0 END AS y FROM pages"""
    return sparse_rows(classes, "SELECT DISTINCT page_id AS rid, unnest(regexp_extract_all(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[a-z]+')) AS name FROM pages")


def speaker_rows() -> str:
    rid = "conv_id * 1000000 + turn AS rid"
    classes = f"SELECT {rid}, CASE role WHEN 'assistant' THEN 0 WHEN 'system' THEN 1 WHEN 'user' THEN 2 END AS y FROM conversations"
    return sparse_rows(classes, f"SELECT DISTINCT {rid}, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]+')) AS name FROM conversations")


def g(c: str) -> str:
    return f"sum({c} * log2({c}))"


def relevance_of(cells: str = "cells") -> str:
    """rel(feature, rel) from cells(feature, x, y, c)."""
    return f"""h2 AS (SELECT feature, {g('c')} AS xy, sum(c) AS n FROM {cells} GROUP BY feature),
        hx AS (SELECT feature, {g('c')} AS x FROM (SELECT feature, x, sum(c) AS c FROM {cells} GROUP BY feature, x) GROUP BY feature),
        hy AS (SELECT feature, {g('c')} AS y FROM (SELECT feature, y, sum(c) AS c FROM {cells} GROUP BY feature, y) GROUP BY feature),
        rel AS (SELECT feature, greatest(log2(n) + (xy - x - y) / n, 0) AS rel FROM h2 JOIN hx USING (feature) JOIN hy USING (feature))"""


CELLS = "cells AS MATERIALIZED (SELECT feature, x, y, count(*) AS c FROM long GROUP BY feature, x, y)"
#: From posts and classes: the cells with code 0 by subtraction.
SPARSE_CELLS = """nz AS (SELECT feature, y, count(*) AS c FROM posts GROUP BY feature, y), tot AS (SELECT y, count(*) AS c FROM classes GROUP BY y),
        cells AS MATERIALIZED (SELECT feature, 1 AS x, y, c FROM nz UNION ALL
            SELECT v.feature, 0, t.y, t.c - coalesce(nz.c, 0) FROM vocab v CROSS JOIN tot t LEFT JOIN nz ON nz.feature = v.feature AND nz.y = t.y WHERE t.c > coalesce(nz.c, 0))"""


def relevance(base: str, features: Sequence[str]) -> str:
    return f"WITH {unpivoted(base, features)}, {CELLS}, {relevance_of()} SELECT {_name('feature', features)} AS name, round(rel, 6) + 0.0 AS rel FROM rel"


def relevance_sparse(rows: str) -> str:
    return f"WITH {rows}, {SPARSE_CELLS}, {relevance_of()} SELECT name, round(rel, 6) + 0.0 AS rel FROM rel JOIN vocab USING (feature)"


def _name(column: str, features: Sequence[str]) -> str:
    return f"[{', '.join(repr(f) for f in features)}][{column} + 1]"


def pairs(long: str = "long") -> str:
    """pair(i, k, mi, cmi) for all ordered pairs."""
    roll = lambda name, keys: f"{name} AS (SELECT i, k, {g('c')} AS {name} FROM (SELECT {', '.join(keys)}, sum(c) AS c FROM pc GROUP BY {', '.join(keys)}) GROUP BY i, k)"
    sets = {"xjy": ["i", "k", "x", "j", "y"], "xj": ["i", "k", "x", "j"], "xy": ["i", "k", "x", "y"], "jy": ["i", "k", "j", "y"], "sx": ["i", "k", "x"], "sj": ["i", "k", "j"], "sy": ["i", "k", "y"]}
    joins = " ".join(f"JOIN {s} USING (i, k)" for s in list(sets)[1:])
    return f"""pc AS MATERIALIZED (SELECT a.feature AS i, b.feature AS k, a.x, b.x AS j, a.y, count(*) AS c FROM {long} a JOIN {long} b USING (rid) GROUP BY ALL),
        {', '.join(roll(s, keys) for s, keys in sets.items())}, np AS (SELECT i, k, sum(c) AS n FROM pc GROUP BY i, k),
        pair AS MATERIALIZED (SELECT i, k, greatest(log2(n) + (xj - sx - sj) / n, 0) AS mi, greatest((xjy + sy - xy - jy) / n, 0) AS cmi FROM xjy {joins} JOIN np USING (i, k))"""


_SCORE = {
    "mim": "any_value(rel)",
    "mifs": "any_value(rel) - {beta} * sum(mi)",
    "jmi": "any_value(rel) - sum(mi) / {s} + sum(cmi) / {s}",
    "cmi": "any_value(rel) - sum(mi) + sum(cmi)",
    "mrmr": "any_value(rel) - sum(mi) / {s}",
    "cmim": "any_value(rel) - max(mi - cmi)",
    "if": "any_value(rel) - max(mi - cmi)",
    "icap": "any_value(rel) - sum(greatest(mi - cmi, 0))",
    "generic": "any_value(rel) - {beta} * sum(mi) + {gamma} * sum(cmi)",
}


def chain(criterion: str, k: int, name: str, beta: float = 1.0, gamma: float = 1.0) -> str:
    """The selection as one CTE for each step, over rel and pair; then step, name, score and rel."""
    parts = ["s1 AS MATERIALIZED (SELECT feature, rel AS score, rel FROM rel ORDER BY round(rel, 12) DESC, feature LIMIT 1)"]
    for t in range(2, k + 1):
        score = _SCORE[criterion].format(s=t - 1, beta=beta, gamma=gamma)
        chosen = " UNION ALL ".join(f"SELECT feature FROM s{i}" for i in range(1, t))
        parts.append(f"""s{t} AS MATERIALIZED (SELECT r.feature, {score} AS score, any_value(rel) AS rel FROM rel r JOIN pair p ON p.i = r.feature JOIN ({chosen}) c ON p.k = c.feature
            WHERE r.feature NOT IN ({chosen}) GROUP BY r.feature ORDER BY round(score, 12) DESC, r.feature LIMIT 1)""")
    union = " UNION ALL ".join(f"SELECT {t} AS step, * FROM s{t}" for t in range(1, k + 1))
    return f"{', '.join(parts)} SELECT CAST(step AS INT) AS step, {name} AS name, round(score, 6) + 0.0 AS score, round(rel, 6) + 0.0 AS rel FROM ({union}) u"


def greedy_by(base: str, by: str, values: Sequence[int], features: Sequence[str], criterion: str, k: int) -> str:
    """The selection within each value of a column."""
    one = lambda v: f"SELECT CAST({v} AS INT) AS {by}, step, name, score FROM ({greedy(f'SELECT * FROM ({base}) WHERE {by} = {v}', features, criterion, k)})"
    return " UNION ALL ".join(one(v) for v in values)


def greedy(base: str, features: Sequence[str], criterion: str, k: int, beta: float = 1.0, gamma: float = 1.0) -> str:
    return f"WITH {unpivoted(base, features)}, {CELLS}, {relevance_of()}, {pairs()}, {chain(criterion, k, _name('u.feature', features), beta, gamma)}"


def _gl(c: str) -> str:
    return f"CASE WHEN {c} > 0 THEN {c} * log2({c}) ELSE 0 END"


def greedy_sparse(rows: str, criterion: str, k: int) -> str:
    """Selection among all features of presence codes: each step counts the rows of the last chosen feature."""
    parts = [f"""tot AS (SELECT y, count(*) AS t FROM classes GROUP BY y), size AS (SELECT sum(t) AS n, sum({_gl('t')}) AS sy FROM tot),
        base AS MATERIALIZED (SELECT v.feature, tot.y, t, coalesce(c, 0) AS a FROM vocab v CROSS JOIN tot LEFT JOIN (SELECT feature, y, count(*) AS c FROM posts GROUP BY feature, y) z ON z.feature = v.feature AND z.y = tot.y),
        own AS MATERIALIZED (SELECT feature, sum({_gl('a')} + {_gl('(t - a)')}) AS xy, {_gl('sum(a)')} + {_gl('(sum(t) - sum(a))')} AS x FROM base GROUP BY feature),
        rel AS MATERIALIZED (SELECT feature, xy, x, greatest(log2(n) + (xy - x - sy) / n, 0) AS rel FROM own CROSS JOIN size),
        s1 AS MATERIALIZED (SELECT feature, rel AS score, rel FROM rel ORDER BY round(rel, 12) DESC, feature LIMIT 1)"""]
    cells = ("m", "(a - m)", "(f - m)", "(t - a - f + m)")
    for t in range(2, k + 1):
        j = f"(SELECT feature FROM s{t - 1})"
        parts.append(f"""q{t} AS MATERIALIZED (SELECT b.feature, b.y, t, a, coalesce(m, 0) AS m, coalesce(f, 0) AS f FROM base b
            LEFT JOIN (SELECT feature, y, count(*) AS m FROM posts WHERE rid IN (SELECT rid FROM posts WHERE feature = {j}) GROUP BY feature, y) z ON z.feature = b.feature AND z.y = b.y
            LEFT JOIN (SELECT y, count(*) AS f FROM posts WHERE feature = {j} GROUP BY y) o ON o.y = b.y),
        p{t} AS MATERIALIZED (SELECT feature, greatest(log2(n) + (xj - x - sj) / n, 0) AS mi, greatest((xjy + sy - xy - jy) / n, 0) AS cmi FROM
            (SELECT feature, sum({' + '.join(_gl(c) for c in cells)}) AS xjy, {' + '.join(_gl(f'sum({c})') for c in cells)} AS xj, sum({_gl('f')} + {_gl('(t - f)')}) AS jy, {_gl('sum(f)')} + {_gl('(sum(t) - sum(f))')} AS sj FROM q{t} GROUP BY feature)
            JOIN rel USING (feature) CROSS JOIN size)""")
        seen, chosen = (" UNION ALL ".join(f"SELECT {what} FROM {x}{i}" for i in range(low, low + t - 1)) for x, what, low in (("p", "*", 2), ("s", "feature", 1)))
        parts.append(f"""s{t} AS MATERIALIZED (SELECT feature, {_SCORE[criterion].format(s=t - 1, beta=1.0, gamma=1.0)} AS score, any_value(rel) AS rel FROM rel JOIN ({seen}) USING (feature)
            WHERE feature NOT IN ({chosen}) GROUP BY feature ORDER BY round(score, 12) DESC, feature LIMIT 1)""")
    union = " UNION ALL ".join(f"SELECT {t} AS step, * FROM s{t}" for t in range(1, k + 1))
    return f"WITH {rows}, {', '.join(parts)} SELECT CAST(step AS INT) AS step, name, round(score, 6) + 0.0 AS score, round(rel, 6) + 0.0 AS rel FROM ({union}) JOIN vocab USING (feature)"


def chi_square(base: str, features: Sequence[str], k: int) -> str:
    return f"""WITH {unpivoted(base, features)}, {CELLS}, fx AS (SELECT feature, x, sum(c) AS cx FROM cells GROUP BY ALL), fy AS (SELECT feature, y, sum(c) AS cy FROM cells GROUP BY ALL),
        st AS (SELECT feature, round(sum(cx * cy * 1.0 / n * power(coalesce(c, 0) / (cx * cy * 1.0 / n) - 1, 2)), 6) AS chi2 FROM fx JOIN fy USING (feature) LEFT JOIN cells USING (feature, x, y) CROSS JOIN (SELECT count(*) AS n FROM base) GROUP BY feature)
        SELECT CAST(step AS INT) AS step, name, chi2 FROM (SELECT row_number() OVER (ORDER BY chi2 DESC, feature) AS step, {_name('feature', features)} AS name, chi2 FROM st) WHERE step <= {k}"""


def auc_nb(target: str, features: Sequence[str], alias: str) -> str:
    """One row: label columns in ``alias`` and the test AUC of naive Bayes on these features."""
    train = bucket("l_orderkey") + " < 80"
    weights = ", ".join(
        f"w{i} AS (SELECT {f} AS x, ln((c1 + 1.0) / (n1 + v)) - ln((c0 + 1.0) / (n0 + v)) AS w FROM (SELECT {f}, sum(y) AS c1, sum(1 - y) AS c0 FROM tr GROUP BY {f}) CROSS JOIN pr CROSS JOIN (SELECT count(DISTINCT {f}) AS v FROM tr))"
        for i, f in enumerate(features)
    )
    joins = " ".join(f"LEFT JOIN w{i} ON w{i}.x = te.{f}" for i, f in enumerate(features))
    odds = " + ".join(f"coalesce(w{i}.w, 0)" for i in range(len(features)))
    return f"""(WITH b AS ({lines(target)}), tr AS (SELECT * FROM b WHERE {train}), te AS (SELECT * FROM b WHERE NOT {train}),
        pr AS (SELECT sum(y) AS n1, sum(1 - y) AS n0, ln((sum(y) + 1.0) / (sum(1 - y) + 1.0)) AS prior FROM tr), {weights},
        sc AS (SELECT te.y, round(prior + {odds}, 10) AS s FROM te CROSS JOIN pr {joins}),
        d AS (SELECT s, sum(y) AS p, sum(1 - y) AS q FROM sc GROUP BY s), r AS (SELECT p, q, sum(q) OVER (ORDER BY s) - q AS below FROM d)
        SELECT {alias}, round(sum(p * (below + q / 2.0)) / (sum(p) * sum(q) * 1.0), 6) + 0.0 AS auc FROM r)"""


def gate_features() -> list[str]:
    return list(GATE)


def event_features() -> list[str]:
    return list(EVENTS)
