"""DuckDB SQL for the queries: flat joins and sums, and loops written out; never the tiled forms."""

from __future__ import annotations

P = 2_147_483_647
K, ETA, CAP, RANK_ITERS = 4, "1e-5", "1.0", 5

CP = "(SELECT o_custkey AS i, l_partkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL)"
SP = "(SELECT l_suppkey AS i, l_partkey AS j, CAST(count(*) AS BIGINT) AS v FROM lineitem GROUP BY ALL)"
OP = "(SELECT l_orderkey AS i, l_partkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY ALL)"
KINDS = "(SELECT event_type, CAST(row_number() OVER (ORDER BY event_type) - 1 AS BIGINT) AS j FROM (SELECT DISTINCT event_type FROM events))"
UE = f"(SELECT user_id AS i, j, CAST(count(*) AS BIGINT) AS v FROM events JOIN {KINDS} USING (event_type) GROUP BY ALL)"
EMB = "(SELECT vec_id AS i, unnest(range(64)) AS j, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings)"
TC = """(SELECT doc_id, term, CAST(count(*) AS BIGINT) AS tf FROM
  (SELECT doc_id, unnest(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[a-z]+')) AS term FROM documents) GROUP BY ALL)"""
VOC = f"(SELECT term, CAST(row_number() OVER (ORDER BY term) - 1 AS BIGINT) AS idx FROM (SELECT term FROM {TC} GROUP BY term HAVING count(*) >= 5))"
DT = f"(SELECT doc_id AS i, idx AS j, tf AS v FROM {TC} JOIN {VOC} USING (term))"
NEXT_ALL = """(SELECT DISTINCT src, dst FROM (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem)
  WHERE dst IS NOT NULL)"""
NEXT = f"(SELECT * FROM {NEXT_ALL} WHERE src <> dst)"
HREF = """(SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path,
  unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages)"""
PAGES = f"(SELECT DISTINCT host || path AS src, host || href AS dst FROM {HREF})"
PATHS = f"(SELECT DISTINCT CAST(page_id AS VARCHAR) AS src, href AS dst FROM {HREF})"
CHAIN = """(SELECT src, dst, count(*) AS w FROM (SELECT event_type AS src, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events)
  WHERE dst IS NOT NULL GROUP BY ALL)"""
TRADE = """(SELECT c_nationkey AS src, s_nationkey AS dst, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey
  JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL)"""
USERS = "(SELECT src, dst, count(*) AS w FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL GROUP BY ALL)"

FLAGSHIP = f"SELECT a.i, b.i AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {SP} a JOIN {CP} b ON a.j = b.j GROUP BY a.i, b.i"
CELLS_SP = f"SELECT i, j, v FROM {SP}"


CUSTOMERS = "(SELECT c_custkey AS i FROM customer)"


def generated(rows: int | str, cols: int, density: float, seed: int) -> str:
    """rows: a number of rows, or a table of their numbers i."""
    x = f"SELECT r.i, s.j, (r.i * 7919 + s.j * 104729 + {seed * 1_299_709 + 12_345}) % {P} AS x FROM {f'range({rows})' if isinstance(rows, int) else rows} r(i), range({cols}) s(j)"
    return f"(SELECT i, j, (x * 16807 + 11) % {P} % 9 + 1 AS v FROM (SELECT i, j, (x * x + 16807) % {P} AS x FROM (SELECT i, j, (x * x + 48271) % {P} AS x FROM ({x}))) WHERE x < {int(density * P)})"


def ranks(edges: str, iters: int = RANK_ITERS, d: str | None = "0.85", dangling: str = "uniform", weighted: bool = False) -> str:
    """A chain of named steps ending in ``ranks`` (id, r)."""
    w = "w" if weighted else "1"
    out = f"""WITH e AS (SELECT src, dst, sum({w}) AS w FROM {edges} GROUP BY ALL), o AS (SELECT src, sum(w) AS w FROM e GROUP BY src),
p AS (SELECT e.src, dst, CAST(e.w AS DOUBLE) / o.w AS p FROM e JOIN o USING (src)),
n AS (SELECT id, id IN (SELECT src FROM o) AS linked, count(*) OVER () AS n FROM (SELECT src AS id FROM e UNION SELECT dst FROM e)),
r0 AS (SELECT id, linked, n, 1.0::DOUBLE / n AS r FROM n)"""
    for t in range(1, iters + 1):
        got = "coalesce(g.got, 0)"
        if dangling == "uniform":
            got += f" + (SELECT coalesce(sum(r), 0) / any_value(n) FROM r{t - 1} WHERE NOT linked)"
            got = got.replace(" / any_value(n)", "") .replace("coalesce(sum(r), 0)", "coalesce(sum(r / n), 0)")
        if dangling == "self":
            got += " + CASE WHEN x.linked THEN 0 ELSE x.r END"
        new = got if d is None else f"(1 - {d}::DOUBLE) / x.n + {d}::DOUBLE * ({got})"
        out += f""",
r{t} AS (SELECT x.id, x.linked, x.n, {new} AS r FROM r{t - 1} x LEFT JOIN (SELECT dst AS id, sum(p * r) AS got FROM p JOIN r{t - 1} ON p.src = r{t - 1}.id GROUP BY dst) g ON x.id = g.id)"""
    return out + f",\nranks AS (SELECT id, r FROM r{iters})"


def rounded(edges: str, **how) -> str:
    return ranks(edges, **how) + "\nSELECT id, round(r, 10) AS r FROM ranks"


def factor(rows: str, seed: int) -> str:
    return f"(SELECT r.i, s.j, (r.i * 7919 + s.j * 104729 + {seed}) % 1009 + 1 AS v FROM range((SELECT count(*) FROM {rows})) r(i), range({K}) s(j))"


W, H = factor("customer", 17), factor("part", 31)
X = f"SELECT a.j AS i, w.j, CAST(sum(a.v * w.v) AS BIGINT) AS v FROM {CP} a JOIN {W} w ON a.i = w.i GROUP BY a.j, w.j"
XW = f"SELECT a.i, h.j, CAST(sum(a.v * h.v) AS BIGINT) AS v FROM {CP} a JOIN {H} h ON a.j = h.i GROUP BY a.i, h.j"
GW = f"SELECT a.j AS i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {W} a JOIN {W} b ON a.i = b.i GROUP BY a.j, b.j"
GH = GW.replace(W, H)
Y = f"SELECT h.i, g.i AS j, CAST(sum(h.v * g.v) AS BIGINT) AS v FROM {H} h JOIN ({GW}) g ON h.j = g.j GROUP BY h.i, g.i"
YW = f"SELECT h.i, g.i AS j, CAST(sum(h.v * g.v) AS BIGINT) AS v FROM {W} h JOIN ({GH}) g ON h.j = g.j GROUP BY h.i, g.i"
NEW_H = f"SELECT h.i, h.j, CAST(h.v * coalesce(x.v, 0) AS DOUBLE) / y.v AS v FROM {H} h JOIN ({Y}) y ON h.i = y.i AND h.j = y.j LEFT JOIN ({X}) x ON h.i = x.i AND h.j = x.j"
NEW_W = f"SELECT h.i, h.j, CAST(h.v * coalesce(x.v, 0) AS DOUBLE) / y.v AS v FROM {W} h JOIN ({YW}) y ON h.i = y.i AND h.j = y.j LEFT JOIN ({XW}) x ON h.i = x.i AND h.j = x.j"


def divergence(h: str) -> str:
    return f"""SELECT (SELECT sum(CAST(v AS DOUBLE) * v) FROM {CP}) - 2 * (SELECT sum(CAST(a.v AS DOUBLE) * w.v * h.v) FROM {CP} a JOIN {W} w ON a.i = w.i JOIN {h} h ON a.j = h.i AND w.j = h.j)
  + (SELECT sum(CAST(g.v AS DOUBLE) * q.v) FROM ({GW}) g JOIN (SELECT a.j AS i, b.j, sum(CAST(a.v AS DOUBLE) * b.v) AS v FROM {h} a JOIN {h} b ON a.i = b.i GROUP BY a.j, b.j) q USING (i, j)) AS error"""


SVM_Y = "(SELECT doc_id AS i, CASE WHEN lang = 'en' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM documents)"


def svm_slope(bias: str) -> str:
    """Gradient at alpha = ETA everywhere, through the features."""
    return f"""WITH t AS MATERIALIZED (SELECT * FROM {DT}), y AS MATERIALIZED (SELECT * FROM {SVM_Y}),
w AS (SELECT j, sum(v * y * {ETA}::DOUBLE) AS w FROM t JOIN y USING (i) GROUP BY j), k AS (SELECT i, sum(v * w) AS k FROM t JOIN w USING (j) GROUP BY i),
g AS (SELECT y.i, 1 - y * (coalesce(k, 0) + {bias} * (SELECT sum(y * {ETA}::DOUBLE) FROM y)) AS g FROM y LEFT JOIN k USING (i))"""


_PART_RANKS = ranks(NEXT) + ", pr AS (SELECT id, round(r, 12) AS r FROM ranks), pl AS (SELECT id, r, row_number() OVER (ORDER BY r DESC, id) AS place, count(*) OVER () AS n FROM pr)"
_IN = "(SELECT dst AS id, CAST(count(DISTINCT src) AS BIGINT) AS in_links FROM {} GROUP BY dst)"


#: Normal quantile of p by halving the distribution function's power series: phi(z) (z + z^3 / 3 + z^5 / (3 5) + ...).
_SERIES = "list_sum(list_transform(range(0, 70), lambda k: exp((2 * k + 1) * ln(greatest(mid, 1e-12)) - lo[k + 1])))"
_ODD = "(SELECT list(s ORDER BY k) AS lo FROM (SELECT k, sum(ln(2 * k + 1)) OVER (ORDER BY k) AS s FROM range(0, 70) t(k)))"


LOGNORMAL = f"""{_PART_RANKS.replace('WITH e AS', 'WITH RECURSIVE e AS', 1)}, lp AS (SELECT id, ln(r) AS ln_r, (n - place + 0.5) / CAST(n AS DOUBLE) AS p FROM pl WHERE r > 0), h(p, low, high, step) AS (SELECT DISTINCT greatest(p, 1 - p), 0.0::DOUBLE, 7.0::DOUBLE, 0 FROM lp UNION ALL
SELECT p, CASE WHEN up THEN mid ELSE low END, CASE WHEN up THEN high ELSE mid END, step + 1 FROM (SELECT p, low, high, mid, step, 0.5 + exp(-mid * mid / 2) / sqrt(2 * pi()) * {_SERIES} < p AS up FROM (SELECT *, (low + high) / 2 AS mid FROM h WHERE step < 45), {_ODD})),
z AS (SELECT id, ln_r, CASE WHEN lp.p < 0.5 THEN -(low + high) / 2 ELSE (low + high) / 2 END AS z FROM lp JOIN h ON h.p = greatest(lp.p, 1 - lp.p) AND step = 45)"""


def _stripe(index: str, length: str, n: int) -> str:
    return f"least({index} // greatest(1, ({length} + {n} - 1) // {n}), {n} - 1)"


def _partials(n: int) -> str:
    parts = "(SELECT count(*) FROM part)"
    copies = f"least(20, (SELECT count(*) FROM customer)) * (SELECT count(*) FROM {SP}) + least(20, (SELECT count(*) FROM supplier)) * (SELECT count(*) FROM {CP})"
    return f"SELECT {n}::BIGINT AS n, CAST({copies} AS BIGINT) AS copied, (SELECT count(*) FROM (SELECT DISTINCT {_stripe('a.j', parts, n)}, a.i, b.i FROM {SP} a JOIN {CP} b ON a.j = b.j)) AS partials"


def _margins(how: str) -> str:
    return f"SELECT coalesce(i, -1) AS i, coalesce(j, -1) AS j, CAST(sum(v) AS BIGINT) AS total, count(v) AS nnz FROM {UE} GROUP BY {how}"


SVM_STEPS, SVM_POWER = 20, 4
_TERMS = f"(SELECT i, j, v / sqrt(sum(v * v) OVER (PARTITION BY i)) AS v FROM {DT})"
_EMBEDDED = "(SELECT vec_id AS i, CASE WHEN label = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y, vec_id % 5 = 0 AS is_test FROM embeddings)"


def _labelled(yes: str) -> str:
    return f"(SELECT doc_id AS i, CASE WHEN {yes} THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y, (row_number() OVER (ORDER BY doc_id) - 1) % 5 = 0 AS is_test FROM documents JOIN labels USING (doc_id))"


def trained(terms: str, labels: str) -> str:
    """Gradient steps written out: power method for the step, then the trainer through the features, then the test rows."""
    out = f"WITH l AS MATERIALIZED (SELECT * FROM {labels}), t AS MATERIALIZED (SELECT * FROM {terms}), o AS MATERIALIZED (SELECT t.* FROM t JOIN l USING (i) WHERE NOT is_test), x0 AS (SELECT i, 1.0::DOUBLE AS v FROM l WHERE NOT is_test)"
    through = lambda state, column: f"(SELECT i, sum(o.v * w.w) AS k FROM o JOIN (SELECT j, sum(o.v * {column}) AS w FROM o JOIN {state} s USING (i) GROUP BY j) w USING (j) GROUP BY i)"
    for r in range(SVM_POWER + 1):
        out += f", y{r} AS MATERIALIZED (SELECT x.i, x.v AS x, coalesce(k, 0) + (SELECT sum(v) FROM x{r}) AS v FROM x{r} x LEFT JOIN {through(f'x{r}', 's.v')} USING (i)), x{r + 1} AS MATERIALIZED (SELECT i, v / (SELECT sum(abs(v)) FROM y{r}) AS v FROM y{r})"
    out += f", eta AS MATERIALIZED (SELECT sum(x * x) / sum(x * v) AS eta FROM y{SVM_POWER}), a0 AS (SELECT i, y, 0.0::DOUBLE AS v FROM l WHERE NOT is_test)"
    for r in range(SVM_STEPS):
        out += f", a{r + 1} AS MATERIALIZED (SELECT a.i, a.y, greatest(0, least(1, a.v + eta * (1 - a.y * (coalesce(k, 0) + (SELECT sum(y * v) FROM a{r}))))) AS v FROM a{r} a LEFT JOIN {through(f'a{r}', 's.y * s.v')} USING (i), eta)"
    out += f""", w AS (SELECT j, sum(o.v * s.y * s.v) AS w FROM o JOIN a{SVM_STEPS} s USING (i) GROUP BY j), m AS (SELECT t.i, sum(t.v * w) AS m FROM t JOIN w USING (j) GROUP BY t.i),
q AS (SELECT l.i, l.y, CASE WHEN coalesce(m, 0) + (SELECT sum(y * v) FROM a{SVM_STEPS}) >= 0 THEN 1 ELSE -1 END AS g FROM l LEFT JOIN m USING (i) WHERE is_test)
SELECT count(*) AS rows, count(*) FILTER (y = g) AS right, round(avg((y = g)::INT), 9) AS accuracy, round((coalesce(avg((y = g)::INT) FILTER (y = 1), 0) + coalesce(avg((y = g)::INT) FILTER (y = -1), 0)) / 2, 9) AS balanced,
  round(greatest(avg((y = 1)::INT), 1 - avg((y = 1)::INT)), 9) AS majority FROM q"""
    return out


def one_against_rest(steps: int = 10, eta: str = "0.001") -> str:
    """All languages against their rests on four fifths of the documents."""
    out = f"""WITH d AS (SELECT doc_id AS i, lang FROM documents WHERE lang IS NOT NULL), c AS (SELECT DISTINCT lang AS c FROM d), t AS MATERIALIZED (SELECT * FROM {_TERMS}),
o AS MATERIALIZED (SELECT t.* FROM t JOIN d USING (i) WHERE i % 5 <> 0), a0 AS (SELECT i, c, CASE WHEN lang = c THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y, 0.0::DOUBLE AS v FROM d, c WHERE i % 5 <> 0)"""
    for r in range(steps):
        out += f""", a{r + 1} AS MATERIALIZED (SELECT a.i, a.c, a.y, greatest(0, least(1, a.v + {eta}::DOUBLE * (1 - a.y * (coalesce(k, 0) + b)))) AS v FROM a{r} a JOIN (SELECT c, sum(y * v) AS b FROM a{r} GROUP BY c) USING (c)
LEFT JOIN (SELECT i, c, sum(o.v * w) AS k FROM o JOIN (SELECT j, c, sum(o.v * s.y * s.v) AS w FROM o JOIN a{r} s USING (i) GROUP BY j, c) USING (j) GROUP BY i, c) USING (i, c))"""
    return out + f""", w AS (SELECT j, c, sum(o.v * s.y * s.v) AS w FROM o JOIN a{steps} s USING (i) GROUP BY j, c), b AS (SELECT c, sum(y * v) AS b FROM a{steps} GROUP BY c),
m AS (SELECT d.i, c, lang, b + coalesce(k, 0) AS m FROM d CROSS JOIN b LEFT JOIN (SELECT t.i, c, sum(t.v * w) AS k FROM t JOIN w USING (j) GROUP BY t.i, c) USING (i, c) WHERE d.i % 5 = 0)
SELECT count(*) AS rows, CAST(sum((c = lang)::INT) AS BIGINT) AS right FROM (SELECT i, c, lang, row_number() OVER (PARTITION BY i ORDER BY m DESC, c) AS q FROM m) WHERE q = 1"""


def fitted(rounds: int = 3) -> str:
    """Errors of H and W updates written out, from positive factors of rank 4."""
    factor_of = lambda rows, seed: f"(SELECT r.i, s.j, ((r.i * 7919 + s.j * 104729 + {seed}) % 1009 + 1) / 1010.0::DOUBLE AS v FROM range((SELECT count(*) FROM {rows})) r(i), range(4) s(j))"
    out = f"WITH a AS MATERIALIZED (SELECT * FROM {CP}), w0 AS MATERIALIZED (SELECT * FROM {factor_of('customer', 17)}), h0 AS MATERIALIZED (SELECT * FROM {factor_of('part', 31)})"
    error = lambda w, h: f"""(SELECT (SELECT sum(v::DOUBLE * v) FROM a) - 2 * (SELECT sum(a.v * w.v * h.v) FROM a JOIN {w} w ON a.i = w.i JOIN {h} h ON a.j = h.i AND w.j = h.j)
 + (SELECT sum(p.v * q.v) FROM (SELECT x.j AS r, y.j AS s, sum(x.v * y.v) AS v FROM {w} x JOIN {w} y USING (i) GROUP BY ALL) p JOIN (SELECT x.j AS r, y.j AS s, sum(x.v * y.v) AS v FROM {h} x JOIN {h} y USING (i) GROUP BY ALL) q USING (r, s)))"""  # noqa: E731

    def update(new: str, own: str, other: str, here: str, there: str) -> str:
        return f""", {new} AS MATERIALIZED (SELECT o.i, o.j, o.v * coalesce(x.v, 0) / y.v AS v FROM {own} o
LEFT JOIN (SELECT a.{here} AS i, f.j, sum(a.v * f.v) AS v FROM a JOIN {other} f ON a.{there} = f.i GROUP BY a.{here}, f.j) x ON o.i = x.i AND o.j = x.j
JOIN (SELECT o.i, g.r AS j, sum(o.v * g.v) AS v FROM {own} o JOIN (SELECT p.j AS r, q.j AS s, sum(p.v * q.v) AS v FROM {other} p JOIN {other} q USING (i) GROUP BY ALL) g ON o.j = g.s GROUP BY o.i, g.r) y ON o.i = y.i AND o.j = y.j)"""

    errors = [error("w0", "h0")]
    for r in range(rounds):
        out += update(f"h{r + 1}", f"h{r}", f"w{r}", "j", "i")
        errors.append(error(f"w{r}", f"h{r + 1}"))
        out += update(f"w{r + 1}", f"w{r}", f"h{r + 1}", "i", "j")
        errors.append(error(f"w{r + 1}", f"h{r + 1}"))
    return out + " " + " UNION ALL ".join(f"SELECT {k}::BIGINT AS step, CAST(printf('%.7e', {e}) AS DOUBLE) AS error" for k, e in enumerate(errors))


def _pid(placement: str) -> str:
    if placement == "row":
        return "alpha % 8"
    mixed = "xor(alpha::BIGINT * 73856093, beta::BIGINT * 19349663)"
    if placement == "random":
        mixed = f"xor({mixed}, gamma::BIGINT * 83492791)"
    return f"((({mixed} % 2147483648) * 48271) >> 8) % 8"


def _balance(placement: str) -> str:
    """Copies of the left operand on a 20 x 6 x 20 grid by worker."""
    edge = "(SELECT count(*) FROM supplier)"
    tags = f"(SELECT {_stripe('i', edge, 20)} AS alpha, {_stripe('j', '(SELECT count(*) FROM part)', 6)} AS gamma, unnest(range(least(20, {edge}))) AS beta FROM {SP})".replace(", 20 - 1)", f", least(20, {edge}) - 1)")
    return f"SELECT '{placement}' AS placement, count(*) AS busy, CAST(max(n) AS BIGINT) AS most, CAST(sum(n) AS DOUBLE) / 8 AS mean FROM (SELECT {_pid(placement)} AS pid, count(*) AS n FROM {tags} GROUP BY pid)"


def _moved(placement: str, m: int) -> str:
    """Copies and partial cells on an m x 6 x m grid (held to the edges' lengths)."""
    a, b, c = ("(SELECT count(*) FROM supplier)", "(SELECT count(*) FROM part)", "(SELECT count(*) FROM customer)")
    stripe = lambda index, edge, n: f"least({index} // greatest(1, ({edge} + least({n}, {edge}) - 1) // least({n}, {edge})), least({n}, {edge}) - 1)"
    copies = f"CAST(least({m}, {c}) * (SELECT count(*) FROM {SP}) + least({m}, {a}) * (SELECT count(*) FROM {CP}) AS BIGINT)"
    parts = f"(SELECT {stripe('a.i', a, m)} AS alpha, {stripe('b.i', c, m)} AS beta, {stripe('a.j', b, 6)} AS gamma, a.i, b.i AS j FROM {SP} a JOIN {CP} b ON a.j = b.j GROUP BY ALL)"
    moved = "0::BIGINT" if placement != "random" else f"(SELECT count(*) FROM (SELECT DISTINCT {_pid('random')} AS pid, {_pid('tile')} AS home, alpha, beta, i, j FROM {parts}) WHERE pid <> home)"
    return f"SELECT placement, m, copied, partials, moved, copied * 36 + moved * 32 AS moved_bytes FROM (SELECT '{placement}' AS placement, {m}::BIGINT AS m, {copies} AS copied, (SELECT count(*) FROM {parts}) AS partials, {moved} AS moved)"


SQL = {
    "svm_language": trained(_TERMS, _labelled("lang = 'en'")),
    "svm_quality": trained(_TERMS, _labelled("quality = 1")),
    "svm_toxic": trained(_TERMS, _labelled("toxic = 1")),
    "svm_embedding_label": trained(EMB, _EMBEDDED),
    "svm_multiclass_language": one_against_rest(),
    "nmf_fit": fitted(),
    "nmf_x_tiled": X,
    "placement_balance_by_placement": " UNION ALL ".join(map(_balance, ("row", "tile", "random"))),
    "intermediate_size_by_placement": " UNION ALL ".join(_moved(p, m) for p, m in (("row", 20), ("tile", 20), ("random", 20), ("random", 40))),
    "distinct_terms_approx": f"""WITH h AS (SELECT DISTINCT CAST('0x' || substr(md5(term), 1, 12) AS BIGINT) AS h FROM {TC} ORDER BY h LIMIT 1024)
SELECT CASE WHEN count(*) < 1024 THEN count(*) ELSE CAST(floor(1023 * pow(2.0::DOUBLE, 48) / max(h)) AS BIGINT) END AS terms FROM h""",
    "event_as_of_order": """WITH o AS (SELECT o_orderkey, o_custkey, CAST(date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS day FROM orders)
SELECT a.o_orderkey, a.o_custkey, a.day - 1 AS day, (SELECT arg_max(b.o_orderkey, (b.day, b.o_orderkey)) FROM o b WHERE b.o_custkey = a.o_custkey AND b.day < a.day) AS last_order FROM o a""",
    "events_in_spans": """SELECT s.event_id AS span, e.event_type, count(*) AS n FROM events s JOIN events e ON s.event_id % 50 = 0 AND e.ts >= s.ts AND e.ts < s.ts + INTERVAL 40 MINUTE GROUP BY ALL""",
    "gram_pairs_udtf": f"SELECT a.j AS i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {OP} a JOIN {OP} b ON a.i = b.i WHERE a.j <= b.j GROUP BY a.j, b.j",
    **dict.fromkeys(
        ("product_supplier_customer", "product_row_placement", "product_random_placement", "product_random_placement_fine", "product_tile_placement", "product_uncombined", "product_staged", "product_planned",
         "product_rows_only", "product_inner_only", "product_columns_only", "product_rows_columns", "product_cells", "tile_product_arrow", "sql_surface_product"), FLAGSHIP),
    "product_broadcast": f"SELECT a.j AS i, g.j, CAST(sum(a.v * g.v) AS BIGINT) AS v FROM {SP} a JOIN (SELECT a.i, b.i AS j, sum(a.v * b.v) AS v FROM {SP} a JOIN {SP} b ON a.j = b.j GROUP BY a.i, b.i) g ON a.i = g.i GROUP BY a.j, g.j",
    "product_broadcast_transposed": f"SELECT b.i, a.i AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {SP} a JOIN {CP} b ON a.j = b.j GROUP BY a.i, b.i",
    "product_broadcast_rows": f"SELECT i, s.j, round(sum(v * ((3 * e.j + s.j) % 7)), 6) + 0.0 AS v FROM {EMB} e, range(4) s(j) GROUP BY i, s.j",
    "matrix_vector": f"SELECT i, CAST(sum(v * (j % 11)) AS BIGINT) AS v FROM {CP} GROUP BY i",
    "generator_cells": f"SELECT * FROM {generated(CUSTOMERS, 80, 0.125, 3)}",
    "product_generated": f"SELECT a.i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {generated(CUSTOMERS, 80, 0.125, 3)} a JOIN {generated(80, 64, 0.125, 4)} b ON a.j = b.i GROUP BY a.i, b.j",
    "gram_suppliers": f"SELECT a.i, b.i AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {SP} a JOIN {SP} b ON a.j = b.j GROUP BY a.i, b.i",
    "gram_parts": f"SELECT a.j AS i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {OP} a JOIN {OP} b ON a.i = b.i GROUP BY a.j, b.j",
    "gram_customers": f"SELECT a.i, b.i AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {CP} a JOIN {CP} b ON a.j = b.j GROUP BY a.i, b.i",
    "doc_term_gram": f"WITH t AS MATERIALIZED (SELECT * FROM {DT}) SELECT a.i, b.i AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM t a JOIN t b ON a.j = b.j WHERE a.i % 20 = 0 GROUP BY a.i, b.i",
    "placement_balance": f"""WITH s AS (SELECT count(*) AS a FROM supplier), g AS (SELECT least(20, a) AS m, a FROM s),
p AS (SELECT least(i // greatest(1, (a + m - 1) // m), m - 1) % 8 AS pid, m FROM {SP}, g), c AS (SELECT pid, count(*) * any_value(m) AS n FROM p GROUP BY pid)
SELECT count(*) AS busy, CAST(max(n) AS BIGINT) AS most, CAST(sum(n) AS DOUBLE) / 8 AS mean FROM c""",
    "intermediate_size_by_grid": " UNION ALL ".join(map(_partials, (1, 3, 6, 12))),
    "scalar_multiplications": f"SELECT CAST(sum(x * y) AS BIGINT) AS flops FROM (SELECT j, count(*) AS x FROM {SP} GROUP BY j) JOIN (SELECT j, count(*) AS y FROM {CP} GROUP BY j) USING (j)",
    "density_stats": " UNION ALL ".join(
        f"SELECT '{name}' AS name, (SELECT count(*) FROM {r}) AS n_rows, (SELECT count(*) FROM part) AS n_cols, count(*) AS nnz, CAST(count(*) AS DOUBLE) / ((SELECT count(*) FROM {r}) * (SELECT count(*) FROM part)) AS density FROM {m}"
        for name, r, m in (("cust_part", "customer", CP), ("supp_part", "supplier", SP), ("order_part", "orders", OP))
    ),
    "embedding_dots": f"SELECT a.i, b.i AS j, round(sum(a.v * b.v), 6) + 0.0 AS v FROM {EMB} a JOIN {EMB} b ON a.j = b.j WHERE a.i % 20 = 0 GROUP BY a.i, b.i",
    "embedding_distances": f"""WITH d AS (SELECT a.i, b.i AS j, sum(a.v * b.v) AS d FROM {EMB} a JOIN {EMB} b ON a.j = b.j WHERE a.i % 20 = 0 GROUP BY a.i, b.i), n AS (SELECT i, sum(v * v) AS n FROM {EMB} GROUP BY i)
SELECT d.i, d.j, round(greatest(0, x.n + y.n - 2 * d), 6) + 0.0 AS v FROM d JOIN n x ON d.i = x.i JOIN n y ON d.j = y.i""",
    "embedding_topk": f"""WITH d AS (SELECT a.i, b.i AS j, sum(a.v * b.v) AS d FROM {EMB} a JOIN {EMB} b ON a.j = b.j WHERE a.i % 20 = 0 AND a.i <> b.i GROUP BY a.i, b.i), n AS (SELECT i, sum(v * v) AS n FROM {EMB} GROUP BY i),
c AS (SELECT d.i, d.j, round(d / sqrt(x.n * y.n), 9) AS v FROM d JOIN n x ON d.i = x.i JOIN n y ON d.j = y.i)
SELECT i, j, round(v, 6) + 0.0 AS v, place FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS place FROM c) WHERE place <= 5""",
    "document_cosine_topk": f"""WITH t AS MATERIALIZED (SELECT * FROM {DT}), d AS (SELECT a.i, b.i AS j, sum(a.v * b.v) AS d FROM t a JOIN t b ON a.j = b.j WHERE a.i % 20 = 0 AND a.i <> b.i GROUP BY a.i, b.i),
n AS (SELECT i, sum(v * v) AS n FROM t GROUP BY i), c AS (SELECT d.i, d.j, round(CAST(d AS DOUBLE) / sqrt(CAST(x.n * y.n AS DOUBLE)), 9) AS v FROM d JOIN n x ON d.i = x.i JOIN n y ON d.j = y.i)
SELECT i, j, round(v, 6) + 0.0 AS v, place FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS place FROM c) WHERE place <= 3""",
    "nearest_centroid": f"""WITH e AS MATERIALIZED (SELECT * FROM {EMB}), c AS (SELECT CAST(label AS BIGINT) AS c, j, avg(v) AS v FROM e JOIN (SELECT vec_id AS i, label FROM embeddings) USING (i) GROUP BY ALL),
n AS (SELECT c, sum(v * v) AS n FROM c GROUP BY c), d AS (SELECT i, c, sum(e.v * c.v) AS d FROM e JOIN c USING (j) GROUP BY ALL)
SELECT i, j FROM (SELECT i, c AS j, row_number() OVER (PARTITION BY i ORDER BY round(n - 2 * d, 9), c) AS q FROM d JOIN n USING (c)) WHERE q = 1""",
    "svm_language_alpha": f"{svm_slope('1')} SELECT i, round(greatest(0, least({CAP}, {ETA}::DOUBLE + {ETA}::DOUBLE * g)), 12) + 0.0 AS v FROM g",
    "svm_language_alpha_materialised": f"{svm_slope('1')} SELECT i, round(greatest(0, least({CAP}, {ETA}::DOUBLE + {ETA}::DOUBLE * g)), 12) + 0.0 AS v FROM g",
    "svm_language_gradient": f"{svm_slope('0')} SELECT i, round(g, 9) + 0.0 AS v FROM g",
    "svm_kernel_stats": f"""WITH ids AS (SELECT i, row_number() OVER (ORDER BY i) - 1 AS p FROM (SELECT DISTINCT doc_id AS i FROM labels WHERE doc_id IN (SELECT doc_id FROM documents))),
t AS MATERIALIZED (SELECT p, j, v FROM {DT} JOIN ids USING (i)), k AS (SELECT greatest(a.p, b.p) AS reach FROM t a JOIN t b ON a.j = b.j GROUP BY a.p, b.p, greatest(a.p, b.p)),
m AS (SELECT count(*) AS n FROM ids), s AS (SELECT (25 * pow(2, q))::BIGINT AS n FROM range(40) t(q), m WHERE q = 0 OR 25 * pow(2, q - 1) < m.n), r AS (SELECT n, count(*) AS n_rows FROM s JOIN ids ON p < n GROUP BY n), c AS (SELECT n, count(*) AS nnz FROM s JOIN k ON reach < n GROUP BY n)
SELECT n, n_rows, nnz, CAST(nnz AS DOUBLE) / (n_rows * n_rows) AS density, nnz * 24 AS bytes FROM r JOIN c USING (n)""",
    "nmf_x": X,
    "nmf_gram": GW,
    "nmf_y": Y,
    "nmf_h_update": NEW_H,
    "nmf_w_update": NEW_W,
    "nmf_divergence_trace": f"""WITH nh AS MATERIALIZED ({NEW_H}) SELECT step, CAST(printf('%.8e', error) AS DOUBLE) AS error FROM (SELECT 0::BIGINT AS step, error FROM ({divergence(H)}) UNION ALL SELECT 1, error FROM ({divergence('nh')}))""",
    "nmf_reconstruct": f"SELECT a.i, a.j, CAST(sum(w.v * h.v) AS BIGINT) AS v FROM {CP} a JOIN {W} w ON a.i = w.i JOIN {H} h ON a.j = h.i AND w.j = h.j GROUP BY a.i, a.j",
    "pagerank_part_graph": rounded(NEXT),
    "pagerank_page_links": rounded(PAGES),
    "pagerank_page_links_drop": rounded(PAGES, dangling="drop"),
    "pagerank_page_links_self": rounded(PAGES, dangling="self"),
    "pagerank_undamped": rounded(NEXT, d=None),
    "pagerank_path_targets": rounded(PATHS),
    "pagerank_mass": " UNION ALL ".join(f"SELECT '{k}' AS dangling, mass FROM ({ranks(PAGES, dangling=k)} SELECT round(sum(r), 9) AS mass FROM ranks)" for k in ("uniform", "drop", "self")),
    "pagerank_top10_inlinks": f"""{ranks(PATHS)}, pr AS (SELECT id, round(r, 12) AS r FROM ranks), li AS (SELECT * FROM {_IN.format(PATHS)}),
cut AS (SELECT min(in_links) AS edge FROM (SELECT in_links FROM li ORDER BY in_links DESC, id LIMIT 100)), b AS (SELECT id, r, row_number() OVER (ORDER BY r DESC, id) AS place FROM pr)
SELECT place, id, round(r, 10) AS r, coalesce(in_links, 0) AS in_links, coalesce(in_links, 0) >= edge AS in_cut FROM b LEFT JOIN li USING (id), cut WHERE place <= 10""",
    "rank_curve": f"{_PART_RANKS} SELECT place, id, round(ln(CAST(place AS DOUBLE)), 9) AS ln_place, round(ln(CASE WHEN r > 0 THEN r END), 7) AS ln_r FROM pl",
    "rank_curve_slope": f"{_PART_RANKS} SELECT round(regr_slope(ln(r), ln(CAST(place AS DOUBLE))), 6) AS slope, round(regr_r2(ln(r), ln(CAST(place AS DOUBLE))), 6) AS r2 FROM pl WHERE r > 0",
    "lognormal_plot": f"{LOGNORMAL} SELECT id, round(ln_r, 7) AS ln_r, round(z, 5) + 0.0 AS z FROM z",
    "lognormal_straightness": f"{LOGNORMAL} SELECT round(corr(ln_r, z), 6) AS straightness FROM z",
    "tail_plateau": f"{ranks(PAGES)} SELECT round(r, 10) AS r, count(*) AS pages FROM ranks GROUP BY round(r, 10) ORDER BY r LIMIT 1",
    "rank_running_mass": f"{ranks(PATHS)}, pr AS (SELECT id, round(r, 12) AS r FROM ranks) SELECT id, round(sum(r) OVER (ORDER BY r DESC, id ROWS UNBOUNDED PRECEDING), 8) AS mass FROM pr",
    "event_chain_stationary": rounded(CHAIN, iters=8, d=None, weighted=True),
    "nation_trade_stationary": rounded(TRADE, iters=8, d=None, weighted=True),
    "user_next_stationary": rounded(USERS, d=None, weighted=True),
    "power_method_gram": f"WITH k AS MATERIALIZED (SELECT a.i, b.i AS j, CAST(sum(a.v * b.v) AS DOUBLE) AS v FROM {SP} a JOIN {SP} b ON a.j = b.j GROUP BY a.i, b.i), x0 AS (SELECT DISTINCT i, 1.0::DOUBLE AS v FROM k)"
    + "".join(f", y{t} AS (SELECT k.i, sum(k.v * x.v) AS v FROM k JOIN x{t - 1} x ON k.j = x.i GROUP BY k.i), x{t} AS (SELECT i, v / (SELECT sum(abs(v)) FROM y{t}) AS v FROM y{t})" for t in range(1, 5))
    + " SELECT i, round(v, 10) AS v FROM x4",
    "linear_gd_orders": """WITH s AS MATERIALIZED (SELECT l_partkey AS j, sum(l_quantity) / 1000 AS q, max(p_retailprice) / 1000 AS p, sum(l_extendedprice) / 1e6::DOUBLE AS y FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY l_partkey),
t0 AS (SELECT 0.0::DOUBLE AS a, 0.0::DOUBLE AS b, 0.0::DOUBLE AS c)"""
    + "".join(f", t{t} AS (SELECT any_value(a) + 1e-5::DOUBLE * sum(q * (y - a * q - b * p - c)) AS a, any_value(b) + 1e-5::DOUBLE * sum(p * (y - a * q - b * p - c)) AS b, any_value(c) + 1e-5::DOUBLE * sum(y - a * q - b * p - c) AS c FROM s, t{t - 1})" for t in (1, 2, 3))
    + " SELECT 0::BIGINT AS i, round(a, 7) + 0.0 AS v FROM t3 UNION ALL SELECT 1, round(b, 7) + 0.0 FROM t3 UNION ALL SELECT 2, round(c, 7) + 0.0 FROM t3",
    "cells_roundtrip": CELLS_SP,
    "cells_from_csv": f"SELECT i, j, CAST(v AS DOUBLE) AS v FROM {SP}",
    "cells_tiles": CELLS_SP,
    "cells_rows": f"SELECT i, j, CAST(v AS DOUBLE) AS v FROM {SP}",
    "sparse_vector_maps": f"SELECT i, j, CAST(v AS DOUBLE) AS v FROM {UE}",
    "matrix_slice": f"SELECT i, j, v FROM {CP} WHERE i >= 10 AND i < 60 AND j >= 5 AND j < 105",
    "matrix_transpose": f"SELECT j AS i, i AS j, v FROM {SP}",
    "matrix_add": f"SELECT coalesce(a.i, b.i) AS i, coalesce(a.j, b.j) AS j, CAST(2 * coalesce(a.v, 0) + coalesce(b.v, 0) AS BIGINT) AS v FROM {SP} a FULL JOIN (SELECT * FROM {CP} WHERE i < (SELECT count(*) FROM supplier)) b ON a.i = b.i AND a.j = b.j",
    "matrix_hadamard": f"SELECT i, j, CAST(a.v * b.v AS BIGINT) AS v FROM {SP} a JOIN {CP} b USING (i, j)",
    "matrix_ratio": f"SELECT a.i, a.j, CAST(a.v AS DOUBLE) / coalesce(CAST(b.v AS DOUBLE), 0.5::DOUBLE) AS v FROM {SP} a LEFT JOIN {CP} b ON a.i = b.i AND a.j = b.j",
    "matrix_margins": _margins("GROUPING SETS ((i), (j), ())"),
    "matrix_margins_cube": _margins("CUBE (i, j)"),
    "matrix_margins_rollup": _margins("ROLLUP (i, j)"),
    "support_intersect": f"SELECT i, j FROM {SP} INTERSECT SELECT i, j FROM {CP}",
    "support_except": f"SELECT i, j FROM {SP} EXCEPT SELECT i, j FROM {CP}",
    "edges_union_dedup": f"SELECT src, dst FROM {NEXT} UNION SELECT dst, src FROM {NEXT}",
    "dangling_nodes": f"SELECT DISTINCT dst AS id FROM {PAGES} WHERE dst NOT IN (SELECT src FROM {PAGES})",
    "linked_parts": f"SELECT p_partkey FROM part WHERE p_partkey IN (SELECT src FROM {NEXT})",
    "nodes_without_inlinks": f"SELECT DISTINCT src AS id FROM {PAGES} WHERE src NOT IN (SELECT dst FROM {PAGES})",
    "similar_pairs_triangular": f"""WITH n AS (SELECT i, sum(v * v) AS n FROM {SP} GROUP BY i), d AS (SELECT a.i, b.i AS j, sum(a.v * b.v) AS d FROM {SP} a JOIN {SP} b ON a.j = b.j WHERE a.i < b.i GROUP BY a.i, b.i),
c AS (SELECT d.i, d.j, CAST(d AS DOUBLE) / sqrt(CAST(x.n * y.n AS DOUBLE)) AS v FROM d JOIN n x ON d.i = x.i JOIN n y ON d.j = y.i) SELECT i, j, round(v, 6) + 0.0 AS v FROM c WHERE v >= 0.04""",
    "degree_histogram_range": f"SELECT CASE WHEN in_links < 10 THEN 0 WHEN in_links < 20 THEN 1 WHEN in_links < 40 THEN 2 WHEN in_links < 80 THEN 3 ELSE 4 END::BIGINT AS bin, count(*) AS n FROM {_IN.format(NEXT)} GROUP BY bin",
    "degree_percentiles": f"SELECT quantile_cont(in_links, 0.5) AS p50, quantile_cont(in_links, 0.9) AS p90, max(in_links) AS top, arg_max(id, (in_links, id)) AS top_id, arg_min(id, (in_links, id)) AS low_id FROM {_IN.format(NEXT)}",
    "topk_parts_per_customer": f"SELECT i, j, v, place FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS place FROM {CP}) WHERE place <= 3",
    "rank_functions": f"""SELECT i, j, rank() OVER t AS rank, dense_rank() OVER t AS dense, percent_rank() OVER t AS pct, cume_dist() OVER t AS cume, ntile(4) OVER (PARTITION BY j ORDER BY v DESC, i) AS quarter
FROM {UE} WINDOW t AS (PARTITION BY j ORDER BY v DESC)""",
    "part_succession": f"SELECT src, dst FROM {NEXT_ALL}",
    "event_gap_lag": "SELECT event_id, gap_us FROM (SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap_us FROM events) WHERE gap_us IS NOT NULL",
    "link_extract": f"SELECT src, dst FROM {PAGES}",
    "url_parts": "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '[?]([^#]*)', 1) AS query, regexp_extract(url, '#(.*)$', 1) AS ref FROM pages",
    "term_counts": f"SELECT doc_id, term, tf FROM {TC}",
    "vocabulary": f"SELECT term, idx FROM {VOC}",
    "event_props_matrix": "SELECT user_id, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS k_sum, count(DISTINCT json_extract_string(props, '$.k')) AS k_kinds FROM events GROUP BY user_id",
    "hourly_event_matrix": "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n FROM events GROUP BY ALL",
    "vector_norms": f"SELECT i, round(sqrt(sum(v * v)), 6) AS norm FROM {EMB} GROUP BY i",
    "vector_norms_udf": f"SELECT i, round(sqrt(sum(v * v)), 6) AS norm FROM {EMB} GROUP BY i",
    "distinct_terms_exact": f"SELECT count(DISTINCT term) AS terms FROM {TC}",
    "outlier_sum_udaf": """SELECT user_id, round(sum(CASE WHEN s = 0 OR abs(value - m) <= 3 * s THEN value END), 4) AS kept_sum
FROM (SELECT user_id, value, avg(value) OVER (PARTITION BY user_id) AS m, stddev_pop(value) OVER (PARTITION BY user_id) AS s FROM events) GROUP BY user_id""",
    "tile_copies_udtf": f"SELECT i, j, v, b AS beta FROM {SP}, range(3) r(b)",
}
