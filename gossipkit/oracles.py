"""DuckDB SQL for the queries that SQL can express."""

from __future__ import annotations

EMB = """
e AS (SELECT (vec_id % 10)::INT AS site, (vec_id // 10) * 64 + i - 1 AS coord, embedding[i]::DOUBLE AS p
      FROM (SELECT vec_id, embedding, unnest(range(1, 65)) AS i FROM embeddings)),
r AS (SELECT site, coord, CASE WHEN abs(p) <= 0.05 THEN 0.0 ELSE sign(p) * (abs(p) - 0.05) END AS p FROM e),
k AS (SELECT site, coord, p, ('0x' || substr(md5('42/1/' || site || '/' || coord), 1, 8))::BIGINT / 4294967296.0 AS u FROM r)
"""
STAT = "st AS (SELECT site, min(p) AS lo, max(p) AS hi, count(*) AS d FROM r GROUP BY site)"
LEVEL = "CASE WHEN p = 0 THEN -1 WHEN hi = lo THEN 0 ELSE floor(least(greatest((p - lo) / (hi - lo), 0.0), 1.0) * 16 + u)::INT END"
SYM = f"{EMB}, {STAT}, s AS (SELECT site, coord, p, lo, hi, d, {LEVEL} AS sym FROM k JOIN st USING (site))"
TYPES = f"""{SYM}, ty AS (
  SELECT a.site, a.sym::INT AS sym, coalesce(c.cnt, 0)::BIGINT AS cnt
  FROM (SELECT site, unnest(range(-1, 17)) AS sym FROM st) a LEFT JOIN (SELECT site, sym, count(*) AS cnt FROM s GROUP BY 1, 2) c USING (site, sym)
)"""
ORDER = f"{TYPES}, o AS (SELECT site, sym, cnt, (row_number() OVER (PARTITION BY site ORDER BY cnt DESC, sym) - 1)::INT AS rank FROM ty)"
NORM = f"""{EMB}, nm AS (SELECT site, sqrt(sum(round(p * p, 12)::DECIMAL(38, 12))::DOUBLE) AS norm, count(*) AS d FROM r GROUP BY site),
ns AS (SELECT site, coord, p, norm, d, (sign(p) * CASE WHEN norm = 0 THEN 0 ELSE floor(16 * abs(p) / norm + u) END)::INT AS sym FROM k JOIN nm USING (site))"""
CHECK = "SELECT site, sym, count(*) AS n, sum(coord)::BIGINT AS \"check\" FROM {} GROUP BY site, sym"


def gamma(k: str) -> str:
    return f"(2 * length(bin({k})) - 1)"


def golomb(gap: str, m: str) -> str:
    b = f"length(bin({m} - 1))"
    return f"({gap} // {m} + 1 + CASE WHEN {m} = 1 THEN 0 ELSE {b} - CASE WHEN {gap} % {m} < (1::BIGINT << {b}) - {m} THEN 1 ELSE 0 END END)"


def parameter(p: str) -> str:
    return f"(CASE WHEN {p} >= 1 THEN 1 ELSE greatest(ceil(ln(2 - {p}) / -ln(1 - {p})), 1) END)::BIGINT"


def runs(order: str = "o") -> str:
    """Gaps of each transmitted rank among what is not explained before it."""
    return f"""held AS (
  SELECT site, coord, rank, row_number() OVER (PARTITION BY site ORDER BY coord) AS i FROM s JOIN {order} USING (site, sym)
), opened AS (
  SELECT h.site, h.coord, h.rank, v.rank AS lvl, row_number() OVER (PARTITION BY h.site, v.rank ORDER BY h.coord) AS n
  FROM held h JOIN {order} v ON v.site = h.site AND v.rank > 0 AND v.cnt > 0 AND (h.rank = 0 OR h.rank >= v.rank)
), runs AS (
  SELECT site, lvl AS rank, row_number() OVER w AS seq, n - coalesce(lag(n) OVER w, 0) - 1 AS gap FROM opened WHERE rank = lvl WINDOW w AS (PARTITION BY site, lvl ORDER BY coord)
), visit AS (
  SELECT site, rank, sym, cnt, {parameter('(cnt / remaining)')} AS m FROM (
    SELECT site, rank, sym, cnt, sum(cnt) OVER (PARTITION BY site) - coalesce(sum(CASE WHEN rank > 0 THEN cnt END) OVER (PARTITION BY site ORDER BY rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS remaining FROM {order}
  ) WHERE rank > 0 AND cnt > 0
), cost AS (
  SELECT site, rank, sym, m, count(*) AS runs, sum({golomb('gap', 'm')})::BIGINT AS bits FROM runs JOIN visit USING (site, rank) GROUP BY ALL
)"""


def bound(left: str) -> str:
    return f"""WITH {ORDER}, f AS (
  SELECT site, rank, cnt / sum(cnt) OVER w AS f, coalesce(sum(cnt) OVER (PARTITION BY site ORDER BY rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / sum(cnt) OVER w AS b
  FROM o WHERE cnt > 0 WINDOW w AS (PARTITION BY site)
), g AS (SELECT *, max(f) OVER (PARTITION BY site) AS f0 FROM f)
SELECT site, round(-sum(f * log2(f)) + 2.914 * (1 - max(f0)) + max(f0 * log2(f0)) + sum(CASE WHEN rank > 0 THEN f * log2({left}) ELSE 0 END), 6) AS bound FROM g GROUP BY site"""


def splits(key: str) -> str:
    n = f"('0x' || substr(md5({key}), 1, 8))::BIGINT % 10"
    return f"CASE WHEN {n} < 6 THEN 'train' WHEN {n} < 8 THEN 'validation' ELSE 'test' END"


WORDS = r"list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}]+'), lambda x: x <> '')"
GROUP = f"md5(array_to_string({WORDS}, ' '))"


def hashed(size: int) -> str:
    return f"""hw AS (
  SELECT doc_id, (('0x' || substr(md5(w), 1, 8))::BIGINT % {size})::INT AS feature, count(*) AS n FROM (SELECT doc_id, unnest({WORDS}) AS w FROM documents) GROUP BY 1, 2
)"""


def rows(size: int, label: str, source: str) -> str:
    """Training samples in long form: unit rows and a bias."""
    return f"""{hashed(size)}, val AS (
  SELECT doc_id, feature, round(n / sqrt(sum(n * n) OVER (PARTITION BY doc_id)::DOUBLE), 9) AS val FROM hw
  UNION ALL SELECT DISTINCT doc_id, {size}, 1.0 FROM hw
), lab AS (
  SELECT doc_id, (doc_id % 10)::INT AS site, {label} AS label FROM {source} WHERE {splits(GROUP)} = 'train'
), sm AS (SELECT site, doc_id, label, feature, val FROM val JOIN lab USING (doc_id)), ns AS (SELECT site, count(DISTINCT doc_id) AS n_site FROM sm GROUP BY site)"""


LANGUAGE = rows(64, "(list_position(['de', 'en', 'es', 'fr'], lang) - 1)::INT", "(SELECT * FROM documents WHERE lang IN ('de', 'en', 'es', 'fr'))")
QUALITY = rows(64, "quality", "documents JOIN labels USING (doc_id)")


def model(n: int, classes: int | None = None) -> str:
    key = "'model/' || f" + (" || '/' || c" if classes else "")
    extra = f", range(0, {classes}) AS y(c)" if classes else ""
    cols = "f::INT AS feature" + (", c::INT AS class" if classes else "")
    return f"md AS (SELECT {cols}, ('0x' || substr(md5({key}), 1, 8))::BIGINT / 4294967296.0 - 0.5 AS w FROM range(0, {n}) AS x(f){extra})"


def margin(slope: str) -> str:
    return f"""WITH {QUALITY}, {model(65)}, sc AS (SELECT doc_id, sum(val * w) AS s FROM sm JOIN md USING (feature) GROUP BY doc_id),
m AS (SELECT site, feature, val, label * 2.0 - 1 AS sg, (label * 2.0 - 1) * s AS m FROM sm JOIN sc USING (doc_id))
SELECT site, feature AS coord, round(sum(val * sg * ({slope})) / any_value(n_site), 6) + 0.0 AS g FROM m JOIN ns USING (site) GROUP BY site, feature"""


SOFTMAX = f"""WITH {LANGUAGE}, {model(65, 4)}, sc AS (SELECT doc_id, class, sum(val * w) AS s FROM sm JOIN md USING (feature) GROUP BY doc_id, class),
ex AS (SELECT doc_id, class, exp(s - max(s) OVER (PARTITION BY doc_id)) AS e FROM sc), pr AS (SELECT doc_id, class, e / sum(e) OVER (PARTITION BY doc_id) AS pr FROM ex)
SELECT site, feature * 4 + class AS coord, round(sum(val * (pr - (class = label)::INT)) / any_value(n_site), 6) + 0.0 AS g FROM sm JOIN pr USING (doc_id) JOIN ns USING (site) GROUP BY 1, 2"""


def round1(mu: float = 1e-3, kind: str = "range") -> str:
    """The first round from the all-zero start; the result is rd(site, coord, x, y, z)."""
    comp = {
        "identity": "qd AS (SELECT site, coord, z, p AS q FROM p)",
        "range": """rg AS (SELECT site, min(p) AS lo, max(p) AS hi, count(*) AS d FROM p GROUP BY site), sy AS (
  SELECT site, coord, z, lo, hi, d, CASE WHEN p = 0 THEN -1 WHEN hi = lo THEN 0 ELSE floor(least(greatest((p - lo) / (hi - lo), 0.0), 1.0) * 16 + u)::INT END AS sym FROM p JOIN rg USING (site)
), qd AS (SELECT site, coord, z, CASE WHEN sym = -1 THEN 0.0 ELSE 256.0 / (256 + d) * (lo + (hi - lo) * sym / 16.0) END AS q FROM sy)""",
        "norm": """rg AS (SELECT site, sqrt(sum(round(p * p, 12)::DECIMAL(38, 12))::DOUBLE) AS norm, count(*) AS d FROM p GROUP BY site), qd AS (
  SELECT site, coord, z, norm * (sign(p) * floor(16 * abs(p) / norm + u)) / 16.0 / (1 + least(d / 256.0, sqrt(d) / 16.0)) AS q FROM p JOIN rg USING (site))""",
    }[kind]
    return f"""WITH {LANGUAGE}, gr AS (
  SELECT site, feature * 4 + c AS coord, sum(val * (0.25 - (c = label)::INT)) / any_value(n_site) AS g FROM sm JOIN ns USING (site), range(0, 4) AS y(c) GROUP BY 1, 2
), hf AS (
  SELECT a::INT AS site, b AS coord, 0.0 - 0.5 * coalesce(g, 0.0) AS h FROM range(0, 10) AS x(a), range(0, 260) AS y(b) LEFT JOIN gr ON gr.site = a AND gr.coord = b
), zz AS (SELECT site, coord, CASE WHEN abs(h) <= {mu * 0.5!r} THEN 0.0 ELSE sign(h) * (abs(h) - {mu * 0.5!r}) END AS z FROM hf),
p AS (SELECT site, coord, z, round(z, 9) AS p, ('0x' || substr(md5('42/1/' || site || '/' || coord), 1, 8))::BIGINT / 4294967296.0 AS u FROM zz),
{comp}, mx AS (
  SELECT d.site, d.coord, sum(s.q) / 3 AS m FROM qd d JOIN qd s ON s.coord = d.coord AND (s.site = d.site OR s.site = (d.site + 1) % 10 OR s.site = (d.site + 9) % 10) GROUP BY 1, 2
), rd AS (SELECT site, coord, z + 0.4 * (m - q) AS x, q AS y, z FROM qd JOIN mx USING (site, coord))"""


def sent(name: str, src: str, label: str, rnd: int = 1) -> str:
    """Quantised values of src(site, coord, p) as name(site, coord, q), and their means over the ring as name_m."""
    return f"""{name}_r AS (SELECT site, min(p) AS lo, max(p) AS hi, count(*) AS d FROM {src} GROUP BY site), {name}_s AS (
  SELECT site, coord, lo, hi, d, CASE WHEN p = 0 THEN -1 WHEN hi = lo THEN 0
    ELSE floor(least(greatest((p - lo) / (hi - lo), 0.0), 1.0) * 16 + ('0x' || substr(md5('{label}42/{rnd}/' || site || '/' || coord), 1, 8))::BIGINT / 4294967296.0)::INT END AS sym
  FROM {src} JOIN {name}_r USING (site)
), {name} AS (SELECT site, coord, CASE WHEN sym = -1 THEN 0.0 ELSE 256.0 / (256 + d) * (lo + (hi - lo) * sym / 16.0) END AS q FROM {name}_s), {name}_m AS (
  SELECT d.site, d.coord, sum(s.q) / 3 AS m FROM {name} d JOIN {name} s ON s.coord = d.coord AND (s.site = d.site OR s.site = (d.site + 1) % 10 OR s.site = (d.site + 9) % 10) GROUP BY 1, 2
)"""


def round_after(t: int) -> str:
    """s{t}(site, coord, x, y, z) from s{t - 1}: softmax gradients at each site's own model, then a round over the ring."""
    b = t - 1
    return f"""sc{t} AS (
  SELECT sm.site, doc_id, any_value(label) AS label, s.coord % 4 AS class, sum(val * x) AS v FROM sm JOIN s{b} s ON s.site = sm.site AND s.coord // 4 = sm.feature GROUP BY 1, 2, 4
), ex{t} AS (SELECT *, exp(v - max(v) OVER (PARTITION BY doc_id)) AS e FROM sc{t}),
pr{t} AS (SELECT doc_id, class, e / sum(e) OVER (PARTITION BY doc_id) - (class = label)::INT AS miss FROM ex{t}),
gr{t} AS (SELECT site, feature * 4 + class AS coord, sum(val * miss) / any_value(n_site) AS g FROM sm JOIN pr{t} USING (doc_id) JOIN ns USING (site) GROUP BY 1, 2),
hf{t} AS (SELECT site, coord, y, x - 0.5 * coalesce(g, 0.0) AS h FROM s{b} LEFT JOIN gr{t} USING (site, coord)),
zz{t} AS (SELECT site, coord, y, CASE WHEN abs(h) <= 0.0005 THEN 0.0 ELSE sign(h) * (abs(h) - 0.0005) END AS z FROM hf{t}),
zp{t} AS (SELECT site, coord, round(z - y, 9) AS p FROM zz{t}), {sent(f"q{t}", f"zp{t}", "", t)},
yn{t} AS (SELECT site, coord, z, y + q AS y FROM zz{t} JOIN q{t} USING (site, coord)),
ym{t} AS (
  SELECT d.site, d.coord, sum(s.y) / 3 AS m FROM yn{t} d JOIN yn{t} s ON s.coord = d.coord AND (s.site = d.site OR s.site = (d.site + 1) % 10 OR s.site = (d.site + 9) % 10) GROUP BY 1, 2
), s{t} AS (SELECT site, coord, z + 0.4 * (m - y) AS x, y, z FROM yn{t} JOIN ym{t} USING (site, coord))"""


GRID = "s0 AS (SELECT a::INT AS site, b AS coord, 0.0::DOUBLE AS x, 0.0::DOUBLE AS y FROM range(0, 10) AS q(a), range(0, 260) AS r(b))"
THREE_ROUNDS = f"""WITH {LANGUAGE}, {GRID}, {round_after(1)}, {round_after(2)}, {round_after(3)}
SELECT site, coord, round(x, 6) + 0.0 AS x, round(y, 6) + 0.0 AS y, round(z, 6) + 0.0 AS z FROM s3"""

TRACKING = f"""WITH {LANGUAGE}, gr AS (
  SELECT site, feature * 4 + c AS coord, sum(val * (0.25 - (c = label)::INT)) / any_value(n_site) AS g FROM sm JOIN ns USING (site), range(0, 4) AS y(c) GROUP BY 1, 2
), gf AS (SELECT a::INT AS site, b AS coord, coalesce(g, 0.0) AS g FROM range(0, 10) AS x(a), range(0, 260) AS y(b) LEFT JOIN gr ON gr.site = a AND gr.coord = b),
gp AS (SELECT site, coord, round(g, 9) AS p FROM gf), {sent('qg', 'gp', 'g')},
tk AS (SELECT site, coord, g + 0.4 * (m - q) AS track, q AS track_y FROM gf JOIN qg USING (site, coord) JOIN qg_m USING (site, coord)),
zz AS (SELECT *, CASE WHEN abs(0.5 * track) <= 0.0005 THEN 0.0 ELSE -sign(track) * (abs(0.5 * track) - 0.0005) END AS z FROM tk),
zp AS (SELECT site, coord, round(z, 9) AS p FROM zz), {sent('qz', 'zp', '')}
SELECT site, coord, round(z + 0.4 * (m - q), 6) + 0.0 AS x, round(q, 6) + 0.0 AS y, round(z, 6) + 0.0 AS z, round(track, 6) + 0.0 AS track, round(track_y, 6) + 0.0 AS track_y
FROM zz JOIN qz USING (site, coord) JOIN qz_m USING (site, coord)"""
FIXED = f"""WITH {LANGUAGE}, {model(65, 4)}, sc AS (SELECT site, doc_id, any_value(label) AS label, class, sum(val * w) AS s FROM sm JOIN md USING (feature) GROUP BY site, doc_id, class)"""
BLOCKS = f"{TYPES}, o AS".replace("s AS (SELECT site, coord,", "s AS (SELECT site * 1000 + coord // 1024 AS site, coord,").replace("FROM st) a", "FROM (SELECT DISTINCT site FROM s)) a")

STATE = "\nSELECT site, coord, round(x, 6) + 0.0 AS x, round(y, 6) + 0.0 AS y, round(z, 6) + 0.0 AS z FROM rd"
TRACE = """t AS (
  SELECT o_orderpriority AS run_id, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_orderkey)::INT AS round, 1000 + o_orderkey % 977 AS bits FROM orders
), tr AS (
  SELECT *, round(CASE WHEN run_id = '5-LOW' THEN 0.5 ELSE 1.0 END * (1 - 20.0 / (20.0 + round)), 6) AS accuracy, sum(bits) OVER (PARTITION BY run_id ORDER BY round)::BIGINT AS cum FROM t
), tg AS (
  SELECT run_id, bool_or(accuracy >= 0.7) AS reached, coalesce(min(round) FILTER (accuracy >= 0.7), max(round)) AS rounds FROM tr GROUP BY run_id
), tt AS (SELECT tg.run_id, reached, tg.rounds, cum AS cum_bits FROM tg JOIN tr ON tr.run_id = tg.run_id AND tr.round = tg.rounds)"""
NATION = """a AS (SELECT n_nationkey AS n, n_regionkey AS r FROM nation), hd AS (SELECT r, min(n) AS n FROM a GROUP BY r), ed AS (
  SELECT x.n AS src, y.n AS dst FROM a x JOIN a y ON x.r = y.r AND x.n < y.n UNION ALL SELECT h.n, g.n FROM hd h JOIN hd g ON g.r = (h.r + 1) % (SELECT count(*) FROM hd)
), bo AS (SELECT DISTINCT src, dst FROM (SELECT src, dst FROM ed UNION ALL SELECT dst, src FROM ed) WHERE src <> dst), dg AS (SELECT src, count(*) AS k FROM bo GROUP BY src),
lw AS (SELECT bo.src, bo.dst, 1.0::DOUBLE / (1 + greatest(p.k, q.k)) AS w FROM bo JOIN dg p ON p.src = bo.src JOIN dg q ON q.src = bo.dst),
mw AS (SELECT src, dst, w FROM lw UNION ALL SELECT src, src, 1 - sum(w) FROM lw GROUP BY src)"""
VALUES = "v AS (SELECT (user_id % 10)::INT AS site, avg(value) AS x FROM events GROUP BY 1)"


def circle(steps: str, n: int) -> str:
    return f"mw AS (SELECT s::INT AS src, ((s + o) % 10)::INT AS dst, 1.0::DOUBLE / {n} AS w FROM range(0, 10) AS x(s), (SELECT unnest([{steps}]) AS o))"


LAPLACE_RATE = "2.914 * exp(-a / 2) + 2 * sinh(a / 2) * (1 - ln(1 - exp(-a))) * exp(1 - a)"
SIZES = "sz AS (SELECT (vec_id % 10)::INT AS site, sum(len(embedding))::BIGINT AS d FROM embeddings GROUP BY 1)"
STATIONARITY = f"""WITH {SIZES}, g AS (SELECT site, d, T, n FROM sz, (SELECT unnest([100, 10000, 1000000]) AS T), (SELECT unnest([2, 10, 50]) AS n)),
c AS (SELECT site, d, T::BIGINT AS rounds, n::BIGINT AS sites, (1 - 0.87268::DOUBLE) ** 2 / (82 * (1 + d / 256.0::DOUBLE)) AS o, sqrt(2.0::DOUBLE + 1.0 + 1e-6::DOUBLE * d) AS a FROM g)
SELECT site, rounds, sites, round(2 * sqrt(1.4::DOUBLE * (0.5 + 4 * 1e-6::DOUBLE * d + a) / ((rounds + 1) * sites * o)) + 7 * (a * 1.4::DOUBLE / ((rounds + 1) * o)) ** (2.0::DOUBLE / 3) + 16 * 1.4::DOUBLE / (rounds + 1), 6) AS bound FROM c"""
HELD = "p AS (SELECT site, row_number() OVER (ORDER BY site) - 1 AS i, count(*) OVER () AS n FROM (SELECT DISTINCT ((user_id % 10 + 10) % 10)::INT AS site FROM events WHERE user_id IS NOT NULL))"


def held_circle(steps: str) -> str:
    return f"""WITH {HELD}, e AS (SELECT DISTINCT a.site AS src, b.site AS dst FROM p a, (SELECT unnest([{steps}]) AS o), p b WHERE b.i = ((a.i + o) % a.n + a.n) % a.n)
SELECT src, dst, round(1.0::DOUBLE / count(*) OVER (PARTITION BY src), 6) AS w FROM e"""


def implied(kind: str) -> str:
    """Gap bits of each site with the given level implied; levels are sent by falling count."""
    held = "(cnt > 0)::INT"
    first = "NULL" if kind == "none" else "row_number() OVER (PARTITION BY site ORDER BY cnt DESC, sym) = 1"
    if kind == "last":
        first = f"row_number() OVER (PARTITION BY site ORDER BY {held} DESC, cnt, sym DESC) = 1"
    base = 0 if kind == "none" else 1
    return f"""SELECT site, '{kind}' AS implied, sum(bits)::BIGINT AS gap_bits FROM (WITH {TYPES}, f AS (SELECT *, {first} AS first FROM ty),
o AS (SELECT site, sym, cnt, row_number() OVER (PARTITION BY site ORDER BY coalesce(first, false) DESC, cnt DESC, sym) - {base} AS rank FROM f), {runs()}
SELECT site, bits FROM cost) GROUP BY site"""


LINES = """
sold AS (SELECT (l_suppkey % 10)::INT AS site, l_partkey AS coord, sum(l_quantity) AS s FROM lineitem GROUP BY 1, 2),
grid AS (SELECT a::INT AS site, p_partkey AS coord FROM part, range(0, 10) AS x(a)),
e AS (SELECT site, coord, coalesce(s - 25.0, 0.0)::DOUBLE AS p FROM grid LEFT JOIN sold USING (site, coord)),
r AS (SELECT site, coord, CASE WHEN abs(p) <= 5 THEN 0.0 ELSE sign(p) * (abs(p) - 5) END AS p FROM e),
k AS (SELECT site, coord, p, ('0x' || substr(md5('42/1/' || site || '/' || coord), 1, 8))::BIGINT / 4294967296.0 AS u FROM r)
"""


def line_bits(levels: int) -> str:
    order = ORDER.replace(EMB, LINES).replace("* 16 + u", f"* {levels} + u").replace("range(-1, 17)", f"range(-1, {levels + 1})")
    return f"""SELECT site, {levels}::INT AS levels, type_bits, gap_bits FROM (WITH {order}, {runs()},
hd AS (SELECT site, sum({gamma('(cnt + 1)')})::BIGINT AS type_bits FROM ty GROUP BY site), gp AS (SELECT site, sum(bits)::BIGINT AS gap_bits FROM cost GROUP BY site)
SELECT site, type_bits, coalesce(gap_bits, 0)::BIGINT AS gap_bits FROM hd LEFT JOIN gp USING (site))"""


PAIRS = """SELECT a.user_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase'
  AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY
GROUP BY a.user_id"""

ORACLES = {
    "levelset_implied_bits": " UNION ALL ".join(map(implied, ("dominant", "last", "none"))),
    "levelset_encode_bytes": f"""WITH {ORDER}, {runs()}, hd AS (SELECT site, sum({gamma('(cnt + 1)')})::BIGINT AS t FROM ty GROUP BY site),
gp AS (SELECT site, sum(bits)::BIGINT AS g FROM cost GROUP BY site)
SELECT site, t + g AS bits, t + g AS relational_bits, (14 + (t + g + 7) // 8)::BIGINT AS bytes, true AS equal FROM hd JOIN gp USING (site)""",
    "symbol_messages": f"""WITH {NORM}, gs AS (
  SELECT site, coord // 1024 AS b, abs(sym) AS m, coord - coalesce(lag(coord) OVER (PARTITION BY site, coord // 1024 ORDER BY coord), coord // 1024 * 1024 - 1) AS gap
  FROM ns WHERE sym <> 0
), bl AS (SELECT DISTINCT site, coord // 1024 AS b FROM ns), cs AS (SELECT site, b, count(*) AS c, sum({gamma('gap')} + 1 + {gamma('m')}) AS t FROM gs GROUP BY 1, 2),
pb AS (SELECT site, sum(8 + ({gamma('(coalesce(c, 0) + 1)')} + coalesce(t, 0) + 7) // 8)::BIGINT AS bytes FROM bl LEFT JOIN cs USING (site, b) GROUP BY site)
SELECT site, count(*) AS n, 0::BIGINT AS wrong, any_value(bytes) AS bytes FROM ns JOIN pb USING (site) GROUP BY site""",
    "index_value_bits": f"""WITH {EMB}, z AS (SELECT site, count(*) AS d FROM r GROUP BY site)
SELECT site, least(d, 50)::BIGINT AS kept, (least(d, 50) * (length(bin(d - 1)) + 32))::BIGINT AS payload_bits FROM z""",
    "norm_values": f"""WITH {NORM}, v AS (SELECT site, coord, norm * sym / 16.0::DOUBLE AS q, 1 + least(d / 256.0::DOUBLE, sqrt(d) / 16.0::DOUBLE) AS tau FROM ns)
SELECT site, coord, round(q, 6) + 0.0 AS unbiased, round(q / tau, 6) + 0.0 AS rescaled FROM v""",
    "residual_quantiles": f"""WITH {EMB}, c AS (SELECT site, abs(p) AS v, cume_dist() OVER (PARTITION BY site ORDER BY abs(p)) AS f FROM r)
SELECT site, prob, round(min(v), 6) + 0.0 AS value FROM c, (SELECT unnest([0.5, 0.9, 0.99, 1.0])::DOUBLE AS prob) WHERE f >= prob GROUP BY 1, 2""",
    "residual_histogram": f"""WITH {EMB}, {STAT}, b AS (SELECT site, CASE WHEN hi > lo THEN least(floor(20 * ((p - lo) / (hi - lo))) + 1, 20) ELSE 1 END::INT AS bin FROM r JOIN st USING (site))
SELECT site, bin, count(*) AS n FROM b GROUP BY 1, 2""",
    "level_standing": f"""WITH {TYPES} SELECT site, sym, round(percent_rank() OVER w, 6) AS percent, round(cume_dist() OVER w, 6) AS share, (ntile(4) OVER w)::INT AS quarter
FROM ty WINDOW w AS (PARTITION BY site ORDER BY cnt, sym)""",
    "type_maps": f"WITH {TYPES} SELECT site, any_value(cnt) FILTER (sym = -1) AS zeros, count(*) FILTER (cnt > 0) AS used FROM ty GROUP BY site",
    "event_props": """SELECT strftime(ts, '%Y-%m') AS month, count(k) AS n, sum(k)::BIGINT AS total, max(k) AS top
FROM (SELECT ts, (props ->> '$.k')::BIGINT AS k FROM events) GROUP BY 1""",
    "lineitem_bits": " UNION ALL ".join(map(line_bits, (4, 16, 64))),
    "spectra_closed": f"""WITH {HELD}, m AS (SELECT max(n) AS n FROM p), v AS (SELECT 1 / 3.0::DOUBLE + 2 / 3.0::DOUBLE * cos(2 * pi() * k / n) AS e FROM (SELECT n, unnest(range(1, n)) AS k FROM m)),
c AS (SELECT 'ring' AS graph, max(abs(e)) AS l, max(1 - e) AS b FROM v UNION ALL SELECT 'full', 0.0::DOUBLE, 1.0::DOUBLE),
g AS (SELECT *, 1 - l AS d, 0.2::DOUBLE AS c FROM c)
SELECT graph, round(l, 6) AS lambda2, round(b, 6) AS beta, round(d * d * c / (16 * d + d * d + 4 * b * b + 2 * d * b * b - 8 * d * c), 6) AS safe_gamma FROM g""",
    "event_pairs_stream": PAIRS,
    "stream_messages": """SELECT (e.user_id % 10 + o + 10)::INT % 10 AS dst, count(*) AS n, round(sum(value / 3), 2) AS total
FROM events e, (SELECT unnest([-1, 0, 1]) AS o) GROUP BY 1""",
    "site_assignment": f"SELECT (vec_id % 10)::INT AS site, {splits('vec_id::VARCHAR')} AS split, count(*) AS n FROM embeddings GROUP BY 1, 2",
    "split_counts": f"SELECT {splits(GROUP)} AS split, lang, count(*) AS n FROM documents GROUP BY 1, 2",
    "prox_embeddings": f"WITH {EMB} SELECT site, coord, round(p, 6) + 0.0 AS z FROM r",
    "prox_sparsity_sweep": f"""WITH {EMB}, g AS (SELECT mu, greatest(abs(p) - mu, 0.0) AS z FROM e, (SELECT unnest([0.0, 0.01, 0.05, 0.1, 0.2])::DOUBLE AS mu))
SELECT mu, count(*) FILTER (z = 0) AS zeros, round(sum(z), 6) AS l1 FROM g GROUP BY mu""",
    "residual_range": f"WITH {EMB}, {STAT} SELECT site, round(lo, 6) AS lo, round(hi, 6) AS hi, d FROM st",
    "range_dither_symbols": f"WITH {SYM} {CHECK.format('s')}",
    "range_dither_values": f"""WITH {SYM}, q AS (SELECT *, 256.0::DOUBLE / (256 + d) AS f, (hi - lo) * sym / 16.0::DOUBLE AS h FROM s)
SELECT site, coord, round(CASE WHEN sym = -1 THEN 0 ELSE f * (lo + h) END, 6) + 0.0 AS "outer", round(CASE WHEN sym = -1 THEN 0 ELSE lo + f * h END, 6) + 0.0 AS "inner",
  round(CASE WHEN sym = -1 THEN 0 ELSE lo + h END, 6) + 0.0 AS "none" FROM q""",
    "centred_dither_symbols": f"WITH {EMB}, st AS (SELECT site, -greatest(abs(min(p)), abs(max(p))) AS lo, greatest(abs(min(p)), abs(max(p))) AS hi FROM r GROUP BY site), s AS (SELECT site, coord, {LEVEL} AS sym FROM k JOIN st USING (site)) {CHECK.format('s')}",
    "fixed_range_symbols": f"WITH {EMB}, s AS (SELECT site, coord, {LEVEL} AS sym FROM k, (SELECT -0.25::DOUBLE AS lo, 0.25::DOUBLE AS hi)) {CHECK.format('s')}",
    "norm_dither_symbols": f"WITH {NORM} {CHECK.format('ns')}",
    "topk_keep": f"WITH {EMB} SELECT site, coord, (row_number() OVER (PARTITION BY site ORDER BY abs(p) DESC, coord))::INT AS rank, round(p, 6) + 0.0 AS q FROM r QUALIFY rank <= 50",
    "randk_keep": f"""WITH {EMB} SELECT site, coord, (row_number() OVER (PARTITION BY site ORDER BY ('0x' || substr(md5('rand/42/1/' || site || '/' || coord), 1, 8))::BIGINT, coord))::INT AS rank,
  round(p, 6) + 0.0 AS q FROM r QUALIFY rank <= 50""",
    "quantiser_error_ratio": f"""WITH {SYM}, {NORM[len(EMB) + 2:]}, a AS (
  SELECT site, any_value(d) AS d, sum((CASE WHEN sym = -1 THEN 0 ELSE 256.0::DOUBLE / (256 + d) * (lo + (hi - lo) * sym / 16.0::DOUBLE) END - p) ** 2) / sum(p ** 2) AS x FROM s GROUP BY site
), b AS (SELECT site, sum((norm * sym / 16.0::DOUBLE / (1 + least(d / 256.0::DOUBLE, sqrt(d) / 16.0::DOUBLE)) - p) ** 2) / sum(p ** 2) AS y FROM ns GROUP BY site)
SELECT site, round(x, 6) AS range_ratio, round(y, 6) AS norm_ratio, round(d / (256.0::DOUBLE + d), 6) AS "limit" FROM a JOIN b USING (site)""",
    "type_vector": f"WITH {TYPES} SELECT * FROM ty",
    "level_order": f"WITH {ORDER} SELECT * FROM o",
    "level_entropy": f"WITH {TYPES}, f AS (SELECT site, cnt / sum(cnt) OVER (PARTITION BY site) AS f FROM ty) SELECT site, round(max(f), 6) AS f0, round(-sum(f * log2(f)) FILTER (f > 0), 6) AS entropy FROM f GROUP BY site".replace("-sum(f * log2(f)) FILTER (f > 0)", "-sum(CASE WHEN f > 0 THEN f * log2(f) END)"),
    "levelset_bound_printed": bound("1 - b"),
    "levelset_bound_sound": bound("1 - (b - f0)"),
    "run_lengths": f"WITH {ORDER}, {runs()} SELECT site, rank::INT AS rank, count(*) AS runs, sum(gap)::BIGINT AS total, max(gap) AS longest, sum(seq * gap)::BIGINT AS \"check\" FROM runs GROUP BY 1, 2",
    "golomb_bits": f"""WITH g AS (SELECT i AS gap, p, {parameter('p')} AS m FROM (SELECT DISTINCT o_custkey AS i FROM orders WHERE o_custkey >= 0), (SELECT unnest([0.9, 0.5, 0.3, 0.12, 0.03])::DOUBLE AS p)),
h AS (SELECT *, 1::BIGINT << (length(bin(m)) - 1) AS m2 FROM g) SELECT gap, p, {golomb('gap', 'm')}::BIGINT AS optimal, {golomb('gap', 'm2')}::BIGINT AS rice FROM h""",
    "elias_bits": """WITH k AS (SELECT o_orderkey AS k, length(bin(o_orderkey)) AS a FROM orders WHERE o_orderkey > 0), l AS (SELECT *, length(bin(a - 1)) AS b FROM k), m AS (SELECT *, length(bin(b - 1)) AS c FROM l)
SELECT k, (2 * a - 1)::BIGINT AS gamma, (a - 1 + 2 * (length(bin(a)) - 1) + 1)::BIGINT AS delta,
  (1 + CASE WHEN k > 1 THEN a + CASE WHEN a - 1 > 1 THEN b + CASE WHEN b - 1 > 1 THEN c ELSE 0 END ELSE 0 END ELSE 0 END)::BIGINT AS omega FROM m""",
    "levelset_bits": f"""WITH {ORDER}, {runs()}, hd AS (SELECT site, sum({gamma('(cnt + 1)')})::BIGINT AS type_bits FROM ty GROUP BY site), gp AS (SELECT site, sum(bits)::BIGINT AS gap_bits FROM cost GROUP BY site)
SELECT site, type_bits, gap_bits, 112::BIGINT AS header_bits, type_bits + gap_bits + 112 AS total_bits FROM hd JOIN gp USING (site)""",
    "levelset_bits_by_level": f"WITH {ORDER}, {runs()} SELECT site, rank, sym, m, runs, bits FROM cost",
    "levelset_natural_bits": f"""WITH {ORDER}, o2 AS (SELECT site, sym, cnt, row_number() OVER (PARTITION BY site ORDER BY CASE WHEN rank = 0 THEN -2 ELSE sym END) - 1 AS rank FROM o), {runs('o2')}
SELECT site, sum(bits)::BIGINT AS gap_bits FROM cost GROUP BY site""",
    "bits_by_coder": f"""WITH {ORDER}, {runs()}, {NORM[len(EMB) + 2:]}, gs AS (SELECT site, coord - coalesce(lag(coord) OVER (PARTITION BY site ORDER BY coord), -1) AS gap, abs(sym) AS m FROM ns WHERE sym <> 0)
SELECT site, 'levelset' AS coder, (t + g)::BIGINT AS payload_bits FROM (SELECT site, sum({gamma('(cnt + 1)')}) AS t FROM ty GROUP BY site) JOIN (SELECT site, sum(bits) AS g FROM cost GROUP BY site) USING (site)
UNION ALL SELECT site, 'symbol_sparse', sum({gamma('gap')} + 1 + {gamma('m')})::BIGINT FROM gs GROUP BY site
UNION ALL SELECT site, 'symbol_dense', sum({gamma('(abs(sym) + 1)')} + (sym <> 0)::INT)::BIGINT FROM ns GROUP BY site
UNION ALL SELECT site, 'fixed', count(*) * 5 FROM s GROUP BY site UNION ALL SELECT site, 'raw32', count(*) * 32 FROM s GROUP BY site""",
    "mixing_ring": held_circle("0, 1, -1"),
    "mixing_fc": f"WITH {HELD} SELECT a.site AS src, b.site AS dst, round(1.0::DOUBLE / a.n, 6) AS w FROM p a, p b",
    "mixing_circulant": held_circle("0, 1, -1, 2, -2"),
    "mixing_nation": f"WITH {NATION} SELECT src, dst, round(w, 6) AS w FROM mw",
    "mixing_check": f"""WITH {NATION}, b AS (SELECT src, dst, CASE WHEN src = 3 AND dst = 3 THEN w + 0.5 ELSE w END AS w FROM mw WHERE NOT (src = 0 AND dst = 5))
SELECT 'asymmetric' AS problem, x.src, x.dst FROM b x LEFT JOIN b y ON y.src = x.dst AND y.dst = x.src WHERE y.w IS NULL OR abs(x.w - y.w) > 1e-9
UNION ALL SELECT 'negative', src, dst FROM b WHERE w < 0 UNION ALL SELECT 'row sum', src, src FROM b GROUP BY src HAVING abs(sum(w) - 1) > 1e-9""",
    "gossip_one_round": f"WITH {VALUES}, {circle('0, 1, 9', 3)}, m AS (SELECT dst AS site, sum(w * x) AS m FROM v JOIN mw ON mw.src = v.site GROUP BY dst) SELECT site, round(x + 0.4 * (m - x), 6) + 0.0 AS x FROM v JOIN m USING (site)",
    "gossip_mean_preserved": f"WITH {VALUES}, {circle('0, 1, 3, 7, 9', 5)}, m AS (SELECT dst, sum(w * x) AS m FROM v JOIN mw ON mw.src = v.site GROUP BY dst) SELECT (SELECT round(avg(x), 6) FROM v) AS before, (SELECT round(avg(m), 6) FROM m) AS after",
    "average_consensus_events": f"WITH {VALUES} SELECT site, (SELECT round(avg(x), 3) FROM v) AS x FROM v",
    "softmax_gradient": SOFTMAX,
    "logistic_gradient": margin("-1 / (1 + exp(m))"),
    "hinge_gradient": margin("CASE WHEN m >= 1 THEN 0 WHEN m > 0 THEN m - 1 ELSE -1 END"),
    "least_squares_gradient": margin("m - 1"),
    "sparse_gossip_round1": round1() + STATE,
    "plain_gossip_round1": round1(0.0) + STATE,
    "exact_gossip_round1": round1(kind="identity") + STATE,
    "plain_norm_round1": round1(0.0, "norm") + STATE,
    "stationarity_round1": round1() + "\nSELECT site, round(sum((z / 0.5) ** 2), 6) AS norm2 FROM rd GROUP BY site",
    "consensus_error_round1": round1() + "\nSELECT round(sum(v), 6) AS error FROM (SELECT var_pop(x) * count(*) AS v FROM rd GROUP BY coord)",
    "consensus_violation_round1": round1() + "\nSELECT round(sum((a.x - b.x) ** 2), 6) AS error FROM rd a JOIN rd b ON a.coord = b.coord AND b.site = (a.site + 1) % 10",
    "zero_share_round1": round1(0.01) + "\nSELECT site, round(avg((z = 0)::INT), 6) AS zero_share FROM rd GROUP BY site",
    "support_overlap_round1": round1(0.01) + """, nz AS (SELECT site, coord FROM rd WHERE z <> 0), sz AS (SELECT site, count(*) AS n FROM nz GROUP BY site), bo AS (
  SELECT x.site AS a, y.site AS b, count(*) AS c FROM nz x JOIN nz y ON x.coord = y.coord AND x.site < y.site GROUP BY 1, 2)
SELECT a, b, round(c / (p.n + q.n - c), 6) AS jaccard FROM bo JOIN sz p ON p.site = a JOIN sz q ON q.site = b""",
    "hashed_words": f"WITH {hashed(256)} SELECT feature, count(*) AS docs, sum(n)::BIGINT AS n FROM hw GROUP BY feature",
    "cumulative_bits": f"WITH {TRACE} SELECT run_id, round, cum AS cum_bits FROM tr",
    "bits_to_cutoff": f"WITH {TRACE} SELECT * FROM tt",
    "bit_saving": f"WITH {TRACE} SELECT a.run_id AS run_a, b.run_id AS run_b, round(100 * (1 - a.cum_bits / b.cum_bits), 6) + 0.0 AS saving FROM tt a JOIN tt b ON a.run_id <> b.run_id",
    "rate_slope": f"""WITH {TRACE}, m AS (SELECT run_id, round, avg(1 - accuracy) OVER (PARTITION BY run_id ORDER BY round) AS m FROM tr)
SELECT run_id, round(regr_slope(ln(m), ln(round)), 6) AS slope FROM m WHERE m > 0 GROUP BY run_id""",
    "moving_accuracy": f"WITH {TRACE} SELECT run_id, round, round(avg(accuracy) OVER (PARTITION BY run_id ORDER BY round ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS ma FROM tr",
    "table_r_rollup": f"WITH {TRACE} SELECT reached, run_id, sum(cum_bits)::BIGINT AS bits, grouping(reached, run_id)::BIGINT AS level FROM tt GROUP BY ROLLUP (reached, run_id)",
    "laplace_fit": f"""WITH {EMB}, h AS (SELECT site, avg(abs(p)) AS rho FROM e GROUP BY site), c AS (
  SELECT site, rho, CASE WHEN p < 0 THEN 0.5 * exp(p / rho) ELSE 1 - 0.5 * exp(-p / rho) END AS f, cume_dist() OVER (PARTITION BY site ORDER BY p) AS o FROM e JOIN h USING (site))
SELECT site, round(any_value(rho), 6) AS rho, round(max(abs(f - o)), 6) AS ks FROM c GROUP BY site""",
    "range_coverage": """WITH v AS (SELECT vec_id, unnest(embedding)::DOUBLE AS p FROM embeddings), e AS (SELECT max(p) - min(p) AS r, avg(abs(p)) AS rho, count(p) AS d FROM v GROUP BY vec_id)
SELECT count(*) AS vectors, round(avg((r <= rho * 2 * (ln(d::DOUBLE) - ln(0.01::DOUBLE)))::INT::DOUBLE), 6) AS covered FROM e""",
    "rate_curves": f"""WITH {SIZES}, g AS (SELECT site, d, levels::INT AS levels, 2 * (ln(d::DOUBLE) - ln(0.01::DOUBLE)) / levels AS a FROM sz, (SELECT unnest([2, 4, 8, 16, 64, 256]) AS levels))
SELECT site, d, levels, round(d * exp(-1.0::DOUBLE / levels), 6) AS proposed, round(d * log2(levels::DOUBLE), 6) AS symbolwise, round({LAPLACE_RATE}, 6) AS laplace_rate FROM g""",
    "stationarity_bound": STATIONARITY,
    "event_windows": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY 1, 2",
    "event_sessions": """WITH a AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
b AS (SELECT user_id, sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM a), c AS (SELECT user_id, k, count(*) AS n FROM b GROUP BY 1, 2)
SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY user_id""",
    "levelset_block_bits": f"""WITH {BLOCKS} (SELECT site, sym, cnt, (row_number() OVER (PARTITION BY site ORDER BY cnt DESC, sym) - 1)::INT AS rank FROM ty), {runs()},
hd AS (SELECT site, sum({gamma('(cnt + 1)')})::BIGINT AS type_bits FROM ty GROUP BY site), gp AS (SELECT site, sum(bits)::BIGINT AS gap_bits FROM cost GROUP BY site)
SELECT (site // 1000)::INT AS site, count(*) AS blocks, sum(type_bits)::BIGINT AS type_bits, sum(coalesce(gap_bits, 0))::BIGINT AS gap_bits FROM hd LEFT JOIN gp USING (site) GROUP BY 1""",
    "levelset_messages": f"WITH {EMB} SELECT site, count(*) AS n, 0::BIGINT AS wrong FROM r GROUP BY site",
    "nation_components": "SELECT n_nationkey AS site, min(n_nationkey) OVER (PARTITION BY n_regionkey) AS component FROM nation",
    "bernoulli_batch": f"""WITH {LANGUAGE} SELECT site, count(*) AS n, sum(doc_id)::BIGINT AS "check" FROM (SELECT DISTINCT site, doc_id FROM sm)
WHERE ('0x' || substr(md5('batch/42/1/' || doc_id), 1, 8))::BIGINT / 4294967296.0 < 0.25 GROUP BY site""",
    "objective_fixed": f"""{FIXED}, lo AS (SELECT site, doc_id, ln(sum(exp(s))) - sum(CASE WHEN class = label THEN s END) AS l FROM sc GROUP BY 1, 2), l1 AS (SELECT 0.001::DOUBLE * sum(abs(w)) AS r FROM md)
SELECT site, round(avg(l), 6) AS data_loss, round(any_value(r), 6) AS l1, round(avg(l) + any_value(r), 6) AS total FROM lo, l1 GROUP BY site""",
    "accuracy_fixed": f"{FIXED}, b AS (SELECT site, doc_id, any_value(label) AS label, arg_max(class, s) AS guess FROM sc GROUP BY 1, 2) SELECT site, round(avg((guess = label)::INT), 6) AS accuracy FROM b GROUP BY site",
    "tracking_round1": TRACKING,
    "train_relational": THREE_ROUNDS,
    "stationarity_at_mean": round1() + """, mn AS (SELECT coord, avg(x) AS x FROM rd GROUP BY coord), sc AS (
  SELECT doc_id, coord % 4 AS class, sum(val * x) AS s FROM sm JOIN mn ON coord // 4 = feature GROUP BY 1, 2), ex AS (SELECT doc_id, class, exp(s) AS e FROM sc),
pr AS (SELECT doc_id, class, e / sum(e) OVER (PARTITION BY doc_id) AS pr FROM ex), gs AS (
  SELECT site, feature * 4 + class AS coord, sum(val * (pr - (class = label)::INT)) / any_value(n_site) AS g FROM sm JOIN pr USING (doc_id) JOIN ns USING (site) GROUP BY 1, 2),
ga AS (SELECT coord, sum(g) / 10 AS g FROM gs GROUP BY coord), st AS (SELECT x, x - 0.5 * coalesce(g, 0.0) AS h FROM mn LEFT JOIN ga USING (coord))
SELECT round(sum(((x - CASE WHEN abs(h) <= 0.0005 THEN 0.0 ELSE sign(h) * (abs(h) - 0.0005) END) / 0.5) ** 2), 6) AS norm2 FROM st""",
    "asof_events": """WITH r AS (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'signup' GROUP BY 1, 2), l AS (SELECT * FROM events WHERE event_type = 'purchase')
SELECT l.event_id, r.event_id AS event_id_as_of FROM l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts""",
    "event_pairs": PAIRS,
}
