"""SQL that checks the registered queries on the same tables."""

from __future__ import annotations

import math

C2 = 1.99
_PI = f"{math.pi!r}::DOUBLE"

_PAIRS = "SELECT c_nationkey AS x, s_nationkey AS y, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL"


def both(pairs: str) -> str:
    """Both directions, summed, without loops, of a query that yields x, y, w."""
    return f"SELECT src::BIGINT AS src, dst::BIGINT AS dst, sum(w)::DOUBLE AS w FROM (SELECT x AS src, y AS dst, w FROM ({pairs}) UNION ALL SELECT y, x, w FROM ({pairs})) WHERE src <> dst GROUP BY ALL"


TRADE = both(_PAIRS)
_REGIONS = "JOIN nation m ON src = m.n_nationkey JOIN nation n ON dst = n.n_nationkey"
CHAIN = f"SELECT src, dst, w * CASE abs(m.n_regionkey - n.n_regionkey) WHEN 0 THEN 1.0::DOUBLE WHEN 1 THEN 0.05::DOUBLE ELSE 0.001::DOUBLE END AS w FROM ({TRADE}) {_REGIONS}"
ALIKE = f"SELECT src, dst, w * CASE WHEN m.n_regionkey = n.n_regionkey THEN 1.0::DOUBLE ELSE 0.02::DOUBLE END AS w FROM ({TRADE}) {_REGIONS}"
COPURCHASE = both("WITH o AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) SELECT a.l_partkey AS x, b.l_partkey AS y, count(*) AS w FROM o a JOIN o b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY ALL")
PART_SUPP = both("SELECT l_partkey AS x, l_suppkey + 1000000000 AS y, count(*) AS w FROM lineitem GROUP BY ALL")
CUST_PART = both("SELECT l_partkey AS x, o_custkey + 1000000000 AS y, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
USER_LINE = both("SELECT x, y, w FROM (SELECT event_id AS y, lag(event_id) OVER o AS x, CASE WHEN ts - lag(ts) OVER o > INTERVAL 2 DAY THEN 0.001 ELSE 1.0 END AS w FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE x IS NOT NULL")
DAY_RING = both("SELECT x, (x + 1) % n AS y, 1.0 AS w FROM (SELECT row_number() OVER (ORDER BY d) - 1 AS x, count(*) OVER () AS n FROM (SELECT DISTINCT l_shipdate::DATE AS d FROM lineitem))")
CONV = both("SELECT x, y, 1.0 AS w FROM (SELECT conv_id * 1000 + turn AS y, lag(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS x FROM conversations) WHERE x IS NOT NULL")
DOC_WORDS = both(
    r"""WITH t AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}_]{2,}')) AS word FROM documents),
    k AS (SELECT word FROM t GROUP BY word HAVING count(*) BETWEEN 0.02 * (SELECT count(*) FROM documents) AND least(0.4 * (SELECT count(*) FROM documents), 20000)),
    o AS (SELECT doc_id, word FROM t SEMI JOIN k USING (word))
    SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS w FROM o a JOIN o b ON a.word = b.word AND a.doc_id < b.doc_id GROUP BY ALL HAVING count(*) >= 3"""
)
#: Rooms that customers fall into.
_ROOMS = "(SELECT DISTINCT c_custkey % 128 AS i FROM customer WHERE c_custkey IS NOT NULL) t"
BUILDING = both(
    """WITH r AS (SELECT i AS id, i // 64 AS f, i % 8 AS gx, (i % 64) // 8 AS gy FROM range(128) t(i))
    SELECT a.id AS x, b.id AS y, CASE WHEN a.f = 1 AND b.f = 1 THEN CASE WHEN (a.gx < 4) <> (b.gx < 4) THEN 0.02::DOUBLE ELSE 1.0::DOUBLE END * CASE WHEN (a.gy < 4) <> (b.gy < 4) THEN 0.06::DOUBLE ELSE 1.0::DOUBLE END ELSE 1.0::DOUBLE END AS w
    FROM r a JOIN r b ON a.id < b.id AND ((a.f = b.f AND sqrt((a.gx - b.gx) ** 2 + (a.gy - b.gy) ** 2) * 7 < 10) OR (a.f = 0 AND b.f = 1 AND a.gx = b.gx AND a.gy = b.gy AND a.gx IN (1, 6) AND a.gy IN (1, 6)))"""
)


def links(edges: str) -> str:
    return f"SELECT src AS a, dst AS b, round(w, 6) + 0.0 AS w FROM ({edges}) WHERE src < dst"


def u0(node: str, seed: int) -> str:
    m = 2147483647
    h = f"((({node} % {m}) * 48271 + {seed * 16807} + 12345) % {m})"
    return f"((({h} * {h}) % {m} + 7919 * ({node} % {m})) % {m})::DOUBLE / {m}.0::DOUBLE"


def loop(edges: str, steps: int, own: float, before: float, message: float, start: str | None = None, previous: str = "u", lazy: bool = False, center: bool = False) -> str:
    """Recursive CTE ``s(t, id, u, v)`` of the same step that the engine takes."""
    half, self_p = ("0.5::DOUBLE *", "0.5::DOUBLE") if lazy else ("", None)
    begin = f"SELECT id, deg, {start or u0('id', 0)} AS u FROM d"
    if center:
        begin = f"SELECT id, deg, u - (SELECT sum(deg * u) / sum(deg) FROM ({begin})) AS u FROM ({begin})"
    loops = f"UNION ALL SELECT id, id, {self_p}, false FROM d" if self_p else ""
    return f"""WITH RECURSIVE e AS MATERIALIZED ({edges}), d AS MATERIALIZED (SELECT src AS id, sum(w) AS deg FROM e GROUP BY src),
    p AS MATERIALIZED (SELECT src, dst, {half} w / deg AS p, false AS own FROM e JOIN d ON src = id {loops} UNION ALL SELECT id, id, 0.0::DOUBLE, true FROM d),
    s(t, id, u, v) AS (
      SELECT 0, id, u, {previous} FROM ({begin})
      UNION ALL
      SELECT t + 1, src, sum(CASE WHEN own THEN {own!r}::DOUBLE * u - {before!r}::DOUBLE * v ELSE {message!r}::DOUBLE * p * u END), max(CASE WHEN own THEN u END)
      FROM s JOIN p ON dst = id WHERE t < {steps} GROUP BY t + 1, src
    )"""


def wave(edges: str, steps: int, **options) -> str:
    return loop(edges, steps, 2 - C2, 1.0, C2, **options)


def last(edges: str, steps: int, digits: int = 6, **options) -> str:
    return f"{wave(edges, steps, **options)} SELECT id, round(u, {digits}) + 0.0 AS u0 FROM s WHERE t = {steps}"


def hann(steps: int) -> str:
    return f"(0.5 - 0.5 * cos({2 * math.pi / steps!r}::DOUBLE * (t - 0.5)))"


def fourier(edges: str, steps: int, bins: str, window: str = "1.0") -> str:
    angle = f"({2 * math.pi / steps!r}::DOUBLE * b * t)"
    return f"{wave(edges, steps)}, f AS (SELECT id, b::INT AS bin, sum({window} * u * cos({angle})) AS re, sum(-({window}) * u * sin({angle})) AS im FROM s, (SELECT unnest([{bins}]) AS b) WHERE t > 0 GROUP BY ALL)"


_W2 = f"acos((2 - {C2} * lam) / 2)"
_RING = f"""SELECT n, round(lam, 6) AS lambda2, round(-1 / ln(cos(turn)), 6) AS tau, round((n / (2 * {_PI})) ** 2, 6) AS tau_printed, round(2 * (n / (2 * {_PI})) ** 2, 6) AS tau_series,
  round(6.5 / {_W2}, 6) AS steps, round(6.5 * n / {math.sqrt(2 * C2) * math.pi!r}, 6) AS steps_large
FROM (SELECT *, 1 - cos(turn) AS lam FROM (SELECT i * 10 AS n, {2 * math.pi!r} / (i * 10) AS turn FROM range(1, 200) t(i)))"""
_MODULUS = "CASE WHEN b * b >= 4 THEN abs((b + sign(b) * sqrt(abs(b * b - 4))) / 2) ELSE sqrt(b * b / 4 + (4 - b * b) / 4) END"
_REP = "WITH r AS (SELECT n_nationkey::BIGINT AS id, n_regionkey, min(n_nationkey) OVER (PARTITION BY n_regionkey)::BIGINT AS group_rep FROM nation)"
_SIDES = f"{_REP}, e AS ({TRADE}), k AS (SELECT e.*, a.group_rep AS ca, b.group_rep AS cb FROM e JOIN r a ON src = a.id JOIN r b ON dst = b.id)"
_CUTS = f"{_SIDES}, c AS (SELECT ca, sum(CASE WHEN ca <> cb THEN w ELSE 0 END) AS cut, sum(w) AS volume FROM k GROUP BY ca), z AS (SELECT c.*, n FROM c JOIN (SELECT group_rep, count(*) AS n FROM r GROUP BY 1) ON ca = group_rep)"
_READ = "SELECT i AS id, coalesce(x, 0.0)::DOUBLE AS x FROM range(128) t(i) LEFT JOIN (SELECT s_suppkey % 128 AS k, avg(s_acctbal) AS x FROM supplier GROUP BY 1) ON i = k"
_FIVE = "CASE WHEN id < 64 THEN 0 ELSE 1 + CASE WHEN id % 8 < 4 THEN 0 ELSE 1 END + CASE WHEN id % 64 < 32 THEN 0 ELSE 2 END END"


def consensus(label: str, rounds: int) -> str:
    a, b = label.replace("id", "src"), label.replace("id", "dst")
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT src, dst FROM ({BUILDING}) WHERE {a} = {b}), n AS (SELECT src, count(*) AS n FROM e GROUP BY 1),
    p0 AS (SELECT e.src, e.dst, 1.0::DOUBLE / (1 + greatest(x.n, y.n)) AS p FROM e JOIN n x ON e.src = x.src JOIN n y ON e.dst = y.src), v AS MATERIALIZED ({_READ}),
    p AS MATERIALIZED (SELECT * FROM p0 UNION ALL SELECT id, id, 1 - coalesce((SELECT sum(p) FROM p0 WHERE src = id), 0) FROM v),
    s(t, id, x) AS (SELECT 0, id, x FROM v UNION ALL SELECT t + 1, src, sum(p * x) FROM s JOIN p ON dst = id WHERE t < {rounds} GROUP BY t + 1, src)
    SELECT id, round(x, 4) + 0.0 AS x FROM s WHERE t = {rounds}"""


_AGENTS = "SELECT s_suppkey AS id, ((s_suppkey * 7919) % 1009)::DOUBLE / 1009 AS x, ((s_suppkey * 104729) % 1013)::DOUBLE / 1013 AS y FROM supplier"
_BASIS = "SELECT i::INT AS k1, j::INT AS k2, (CASE WHEN i = 0 THEN 1.0 ELSE 0.5 END * CASE WHEN j = 0 THEN 1.0 ELSE 0.5 END)::DOUBLE AS norm, pow(1.0 + i * i + j * j, -1.5) AS lam FROM range({n}) a(i), range({n}) b(j)"
_B3 = _BASIS.format(n=4)
_VALUE = f"cos(k1 * {_PI} * x) * cos(k2 * {_PI} * y)"
_MU = f"SELECT k1, k2, norm, lam, sum(mass * {_VALUE}) / sum(mass) / norm AS mu FROM (SELECT ((o_custkey * 31) % 997)::DOUBLE / 997 AS x, ((o_custkey * 17) % 991)::DOUBLE / 991 AS y, o_totalprice AS mass FROM orders), ({_B3}) GROUP BY k1, k2, norm, lam"
_SUMS = f"SELECT k1, k2, round(sum({_VALUE} / norm), 5) + 0.0 AS total FROM ({_AGENTS}), ({_B3}) GROUP BY ALL"
_CONTAMINANT = f"""WITH RECURSIVE air AS MATERIALIZED (SELECT src, dst, w AS f FROM ({BUILDING}) UNION ALL VALUES (-1, 127, 2.0), (0, -1, 0.5), (7, -1, 0.5), (56, -1, 0.5), (63, -1, 0.5)),
  m AS MATERIALIZED (SELECT src AS id, src AS too, -sum(f) AS f, true AS own FROM air WHERE src >= 0 GROUP BY src UNION ALL SELECT src, dst, f, false FROM air WHERE src >= 0 AND dst >= 0),
  s(t, id, c) AS (SELECT 0, i, 0.0::DOUBLE FROM range(128) r(i) UNION ALL
    SELECT t + 1, too, max(CASE WHEN own THEN c END) + 0.1::DOUBLE / 50 * (sum(f * c) + CASE WHEN too IN (9, 54, 73, 118) THEN 5 ELSE 0 END - 0.01::DOUBLE * max(CASE WHEN own THEN c END))
    FROM s JOIN m USING (id) WHERE t < 100 GROUP BY t + 1, too)
  SELECT id, round(c, 9) + 0.0 AS c FROM s WHERE t = 100"""
_HALF = f"SELECT x, y, sum(w) AS w FROM (SELECT month(o_orderdate) AS m, c_nationkey AS x, s_nationkey AS y, 1 AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey) WHERE {{}} GROUP BY ALL"

ORACLES: dict[str, str] = {
    **{f"{name}_graph": links(sql) for name, sql in {"trade": TRADE, "region_chain": CHAIN, "region_trade": ALIKE, "copurchase": COPURCHASE, "part_supp": PART_SUPP, "cust_part": CUST_PART, "user_line": USER_LINE, "day_ring": DAY_RING, "conv_chain": CONV, "building": BUILDING.replace("range(128) t(i)", _ROOMS)}.items()},
    "doc_words_graph": f"""WITH RECURSIVE e AS MATERIALIZED ({DOC_WORDS}), d AS MATERIALIZED (SELECT DISTINCT doc_id::BIGINT AS doc_id FROM documents WHERE doc_id IS NOT NULL),
  m AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT doc_id, doc_id FROM d),
  l(t, id, c) AS (SELECT 0, doc_id, doc_id FROM d UNION ALL SELECT t + 1, dst, min(c) FROM l JOIN m ON src = id WHERE t < 24 GROUP BY t + 1, dst)
  SELECT doc_id, count(src) AS n_links, coalesce(sum(w), 0)::DOUBLE AS weight, any_value(c) AS component_id FROM d JOIN l ON id = doc_id AND t = 24 LEFT JOIN e ON src = doc_id GROUP BY doc_id""",
    "event_flow": "SELECT last AS a, event_type AS b, count(*) AS w FROM (SELECT event_type, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS last FROM events WHERE user_id IS NOT NULL) WHERE last IS NOT NULL GROUP BY ALL",
    "page_links": "SELECT host, target, count(*) AS w FROM (SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS target FROM pages) GROUP BY ALL",
    "degree_table": f"SELECT src AS id, round(sum(w), 6) AS deg FROM ({TRADE}) GROUP BY src",
    "walk_table": f"SELECT src, dst, round(w / sum(w) OVER (PARTITION BY src), 6) AS p FROM ({TRADE})",
    "walk_table_sym": f"WITH e AS ({TRADE}), d AS (SELECT src AS id, sum(w) AS deg FROM e GROUP BY 1) SELECT src, dst, round(w / sqrt(a.deg * b.deg), 6) AS p FROM e JOIN d a ON src = a.id JOIN d b ON dst = b.id",
    "components_conv_chain": "SELECT conv_id * 1000 + turn AS id, min(conv_id * 1000 + turn) OVER (PARTITION BY conv_id) AS component FROM conversations QUALIFY count(*) OVER (PARTITION BY conv_id) > 1",
    "wave_1": last(TRADE, 1), "wave_2": last(TRADE, 2), "wave_50": last(TRADE, 50), "wave_centered": last(TRADE, 20, center=True),
    "wave_lazy_20": loop(TRADE, 20, 2 - 1.95, 1.0, 1.95, lazy=True) + " SELECT id, round(u, 6) + 0.0 AS u0 FROM s WHERE t = 20",
    "wave_multi_seed": f"SELECT a.id, a.u0, b.u0 AS u1, c.u0 AS u2 FROM ({last(TRADE, 10)}) a JOIN ({last(TRADE, 10, start=u0('id', 1))}) b USING (id) JOIN ({last(TRADE, 10, start=u0('id', 2))}) c USING (id)",
    "wave_copurchase_10": last(COPURCHASE, 10), "wave_part_supp_10": last(PART_SUPP, 10), "day_ring_wave_5": last(DAY_RING, 5),
    "growth_bad_start": f"{wave(TRADE, 40, previous='0.0::DOUBLE')} SELECT t::INT AS t, round(max(abs(u)), 5) AS amplitude FROM s WHERE t > 0 GROUP BY t",
    "dft_bins_trade": fourier(TRADE, 32, "1, 2, 4, 8") + " SELECT id, bin, round(re, 6) + 0.0 AS re, round(im, 6) + 0.0 AS im FROM f",
    "windowed_dft": fourier(TRADE, 32, "2, 8", hann(32)) + " SELECT id, bin, round(re, 6) + 0.0 AS re, round(im, 6) + 0.0 AS im FROM f",
    "online_sums_trade": fourier(TRADE, 32, "2") + " SELECT id, round(re, 6) + 0.0 AS re, round(im, 6) + 0.0 AS im FROM f",
    "power_spectrum_region": fourier(CHAIN, 48, ", ".join(map(str, range(25))), hann(48)) + " SELECT bin, round(sum(deg * (re * re + im * im)), 3) AS power FROM f JOIN d USING (id) GROUP BY bin",
    "matched_filter_trade": f"{wave(TRADE, 32)} SELECT id, j::INT AS j, round(sum({hann(32)} * u * cos(w * (t + 0.5))), 6) + 0.0 AS coef FROM s, (VALUES (1, 1.0::DOUBLE), (2, 1.5::DOUBLE)) o(j, w) WHERE t > 0 GROUP BY ALL",
    "matched_sine_trade": f"{wave(TRADE, 32)} SELECT id, j::INT AS j, round(sum({hann(32)} * u * sin(w * t)), 6) + 0.0 AS coef FROM s, (VALUES (1, 1.0::DOUBLE), (2, 1.5::DOUBLE)) o(j, w) WHERE t > 0 GROUP BY ALL",
    "companion_modulus": f"SELECT round(lam, 6) AS lam, round({_MODULUS}, 6) AS modulus, round(CASE WHEN b * b >= 4 THEN atan2(0.0, (b + sign(b) * sqrt(abs(b * b - 4))) / 2) ELSE atan2(sqrt(4 - b * b) / 2, b / 2) END, 6) AS phase FROM (SELECT lam, 2 - {C2} * lam AS b FROM (SELECT n_nationkey / 12.0::DOUBLE AS lam FROM nation))",
    "stability_sweep": f"SELECT round(c2, 6) AS c2, round(max({_MODULUS}), 6) AS modulus, max({_MODULUS}) < 1 + 1e-6 AS stable FROM (SELECT i / 10.0::DOUBLE AS c2, 2 - (i / 10.0::DOUBLE) * (j / 10.0::DOUBLE) AS b FROM range(1, 25) a(i), range(0, 21) c(j)) GROUP BY c2",
    "ring_bounds": _RING,
    "rate_compare": f"SELECT tau, n, round(w, 6) AS wave_steps, round(w + n, 6) AS wave_with_gather, round(tau * log2(n) ** 2, 6) AS walk_rounds, round(sqrt(tau) / sqrt({C2}), 6) AS wave_large_tau FROM (SELECT (10.0 * 2 ** k)::DOUBLE AS tau, n::BIGINT AS n, 6.5 / acos((2 + {C2} * (exp(-1 / (10.0 * 2 ** k)) - 1)) / 2) AS w FROM range(12) a(k), (SELECT unnest([100, 1000, 10000, 1000000]) AS n))",
    "mixing_kinds": "SELECT round(lam, 6) AS lam, round(-1 / ln(abs(1 - lam)), 6) AS second, round(-1 / ln(1 - lam / 2), 6) AS lazy, round(-1 / ln(greatest(abs(1 - lam), 0.9)), 6) AS slem FROM (SELECT i / 20.0::DOUBLE AS lam FROM range(1, 20) t(i))",
    "horizon_rules": f"SELECT round(lam, 6) AS lam, round({2 * math.pi * 6.5!r} / w, 6) AS cycles, round(6.5 / w, 6) AS printed, round({2 * math.pi * 6.5!r} / w + 1000, 6) AS gathered, round(1 / abs(w - acos((2 - {C2} * (lam + 0.05)) / 2)), 6) AS resolution FROM (SELECT lam, {_W2} AS w FROM (SELECT DISTINCT l_quantity / 51.0::DOUBLE AS lam FROM lineitem WHERE l_quantity IS NOT NULL))",
    **dict.fromkeys(["cluster_region", "spectral_exact_region"], "SELECT n_nationkey::BIGINT AS n_nationkey, min(n_nationkey) OVER (PARTITION BY n_regionkey)::BIGINT AS group_rep FROM nation"),
    "line20_cut_distributed": "SELECT i AS id, CASE WHEN i <= 10 THEN 1 ELSE 11 END::BIGINT AS group_rep FROM range(1, 21) t(i)",
    "line200_cut": "SELECT i AS id, CASE WHEN i <= 100 THEN 1 ELSE 101 END::BIGINT AS group_rep FROM range(1, 201) t(i)",
    "planted_cut": "SELECT i AS id, CASE WHEN i < 680 THEN 0 ELSE 680 END::BIGINT AS group_rep FROM range(1000) t(i)",
    "building_clusters": "SELECT i AS id, (64 + CASE WHEN i % 8 < 4 THEN 0 ELSE 4 END + CASE WHEN i % 64 < 32 THEN 0 ELSE 32 END)::BIGINT AS group_rep FROM " + _ROOMS + " WHERE i >= 64",
    "heat_20": loop(TRADE, 20, 0.5, 0.0, 0.5) + " SELECT id, round(u, 6) + 0.0 AS u0 FROM s WHERE t = 20",
    "lazy_power_30": loop(TRADE, 30, 0.5, 0.0, 0.5, center=True) + " SELECT id, round(u, 9) + 0.0 AS u0 FROM s WHERE t = 30",
    "minimum_cut_line": "SELECT 992::BIGINT AS mask, 0.1::DOUBLE AS cut, 5::BIGINT AS size",
    "best_ratio_cut_line": """WITH n AS MATERIALIZED (SELECT row_number() OVER (ORDER BY q) - 1 AS i, count(*) OVER () AS n FROM (SELECT DISTINCT l_quantity AS q FROM lineitem WHERE l_quantity <= 10)),
  e AS MATERIALIZED (SELECT i, CASE WHEN i = 4 THEN 0.1::DOUBLE ELSE 1.0::DOUBLE END AS w FROM n WHERE i < n - 1), m AS MATERIALIZED (SELECT DISTINCT x * 2 AS mask, n FROM range(1, 512) t(x), n WHERE x < 1 << (n - 1)::INT),
  c AS (SELECT mask, n, bit_count(mask) AS size, sum(CASE WHEN (mask >> i::INT) & 1 <> (mask >> (i + 1)::INT) & 1 THEN w ELSE 0 END) AS cut FROM m, e GROUP BY ALL)
  SELECT mask::BIGINT AS mask, round(cut * (1.0::DOUBLE / size + 1.0::DOUBLE / (n - size)), 6) AS ratio FROM c ORDER BY ratio, mask LIMIT 1""",
    "cut_weight_region": f"{_SIDES} SELECT round(sum(CASE WHEN ca <> cb THEN w ELSE 0 END) / 2, 6) AS cut FROM k",
    "ratio_cut_region": f"{_CUTS} SELECT round(sum(cut / n), 6) AS ratio_cut FROM z",
    "ncut_region": f"{_CUTS} SELECT round(sum(cut / volume), 6) AS ncut FROM z",
    "contingency": "SELECT cluster, truth, count(*) AS n FROM (SELECT (n_nationkey % 3)::BIGINT AS cluster, n_regionkey::BIGINT AS truth FROM nation) GROUP BY CUBE (cluster, truth)",
    "partition_scores": """WITH c AS (SELECT n_nationkey % 3 AS p, n_regionkey AS q, count(*) AS n FROM nation GROUP BY ALL), r AS (SELECT p, sum(n) AS n, max(n) AS top FROM c GROUP BY p), t AS (SELECT q, sum(n) AS n FROM c GROUP BY q),
      g AS (SELECT sum(n) AS n, sum(n * (n - 1) / 2.0) AS x FROM c), a AS (SELECT sum(n * (n - 1) / 2.0) AS a, -sum(n / 25.0 * ln(n / 25.0)) AS h, sum(top) AS top FROM r), b AS (SELECT sum(n * (n - 1) / 2.0) AS b, -sum(n / 25.0 * ln(n / 25.0)) AS h FROM t),
      i AS (SELECT sum(c.n / 25.0 * ln(c.n * 25.0 / (r.n * t.n))) AS i FROM c JOIN r USING (p) JOIN t USING (q))
      SELECT round(a.top / 25.0, 6)::DOUBLE AS purity, round((x - a * b / 300.0) / ((a + b) / 2 - a * b / 300.0), 6)::DOUBLE AS ari, round(i / ((a.h + b.h) / 2), 6) AS nmi, (25 - a.top)::BIGINT AS errors, 25::BIGINT AS n FROM g, a, b, i""",
    "agreement": "SELECT round(greatest(s, 1 - s), 6) AS agreement, greatest(s, 1 - s) = 1.0 AS equal FROM (SELECT avg(CASE WHEN n_regionkey % 2 = n_nationkey % 2 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS s FROM nation)",
    "messages": f"SELECT (count(*) * 200)::BIGINT AS messages, (count(*) * 3200)::BIGINT AS matrix_messages FROM ({TRADE})",
    "consensus_10_two": consensus("id // 64", 10), "consensus_10_five": consensus(_FIVE, 10), "consensus_60_five": consensus(_FIVE, 60),
    "cluster_means": f"SELECT cluster, round(avg(x), 4) AS mean, count(*) AS n FROM (SELECT ({_FIVE})::BIGINT AS cluster, x FROM ({_READ})) GROUP BY cluster",
    "fused_mean": f"SELECT round(avg(x), 4) AS x FROM ({_READ})",
    "contaminant_100": _CONTAMINANT,
    "basis_table": "SELECT k1, k2, norm, round(lam, 6) AS lam FROM (" + _BASIS.replace("range({n})", "(SELECT DISTINCT l_linenumber - 1 FROM lineitem WHERE l_linenumber BETWEEN 1 AND 5)") + ")",
    "prior_mu": f"SELECT k1, k2, round(mu, 6) + 0.0 AS mu FROM ({_MU})",
    "search_sum_central": _SUMS, "search_sum_clustered": _SUMS,
    "search_gradient": f"SELECT id, round(sum(lam * -mu / norm * -k1 * {_PI} * sin(k1 * {_PI} * x) * cos(k2 * {_PI} * y)), 5) + 0.0 AS bx, round(sum(lam * -mu / norm * -k2 * {_PI} * cos(k1 * {_PI} * x) * sin(k2 * {_PI} * y)), 5) + 0.0 AS by FROM ({_AGENTS}), ({_MU}) GROUP BY id",
    "weekly_event_flow": "SELECT (epoch(ts)::BIGINT // 604800 * 604800)::BIGINT AS start, last AS a, event_type AS b, count(*) AS w FROM (SELECT ts, event_type, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS last FROM events WHERE user_id IS NOT NULL) WHERE last IS NOT NULL GROUP BY ALL",
    "event_sessions": "WITH g AS (SELECT *, sum(CASE WHEN since IS NULL OR ts - since >= INTERVAL 2 DAY THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS since FROM events WHERE user_id IS NOT NULL)) SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, floor(epoch(max(ts) + INTERVAL 2 DAY))::BIGINT AS \"end\", count(*) AS n FROM g GROUP BY user_id, k",
    "monthly_trade_drift": f"WITH a AS ({both(_HALF.format('m <= 6'))}), b AS ({both(_HALF.format('m > 6'))}) SELECT round(sum(abs(coalesce(a.w, 0) - coalesce(b.w, 0))) / sum(coalesce(a.w, 0) + coalesce(b.w, 0)), 6) AS drift FROM a FULL JOIN b ON a.src = b.src AND a.dst = b.dst",
}
ORACLES["dft_arrays_trade"] = ORACLES["dft_bins_trade"]
for _name, _lazy in (("walk_20", False), ("lazy_walk_20", True)):
    _half = "0.5::DOUBLE *" if _lazy else ""
    _loops = "UNION ALL SELECT id, id, 0.5::DOUBLE FROM d" if _lazy else ""
    ORACLES[_name] = f"""WITH RECURSIVE e AS MATERIALIZED ({TRADE}), d AS MATERIALIZED (SELECT src AS id, sum(w) AS deg FROM e GROUP BY 1), p AS MATERIALIZED (SELECT src, dst, {_half} w / deg AS p FROM e JOIN d ON src = id {_loops}),
    s(t, id, pi) AS (SELECT 0, 0::BIGINT, 1.0::DOUBLE UNION ALL SELECT t + 1, dst, sum(p * pi) FROM s JOIN p ON src = id WHERE t < 20 GROUP BY t + 1, dst) SELECT id, round(pi, 6) AS pi FROM s WHERE t = 20"""
