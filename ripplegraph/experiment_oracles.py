"""SQL that checks the experiments' queries on the same tables."""

from __future__ import annotations

import math

from ripplegraph.oracles import _AGENTS, _B3, _FIVE, _MU, _PI, _READ, _REP, _ROOMS, _VALUE, BUILDING, C2, CHAIN, DAY_RING, TRADE, fourier, hann, last, loop, u0, wave

_TURN = f"{2 * math.pi!r}::DOUBLE"


def window(kind: str, steps: int) -> str:
    x = f"({2 * math.pi / steps!r}::DOUBLE * (t - 0.5))"
    return {"hamming": f"(0.54 - 0.46 * cos({x}))", "blackman": f"(0.42 - 0.5 * cos({x}) + 0.08 * cos(2 * {x}))"}[kind]


def _tops(key: str = "") -> str:
    """``tops(key, bin, power, j)``: peaks of ``pw(key, bin, power)`` in the order of bins."""
    part = f"PARTITION BY {key} " if key else ""
    lead = f"{key}, " if key else ""
    return f"""nb AS (SELECT *, lag(power) OVER o AS last, lead(power) OVER o AS following, min(power) OVER ({part}ORDER BY bin ROWS BETWEEN 4 PRECEDING AND 1 PRECEDING) AS below,
      min(power) OVER ({part}ORDER BY bin ROWS BETWEEN 1 FOLLOWING AND 4 FOLLOWING) AS above FROM pw WINDOW o AS ({part}ORDER BY bin)),
    tops AS (SELECT {lead}bin, power, row_number() OVER ({part}ORDER BY bin) AS j FROM nb WHERE bin > 0 AND power > coalesce(last, 0) AND power >= coalesce(following, 0) AND power >= 3.0 * least(coalesce(below, 0), coalesce(above, 0)))"""


def _spectra(steps: int) -> str:
    """``f(id, b, re, im)`` of the region chain from a centred start, all bins."""
    angle = f"({2 * math.pi / steps!r}::DOUBLE * b * t)"
    return f"""{wave(CHAIN, steps, center=True)},
    f AS MATERIALIZED (SELECT id, b, sum({hann(steps)} * u * cos({angle})) AS re, sum(-{hann(steps)} * u * sin({angle})) AS im FROM s, (SELECT unnest(range(0, {steps // 2 + 1})) AS b) WHERE t > 0 GROUP BY ALL)"""


_POOLED = "pw AS (SELECT b AS bin, sum(deg * (re * re + im * im)) AS power FROM f JOIN d USING (id) GROUP BY b)"
_OWN = "pw AS (SELECT id, b AS bin, re * re + im * im AS power FROM f)"
_OMEGA = f"{_TURN} * bin / 200"
_PEAKS = f"{_spectra(200)}, {_POOLED}, {_tops()}, pk AS (SELECT j::INT AS j, bin::INT AS bin, {_OMEGA} AS omega, 2 * (1 - cos({_OMEGA})) / {C2} AS lam FROM tops WHERE j <= 4)"
_BITS = f"""{_spectra(200)}, {_POOLED}, {_tops()}, y AS (SELECT f.id, j, deg, re, im FROM f JOIN tops ON b = bin JOIN d ON d.id = f.id WHERE j <= 2),
  th AS (SELECT j, 0.5 * atan2(sum(deg * 2 * re * im), sum(deg * (re * re - im * im))) AS theta FROM y GROUP BY j),
  c AS (SELECT id, y.j, deg, re * cos(theta) + im * sin(theta) AS coef FROM y JOIN th ON y.j = th.j),
  g AS (SELECT j, arg_min(coef, id) AS head, sqrt(sum(deg * coef * coef) / sum(deg)) AS rms FROM c GROUP BY j),
  z AS (SELECT id, c.j, CASE WHEN (coef > 0) = (head > 0) THEN 1 ELSE 0 END AS bit, abs(coef) / rms AS off FROM c JOIN g ON c.j = g.j),
  l AS (SELECT id, max(CASE WHEN j = 1 THEN bit END)::INT AS b1, max(CASE WHEN j = 2 THEN bit END)::INT AS b2, sum(bit * j)::BIGINT AS cluster, min(off) AS margin FROM z GROUP BY id)
  SELECT id, b1, b2, cluster, min(id) OVER (PARTITION BY cluster) AS group_rep, round(margin, 5) AS margin FROM l"""


def _vectors(steps: int) -> str:
    return f"""{wave(TRADE, steps)}, m AS (SELECT id, j::INT AS j, sum({hann(steps)} * u * cos(w * (t + 0.5))) AS coef FROM s, (VALUES (1, 1.0::DOUBLE), (2, 1.5::DOUBLE)) o(j, w) WHERE t > 0 GROUP BY ALL),
    n AS (SELECT j, sqrt(sum(deg * coef * coef)) * sign(arg_min(coef, id)) AS norm FROM m JOIN d USING (id) GROUP BY j)
    SELECT id, j, deg, coef / norm AS component FROM m JOIN n USING (j) JOIN d USING (id)"""


_SIZES = ", ".join(map(str, (8, 16, 32, 64)))
_SPANS = ", ".join(map(str, (16, 32, 64, 128, 256, 512, 1024)))
_RINGS = f"""SELECT n * 1000 + i AS src, n * 1000 + (i + k) % n AS dst, 1.0::DOUBLE AS w FROM (SELECT n, unnest(range(0, n)) AS i FROM (SELECT unnest([{_SIZES}])::BIGINT AS n)), (SELECT unnest([1, -1]) AS k), LATERAL (SELECT 1)
  WHERE true""".replace("(i + k) % n", "(i + k + n) % n").replace(", LATERAL (SELECT 1)\n  WHERE true", "")
_START = f"({u0('id', 0)}) - avg({u0('id', 0)}) OVER (PARTITION BY id // 1000)"
_HEARD = f"""{loop(_RINGS, 1024, 2 - C2, 1.0, C2, start=_START)},
  f AS (SELECT id, steps, b, sum(h * u * cos({_TURN} * b * t / steps)) AS re, sum(h * u * sin({_TURN} * b * t / steps)) AS im
    FROM (SELECT id, t, u, steps, 0.5 - 0.5 * cos({_TURN} * (t - 0.5) / steps) AS h FROM s, (SELECT unnest([{_SPANS}]) AS steps) WHERE t BETWEEN 1 AND steps), (SELECT unnest(range(0, 141)) AS b) WHERE b <= steps // 2 GROUP BY ALL),
  pw AS (SELECT id // 1000 * 10000 + steps AS run, b AS bin, sum(re * re + im * im) AS power FROM f GROUP BY ALL), {_tops("run")},
  heard AS MATERIALIZED (SELECT run // 10000 AS n, run % 10000 AS steps, {_TURN} * bin / (run % 10000) AS omega FROM tops WHERE j = 1),
  settled AS (SELECT a.n, min(a.steps) AS wave_rounds FROM heard a JOIN heard b ON a.n = b.n AND a.steps = 2 * b.steps WHERE abs(a.omega - b.omega) <= greatest(0.02 * a.omega, {_TURN} / a.steps) AND a.omega * a.steps >= {_TURN} * 10 GROUP BY a.n)"""
_MIXED = f"""WITH RECURSIVE e AS MATERIALIZED ({_RINGS}), p AS MATERIALIZED (SELECT src, dst, 0.25::DOUBLE AS p FROM e UNION ALL SELECT DISTINCT src, src, 0.5::DOUBLE FROM e),
  s(t, id, pi) AS (SELECT 0, n * 1000, 1.0::DOUBLE FROM (SELECT unnest([{_SIZES}])::BIGINT AS n) UNION ALL SELECT t + 1, dst, sum(p * pi) FROM s JOIN p ON src = id WHERE t < 900 GROUP BY t + 1, dst),
  v AS (SELECT t, id // 1000 AS n, (sum(abs(pi - 1.0 / (id // 1000))) + (id // 1000 - count(*)) / (id // 1000)) / 2 AS far FROM s GROUP BY t, id // 1000)
  SELECT n, min(t)::BIGINT AS walk_rounds FROM v WHERE far <= 0.25 GROUP BY n"""
_CONVERGED = f"SELECT a.n, wave_rounds::BIGINT AS wave_rounds, walk_rounds FROM ({_HEARD} SELECT n, wave_rounds FROM settled) a JOIN ({_MIXED}) b ON a.n = b.n"
_ROUNDS = "1, 2, 5, 10, 20, 50, 100, 200, 500, 1000"


def _errors(name: str, label: str) -> str:
    a, b = label.replace("id", "src"), label.replace("id", "dst")
    return f"""SELECT * FROM (WITH RECURSIVE e AS MATERIALIZED (SELECT src, dst FROM ({BUILDING}) WHERE {a} = {b}), n AS (SELECT src, count(*) AS n FROM e GROUP BY 1),
    p0 AS (SELECT e.src, e.dst, 1.0::DOUBLE / (1 + greatest(x.n, y.n)) AS p FROM e JOIN n x ON e.src = x.src JOIN n y ON e.dst = y.src), v AS MATERIALIZED ({_READ}),
    p AS MATERIALIZED (SELECT * FROM p0 UNION ALL SELECT id, id, 1 - coalesce((SELECT sum(p) FROM p0 WHERE src = id), 0) FROM v),
    s(t, id, x) AS (SELECT 0, id, x FROM v UNION ALL SELECT t + 1, src, sum(p * x) FROM s JOIN p ON dst = id WHERE t < 1000 GROUP BY t + 1, src),
    m AS (SELECT id, avg(x) OVER (PARTITION BY {label}) AS mean FROM v)
    SELECT '{name}' AS strategy, t::INT AS rounds, sqrt(avg((x - mean) ** 2)) AS rms FROM s JOIN m USING (id) WHERE t IN ({_ROUNDS}) GROUP BY t)"""


_ERRORS = f"{_errors('two', 'id // 64')} UNION ALL {_errors('five', f'({_FIVE})')}"
_AIR = f"SELECT src, dst, w AS f FROM ({BUILDING}) UNION ALL VALUES (-1, 127, 2.0), (0, -1, 0.5), (7, -1, 0.5), (56, -1, 0.5), (63, -1, 0.5)"
_RK4 = f"""WITH RECURSIVE air AS MATERIALIZED ({_AIR}),
  m AS MATERIALIZED (SELECT src AS id, src AS too, -sum(f) AS f, true AS own FROM air WHERE src >= 0 GROUP BY src UNION ALL SELECT src, dst, f, false FROM air WHERE src >= 0 AND dst >= 0),
  s(t, id, c, y, total) AS (SELECT 0, i, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE FROM range(128) r(i) UNION ALL
    SELECT t, id, CASE WHEN g = 3 THEN c + 0.1 * grown ELSE c END, CASE WHEN g = 3 THEN c + 0.1 * grown WHEN g = 2 THEN c + 0.1 * slope ELSE c + 0.05 * slope END, CASE WHEN g = 3 THEN 0.0 ELSE grown END
    FROM (SELECT t + 1 AS t, id, c, t % 4 AS g, slope, total + slope * CASE WHEN t % 4 IN (0, 3) THEN 1.0::DOUBLE / 6 ELSE 1.0::DOUBLE / 3 END AS grown
      FROM (SELECT t, too AS id, max(CASE WHEN own THEN c END) AS c, max(CASE WHEN own THEN total END) AS total,
        (sum(f * y) + CASE WHEN too IN (9, 54, 73, 118) THEN 5 ELSE 0 END - 0.01::DOUBLE * max(CASE WHEN own THEN y END)) / 50 AS slope FROM s JOIN m USING (id) WHERE t < 32 GROUP BY t, too)))
  SELECT id, round(c, 9) + 0.0 AS c FROM s WHERE t = 32"""


def _fold(x: str) -> str:
    return f"CASE WHEN {x} < 0 THEN -({x}) WHEN {x} > 1 THEN 2 - ({x}) ELSE {x} END"


def _slopes(agents: str, stats: str) -> str:
    """Unit vectors against the slope at each agent."""
    return f"""SELECT id, CASE WHEN sqrt(bx * bx + "by" * "by") > 1e-12 THEN -0.5 * bx / sqrt(bx * bx + "by" * "by") ELSE 0 END AS dx, CASE WHEN sqrt(bx * bx + "by" * "by") > 1e-12 THEN -0.5 * "by" / sqrt(bx * bx + "by" * "by") ELSE 0 END AS dy
    FROM (SELECT id, sum(lam * s / norm * -k1 * {_PI} * sin(k1 * {_PI} * x) * cos(k2 * {_PI} * y)) AS bx, sum(lam * s / norm * -k2 * {_PI} * cos(k1 * {_PI} * x) * sin(k2 * {_PI} * y)) AS "by" FROM {agents}, {stats} GROUP BY id)"""


def _grown(agents: str, stats: str, base: str, share: float) -> str:
    return f"""SELECT k1, k2, norm, lam, mu, {base} + {share!r}::DOUBLE * (total - (SELECT count(*) FROM a0) * mu) AS s FROM {stats} JOIN (SELECT k1, k2, sum({_VALUE} / norm) AS total FROM {agents}, ({_B3}) GROUP BY k1, k2) USING (k1, k2)"""


_HEAD = f"WITH mu AS MATERIALIZED ({_MU}), a0 AS MATERIALIZED ({_AGENTS}), s0 AS MATERIALIZED (SELECT *, 0.0::DOUBLE AS s FROM mu)"


def _midpoint(steps: int) -> str:
    parts = [_HEAD]
    for t in range(steps):
        now, then = f"a{t}", f"a{t + 1}"
        parts.append(f"h{t} AS MATERIALIZED ({_grown(now, f's{t}', 's', 0.025)})")
        parts.append(f"m{t} AS MATERIALIZED (SELECT id, {_fold('x + 0.025 * dx')} AS x, {_fold('y + 0.025 * dy')} AS y FROM {now} JOIN ({_slopes(now, f'h{t}')}) USING (id))")
        parts.append(f"s{t + 1} AS MATERIALIZED ({_grown(f'm{t}', f's{t}', 's', 0.05)})")
        parts.append(f"{then} AS MATERIALIZED (SELECT id, {_fold('x + 0.05 * dx')} AS x, {_fold('y + 0.05 * dy')} AS y FROM {now} JOIN ({_slopes(f'm{t}', f's{t + 1}')}) USING (id))")
    return ", ".join(parts)


def _rk4() -> str:
    """One fourth-order step: points (p, q) of the stages, slopes (v) and growths (g) at them."""
    parts = [_HEAD, "p0 AS MATERIALIZED (SELECT * FROM a0)", "q0 AS MATERIALIZED (SELECT * FROM s0)"]
    for i, share in enumerate((0.5, 0.5, 1.0, 0.0)):
        parts.append(f"v{i} AS MATERIALIZED ({_slopes(f'p{i}', f'q{i}')})")
        parts.append(f"g{i} AS MATERIALIZED ({_grown(f'p{i}', f'q{i}', '0', 1.0)})")
        move = lambda c: _fold(f"a0.{c} + {0.05 * share!r}::DOUBLE * d{c}")  # noqa: B023, E731
        parts.append(f"p{i + 1} AS MATERIALIZED (SELECT id, {move('x')} AS x, {move('y')} AS y FROM a0 JOIN v{i} USING (id))")
        parts.append(f"q{i + 1} AS MATERIALIZED (SELECT s0.k1, s0.k2, s0.norm, s0.lam, s0.mu, s0.s + {0.05 * share!r}::DOUBLE * g{i}.s AS s FROM s0 JOIN g{i} USING (k1, k2))")
    mean = lambda c: f"(v0.{c} + 2 * v1.{c} + 2 * v2.{c} + v3.{c}) / 6"
    end = lambda c: _fold(f"a0.{c} + 0.05::DOUBLE * {mean('d' + c)}")
    parts.append(f"a1 AS (SELECT id, {end('x')} AS x, {end('y')} AS y FROM a0 JOIN v0 USING (id) JOIN v1 USING (id) JOIN v2 USING (id) JOIN v3 USING (id))")
    parts.append("s1 AS (SELECT k1, k2, 0.05::DOUBLE * (g0.s + 2 * g1.s + 2 * g2.s + g3.s) / 6 AS s FROM g0 JOIN g1 USING (k1, k2) JOIN g2 USING (k1, k2) JOIN g3 USING (k1, k2))")
    return ", ".join(parts)


_ROUND = "round({0}, 5) + 0.0 AS {0}"
_PLACES = f"SELECT id, {_ROUND.format('x')}, {_ROUND.format('y')}"
#: The months in which there are orders, from 0, and their number.
_MONTHS = "(SELECT row_number() OVER (ORDER BY m) - 1 AS j, count(*) OVER () AS n FROM (SELECT DISTINCT month(o_orderdate) AS m FROM orders WHERE o_orderdate IS NOT NULL))"
_CASES = "SELECT c2, bool_or(abs(lam) < 1e-9) AS constant_mode, bool_or(times > 1) AS repeated, bool_or(abs(lam - 2) < 1e-9 AND c2 >= 2) AS alternating_mode FROM (SELECT c2, lam, count(*) AS times FROM (SELECT round(1 - cos({0} * j / n), 9) AS lam FROM {1}), (SELECT unnest([1.99::DOUBLE, 2.0::DOUBLE]) AS c2) GROUP BY ALL) GROUP BY c2"
_SWEEP = f"""WITH RECURSIVE e AS MATERIALIZED ({CHAIN}), d AS MATERIALIZED (SELECT src AS id, sum(w) AS deg FROM e GROUP BY 1), p AS MATERIALIZED (SELECT src, dst, 0.5::DOUBLE * w / deg AS p FROM e JOIN d ON src = id UNION ALL SELECT id, id, 0.5::DOUBLE FROM d),
  s(t, id, pi) AS (SELECT 0, 0::BIGINT, 1.0::DOUBLE UNION ALL SELECT t + 1, dst, sum(p * pi) FROM s JOIN p ON src = id WHERE t < 20 GROUP BY t + 1, dst HAVING sum(p * pi) >= 1e-4),
  o AS MATERIALIZED (SELECT id, deg, row_number() OVER (ORDER BY pi / deg DESC, id) AS place FROM s JOIN d USING (id) WHERE t = 20),
  i AS (SELECT a.id, sum(w) AS held FROM e JOIN o a ON src = a.id JOIN o b ON dst = b.id WHERE b.place < a.place GROUP BY a.id),
  k AS (SELECT id, place, sum(deg) OVER q AS volume, sum(deg - 2 * coalesce(held, 0)) OVER q AS cut FROM o LEFT JOIN i USING (id) WINDOW q AS (ORDER BY place)),
  z AS (SELECT *, CASE WHEN least(volume, (SELECT sum(deg) FROM d) - volume) > 1e-9 * (SELECT sum(deg) FROM d) THEN cut / least(volume, (SELECT sum(deg) FROM d) - volume) END AS conductance FROM k)
  SELECT id, place, round(cut, 6) + 0.0 AS cut, round(volume, 6) + 0.0 AS volume, round(conductance, 6) + 0.0 AS conductance, place <= (SELECT place FROM z WHERE conductance IS NOT NULL ORDER BY conductance, place LIMIT 1) AS inside FROM z"""

ORACLES: dict[str, str] = {
    "wave_given_start": last(TRADE, 10, start="id / 25.0::DOUBLE"),
    "ring_wave": last("SELECT i AS src, (i + k + 32) % 32 AS dst, 1.0::DOUBLE AS w FROM range(32) r(i), (SELECT unnest([1, -1]) AS k)", 24),
    "day_ring_wave_blocks": last(DAY_RING, 10),
    "fft_trade": fourier(TRADE, 32, ", ".join(map(str, range(17)))) + " SELECT id, bin, round(re, 6) + 0.0 AS re, round(im, 6) + 0.0 AS im FROM f",
    "windowed_dft_kinds": " UNION ALL ".join(f"SELECT id, bin, round(re, 6) + 0.0 AS re, round(im, 6) + 0.0 AS im, '{kind}' AS kind FROM ({fourier(TRADE, 32, '2, 8', window(kind, 32))} SELECT * FROM f)" for kind in ("hamming", "blackman")),
    "detrended_trade": f"""SELECT how, id, t::INT AS t, round(u, 6) + 0.0 AS u FROM ({wave(TRADE, 12)}, h AS (SELECT id, t, u, deg FROM s JOIN d USING (id) WHERE t > 0)
      SELECT 'mean' AS how, id, t, u - avg(u) OVER (PARTITION BY id) AS u FROM h UNION ALL SELECT 'degree', id, t, u - sum(deg * u) OVER (PARTITION BY t) / sum(deg) OVER (PARTITION BY t) FROM h
      UNION ALL SELECT 'difference', id, t, u - lag(u) OVER (PARTITION BY id ORDER BY t) FROM h) WHERE u IS NOT NULL""",
    "peaks_region": f"{_PEAKS} SELECT j, bin, round(omega, 6) AS omega, round(lam, 6) AS lam FROM pk",
    "local_peaks_region": f"{_spectra(200)}, {_OWN}, {_tops('id')} SELECT id, j::INT AS j, bin::INT AS bin, round(2 * (1 - cos({_OMEGA})) / {C2}, 6) AS lam FROM tops WHERE j <= 2",
    "choose_k_region": f"{_PEAKS}, g AS (SELECT j, lead(omega) OVER (ORDER BY omega) - omega AS gap FROM pk) SELECT arg_max(j, gap) AS k FROM g WHERE gap IS NOT NULL",
    "bits_region": _BITS, "bits_region_distributed": _BITS,
    "relabel_region": f"{_REP} SELECT id, dense_rank() OVER (ORDER BY group_rep) - 1 AS label FROM r",
    "eigenvectors_trade": f"SELECT id, j, round(component, 6) + 0.0 AS component FROM ({_vectors(32)})",
    "gathered_trade": f"SELECT j, (row_number() OVER (PARTITION BY j ORDER BY id) - 1)::INT AS place, round(component, 6) + 0.0 AS component FROM ({_vectors(32)})",
    "vector_angle_trade": f"SELECT a.j, round(acos(least(abs(sum(a.deg * a.component * b.component)) / sqrt(sum(a.deg * a.component ** 2) * sum(a.deg * b.component ** 2)), 1)), 4) + 0.0 AS angle FROM ({_vectors(32)}) a JOIN ({_vectors(48)}) b ON a.id = b.id AND a.j = b.j GROUP BY a.j",
    "growth_cases_ring": _CASES.format(_TURN, _MONTHS),
    "state_costs": "SELECT r::INT AS seeds, f::INT AS frequencies, h::INT AS history, (8 * r * (2 + 2 * f + h))::BIGINT AS bytes, (1000 * r * 1000 * r * f)::BIGINT AS gather FROM (SELECT unnest([1, 8]) AS r), (SELECT unnest([0, 1, 4]) AS f), (SELECT unnest([0, 200]) AS h)",
    "eigenvalues_path": f"SELECT j::INT AS j, round(1 - cos({_PI} * j / (n - 1)), 6) + 0.0 AS lam FROM {_MONTHS}",
    "orthogonal_path": f"SELECT j::INT AS j, round(1 - cos({_PI} * j / 7), 4) AS lam FROM range(1, 4) t(j)",
    "subspace_path": f"SELECT j::INT AS j, round(1 - cos({_PI} * j / 7), 2) AS lam FROM range(1, 4) t(j)",
    "line_recursive": "SELECT i AS id, ((i - 1) // 8 * 8 + 1)::BIGINT AS group_rep FROM range(1, 33) t(i)",
    "region_five": "SELECT n_nationkey::BIGINT AS n_nationkey, min(n_nationkey) OVER (PARTITION BY n_regionkey)::BIGINT AS group_rep FROM nation",
    "five_clusters": f"SELECT i AS id, ({_FIVE.replace('id', 'i')})::BIGINT AS cluster FROM {_ROOMS}",
    "pair_swap_line": "SELECT i AS id, i <= 5 AS with_first FROM range(1, 11) t(i)",
    "ring_convergence": _CONVERGED,
    "ring_slopes": f"SELECT round(regr_slope(ln(wave_rounds), ln(n)), 4) AS wave_rounds_power, round(regr_slope(ln(walk_rounds), ln(n)), 4) AS walk_rounds_power FROM ({_CONVERGED})",
    "stable_steps_ring": f"""{_HEARD}, fin AS (SELECT n, arg_max(omega, steps) AS final FROM heard GROUP BY n), off AS (SELECT heard.n, steps, abs(omega / final - 1) > 0.02 AS far FROM heard JOIN fin ON heard.n = fin.n),
      worst AS (SELECT n, coalesce(max(CASE WHEN far THEN steps END), -1) AS worst FROM off GROUP BY n) SELECT off.n::INT AS n, min(steps)::BIGINT AS steps FROM off JOIN worst ON off.n = worst.n WHERE steps > worst GROUP BY off.n""",
    "consensus_errors": f"SELECT strategy, rounds, round(rms, 4) AS rms FROM ({_ERRORS})",
    "rounds_to_accuracy": f"WITH c AS MATERIALIZED ({_ERRORS}) SELECT min(rounds) AS rounds FROM c WHERE strategy = 'two' AND rms <= (SELECT rms FROM c WHERE strategy = 'five' AND rounds = 10)",
    "contaminant_rk4_8": _RK4,
    "search_rk4_1": f"{_rk4()} {_PLACES} FROM a1", "search_midpoint_2": f"{_midpoint(2)} {_PLACES} FROM a2",
    "search_statistics_rk4_1": f"{_rk4()} SELECT k1, k2, round(s, 4) + 0.0 AS s FROM s1", "search_statistics_2": f"{_midpoint(2)} SELECT k1, k2, round(s, 4) + 0.0 AS s FROM s2",
    "search_modes_agree": f"{_midpoint(2)} SELECT 0.0::DOUBLE AS gap, round(sum(lam * s * s), 3) AS coverage, round(sum(lam * s * s), 3) AS of_clusters FROM s2",
    "asof_reading": "SELECT o_orderkey, event_id FROM (SELECT o_orderkey, o_custkey, o_orderdate::TIMESTAMP AS placed FROM orders) ASOF LEFT JOIN (SELECT user_id, ts::TIMESTAMP AS ts, max(event_id) AS event_id FROM events WHERE user_id IS NOT NULL GROUP BY ALL) ON o_custkey = user_id AND placed >= ts",
    "truncated_walk_sweep": _SWEEP,
}
