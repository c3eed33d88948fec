"""DuckDB twins of the catalogue's queries: plain definitions, no tables of moves and no ranges."""

from __future__ import annotations

M, N, PARTS, SAMPLES = 12, 4, 8, 64


def _emb(m: int, n: int, words: int = 1) -> str:
    pick = f"""SELECT vec_id, i, row_number() OVER (PARTITION BY vec_id ORDER BY v DESC, i) AS r
      FROM (SELECT vec_id, unnest(embedding[1:{m}]) AS v, unnest(range(0, {m})) AS i FROM embeddings)"""
    if words == 1:
        return f"SELECT DISTINCT sum(1::BIGINT << i)::BIGINT AS w0 FROM ({pick}) WHERE r <= {n} GROUP BY vec_id"
    low, high = "CASE WHEN i < 63 THEN 1::BIGINT << i ELSE 0 END", "CASE WHEN i >= 63 THEN 1::BIGINT << (i - 63) ELSE 0 END"
    return f"SELECT DISTINCT sum({low})::BIGINT AS w0, sum({high})::BIGINT AS w1 FROM ({pick}) WHERE r <= {n} GROUP BY vec_id"


_BRANDS = "SELECT p_partkey, dense_rank() OVER (ORDER BY p_brand) - 1 AS o FROM part"
_LINES = f"SELECT l_orderkey AS k, o FROM lineitem JOIN ({_BRANDS}) ON l_partkey = p_partkey"


def _ord(n: int) -> str:
    return f"""SELECT DISTINCT sum(1::BIGINT << o)::BIGINT AS w0 FROM (
      SELECT k, o, row_number() OVER (PARTITION BY k ORDER BY o) AS r, count(*) OVER (PARTITION BY k) AS c
      FROM (SELECT DISTINCT l_orderkey AS k, o FROM lineitem JOIN ({_BRANDS}) ON l_partkey = p_partkey)) WHERE r <= {n} AND c >= {n} GROUP BY k"""


def _hours(groups: str, n: int = 3, order: str = "c DESC, h") -> str:
    return f"""SELECT DISTINCT sum(1::BIGINT << h)::BIGINT AS w0 FROM (
      SELECT user_id, g, h, row_number() OVER (PARTITION BY user_id, g ORDER BY {order}) AS r, count(*) OVER (PARTITION BY user_id, g) AS k
      FROM ({groups})) WHERE r <= {n} AND k >= {n} GROUP BY user_id, g"""


_DAYS = "SELECT user_id, date_trunc('day', ts) AS g, hour(ts) AS h, count(*) AS c FROM events GROUP BY ALL"
_SLIDING = """SELECT user_id, g, hour(ts) AS h, count(*) AS c FROM (
  SELECT user_id, ts, unnest([0, 6, 12, 18]) AS back, time_bucket(INTERVAL 6 HOURS, ts, TIMESTAMP '1970-01-01') - to_hours(back::INTEGER) AS g FROM events) GROUP BY ALL"""
_SESSIONS = """SELECT user_id, g, hour(ts) AS h, count(*) AS c FROM (
  SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (
    SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY ALL"""

_DOCS = """SELECT DISTINCT sum(1::BIGINT << i)::BIGINT AS w0 FROM (
  SELECT doc_id, i, row_number() OVER (PARTITION BY doc_id ORDER BY c DESC, i) AS r, count(*) OVER (PARTITION BY doc_id) AS k FROM (
    SELECT doc_id, i, length(t) - length(replace(t, chr(97 + i::INTEGER), '')) AS c FROM (SELECT doc_id, lower(text) AS t, unnest(range(0, 26)) AS i FROM documents)) WHERE c > 0)
  WHERE r <= 6 AND k >= 6 GROUP BY doc_id"""


def _space(m: int, n: int) -> str:
    return f"SELECT range::BIGINT AS w FROM range(0, {1 << m}) WHERE bit_count(range::BIGINT) = {n}"


#: integrals of the table Hamiltonian: factor matrices b, one-body h1, two-body g, direct minus exchange v
_HAM = f"""br AS ({_BRANDS}),
ln AS (SELECT DISTINCT l_returnflag AS f, l_orderkey AS k, o::INTEGER AS o FROM lineitem JOIN br ON l_partkey = p_partkey WHERE o < {M}),
cn AS (SELECT a.f, a.o AS p, b.o AS q, count(*) AS c FROM ln a JOIN ln b ON a.f = b.f AND a.k = b.k GROUP BY ALL),
fs AS (SELECT DISTINCT f FROM ln), ob AS (SELECT range::INTEGER AS o FROM range(0, {M})),
gr AS (SELECT fs.f, x.o AS p, y.o AS q, coalesce(c, 0) AS c, coalesce(c, 0) % 7 - 3 AS b FROM fs CROSS JOIN ob x CROSS JOIN ob y LEFT JOIN cn ON cn.f = fs.f AND cn.p = x.o AND cn.q = y.o),
h1 AS (SELECT p, q, (CASE WHEN p = q THEN -(sum(c) % 101) ELSE -(sum(c) % 11) END)::BIGINT AS v FROM gr GROUP BY p, q),
g AS MATERIALIZED (SELECT x.p, x.q, y.p AS r, y.q AS s, sum(x.b * y.b)::BIGINT AS v FROM gr x JOIN gr y ON x.f = y.f GROUP BY ALL),
v AS MATERIALIZED (SELECT d.p, d.r AS q, d.q AS a, d.s AS b, d.v - e.v AS v FROM g d JOIN g e ON e.p = d.p AND e.q = d.s AND e.r = d.r AND e.s = d.q),
ctx AS MATERIALIZED (SELECT d.p, d.q AS a, d.r AS k, d.v - e.v AS v FROM g d JOIN g e ON d.r = d.s AND e.p = d.p AND e.q = d.r AND e.r = d.r AND e.s = d.q)"""

_GAP = "(((1::BIGINT << greatest({0}, {1})) - 1) & ~((1::BIGINT << (least({0}, {1}) + 1)) - 1))"
_GAP = "(((1::BIGINT << greatest({0}, {1})) - 1) - ((1::BIGINT << greatest({0}, {1})) - 1) % (2::BIGINT << least({0}, {1})))"


def _bit(x: str) -> str:
    return f"(bit_count(({x}) - 1)::INTEGER)"


def _edges(sources: str) -> str:
    """CTEs ending in ``ed(sw0, w0, h, kind)``: every source against every configuration, values by the rules for moved particles."""
    low = lambda x: f"(({x}) & -({x}))"
    return f"""{_HAM},
src AS MATERIALIZED ({sources}), fl AS MATERIALIZED ({_space(M, N)}),
pr AS MATERIALIZED (SELECT s.w0 AS i, fl.w AS j, (s.w0 & xor(s.w0, fl.w)) AS off, (fl.w & xor(s.w0, fl.w)) AS new FROM src s, fl WHERE bit_count(xor(s.w0, fl.w)) <= 4),
occ AS MATERIALIZED (SELECT w0 AS i, o FROM src, ob WHERE (w0 >> o) & 1 = 1),
e0 AS (SELECT i, i AS j, sum(x)::BIGINT AS h FROM (SELECT occ.i, h1.v AS x FROM occ JOIN h1 ON h1.p = o AND h1.q = o
       UNION ALL SELECT c.i, v.v FROM occ c JOIN occ d ON c.i = d.i AND c.o < d.o JOIN v ON v.p = c.o AND v.q = d.o AND v.a = c.o AND v.b = d.o) GROUP BY i),
m1 AS (SELECT i, j, {_bit('off')} AS p, {_bit('new')} AS a FROM pr WHERE bit_count(off) = 1),
e1 AS (SELECT m1.i, m1.j, (min(h1.v) + sum(ctx.v)) * (1 - 2 * (bit_count(m1.i & min({_GAP.format('m1.p', 'm1.a')})) % 2)) AS h
       FROM m1 JOIN h1 ON h1.p = m1.p AND h1.q = m1.a JOIN occ ON occ.i = m1.i JOIN ctx ON ctx.p = m1.p AND ctx.a = m1.a AND ctx.k = occ.o GROUP BY m1.i, m1.j),
m2 AS (SELECT i, j, {_bit(low('off'))} AS p, {_bit(f"off - {low('off')}")} AS q, {_bit(low('new'))} AS a, {_bit(f"new - {low('new')}")} AS b FROM pr WHERE bit_count(off) = 2),
e2 AS (SELECT i, j, v.v * (1 - 2 * ((bit_count(i & {_GAP.format('m2.p', 'm2.a')}) + bit_count(xor(xor(i, 1::BIGINT << m2.p), 1::BIGINT << m2.a) & {_GAP.format('m2.q', 'm2.b')})) % 2)) AS h
       FROM m2 JOIN v ON v.p = m2.p AND v.q = m2.q AND v.a = m2.a AND v.b = m2.b),
ed AS MATERIALIZED (SELECT i AS sw0, j AS w0, h::BIGINT AS h, 0 AS kind FROM e0 UNION ALL SELECT i, j, h::BIGINT, 1 FROM e1 WHERE h <> 0 UNION ALL SELECT i, j, h::BIGINT, 2 FROM e2 WHERE h <> 0)"""


_EMB12 = _emb(M, N)
_WITH = f"WITH {_edges(_EMB12)}"
_PSI = "({0} * 7919 % 1009 - 504)"
_EDGES = f"{_WITH} SELECT sw0, w0, h, kind::INTEGER AS kind FROM ed"


def _moved(name: str, m: int, n: int, sources: str) -> str:
    """CTEs ``src`` and ``mv(i, j)``: targets of all moves, by comparing all pairs."""
    return f"""WITH src AS MATERIALIZED ({sources}), fl AS MATERIALIZED ({_space(m, n)}),
mv AS (SELECT s.w0 AS i, fl.w AS j FROM src s, fl WHERE bit_count(xor(s.w0, fl.w)) IN (2, 4))"""


_ORD3 = _moved("ord3", 25, 3, _ord(3))
_DISTINCT = f"{_ORD3} SELECT DISTINCT j AS w0 FROM mv"
_SCORED = f"{_moved('emb12', M, N, _EMB12)}, sc AS (SELECT DISTINCT j AS w0, abs({_PSI.format('j')}) AS score FROM mv)"
_TOP = f"{_SCORED} SELECT w0, score::BIGINT AS score FROM sc ORDER BY score DESC, w0 LIMIT 50"

_KEYS = "SELECT (l_partkey * 1048576 + l_suppkey)::BIGINT AS w0 FROM lineitem"
_SPLIT = f"""WITH ky AS MATERIALIZED ({_KEYS}),
rk AS (SELECT w0, w0 % 8 AS g, row_number() OVER (PARTITION BY w0 % 8 ORDER BY w0) - 1 AS r, count(*) OVER (PARTITION BY w0 % 8) AS d FROM ky),
pl AS (SELECT DISTINCT g, d, CASE WHEN d < {SAMPLES} THEN k ELSE k * d // {SAMPLES} END AS r FROM (SELECT g, d, unnest(range(0, least(d, {SAMPLES}))) AS k FROM (SELECT DISTINCT g, d FROM rk))),
sm AS (SELECT rk.w0, rk.d / least(rk.d, {SAMPLES}) AS wt FROM rk JOIN pl USING (g, r)),
cu AS (SELECT w0, sum(wt) OVER (ORDER BY w0 ROWS UNBOUNDED PRECEDING) AS c, sum(wt) OVER () AS t FROM sm),
sp AS (SELECT j, min(w0) AS w0 FROM cu, range(1, {PARTS}) x(j) WHERE c >= j / {PARTS} * t - 1e-9 GROUP BY j)"""
_BALANCE = f"""{_SPLIT}, pt AS (SELECT w0, (SELECT count(*) FROM sp WHERE sp.w0 <= ky.w0) AS part FROM ky),
n AS (SELECT part, count(*)::DOUBLE AS n FROM pt GROUP BY part)
SELECT round(max(n), 6) AS max, round(min(n), 6) AS min, round(avg(n), 6) AS mean, round(stddev_pop(n), 6) AS std, round(max(n) / min(n), 6) AS ratio, round(stddev_pop(n) / avg(n), 6) AS cv FROM n"""


def _rbm(hidden: int = 3) -> str:
    sign = lambda i: f"(2 * ((w0 >> {i}) & 1) - 1)"
    visible = " + ".join(f"{sign(i)} * {(i * 7 % 5 - 2) / 10}" for i in range(M))
    terms = []
    for h in range(hidden):
        t = " + ".join([f"{(h - 1) / 5.0}"] + [f"{sign(i)} * {((h * 3 + i * 5) % 7 - 3) / 10}" for i in range(M)])
        terms.append(f"ln(exp({t}) + exp(-({t})))")
    return f"SELECT w0, round(({visible} + {' + '.join(terms)})::DOUBLE, 6) AS log_abs FROM ({_EMB12})"


def _energy(where: str = "") -> str:
    return f"""{_WITH}, nm AS (SELECT sw0, sum(h * {_PSI.format('w0')}) AS num FROM ed {where} GROUP BY sw0)
SELECT sum({_PSI.format('sw0')} * num)::BIGINT AS num, sum({_PSI.format('sw0')} * {_PSI.format('sw0')})::BIGINT AS norm,
  round((sum({_PSI.format('sw0')} * num) / sum({_PSI.format('sw0')} * {_PSI.format('sw0')}))::DOUBLE, 6) AS energy, count(*)::BIGINT AS n FROM nm"""


_HOUR = "(date_diff('day', DATE '1970-01-01', ts::DATE) * 24 + hour(ts))::INTEGER"
_CENTS = "sum(round(value * 100)::BIGINT)::BIGINT"


def _peaks(where: str = "") -> str:
    return f"SELECT {_HOUR} AS iter, -max(value) AS energy FROM events {where} GROUP BY 1"


_SPEED = f"""WITH x AS (SELECT day(ts) > 15 AS late, event_type AS stage, {_CENTS} AS s FROM events GROUP BY 1, 2),
b AS (SELECT * FROM x WHERE NOT late), a AS (SELECT * FROM x WHERE late)
SELECT b.stage, round(b.s / a.s, 6) AS speedup FROM b JOIN a USING (stage) UNION ALL SELECT 'all', round((SELECT sum(s) FROM b) / (SELECT sum(s) FROM a), 6)"""
_FULL = f"WITH {_edges(f'SELECT w AS w0 FROM ({_space(M, N)})')}"

_EMB20 = _moved("emb20", 20, 5, _emb(20, 5))


def _moved64() -> str:
    """CTEs ``so`` and ``un(w0, w1)``: the 64-orbital set and its distinct targets, from occupied and empty orbitals."""
    mask = lambda x: f"CASE WHEN {x} < 63 THEN 1::BIGINT << {x}::INTEGER ELSE 0 END AS a, CASE WHEN {x} >= 63 THEN 1::BIGINT << ({x} - 63)::INTEGER ELSE 0 END AS b"
    return f"""WITH so AS MATERIALIZED ({_emb(64, 6, 2)}), og AS (SELECT range::INTEGER AS o, {mask('range')} FROM range(0, 64)),
oc AS MATERIALIZED (SELECT s.w0 AS i0, s.w1 AS i1, o, a, b FROM so s, og WHERE (s.w0 & a) + (s.w1 & b) > 0),
em AS MATERIALIZED (SELECT s.w0 AS i0, s.w1 AS i1, o, a, b FROM so s, og WHERE (s.w0 & a) + (s.w1 & b) = 0),
o2 AS (SELECT x.i0, x.i1, x.a + y.a AS a, x.b + y.b AS b FROM oc x JOIN oc y ON x.i0 = y.i0 AND x.i1 = y.i1 AND x.o < y.o),
e2 AS (SELECT x.i0, x.i1, x.a + y.a AS a, x.b + y.b AS b FROM em x JOIN em y ON x.i0 = y.i0 AND x.i1 = y.i1 AND x.o < y.o),
un AS MATERIALIZED (SELECT xor(xor(x.i0, x.a), y.a) AS w0, xor(xor(x.i1, x.b), y.b) AS w1 FROM oc x JOIN em y ON x.i0 = y.i0 AND x.i1 = y.i1
   UNION SELECT xor(xor(x.i0, x.a), y.a), xor(xor(x.i1, x.b), y.b) FROM o2 x JOIN e2 y ON x.i0 = y.i0 AND x.i1 = y.i1)"""


def _loop(iterations: int = 3, k: int = 50) -> str:
    """The outer loop unrolled: spaces s0, s1, ..., each grown by the largest amplitudes that it is coupled with."""
    steps, rows = [f"s0 AS MATERIALIZED (SELECT {(1 << N) - 1}::BIGINT AS w0)"], []
    for i in range(iterations):
        steps.append(f"u{i} AS MATERIALIZED (SELECT DISTINCT w0 FROM ed WHERE sw0 IN (SELECT w0 FROM s{i}))")
        steps.append(f"s{i + 1} AS MATERIALIZED (SELECT w0 FROM s{i} UNION ALL SELECT w0 FROM (SELECT w0 FROM u{i} WHERE w0 NOT IN (SELECT w0 FROM s{i}) ORDER BY abs({_PSI.format('w0')}) DESC, w0 LIMIT {k}))")
        inside = f"FROM ed WHERE sw0 IN (SELECT w0 FROM s{i})"
        rows.append(
            f"SELECT {i}::INTEGER AS iter, (SELECT count(*) FROM s{i})::BIGINT AS n_space, (SELECT count(*) {inside})::BIGINT AS n_generated, (SELECT count(*) FROM u{i})::BIGINT AS n_unique, "
            f"round(((SELECT sum({_PSI.format('sw0')} * h * {_PSI.format('w0')}) {inside} AND w0 IN (SELECT w0 FROM s{i})) / (SELECT sum({_PSI.format('w0')} * {_PSI.format('w0')}) FROM s{i}))::DOUBLE, 6) AS energy"
        )
    return f"{_FULL}, {', '.join(steps)} {' UNION ALL '.join(rows)}"


ORACLES = {
    "config_pack_emb": _emb(20, 5), "config_pack_emb64": _emb(64, 6, 2), "config_pack_orders": _ord(3), "config_pack_orders4": _ord(4), "config_pack_events": _hours(_DAYS), "config_pack_docs": _DOCS,
    "space_enumerate": f"SELECT w AS w0 FROM (SELECT unnest(range(0, (SELECT 1::BIGINT << (max(o) + 1)::INTEGER FROM ({_LINES})))) AS w) WHERE bit_count(w) = {N}",
    "excitation_single": f"""WITH {_HAM} SELECT h1.p, h1.q AS a, h1.v AS h, sum(ctx.v)::BIGINT AS ctx, xor(1::BIGINT << h1.p, 1::BIGINT << h1.q) AS flip, {_GAP.format('h1.p', 'h1.q')}::BIGINT AS parity
      FROM h1 JOIN ctx ON ctx.p = h1.p AND ctx.a = h1.q WHERE h1.p <> h1.q GROUP BY h1.p, h1.q, h1.v HAVING h1.v <> 0 OR sum(abs(ctx.v)) > 0""",
    "excitation_double": f"""WITH {_HAM} SELECT p, q, a, b, v AS h, (1::BIGINT << p) + (1::BIGINT << q) + (1::BIGINT << a) + (1::BIGINT << b) AS flip,
      xor({_GAP.format('p', 'a')}, {_GAP.format('q', 'b')})::BIGINT AS parity, (bit_count(((1::BIGINT << p) | (1::BIGINT << a)) & {_GAP.format('q', 'b')}) % 2)::INTEGER AS sgn0
      FROM v WHERE p < q AND a < b AND p NOT IN (a, b) AND q NOT IN (a, b) AND v <> 0""",
    "excitation_padded": f"""WITH {_HAM}, c AS (SELECT p, q, count(*) AS n FROM v WHERE p < q AND a < b AND p NOT IN (a, b) AND q NOT IN (a, b) AND v <> 0 GROUP BY p, q)
      SELECT p, q, (max(n) OVER ())::INTEGER AS length, n::INTEGER AS filled FROM c""",
    "couple_virtual": _EDGES, "couple_join": _EDGES, "couple_batch": _EDGES, "couple_rowwise": _EDGES,
    "couple_allpairs": f"WITH src AS ({_EMB12}), fl AS ({_space(M, N)}) SELECT s.w0 AS sw0, fl.w AS w0, (bit_count(xor(s.w0, fl.w)) // 2)::INTEGER AS kind FROM src s, fl WHERE bit_count(xor(s.w0, fl.w)) <= 4",
    "couple_screened": f"{_WITH} SELECT sw0, w0, h, kind::INTEGER AS kind FROM ed WHERE kind = 0 OR abs(h) > 10",
    "couple_screened_scaled": f"{_WITH} SELECT sw0, w0, h, kind::INTEGER AS kind FROM ed WHERE kind = 0 OR abs(h) * abs({_PSI.format('sw0')}) > 2000",
    **{f"dedup_{k}": f"SELECT DISTINCT w0 FROM ({_KEYS})" for k in ("local", "range_sampled", "range_window", "range_rebalanced", "range_native", "hash", "salted", "central")},
    "dedup_sample": f"{_SPLIT} SELECT g::INTEGER AS g, w0, round(d / least(d, {SAMPLES}), 9) AS weight FROM rk JOIN pl USING (g, d, r)",
    "dedup_two_words": f"{_moved64()} SELECT (w0 % 97)::INTEGER AS g, count(*)::BIGINT AS \"unique\", sum(w0 % 1000003)::BIGINT AS low, sum(w1)::BIGINT AS high FROM un GROUP BY g",
    "w3_medium": f"{_moved64()} SELECT (SELECT count(*) FROM so)::BIGINT AS sources, (SELECT count(*) FROM so)::BIGINT * 25143 AS generated, count(*)::BIGINT AS \"unique\", 1 - count(*) / ((SELECT count(*) FROM so) * 25143.0::DOUBLE) AS rate FROM un",
    "couple_kinds": _EDGES, "loop_growth": _loop(),
    "space_reference": f"""WITH l AS ({_LINES}) SELECT DISTINCT (SELECT max(o) + 1 FROM l)::INTEGER AS m, n::INTEGER AS n, ((1::BIGINT << n::INTEGER) - 1)::BIGINT AS w0
      FROM (SELECT count(DISTINCT o) AS n FROM l GROUP BY k)""",
    "footprint_table": f"""WITH {_HAM}, s AS (SELECT h1.p, count(*) AS c FROM h1 JOIN (SELECT p, a, sum(abs(v)) AS t FROM ctx GROUP BY p, a) x ON x.p = h1.p AND x.a = h1.q WHERE h1.p <> h1.q AND (h1.v <> 0 OR t > 0) GROUP BY h1.p),
      d AS (SELECT p, q, count(*) AS c FROM v WHERE p < q AND a < b AND p NOT IN (a, b) AND q NOT IN (a, b) AND v <> 0 GROUP BY p, q)
      SELECT ((12 * (SELECT max(c) FROM s) + 66 * (SELECT max(c) FROM d)) * 12)::BIGINT AS bytes, (6 * (SELECT max(c) FROM d) * 12)::BIGINT AS pair_bytes""",
    "w7_load": " UNION ALL ".join(f"SELECT {p}::INTEGER AS p, count(*)::BIGINT AS generated, count(DISTINCT j)::BIGINT AS \"unique\" FROM ({_EMB20} SELECT i, j FROM mv) WHERE i * 7919 % 1009 % 64 < {p}" for p in (2, 4, 8, 16, 32, 64)),
    "w8_growth": f"""{_moved('doc6', 26, 6, _DOCS)}, b AS MATERIALIZED (SELECT j, (i * 7919 % 1009 % 16)::INTEGER AS block FROM mv), f AS (SELECT j, min(block) AS block FROM b GROUP BY j)
      SELECT block, (sum(g) OVER (ORDER BY block))::BIGINT AS generated, (sum(coalesce(u, 0)) OVER (ORDER BY block))::BIGINT AS "unique"
      FROM (SELECT block, count(*) AS g FROM b GROUP BY block) LEFT JOIN (SELECT block, count(*) AS u FROM f GROUP BY block) USING (block)""",
    "w9_counts": " UNION ALL ".join(f"SELECT '{name}' AS source, (SELECT count(*) FROM ({src}))::BIGINT AS sources, count(*)::BIGINT AS generated, count(DISTINCT j)::BIGINT AS \"unique\" FROM ({mv} SELECT i, j FROM mv)" for name, src, mv in (("emb20", _emb(20, 5), _EMB20), ("evt3", _hours(_DAYS), _moved("evt3", 24, 3, _hours(_DAYS))))),
    "dedup_splitters": f"{_SPLIT} SELECT j::INTEGER AS j, w0 FROM sp", "dedup_balance": _BALANCE,
    "reverse_index": f"{_WITH} SELECT w0, count(*)::BIGINT AS sources, min(sw0) AS first, max(sw0) AS last FROM ed GROUP BY w0",
    "remap_jit": f"{_WITH} SELECT sw0, sum(h * {_PSI.format('w0')})::BIGINT AS num FROM ed GROUP BY sw0",
    "amplitude_closed_form": f"SELECT w0, {_PSI.format('w0')}::BIGINT AS psi FROM ({_EMB12})",
    "amplitude_rbm": _rbm(), "amplitude_rbm_batched": _rbm(),
    "topk_exact": _TOP, "topk_two_level": _TOP, "topk_running": _TOP, "topk_large": _TOP,
    "space_grow": f"""{_SCORED}, nw AS (SELECT * FROM sc WHERE w0 NOT IN (SELECT w0 FROM src) ORDER BY score DESC, w0 LIMIT 50)
      SELECT w0, 0 AS iter_added, 0::BIGINT AS score FROM src UNION ALL SELECT w0, 1, score::BIGINT FROM nw""",
    "local_energy": f"""{_WITH}, nm AS (SELECT sw0, sum(h * {_PSI.format('w0')})::BIGINT AS num, {_PSI.format('sw0')}::BIGINT AS psi FROM ed GROUP BY sw0)
      SELECT sw0, num, psi, CASE WHEN psi <> 0 THEN round(num::DOUBLE / psi::DOUBLE, 6) END AS eloc FROM nm""",
    "global_energy": _energy(), "variational_energy": _energy("WHERE w0 IN (SELECT w0 FROM src)"),
    "exact_power_step": f"{_FULL} SELECT sw0 AS w0, sum(h * {_PSI.format('w0')})::BIGINT AS x FROM ed GROUP BY sw0",
    "redundancy_curve": f"""{_ORD3}, b AS (SELECT j, (i % 8)::INTEGER AS block FROM mv), f AS (SELECT j, min(block) AS block FROM b GROUP BY j)
      SELECT block, (sum(g) OVER (ORDER BY block))::BIGINT AS generated, (sum(u) OVER (ORDER BY block))::BIGINT AS unique
      FROM (SELECT block, count(*) AS g FROM b GROUP BY block) LEFT JOIN (SELECT block, count(*) AS u FROM f GROUP BY block) USING (block)""".replace(" AS unique\n", ' AS "unique"\n'),
    "redundancy": f"""{_ORD3} SELECT count(*)::BIGINT AS generated, count(DISTINCT j)::BIGINT AS "unique", round(1 - count(DISTINCT j) / count(*), 9) AS rate FROM mv""",
    "edge_bound": f"SELECT count(*)::BIGINT * 759 AS bound FROM ({_ord(3)})",
    "trajectory_diff": f"""WITH a AS ({_peaks("WHERE event_type = 'view'")}), b AS ({_peaks("WHERE event_type = 'click'")}), d AS (SELECT abs(a.energy - b.energy) AS d FROM a JOIN b USING (iter))
      SELECT round(avg(d), 6) AS mae, round(sqrt(avg(d * d)), 6) AS rmse, round(max(d), 6) AS max FROM d""",
    "stage_share": f"SELECT iter, stage, round(s / sum(s) OVER (PARTITION BY iter), 9) AS share FROM (SELECT {_HOUR} AS iter, event_type AS stage, {_CENTS} AS s FROM events GROUP BY 1, 2)",
    "stage_speedup": _SPEED,
    "scaling_efficiency": f"""WITH x AS (SELECT (hour(ts) + 1)::INTEGER AS p, {_CENTS} AS s FROM events GROUP BY 1), y AS (SELECT *, first_value(s) OVER (ORDER BY p) AS s0, first_value(p) OVER (ORDER BY p) AS p0 FROM x)
      SELECT 'strong' AS mode, p, round(s0 * p0 / (s * p), 9) AS efficiency FROM y UNION ALL SELECT 'weak', p, round(s0 / s, 9) FROM y""",
    "first_below": f"WITH h AS ({_peaks()}) SELECT min(iter)::INTEGER AS first FROM h WHERE abs(energy - (SELECT min(energy) FROM h)) < 1.6e-3",
    "stream_topk": "SELECT event_id AS w0, value AS score FROM events ORDER BY value DESC, event_id LIMIT 50",
    "stream_dedup": "SELECT DISTINCT (user_id * 24 + hour(ts))::BIGINT AS w0 FROM events",
    "window_day": _hours(_DAYS, order="h"), "window_sliding": _hours(_SLIDING, order="h"), "window_session": _hours(_SESSIONS, order="h"),
    "iteration": f"""{_ORD3}, sc AS (SELECT DISTINCT j AS w0, abs({_PSI.format('j')}) AS score FROM mv),
      nw AS (SELECT * FROM sc WHERE w0 NOT IN (SELECT w0 FROM src) ORDER BY score DESC, w0 LIMIT 100)
      SELECT w0, 0 AS iter_added, 0::BIGINT AS score FROM src UNION ALL SELECT w0, 1, score::BIGINT FROM nw""",
}
