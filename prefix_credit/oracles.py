"""The queries of `queries` in DuckDB's SQL, written on their own."""

from __future__ import annotations

from .config import BANDS

SUBSET = 800

_TH = "CASE p_type WHEN 'SMALL' THEN .1 WHEN 'ECONOMY' THEN .2 WHEN 'STANDARD' THEN .3 WHEN 'MEDIUM' THEN .5 WHEN 'LARGE' THEN .7 WHEN 'PROMO' THEN .85 ELSE .5 END"
_ORDER = "((sample_id * 7919 + 104729) % 1000003)"

# ---- stage 1 and 2 ------------------------------------------------------------------------------------------------------

CAND = f"""ans AS (
  SELECT l_partkey AS sample_id, p_type AS task, CAST(l_extendedprice / l_quantity AS DOUBLE) AS answer, p_retailprice AS truth, {_TH} AS th,
         row_number() OVER (PARTITION BY l_partkey ORDER BY l_orderkey, l_linenumber, l_suppkey, l_extendedprice, l_quantity) - 1 AS rn,
         count(*) OVER (PARTITION BY l_partkey) AS n
  FROM lineitem JOIN part ON l_partkey = p_partkey
), rew AS (
  SELECT *, CASE WHEN answer > 0 AND truth > 0 THEN least(answer / truth, truth / answer) ELSE 0 END AS reward FROM ans
), cand AS (SELECT *, reward >= th AS correct FROM rew WHERE rn < 8)"""
STRATA = f"""{CAND}, st AS (
  SELECT sample_id, task, count(*) AS k, count(*) FILTER (WHERE correct) AS n_correct,
         CASE WHEN count(*) FILTER (WHERE correct) = count(*) THEN 'easy' WHEN count(*) FILTER (WHERE correct) = 0 THEN 'hard' ELSE 'uncertain' END AS stratum
  FROM cand GROUP BY 1, 2
)"""
TUNING = f"""{STRATA}, tun AS (
  SELECT sample_id, task, stratum, k, n_correct FROM (
    SELECT *, row_number() OVER (PARTITION BY task, stratum ORDER BY {_ORDER}, sample_id) AS place,
           count(*) FILTER (WHERE stratum = 'easy') OVER (PARTITION BY task) AS ne
    FROM st) x
  WHERE stratum = 'uncertain' OR (stratum = 'easy' AND place <= ceil(round(ne * 0.2, 9)))
)"""
OUT = """outc AS (
  SELECT sample_id, task, i AS iter, bool_or(ok) <> bool_and(ok) AS effective, NOT bool_or(ok) AS hard, bool_and(ok) AS easy
  FROM (SELECT sample_id, task, i, reward >= th * pow(0.85, i) AS ok FROM rew, range(0, 6) g(i) WHERE (((rn - 8 * i) % n) + n) % n < 8) x
  GROUP BY 1, 2, 3
)"""
POOL = "pool AS (SELECT sample_id, task, row_number() OVER (PARTITION BY task ORDER BY sample_id) AS pos FROM st WHERE stratum <> 'easy')"


def loop(rounds: int, beta: float = 0.8, requeue: bool = True, refresh: bool = True) -> str:
    """CTEs of the quota rounds: s{i} is the state after round i, d{i} its draws, w{i} the waiting list after it."""
    sql = f"""{STRATA}, {OUT}, {POOL}, len AS (SELECT task, max(pos) AS n, (SELECT count(DISTINCT task) FROM pool) AS tasks FROM pool GROUP BY 1),
s0 AS (SELECT len.task, 0 AS hi, avg(CAST(effective AS INT)) AS e FROM len JOIN pool ON pool.task = len.task AND pos <= 32 JOIN outc ON outc.sample_id = pool.sample_id AND iter = 0 GROUP BY 1),
w0 AS (SELECT CAST(NULL AS VARCHAR) AS task, CAST(NULL AS BIGINT) AS sample_id, 0 AS no, 0 AS er, CAST(0 AS BIGINT) AS es WHERE false)"""
    for i in range(1, rounds + 1):
        p = i - 1
        sql += f""",
q{i} AS (
  SELECT s.task, s.e, s.hi AS lo, least(s.hi + q, len.n) AS hi, q, q - (least(s.hi + q, len.n) - s.hi) AS short
  FROM (SELECT s{p}.*, CAST(ceil(round({SUBSET} / ((SELECT max(tasks) FROM len) * greatest(e, 1 / 64.0)), 9)) AS BIGINT) AS q FROM s{p}) s JOIN len ON len.task = s.task
), d{i} AS (
  SELECT x.*, effective, hard, easy FROM (
    SELECT pool.task, pool.sample_id, 0 AS no, 0 AS src, pos AS place FROM pool JOIN q{i} ON q{i}.task = pool.task AND pos > lo AND pos <= hi
    UNION ALL
    SELECT w.task, w.sample_id, no, 1, place FROM (SELECT *, row_number() OVER (PARTITION BY task ORDER BY er, es) AS place FROM w{p}) w JOIN q{i} ON q{i}.task = w.task AND place <= short
  ) x JOIN outc ON outc.sample_id = x.sample_id AND iter = {i}
), w{i} AS (
  SELECT * FROM w{p} WHERE (task, sample_id) NOT IN (SELECT (task, sample_id) FROM d{i} WHERE src = 1)
  UNION ALL
  SELECT task, sample_id, no + 1, {i}, row_number() OVER (PARTITION BY task ORDER BY src, place) FROM d{i} WHERE hard AND no + 1 <= 3{'' if requeue else ' AND false'}
), c{i} AS (
  SELECT task, count(*) FILTER (WHERE src = 0) AS fresh, count(*) FILTER (WHERE src = 1) AS again, count(*) FILTER (WHERE effective) AS eff, count(*) AS drawn FROM d{i} GROUP BY 1
), s{i} AS (
  SELECT q{i}.task, {f'q{i}.hi' if refresh else '0'} AS hi, CASE WHEN coalesce(drawn, 0) = 0 THEN e ELSE {beta} * e + {1 - beta:.6g} * (CAST(eff AS DOUBLE) / drawn) END AS e
  FROM q{i} LEFT JOIN c{i} ON c{i}.task = q{i}.task
)"""
    return sql


def _round(i: int) -> str:
    return f"""WITH {loop(i)}
SELECT q.task, q.q AS quota, coalesce(fresh, 0) AS fresh, coalesce(again, 0) AS requeued, coalesce(eff, 0) AS effective, round(s.e, 6) AS eta_ema
FROM q{i} q JOIN s{i} s ON s.task = q.task LEFT JOIN c{i} c ON c.task = q.task"""


HISTORY = " UNION ALL ".join(f"SELECT *, {i} AS iter FROM d{i}" for i in (1, 2, 3))
DISCARD = f"""run AS (
  SELECT *, row_number() OVER w AS draw_no, sum(CAST(effective AS INT)) OVER (w ROWS UNBOUNDED PRECEDING) AS ne
  FROM (SELECT p.sample_id, p.task, effective FROM pool p JOIN outc o ON o.sample_id = p.sample_id AND iter = 1) x WINDOW w AS (ORDER BY {_ORDER}, sample_id)
), dis AS (SELECT * FROM run WHERE ne - CAST(effective AS INT) < {SUBSET})"""
COSTS = f"""WITH {loop(1)}, {DISCARD}, cost AS (
  SELECT task, 'discard' AS method, count(*) AS sampled, count(*) FILTER (WHERE effective) AS effective FROM dis GROUP BY 1
  UNION ALL SELECT task, 'quota', count(*), count(*) FILTER (WHERE effective) FROM d1 GROUP BY 1
)"""
RATES = """dy AS (
  SELECT CAST(ts AS DATE) AS day, user_id, CAST(user_id % 5 AS INT) AS task, bool_or(event_type = 'purchase') AND bool_or(event_type <> 'purchase') AS eff
  FROM events GROUP BY 1, 2, 3
), rt AS (SELECT task, day, count(*) AS sampled, count(*) FILTER (WHERE eff) AS effective, count(*) FILTER (WHERE eff) / CAST(count(*) AS DOUBLE) AS eta FROM dy GROUP BY 1, 2)"""
EMA = f"""{RATES}, nb AS (SELECT *, row_number() OVER (PARTITION BY task ORDER BY day) AS j FROM rt),
em AS (
  SELECT a.task, a.day, any_value(a.eta) AS eta, 0.5 * pow(0.8, any_value(a.j)) + sum(0.2 * pow(0.8, a.j - b.j) * b.eta) AS eta_ema
  FROM nb a JOIN nb b ON a.task = b.task AND b.j <= a.j GROUP BY 1, 2
)"""

# ---- stage 3 ------------------------------------------------------------------------------------------------------------


def votes(shift: int = 0) -> str:
    return " + ".join(f"CASE WHEN (o_orderkey * {m} + {b + shift}) % 100 < (CASE o_orderstatus WHEN 'F' THEN 80 WHEN 'O' THEN 50 ELSE 20 END) THEN 1 ELSE -1 END" for m, b in ((7, 13), (11, 29), (17, 41), (23, 53), (31, 67)))


def lab(shift: int = 0) -> str:
    return f"lab AS (SELECT o_custkey AS task, o_orderkey AS traj, o_orderdate, o_orderstatus, {votes(shift)} AS vs, CASE WHEN ({votes(shift)}) > 0 THEN 1 ELSE -1 END AS r FROM orders)"


def plans(shift: int = 0) -> str:
    return f"""{lab(shift)}, ord AS (
  SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY task ORDER BY o_orderdate, traj) AS place FROM lab WHERE traj IN (SELECT l_orderkey FROM lineitem)) x WHERE place <= 15
)"""


TRO = f"""{plans()}, li AS (
  SELECT l_orderkey AS traj, l_returnflag AS verb, l_returnflag || '/' || l_linestatus AS txt, l_returnflag || '/' || l_linestatus || '/∅' AS a,
         row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity) AS t,
         count(*) OVER (PARTITION BY l_orderkey) AS n_steps
  FROM lineitem
), stp AS (
  SELECT ord.task, li.traj, r, place, o_orderdate, t, n_steps, verb, txt, a, pow(0.95, n_steps - t) * r AS ret,
         '>' || string_agg(a, '>') OVER (PARTITION BY li.traj ORDER BY t) AS path
  FROM li JOIN ord ON ord.traj = li.traj
)"""
TRE = """e0 AS (
  SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 12 HOUR THEN 1 ELSE 0 END AS cut FROM events
), e1 AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS ses FROM e0),
e2 AS (
  SELECT user_id AS task, CAST(ses AS BIGINT) AS traj, event_type AS verb, event_type || '/∅/∅' AS a,
         row_number() OVER (PARTITION BY user_id, ses ORDER BY ts, event_id) AS t, count(*) OVER (PARTITION BY user_id, ses) AS n_steps,
         CASE WHEN bool_or(event_type = 'purchase') OVER (PARTITION BY user_id, ses)
               AND last_value(event_type) OVER (PARTITION BY user_id, ses ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) <> 'error' THEN 1 ELSE -1 END AS r
  FROM e1 WHERE ses < 15
), stp AS (SELECT *, pow(0.95, n_steps - t) * r AS ret, '>' || string_agg(a, '>') OVER (PARTITION BY task, traj ORDER BY t) AS path FROM e2)"""
TRC = """d2 AS (
  SELECT conv_id % 6 AS task, conv_id AS traj, role AS verb, role || '/' || CAST(length(text) // 200 AS VARCHAR) || '/∅' AS a,
         row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS t, count(*) OVER (PARTITION BY conv_id) AS n_steps, 1 AS r FROM conversations
), stp AS (SELECT *, pow(0.95, n_steps - t) * r AS ret, '>' || string_agg(a, '>') OVER (PARTITION BY traj ORDER BY t) AS path FROM d2)"""
NODES = """nd AS (
  SELECT task, t AS depth, path, any_value(verb) AS verb, any_value(a) AS a, left(path, length(path) - length(any_value(a)) - 1) AS parent, avg(ret) AS q, count(*) AS n FROM stp GROUP BY 1, 2, 3
)"""
ADV = """ad AS (
  SELECT *, count(*) OVER w AS k, avg(q) OVER w AS mu, sqrt(var_pop(q) OVER w + 1e-6) AS sigma, (q - avg(q) OVER w) / sqrt(var_pop(q) OVER w + 1e-6) AS adv
  FROM nd WINDOW w AS (PARTITION BY task, depth, parent)
)"""
_PRE = f"WITH {TRO}, {NODES}"


def contrast(steps: str, name: str) -> str:
    return f"""SELECT * FROM (WITH {steps}, {NODES}, {ADV}, ps AS (SELECT DISTINCT task, traj, r FROM stp),
wh AS (SELECT *, (r - avg(r) OVER (PARTITION BY task)) / sqrt(var_pop(r) OVER (PARTITION BY task) + 1e-6) AS w FROM ps)
SELECT CAST(stp.r AS BIGINT) AS r, count(*) AS steps, count(*) FILTER (WHERE adv > 0) AS positive, count(*) FILTER (WHERE adv < 0) AS negative,
       count(*) FILTER (WHERE sign(adv) = sign(w)) AS same_sign, count(*) FILTER (WHERE abs(w) <= 0.001) AS flat_in_baseline, '{name}' AS source
FROM stp JOIN ad ON ad.task = stp.task AND ad.path = stp.path JOIN wh ON wh.task = stp.task AND wh.traj = stp.traj
WHERE k > 1 AND abs(adv) > 0.001 GROUP BY stp.r)"""


def shape(steps: str, name: str) -> str:
    return f"""SELECT * FROM (WITH {steps}, {NODES}, gr AS (SELECT task, parent, count(*) AS k FROM nd GROUP BY 1, 2),
br AS (SELECT task, count(*) AS b, sum(k) AS c FROM gr WHERE k > 1 GROUP BY 1),
lv AS (SELECT task, count(*) AS l FROM nd WHERE (task, path) NOT IN (SELECT (task, parent) FROM gr) GROUP BY 1)
SELECT count(*) AS tasks, round(avg(coalesce(b, 0)), 6) AS branching, round(avg(l), 6) AS leaves, round(sum(c) / CAST(sum(b) AS DOUBLE), 6) AS group_size, '{name}' AS source
FROM lv LEFT JOIN br ON br.task = lv.task)"""


POLICY = """hs AS (SELECT *, coalesce(lag(a) OVER (PARTITION BY traj ORDER BY t), '') AS history, CAST(o_orderdate AS DATE) < DATE '1998-01-01' AS early FROM stp),
voc AS (SELECT DISTINCT a AS action FROM stp),
ph AS (SELECT k.k, hs.history, hs.a AS action FROM hs JOIN (VALUES ('old'), ('new'), ('ref')) k(k) ON k.k = 'ref' OR (k.k = 'old') = early),
gp AS (SELECT h.k, h.history, voc.action, coalesce(c.n, 0) + 1.0 AS n FROM (SELECT DISTINCT k, history FROM ph) h CROSS JOIN voc
       LEFT JOIN (SELECT k, history, action, count(*) AS n FROM ph GROUP BY 1, 2, 3) c ON c.k = h.k AND c.history = h.history AND c.action = voc.action),
pp AS (SELECT k, history, action, CAST(n AS DOUBLE) / sum(CAST(n AS DOUBLE)) OVER (PARTITION BY k, history) AS p FROM gp),
rat AS (SELECT n.history, n.action, n.p AS p_new, o.p AS p_old, f.p AS p_ref, n.p / o.p AS rho
        FROM pp n JOIN pp o ON o.k = 'old' AND o.history = n.history AND o.action = n.action JOIN pp f ON f.k = 'ref' AND f.history = n.history AND f.action = n.action WHERE n.k = 'new')"""
SHEET = f"""{TUNING}, sh AS (
  SELECT 'filtered' AS system, p_brand AS benchmark, 100 * sum(n_correct) / sum(k) AS value FROM tun JOIN part ON p_partkey = sample_id GROUP BY 2
  UNION ALL SELECT 'uncertain_only', p_brand, 100 * sum(n_correct) / sum(k) FROM st JOIN part ON p_partkey = sample_id WHERE stratum = 'uncertain' GROUP BY 2
  UNION ALL SELECT 'unfiltered', p_brand, 100 * sum(n_correct) / sum(k) FROM st JOIN part ON p_partkey = sample_id GROUP BY 2
), sheet AS (SELECT system, benchmark, CAST(value AS DOUBLE) AS value, substr(benchmark, 1, 7) AS category FROM sh)"""
SPLIT = f"""{TRO}, tr AS (SELECT * FROM stp WHERE place <= 10), te AS (SELECT *, left(path, length(path) - length(a) - 1) AS parent FROM stp WHERE place > 10),
nd AS (SELECT task, t AS depth, path, any_value(a) AS a, left(path, length(path) - length(any_value(a)) - 1) AS parent, avg(ret) AS q FROM tr GROUP BY 1, 2, 3)"""
BEST = "bc AS (SELECT task, parent, arg_max(a, (round(q, 9), a)) AS best, arg_max(q, (round(q, 9), a)) AS best_q FROM nd GROUP BY 1, 2)"
GEO = """un AS (SELECT vec_id, label, unnest(range(1, 19)) AS i, CAST(embedding AS DOUBLE[]) AS v FROM embeddings),
tr AS (SELECT label, list(g ORDER BY i) AS g FROM (SELECT label, i, avg(v[i]) AS g FROM un GROUP BY 1, 2) x GROUP BY 1),
geo AS (SELECT vec_id, e.label, CAST(embedding AS DOUBLE[]) AS v, g FROM embeddings e JOIN tr ON tr.label = e.label)"""


def _iou(dims: int) -> str:
    lo = lambda s, k: f"least({s}[{k + 1}], {s}[{k + 1 + dims}])"
    hi = lambda s, k: f"(greatest({s}[{k + 1}], {s}[{k + 1 + dims}]) + 0.05)"
    inter = " * ".join(f"greatest(0, least({hi('v', k)}, {hi('g', k)}) - greatest({lo('v', k)}, {lo('g', k)}))" for k in range(dims))
    vol = lambda s: " * ".join(f"({hi(s, k)} - {lo(s, k)})" for k in range(dims))
    return f"(({inter}) / (({vol('v')}) + ({vol('g')}) - ({inter})))"


_POINT = "greatest(0, 1 - (abs((v[1] + 1) / 2 - (g[1] + 1) / 2) + abs((v[2] + 1) / 2 - (g[2] + 1) / 2)) / 2)"
_TOK = "list_distinct(list_filter(string_split(lower(trim(regexp_replace({0}, '\\s+', ' ', 'g'))), ' '), lambda w: w <> ''))"
JACC = f"""pr AS (SELECT conv_id, turn, {_TOK.format('text')} AS x, {_TOK.format('bf')} AS y FROM (SELECT *, lag(text) OVER (PARTITION BY conv_id ORDER BY turn) AS bf FROM conversations) z WHERE bf IS NOT NULL),
jc AS (SELECT conv_id, turn, CASE WHEN len(x) + len(y) = 0 THEN 1.0 ELSE len(list_intersect(x, y)) / CAST(len(x) + len(y) - len(list_intersect(x, y)) AS DOUBLE) END AS j FROM pr)"""
_SEEDS = " UNION ALL ".join(
    f"""SELECT {s} AS seed, avg(CAST(f AS DOUBLE)) AS first_plan, avg(CAST(y AS DOUBLE)) AS any_plan, avg(CAST(m AS DOUBLE)) AS most_plans FROM (
  WITH {plans(20 * s)} SELECT task, CAST(arg_min(r, (o_orderdate, traj)) = 1 AS INT) AS f, CAST(max(r) = 1 AS INT) AS y, CAST(avg(r) > 0 AS INT) AS m FROM ord WHERE task <= 99 GROUP BY task)"""
    for s in range(5)
)

ORACLES: dict[str, str] = {
    "capability_mix": "SELECT lang, source, count(*) AS n, round(count(*) / CAST(sum(count(*)) OVER () AS DOUBLE), 6) AS share FROM documents GROUP BY 1, 2",
    "balanced_draw": "SELECT doc_id, lang FROM (SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY (doc_id * 7919 + 104729) % 1000003, doc_id) AS place FROM documents) x WHERE place <= 40",
    "strata_parts": f"WITH {STRATA} SELECT sample_id, task, k, n_correct, stratum FROM st",
    "strata_vectors": """WITH p AS (
  SELECT a.vec_id AS sample_id, CAST(a.label AS VARCHAR) AS task, a.label = b.label AS ok,
         row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) DESC, b.vec_id) AS place
  FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)
SELECT sample_id, task, count(*) AS k, count(*) FILTER (WHERE ok) AS n_correct,
  CASE WHEN bool_and(ok) THEN 'easy' WHEN NOT bool_or(ok) THEN 'hard' ELSE 'uncertain' END AS stratum FROM p WHERE place <= 8 GROUP BY 1, 2""",
    "tuning_set": f"WITH {TUNING} SELECT sample_id, task, stratum FROM tun",
    "answer_entropy": f"WITH {CAND}, c AS (SELECT sample_id, floor(answer / 100) AS b, count(*) AS c FROM cand GROUP BY 1, 2), p AS (SELECT sample_id, c / CAST(sum(c) OVER (PARTITION BY sample_id) AS DOUBLE) AS p FROM c) SELECT sample_id, round(-sum(p * ln(p)), 6) + 0.0 AS entropy FROM p GROUP BY 1",
    "filter_cost_rule": f"""WITH {TUNING}, a AS (SELECT task, CAST(sum(k) AS BIGINT) AS scored, count(*) AS samples, round(avg(n_correct / CAST(k AS DOUBLE)), 6) AS p_all FROM st GROUP BY 1),
b AS (SELECT task, count(*) AS kept, round(avg((n_correct / CAST(k AS DOUBLE)) * (1 - n_correct / CAST(k AS DOUBLE))), 6) AS variance_kept FROM tun GROUP BY 1)
SELECT a.task, scored, samples, p_all, kept, variance_kept FROM a LEFT JOIN b ON b.task = a.task""",
    "filter_cost_judge": f"""WITH {JACC}, s AS (SELECT conv_id, count(*) AS k, CASE WHEN bool_and(j >= 0.05) THEN 'easy' WHEN NOT bool_or(j >= 0.05) THEN 'hard' ELSE 'uncertain' END AS stratum FROM jc GROUP BY 1)
SELECT stratum, count(*) AS samples, CAST(sum(k) AS BIGINT) AS judged FROM s GROUP BY 1""",
    "strata_drift": f"""WITH {CAND}, s AS (
  SELECT CAST(i AS INT) AS iter, sample_id, CASE WHEN bool_and(ok) THEN 'easy' WHEN NOT bool_or(ok) THEN 'hard' ELSE 'uncertain' END AS stratum
  FROM (SELECT sample_id, i, reward >= th * pow(0.85, i) AS ok FROM rew, range(0, 5) g(i) WHERE (((rn - 8 * i) % n) + n) % n < 8) x GROUP BY 1, 2)
SELECT iter, stratum, count(*) AS n, round(count(*) / CAST(sum(count(*)) OVER (PARTITION BY iter) AS DOUBLE), 6) AS share FROM s GROUP BY 1, 2""",
    "quota_round1": _round(1),
    "quota_round2": _round(2),
    "quota_round3": _round(3),
    "sample_status": f"""WITH {loop(3)}, h AS ({HISTORY}), l AS (SELECT task, sample_id, count(*) AS draws, arg_max(CASE WHEN effective THEN 'trained' WHEN hard AND no < 3 THEN 'waiting' WHEN hard THEN 'exhausted' ELSE 'mastered' END, iter) AS status FROM h GROUP BY 1, 2)
SELECT task, status, count(*) AS samples, CAST(sum(draws) AS BIGINT) AS draws FROM l GROUP BY 1, 2""",
    "training_intensity": f"""WITH {loop(3)}, h AS ({HISTORY}), d AS (SELECT task, count(*) AS draws, count(DISTINCT sample_id) AS samples FROM h GROUP BY 1)
SELECT len.task, n AS size, coalesce(draws, 0) AS draws, coalesce(samples, 0) AS samples, round(coalesce(draws, 0) / CAST(n AS DOUBLE), 6) AS intensity FROM len LEFT JOIN d ON d.task = len.task""",
    "discard_vs_quota": f"{COSTS} SELECT task, method, sampled, effective, round(CASE WHEN effective = 0 THEN NULL ELSE sampled / CAST(effective AS DOUBLE) END, 6) AS cost FROM cost",
    "task_balance": f"""{COSTS} SELECT method, max(effective) AS most, min(effective) AS least, round(CASE WHEN min(effective) = 0 THEN NULL ELSE max(effective) / CAST(min(effective) AS DOUBLE) END, 6) AS ratio,
round(stddev_pop(effective) / avg(effective), 6) AS variation, round(avg(abs(effective - ev)), 6) AS mean_gap FROM (SELECT *, avg(effective) OVER (PARTITION BY method) AS ev FROM cost) x GROUP BY 1""",
    "running_discard": f"WITH {STRATA}, {OUT}, {POOL}, {DISCARD} SELECT sample_id, draw_no, CAST(ne AS BIGINT) AS n_effective FROM dis",
    "balanced_batches": f"""WITH {STRATA}, x AS (SELECT task, stratum AS tier, sample_id, row_number() OVER (PARTITION BY task, stratum ORDER BY sample_id) AS turn FROM st WHERE stratum <> 'easy'),
y AS (SELECT *, (row_number() OVER (ORDER BY turn, task, tier, sample_id) - 1) // 64 AS batch FROM x) SELECT batch, task, tier, count(*) AS n FROM y GROUP BY 1, 2, 3""",
    "daily_rates": f"WITH {RATES} SELECT task, day, sampled, effective, round(eta, 6) AS eta FROM rt",
    "ema_rates": f"WITH {EMA} SELECT task, day, round(eta, 6) AS eta, round(eta_ema, 6) AS eta_ema FROM em",
    "daily_quota": f"WITH {EMA} SELECT task, day, CAST(ceil(round(800 / (5 * greatest(eta_ema, 1 / 64.0)), 9)) AS BIGINT) AS quota FROM em",
    "sliding_rate": f"WITH {RATES} SELECT task, day, round(avg(eta) OVER (PARTITION BY task ORDER BY day ROWS 6 PRECEDING), 6) AS eta_7 FROM rt",
    "seesaw": f"WITH {RATES}, c AS (SELECT task, round(eta, 9) - lag(round(eta, 9)) OVER (PARTITION BY task ORDER BY day) AS ch FROM rt) SELECT task, count(*) FILTER (WHERE ch < 0) AS falls, round(min(ch), 6) AS worst FROM c GROUP BY 1",
    "curve_drop": f"WITH {RATES} SELECT task, round(max(eta), 6) AS peak, round(arg_max(eta, day), 6) AS last, round(max(eta) - arg_max(eta, day), 6) + 0.0 AS drop FROM rt GROUP BY 1",
    "trie_nodes": f"{_PRE} SELECT task, depth, parent AS parent_path, path, n FROM nd",
    "node_values": f"{_PRE} SELECT task, path, n, round(q + 1e-9, 6) + 0.0 AS q FROM nd",
    "sibling_advantage": f"{_PRE}, {ADV} SELECT task, path, k, round(mu + 1e-9, 6) + 0.0 AS mu, round(sigma + 1e-9, 6) + 0.0 AS sigma, round(adv + 1e-9, 5) + 0.0 AS advantage FROM ad WHERE k > 1",
    "sibling_advantage_by_visits": f"{_PRE}, w AS (SELECT *, count(*) OVER p AS k, sum(q * n) OVER p / sum(n) OVER p AS mu FROM nd WINDOW p AS (PARTITION BY task, depth, parent)) SELECT task, path, round(mu + 1e-9, 6) + 0.0 AS mu, round(q - mu + 1e-9, 6) + 0.0 AS advantage FROM w WHERE k > 1",
    "credit_rows": f"""{_PRE}, {ADV} SELECT stp.task, stp.traj, stp.t, coalesce(ctx, '') AS context, txt AS step, round(adv + 1e-9, 5) + 0.0 AS advantage
FROM (SELECT *, string_agg(txt, ' ') OVER (PARTITION BY traj ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS ctx FROM stp) stp JOIN ad ON ad.task = stp.task AND ad.path = stp.path
WHERE k > 1 AND abs(adv) > 0.001""",
    "credit_contrast": contrast(TRO, "orders") + " UNION ALL " + contrast(TRE, "sessions"),
    "trajectory_credit": f"WITH {TRO}, ps AS (SELECT DISTINCT task, traj, r FROM stp), w AS (SELECT *, (r - avg(r) OVER (PARTITION BY task)) / sqrt(var_pop(r) OVER (PARTITION BY task) + 1e-6) AS av FROM ps) SELECT stp.task, stp.traj, t, round(av, 6) + 0.0 AS advantage FROM stp JOIN w ON w.traj = stp.traj",
    "trie_shape": " UNION ALL ".join((shape(TRO, "orders"), shape(TRE, "sessions"), shape(TRC, "dialogues"))),
    "group_size_by_verb": f"WITH {TRE}, {NODES}, g AS (SELECT task, parent, count(*) AS k FROM nd GROUP BY 1, 2 HAVING count(*) > 1) SELECT verb, count(*) AS parents, round(avg(k), 6) AS group_size FROM g JOIN nd ON nd.task = g.task AND nd.path = g.parent GROUP BY 1",
    "step_ratio": f"WITH {TRO}, {POLICY} SELECT history, action, round(p_new, 6) AS p_new, round(p_old, 6) AS p_old, round(p_ref, 6) AS p_ref, round(rho, 6) AS rho FROM rat",
    "policy_divergence": f"WITH {TRO}, {POLICY} SELECT history, round(sum(p_new * ln(p_new / p_ref)), 6) + 0.0 AS kl FROM rat GROUP BY 1",
    "sibling_loss": f"""WITH {TRO}, {NODES}, {ADV}, {POLICY}, kl AS (SELECT history, sum(p_new * ln(p_new / p_ref)) AS kl FROM rat GROUP BY 1),
c AS (SELECT ad.*, CASE WHEN parent = '' THEN '' ELSE regexp_extract(parent, '([^>]*)$', 1) END AS history FROM ad WHERE k > 1),
l AS (SELECT task, depth, parent, -sum(least(rho * adv, greatest(0.8, least(rho, 1.2)) * adv) - 0.01 * kl.kl) AS s, count(*) AS k, sum(n) AS v FROM c JOIN rat ON rat.history = c.history AND rat.action = c.a JOIN kl ON kl.history = c.history GROUP BY 1, 2, 3)
SELECT depth, count(*) AS parents, round(sum(s / k), 6) + 0.0 AS loss, round(sum(s / v), 6) + 0.0 AS loss_by_visits FROM l GROUP BY 1""",
    "score_sheet": f"WITH {SHEET} SELECT system, category, round(avg(value), 6) AS value FROM sheet GROUP BY 1, 2 UNION ALL SELECT system, 'overall', round(avg(value), 6) FROM sheet GROUP BY 1",
    "podium": f"WITH {SHEET}, p AS (SELECT *, dense_rank() OVER (PARTITION BY benchmark ORDER BY round(value, 9) DESC) AS d FROM sheet) SELECT system, benchmark, CASE WHEN d <= 2 THEN d END AS place, round(value, 6) AS value FROM p",
    "score_gain": f"WITH {SHEET} SELECT benchmark, round(max(value) FILTER (WHERE system = 'filtered') - max(value) FILTER (WHERE system = 'unfiltered'), 6) + 0.0 AS gain FROM sheet GROUP BY 1",
    "rollup_scores": f"WITH {SHEET} SELECT system, category, round(avg(value), 6) AS value, count(*) AS n FROM sheet GROUP BY ROLLUP (system, category)",
    "plan_success": f"WITH {plans()} SELECT task, count(*) AS plans, count(*) FILTER (WHERE r = 1) AS successes, round(100 * avg(CASE WHEN r = 1 THEN 1.0 ELSE 0 END), 6) AS success_pct FROM ord WHERE task <= 99 AND (SELECT count(*) FROM lineitem WHERE l_orderkey = traj) <= 25 GROUP BY 1",
    "plan_length": f"""SELECT * FROM (WITH {TRO}, p AS (SELECT traj, count(*) AS n FROM stp GROUP BY 1) SELECT count(*) AS plans, round(avg(n), 6) AS mean_steps, max(n) AS max_steps, round(quantile_cont(n, 0.5), 6) AS median_steps, 'orders' AS source FROM p)
UNION ALL SELECT * FROM (WITH {TRE}, p AS (SELECT task, traj, count(*) AS n FROM stp GROUP BY 1, 2) SELECT count(*), round(avg(n), 6), max(n), round(quantile_cont(n, 0.5), 6), 'sessions' FROM p)""",
    "seed_summary": f"""WITH s AS ({_SEEDS}), u AS (SELECT 'first_plan' AS system, 100 * first_plan AS value FROM s UNION ALL SELECT 'any_plan', 100 * any_plan FROM s UNION ALL SELECT 'most_plans', 100 * most_plans FROM s)
SELECT system, count(*) AS runs, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS std_sample, round(stddev_pop(value), 6) AS std_population, round(var_samp(value), 6) AS var_sample FROM u GROUP BY 1""",
    "primitive_only": f"WITH {TRE}, p AS (SELECT task, traj, count(*) FILTER (WHERE verb <> 'signup') AS n, count(*) FILTER (WHERE verb = 'signup') AS b FROM stp GROUP BY 1, 2) SELECT count(*) AS plans, CAST(sum(n) AS BIGINT) AS steps, count(*) FILTER (WHERE n = 0) AS emptied, CAST(sum(b) AS BIGINT) AS violations FROM p",
    "replan_success": f"""WITH {TRE}, {NODES}, {BEST}, pl AS (SELECT DISTINCT task, traj, r FROM stp),
f AS (SELECT stp.task, stp.traj, arg_max(best_q, t) AS bq FROM stp JOIN nd ON nd.task = stp.task AND nd.path = stp.path JOIN bc ON bc.task = nd.task AND bc.parent = nd.parent
      WHERE r = -1 AND round(best_q, 9) > round(q, 9) GROUP BY 1, 2),
g AS (SELECT task, count(*) AS replanned, count(*) FILTER (WHERE bq > 0) AS recovered FROM f GROUP BY 1)
SELECT pl.task, count(*) AS plans, count(*) FILTER (WHERE r = -1) AS failed, coalesce(any_value(replanned), 0) AS replanned, coalesce(any_value(recovered), 0) AS recovered FROM pl LEFT JOIN g ON g.task = pl.task GROUP BY 1""",
    "stepwise_agent": f"""WITH RECURSIVE {TRE}, {NODES}, bs AS (SELECT task, parent, arg_max(path, (round(q, 9), a)) AS path, arg_max(verb, (round(q, 9), a)) AS verb, max(round(q, 9)) AS q FROM nd GROUP BY 1, 2),
w AS (SELECT task, '' AS place, 0 AS steps, CAST(NULL AS VARCHAR) AS verb, CAST(NULL AS DOUBLE) AS q FROM (SELECT DISTINCT task FROM nd) x
      UNION ALL SELECT w.task, bs.path, steps + 1, bs.verb, bs.q FROM w JOIN bs ON bs.task = w.task AND bs.parent = w.place WHERE steps < 25)
SELECT task, CAST(max(steps) AS BIGINT) AS steps, arg_max(verb, steps) AS last_verb, round(arg_max(q, steps), 6) AS last_q FROM w GROUP BY 1""",
    "failure_monitor": f"""WITH {lab()}, x AS (SELECT r = 1 AS s, o_orderstatus = 'F' AS g FROM lab ORDER BY traj LIMIT 160),
y AS (SELECT count(*) AS n, avg(CASE WHEN s = g THEN 1.0 ELSE 0 END) AS accuracy, count(*) FILTER (WHERE s AND g) / CAST(count(*) FILTER (WHERE s) AS DOUBLE) AS precision, count(*) FILTER (WHERE s AND g) / CAST(count(*) FILTER (WHERE g) AS DOUBLE) AS recall FROM x)
SELECT n, round(accuracy, 6) AS accuracy, round(precision, 6) AS precision, round(recall, 6) AS recall, round(2 * precision * recall / (precision + recall), 6) AS f1 FROM y""",
    "vote_margins": f"WITH {lab()} SELECT CAST(r AS BIGINT) AS r, round(abs(vs) / 5.0, 6) AS margin, count(*) AS plans FROM lab GROUP BY 1, 2",
    "scene_success": f"""WITH {lab()}, s AS (SELECT l_orderkey, count(*) AS o, max(p_size) AS z FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1 HAVING count(*) <= 9 ORDER BY 1 LIMIT 50)
SELECT CAST(least(floor((z - 1) / 12.5), 3) AS BIGINT) AS category, count(*) AS plans, count(*) FILTER (WHERE r = 1) AS successes, round(100 * avg(CASE WHEN r = 1 THEN 1.0 ELSE 0 END), 6) AS success_pct FROM s JOIN lab ON traj = l_orderkey GROUP BY 1""",
    "judge_step": f"""WITH {SPLIT}, kn AS (SELECT DISTINCT task, parent FROM nd)
SELECT t, coalesce(round(q, 9) >= 0, false) AS verdict, CAST(te.r AS BIGINT) AS r, count(*) AS n FROM te JOIN kn ON kn.task = te.task AND kn.parent = te.parent LEFT JOIN nd ON nd.task = te.task AND nd.path = te.path GROUP BY 1, 2, 3""",
    "next_step": f"WITH {SPLIT}, {BEST} SELECT t, count(*) AS n, count(*) FILTER (WHERE best = te.a) AS hits FROM te JOIN bc ON bc.task = te.task AND bc.parent = te.parent GROUP BY 1",
    "expansion_cost": f"{_PRE}, o AS (SELECT depth, count(*) AS observed FROM nd GROUP BY 1) SELECT d AS depth, CAST(pow(6, d) AS BIGINT) AS \"full\", CAST(sum(pow(6, d)) OVER (ORDER BY d) AS BIGINT) AS full_total, coalesce(observed, 0) AS observed FROM range(1, 9) x(d) LEFT JOIN o ON o.depth = d",
    "reward_exact": "SELECT CAST(count(*) AS DOUBLE) AS loose, 0.0::DOUBLE AS strict, CAST(count(*) FILTER (WHERE lower(string_split(p_name, ' ')[1]) = lower(p_type)) AS DOUBLE) AS other FROM part",
    "reward_semantic": f"WITH {JACC} SELECT conv_id, turn, round(j, 6) + 0.0 AS jaccard, CASE WHEN j >= 0.1 THEN 1.0 ELSE 0.0 END::DOUBLE AS reward FROM jc",
    "reward_point": f"WITH {GEO} SELECT vec_id, round({_POINT}, 6) AS reward, round({_POINT}, 6) AS per_axis FROM geo",
    "reward_distance": f"WITH {CAND} SELECT sample_id, round(sum(reward), 6) AS reward, round(min(reward), 6) AS worst FROM cand GROUP BY 1",
    "reward_box": f"WITH {GEO}, b AS (SELECT vec_id, {_iou(2)} AS i2, {_iou(3)} AS i3 FROM geo) SELECT vec_id, round(CASE WHEN i2 >= 0.05 THEN i2 ELSE 0 END, 6) + 0.0 AS box2, round(CASE WHEN i3 >= 0.01 THEN i3 ELSE 0 END, 6) + 0.0 AS box3, round(i2, 6) + 0.0 AS soft2 FROM b",
    "reward_hybrid": f"""WITH {GEO}, k AS (SELECT *, ['exact', 'semantic', 'point', 'distance', 'box'][vec_id % 5 + 1] AS kind, {_iou(2)} AS i2 FROM geo)
SELECT kind, count(*) AS n, round(avg(CASE kind WHEN 'exact' THEN CASE WHEN vec_id % 10 = label THEN 1.0 ELSE 0 END
  WHEN 'semantic' THEN CASE WHEN list_cosine_similarity(v[1:18], g) >= 0.2 THEN 1.0 ELSE 0 END WHEN 'point' THEN {_POINT}
  WHEN 'distance' THEN least(abs(v[1]) / abs(g[1]), abs(g[1]) / abs(v[1])) ELSE CASE WHEN i2 >= 0.05 THEN i2 ELSE 0 END END), 6) + 0.0 AS reward FROM k GROUP BY 1""",
    "leakage": "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text) WHERE len(list_filter(string_split_regex(b.text, '\\s+'), lambda w: w <> '')) >= 1",
    "join_semi_drawn": f"WITH {STRATA}, {POOL} SELECT l_partkey, count(*) AS lines, sum(l_quantity) AS quantity FROM lineitem WHERE l_partkey IN (SELECT sample_id FROM pool WHERE pos <= 40) GROUP BY 1",
    "join_anti_leaves": f"{_PRE} SELECT depth, count(*) AS leaves FROM nd WHERE (task, path) NOT IN (SELECT (task, parent) FROM nd) GROUP BY 1",
    "asof_rate": f"WITH {RATES} SELECT event_id, round(eta, 6) AS eta FROM (SELECT event_id, CAST(user_id % 5 AS INT) AS task, CAST(ts AS DATE) AS place FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN rt ON rt.task = e.task AND e.place > rt.day",
    "range_band": "SELECT band, count(*) AS lines FROM lineitem JOIN (VALUES " + ", ".join(f"({k}, {lo}, {hi})" for k, (lo, hi) in enumerate(BANDS)) + ") b(band, lo, hi) ON l_extendedprice >= lo AND l_extendedprice < hi GROUP BY 1",
    "cube_strata": f"WITH {STRATA} SELECT task, stratum, count(*) AS n FROM st GROUP BY CUBE (task, stratum)",
    "pivot_strata": f"WITH {STRATA} SELECT task, " + ", ".join(f"count(*) FILTER (WHERE stratum = '{s}') AS {s}" for s in ("easy", "uncertain", "hard")) + " FROM st GROUP BY 1",
    "set_overlap": f"""WITH {TUNING}, b AS (SELECT sample_id FROM st ORDER BY {_ORDER}, sample_id LIMIT 500)
SELECT count(*) AS n, 'both' AS part FROM tun WHERE sample_id IN (SELECT sample_id FROM b) UNION ALL SELECT count(*), 'filtered_only' FROM tun WHERE sample_id NOT IN (SELECT sample_id FROM b)
UNION ALL SELECT count(*), 'random_only' FROM b WHERE sample_id NOT IN (SELECT sample_id FROM tun)""",
    "json_actions": "SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) // 50 AS half, count(*) AS n FROM events GROUP BY 1, 2",
    "map_synonyms": "SELECT l_returnflag AS verb, l_linestatus AS receptacle, true AS known, count(*) AS n FROM lineitem GROUP BY 1, 2",
}
