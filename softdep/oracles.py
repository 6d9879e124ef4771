"""The driver's queries in SQL for DuckDB, written apart from the engine."""

from __future__ import annotations

from itertools import combinations
from math import comb

from softdep.fixtures import SIX, NULLBREAK, nullbreak_rows

RELATIONS = {
    "lineitem": ("SELECT * FROM lineitem", "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate"),
    "orders": ("SELECT * FROM orders", "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority"),
    "customer": ("SELECT * FROM customer", "c_custkey c_name c_nationkey c_acctbal c_mktsegment"),
    "part": ("SELECT * FROM part", "p_partkey p_name p_brand p_type p_size p_retailprice"),
    "events": (
        """SELECT user_id, event_type, value, CAST(regexp_extract(props, '"k": *(-?[0-9]+)', 1) AS INTEGER) AS k, hour(ts) AS hour, day(ts) AS day FROM events""",
        "user_id event_type value k hour day",
    ),
    "doc": (
        "SELECT d.doc_id, lang, source, n_chars, quality, toxic, CAST(floor(log2(n_chars + 1)) AS INTEGER) AS size_band FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
        "doc_id lang source n_chars quality toxic size_band",
    ),
    "dirty": (
        """SELECT c_nationkey, n_name, r_name, c_mktsegment, CASE WHEN (c_custkey * 7919) % 101 < 4 THEN 'OTHER' ELSE r_name END AS market,
           CASE WHEN (c_custkey * 31) % 37 = 0 THEN NULL ELSE 10 * c_nationkey + CASE WHEN c_custkey % 3 = 0 THEN 1 ELSE 0 END END AS rep, c_acctbal
           FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
        "c_nationkey n_name r_name c_mktsegment market rep c_acctbal",
    ),
    "conv": (
        r"""SELECT conv_id, turn, role, CASE WHEN t = '' THEN 0 ELSE len(w) END AS n_words, turn % 2 AS parity, w[1] AS first_word
            FROM (SELECT *, string_split_regex(t, '[ \t\n\r]+') AS w FROM (SELECT *, regexp_replace(coalesce(text, ''), '^[ \t\n\r]+|[ \t\n\r]+$', '', 'g') AS t FROM conversations))""",
        "conv_id turn role n_words parity first_word",
    ),
    "page": (
        """SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]*/([a-z][a-z])(?:[/?#]|$)', 1) AS url_lang,
           regexp_extract(html, '<html lang="([^"]*)"', 1) AS html_lang, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, contains(url, '?') AS has_query,
           length(url) - length(replace(url, '/', '')) AS depth, CAST(floor(length(html) / 1024) AS INTEGER) AS kb FROM pages""",
        "host url_lang html_lang scheme has_query depth kb",
    ),
    "wide": (
        """SELECT * FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
        "l_orderkey l_partkey l_suppkey l_returnflag l_linestatus l_discount o_custkey o_orderstatus o_orderpriority c_nationkey c_mktsegment n_name n_regionkey r_name",
    ),
    "six": ("SELECT * FROM (VALUES " + ", ".join(f"('{x}', {a})" for x, a in SIX) + ") t(x, a)", "x a"),
    "nullbreak": ("SELECT * FROM (VALUES " + ", ".join("(" + ", ".join("NULL" if v is None else str(v) for v in r) + ")" for r in nullbreak_rows()) + f") t({', '.join(NULLBREAK)})", " ".join(NULLBREAK)),
}


def columns(rel: str) -> list[str]:
    return RELATIONS[rel][1].split()


def candidates(rel: str, max_lhs: int) -> list[tuple[tuple[int, ...], int]]:
    m = len(columns(rel))
    return [(x, a) for k in range(1, min(max_lhs, m - 1) + 1) for x in combinations(range(m), k) for a in range(m) if a not in x]


def scored(rel: str, cands: list[tuple[tuple[int, ...], int]], source: str | None = None, cols: list[str] | None = None, name: str = "sc") -> str:
    """CTEs that end in one called name: a row for each candidate with every statistic."""
    c = cols or columns(rel)
    ctes = [f"rel_{name} AS MATERIALIZED ({source or RELATIONS[rel][0]})"]
    selects = []
    for i, (x, a) in enumerate(cands):
        xs = [c[p] for p in x]
        lhs, rhs, all_ = ", ".join(xs), c[a], [*xs, c[a]]
        ctes.append(f"j{i}_{name} AS MATERIALIZED (SELECT {', '.join(all_)}, count(*) AS f_ FROM rel_{name} WHERE {' AND '.join(f'{v} IS NOT NULL' for v in all_)} GROUP BY {', '.join(all_)})")
        selects.append(
            f"""SELECT '{",".join(xs)}' AS lhs, '{rhs}' AS rhs, {list(x)} AS lpos, {a} AS rpos, l.n, l.d_lhs, l.d_joint, l.dx, r.da, r.d_rhs, l.top FROM
            (SELECT CAST(coalesce(sum(s_), 0) AS BIGINT) AS n, count(*) AS d_lhs, CAST(sum(k_) AS BIGINT) AS d_joint, sum(CASE WHEN k_ > 1 THEN s_ - q_ / s_ ELSE 0 END) / sum(s_) AS dx, CAST(sum(m_) AS BIGINT) AS top
             FROM (SELECT {lhs}, sum(f_) AS s_, CAST(sum(f_ * f_) AS DOUBLE) AS q_, count(*) AS k_, max(f_) AS m_ FROM j{i}_{name} GROUP BY {lhs})) l,
            (SELECT 1 - CAST(sum(s_ * s_) AS DOUBLE) / (CAST(sum(s_) AS DOUBLE) * CAST(sum(s_) AS DOUBLE)) AS da, count(*) AS d_rhs FROM (SELECT {rhs}, sum(f_) AS s_ FROM j{i}_{name} GROUP BY {rhs})) r"""
        )
    ctes.append(f"raw_{name} AS MATERIALIZED ({' UNION ALL '.join(selects)})")
    ctes.append(f"""{name} AS MATERIALIZED (SELECT *, d_joint = d_lhs AS is_exact, CASE WHEN d_joint = d_lhs OR n = d_lhs OR d_rhs = 1 THEN 0 ELSE dx / da * (n - 1) / (n - d_lhs) END AS rho FROM raw_{name} WHERE n > 1)""")
    return ",\n".join(ctes)


MU = "greatest(0, 1 - rho)"
KEY = "CASE WHEN rho > 0 THEN round(least(rho, 1) * pow(10, 11 - floor(log10(least(rho, 1))))) / pow(10, 11 - floor(log10(least(rho, 1)))) ELSE 0 END"
FULL = f"lhs, rhs, n, d_lhs, d_joint, round({MU}, 6) AS mu_plus, is_exact"


def table(rel: str, max_lhs: int, what: str, where: str = "true") -> str:
    return f"WITH {scored(rel, candidates(rel, max_lhs))}\nSELECT {what} FROM sc WHERE {where}"


def ranked_cte(name: str = "sc", out: str = "ranked", where: str = "true") -> str:
    return f"{out} AS (SELECT *, row_number() OVER (ORDER BY {KEY}, len(lpos), lpos, rpos) AS rank FROM {name} WHERE NOT is_exact AND {where})"


def topk(rel: str, max_lhs: int, k: int = 20, where: str = "true") -> str:
    return f"WITH {scored(rel, candidates(rel, max_lhs))},\n{ranked_cte(where=where)}\nSELECT CAST(rank AS INTEGER) AS rank, lhs, rhs, round({MU}, 6) AS mu_plus FROM ranked WHERE rank <= {k}"


ORACLES: dict[str, str] = {}
for _r in ("part", "orders", "dirty"):
    ORACLES[f"agreement_{_r}"] = table(_r, 1, "lhs, rhs, round(1 - dx, 6) AS agreement")
for _r in ("lineitem", "doc"):
    ORACLES[f"marginal_agreement_{_r}"] = f"WITH rel AS ({RELATIONS[_r][0]}) " + " UNION ALL ".join(
        f"SELECT '{c}' AS attribute, CAST(sum(f) AS BIGINT) AS n, count(*) AS d, round(CAST(sum(f * f) AS DOUBLE) / CAST(sum(f) AS DOUBLE) / CAST(sum(f) AS DOUBLE), 6) AS agreement FROM (SELECT count(*) AS f FROM rel WHERE {c} IS NOT NULL GROUP BY {c})" for c in columns(_r)
    )
ORACLES["lift_part"] = table("part", 1, "lhs, rhs, round((1 - dx) / (1 - da), 6) AS lift")
ORACLES["rho_raw_events"] = table("events", 1, "lhs, rhs, round(rho, 6) AS rho, round(1 - rho, 6) AS mu_raw")
ORACLES["g3_part"] = table("part", 1, "lhs, rhs, round(1 - top / n, 6) AS g3_error")
ORACLES["gain_part"] = table("part", 1, "lhs, rhs, round(CASE WHEN da > 0 THEN 1 - dx / da ELSE 1 END, 6) AS gain")
for _r in ("lineitem", "orders", "customer", "part", "events", "doc", "dirty", "conv", "page", "wide"):
    ORACLES[f"scores_l1_{_r}"] = table(_r, 1, FULL)
for _r in ("part", "orders", "events", "doc", "dirty"):
    ORACLES[f"scores_l2_{_r}"] = table(_r, 2, FULL)
_LI = columns("lineitem")
_CHAIN = [((_LI.index("l_quantity"),), 3), ((_LI.index("l_quantity"), _LI.index("l_extendedprice")), 3), ((_LI.index("l_quantity"), _LI.index("l_extendedprice"), _LI.index("l_returnflag")), 3)]
ORACLES["mu_plus_lineitem_chain"] = f"WITH {scored('lineitem', _CHAIN)} SELECT lhs, rhs, n, d_lhs, d_joint, round({MU}, 6) AS mu_plus FROM sc"
BOUND = "CASE WHEN n > d_lhs AND da > 0 THEN 1 - (n - 1) / (n * da * (n - d_lhs)) END"
ORACLES["six_row_example"] = table("doc", 1, f"lhs, rhs, n, d_lhs, round(dx, 6) AS disagree_lhs, round(da, 6) AS disagree_rhs, round(rho, 6) AS rho, round({MU}, 6) AS mu_plus, round({BOUND}, 6) AS bound")
ORACLES["bound_table_orders"] = table("orders", 1, f"lhs, rhs, round({BOUND}, 6) AS bound", "NOT is_exact")
_COMPLETE = "(SELECT count(*) FROM rel_sc WHERE " + " AND ".join(f"{c} IS NOT NULL" for c in columns("doc")) + ")"
_NU = f"CAST(least(n, greatest(2, {_COMPLETE})) AS DOUBLE)"
ORACLES["sound_bound_doc"] = table("doc", 1, f"lhs, rhs, round(1 - ({_NU} - 1) / ({_NU} * least(1 - 1.0 / d_rhs, (n / {_NU}) * (n / {_NU}) * da) * (n - d_lhs)), 6) AS sound_bound", "NOT is_exact")
ORACLES["exact_fd_customer"] = table("customer", 2, "lhs, rhs", "is_exact")
ORACLES["exact_fd_wide"] = table("wide", 1, "lhs, rhs", "is_exact")
for _r in ("customer", "dirty"):
    ORACLES[f"exact_fd_minimal_{_r}"] = f"WITH {scored(_r, candidates(_r, 2))} SELECT lhs, rhs FROM sc s WHERE is_exact AND NOT EXISTS (SELECT 1 FROM sc t WHERE t.is_exact AND t.rpos = s.rpos AND len(t.lpos) < len(s.lpos) AND list_has_all(s.lpos, t.lpos))"
for _v in range(5):
    ORACLES[f"topk_v{_v}_part"] = topk("part", 2)
for _r, _l in {"orders": 3, "events": 2, "doc": 2, "dirty": 3}.items():
    ORACLES[f"topk_v4_{_r}"] = topk(_r, _l)
ORACLES["topk_customer_short"] = topk("customer", 4)
for _m in ("sound", "heuristic", "nobound"):
    ORACLES[f"topk_doc_{_m}"] = topk("doc", 2)
ORACLES["topk_dirty_late_all_subsets"] = topk("dirty", 3)
ORACLES["nullbreak_exhaustive"] = ORACLES["nullbreak_sound"] = topk("doc", 2, 1)
ORACLES["fixed_rhs_market"] = topk("dirty", 2, 10, "rhs = 'market'")
for _t in (50, 80, 90, 95):
    ORACLES[f"threshold_dirty_{_t}"] = table("dirty", 2, f"lhs, rhs, round({MU}, 6) AS mu_plus", f"NOT is_exact AND {MU} >= {_t / 100}")
ORACLES["candidate_counts"] = """
WITH RECURSIVE binomial(m, k, c) AS (
  SELECT m::BIGINT, 0::BIGINT, 1::HUGEINT FROM range(0, 110) t(m)
  UNION ALL SELECT m, k + 1, c * (m - k) // (k + 1) FROM binomial WHERE k < 6),
counts AS (SELECT m, k, CAST(sum(c * (m - k)) OVER (PARTITION BY m ORDER BY k) AS BIGINT) AS candidates FROM binomial WHERE k >= 1),
v AS (SELECT row_number() OVER () AS id, embedding AS e FROM embeddings),
held AS (SELECT id, i + 1 AS m, sum(CASE WHEN i < 64 AND e[i + 1] > 0 OR i >= 64 AND abs(e[i - 63]) > 0.125::DOUBLE THEN 1 ELSE 0 END) OVER (PARTITION BY id ORDER BY i) AS present FROM v, range(109) t(i)),
patterns AS (SELECT m, present, count(*) AS n FROM held GROUP BY ALL),
kept AS (SELECT p.m, c.k, CAST(sum(p.n * c.candidates) AS BIGINT) AS tuples FROM patterns p JOIN counts c ON p.present = c.m GROUP BY ALL)
SELECT CAST(c.m AS INTEGER) AS m, CAST(c.k AS INTEGER) AS max_lhs, candidates, coalesce(tuples, 0) AS tuples
FROM counts c LEFT JOIN kept USING (m, k) WHERE c.m > 1 AND c.k < c.m"""
_LEFT = "{s} & ~CAST(coalesce((SELECT sum(1 << rpos) FROM sc WHERE is_exact AND lpos = {x}), 0) AS BIGINT)"
ORACLES["next_level_demo"] = f"""
WITH {scored('part', candidates('part', 2))},
one AS (SELECT a, {_LEFT.format(s='(63 - (1 << a))', x='[a]')} AS s FROM (SELECT CAST(i AS INTEGER) AS a FROM range(6) t(i))),
two AS (SELECT p.a AS a, q.a AS b, p.s & q.s & ~(1 << p.a) & ~(1 << q.a) AS s FROM one p JOIN one q ON p.a < q.a),
open AS (SELECT a, b, {_LEFT.format(s='s', x='[a, b]')} AS s FROM two),
three AS (SELECT p.a, p.b, q.b AS c, p.s & q.s & ~(1 << p.a) & ~(1 << p.b) & ~(1 << q.b) AS s FROM open p JOIN open q ON p.a = q.a AND p.b < q.b)
SELECT a || ',' || b AS lhs, CAST(s AS BIGINT) AS mask FROM two WHERE s <> 0 UNION ALL SELECT a || ',' || b || ',' || c, CAST(s AS BIGINT) FROM three WHERE s <> 0"""
_NE = f"ne AS MATERIALIZED (SELECT *, {MU} AS mu, {KEY} AS key FROM sc WHERE NOT is_exact)"
_DIRTY2 = scored("dirty", candidates("dirty", 2))
ORACLES["paradigms_dirty"] = f"WITH {_DIRTY2}, {_NE} " + " UNION ALL ".join(
    [f"SELECT 'threshold {t}' AS paradigm, count(*) AS n_results, round(max(mu), 6) AS best FROM ne WHERE mu >= {t}" for t in (0.5, 0.8, 0.9, 0.95)]
    + ["SELECT 'fixed market', count(*), round(max(mu), 6) FROM (SELECT mu FROM ne WHERE rhs = 'market' ORDER BY mu DESC LIMIT 10)", "SELECT 'global', count(*), round(max(mu), 6) FROM (SELECT mu FROM ne ORDER BY mu DESC LIMIT 20)"]
)
_SUB = "EXISTS (SELECT 1 FROM {b} t WHERE t.rpos = s.rpos AND len(t.lpos) < len(s.lpos) AND list_has_all(s.lpos, t.lpos))"
ORACLES["minimal_literal_dirty"] = f"WITH {_DIRTY2}, {_NE} SELECT lhs, rhs, round(mu, 6) AS mu_plus FROM ne s WHERE NOT {_SUB.format(b='ne')}"
ORACLES["minimal_scored_dirty"] = f"WITH {_DIRTY2}, {_NE}, hi AS (SELECT * FROM ne WHERE mu >= 0.9) SELECT lhs, rhs, round(mu, 6) AS mu_plus FROM hi s WHERE NOT {_SUB.format(b='hi')}"
ORACLES["growth_pairs_dirty"] = f"WITH {_DIRTY2}, {_NE} SELECT a.rhs, a.lhs AS small, b.lhs AS large, round(a.mu, 6) AS low, round(b.mu, 6) AS high FROM ne a JOIN ne b ON a.rpos = b.rpos AND len(a.lpos) < len(b.lpos) AND list_has_all(b.lpos, a.lpos) WHERE b.mu > a.mu + 1e-9"
_G = "g AS (SELECT c_nationkey, sum(f) AS group_size, count(*) AS k, max(f) AS top FROM j GROUP BY c_nationkey), mj AS (SELECT j.c_nationkey, min(market) AS majority FROM j JOIN g ON j.c_nationkey = g.c_nationkey AND f = top GROUP BY j.c_nationkey)"
_AUDIT = f"WITH rel AS ({RELATIONS['dirty'][0]}), j AS (SELECT c_nationkey, market, count(*) AS f FROM rel WHERE c_nationkey IS NOT NULL AND market IS NOT NULL GROUP BY ALL), {_G} "
ORACLES["violations_market"] = _AUDIT + "SELECT r.c_nationkey, r.market, CAST(group_size AS BIGINT) AS group_size, j.f AS rhs_count, majority, r.market <> majority AS is_violation, round(c_acctbal, 2) AS c_acctbal FROM rel r JOIN g ON r.c_nationkey = g.c_nationkey JOIN mj ON r.c_nationkey = mj.c_nationkey JOIN j ON r.c_nationkey = j.c_nationkey AND r.market = j.market WHERE g.k > 1"
ORACLES["repairs_market"] = _AUDIT + "SELECT j.c_nationkey, j.market AS found, majority AS suggested, j.f AS n_rows, round(top / group_size, 6) AS support FROM j JOIN g ON j.c_nationkey = g.c_nationkey JOIN mj ON j.c_nationkey = mj.c_nationkey WHERE g.k > 1 AND j.market <> majority"
_DEPTHS = f"WITH {scored('dirty', candidates('dirty', 3))}, " + ", ".join(ranked_cte(out=f"r{k}", where=f"len(lpos) <= {k}") for k in (1, 2, 3))
ORACLES["depth_overlap_dirty"] = _DEPTHS + " " + " UNION ALL ".join(f"SELECT {k} AS max_lhs, 100.0::DOUBLE * count(*) / 20 AS overlap FROM r{k} a JOIN r{k + 1} b ON a.lpos = b.lpos AND a.rpos = b.rpos WHERE a.rank <= 20 AND b.rank <= 20" for k in (1, 2))
ORACLES["depth_tau_dirty"] = _DEPTHS + ", taus AS (" + " UNION ALL ".join(f"SELECT {k} AS max_lhs, max(CASE WHEN rank = 20 THEN {MU} END) AS tau FROM r{k}" for k in (1, 2, 3)) + ") SELECT max_lhs, round(tau, 6) AS tau, round(tau - lag(tau) OVER (ORDER BY max_lhs), 6) AS increment FROM taus"
_PAIRS = candidates("lineitem", 1)
ORACLES["scale_rows_lineitem"] = "WITH " + ", ".join(scored("lineitem", _PAIRS, f"SELECT * FROM lineitem WHERE (l_orderkey * 31 + l_linenumber) % 10 < {t}", name=f"s{t}") for t in (1, 2, 4, 6, 8, 10)) + " " + " UNION ALL ".join(
    f"SELECT {t} AS tenths, max(n) AS n, CAST(sum(CASE WHEN is_exact THEN 1 ELSE 0 END) AS BIGINT) AS exact, round(max(CASE WHEN NOT is_exact THEN {MU} END), 6) AS best, round(sum({MU}), 6) AS total FROM s{t}" for t in (1, 2, 4, 6, 8, 10)
)
ORACLES["cost_model_table"] = "WITH " + ", ".join(f"t{m} AS (SELECT count(*) AS n FROM (SELECT DISTINCT {', '.join(f'embedding[{i + 1}] > 0 AS b{i}' for i in range(m))} FROM embeddings))" for m in (5, 10, 20)) + " " + " UNION ALL ".join(
    f"SELECT '{v}' AS variant, {m} AS m, n, CAST({sum(comb(m, k) * (m - k) for k in (1, 2, 3))} * n AS BIGINT) AS row_scans, CAST({sum(comb(m, k) * (1 if v == 'V2' else m - k) * k for k in (1, 2, 3))} * n AS BIGINT) AS lhs_key_evaluations, CAST({sum(comb(m, k) * (m - k) for k in (1, 2, 3))} AS BIGINT) AS heap_operations, CAST({0 if v == 'V0' else sum(comb(m, k) for k in (1, 2, 3))} AS BIGINT) AS mask_words FROM t{m}"
    for v in ("V0", "V1", "V2")
    for m in (5, 10, 20)
)
ORACLES["null_patterns_doc"] = f"WITH rel AS ({RELATIONS['doc'][0]}) SELECT CAST({' + '.join(f'CASE WHEN {c} IS NULL THEN {1 << i} ELSE 0 END' for i, c in enumerate(columns('doc')))} AS BIGINT) AS null_mask, count(*) AS n FROM rel GROUP BY 1"
ORACLES["joint_table_doc"] = f"SELECT lang, quality, toxic, count(*) AS f FROM ({RELATIONS['doc'][0]}) WHERE lang IS NOT NULL AND quality IS NOT NULL AND toxic IS NOT NULL GROUP BY ALL"
ORACLES["grouping_sets_part"] = "SELECT p_brand, p_type, count(*) AS f, CAST(grouping(p_brand, p_type) AS BIGINT) AS gid FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), (p_brand, p_type))"
ORACLES["cube_part"] = "SELECT p_brand, p_type, count(*) AS f, max(p_size) AS max_size FROM part GROUP BY CUBE (p_brand, p_type)"
ORACLES["rollup_orders"] = "SELECT o_orderstatus, o_orderpriority, count(*) AS f, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"
ORACLES["asof_prev_event"] = "SELECT a.event_id, a.user_id, b.event_type AS prev_type FROM events a ASOF LEFT JOIN events b ON a.user_id = b.user_id AND a.ts > b.ts"
ORACLES["asof_last_purchase"] = "SELECT a.event_id, b.event_id AS seen_id FROM events a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = (SELECT min(event_type) FROM events)) b ON a.user_id = b.user_id AND a.ts >= b.ts"
ORACLES["interval_join_events"] = "SELECT a.event_id, b.event_id AS earlier_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 6 HOUR"
_EV = """e AS (SELECT ts, event_type, CAST(regexp_extract(props, '"k": *(-?[0-9]+)', 1) AS INTEGER) AS k FROM events)"""


def _windows(rows: str) -> str:
    """Scores by window from CTEs that end in w(ts, event_type, k, a, b)."""
    return f"""WITH {_EV}, {rows}, j AS (SELECT a, b, event_type, k, count(*) AS f FROM w WHERE event_type IS NOT NULL AND k IS NOT NULL GROUP BY ALL),
    l AS (SELECT a, b, CAST(sum(s) AS BIGINT) AS n, count(*) AS d_lhs, CAST(sum(c) AS BIGINT) AS d_joint, sum(CASE WHEN c > 1 THEN s - q / s ELSE 0 END) / sum(s) AS dx FROM (SELECT a, b, event_type, sum(f) AS s, CAST(sum(f * f) AS DOUBLE) AS q, count(*) AS c FROM j GROUP BY ALL) GROUP BY a, b),
    r AS (SELECT a, b, 1 - CAST(sum(s * s) AS DOUBLE) / (CAST(sum(s) AS DOUBLE) * CAST(sum(s) AS DOUBLE)) AS da FROM (SELECT a, b, k, sum(f) AS s FROM j GROUP BY ALL) GROUP BY a, b)
    SELECT strftime(l.a, '%Y-%m-%d %H:%M:%S') AS start, strftime(l.b, '%Y-%m-%d %H:%M:%S') AS "end", n, d_lhs, d_joint, round(CASE WHEN n <= 1 THEN NULL WHEN d_joint = d_lhs OR n = d_lhs OR da <= 0 THEN 1 ELSE greatest(0, 1 - dx / da * (n - 1) / (n - d_lhs)) END, 6) AS mu_plus FROM l JOIN r ON l.a = r.a AND l.b = r.b"""


ORACLES["windowed_scores_events"] = _windows("w AS (SELECT *, CAST(date_trunc('day', ts) AS TIMESTAMP) AS a, CAST(date_trunc('day', ts) AS TIMESTAMP) + INTERVAL 1 DAY AS b FROM e)")
ORACLES["sliding_scores_events"] = _windows("w AS (SELECT e.*, CAST(date_trunc('day', ts) AS TIMESTAMP) - to_days(CAST(i AS INTEGER)) AS a, CAST(date_trunc('day', ts) AS TIMESTAMP) - to_days(CAST(i AS INTEGER)) + INTERVAL 2 DAY AS b FROM e, range(0, 2) t(i))")
ORACLES["session_scores_events"] = _windows(
    "o AS (SELECT *, CASE WHEN ts - lag(ts) OVER (ORDER BY ts) <= INTERVAL 20 MINUTE THEN 0 ELSE 1 END AS fresh FROM e), p AS (SELECT *, sum(fresh) OVER (ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM o), w AS (SELECT ts, event_type, k, min(ts) OVER (PARTITION BY sid) AS a, max(ts) OVER (PARTITION BY sid) + INTERVAL 20 MINUTE AS b FROM p)"
)
ORACLES["stream_counts_events"] = f"""WITH {_EV} SELECT '{{"event_type":"' || event_type || '"}}' AS lhs_key, CAST(k AS VARCHAR) AS rhs_value, count(*) AS f FROM e WHERE event_type IS NOT NULL AND k IS NOT NULL GROUP BY ALL"""
_RANKED = f"r AS (SELECT lhs, rhs, round({MU}, 6) AS mu_plus FROM sc WHERE NOT is_exact)"
ORACLES["rank_by_rhs_dirty"] = f"""WITH {_DIRTY2}, {_RANKED} SELECT lhs, rhs, mu_plus, CAST(rank() OVER w AS INTEGER) AS rank, CAST(dense_rank() OVER w AS INTEGER) AS dense, round(percent_rank() OVER w, 6) AS percent,
    CAST(ntile(4) OVER (PARTITION BY rhs ORDER BY mu_plus DESC, lhs) AS INTEGER) AS quarter FROM r WINDOW w AS (PARTITION BY rhs ORDER BY mu_plus DESC)"""
_MARKETS = ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST", "OTHER"]
ORACLES["contingency_dirty"] = "SELECT c_nationkey, " + ", ".join(f"count(*) FILTER (market = '{m}') AS {m.lower().replace(' ', '_')}" for m in _MARKETS) + f" FROM ({RELATIONS['dirty'][0]}) GROUP BY c_nationkey"
ORACLES["result_identity_dirty"] = "SELECT 'V' || v AS variant, true AS same FROM range(5) t(v)"
ORACLES["lattice_tables_dirty"] = ORACLES["topk_dirty_late_all_subsets"]
ORACLES["sentence_dirty"] = f"WITH {_DIRTY2}, {_NE} SELECT lhs, rhs, round(mu, 6) AS mu_plus FROM ne WHERE rhs = 'market' AND mu >= 0.5 ORDER BY mu DESC, len(lpos), lpos LIMIT 10"
for _k in ("joint", "shared", "each"):
    ORACLES[f"scores_l1_{_k}_kernel"] = ORACLES["scores_l1_part"]
ORACLES["scores_l1_many_blocks"] = ORACLES["scores_l1_doc"]
ORACLES["null_patterns_bits"] = "WITH b AS (SELECT len(list_filter(embedding[1:64], lambda x: x <= 0)) AS nulls FROM embeddings) SELECT CAST(nulls AS BIGINT) AS nulls, CAST(count(*) AS BIGINT) AS n FROM b GROUP BY nulls"

# The three properties, on all scores to depth 2.
_INSIDE = "EXISTS (SELECT 1 FROM ne t WHERE t.rpos = s.rpos AND len(t.lpos) < len(s.lpos) AND list_has_all(s.lpos, t.lpos))"
_PLACED = f"pl AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY key, len(lpos), lpos, rpos) AS place, NOT {_INSIDE} AS least FROM ne s)"
_KEPT = """p23 AS (SELECT * FROM pl WHERE place <= 2),
p13 AS (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY place) AS r FROM pl WHERE least) WHERE r <= 2),
p12 AS (SELECT * FROM p23 WHERE place < coalesce((SELECT min(place) FROM p23 WHERE NOT least), 3))"""
ORACLES["properties_dirty"] = f"WITH {_DIRTY2}, {_NE}, {_PLACED}, {_KEPT} " + " UNION ALL ".join(
    f"""SELECT '{n}' AS kept, NOT EXISTS (SELECT 1 FROM {t} WHERE NOT least) AS minimal,
    coalesce((SELECT max(mu) FROM pl WHERE place NOT IN (SELECT place FROM {t})) <= (SELECT min(mu) FROM {t}) + 1e-9, true) AS top_k, (SELECT count(*) FROM {t}) = least(2, (SELECT count(*) FROM pl)) AS exactly_k"""
    for n, t in (("P2P3", "p23"), ("P1P3", "p13"), ("P1P2", "p12"))
)
ORACLES["incompatibility_dirty"] = f"""WITH {_DIRTY2}, {_NE}, {_PLACED},
ch AS (SELECT b.rhs, b.rpos, a.lhs AS small, b.lhs AS large, b.lpos AS big, a.mu AS low, b.mu AS high FROM pl a JOIN pl b ON a.rpos = b.rpos AND len(a.lpos) < len(b.lpos) AND list_has_all(b.lpos, a.lpos)
  WHERE a.least AND b.mu > a.mu + 1e-9 ORDER BY b.mu DESC, len(b.lpos), b.lpos, b.rpos, a.mu DESC, len(a.lpos), a.lpos LIMIT 1),
th AS (SELECT p.lhs AS other_lhs, p.rhs AS other_rhs, p.mu AS other FROM pl p, ch WHERE p.least AND p.mu > 0 AND p.mu < low AND NOT list_has_any(list_append(p.lpos, p.rpos), list_append(big, ch.rpos)) ORDER BY p.mu DESC, len(p.lpos), p.lpos, p.rpos LIMIT 1)
SELECT rhs, small, large, round(low, 6) AS low, round(high, 6) AS high, other_lhs, other_rhs, round(other, 6) AS other FROM ch LEFT JOIN th ON true"""


# Reliable fraction of information: the mean overlap under permutations, from the numbers of groups by size.
def rfi(rel: str, cands: list[tuple[tuple[int, ...], int]]) -> str:
    c, out, ctes = columns(rel), [], [f"rel AS MATERIALIZED ({RELATIONS[rel][0]})"]
    for i, (x, a) in enumerate(cands):
        xs = ", ".join(c[p] for p in x)
        every = [*(c[p] for p in x), c[a]]
        ctes.append(f"j{i} AS MATERIALIZED (SELECT {', '.join(every)}, count(*) AS f_ FROM rel WHERE {' AND '.join(f'{v} IS NOT NULL' for v in every)} GROUP BY {', '.join(every)})")
        for side, by in (("l", xs), ("r", c[a])):
            ctes.append(f"{side}{i} AS MATERIALIZED (SELECT s, count(*) AS c FROM (SELECT sum(f_) AS s FROM j{i} GROUP BY {by}) GROUP BY s)")
        ctes.append(
            f"""e{i} AS MATERIALIZED (SELECT sum(l.c * r.c * k / n * log2(n * k / (l.s * r.s)) * exp(lgamma(l.s + 1) + lgamma(n - l.s + 1) + lgamma(r.s + 1) + lgamma(n - r.s + 1) - lgamma(n + 1) - lgamma(k + 1) - lgamma(l.s - k + 1) - lgamma(r.s - k + 1) - lgamma(n - l.s - r.s + k + 1))) AS e
            FROM (SELECT CAST(s AS DOUBLE) AS s, c FROM l{i}) l, (SELECT CAST(s AS DOUBLE) AS s, c FROM r{i}) r, (SELECT CAST(sum(f_) AS DOUBLE) AS n FROM j{i}), LATERAL (SELECT CAST(unnest(range(CAST(greatest(1, l.s + r.s - n) AS BIGINT), CAST(least(l.s, r.s) AS BIGINT) + 1)) AS DOUBLE) AS k))"""
        )
        h = lambda t, s, w: f"(SELECT -sum({w} * ({s} / n) * log2({s} / n)) FROM {t}, (SELECT CAST(sum(f_) AS DOUBLE) AS n FROM j{i}))"
        out.append(f"SELECT '{','.join(c[p] for p in x)}' AS lhs, '{c[a]}' AS rhs, (SELECT CAST(sum(f_) AS BIGINT) FROM j{i}) AS n, {h(f'l{i}', 's', 'c')} + {h(f'r{i}', 's', 'c')} - {h(f'j{i}', 'f_', '1')} AS mi, {h(f'r{i}', 's', 'c')} AS top, (SELECT e FROM e{i}) AS e")
    return f"WITH {', '.join(ctes)}, a AS ({' UNION ALL '.join(out)}) SELECT lhs, rhs, n, round(CASE WHEN top <= 1e-15 OR e / top >= 1 - 1e-12 THEN 0 ELSE greatest(0, (mi / top - e / top) / (1 - e / top)) END, 6) AS rfi FROM a"


ORACLES["rfi_plus_dirty"] = rfi("dirty", candidates("dirty", 1))


# What a search evaluates: the levels one after the other, with the threshold after each candidate.
def simulated(rel: str, max_lhs: int, k: int, bound: str | None, exact: bool, tag: str) -> str:
    """CTEs {tag}1, {tag}2, ...: the candidates that each level evaluates, with gone (its right side goes) and tau. bound:
    strict or sound or None."""
    depth = min(max_lhs, len(columns(rel)) - 1)
    b = {"strict": "b_strict", "sound": "b_sound", None: "NULL"}[bound]
    out = []
    for level in range(1, depth + 1):
        parents = "" if level == 1 else f" AND EXISTS (SELECT 1 FROM {tag}{level - 1} p WHERE NOT p.gone AND p.rpos = s.rpos AND p.lpos = s.lpos[1:{level - 1}]) AND EXISTS (SELECT 1 FROM {tag}{level - 1} p WHERE NOT p.gone AND p.rpos = s.rpos AND p.lpos = list_concat(s.lpos[1:{level - 2}], s.lpos[{level}:{level}]))"
        if not exact:
            parents = ""
        before = "".join(f" UNION ALL SELECT ord, key, false FROM {tag}{x} WHERE NOT ex AND NOT skip" for x in range(1, level))
        out.append(f"{tag}e{level} AS MATERIALIZED (SELECT * FROM sq s WHERE sz = {level}{parents})")
        out.append(f"{tag}w{level} AS MATERIALIZED (SELECT ord, now, list_sort(list_filter(list(key) OVER (ORDER BY ord ROWS UNBOUNDED PRECEDING), lambda x: x IS NOT NULL)) AS keys FROM (SELECT ord, CASE WHEN NOT ex AND NOT skip THEN key END AS key, true AS now FROM {tag}e{level}{before}))")
        out.append(f"{tag}t{level} AS MATERIALIZED (SELECT e.*, CASE WHEN len(keys) >= {k} THEN greatest(0, 1 - keys[{k}]) END AS tau, len(keys) AS offered FROM {tag}e{level} e JOIN {tag}w{level} w ON e.ord = w.ord AND w.now)")
        out.append(f"{tag}{level} AS MATERIALIZED (SELECT *, coalesce(NOT ex AND NOT skip AND {b} IS NOT NULL AND greatest({b}, 0) <= tau, false) AS weak, ex OR skip OR coalesce({b} IS NOT NULL AND greatest({b}, 0) <= tau, false) AS gone FROM {tag}t{level})")
    return ",\n".join(out)


def sequence_cte(rel: str, max_lhs: int) -> str:
    """All candidates in the order of evaluation, with both bounds."""
    complete = f"(SELECT count(*) FROM rel_sc WHERE {' AND '.join(f'{c} IS NOT NULL' for c in columns(rel))})"
    nu = f"CAST(least(n, greatest(2, {complete})) AS DOUBLE)"
    return f"""{scored(rel, candidates(rel, max_lhs))},
    sq AS MATERIALIZED (SELECT *, {KEY} AS key FROM (SELECT *, len(lpos) AS sz, row_number() OVER (ORDER BY len(lpos), lpos, rpos) AS ord, n <= 1 AS skip, n > 1 AND d_joint = d_lhs AS ex,
      CASE WHEN n <= 1 OR d_joint = d_lhs OR n = d_lhs OR d_rhs = 1 THEN 0 ELSE dx / da * (n - 1) / (n - d_lhs) END AS rho,
      CASE WHEN n > d_lhs AND da > 0 THEN 1 - (n - 1) / (n * da * (n - d_lhs)) END AS b_strict,
      CASE WHEN n > d_lhs AND da > 0 THEN 1 - ({nu} - 1) / ({nu} * least(1 - 1.0 / d_rhs, (n / {nu}) * (n / {nu}) * da) * (n - d_lhs)) END AS b_sound FROM raw_sc))"""


def theoretical(m: int, max_lhs: int) -> int:
    return sum(comb(m, x) * (m - x) for x in range(1, min(max_lhs, m - 1) + 1))


def cost_row(rel: str, variant: str, k: int, max_lhs: int, tag: str) -> str:
    m = len(columns(rel))
    depth = min(max_lhs, m - 1)
    every = " UNION ALL ".join(f"SELECT ord, ex, skip, tau, offered FROM {tag}{x}" for x in range(1, depth + 1))
    return f"""SELECT '{rel}' AS name, '{variant}' AS variant, {k} AS k, {depth} AS max_lhs, (SELECT count(*) FROM rel_sc) AS n, {m} AS m, count(*) AS ecn, round(1 - count(*) / CAST({theoretical(m, max_lhs)} AS DOUBLE), 6) AS pruning_ratio,
    count(*) FILTER (ex) AS exact, round(coalesce(arg_max(tau, ord) FILTER (offered >= {k}), -1), 6) AS tau, CAST(least({k}, max(offered)) AS INTEGER) AS n_results FROM ({every})"""


def _bound(rel: str) -> str:
    return "sound" if rel in ("doc", "dirty", "nullbreak") else "strict"


_MODES = {"V0": lambda r: (None, False), "V1": lambda r: (None, False), "V2": lambda r: (None, False), "V3": lambda r: (None, True), "V4": lambda r: (_bound(r), True), "off": lambda r: (None, True), "heuristic": lambda r: ("strict", True), "sound": lambda r: ("sound", True)}


def costs(rel: str, max_lhs: int, runs: list[tuple[str, int]]) -> str:
    """A row for each (variant, k)."""
    tags = [f"{v.lower()}_{k}_" for v, k in runs]
    return f"WITH {sequence_cte(rel, max_lhs)},\n" + ",\n".join(simulated(rel, max_lhs, k, *_MODES[v](rel), t) for (v, k), t in zip(runs, tags, strict=True)) + "\n" + " UNION ALL ".join(cost_row(rel, v, k, max_lhs, t) for (v, k), t in zip(runs, tags, strict=True))


for _r, _l in {"orders": 5, "customer": 4, "part": 5, "events": 5, "doc": 5, "dirty": 5, "conv": 5, "page": 5}.items():
    ORACLES[f"overall_{_r}"] = costs(_r, _l, [("V0", 20), ("V4", 20)])
for _r in ("orders", "dirty", "events"):
    ORACLES[f"workload_ablation_{_r}"] = costs(_r, 5, [(v, 20) for v in ("V0", "V1", "V2", "V3", "V4")])
ORACLES["workload_scale_k"] = " UNION ALL ".join(f"SELECT * FROM ({costs(r, 3, [('V4', k) for k in (5, 10, 20, 50, 100)])})" for r in ("dirty", "doc"))
ORACLES["workload_null_bound"] = " UNION ALL ".join(f"SELECT * FROM ({costs(r, d, [(v, k) for v in ('off', 'heuristic', 'sound')])})" for r, k, d in (("doc", 20, 3), ("dirty", 20, 3), ("nullbreak", 1, 2)))
_LEVELS = []
for _v, _t in (("V0", "v0_20_"), ("V3", "v3_20_"), ("V4", "v4_20_")):
    _sum = " + ".join(f"(SELECT count(*) FROM {_t}{x})" for x in range(1, 6))
    _LEVELS += [
        f"SELECT '{_v}' AS variant, {x} AS level, count(*) AS ecn, CAST({' + '.join(f'(SELECT count(*) FROM {_t}{y})' for y in range(1, x + 1))} AS BIGINT) AS running_ecn, count(*) FILTER (ex) AS exact, count(*) FILTER (weak) AS bound_pruned, round(coalesce(arg_max(tau, ord) FILTER (offered >= 20), -1), 6) AS tau, round(1 - ({_sum}) / CAST({theoretical(6, 5)} AS DOUBLE), 6) AS pruning_ratio FROM {_t}{x} HAVING count(*) > 0"
        for x in range(1, 6)
    ]
ORACLES["ecn_report_orders"] = f"WITH {sequence_cte('orders', 5)}, " + ", ".join(simulated("orders", 5, 20, *_MODES[v]("orders"), f"{v.lower()}_20_") for v in ("V0", "V3", "V4")) + " " + " UNION ALL ".join(_LEVELS)


def sweep(rel: str, most: int, k: int = 20) -> str:
    """Threshold and overlap by depth, from the list of each depth."""
    depth = min(most, len(columns(rel)) - 1)
    lists = ", ".join(ranked_cte(out=f"r{x}", where=f"len(lpos) <= {x}") for x in range(1, depth + 1))
    share = lambda x: f"(SELECT 100.0::DOUBLE * count(*) / {k} FROM r{x} a JOIN r{x + 1} b ON a.lpos = b.lpos AND a.rpos = b.rpos WHERE a.rank <= {k} AND b.rank <= {k})" if x < depth else "CAST(NULL AS DOUBLE)"
    return f"WITH {scored(rel, candidates(rel, depth))}, {lists} " + " UNION ALL ".join(f"SELECT '{rel}' AS name, {x} AS max_lhs, round(coalesce(max(CASE WHEN rank = {k} THEN {MU} END), -1), 6) AS tau, {share(x)} AS overlap FROM r{x}" for x in range(1, depth + 1))


for _r in ("events", "doc", "dirty"):
    ORACLES[f"workload_depth_{_r}"] = sweep(_r, 6)
ORACLES["workload_paradigms"] = f"WITH {scored('dirty', candidates('dirty', 3))}, {_NE} " + " UNION ALL ".join(
    [f"SELECT 'threshold {t}' AS paradigm, count(*) AS n_results, round(max(mu), 6) AS best FROM ne WHERE mu >= {t}" for t in (0.5, 0.8, 0.9, 0.95)]
    + ["SELECT 'fixed market', count(*), round(max(mu), 6) FROM (SELECT mu FROM ne WHERE rhs = 'market' ORDER BY mu DESC LIMIT 10)", "SELECT 'global', count(*), round(max(mu), 6) FROM (SELECT mu FROM ne ORDER BY mu DESC LIMIT 20)"]
)
ORACLES["workload_case_study"] = f"""WITH {scored('dirty', candidates('dirty', 3))}, {ranked_cte()}, t AS (SELECT * FROM ranked WHERE rank <= 20)
SELECT CAST(rank AS INTEGER) AS rank, lhs, rhs, round({MU}, 6) AS mu_plus, CAST(n - top AS BIGINT) AS n_violations, CAST((SELECT count(DISTINCT rhs) FROM t u WHERE u.rank <= t.rank) AS INTEGER) AS distinct_rhs,
round((SELECT count(DISTINCT rhs) FROM t u WHERE u.rank <= t.rank) / CAST(rank AS DOUBLE), 6) AS rhs_per_rank FROM t"""
# On sign bits no dependency is exact and nothing is pruned: the numbers follow from the number of columns alone.
ORACLES["workload_scale_columns"] = " UNION ALL ".join(
    f"SELECT 'bits {b}' AS name, '{v}' AS variant, {b + 1} AS m, (SELECT count(*) FROM embeddings) AS n, CAST({theoretical(b + 1, 2)} AS BIGINT) AS ecn, CAST(0 AS BIGINT) AS exact, 20 AS n_results" for b in (8, 12, 16, 20, 32, 64) for v in ("V0", "V4")
)
