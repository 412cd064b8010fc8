"""DuckDB SQL of the queries that SQL can express."""

from __future__ import annotations

WORDS = "list_distinct(regexp_extract_all(lower({0}), '[a-z]{{3,}}'))"
LINES = """(SELECT c.c_custkey, c.c_mktsegment, c.c_acctbal, b.p_type, b.p_brand, b.p_size FROM customer c LEFT JOIN
  (SELECT o_custkey, p_type, p_brand, p_size FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey) b ON b.o_custkey = c.c_custkey) AS x"""

LONG = {
    "emb_sign": "SELECT DISTINCT vec_id AS tid, CASE WHEN embedding[u.i] > 0 THEN 'd' || lpad(CAST(u.i - 1 AS VARCHAR), 2, '0') END AS item, CAST(label < 5 AS INT) AS label FROM embeddings, unnest(range(1, len(embedding) + 1)) AS u(i)",
    "doc_words": f"SELECT d.doc_id AS tid, unnest({WORDS.format('text')}) AS item, CAST(quality = 1 AS INT) AS label FROM documents d JOIN labels l ON d.doc_id = l.doc_id",
    "conv_words": f"SELECT DISTINCT tid, item, label FROM (SELECT conv_id AS tid, unnest({WORDS.format('text')}) AS item FROM conversations) JOIN (SELECT conv_id AS tid, max(CAST(role = 'system' AS INT)) AS label FROM conversations GROUP BY conv_id) USING (tid)",
    "page_words": "SELECT page_id AS tid, unnest(" + WORDS.format("regexp_replace(html, '<[^>]*>', ' ', 'g')") + ") AS item, CAST(contains(html, '<html lang=\"en\"') AS INT) AS label FROM pages",
    "user_slots": "SELECT DISTINCT e.user_id AS tid, event_type || '/' || (day(ts) // 4) AS item, label FROM events e JOIN (SELECT user_id, CAST(avg(value) >= (SELECT avg(value) FROM events) AS INT) AS label FROM events GROUP BY user_id) u ON u.user_id = e.user_id",
    "cust_parts": f"SELECT DISTINCT c_custkey AS tid, p_type || '/' || (p_size // 10) AS item, CAST(c_mktsegment = 'BUILDING' AS INT) AS label FROM {LINES}",
    "cust_brands": f"SELECT DISTINCT c_custkey AS tid, p_brand AS item, CAST(c_acctbal >= 5000 AS INT) AS label FROM {LINES}",
    "supp_dates": "SELECT DISTINCT s_suppkey AS tid, year(l_shipdate) || '/' || (month(l_shipdate) // 2) AS item, CAST(r_regionkey < 2 AS INT) AS label FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey LEFT JOIN lineitem ON l_suppkey = s_suppkey AND l_returnflag = 'R' AND l_discount >= 0.05",
    "order_lines": """SELECT DISTINCT l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey AS tid,
      unnest(['status=' || l_linestatus, 'quantity=' || CAST(floor(l_quantity / 10) AS INT), 'discount=' || CAST(round(l_discount * 100) AS INT), 'tax=' || CAST(round(l_tax * 100) AS INT), 'priority=' || o_orderpriority,
      'segment=' || c_mktsegment, 'type=' || p_type, 'size=' || (p_size // 10), 'year=' || year(l_shipdate)]) AS item, CAST(l_returnflag = 'R' AS INT) AS label
      FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey""",
    "part_supp": "SELECT DISTINCT p_partkey AS tid, 's' || (l_suppkey % 20) AS item, CAST(p_size <= 25 AS INT) AS label FROM part LEFT JOIN lineitem ON l_partkey = p_partkey",
}


def long(name: str) -> str:
    return f"WITH long AS MATERIALIZED ({LONG[name]})"


def base(name: str = "emb_sign", part: float = 0.2, longest: int = 3) -> str:
    """Patterns of up to ``longest`` items, with counts and the dictionary."""
    levels, names = [], "abcdefgh"[:longest]
    enough = f"HAVING count(*) >= (SELECT ceil(n * {part}) FROM n)"
    for size in range(2, longest + 1):
        own = names[:size]
        picked = ", ".join(f"t{c}.i AS {c}" for c in own)
        joined = " ".join(f"JOIN often t{d} ON t{d}.tid = ta.tid AND t{c}.i < t{d}.i" for c, d in zip(own, own[1:]))
        before = f"JOIN p{size - 1} q ON " + " AND ".join(f"q.{c} = t{c}.i" for c in own[:-1])
        levels.append(f"), p{size} AS MATERIALIZED (\n  SELECT {picked}, count(*) AS sup, count(*) FILTER (ta.label = 1) AS sup_pos FROM often ta {joined} {before} GROUP BY {', '.join(f't{c}.i' for c in own)} {enough}\n")
    united = " UNION ALL ".join(f"SELECT {' || chr(44) || '.join(f'CAST({c} AS VARCHAR)' for c in names[:size])} AS pattern, [{', '.join(names[:size])}] AS items, CAST({size} AS INT) AS len, sup, sup_pos FROM p{size}" for size in range(1, longest + 1))
    return f"""{long(name)}, n AS MATERIALIZED (
  SELECT count(DISTINCT tid) AS n, count(DISTINCT CASE WHEN label = 1 THEN tid END) AS n_pos FROM long
), counts AS MATERIALIZED (
  SELECT item, count(DISTINCT tid) AS support FROM long WHERE item IS NOT NULL GROUP BY item
), dict AS MATERIALIZED (
  SELECT CAST(row_number() OVER (ORDER BY support DESC, item) - 1 AS INT) AS i, item, support FROM counts {"WHERE support >= (SELECT ceil(n * " + str(part) + ") FROM n)" if name.endswith("_words") else ""}
), tx AS MATERIALIZED (
  SELECT tid, i, label FROM long JOIN dict USING (item)
), p1 AS MATERIALIZED (
  SELECT i AS a, count(*) AS sup, count(*) FILTER (label = 1) AS sup_pos FROM tx GROUP BY i {enough}
), often AS MATERIALIZED (
  SELECT tid, i, label FROM tx JOIN p1 ON p1.a = i
{"".join(levels)}), patterns AS MATERIALIZED (
  {united}
), exploded AS MATERIALIZED (
  SELECT pattern, unnest(items) AS i FROM patterns
)"""


B = base()
U32 = "CAST('0x' || substr(md5({0}), 1, 8) AS BIGINT)"
U01 = "((" + U32 + " + 1) / 4294967297.0)"
WEIGHTED = B + """, scored AS MATERIALIZED (
  SELECT p.*, s.s + 0.5 * len / (SELECT count(*) FROM dict) - 0.3 * sup / (SELECT n FROM n) AS score
  FROM patterns p JOIN (SELECT pattern, sum((i * 37 % 11 - 5) / 10.0) AS s FROM exploded GROUP BY pattern) s ON s.pattern = p.pattern
), weighted AS MATERIALIZED (
  SELECT *, 0.1 + 0.9 / (1 + exp(-score)) AS w FROM scored
)"""
FEEDBACK = """, feedback AS MATERIALIZED (
  SELECT 's' AS session_id, it AS iter, row_number() OVER (PARTITION BY it ORDER BY sup DESC, pattern) AS pos, sup AS level, pattern
  FROM (SELECT pattern, sup, CAST((row_number() OVER (ORDER BY md5(pattern)) - 1) // 5 AS INT) AS it FROM patterns ORDER BY md5(pattern) LIMIT 30)
), pairs AS MATERIALIZED (
  SELECT x.iter, x.pattern AS winner, y.pattern AS loser FROM feedback x JOIN feedback y ON x.iter = y.iter AND x.pos < y.pos AND x.level <> y.level
)"""


def xors(m: int | str, draws: int, n_items: str = "(SELECT count(*) FROM dict)", seed: int = 7) -> str:
    key = f"'{seed}|' || d.d || '|' || x.x || '|' || "
    return f""", bits AS MATERIALIZED (
  SELECT CAST(d.d AS INT) AS draw_id, CAST(x.x AS INT) AS x, CAST(i.i AS INT) AS i, {U32.format(key + "i.i")} % 2 AS b FROM range({draws}) AS d(d), range({m}) AS x(x), range({n_items}) AS i(i)
), parities AS MATERIALIZED (
  SELECT CAST(d.d AS INT) AS draw_id, CAST(x.x AS INT) AS x, CAST({U32.format(key + "'parity'")} % 2 AS INT) AS parity FROM range({draws}) AS d(d), range({m}) AS x(x)
)"""


CELL = """, met AS MATERIALIZED (
  SELECT b.draw_id, b.x, e.pattern, sum(b.b) % 2 AS own FROM exploded e JOIN bits b ON b.i = e.i GROUP BY ALL
), cells AS MATERIALIZED (
  SELECT m.draw_id, m.pattern FROM met m JOIN parities q ON q.draw_id = m.draw_id AND q.x = m.x GROUP BY ALL HAVING bool_and(m.own = q.parity)
)"""
CELLS = WEIGHTED + xors(4, 3) + CELL
FREQUENT = " SELECT pattern, len, sup, sup_pos FROM patterns"
COUNTED = "SELECT item, count(DISTINCT tid) AS support, count(DISTINCT CASE WHEN label = 1 THEN tid END) AS sup_pos FROM long WHERE item IS NOT NULL GROUP BY item"
SURPRISE = B + """, quality AS (
  SELECT p.pattern, greatest(any_value(sup) / any_value(n.n) - exp(sum(ln(d.support / n.n))), 0) AS phi FROM patterns p JOIN exploded e ON e.pattern = p.pattern JOIN dict d ON d.i = e.i CROSS JOIN n GROUP BY p.pattern
)"""
TOP5 = ", top5 AS MATERIALIZED (SELECT * FROM patterns WHERE len {0} ORDER BY sup DESC, pattern LIMIT {1})"
XOR_ROWS = """SELECT b.draw_id, b.x, CAST(CASE WHEN sum(b * (CAST(1 AS HUGEINT) << i)) >= (CAST(1 AS HUGEINT) << 63) THEN sum(b * (CAST(1 AS HUGEINT) << i)) - (CAST(1 AS HUGEINT) << 64) ELSE sum(b * (CAST(1 AS HUGEINT) << i)) END AS BIGINT) AS c0, any_value(q.parity) AS parity
FROM bits b JOIN parities q ON q.draw_id = b.draw_id AND q.x = b.x GROUP BY b.draw_id, b.x"""


REGRETS = "round(avg({0}_regret), 6) AS {0}_regret, round(stddev_samp({0}_regret), 6) AS {0}_regret_sd"
STATS = "count(*) AS sessions, " + ", ".join(REGRETS.format(m) for m in ("avg", "max", "entropy")) + ", round(avg(entropy_bits), 6) AS entropy_bits"
MEASURES = {"avg": "avg_quality", "max": "max_quality", "entropy": "entropy_share"}


def oracles() -> dict[str, str]:
    out = {f"enc_{n}": f"{long(n)} {COUNTED}" for n in LONG}
    out |= {n: B + FREQUENT for n in ("frequent_emb_len3", "frequent_fpgrowth", "frequent_levelwise", "frequent_partitioned")}
    from prefpat import oracle_sessions as rounds
    from prefpat import queries as q

    samplers = rounds.sampler_sql(B)
    out |= {
        "dataset_stats": B + " SELECT 'emb_sign' AS dataset, CAST((SELECT count(*) FROM dict) AS INT) AS items, CAST((SELECT count(*) FROM dict) AS INT) AS frequent_items, CAST(n AS INT) AS transactions, CAST(ceil(n * 0.2) AS INT) AS min_sup, (SELECT count(*) FROM patterns) AS patterns, (SELECT max(len) FROM patterns) AS longest FROM n",
        "frequent_cust_brands_len3": base("cust_brands", 0.4) + FREQUENT,
        "support_by_class": B + " SELECT pattern, sup, sup_pos, sup - sup_pos AS sup_neg FROM patterns",
        "closed_patterns": base("conv_words", q.CLOSED_PART, q.CLOSED_LONGEST) + " SELECT pattern, sup FROM patterns p WHERE NOT EXISTS (SELECT 1 FROM patterns q WHERE q.len = p.len + 1 AND q.sup = p.sup AND list_has_all(q.items, p.items))",
        "topk_by_support": B + " SELECT pattern, sup FROM patterns WHERE len >= 2 ORDER BY sup DESC, pattern LIMIT 25",
        "constrained_patterns": B + " SELECT pattern, sup FROM patterns WHERE list_contains(items, 3) AND len >= 2",
        "association_rules": B + ", split AS (SELECT sup, unnest(items) AS rhs, items FROM patterns WHERE len > 1), named AS (SELECT sup, rhs, array_to_string(list_filter(items, lambda i: i <> rhs), ',') AS lhs FROM split) SELECT lhs, rhs, s.sup, round(s.sup / l.sup, 6) AS confidence, round(s.sup / l.sup * n / r.sup, 6) AS lift FROM named s JOIN patterns l ON l.pattern = s.lhs JOIN patterns r ON r.pattern = CAST(s.rhs AS VARCHAR) CROSS JOIN n WHERE s.sup / l.sup >= 0.5",
        "lazy_cell": B + xors(4, 1) + CELL + " SELECT p.pattern, sup FROM cells c JOIN patterns p ON p.pattern = c.pattern",
        "q_frequency": B + " SELECT pattern, round(sup / n, 6) AS phi FROM patterns CROSS JOIN n",
        "q_surprisingness": SURPRISE + " SELECT pattern, round(phi, 6) AS phi FROM quality",
        "q_chi2": B + " SELECT pattern, round(CASE WHEN sup = n THEN 0.0 ELSE n::DOUBLE * ((sup_pos * (n - n_pos - sup + sup_pos))::DOUBLE - ((sup - sup_pos) * (n_pos - sup_pos))::DOUBLE) ** 2 / (sup::DOUBLE * (n - sup) * n_pos * (n - n_pos)) END, 6) AS phi FROM patterns CROSS JOIN n",
        "q_chi2_literal": B + " SELECT pattern, round((sup_pos - n_pos) ** 2 / n_pos::DOUBLE + (sup - sup_pos - (n - n_pos)) ** 2 / (n - n_pos)::DOUBLE, 6) AS phi FROM patterns CROSS JOIN n",
        "percentile_rank": B + " SELECT pattern, round(cume_dist() OVER (ORDER BY sup), 6) AS pct FROM patterns",
        "quality_boxplot": SURPRISE + " SELECT round(min(phi), 6) AS least, round(quantile_cont(phi, 0.25), 6) AS \"lower\", round(quantile_cont(phi, 0.5), 6) AS median, round(quantile_cont(phi, 0.75), 6) AS \"upper\", round(max(phi), 6) AS most FROM quality",
        "feat_ilf": B + " SELECT pattern, i AS feature_id, 1.0::DOUBLE AS value FROM exploded UNION ALL SELECT pattern, CAST((SELECT count(*) FROM dict) AS INT), round(len / (SELECT count(*) FROM dict), 6) FROM patterns UNION ALL SELECT pattern, CAST((SELECT count(*) FROM dict) + 1 AS INT), round(sup / (SELECT n FROM n), 6) FROM patterns",
        "feat_transactions": B + TOP5.format(">= 2", 5) + " SELECT p.pattern, t.tid FROM top5 p JOIN (SELECT tid, list(i) AS l FROM tx GROUP BY tid) t ON list_has_all(t.l, p.items)",
        "score_fixed_weights": WEIGHTED + " SELECT pattern, round(score, 9) AS score FROM scored",
        "logistic_quality": WEIGHTED + " SELECT pattern, round(w, 6) AS w FROM weighted",
        "pairs_from_rankings": B + FEEDBACK + " SELECT iter, winner, loser FROM pairs",
        "pair_deltas": B + FEEDBACK + " SELECT iter, winner, loser, feature_id, sum(v)::DOUBLE AS delta FROM (SELECT p.*, e.i AS feature_id, 1 AS v FROM pairs p JOIN exploded e ON e.pattern = winner UNION ALL SELECT p.*, e.i, -1 FROM pairs p JOIN exploded e ON e.pattern = loser) GROUP BY ALL HAVING sum(v) <> 0",
        "discordant_pairs": WEIGHTED + FEEDBACK + " SELECT 's' AS session_id, count(*) AS pairs, count(*) FILTER (round(a.score, 9) <= round(b.score, 9)) AS discordant FROM pairs p JOIN scored a ON a.pattern = winner JOIN scored b ON b.pattern = loser",
        "user_effort": B + FEEDBACK + " SELECT count(*) AS shown, count(DISTINCT pattern) AS distinct_shown, CAST((SELECT sum(k * (k - 1) // 2) FROM (SELECT count(*) AS k FROM feedback GROUP BY iter)) AS BIGINT) AS pairs FROM feedback",
        "xor_draws": B + xors(4, 3) + " " + XOR_ROWS,
        "udtf_xor_draws": B + xors(4, 3) + " " + XOR_ROWS,
        "xor_cell_members": B + xors(4, 3) + CELL + " SELECT draw_id, pattern FROM cells",
        "xor_cell_sizes": B + xors(4, 1) + CELL + " SELECT cell_id, count(*) AS size FROM (SELECT pattern, CAST(sum(own * (1 << (3 - x))) AS BIGINT) AS cell_id FROM met GROUP BY pattern) GROUP BY cell_id",
        "nested_cells": CELLS + ", prefixes AS (SELECT m.draw_id, m.pattern, coalesce(min(m.x) FILTER (m.own <> q.parity), 4) AS matched FROM met m JOIN parities q ON q.draw_id = m.draw_id AND q.x = m.x GROUP BY ALL) SELECT draw_id, CAST(u.m AS INT) AS m, round(sum(w), 6) AS weight, count(*) AS size FROM prefixes JOIN weighted USING (pattern), range(5) AS u(m) WHERE u.m <= matched GROUP BY ALL",
        "cell_top1": CELLS + " SELECT draw_id, pattern FROM cells JOIN weighted USING (pattern) QUALIFY row_number() OVER (PARTITION BY draw_id ORDER BY round(w, 9) DESC, pattern) <= 1",
        "cell_top3": CELLS + " SELECT draw_id, pattern FROM cells JOIN weighted USING (pattern) QUALIFY row_number() OVER (PARTITION BY draw_id ORDER BY round(w, 9) DESC, pattern) <= 3",
        "cell_random": CELLS + f" SELECT draw_id, pattern FROM cells JOIN weighted USING (pattern) QUALIFY row_number() OVER (PARTITION BY draw_id ORDER BY -ln({U01.format("'5|' || draw_id || '|' || pattern")}) / w, pattern) = 1",
        "within_cell_prob": CELLS + " SELECT draw_id, pattern, round(w / sum(w) OVER (PARTITION BY draw_id), 6) AS prob FROM cells JOIN weighted USING (pattern)",
        "xor_count_estimate": WEIGHTED + ", t AS (SELECT sum(w) AS total, max(w) AS w_max FROM weighted) SELECT round(total, 6) AS total, round(w_max, 6) AS w_max, CAST(greatest(0, floor(log2(total / w_max / 18) + log2(1.8)) - 3) AS INT) AS first_m, CAST(greatest(1, ceil(log2(total / w_max / 18) + log2(1.8)) + 4) AS INT) AS last_m FROM t",
        "uniform_pool": B + f" SELECT pattern FROM patterns ORDER BY -ln({U01.format("'3|race|' || pattern")}), pattern LIMIT 50",
        "ideal_sampler": B + f" SELECT CAST(d.d AS INT) AS draw_id, pattern FROM patterns, range(20) AS d(d) QUALIFY row_number() OVER (PARTITION BY d.d ORDER BY -ln({U01.format("'3|' || d.d || '|' || pattern")}) / sup, pattern) = 1",
        "multiplicative_round1": B + f" SELECT arg_max(p.pattern, s - ln(-ln({U01.format("'3|gumbel|' || p.pattern")} - 1e-12))) AS pattern FROM patterns p JOIN (SELECT pattern, sum((i % 7 - 3) / 10.0) AS s FROM exploded GROUP BY pattern) l ON l.pattern = p.pattern",
        "source_ranking": B + f", pool AS (SELECT * FROM patterns ORDER BY -ln({U01.format("'3|race|' || pattern")}), pattern LIMIT 100) SELECT pattern, CAST(row_number() OVER (ORDER BY sup DESC, pattern) AS INT) AS source_rank FROM pool",
        "joint_entropy_fixed": B + TOP5.format("= 2", 5) + ", signed AS (SELECT t.tid, string_agg(CASE WHEN list_has_all(t.l, p.items) THEN '1' ELSE '0' END, '' ORDER BY p.pattern) AS s FROM (SELECT tid, list(i) FILTER (i IS NOT NULL) AS l FROM (SELECT DISTINCT tid FROM long) LEFT JOIN tx USING (tid) GROUP BY tid) t CROSS JOIN top5 p GROUP BY t.tid), counts AS (SELECT s, count(*) / (SELECT n FROM n) AS q FROM signed GROUP BY s) SELECT CAST(5 AS INT) AS k, round(-sum(q * log2(q)), 6) AS entropy FROM counts",
        "session_quality": samplers + " SELECT session_id, CAST(iter AS INT) AS iter, round(avg_quality, 6) AS avg_quality, round(max_quality, 6) AS max_quality, round(entropy, 6) AS entropy, round(entropy_share, 6) AS entropy_share FROM measured",
        "cumulative_regret": samplers + " SELECT session_id, measure, CAST(iter AS INT) AS iter, round(1 - value, 6) AS regret, round(sum(1 - value) OVER (PARTITION BY session_id, measure ORDER BY iter), 6) AS cumulative FROM (" + " UNION ALL ".join(f"SELECT session_id, iter, '{m}' AS measure, {m} AS value FROM measured" for m in MEASURES.values()) + ")",
        "regret_grouping_sets": samplers + ", parts AS (SELECT string_split(session_id, '/') AS s, * FROM measured), r AS MATERIALIZED (SELECT s[1] AS method, s[2] AS phi, s[3] AS k, s[4] AS seed, sum(entropy) AS entropy_bits, " + ", ".join(f"sum(1 - {c}) AS {m}_regret" for m, c in MEASURES.items()) + " FROM parts GROUP BY ALL) " + " UNION ALL ".join(f"SELECT '{f}' AS factor, {f} AS level, {STATS} FROM r GROUP BY {f}" for f in ("method", "phi", "k")),
        "jaccard_top": B + ", top10 AS (SELECT * FROM patterns ORDER BY sup DESC, pattern LIMIT 10), j AS (SELECT len(list_intersect(x.items, y.items)) / (x.len + y.len - len(list_intersect(x.items, y.items))) AS j FROM top10 x JOIN top10 y ON x.pattern < y.pattern) SELECT round(avg(j), 6) AS mean, round(min(j)::DOUBLE, 6) AS least, round(max(j)::DOUBLE, 6) AS most FROM j",
        "pca_gram": B + " SELECT x.i AS i, y.i AS j, count(*) AS n FROM exploded x JOIN exploded y ON x.pattern = y.pattern AND x.i <= y.i GROUP BY ALL",
        "agreement": WEIGHTED + ", v AS (SELECT round(w, 9) AS w, sup FROM weighted), ranks AS (SELECT w, sup, rank() OVER (ORDER BY w) + (count(*) OVER (PARTITION BY w) - 1) / 2.0 AS rw, rank() OVER (ORDER BY sup) + (count(*) OVER (PARTITION BY sup) - 1) / 2.0 AS rs FROM v) SELECT round(corr(w, sup), 6) AS pearson, round(corr(rw, rs), 6) AS spearman FROM ranks",
        "stream_user_slots": "SELECT user_id, event_type || '/' || (day(ts) // 4) AS item, count(*) AS events FROM events GROUP BY ALL",
        "asof_weights": "SELECT b.event_id, b.user_id, v.seen_id FROM (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase') b ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS seen_id FROM events WHERE event_type = 'view' GROUP BY user_id, ts) v ON b.user_id = v.user_id AND b.ts >= v.ts",
        "range_bins": "SELECT bin, count(*) AS n FROM lineitem JOIN (VALUES ('low', 0, 10), ('middle', 10, 25), ('high', 25, 1000)) AS e(bin, lo, hi) ON l_quantity >= lo AND l_quantity < hi GROUP BY bin",
        "loop_round1": rounds.session_sql(B, "round1", "frequency", 1),
        "loop_spark_session": rounds.session_sql(B, "emb", "frequency", 3),
        "loop_random_session": rounds.session_sql(B, "random", "chi2", 3, k=3, floor=0.1, parts="I", cell="random"),
        "loop_retention": rounds.session_sql(base(longest=5), "frequency", "frequency", 30, keep=3, parts="ILF"),
        "loop_whole_session": rounds.session_sql(base(longest=5), "frequency", "frequency", 30),
        "loop_chi2_session": rounds.session_sql(base(longest=5), "chi2", "chi2", 30, k=10, floor=0.1, cell="top3", seed=3),
        "scd_weights": rounds.scd_sql(B + FEEDBACK),
        "like_items": rounds.like_items_sql(B),
        "multiplicative_session": rounds.multiplicative_sql(B, q.SAMPLES),
        "mmr_pick": rounds.mmr_sql(B),
        "sample_batch": WEIGHTED.replace("/ (1 + exp(-score)) AS w", "/ (1 + exp(-score)) AS w0").replace("SELECT *, 0.1", "SELECT *, round(w0, 9) AS w FROM (SELECT *, 0.1").replace("AS w0 FROM scored", "AS w0 FROM scored)") + f""", total AS MATERIALIZED (
  SELECT w_max, CAST(greatest(0, floor(g) - 3) AS INT) AS first, CAST(greatest(1, ceil(g) + 4) AS INT) AS last FROM (SELECT max(w) AS w_max, log2(sum(w) / max(w) / 18) + log2(1.8) AS g FROM weighted)
)""" + xors("(SELECT last FROM total)", 8) + CELL + f""", prefixes AS MATERIALIZED (
  SELECT m.draw_id, m.pattern, coalesce(min(m.x) FILTER (m.own <> q.parity), (SELECT last FROM total)) AS matched FROM met m JOIN parities q ON q.draw_id = m.draw_id AND q.x = m.x GROUP BY ALL
), nested AS (
  SELECT draw_id, u.m, sum(w) / any_value(t.w_max) AS weight FROM prefixes JOIN weighted USING (pattern) CROSS JOIN total t, range(t.first, t.last + 1) AS u(m) WHERE u.m <= matched GROUP BY ALL
), accepted AS (
  SELECT draw_id, min(m) AS m FROM nested WHERE weight BETWEEN {rounds.LOW} AND {rounds.HIGH} GROUP BY draw_id
), tops AS (
  SELECT p.draw_id, p.pattern, w FROM prefixes p JOIN accepted a ON a.draw_id = p.draw_id AND p.matched >= a.m JOIN weighted USING (pattern) QUALIFY row_number() OVER (PARTITION BY p.draw_id ORDER BY w DESC, pattern) = 1
) SELECT min(draw_id) AS draw_id, pattern FROM tops GROUP BY pattern ORDER BY min(draw_id), max(w) DESC, pattern LIMIT 4""",
        "predicted_ranking": WEIGHTED + " SELECT pattern, row_number() OVER (ORDER BY -round(score, 9), pattern) AS place FROM scored",
        "session_windows": "WITH t AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events), s AS (SELECT user_id, sum(CAST(before IS NULL OR ts - before >= INTERVAL 1 DAY AS INT)) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM t), c AS (SELECT user_id, s, count(*) AS n FROM s GROUP BY ALL) SELECT user_id, count(*) AS sessions, max(n) AS longest, CAST(sum(n) AS BIGINT) AS events FROM c GROUP BY user_id",
        "json_items": "SELECT 'k' || CAST(floor(CAST(json_extract(props, '$.k') AS INT) / 10) AS INT) AS item, count(DISTINCT user_id) AS support, count(*) AS events FROM events GROUP BY 1",
        "result_sets": B + ", one AS MATERIALIZED (SELECT pattern FROM patterns ORDER BY sup_pos DESC, pattern LIMIT 100), two AS MATERIALIZED (SELECT pattern FROM patterns ORDER BY sup - sup_pos DESC, pattern LIMIT 100) SELECT coalesce(one.pattern, two.pattern) AS pattern, CASE WHEN two.pattern IS NULL THEN 'positive' WHEN one.pattern IS NULL THEN 'negative' ELSE 'both' END AS kind FROM one FULL JOIN two ON one.pattern = two.pattern",
        "pattern_rollup": B + " SELECT len, tens, count(*) AS n, max(sup) AS most FROM (SELECT len, CAST(floor(sup / 10) AS BIGINT) AS tens, sup FROM patterns) GROUP BY ROLLUP (len, tens)",
        "pattern_cube": B + " SELECT len, leans, count(*) AS n, CAST(sum(sup) AS BIGINT) AS covered FROM (SELECT len, sup_pos * 2 > sup AS leans, sup FROM patterns) GROUP BY CUBE (len, leans)",
        "distinct_shown": samplers + " SELECT count(DISTINCT pattern) AS n, true AS close FROM shown",
        "weight_map": B + " SELECT pattern, round(sum((i * 37 % 11 - 5) / 10.0), 6) AS score FROM exploded GROUP BY pattern",
        "match_unseen": base("doc_words", 0.25, 4) + f", unseen AS (SELECT item_id AS tid, list(d.i) AS l FROM (SELECT item_id, unnest({WORDS.format('text')}) AS item FROM benchmark) u JOIN dict d ON d.item = u.item GROUP BY item_id) SELECT u.tid, p.pattern FROM patterns p JOIN unseen u ON list_has_all(u.l, p.items) WHERE p.len >= 2",
        "unseen_patterns": B + FEEDBACK + " SELECT pattern FROM patterns WHERE pattern NOT IN (SELECT pattern FROM feedback)",
    }
    return out
