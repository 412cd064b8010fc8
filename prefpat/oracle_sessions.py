"""DuckDB SQL of whole rounds of the loop and of its baselines' sessions.

Written from the methods' definitions and not from the Python code, so that the two
check each other: cells, their acceptance, picks, rankings, difference vectors, the
descent's updates and the next weights are all relations here.
"""

from __future__ import annotations

from prefpat.oracles import U01, U32

#: Bounds of accepted cells at a tolerance of 0.9, in units of the largest weight.
PIVOT, KAPPA = 18, 0.9
LOW, HIGH = PIVOT / (1 + KAPPA), 1 + (1 + KAPPA) * PIVOT
PHI = {
    "frequency": "sup / n",
    "chi2": "CASE WHEN sup = n THEN 0.0 ELSE n::DOUBLE * ((sup_pos * (n - n_pos - sup + sup_pos))::DOUBLE - ((sup - sup_pos) * (n_pos - sup_pos))::DOUBLE) ** 2 / (sup::DOUBLE * (n - sup) * n_pos * (n - n_pos)) END",
}


def prelude(phi: str) -> str:
    """Masks, hidden quality and percentile of patterns; masks and numbers of transactions."""
    return f""", graded AS MATERIALIZED (
  SELECT p.*, {PHI[phi]} AS phi, list_sum(list_transform(items, lambda i: 1::UBIGINT << i::UBIGINT))::UBIGINT AS mask FROM patterns p CROSS JOIN n
), ranked AS MATERIALIZED (
  SELECT *, cume_dist() OVER (ORDER BY phi) AS pct FROM graded
), rows_ AS MATERIALIZED (
  SELECT row_number() OVER (ORDER BY tid) - 1 AS row, coalesce(sum(1::UBIGINT << i::UBIGINT), 0)::UBIGINT AS mask FROM (SELECT DISTINCT tid FROM long) LEFT JOIN tx USING (tid) GROUP BY tid
), size_ AS MATERIALIZED (
  SELECT count(*) AS m, (SELECT n FROM n) AS n FROM dict
)"""


def descent(r: str, deltas: str, seed: str, width: str, updates: int = 1000, lam: float = 1e-3) -> str:
    """CTEs ``fit{r}(j, w)``: the weights after all updates. ``deltas`` is a relation
    ``(j, pair, d)`` with a row for each drawn coordinate and pair."""
    return f""", drawn{r} AS MATERIALIZED (
  SELECT t.t, {U32.format(f"'{seed}|scd|' || t.t")} % {width} AS j FROM range({updates}) AS t(t)
), used{r} AS MATERIALIZED (
  SELECT j, row_number() OVER (ORDER BY j) AS k FROM (SELECT DISTINCT j FROM drawn{r})
), cols{r} AS MATERIALIZED (
  SELECT j, list(d::DOUBLE ORDER BY pair) AS d, max(d * d) / 4 AS beta, count(*) AS n FROM {deltas} GROUP BY j
), plan{r} AS MATERIALIZED (
  SELECT t, k, d, beta, n FROM drawn{r} JOIN used{r} USING (j) JOIN cols{r} USING (j)
), state{r} AS (
  SELECT 0 AS t, list_transform(range((SELECT count(*) FROM used{r})), lambda x: 0.0::DOUBLE) AS w, list_transform(range((SELECT max(n) FROM cols{r})), lambda x: 0.0::DOUBLE) AS z
  UNION ALL
  SELECT t + 1, CASE WHEN beta = 0 THEN w ELSE list_concat(list_concat(w[:k - 1], [new]), w[k + 1:]) END,
         CASE WHEN beta = 0 THEN z ELSE list_transform(z, lambda x, i: x + d[i] * (new - w[k])) END
  FROM (
    SELECT *, sign(moved) * greatest(abs(moved) - {lam} / beta, 0) AS new FROM (
      SELECT s.t, s.w, s.z, p.k, p.d, p.beta, s.w[p.k] + list_sum(list_transform(s.z, lambda x, i: p.d[i] / (1 + exp(x)))) / p.n / p.beta AS moved
      FROM state{r} s JOIN plan{r} p ON p.t = s.t
    )
  )
), fit{r} AS MATERIALIZED (
  SELECT u.j, s.w[u.k] AS w FROM used{r} u CROSS JOIN (SELECT w FROM state{r} WHERE t = {updates}) s
)"""


def features_of(r: int, parts: str) -> str:
    """CTE ``deltas{r}``: differences of all pairs so far, for every drawn coordinate."""
    inside = "CAST((p.mask & t.mask) = p.mask AS INT)"
    if parts == "I":
        value = "CAST(p.mask & (1::UBIGINT << j::UBIGINT) > 0 AS INT)"
        return f""", value{r} AS MATERIALIZED (SELECT p.pattern, j, {value} AS v FROM (SELECT DISTINCT pattern, mask FROM seen{r}) p CROSS JOIN used{r} CROSS JOIN size_ z)"""
    item = "CAST(p.mask & (1::UBIGINT << least(j, 63)::UBIGINT) > 0 AS INT)"
    value = f"CASE WHEN j < z.m THEN {item} WHEN j = z.m THEN p.len / z.m WHEN j = z.m + 1 THEN p.sup / z.n ELSE {inside} END"
    return f""", value{r} AS MATERIALIZED (SELECT p.pattern, j, {value} AS v FROM (SELECT DISTINCT pattern, mask, len, sup FROM seen{r}) p CROSS JOIN used{r} CROSS JOIN size_ z LEFT JOIN rows_ t ON t.row = j - z.m - 2)"""


def session_sql(base: str, name: str, phi: str, rounds: int, k: int = 5, keep: int = 1, floor: float = 0.5, parts: str = "ILFT", cell: str = "top1", seed: int = 0) -> str:
    """Rows of a session of the loop, round by round. Cells of the first attempt have to
    suffice for a query, which the tests check."""
    out = base + prelude(phi)
    for r in range(1, rounds + 1):
        if r == 1:
            out += f", weighted1 AS MATERIALIZED (SELECT *, {floor + (1 - floor) / 2}::DOUBLE AS w FROM ranked), kept1 AS (SELECT NULL::VARCHAR AS pattern, NULL::DOUBLE AS w WHERE false)"
        else:
            transactions = "" if parts == "I" else f" + f.freq * p.sup / z.n + f.length * p.len / z.m + coalesce(t.s, 0)"
            out += f""", flat{r} AS MATERIALIZED (
  SELECT list(coalesce(f.w, 0.0) ORDER BY i.i) AS items, coalesce((SELECT w FROM fit{r - 1} WHERE j = (SELECT m FROM size_)), 0) AS length, coalesce((SELECT w FROM fit{r - 1} WHERE j = (SELECT m + 1 FROM size_)), 0) AS freq
  FROM range((SELECT m FROM size_)) AS i(i) LEFT JOIN fit{r - 1} f ON f.j = i.i
), heavy{r} AS MATERIALIZED (
  SELECT t.mask, f.w FROM fit{r - 1} f CROSS JOIN size_ z JOIN rows_ t ON t.row = f.j - z.m - 2 WHERE f.w <> 0
), inside{r} AS MATERIALIZED (
  SELECT p.pattern, sum(h.w) AS s FROM ranked p JOIN heavy{r} h ON (p.mask & h.mask) = p.mask GROUP BY p.pattern
), weighted{r} AS MATERIALIZED (
  SELECT p.*, {floor} + {1 - floor} / (1 + exp(-(list_sum(list_transform(p.items, lambda i: f.items[i + 1])){transactions}))) AS w
  FROM ranked p CROSS JOIN flat{r} f CROSS JOIN size_ z LEFT JOIN inside{r} t ON t.pattern = p.pattern
), kept{r} AS MATERIALIZED (
  SELECT pattern, w FROM order{r - 1} WHERE pos <= {keep}
)"""
        need = k if r == 1 else k - keep
        top = 1 if cell == "random" else int(cell[3:])
        draws, key = 2 * -(-need // top), f"{seed}/round{r}/0"
        best = f"-ln({U01.format(f"'{key}/' || c.draw_id || '|' || c.pattern")}) / c.w, c.pattern" if cell == "random" else "round(c.w, 9) DESC, c.pattern"
        out += f""", total{r} AS MATERIALIZED (
  SELECT total, w_max, CASE WHEN total / w_max <= {HIGH} THEN 0 ELSE greatest(0, floor(guess) - 3) END::INT AS first, CASE WHEN total / w_max <= {HIGH} THEN 0 ELSE greatest(1, ceil(guess) + 4) END::INT AS last
  FROM (SELECT *, log2(total / w_max / {PIVOT}) + log2(1.8) AS guess FROM (SELECT sum(w) AS total, max(w) AS w_max FROM weighted{r}))
), bits{r} AS MATERIALIZED (
  SELECT d.d, x.x, sum(CASE WHEN {U32.format(f"'{key}|' || d.d || '|' || x.x || '|' || i.i")} % 2 = 1 THEN 1::UBIGINT << i.i::UBIGINT ELSE 0 END)::UBIGINT AS c, any_value({U32.format(f"'{key}|' || d.d || '|' || x.x || '|parity'")} % 2) AS parity
  FROM range({draws}) AS d(d), range((SELECT last FROM total{r})) AS x(x), range((SELECT m FROM size_)) AS i(i) GROUP BY d.d, x.x
), met{r} AS MATERIALIZED (
  SELECT b.d AS draw_id, p.pattern, p.w, coalesce(min(b.x) FILTER (bit_count(p.mask & b.c) % 2 <> b.parity), (SELECT last FROM total{r})) AS matched FROM weighted{r} p CROSS JOIN bits{r} b GROUP BY b.d, p.pattern, p.w
), nested{r} AS MATERIALIZED (
  SELECT d.d AS draw_id, m.m, coalesce(sum(c.w), 0) / any_value(t.w_max) AS weight FROM range({draws}) AS d(d) CROSS JOIN total{r} t, range(t.first, t.last + 1) AS m(m) LEFT JOIN met{r} c ON c.draw_id = d.d AND c.matched >= m.m GROUP BY d.d, m.m
), accepted{r} AS MATERIALIZED (
  SELECT draw_id, m FROM nested{r} WHERE weight <= {HIGH} QUALIFY row_number() OVER (PARTITION BY draw_id ORDER BY m) = 1 AND weight >= {LOW}
), chosen{r} AS MATERIALIZED (
  SELECT c.draw_id, c.pattern, c.w, row_number() OVER (PARTITION BY c.draw_id ORDER BY {best}) AS place FROM met{r} c JOIN accepted{r} a ON a.draw_id = c.draw_id AND c.matched >= a.m QUALIFY place <= {top}
), picked{r} AS MATERIALIZED (
  SELECT pattern, any_value(w) AS w, min(draw_id * 100 + place) AS spot FROM chosen{r} WHERE pattern NOT IN (SELECT pattern FROM kept{r} WHERE pattern IS NOT NULL) GROUP BY pattern ORDER BY spot LIMIT {need}
), order{r} AS MATERIALIZED (
  SELECT {r} AS iter, row_number() OVER (ORDER BY p.phi DESC, p.pattern) AS pos, p.pattern, q.origin, p.phi, q.w, p.pct, p.mask, p.len, p.sup
  FROM (SELECT pattern, w, 'retained' AS origin FROM kept{r} UNION ALL SELECT pattern, w, 'sampled' FROM picked{r}) q JOIN ranked p ON p.pattern = q.pattern
)"""
        if r < rounds:
            seen = " UNION ALL ".join(f"SELECT * FROM order{i}" for i in range(1, r + 1))
            width = {"I": "(SELECT m FROM size_)", "ILF": "(SELECT m + 2 FROM size_)", "ILFT": "(SELECT m + 2 + n FROM size_)"}[parts]
            before, after = descent(str(r), f"deltas{r}", f"{seed}/{r}", width).split(f", cols{r} AS", 1)
            out += f""", seen{r} AS MATERIALIZED (
  {seen}
), pairs{r} AS MATERIALIZED (
  SELECT row_number() OVER (ORDER BY a.iter, a.pos, b.pos) AS pair, a.pattern AS winner, b.pattern AS loser FROM seen{r} a JOIN seen{r} b ON a.iter = b.iter AND a.pos < b.pos AND a.phi <> b.phi
)""" + before + features_of(r, parts) + f""", deltas{r} AS MATERIALIZED (
  SELECT a.j, q.pair, a.v - b.v AS d FROM pairs{r} q JOIN value{r} a ON a.pattern = q.winner JOIN value{r} b ON b.pattern = q.loser AND b.j = a.j
), cols{r} AS""" + after
    rows = " UNION ALL ".join(f"SELECT * FROM order{r}" for r in range(1, rounds + 1))
    return f"{out.replace('WITH ', 'WITH RECURSIVE ', 1)} SELECT '{name}' AS session_id, CAST(iter AS INT) AS iter, CAST(pos AS INT) AS pos, pattern, origin, round(phi, 6) AS level, round(w, 6) AS w, round(phi, 6) AS phi, round(pct, 6) AS pct FROM ({rows})"


def liked(base: str) -> str:
    """CTE ``interesting(i)`` and the liked share: items of the best patterns, one at a
    time, until enough patterns are liked."""
    return base + prelude("frequency") + """, entering AS MATERIALIZED (
  SELECT i, row_number() OVER (ORDER BY place, spot) AS turn FROM (
    SELECT e.i, min(p.place) AS place, arg_min(e.spot, p.place) AS spot FROM (SELECT pattern, row_number() OVER (ORDER BY phi DESC, pattern) AS place FROM ranked) p
    JOIN (SELECT pattern, unnest(items) AS i, unnest(range(len(items))) AS spot FROM patterns) e ON e.pattern = p.pattern GROUP BY e.i)
), grown AS MATERIALIZED (
  SELECT a.turn, sum(1::UBIGINT << b.i::UBIGINT)::UBIGINT AS mask FROM entering a JOIN entering b ON b.turn <= a.turn GROUP BY a.turn
), shares AS MATERIALIZED (
  SELECT g.turn, any_value(g.mask) AS mask, count(*) FILTER (2 * bit_count(p.mask & g.mask) > p.len) / count(*) AS share FROM grown g CROSS JOIN ranked p GROUP BY g.turn
), enough AS MATERIALIZED (
  SELECT * FROM shares WHERE share >= 0.15 ORDER BY turn LIMIT 1
)"""


def like_items_sql(base: str) -> str:
    return liked(base) + " SELECT CAST(i AS INT) AS item_id, round(share, 6) AS liked_share FROM entering e JOIN enough s ON e.turn <= s.turn"


def multiplicative_sql(base: str, samples: int) -> str:
    """Draws one after the other: the first pattern at which the running weight passes a
    share of the whole; a liked one multiplies its items' weights by 1.75, others divide."""
    return (liked(base) + f""", numbers AS MATERIALIZED (
  SELECT s.s, {U01.format("'0|multiplicative|' || s.s")} AS u FROM range({samples}) AS s(s)
), chain AS (
  SELECT -1::BIGINT AS s, NULL::VARCHAR AS pattern, NULL::BOOLEAN AS liked, list_transform(range((SELECT m FROM size_)), lambda x: 0.0::DOUBLE) AS lw
  UNION ALL
  SELECT s, pattern, liked, list_transform(lw, lambda x, i: x + CASE WHEN (mask & (1::UBIGINT << (i - 1)::UBIGINT)) > 0 THEN CASE WHEN liked THEN ln(1.75) ELSE -ln(1.75) END ELSE 0 END)
  FROM (
    SELECT s, arg_min(pattern, pattern) FILTER (reached >= u * whole) AS pattern, arg_min(liked, pattern) FILTER (reached >= u * whole) AS liked, arg_min(mask, pattern) FILTER (reached >= u * whole) AS mask, any_value(lw) AS lw
    FROM (
      SELECT *, sum(e) OVER (ORDER BY pattern) AS reached, sum(e) OVER () AS whole FROM (
        SELECT n.s, n.u, p.pattern, p.mask, c.lw, 2 * bit_count(p.mask & g.mask) > p.len AS liked, exp(list_sum(list_transform(p.items, lambda i: c.lw[i + 1]))) AS e
        FROM chain c JOIN numbers n ON n.s = c.s + 1 CROSS JOIN ranked p CROSS JOIN enough g
      )
    ) GROUP BY s
  )
) SELECT CAST(s AS INT) AS sample, pattern, liked FROM chain WHERE s >= 0""").replace("WITH ", "WITH RECURSIVE ", 1)


def mmr_sql(base: str, size: int = 200, k: int = 5) -> str:
    """Greedy picks, one common table each: relevance against likeness to shown and picked."""
    jaccard = "(bit_count(a.mask & b.mask)::DOUBLE / (a.len + b.len - bit_count(a.mask & b.mask)))"
    out = base + prelude("frequency") + f""", pool AS MATERIALIZED (
  SELECT row_number() OVER (ORDER BY sup DESC, pattern) - 1 AS spot, * FROM ranked ORDER BY sup DESC, pattern LIMIT {size}
), pick0 AS MATERIALIZED (
  SELECT a.spot, a.pattern, a.mask, a.len, 1 - a.spot / (SELECT max(spot) FROM pool)::DOUBLE AS relevance, max({jaccard}) AS shown, 0.0::DOUBLE AS picked, false AS gone FROM pool a JOIN pool b ON b.spot < 2 GROUP BY ALL
)"""
    for i in range(1, k + 1):
        out += f""", best{i} AS MATERIALIZED (
  SELECT * FROM pick{i - 1} WHERE NOT gone ORDER BY 0.7::DOUBLE * relevance - (1 - 0.7::DOUBLE) * ((1 - 0.3::DOUBLE) * picked + 0.3::DOUBLE * shown) DESC, spot LIMIT 1
), pick{i} AS MATERIALIZED (
  SELECT a.spot, a.pattern, a.mask, a.len, a.relevance, a.shown, greatest(a.picked, {jaccard}) AS picked, a.gone OR a.spot = b.spot AS gone FROM pick{i - 1} a CROSS JOIN best{i} b
)"""
    return out + " SELECT * FROM (" + " UNION ALL ".join(f"SELECT CAST({i - 1} AS INT) AS pick, pattern FROM best{i}" for i in range(1, k + 1)) + ")"


def scd_sql(feedback: str) -> str:
    """The fixed feedback's fit; ``feedback`` gives ``pairs`` and ``exploded``."""
    made = """, numbered AS MATERIALIZED (
  SELECT row_number() OVER (ORDER BY iter, winner, loser) AS pair, winner, loser FROM pairs
), sparse AS MATERIALIZED (
  SELECT pair, i AS j, sum(v) AS d FROM (SELECT pair, e.i, 1 AS v FROM numbered JOIN exploded e ON e.pattern = winner UNION ALL SELECT pair, e.i, -1 FROM numbered JOIN exploded e ON e.pattern = loser) GROUP BY ALL
), wide AS MATERIALIZED (
  SELECT max(j) + 1 AS n FROM sparse WHERE d <> 0
), deltas AS MATERIALIZED (
  SELECT j.j, p.pair, coalesce(s.d, 0) AS d FROM range((SELECT n FROM wide)) AS j(j) CROSS JOIN (SELECT DISTINCT pair FROM sparse WHERE d <> 0) p LEFT JOIN sparse s ON s.j = j.j AND s.pair = p.pair
)"""
    return (feedback + made + descent("", "deltas", "fit", "(SELECT n FROM wide)")).replace("WITH ", "WITH RECURSIVE ", 1) + " SELECT CAST(j AS INT) AS feature_id, round(w, 6) AS w FROM fit WHERE w <> 0"


def sampler_sql(base: str) -> str:
    """CTEs up to ``series``: queries of sessions without learning, and their measures."""
    one = "SELECT '{m}/{p}/k' || k.k || '/s' || s.s AS session_id, '{p}' AS phi_name, r.r AS iter, pattern, {v} AS pct FROM g CROSS JOIN (VALUES (5), (10)) AS k(k), range(3) AS s(s), range(1, 6) AS r(r) WHERE {w} > 0 QUALIFY row_number() OVER (PARTITION BY k.k, s.s, r.r ORDER BY -ln({u}) / {w}, pattern) <= k.k"
    parts = [one.format(m=m, p=p, v=f"pct_{p}", w="1.0" if m == "uniform" else f"phi_{p}", u=U01.format(f"'{m}' || s.s || '|' || r.r || '|' || pattern")) for p in PHI for m in ("uniform", "ideal")]
    return base + f""", g AS MATERIALIZED (
  SELECT *, cume_dist() OVER (ORDER BY round(phi_frequency, 9)) AS pct_frequency, cume_dist() OVER (ORDER BY round(phi_chi2, 9)) AS pct_chi2
  FROM (SELECT p.*, {PHI["frequency"]} AS phi_frequency, {PHI["chi2"]} AS phi_chi2 FROM patterns p CROSS JOIN n)
), shown AS MATERIALIZED (
  {" UNION ALL ".join(parts)}
), held AS MATERIALIZED (
  SELECT p.pattern, list(t.tid) AS tids FROM (SELECT DISTINCT pattern FROM shown) s JOIN patterns p ON p.pattern = s.pattern JOIN (SELECT tid, list(i) AS l FROM tx GROUP BY tid) t ON list_has_all(t.l, p.items) GROUP BY p.pattern
), signed AS (
  SELECT session_id, iter, tid, string_agg(s.pattern, ' ' ORDER BY s.pattern) AS s FROM shown s JOIN (SELECT pattern, unnest(tids) AS tid FROM held) h ON h.pattern = s.pattern GROUP BY ALL
), counted AS (
  SELECT session_id, iter, s, count(*) AS c FROM signed GROUP BY ALL
), whole AS (
  SELECT session_id, iter, c FROM counted UNION ALL SELECT session_id, iter, (SELECT n FROM n) - sum(c) FROM counted GROUP BY ALL HAVING sum(c) < (SELECT n FROM n)
), entropies AS (
  SELECT session_id, iter, -sum(c / n.n * log2(c / n.n)) AS entropy FROM whole CROSS JOIN n GROUP BY ALL
), measured AS MATERIALIZED (
  SELECT s.session_id, s.iter, avg(pct) AS avg_quality, max(pct) AS max_quality, any_value(e.entropy) AS entropy, any_value(e.entropy) / count(*) AS entropy_share FROM shown s JOIN entropies e ON e.session_id = s.session_id AND e.iter = s.iter GROUP BY ALL
)"""
