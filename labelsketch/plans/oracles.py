"""SQL for DuckDB that must give the queries' rows; loops are unrolled into chained common table expressions."""

from __future__ import annotations

from ..operators.builders import BUILDERS, LINE_DOCS, TOYS
from ..operators.graph import CHUNK_ROWS, HUB_CHUNKS, HUB_DEGREE
from ..operators.local import mix_sql
from ..operators.propagate import LPConfig, PickLess
from ..operators.selectors import Exact, HeavyHitter, MajorityVote
from .queries import LP_RUNS, SPREAD

WORDS = "list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda w: w <> '')"

LINES = "lines AS (SELECT DISTINCT doc_id, md5(line) AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20)"

#: Common table expressions that end in pairs p(src, dst, weight), and how parallel pairs combine.
PAIRS: dict[str, tuple[str, str]] = {
    "weblink": ("links AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS target FROM pages), keyed AS (SELECT page_id, dense_rank() OVER (ORDER BY encode(target)) - 1 AS k FROM links), p AS (SELECT 2 * page_id AS src, 2 * k + 1 AS dst, 1.0 AS weight FROM keyed)", "sum"),
    "copurchase": ("p AS (SELECT a.l_partkey AS src, b.l_partkey AS dst, count(*) AS weight FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_partkey < b.l_partkey GROUP BY 1, 2)", "sum"),
    "supply": ("p AS (SELECT 2 * l_suppkey AS src, 2 * l_partkey + 1 AS dst, sum(l_quantity) AS weight FROM lineitem GROUP BY 1, 2)", "sum"),
    "trade": ("p AS (SELECT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst, sum(l_quantity) AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2)", "sum"),
    "order_path": ("p AS (SELECT * FROM (SELECT lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS src, o_orderkey AS dst, 1.0 AS weight FROM orders) WHERE src IS NOT NULL)", "sum"),
    "kmer": ("piece AS (SELECT substring(text, b, 268) AS text FROM (SELECT text, unnest(range(1, length(text) - 11, 256)) AS b FROM documents WHERE length(text) > 12)), place AS (SELECT text, unnest(range(1, length(text) - 11)) AS i FROM piece), raw AS (SELECT DISTINCT substring(text, i, 12) AS a, substring(text, i + 1, 12) AS b FROM place), pair AS (SELECT * FROM raw WHERE a <> b), ids AS (SELECT w, row_number() OVER (ORDER BY encode(w)) - 1 AS k FROM (SELECT a AS w FROM pair UNION SELECT b FROM pair)), p AS (SELECT x.k AS src, y.k AS dst, 1.0 AS weight FROM pair JOIN ids x ON x.w = a JOIN ids y ON y.w = b)", "max"),
    "bigram": (f"cut AS (SELECT {WORDS} AS w FROM documents), place AS (SELECT w, unnest(range(1, len(w))) AS i FROM cut), pair AS (SELECT w[i] AS a, w[i + 1] AS b, count(*) AS n FROM place WHERE w[i] <> w[i + 1] GROUP BY 1, 2), ids AS (SELECT w, row_number() OVER (ORDER BY encode(w)) - 1 AS k FROM (SELECT a AS w FROM pair UNION SELECT b FROM pair)), p AS (SELECT x.k AS src, y.k AS dst, n AS weight FROM pair JOIN ids x ON x.w = a JOIN ids y ON y.w = b)", "sum"),
    "docword": (f"pair AS (SELECT DISTINCT doc_id, unnest({WORDS}) AS word FROM documents), p AS (SELECT 2 * doc_id AS src, 2 * (dense_rank() OVER (ORDER BY encode(word)) - 1) + 1 AS dst, 1.0 AS weight FROM pair)", "sum"),
    "shared_line": (f"{LINES}, counted AS (SELECT *, count(*) OVER (PARTITION BY line) AS n, min(doc_id) OVER (PARTITION BY line) AS least FROM lines), p AS (SELECT src, dst, count(*) AS weight FROM (SELECT x.doc_id AS src, y.doc_id AS dst FROM counted x JOIN counted y USING (line) WHERE x.n <= {LINE_DOCS} AND x.doc_id < y.doc_id UNION ALL SELECT least, doc_id FROM counted WHERE n > {LINE_DOCS} AND least <> doc_id) GROUP BY 1, 2)", "sum"),
    "shared_line_star": (f"{LINES}, p AS (SELECT src, doc_id AS dst, count(*) AS weight FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY line) AS src FROM lines) WHERE src <> doc_id GROUP BY 1, 2)", "sum"),
    "knn": ("v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE embedding IS NOT NULL), unit AS (SELECT vec_id, list_transform(e, lambda y: y / greatest(sqrt(list_sum(list_transform(e, lambda z: z * z))), 1e-12)) AS u FROM v), near AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(1e6 * (1 + list_dot_product(a.u, b.u))) AS weight FROM unit a JOIN unit b ON a.vec_id <> b.vec_id), p AS (SELECT src, dst, weight FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst) AS r FROM near) WHERE r <= 5)", "max"),
    "user_activity": ("act AS (SELECT user_id, strftime(ts, '%Y-%m-%d') || '|' || event_type AS slot, sum(CAST(round(value * 100) AS BIGINT)) AS w FROM events GROUP BY 1, 2 HAVING sum(CAST(round(value * 100) AS BIGINT)) > 0), p AS (SELECT 2 * user_id AS src, 2 * (dense_rank() OVER (ORDER BY encode(slot)) - 1) + 1 AS dst, w AS weight FROM act)", "sum"),
    "turn_path": ("turns AS (SELECT DISTINCT conv_id, turn FROM conversations), p AS (SELECT * FROM (SELECT conv_id * 1048576 + turn AS src, conv_id * 1048576 + lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst, 1.0 AS weight FROM turns) WHERE dst IS NOT NULL)", "sum"),
}


def edges(name: str) -> str:
    """Common table expressions that end in edges(src, dst, weight)."""
    ctes, how = PAIRS[name]
    return f"{ctes}, one AS (SELECT least(src, dst) AS a, greatest(src, dst) AS b, CAST({how}(weight) AS DOUBLE) AS w FROM p GROUP BY 1, 2), edges AS MATERIALIZED (SELECT CAST(a AS BIGINT) AS src, CAST(b AS BIGINT) AS dst, w AS weight FROM one UNION ALL SELECT CAST(b AS BIGINT), CAST(a AS BIGINT), w FROM one WHERE a <> b)"


PREPARED = f"prep AS MATERIALIZED (SELECT dst, src, weight, ord, CASE WHEN deg >= {HUB_DEGREE} THEN ord % greatest({HUB_CHUNKS}, CAST(ceil(deg / {CHUNK_ROWS}.0) AS BIGINT)) ELSE 0 END AS chunk FROM (SELECT dst, src, weight, row_number() OVER (PARTITION BY dst ORDER BY src) - 1 AS ord, count(*) OVER (PARTITION BY dst) AS deg FROM edges WHERE src <> dst))"


def mg(pairs: str, k: int, overflow: str) -> str:
    """Ordered fold of a list of {l, w} into at most k slots."""
    low = lambda by, keep: f"list_filter(list_transform(a, lambda e: {{'l': e.l, 'w': e.w - {by}}}), lambda e: e.w {keep})"
    if overflow == "residual":
        by = "least(x[1].w, list_min(list_transform(a, lambda e: e.w)))"
        full = f"list_concat({low(by, '> 0')}, list_filter([{{'l': x[1].l, 'w': x[1].w - {by}}}], lambda e: e.w > 0))"
    else:
        full = low("x[1].w", "> 0" if overflow == "floor" else "<> 0")
    added = "list_transform(a, lambda e: {'l': e.l, 'w': CASE WHEN e.l = x[1].l THEN e.w + x[1].w ELSE e.w END})"
    if overflow == "as_described":
        added = f"list_filter({added}, lambda e: e.w <> 0)"
    return f"list_reduce(list_transform({pairs}, lambda q: [q]), lambda a, x: CASE WHEN list_contains(list_transform(a, lambda e: e.l), x[1].l) THEN {added} WHEN len(a) < {k} THEN list_append(a, x[1]) ELSE {full} END)"


def vote(pairs: str, rule: str) -> str:
    taken = "x.w" if rule == "replace" else "x.w - a.w"
    return f"list_reduce({pairs}, lambda a, x: CASE WHEN a.l = x.l AND a.w > 0 THEN {{'l': a.l, 'w': a.w + x.w}} WHEN a.w > x.w THEN {{'l': a.l, 'w': a.w - x.w}} ELSE {{'l': x.l, 'w': {taken}}} END)"


LISTED = "list({'l': label, 'w': weight} ORDER BY ord)"


def best(rows: str, weight: str = "weight") -> str:
    """id, candidate of rows dst, label, weight."""
    return f"SELECT dst AS id, label AS candidate FROM (SELECT dst, label, row_number() OVER (PARTITION BY dst ORDER BY {weight} DESC, label) AS r FROM ({rows})) WHERE r = 1"


def sketches(selector: HeavyHitter, pairs: str, t: str) -> str:
    """Common table expressions partial{t}(dst, chunk, s) and, merged, slots{t}(dst, label, weight)."""
    chunk = "0" if selector.consolidation == "shared" else "chunk"
    ctes = f"partial{t} AS MATERIALIZED (SELECT dst, c AS chunk, {mg('l', selector.k, selector.overflow)} AS s FROM (SELECT dst, {chunk} AS c, {LISTED} AS l FROM {pairs} GROUP BY 1, 2))"
    if selector.merge == "replay":
        ctes += f", whole{t} AS (SELECT dst, CASE WHEN n = 1 THEN f[1] WHEN len(flatten(f)) = 0 THEN [] ELSE {mg('flatten(f)', selector.k, selector.overflow)} END AS s FROM (SELECT dst, count(*) AS n, list(s ORDER BY chunk) AS f FROM partial{t} GROUP BY 1)), slots{t} AS MATERIALIZED (SELECT dst, u.l AS label, u.w AS weight FROM (SELECT dst, unnest(s) AS u FROM whole{t}))"
    else:
        ctes += f", sums{t} AS (SELECT dst, u.l AS label, sum(u.w) AS weight FROM (SELECT dst, unnest(s) AS u FROM partial{t}) GROUP BY 1, 2), ranked{t} AS (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY weight DESC, label) AS r FROM sums{t}), slots{t} AS MATERIALIZED (SELECT dst, label, weight - cut AS weight FROM (SELECT *, coalesce(max(CASE WHEN r = {selector.k + 1} THEN weight END) OVER (PARTITION BY dst), 0) AS cut FROM ranked{t}) WHERE weight > cut)"
    return ctes


def candidates(selector, pairs: str, t: str) -> str:
    """Common table expressions that end in cand{t}(id, candidate)."""
    sums = f"SELECT dst, label, sum(weight) AS weight FROM {pairs} GROUP BY 1, 2"
    if isinstance(selector, Exact):
        return f"cand{t} AS ({best(sums)})"
    if isinstance(selector, HeavyHitter):
        ctes = sketches(selector, pairs, t)
        if selector.scan == "single":
            return f"{ctes}, cand{t} AS ({best(f'SELECT * FROM slots{t} WHERE weight > 0')})"
        return f"{ctes}, cand{t} AS ({best(f'SELECT dst, label, sum(weight) AS weight FROM {pairs} SEMI JOIN slots{t} USING (dst, label) GROUP BY 1, 2')})"
    states = f"SELECT dst, v.l AS label, v.w AS weight FROM (SELECT dst, {vote('l', selector.rule)} AS v FROM (SELECT dst, chunk, {LISTED} AS l FROM {pairs} GROUP BY 1, 2)) WHERE v.w > 0"
    if selector.combine == "max":
        return f"cand{t} AS ({best(states)})"
    return f"cand{t} AS ({best(f'SELECT dst, label, rest AS weight FROM (SELECT dst, label, 2 * weight - sum(weight) OVER (PARTITION BY dst) AS rest FROM (SELECT dst, label, sum(weight) AS weight FROM ({states}) GROUP BY 1, 2)) WHERE rest >= 0')})"


def unrolled(name: str, config: LPConfig, last: int | None = None) -> tuple[str, str]:
    """(common table expressions, name of the labels table) of a run's iterations."""
    ctes = f"{edges(name)}, {PREPARED}, labels0 AS MATERIALIZED (SELECT DISTINCT dst AS id, dst AS label FROM edges)"
    now, n, b = "labels0", 0, config.schedule.batches
    for t in range(last or config.stop.max_iterations):
        for j in range(b):
            n += 1
            own = f" WHERE {mix_sql('dst', b)} = {j}" if b > 1 else ""
            ctes += f", pairs{n} AS MATERIALIZED (SELECT dst, chunk, ord, label, weight FROM prep JOIN {now} ON src = id{own}), {candidates(config.selector, f'pairs{n}', str(n))}"
            rule = "candidate < label" if config.pick_less.applies(t) else "candidate <> label"
            ctes += f", labels{n} AS MATERIALIZED (SELECT id, CASE WHEN {rule} THEN candidate ELSE label END AS label FROM {now} LEFT JOIN cand{n} USING (id))"
            now = f"labels{n}"
    return ctes, now


def stopped(name: str, config: LPConfig) -> str:
    """The labels of a run with its stop rule: iterations after the stop change nothing."""
    tau = config.stop.tolerance
    ctes = f"{edges(name)}, {PREPARED}, labels0 AS MATERIALIZED (SELECT DISTINCT dst AS id, dst AS label FROM edges), stop0 AS (SELECT false AS done)"
    for t in range(config.stop.max_iterations):
        n, less = t + 1, config.pick_less.applies(t)
        rule = "candidate < label" if less else "candidate <> label"
        ctes += f", pairs{n} AS MATERIALIZED (SELECT dst, chunk, ord, label, weight FROM prep JOIN labels{t} ON src = id WHERE NOT (SELECT done FROM stop{t})), {candidates(config.selector, f'pairs{n}', str(n))}"
        ctes += f", moved{n} AS MATERIALIZED (SELECT id, CASE WHEN {rule} THEN candidate ELSE label END AS label, coalesce({rule}, false) AS moved FROM labels{t} LEFT JOIN cand{n} USING (id)), labels{n} AS MATERIALIZED (SELECT id, label FROM moved{n})"
        ends = "false" if less and not config.pick_less.always else f"(SELECT count(*) FILTER (moved) <= {tau} * count(*) FROM moved{n})"
        ctes += f", stop{n} AS MATERIALIZED (SELECT done OR {ends} AS done FROM stop{t})"
    return f"WITH {ctes} SELECT id, label FROM labels{config.stop.max_iterations}"


def louvain_one_pass() -> str:
    """One round of local moves from unique labels, towards smaller ones."""
    gain = "w - k * (total - CASE WHEN label = own THEN k ELSE 0 END) / two_m"
    return (
        f"WITH {edges('weblink')}, deg AS (SELECT dst AS id, sum(weight) AS k FROM edges GROUP BY 1), m AS (SELECT sum(weight) AS two_m FROM edges), "
        f"link AS (SELECT dst AS id, dst AS own, src AS label, sum(weight) AS w FROM edges WHERE src <> dst GROUP BY 1, 2, 3 UNION ALL SELECT id, id, id, 0 FROM deg), "
        f"gains AS (SELECT link.id, own, label, max({gain}) AS gain FROM (SELECT link.*, a.k, b.k AS total FROM link JOIN deg a ON a.id = link.id JOIN deg b ON b.id = label) link, m GROUP BY 1, 2, 3), "
        f"best AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY round(gain, 9) DESC, (label = own) DESC, label) AS r FROM gains) SELECT id, CASE WHEN label < own THEN label ELSE own END AS label FROM best WHERE r = 1"
    )


def run_sql(run: str) -> str:
    ctes, now = unrolled(*LP_RUNS[run])
    return f"WITH {ctes} SELECT id, label FROM {now}"


def modularity(labels: str) -> str:
    return f"SELECT sum(i) / max(t) - sum(d * d) / (max(t) * max(t)) AS q, count(*) AS communities FROM (SELECT y.label, sum(CASE WHEN x.label = y.label THEN weight ELSE 0 END) AS i, sum(weight) AS d, sum(sum(weight)) OVER () AS t FROM edges JOIN {labels} x ON x.id = src JOIN {labels} y ON y.id = dst GROUP BY y.label)"


def quality_sql(run: str) -> str:
    ctes, now = unrolled(*LP_RUNS[run])
    return f"WITH {ctes} SELECT round(q, 6) AS q, communities FROM ({modularity(now)})"


def spread(name: str) -> str:
    return f"{edges(name)}, {PREPARED}, pairs AS MATERIALIZED (SELECT dst, chunk, ord, src % {SPREAD} AS label, weight FROM prep)"


def slots_sql(selector: HeavyHitter, name: str, whole: bool) -> str:
    ctes = f"WITH {spread(name)}, {sketches(selector, 'pairs', '')}"
    if whole:
        return f"{ctes} SELECT dst, CAST(0 AS BIGINT) AS chunk, label, weight FROM slots"
    return f"{ctes} SELECT dst, CAST(chunk AS BIGINT) AS chunk, u.l AS label, u.w AS weight FROM (SELECT dst, chunk, unnest(s) AS u FROM partial)"


def picked_sql(selector, name: str) -> str:
    return f"WITH {spread(name)}, {candidates(selector, 'pairs', '')} SELECT id, candidate AS label FROM cand"


STATS = "SELECT count(*) AS n, CAST(sum(d) AS BIGINT) AS m_edges, sum(w) / 2 AS total_weight, round(sum(d) / count(*), 6) AS d_avg, max(d) AS max_degree FROM (SELECT dst, count(*) AS d, sum(weight) AS w FROM edges GROUP BY 1)"
DEGREES = "SELECT dst AS id, count(*) AS degree FROM edges WHERE src <> dst GROUP BY 1"


def oracle_sql() -> dict[str, str]:
    found = {f"graph_{name}_edges": f"WITH {edges(name)} SELECT src, dst, weight FROM edges" for name in PAIRS if name in BUILDERS}
    found |= {run: run_sql(run) for run in LP_RUNS}
    found |= {"graph_stats": f"WITH {edges('copurchase')} {STATS}", "graph_stats_trade": f"WITH {edges('trade')} {STATS}"}
    trade = edges("trade")
    found["degree_histogram"] = f"WITH {trade} SELECT degree, count(*) AS vertices FROM ({DEGREES}) GROUP BY 1"
    found["degree_split"] = f"WITH {trade} SELECT src, dst, weight FROM edges WHERE dst IN (SELECT id FROM ({DEGREES}) WHERE degree >= {HUB_DEGREE})"
    found["weighted_degrees"] = f"WITH {trade} SELECT dst AS id, sum(weight) AS k FROM edges GROUP BY 1"
    found["vertex_map_layout"] = f"WITH {trade} SELECT id, degree, CAST(pow(2, ceil(log2(degree + 1e-9))) - 1 AS BIGINT) AS capacity, 2 * degree AS reserved, CAST(2 * (sum(degree) OVER (ORDER BY id) - degree) AS BIGINT) AS \"offset\" FROM ({DEGREES})"
    one = HeavyHitter(consolidation="shared")
    found |= {
        "mg_partial_k8": slots_sql(HeavyHitter(), "trade", False), "mg_sketch_k8": slots_sql(one, "trade", False),
        "mg_sketch_k2_floor": slots_sql(HeavyHitter(k=2, overflow="floor", consolidation="shared"), "supply", False), "mg_sketch_as_described": slots_sql(HeavyHitter(overflow="as_described", consolidation="shared"), "trade", False),
        "mg_merge_replay": slots_sql(HeavyHitter(), "trade", True), "mg_sketch_arrow": slots_sql(HeavyHitter(), "trade", True), "mg_merge_subtract": slots_sql(HeavyHitter(merge="subtract"), "trade", True),
        "vote_combine_max": picked_sql(MajorityVote(), "trade"), "mg_pick_double": picked_sql(HeavyHitter(scan="double"), "trade"), "exact_pick": picked_sql(Exact(), "trade"),
    }
    found["vote_state"] = f"WITH {spread('trade')} SELECT dst, CAST(chunk AS BIGINT) AS chunk, v.l AS label, v.w AS weight FROM (SELECT dst, chunk, {vote('l', 'replace')} AS v FROM (SELECT dst, chunk, {LISTED} AS l FROM pairs GROUP BY 1, 2)) WHERE v.w > 0"
    found["heavy_hitters_udtf"] = f"WITH {spread('trade')}, {sketches(one, 'pairs', '')} SELECT dst, label, weight FROM slots"
    found["neighbor_label_weights"] = f"WITH {spread('trade')} SELECT dst, label, sum(weight) AS weight FROM pairs GROUP BY 1, 2"
    found |= {name: quality_sql(run) for name, run in (("modularity_exact", "exact_lp_8"), ("modularity_mg", "mg_lp_8"), ("modularity_vote", "vote_lp_8"), ("modularity_baseline_c", "baseline_c"))}
    ctes, now = unrolled(*LP_RUNS["mg_lp_8"])
    found["community_sizes"] = f"WITH {ctes} SELECT label, count(*) AS members FROM {now} GROUP BY 1"
    found["top_communities"] = f"WITH {ctes} SELECT label, count(*) AS members FROM {now} GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10"
    both = f"edges JOIN {now} x ON x.id = src JOIN {now} y ON y.id = dst"
    found["boundary_edges"] = f"WITH {ctes} SELECT src, dst, weight FROM {both} WHERE x.label <> y.label"
    found["contract_graph"] = f"WITH {ctes} SELECT x.label AS src, y.label AS dst, sum(weight) AS weight FROM {both} GROUP BY 1, 2"
    ctes, now = unrolled(*LP_RUNS["mg_lp_8"])
    found["delta_modularity"] = (
        f"WITH {ctes}, tot AS (SELECT label, sum(weight) AS s FROM edges JOIN {now} ON id = dst GROUP BY 1), deg AS (SELECT dst AS id, sum(weight) AS k FROM edges GROUP BY 1), link AS (SELECT dst AS id, label, sum(weight) AS w FROM edges JOIN {now} ON id = src WHERE src <> dst GROUP BY 1, 2), mm AS (SELECT sum(weight) / 2 AS m FROM edges) "
        f"SELECT l.id, l.label AS target, round(1e6 * CASE WHEN l.label = o.label THEN 0.0 ELSE (l.w - coalesce(f.w, 0)) / m - k * (k + a.s - c.s) / (2 * m * m) END, 3) AS dq_millionths FROM link l JOIN {now} o ON o.id = l.id JOIN deg ON deg.id = l.id JOIN mm ON true JOIN tot a ON a.label = l.label JOIN tot c ON c.label = o.label LEFT JOIN link f ON f.id = l.id AND f.label = o.label"
    )
    ctes, now = unrolled(*LP_RUNS["exact_lp_supply"])
    found["community_profile_nation"] = f"WITH {ctes} SELECT label, n_name, count(*) AS members FROM {now} JOIN supplier ON id = 2 * s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1, 2"
    ctes, now = unrolled(*LP_RUNS["exact_lp_shared_line"])
    found["nmi_lang"] = f"WITH {ctes}, cell AS (SELECT label, lang, count(*) AS n FROM {now} JOIN documents ON id = doc_id WHERE lang IS NOT NULL GROUP BY 1, 2), full_cell AS (SELECT n, sum(n) OVER (PARTITION BY label) AS a, sum(n) OVER (PARTITION BY lang) AS b, sum(n) OVER () AS t FROM cell) SELECT round(CASE WHEN h = 0 THEN 1.0 ELSE 2 * i / h END, 6) AS nmi FROM (SELECT sum(n / t * ln(n * t / (a * b))) AS i, -sum(n / t * ln(a / t)) - sum(n / t * ln(b / t)) AS h FROM full_cell)"
    found["working_set_memory"] = f"WITH {edges('copurchase')}, s AS ({STATS}) SELECT 'mg' AS method, CAST(5 * n AS BIGINT) AS bytes FROM s UNION ALL SELECT 'vote', 5 * n FROM s UNION ALL SELECT 'thread_map', 5 * n + 512 * n FROM s UNION ALL SELECT 'vertex_map', 5 * n + 16 * m_edges FROM s"
    found["selection_agreement"] = f"WITH {spread('trade')}, {candidates(HeavyHitter(), 'pairs', '1')}, {candidates(HeavyHitter(scan='double'), 'pairs', '2')}, {candidates(Exact(), 'pairs', '3')} SELECT count(*) AS vertices, count(*) FILTER (a.candidate = b.candidate) AS single_double, count(*) FILTER (b.candidate = c.candidate) AS double_exact, count(*) FILTER (a.candidate = c.candidate) AS single_exact FROM cand3 c LEFT JOIN cand1 a USING (id) LEFT JOIN cand2 b USING (id)"
    found["sketch_guarantee"] = f"WITH {spread('trade')}, {sketches(one, 'pairs', '')}, truth AS (SELECT dst, label, sum(weight) AS w, sum(sum(weight)) OVER (PARTITION BY dst) AS t FROM pairs GROUP BY 1, 2), kept AS (SELECT dst, sum(weight) AS kept FROM slots GROUP BY 1) SELECT count(*) FILTER (w * 9 > t AND coalesce(s.weight, 0) = 0) AS lost, count(*) FILTER (coalesce(s.weight, 0) > w) AS \"over\", count(*) FILTER ((w - coalesce(s.weight, 0)) * 9 > t - coalesce(kept, 0) + 1e-9) AS beyond FROM truth LEFT JOIN slots s USING (dst, label) LEFT JOIN kept USING (dst)"
    found["shuffle_model"] = f"WITH {spread('copurchase')} SELECT (SELECT count(*) FROM (SELECT DISTINCT dst, label FROM pairs)) AS exact_rows, CAST(sum(least(d, 8)) AS BIGINT) AS sketch_rows, count(*) AS vote_rows FROM (SELECT dst, chunk, count(DISTINCT label) AS d FROM pairs GROUP BY 1, 2)"
    ctes, now = unrolled(*LP_RUNS["mg_lp_1"])
    found["pickless_step"] = f"WITH {ctes} SELECT id, CASE WHEN candidate < label THEN candidate ELSE label END AS label, coalesce(candidate < label, false) AS moved, coalesce(candidate > label, false) AS refused FROM labels0 LEFT JOIN cand1 USING (id)"
    ctes, _ = unrolled("weblink", LP_RUNS["mg_lp_8"][1], 3)
    found["label_delta"] = f"WITH {ctes} SELECT count(*) AS vertices, count(*) AS \"both\", count(*) FILTER (a.label = b.label) AS equal FROM labels2 a JOIN labels3 b USING (id)"
    ctes, _ = unrolled("weblink", LPConfig(**{**LP_RUNS["pickless_none"][1].__dict__, "selector": Exact()}), 3)
    found["swap_count"] = f"WITH {ctes} SELECT count(*) FILTER (a.label = c.label AND a.label <> b.label) AS swaps FROM labels1 a JOIN labels2 b USING (id) JOIN labels3 c USING (id)"
    rows = []
    for k in (2, 4, 8, 16, 32):
        ctes, now = unrolled("trade", LP_RUNS["mg_lp_k2"][1].__class__(**{**LP_RUNS["mg_lp_k2"][1].__dict__, "selector": HeavyHitter(k=k)}))
        rows.append(f"SELECT * FROM (WITH {ctes} SELECT {k} AS k, round(q, 6) AS q, communities FROM ({modularity(now)}))")
    found["mg_slot_sweep"] = " UNION ALL ".join(rows)
    found["mg_frequent_items"] = "SELECT user_id AS item, count(*) AS n FROM events GROUP BY 1 HAVING count(*) * 51 > (SELECT count(*) FROM events)"
    found |= {f"{name}_lp_converged": stopped("weblink", LPConfig(selector)) for name, selector in (("exact", Exact()), ("mg", HeavyHitter()), ("vote", MajorityVote()))}
    found["baseline_c_converged"] = stopped("weblink", LPConfig(Exact(), PickLess(4)))
    found["louvain_one_pass"] = louvain_one_pass()
    found["majority_item"] = "SELECT CASE WHEN l_linestatus = 'F' THEN 1 ELSE 0 END AS item, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) * 2 > (SELECT count(*) FROM lineitem)"
    found["method_recommendation"] = " UNION ALL ".join(f"SELECT * FROM (WITH {edges(g)}, s AS ({STATS}) SELECT '{g}' AS graph, d_avg, CASE WHEN d_avg < 3 THEN 'exact' ELSE 'mg8' END AS method FROM s)" for g in ("weblink", "copurchase", "order_path", "turn_path"))
    pairs = ", ".join(f"({x}, {y})" for x, y in TOYS["two_triangles"])
    PAIRS["two_triangles"] = (f"keys AS (SELECT DISTINCT p_partkey AS x FROM part WHERE p_partkey IS NOT NULL), toy AS (SELECT * FROM (VALUES {pairs}) AS v(a, b)), p AS (SELECT s.x AS src, d.x AS dst, 1.0 AS weight FROM keys s JOIN toy ON (s.x % 6 + 6) % 6 + 1 = a JOIN keys d ON d.x = s.x - a + b)", "sum")
    found["toy_two_triangles"] = stopped("two_triangles", LPConfig(HeavyHitter()))
    return found
