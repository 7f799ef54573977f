"""SQL for DuckDB that computes the same rows as the queries, over the same Parquet tables."""

from __future__ import annotations

from .plans.goal import Goal
from .queries import EPS_GRID, K_GRID, SMALL, USUAL


def fold(x: str) -> str:
    return rf"regexp_replace({x}, '[^\x00-\x7F]', '?', 'g')"


def md5_number(x: str) -> str:
    return f"CAST('0x' || substr(md5({x}), 1, 15) AS BIGINT)"


def _dedupe(id_: str, s: str, table: str, where: str = "TRUE") -> str:
    return f"SELECT CAST(min({id_}) AS BIGINT) AS id, s, CAST(length(s) AS INTEGER) AS len FROM (SELECT {id_}, {s} AS s FROM {table}) WHERE s IS NOT NULL AND {where} GROUP BY s"


TITLE = fold("nullif(regexp_extract(html, '<title>(.*?)</title>', 1), '')")
CORPUS = {
    "names": _dedupe("p_partkey", "p_name", "part"),
    "clients": _dedupe("c_custkey", "c_name", "customer"),
    "urls": _dedupe("page_id", "url", "pages"),
    "titles": _dedupe("page_id", TITLE, "pages"),
    "passages": _dedupe("item_id", fold("text"), "benchmark"),
    "turns": f"SELECT min(id) AS id, s, CAST(length(s) AS INTEGER) AS len FROM (SELECT {md5_number('conv_id::VARCHAR || chr(58) || turn::VARCHAR')} AS id, {fold('text')} AS s FROM conversations) WHERE s IS NOT NULL GROUP BY s",
    "lines": f"SELECT {md5_number('s')} AS id, s, CAST(length(s) AS INTEGER) AS len FROM (SELECT DISTINCT trim(x) AS s FROM (SELECT unnest(string_split({fold('text')}, chr(10))) AS x FROM documents)) WHERE length(s) BETWEEN 40 AND 142",
    "chains": "SELECT CAST(o_orderkey AS BIGINT) AS id, string_agg(md5(o_orderkey::VARCHAR || '-' || i::VARCHAR), '' ORDER BY i) AS s, CAST(32 * (1 + o_orderkey % 17) AS INTEGER) AS len FROM orders, range(17) AS r(i) WHERE i <= o_orderkey % 17 GROUP BY o_orderkey",
}
OWN = "SELECT CAST(row_number() OVER (ORDER BY md5(s), id) AS INTEGER) AS qid, s AS q FROM c QUALIFY row_number() OVER (ORDER BY md5(s), id) <= {n}"
RING = "SELECT 1 AS qid, 'small ring' AS q"
THREE = "SELECT * FROM (VALUES (1, 'small ring'), (2, 'cold bolt'), (3, 'smal wigdet')) AS v(qid, q)"


def setting(corpus: str, queries: str) -> str:
    return f"WITH c AS MATERIALIZED ({CORPUS[corpus]}), q AS MATERIALIZED ({queries}), d AS MATERIALIZED (SELECT qid, id, s, len, CAST(levenshtein(s, q) AS INTEGER) AS dist FROM c, q)"


LINES, NAMES, NAME = setting("lines", OWN.format(n=5)), setting("names", THREE), setting("names", RING)


def relaxed(goal: Goal, name: str = "r", *, start: int = 1, step: int = 1, inclusive: bool = False, order: str = "dist, id") -> str:
    """CTEs that end in a table of candidates."""
    plus, less = (0, "<=") if inclusive else (1, "<")
    return f"""{name}n AS (SELECT qid, dist, sum(count(*)) OVER (PARTITION BY qid ORDER BY dist) AS n FROM d GROUP BY qid, dist),
{name}e AS (SELECT qid, CAST({start} + {step} * ceil(greatest(min(CASE WHEN n >= {goal.least} THEN dist + {plus} END) - {start}, 0) / {step}::DOUBLE) AS INTEGER) AS eps, min(CASE WHEN n >= {goal.least} THEN dist END) IS NULL AS none FROM {name}n GROUP BY qid),
{name} AS MATERIALIZED (SELECT *, CASE WHEN none THEN NULL ELSE eps END AS eps_final, none AS exhausted FROM (SELECT d.qid, d.id, d.s, d.dist, e.eps, e.none,
   CAST(greatest(ceil((d.dist - {start} + {plus}) / {step}::DOUBLE), 0) AS INTEGER) AS round FROM d JOIN {name}e e USING (qid) WHERE none OR dist {less} eps)
   QUALIFY row_number() OVER (PARTITION BY qid ORDER BY {order}) <= {goal.most})"""


RELAXED = "SELECT qid, id, dist, round, eps_final, exhausted FROM r"


def ranked(goal: Goal, name: str = "k", r: str = "r", *, share: float | None = 0.25, factor: float = 0.75, after: bool = False, backfill: bool = True, exact: bool = False) -> str:
    """CTEs from candidates to the ranked answer."""
    prune = f"contrib < {factor} * (sum(CASE WHEN y <= ceil({share} * m) THEN contrib END) OVER (PARTITION BY qid) / sum(CASE WHEN y <= ceil({share} * m) THEN 1 END) OVER (PARTITION BY qid)::DOUBLE)" if share else "FALSE"
    prune = f"({prune}) AND dist > 0" if exact else prune
    first = "CASE WHEN dist = 0 THEN 0 ELSE 1 END" if exact else "0"
    base = "sum(CASE WHEN pruned THEN 0 ELSE 1 END) OVER (PARTITION BY qid)" if after else "m"
    allowed = f"(NOT pruned OR rank <= {goal.kmin})" if backfill else "NOT pruned"
    return f"""{name}p AS MATERIALIZED (SELECT a.qid, a.id AS i, b.id AS j, levenshtein(a.s, b.s) AS d FROM {r} a JOIN {r} b ON a.qid = b.qid AND a.id <> b.id),
{name}c AS (SELECT qid, id, s, dist, coalesce((SELECT sum(d) FROM {name}p p WHERE p.qid = r.qid AND p.i = r.id), 0)::BIGINT AS contrib FROM {r} r),
{name}s AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY md5(id::VARCHAR), id) AS y, count(*) OVER (PARTITION BY qid) AS m FROM {name}c),
{name}x AS (SELECT *, {prune} AS pruned FROM {name}s),
{name}y AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid ORDER BY pruned, {first}, contrib DESC, id) AS INTEGER) AS rank, {base} AS base FROM {name}x),
{name} AS MATERIALIZED (SELECT qid, id, s, dist, contrib, rank, pruned FROM {name}y WHERE rank <= least(greatest(floor(base / {1 + goal.lam}), {goal.kmin}), {goal.kmax}, base) AND {allowed})"""


RANKED = "SELECT qid, id, dist, contrib, rank, pruned FROM k"


def card(lam: float, kmin: int, kmax: int, name: str = "g", k: str = "k") -> str:
    return f"""{name} AS (SELECT a.qid, a.result_count, a.mean_query_distance, coalesce(b.p, 0.0) AS mean_pair_distance, {lam} * coalesce(b.p, 0.0) - {1 - lam} * a.mean_query_distance AS balance_score, a.result_count BETWEEN {kmin} AND {kmax} AS in_range
 FROM (SELECT qid, count(*) AS result_count, avg(dist) AS mean_query_distance FROM {k} GROUP BY qid) a LEFT JOIN (SELECT x.qid, avg(levenshtein(x.s, y.s)) AS p FROM {k} x JOIN {k} y ON x.qid = y.qid AND x.id < y.id GROUP BY x.qid) b USING (qid))"""


def sweep(values) -> str:
    """values: (label, value, goal, start)."""
    ctes, rows = [LINES], []
    for i, (label, value, goal, start) in enumerate(values):
        ctes += [relaxed(goal, f"r{i}_", start=start), ranked(goal, f"k{i}_", f"r{i}_"), card(goal.lam, goal.kmin, goal.kmax, f"g{i}_", f"k{i}_")]
        rows.append(f"SELECT '{label}' AS method, {float(value)}::DOUBLE AS value, round(avg(balance_score), 6) AS score, round(avg(mean_query_distance), 6) AS distance, round(avg(mean_pair_distance), 6) AS spread, round(avg(result_count), 6) AS results, CAST(sum(CASE WHEN in_range THEN 0 ELSE 1 END) AS BIGINT) AS out_of_range FROM g{i}_")
    return ",\n".join(ctes) + "\n" + " UNION ALL ".join(rows)


SHOWN = "translate(gram, chr(2) || chr(3), '^$')"


def gram_rows(source: str, s: str, key: str, pad: bool = True) -> str:
    p = f"chr(2) || {s} || chr(3)" if pad else s
    return f"SELECT {key}, gram, CAST(row_number() OVER (PARTITION BY {key.split(',')[0]}, gram ORDER BY i) AS INTEGER) AS occ FROM (SELECT {key}, i, substring({p}, CAST(i AS BIGINT), 2) AS gram FROM {source}, unnest(range(1, greatest(length({p}), 1))) AS u(i))"


def probed(eps: int, mode: str) -> str:
    only = "WHERE occ = 1" if mode == "set" else ""
    size = "(SELECT count(*) FROM gq z WHERE z.qid = x.qid)" if mode == "set" else "qlen + 1"
    return f"""{LINES}, gc AS (SELECT * FROM ({gram_rows('c', 's', 'id, len')}) {only}), gq AS (SELECT * FROM ({gram_rows('(SELECT *, length(q) AS qlen FROM q)', 'q', 'qid, qlen')}) {only}),
x AS (SELECT qid, qlen, id, count(*) AS common FROM gc JOIN gq USING (gram, occ) WHERE abs(len - qlen) <= {eps - 1} GROUP BY ALL)
SELECT qid, id, common FROM x WHERE common >= {size} - 2 * {eps - 1}"""


def events(body: str) -> str:
    return f"WITH e AS (SELECT * FROM events) {body}"


_cands = f"{NAMES}, {relaxed(SMALL)}"
_lines = f"{LINES}, {relaxed(USUAL, start=30)}, {ranked(USUAL)}"
_near = "n AS (SELECT qid, id, s, dist FROM d QUALIFY row_number() OVER (PARTITION BY qid ORDER BY dist, id) <= 25)"
_two = f"{_lines}, {_near}, b AS (SELECT 'relax_rank' AS method, qid, id, s, dist FROM k UNION ALL SELECT 'nearest', qid, id, s, dist FROM n)"
_aligned = "WITH a AS (SELECT CAST(floor(c_custkey / 10) AS BIGINT) AS qid, CAST(c_custkey AS BIGINT) AS id, translate(c_name, '0', '-') AS r FROM customer), x AS (SELECT qid, id, i AS pos, substring(r, CAST(i AS BIGINT), 1) AS ch FROM a, unnest(range(1, length(r) + 1)) AS u(i))"
_motif = "SELECT qid, string_agg(ch, '' ORDER BY pos) AS motif FROM (SELECT * FROM (SELECT qid, pos, ch, count(*) AS n FROM x {0} GROUP BY qid, pos, ch) QUALIFY row_number() OVER (PARTITION BY qid, pos ORDER BY n DESC, ch = '-', ch) = 1) WHERE ch <> '-' GROUP BY qid"
_e = "WITH e AS (SELECT vec_id AS id, embedding::DOUBLE[64] AS vec, label AS cid FROM embeddings), f AS (SELECT id, cid, i, vec[i] AS x FROM e, unnest(range(1, 65)) AS u(i))"
_mean = f"{_e}, m AS (SELECT cid, list(x ORDER BY i)::DOUBLE[64] AS centre FROM (SELECT cid, i, avg(x) AS x FROM f GROUP BY ALL) GROUP BY cid), g AS (SELECT a.cid AS src, b.cid AS dst, array_distance(a.centre, b.centre) AS w FROM m a JOIN m b ON a.cid <> b.cid)"
_walk = f"WITH c AS ({CORPUS['names']}), t AS (SELECT *, CAST(dense_rank() OVER (ORDER BY levenshtein(w, 'ring'), w) - 1 AS INTEGER) AS hop FROM (SELECT *, regexp_extract(s, '^\\S+ (.*)$', 1) AS w FROM c)), v AS (SELECT 1 AS qid, hop AS cid, hop, id, levenshtein(s, 'small ring') AS vdist FROM t WHERE hop < 4)"


def _quota(goal: Goal, width: int = 4) -> str:
    first = int(goal.quota) + 1
    need = first + max(-(-(goal.kmin - first + 1) // width), 1) * width - 1
    return f"""{_walk}, y AS (SELECT *, row_number() OVER (PARTITION BY cid ORDER BY vdist, id) AS r FROM v),
z AS (SELECT *, CASE WHEN hop = 0 AND r <= {first} THEN r WHEN hop = 0 THEN {first} + (r - {first}) * {width} ELSE {first} + (r - 1) * {width} + hop END AS place FROM y)
SELECT qid, CAST(row_number() OVER (ORDER BY place) AS INTEGER) AS pick, cid, id FROM z WHERE place <= {min(need, goal.kmax)}"""


ORACLE: dict[str, str] = {
    **{f"corpus_{n}": f"SELECT id, s, len FROM ({sql})" for n, sql in CORPUS.items()},
    "corpus_stats": " UNION ALL ".join(f"SELECT '{n}' AS corpus, count(*) AS n, min(len) AS shortest, max(len) AS longest, round(avg(len), 6) AS mean FROM ({CORPUS[n]})" for n in ("names", "urls", "titles", "lines")),
    "queries_typo": f"WITH c AS ({CORPUS['names']}), o AS ({OWN.format(n=5)}), t AS (SELECT qid, q[1] || q[3] || q[2] || q[4:] AS s FROM o) SELECT qid, 'x' || s[1:3] || s[5:] AS q FROM t",
    "edit_distance_scan": f"{NAMES} SELECT qid, id, dist FROM d",
    "bounded_scan": f"{LINES} SELECT qid, id, dist FROM d WHERE dist <= 39",
    "length_band_scan": f"{LINES} SELECT q.qid, count(*) AS n FROM c JOIN q ON abs(len - length(q)) < 10 GROUP BY q.qid",
    "hamming_cells": f"WITH c AS ({CORPUS['clients']}) SELECT a.id AS i, b.id AS j, CAST(hamming(a.s, b.s) AS INTEGER) AS d FROM c a JOIN c b ON a.id % 100 = 0 AND a.id <> b.id AND a.len = b.len",
    "metrics_other": f"WITH c AS ({CORPUS['names']}), g AS (SELECT id, s, list_distinct([substring('^' || s || '$', i, 2) for i in range(1, length(s) + 2)]) AS x FROM c), r AS (SELECT list_distinct([substring('^small ring$', i, 2) for i in range(1, 12)]) AS y) SELECT id, round(levenshtein(s, 'small ring') / greatest(length(s), 10)::DOUBLE, 6) AS norm_edit, round(1 - len(list_intersect(x, y)) / (len(x) + len(y) - len(list_intersect(x, y)))::DOUBLE, 6) AS jaccard_gram FROM g, r",
    "grams_padded": f"WITH c AS ({CORPUS['names']}) SELECT id, {SHOWN} AS gram, occ FROM ({gram_rows('c', 's', 'id')})",
    "grams_unpadded": f"WITH c AS ({CORPUS['names']}) {gram_rows('c', 's', 'id', False)}",
    "postings": f"WITH c AS ({CORPUS['lines']}), g AS ({gram_rows('c', 's', 'id, len')}) SELECT {SHOWN} AS gram, occ, n, chars FROM (SELECT gram, occ, count(*) AS n, CAST(sum(len) AS BIGINT) AS chars FROM g GROUP BY gram, occ)",
    "posting_lengths": f"WITH c AS ({CORPUS['titles']}), g AS ({gram_rows('c', 's', 'id')}), n AS (SELECT gram, count(DISTINCT id) AS strings FROM g GROUP BY gram) SELECT strings, count(*) AS grams FROM n GROUP BY strings",
    "gram_probe": probed(20, "bag"),
    "gram_probe_set": probed(10, "set"),
    "index_range_search": f"{LINES} SELECT qid, id, dist FROM d WHERE dist < 40",
    "stream_append": f"{LINES} SELECT qid, id, dist FROM d WHERE dist < 40",
    "index_engine": f"{LINES} SELECT qid, CASE WHEN length(q) + 1 - 78 <= 0 THEN 'scan' ELSE 'index' END AS engine FROM q",
    "edit_selfjoin": f"WITH c AS ({CORPUS['urls']}) SELECT a.id AS i, b.id AS j, CAST(levenshtein(a.s, b.s) AS INTEGER) AS dist FROM c a JOIN c b ON a.id < b.id WHERE levenshtein(a.s, b.s) < 6",
    "relax_names": f"{NAME}, {relaxed(SMALL)} {RELAXED}",
    "relax_batch": f"{LINES}, {relaxed(USUAL, start=30)} {RELAXED}",
    "relax_auto": f"{LINES}, {relaxed(USUAL, start=30)} {RELAXED}",
    "relax_max_rounds": f"{NAMES}, {relaxed(SMALL)}, m AS (SELECT qid, CAST(least(coalesce(CASE WHEN none THEN NULL ELSE eps END, 4), 4) AS INTEGER) AS most FROM re) SELECT d.qid, d.id, d.dist, d.dist AS round, most AS eps_final, FALSE AS exhausted FROM d JOIN m USING (qid) WHERE d.dist < most QUALIFY row_number() OVER (PARTITION BY d.qid ORDER BY d.dist, d.id) <= {SMALL.most}",
    "index_sizes": " UNION ALL ".join(f"SELECT * FROM (WITH c AS ({CORPUS[n]}), g AS ({gram_rows('c', 's', 'id')}) SELECT '{n}' AS corpus, count(DISTINCT id) AS strings, count(*) AS postings, count(DISTINCT gram) AS grams FROM g)" for n in ("titles", "turns", "lines")),
    "index_recall": f"{LINES} SELECT CAST(e AS INTEGER) AS eps, CAST(sum(CASE WHEN dist < e THEN 1 ELSE 0 END) AS BIGINT) AS found, CAST(sum(CASE WHEN dist < e THEN 1 ELSE 0 END) AS BIGINT) AS truth FROM d, (VALUES (2), (5), (10), (20), (30), (40)) AS v(e) GROUP BY e",
    "search_counters": f"""{LINES}, g AS MATERIALIZED ({gram_rows('c', 's', 'id')}), h AS MATERIALIZED ({gram_rows('q', 'q', 'qid')}),
m AS MATERIALIZED (SELECT qid, g.id, count(*) AS common FROM g JOIN h USING (gram, occ) GROUP BY qid, g.id), e AS (SELECT * FROM (VALUES (2), (5), (10), (20), (30), (40)) AS v(eps)),
f AS (SELECT d.qid, d.dist, abs(d.len - length(q.q)) AS gap, length(q.q) AS n, coalesce(m.common, 0) AS common FROM d JOIN q USING (qid) LEFT JOIN m USING (qid, id))
SELECT qid, CAST(eps AS INTEGER) AS eps, CAST(sum(CASE WHEN gap < eps THEN 1 ELSE 0 END) AS BIGINT) AS verified_by_scan, CAST(sum(CASE WHEN gap < eps THEN common ELSE 0 END) AS BIGINT) AS postings_read,
  CAST(sum(CASE WHEN gap < eps AND common > 0 AND common >= n + 1 - 2 * (eps - 1) THEN 1 ELSE 0 END) AS BIGINT) AS verified_by_index, CAST(sum(CASE WHEN dist < eps THEN 1 ELSE 0 END) AS BIGINT) AS results FROM f, e GROUP BY qid, eps""",
    "relax_gallop": f"{LINES}, {relaxed(USUAL, start=30)} {RELAXED}",
    "relax_index": f"{LINES}, {relaxed(USUAL, start=5)} {RELAXED}",
    "relax_rounds": f"{_cands} {RELAXED}",
    "relax_arrival": f"{NAMES}, {relaxed(SMALL, start=4, step=3, order='round, id')} {RELAXED}",
    "relax_inclusive": f"{NAMES}, {relaxed(SMALL, inclusive=True)} {RELAXED}",
    "relax_step": f"{NAMES}, {relaxed(SMALL, start=2, step=4)} {RELAXED}",
    "relax_exhausted": f"{NAME}, {relaxed(Goal(60, 100, 0.5))} {RELAXED}",
    "relax_if_empty_names": f"{NAMES}, m AS (SELECT qid, CAST(greatest(1, min(dist) + 1) AS INTEGER) AS eps_final FROM d GROUP BY qid) SELECT qid, id, dist, eps_final FROM d JOIN m USING (qid) WHERE dist < eps_final",
    "nearest_k": f"{LINES} SELECT qid, id, dist, CAST(row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS INTEGER) AS rank FROM d QUALIFY rank <= 25",
    "relax_chains": f"WITH c AS MATERIALIZED ({CORPUS['chains']}), q AS ({OWN.format(n=1)}), d AS MATERIALIZED (SELECT qid, id, s, len, CAST(levenshtein(s, q) AS INTEGER) AS dist FROM c, q), {relaxed(USUAL, start=30)} {RELAXED}",
    "pair_distances": f"{_cands} SELECT a.qid, a.id AS i, b.id AS j, CAST(levenshtein(a.s, b.s) AS INTEGER) AS d FROM r a JOIN r b ON a.qid = b.qid AND a.id < b.id",
    "contribution": f"{_cands}, {ranked(SMALL)} SELECT qid, id, contrib FROM kc",
    "cut_off_sampled": f"{_cands}, {ranked(SMALL)} SELECT qid, round(0.75 * avg(contrib), 6) AS cut FROM ks WHERE y <= ceil(0.25 * m) GROUP BY qid",
    "cut_off_exact": f"{_cands}, {ranked(SMALL)} SELECT qid, round(0.75 * avg(contrib), 6) AS cut FROM ks GROUP BY qid",
    "relax_rank": f"{_lines} {RANKED}",
    "relax_rank_names": f"{_cands}, {ranked(SMALL, share=1.0)} {RANKED}",
    "relax_rank_noprune": f"{LINES}, {relaxed(USUAL, start=30)}, {ranked(USUAL, share=None)} {RANKED}",
    "relax_rank_literal": f"{_cands}, {ranked(SMALL, share=1.0, factor=0.99, backfill=False)} {RANKED}",
    "relax_rank_after": f"{_cands}, {ranked(SMALL, share=1.0, factor=0.95, after=True)} {RANKED}",
    "relax_rank_exact_kept": f"{_cands}, {ranked(SMALL, share=1.0, exact=True)} {RANKED}",
    "relax_medoid": f"{_cands}, {ranked(SMALL, share=None)}, z AS (SELECT *, CAST(levenshtein(s, first_value(s) OVER (PARTITION BY qid ORDER BY contrib, id)) AS INTEGER) AS to_centre, count(*) OVER (PARTITION BY qid) AS m FROM kc) SELECT qid, id, dist, to_centre, CAST(row_number() OVER (PARTITION BY qid ORDER BY to_centre DESC, id) AS INTEGER) AS rank FROM z QUALIFY rank <= least(greatest(floor(m / 1.5), 5), 8, m)",
    "measures_relax_rank": f"{_lines}, {card(0.5, 25, 55)} SELECT qid, result_count, round(mean_query_distance, 6) AS mean_query_distance, round(mean_pair_distance, 6) AS mean_pair_distance, round(balance_score, 6) AS balance_score, in_range FROM g",
    "score_identity": f"{LINES}, {_near}, {card(0.3, 25, 55, 'g', 'n')} SELECT qid, abs(0.3 * (mean_pair_distance + mean_query_distance) - mean_query_distance - balance_score) < 1e-9 AS same FROM g",
    "lambda_sweep": sweep([("relax_rank", lam, Goal(25, 55, lam), 30) for lam in (0.0, 0.2, 0.4, 0.6, 0.8, 1.0)]),
    "k_sweep": sweep([("relax_rank", k + 15, Goal(k, k + 30, 0.5), 30) for k in K_GRID]),
    "eps_sweep_counts": f"{LINES}, " + ", ".join(f"{relaxed(USUAL, f'r{e}_', start=e)}, {ranked(USUAL, f'k{e}_', f'r{e}_')}" for e in EPS_GRID) + " " + " UNION ALL ".join(f"SELECT {e} AS eps, 'range_k' AS method, q.qid, CAST(least(count(d.id), 25) AS BIGINT) AS n FROM q LEFT JOIN d ON d.qid = q.qid AND dist < {e} GROUP BY q.qid UNION ALL SELECT {e}, 'relax_rank', q.qid, count(k.id) FROM q LEFT JOIN k{e}_ k USING (qid) GROUP BY q.qid" for e in EPS_GRID),
    "measures_cube": f"{_two} SELECT method, qid, count(*) AS n, round(avg(dist), 6) AS distance, round(stddev_pop(dist), 6) AS stability FROM b GROUP BY CUBE (method, qid)",
    "rollup_measures": f"{_two} SELECT method, qid, min(dist) AS lowest, max(dist) AS highest, count(DISTINCT id) AS ids FROM b GROUP BY ROLLUP (method, qid)",
    "overlap_methods": f"{_two} SELECT qid, part, count(*) AS n FROM (SELECT qid, id, CASE count(*) WHEN 2 THEN 'both' ELSE min(method) END AS part FROM b GROUP BY qid, id) GROUP BY qid, part",
    "sum_of_pairs": f"{_aligned} SELECT a.qid, a.id::BIGINT AS i, b.id::BIGINT AS j, CAST(sum(CASE WHEN a.ch = '-' AND b.ch = '-' THEN 0 WHEN a.ch = '-' OR b.ch = '-' THEN -1 WHEN a.ch = b.ch THEN 1 ELSE 0 END) AS BIGINT) AS score FROM x a JOIN x b ON a.qid = b.qid AND a.pos = b.pos AND a.id < b.id GROUP BY a.qid, a.id, b.id",
    "motif_fixed": f"{_aligned} {_motif.format('')}",
    "udaf_motif": f"{_aligned} {_motif.format('')}",
    "motif_nogap": f"{_aligned} " + _motif.format("WHERE ch <> '-'"),
    "token_segments": f"SELECT doc_id, CAST(len(list_filter(regexp_split_to_array(lower({fold('text')}), '[^0-9a-z?]+'), lambda w: w <> '')) AS INTEGER) AS words FROM documents",
    "knn_embeddings": f"{_e} SELECT q.id AS qid, e.id, CAST(row_number() OVER (PARTITION BY q.id ORDER BY array_distance(q.vec, e.vec), e.id) AS INTEGER) AS rank FROM e JOIN e q ON q.id % 100 = 0 AND e.id <> q.id QUALIFY rank <= 5",
    "centre_graph": f"{_mean} SELECT src, dst, round(w, 4) AS w FROM g",
    "centre_median": f"{_e} SELECT cid, CAST(i - 1 AS INTEGER) AS component, round(quantile_cont(x, 0.5), 5) AS x FROM f GROUP BY cid, i",
    "reachable": f"{_mean} SELECT src, dst, CAST(row_number() OVER (PARTITION BY src ORDER BY w, dst) AS INTEGER) AS hop FROM g QUALIFY hop < 5 UNION ALL SELECT DISTINCT src, src, 0 FROM g",
    "training_sample": f"{_e} SELECT cid, id FROM e QUALIFY row_number() OVER (PARTITION BY cid ORDER BY md5(id::VARCHAR), id) <= greatest(1, ceil(0.05 * count(*) OVER (PARTITION BY cid)))",
    "knn_classes": f"{_e}, t AS (SELECT * FROM e QUALIFY row_number() OVER (PARTITION BY cid ORDER BY md5(id::VARCHAR), id) <= greatest(1, ceil(0.05 * count(*) OVER (PARTITION BY cid)))), p AS (SELECT q.id AS qid, t.cid, array_distance(q.vec, t.vec) AS d FROM e q, t WHERE q.id % 100 = 0 QUALIFY row_number() OVER (PARTITION BY q.id ORDER BY array_distance(q.vec, t.vec), t.id) <= 5) SELECT qid, cid FROM p GROUP BY qid, cid QUALIFY row_number() OVER (PARTITION BY qid ORDER BY count(*) DESC, sum(d), cid) = 1",
    "quota_walk": _quota(SMALL),
    "random_subset": f"{_cands} SELECT qid, id, CAST(row_number() OVER (PARTITION BY qid ORDER BY md5('1:' || id::VARCHAR), id) AS INTEGER) AS rank FROM r QUALIFY rank <= 5",
    "exact_best": f"""{NAME}, {relaxed(SMALL)}, o AS (SELECT *, row_number() OVER (ORDER BY id) - 1 AS b FROM r),
t AS (SELECT m FROM range(1, CAST(pow(2, (SELECT count(*) FROM o)) AS BIGINT)) AS u(m) WHERE bit_count(m) BETWEEN 5 AND 8),
x AS (SELECT m, avg(dist) AS near FROM t JOIN o ON (m >> CAST(b AS INTEGER)) & 1 = 1 GROUP BY m),
y AS (SELECT m, avg(levenshtein(a.s, z.s)) AS far FROM t JOIN o a ON (m >> CAST(a.b AS INTEGER)) & 1 = 1 JOIN o z ON (m >> CAST(z.b AS INTEGER)) & 1 = 1 AND a.b < z.b GROUP BY m)
SELECT 1 AS qid, round(max(0.5 * far - 0.5 * near), 6) AS balance_score FROM x JOIN y USING (m)""",
    "join_labels": "SELECT lang, count(*) AS n FROM documents JOIN labels USING (doc_id) WHERE quality = 1 GROUP BY lang",
    "join_sales": f"{NAME}, {relaxed(SMALL)}, {ranked(SMALL, share=1.0)} SELECT p_brand, count(*) AS lines, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_name IN (SELECT s FROM k) GROUP BY p_brand",
    "semi_taken": f"{_cands} SELECT id, s FROM c WHERE id IN (SELECT id FROM r)",
    "anti_missing": f"{_cands} SELECT id, s FROM c WHERE id NOT IN (SELECT id FROM r)",
    "count_with_zero": f"WITH c AS ({CORPUS['names']}), q AS (SELECT * FROM (VALUES (1, 'small ring'), (2, 'zzzzzzzzzzzz')) AS v(qid, q)) SELECT qid, count(c.id) AS n FROM q LEFT JOIN c ON levenshtein(s, q) <= 2 GROUP BY qid",
    "asof_version": "SELECT a.event_id, arg_max(b.event_id, (b.ts, b.event_id)) AS view_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'view' AND b.ts <= a.ts WHERE a.event_type = 'purchase' GROUP BY a.event_id",
    "win_running_count": f"{LINES}, n AS (SELECT qid, dist, count(*) AS n FROM d GROUP BY qid, dist) SELECT qid, dist, n, CAST(sum(n) OVER w AS BIGINT) AS running, n - coalesce(lag(n) OVER w, 0) AS change FROM n WINDOW w AS (PARTITION BY qid ORDER BY dist)",
    "fn_surface": "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS k, round(avg(abs(value)), 6) AS size, strftime(max(ts), '%Y-%m-%d') AS last_day FROM events GROUP BY event_type",
    "udtf_grams": f"WITH c AS ({CORPUS['names']}) SELECT id, {SHOWN} AS gram, occ FROM ({gram_rows('c', 's', 'id')})",
    "sql_relax": f"{NAME}, {relaxed(SMALL)} SELECT id, dist FROM r",
    "udf_distance": f"{NAME} SELECT id, dist FROM d",
    "stream_tumbling": "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS s FROM events) GROUP BY 1",
    "stream_session": "WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM events), s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM o) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, g",
    "stream_dedup": "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type",
}
