"""Relaxation: widen the distance limit until enough strings are near, for a batch of queries.

The loop by growing limits takes, at the end, all strings under the smallest limit that holds enough of them. The closed
form asks for that limit directly: distances are counted per query, a running count finds the limit, and the nearest
strings up to the cap are kept. One scan serves all queries; the corpus is never shuffled, queries are broadcast (a batch is
bounded by ``MOST_QUERIES``; a longer one is refused, to be cut by its caller)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from ..functions import edits
from ..plans.goal import Goal

MOST_QUERIES = 10_000
#: Pairs of strings and queries up to which all distances are worked out without a limit.
FEW_PAIRS = 2_000_000
#: Length from which distances are worked out bit-parallel, many strings at once, instead of cell by cell.
LONG = 64


def small(queries: DataFrame) -> DataFrame:
    n = queries.limit(MOST_QUERIES + 1).count()
    if n > MOST_QUERIES:
        raise ValueError(f"a batch has at most {MOST_QUERIES} queries; call once per batch")
    return F.broadcast(queries)


def range_scan(corpus: DataFrame, queries: DataFrame, limit: int | None = None) -> DataFrame:
    """(qid, id, s, len, dist) of all pairs, or of those with dist <= limit (inclusive).

    The length band is checked first; the distance is put into an array and exploded, which keeps the optimizer from
    working it out once for the filter and again for the output."""
    q = small(queries.select("qid", "q", F.length("q").alias("qlen")))
    if limit is None:
        pairs = corpus.crossJoin(q)
        return pairs.select("qid", "id", "s", "len", F.levenshtein("s", "q").alias("dist"))
    pairs = corpus.join(q, F.abs(F.col("len") - F.col("qlen")) <= limit)
    near = pairs.select("qid", "id", "s", "len", F.explode(F.array(F.levenshtein("s", "q", limit))).alias("dist"))
    return near.where("dist >= 0")


def long_scan(corpus: DataFrame, queries: DataFrame, limit: int, above: int = -1, most: int | None = None) -> DataFrame:
    """(qid, id, s, len, dist) of strings whose length differs from the query's by more than ``above`` and at most ``limit``.

    For long strings: each task holds some thousand of them and compares them with a query at once. With ``most``, a task
    gives only its so many nearest of a query by (dist, id): what is left out is beyond the nearest so many of all tasks."""
    small(queries)
    asked = sorted((r.qid, r.q) for r in queries.select("qid", "q").where("q is not null").collect())
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in [queries.schema["qid"], *(corpus.schema[c] for c in ("id", "s", "len"))]) + ", dist int"
    kind = to_arrow_type(queries.schema["qid"].dataType)
    lengths = np.unique([len(q) for _, q in asked])

    def near(held, best):
        rows = pa.Table.from_batches(held)
        off = rows.column("len").to_numpy()
        for qid, q in asked:
            gap = np.abs(off - len(q))
            band = rows.filter(pa.array((gap > above) & (gap <= limit)))
            dist = edits.Texts(band.column("s").to_pylist()).distances(q)
            cols = [pa.array([qid] * len(band), kind), *(band.column(c) for c in ("id", "s", "len")), pa.array(dist.astype(np.int32))]
            found = pa.table(cols, names=["qid", "id", "s", "len", "dist"])
            if most is None:
                yield from found.to_batches()
            else:
                found = pa.concat_tables([best[qid], found]) if qid in best else found
                best[qid] = found.take(pc.sort_indices(found, [("dist", "ascending"), ("id", "ascending")])[:most])

    def run(batches):
        held, n, best = [], 0, {}
        for batch in batches if asked else ():
            batch = batch.filter(batch.column("s").is_valid())
            size = batch.column("len").to_numpy()
            least = lengths[np.minimum(np.searchsorted(lengths, size - limit), len(lengths) - 1)]  # of those not below the band
            held.append(batch.filter(pa.array(np.abs(least - size) <= limit)))
            n += held[-1].num_rows
            if n >= edits.BLOCK:
                yield from near(held, best)
                held, n = [], 0
        if n:
            yield from near(held, best)
        for found in best.values():
            yield from found.combine_chunks().to_batches()

    return corpus.select("id", "s", "len").mapInArrow(run, schema)


def final_threshold(dists: DataFrame, goal: Goal, *, eps_start: int = 1, step: int = 1, inclusive: bool = False) -> DataFrame:
    """(qid, eps_final): the first limit of the grid eps_start, eps_start + step, ... that holds goal.least strings.

    Null where all strings together are too few."""
    counts = dists.groupBy("qid", "dist").count()
    running = F.sum("count").over(Window.partitionBy("qid").orderBy("dist"))
    need = F.min(F.when(F.col("n") >= goal.least, F.col("dist") + (0 if inclusive else 1)))
    at = counts.withColumn("n", running).groupBy("qid").agg(need.alias("need"))
    start = F.lit(eps_start)
    grid = start + F.lit(step) * F.ceil(F.greatest(F.col("need") - start, F.lit(0)) / step)
    return at.select("qid", F.when(F.col("need").isNotNull(), grid.cast("int")).alias("eps_final"))


def cap(rows: DataFrame, goal: Goal, order: list[str]) -> DataFrame:
    w = Window.partitionBy("qid").orderBy(*order)
    return rows.withColumn("place", F.row_number().over(w)).where(F.col("place") <= goal.most).drop("place")


def plan_engine(corpus: DataFrame, queries: DataFrame, eps_start: int = 1, index=None) -> tuple[str, str]:
    """The engine for a batch, and why. With an index whose count bound says something about all of the queries at the first
    limit, and whose lists for them are shorter than the corpus, candidates come from the lists. Else few pairs are measured
    without a limit in one scan, and many by scans under doubled limits, whose bounded distances fill a band only."""
    strings, asked = corpus.count(), queries.count()
    if index is not None:
        blind = queries.where(index.blind(max(1, eps_start))).limit(1).count()
        if not blind:
            read = index.postings_read(queries, max(1, eps_start))
            if read < strings * asked:
                return "index", f"{read} postings for {strings * asked} pairs"
    if strings * asked <= FEW_PAIRS:
        return "histogram", f"{strings * asked} pairs"
    return "gallop", f"{strings * asked} pairs"


def relax(corpus: DataFrame, queries: DataFrame, goal: Goal, *, eps_start: int = 1, step: int = 1, engine: str = "auto", inclusive: bool = False, tie_order: str = "nearest", index=None, max_rounds: int | None = None) -> DataFrame:
    """Candidates (qid, id, s, dist, round, eps_final, exhausted). max_rounds: limits that are tried at most.

    histogram: one scan of all distances. gallop: bounded scans with a doubled limit, only for queries that still lack
    strings. index: candidates from a gram index per limit, where its count filter says anything. rounds: the literal loop.
    auto: one of the first three, by ``plan_engine``."""
    if engine == "auto":
        engine = plan_engine(corpus, queries, eps_start, index)[0]
    if engine == "rounds":
        return _rounds(corpus, queries, goal, eps_start, step, inclusive, tie_order)
    if engine == "gallop":
        longest = queries.agg(F.max(F.length("q"))).first()[0] or 0
        bands = longest > LONG and tie_order == "nearest" and isinstance(goal, Goal)
        dists = _gallop(corpus, queries, goal, eps_start, step, inclusive, range_scan, bands)
    elif engine == "index":
        dists = _gallop(corpus, queries, goal, eps_start, step, inclusive, lambda c, q, t: index.range_search(q, t + 1))
    elif engine == "histogram":
        dists = range_scan(corpus, queries).persist()
    else:
        raise ValueError(f"no engine {engine!r}")
    limits = final_threshold(dists, goal, eps_start=eps_start, step=step, inclusive=inclusive)
    if max_rounds is not None:
        last = eps_start + step * (max_rounds - 1)
        limits = limits.withColumn("eps_final", F.least(F.coalesce("eps_final", F.lit(last)), F.lit(last)))
    return take(dists, limits, goal, eps_start, step, inclusive, tie_order)


def take(dists: DataFrame, limits: DataFrame, goal: Goal, eps_start: int, step: int, inclusive: bool, tie_order: str = "nearest") -> DataFrame:
    inside = F.col("dist") <= F.col("eps_final") if inclusive else F.col("dist") < F.col("eps_final")
    rows = dists.join(F.broadcast(limits), "qid").where(F.col("eps_final").isNull() | inside)
    over = F.col("dist") - eps_start + (0 if inclusive else 1)
    rows = rows.withColumn("round", F.greatest(F.ceil(over / step), F.lit(0)).cast("int")).withColumn("exhausted", F.col("eps_final").isNull())
    order = ["round", "id"] if tie_order == "arrival" else ["dist", "id"]
    return cap(rows, goal, order).select("qid", "id", "s", "dist", "round", "eps_final", "exhausted")


def _gallop(corpus, queries, goal, eps_start, step, inclusive, search, bands=False):
    """Union of the queries' rows under the first doubled limit that reaches their final threshold; the ids of the queries
    that are still open (a batch is bounded) come to the driver after each doubling, so plans do not grow with the rounds.

    With bands the distances are those of ``long_scan``, which no limit makes cheaper: strings that an earlier limit let in by
    their length keep theirs, and only the new ones are compared. Of each task's rows the nearest ``goal.most`` stay."""
    longest = corpus.agg(F.max("len")).first()[0] or 0
    top = max(longest, queries.agg(F.max(F.length("q"))).first()[0] or 0)
    open_, found, limit = queries.select("qid", "q"), None, max(1, eps_start)
    kept, above, over = None, -1, []
    while True:
        if bands:
            new = long_scan(corpus, open_, limit, above, goal.most).persist()
            kept, above = new if kept is None else kept.unionByName(new), limit
            rows = kept.where((F.col("dist") <= limit) & ~F.col("qid").isin(over))
        else:
            rows = search(corpus, open_, limit).select("qid", "id", "s", "len", "dist").persist()
        if limit > top:
            return rows if found is None else found.unionByName(rows)
        # the final threshold lies on a grid and may lie beyond the limit that held enough
        reached = final_threshold(rows, goal, eps_start=eps_start, step=step, inclusive=inclusive)
        done = [r.qid for r in reached.where(F.col("eps_final") <= limit + (0 if inclusive else 1)).select("qid").collect()]
        if done:
            rows = rows.where(F.col("qid").isin(done))
            found = rows if found is None else found.unionByName(rows)
            open_, over = open_.where(~F.col("qid").isin(done)), over + done
            if not open_.limit(1).count():
                return found
        limit *= 2


def _rounds(corpus, queries, goal, eps_start, step, inclusive, tie_order):
    """One limit after another, as the method is told, on the counts per distance: at most one row per query and
    distance comes to the driver, never strings."""
    dists = range_scan(corpus, queries).persist()
    counts: dict[int, dict[int, int]] = {}
    for qid, dist, n in dists.groupBy("qid", "dist").count().collect():
        counts.setdefault(qid, {})[dist] = n
    limits = []
    for qid, held in counts.items():
        eps, taken, top = eps_start, 0, max(held)
        left = dict(held)
        while True:
            for dist in [d for d in left if (d <= eps if inclusive else d < eps)]:
                taken += left.pop(dist)
            if taken >= goal.least or not left or eps > top:
                break
            eps += step
        limits.append((qid, eps if taken >= goal.least else None))
    frame = dists.sparkSession.createDataFrame(limits, "qid int, eps_final int")
    return take(dists, frame, goal, eps_start, step, inclusive, tie_order)


def relax_if_empty(corpus: DataFrame, queries: DataFrame, eps: int) -> DataFrame:
    """The earlier technique: the limit grows only while nothing at all is found, and nothing is capped."""
    dists = range_scan(corpus, queries)
    limits = dists.groupBy("qid").agg(F.greatest(F.lit(eps), F.min("dist") + 1).alias("eps_final"))
    return dists.join(F.broadcast(limits), "qid").where("dist < eps_final").select("qid", "id", "s", "dist", "eps_final")


def nearest(corpus: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Plain similarity search: the k nearest, the exact best answer where difference counts nothing."""
    w = Window.partitionBy("qid").orderBy("dist", "id")
    return range_scan(corpus, queries).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "id", "s", "dist", "rank")
