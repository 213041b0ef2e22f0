"""Hybrid search in stages: masks and counts, partition selection, pruning by one-bit codes, bounds, refinement, merge."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from packvec.functions.vectors import l2
from packvec.operators import lowbit, lowerbound, predicates, segments, select
from packvec.plans.index import Index
from packvec.plans.shared import stored
from packvec.plans.tiles import looked_up


@dataclass(frozen=True)
class Plan:
    """hperc: percent of candidates that one-bit pruning leaves (100: none pruned). rerank: shortlist length over k.

    policy: see select.reach. bound: table, direct, fused or centre. refine: exact distances of the shortlist. With
    exact_stop, every row whose bound is within the k-th exact distance is refined too, which with policy all and hperc
    100 gives the exact answer.
    """

    hperc: float = 10.0
    floor_rk: bool = True
    rerank: float = 2.0
    threshold: float | None = None
    policy: str = "both"
    nprobe: int = 1
    bound: str = "table"
    refine: bool = True
    exact_stop: bool = False
    mode: str = "exact"


def passing(batch: dict[str, np.ndarray], predicate: predicates.Predicate, attributes, mode: str, n: int) -> np.ndarray:
    """Array twin of filters.mask: cells are looked up, conditions combined, straddling cells compared by number."""
    if not predicate:
        return np.ones(n, bool)
    total = np.zeros(n, bool)
    for clause in predicate:
        held = np.ones(n, bool)
        for c in clause:
            a = attributes[c.attribute]
            table = np.array([*predicates.cell_pass(c, a), predicates.FAIL])  # the last entry is for null
            state = table[batch[f"c_{a.name}"]]
            ok = state == predicates.PASS
            if mode != "strict" and (state == predicates.STRADDLE).any():
                i, x = predicates.interval(c, a), batch[f"x_{a.name}"]
                ok |= (state == predicates.STRADDLE) & (np.ones(n, bool) if mode == "inclusive" else ((x > i.lo) if i.lo_open else (x >= i.lo)) & ((x < i.hi) if i.hi_open else (x <= i.hi)))
            held &= ok
        total |= held
    return total


def _attribute_columns(t, attributes) -> dict[str, np.ndarray]:
    out = {}
    for a in attributes:
        code = t.column(f"c_{a}")
        code = code.combine_chunks() if isinstance(code, pa.ChunkedArray) else code
        out[f"c_{a}"] = code.fill_null(-1).to_numpy(zero_copy_only=False)
        x = t.column(f"x_{a}")
        out[f"x_{a}"] = x.to_numpy(zero_copy_only=False) if isinstance(x, pa.Array) else x.to_numpy()
    return out


def counts(index: Index, preds: dict[str, predicates.Predicate], mode: str = "exact") -> DataFrame:
    """pred, part_id, n_pass. Only attribute columns are read; sums are made within tasks before the shuffle."""
    kinds, names = index.attributes, sorted(index.attributes)
    columns = [f"{p}{a}" for a in names for p in ("c_", "x_")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[str, int], int] = {}
        for batch in batches:
            t = pa.Table.from_batches([batch])
            part, held = t.column("part_id").to_numpy(), _attribute_columns(t, names)
            for text, p in preds.items():
                hit = passing(held, p, kinds, mode, len(part))
                for q, n in zip(*np.unique(part[hit], return_counts=True)):
                    total[text, int(q)] = total.get((text, int(q)), 0) + int(n)
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in total], pa.string()), pa.array([k[1] for k in total], pa.int32()), pa.array([*total.values()], pa.int64())], names=["pred", "part_id", "n_pass"])

    parts = index.rows.select("part_id", *columns).mapInArrow(run, "pred string, part_id int, n_pass long")
    return parts.groupBy("pred", "part_id").agg(F.sum("n_pass").alias("n_pass"))


CANDIDATES = "query_id long, part_id int, chunk int, vec_id long, bound double, n_filter long, n_low long"


#: Queries whose bounds of all rows are taken together; rows unpacked at once, and codes kept unpacked; queries of a task at most.
BLOCK, UNPACKED, CODES, HELD = 64, 4096, 64_000_000, 16_384


def nearest_codes(words: np.ndarray, query: np.ndarray, left: int) -> np.ndarray:
    """Places of the left rows of least Hamming distance; of equal ones the first."""
    ham = np.bitwise_count(words ^ query).sum(1, dtype=np.int32) if words.shape[1] > 1 else np.bitwise_count(words[:, 0] ^ query[0])
    upto = np.cumsum(np.bincount(ham))
    edge = int(np.searchsorted(upto, left))
    stays = ham <= edge
    if upto[edge] > left:
        stays[np.flatnonzero(ham == edge)[left - upto[edge] :]] = False
    return np.flatnonzero(stays)


def least(bound: np.ndarray, n: int) -> np.ndarray:
    """Places of the n least, in order; of equal ones the first."""
    at = np.flatnonzero(bound <= np.partition(bound, n - 1)[n - 1]) if len(bound) > n else np.arange(len(bound))
    return at[np.argsort(bound[at], kind="stable")][:n]


def scanner(index: Index, plan: Plan, k: int):
    """Packed rows of one chunk and queries that visit it into candidates: the whole partition-local part.

    Rows are unpacked once for all queries, and bounds by tables are summed for blocks of queries where at least a fifth
    of the rows are left of pruning.
    """
    d, kinds, names, raw = index.d, index.attributes, sorted(index.attributes), index.cfg.lowbit_space == "raw"

    def run(rows: pa.Table, load: pa.Table) -> pa.Table:
        out: list[list[np.ndarray]] = [[] for _ in range(7)]
        if rows.num_rows and load.num_rows:
            m = {c: load.column(c)[0].as_py() for c in ("mean", "rotation", "bits", "edges", "low_mean", "queries")}
            rows = rows.sort_by("vec_id")  # of equals the first stay
            ids, part, chunk = rows.column("vec_id").to_numpy(), rows.column("part_id")[0].as_py(), rows.column("chunk")[0].as_py()
            packed = np.frombuffer(b"".join(rows.column("packed").to_pylist()), np.uint8).reshape(len(ids), -1)
            low = _words(np.frombuffer(b"".join(rows.column("low").to_pylist()), np.uint8).reshape(len(ids), -1))
            held = _attribute_columns(rows, names)
            edges = [np.array(e) for e in m["edges"]]
            mean, turn = np.array(m["mean"]), np.array(m["rotation"]).reshape(d, d)
            kind = np.uint16 if max(m["bits"], default=0) <= 16 else np.int64

            def unpacked(own: np.ndarray) -> np.ndarray:
                codes = np.empty((len(own), d), kind)
                for at in range(0, len(own), UNPACKED):
                    codes[at : at + UNPACKED] = segments.unpack_matrix(own[at : at + UNPACKED], m["bits"])
                return codes

            every = unpacked(packed) if packed.shape[0] * d <= CODES else None
            texts: dict[str, list[dict]] = {}
            for q in m["queries"]:
                texts.setdefault(q["pred"] or "", []).append(q)
            for text, own in texts.items():
                some = np.flatnonzero(passing(held, predicates.parse(text), kinds, plan.mode, len(ids)))
                n_filter = len(some)
                if not n_filter:
                    continue
                floor = int(np.ceil(plan.rerank * k)) if plan.floor_rk else 0
                left = min(n_filter, max(int(np.ceil(plan.hperc * n_filter / 100)), floor))
                words, some_ids = low[some] if left < n_filter else None, ids[some]
                codes = None if every is None else every[some] if n_filter < len(ids) else every
                together = plan.bound == "table" and codes is not None and 5 * left >= n_filter
                for first in range(0, len(own), BLOCK):
                    block = own[first : first + BLOCK]
                    xs = [np.array(q["qvec"]) for q in block]
                    ys = [(x - mean) @ turn for x in xs]
                    if together:
                        tables = [lowerbound.table(y, edges) for y in ys]
                        tables, bounds = [np.stack([t[j] for t in tables], axis=1) for j in range(d)], np.empty((len(ys), n_filter))
                        for at in range(0, n_filter, UNPACKED):
                            bounds[:, at : at + UNPACKED] = np.sqrt(looked_up(tables, codes[at : at + UNPACKED])).T
                    for b, (q, x, y) in enumerate(zip(block, xs, ys)):
                        at = nearest_codes(words, _words(lowbit.pack_signs(((x if raw else y) - np.array(m["low_mean"]))[None, :]))[0], left) if left < n_filter else slice(None)
                        if together:
                            bound = bounds[b][at]
                        else:
                            mine = codes[at] if codes is not None else unpacked(packed[some[at]])
                            if plan.bound == "fused":
                                bound = lowerbound.fused(mine, y, edges, m["bits"])
                            elif plan.bound == "table":
                                bound = lowerbound.by_table(np.ascontiguousarray(mine.T, np.intp).T, lowerbound.table(y, edges))
                            else:
                                bound = (lowerbound.direct if plan.bound == "direct" else lowerbound.centre)(mine, y, edges)
                        keep = np.flatnonzero(bound <= q["most"] + 1e-9) if q["most"] is not None else least(bound, max(1, int(np.ceil(plan.rerank * k))))
                        n = len(keep)
                        for column, v in zip(out, (np.full(n, q["query_id"]), np.full(n, part, np.int32), np.full(n, chunk, np.int32), some_ids[at][keep], bound[keep], np.full(n, n_filter), np.full(n, left))):
                            column.append(v)
        types = (np.int64, np.int32, np.int32, np.int64, np.float64, np.int64, np.int64)
        return pa.table([pa.array(np.concatenate(c).astype(t) if c else np.zeros(0, t)) for c, t in zip(out, types)], names=["query_id", "part_id", "chunk", "vec_id", "bound", "n_filter", "n_low"])

    return run


def _words(signs: np.ndarray) -> np.ndarray:
    """Rows of bytes as rows of 64-bit words, zeros behind."""
    return np.pad(signs, ((0, 0), (0, -signs.shape[1] % 8))).view(np.uint64)


def slices(queries: DataFrame, groups: int) -> int:
    """Parts into which the queries of each of so many groups are split: a task each or more, but not of a few queries."""
    tasks, n = int(queries.sparkSession.conf.get("spark.sql.shuffle.partitions")), queries.count()
    return max(1, min(-(-2 * tasks // max(groups, 1)), -(-n // BLOCK)), -(-n // HELD))


def visit(index: Index, queries: DataFrame, reached: DataFrame, plan: Plan, k: int) -> DataFrame:
    """Candidates of all visited (query, partition) pairs. A partition's queries travel to it as payloads (M41), one a slice."""
    queries = queries if "most" in queries.columns else queries.withColumn("most", F.lit(None).cast("double"))
    chunks = index.rows.groupBy("part_id").agg(F.max("chunk").alias("last"))
    n = slices(queries, chunks.agg(F.sum(F.col("last") + 1)).first()[0] or 0)
    sliced = reached.select("query_id", "part_id").join(queries, "query_id").withColumn("slice", F.pmod(F.xxhash64("query_id"), F.lit(n)).cast("int"))
    each = sliced.groupBy("part_id", "slice").agg(F.collect_list(F.struct("query_id", "qvec", "pred", "most")).alias("queries"))
    load = each.join(index.models, "part_id")
    chunks = chunks.select((F.col("part_id") + 0).alias("part_id"), F.explode(F.sequence(F.lit(0), F.col("last"))).alias("chunk"))
    rows = index.rows.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    by = ("part_id", "chunk", "slice")
    return rows.groupBy(*by).cogroup(load.join(chunks, "part_id").groupBy(*by)).applyInArrow(scanner(index, plan, k), CANDIDATES)


def refined(index: Index, queries: DataFrame, candidates: DataFrame) -> DataFrame:
    """Candidates with their exact distance from the full vectors, fetched by key."""
    full = candidates.join(index.vectors.select(F.col("part_id").alias("_p"), F.col("vec_id").alias("_v"), "embedding"), (F.col("part_id") == F.col("_p")) & (F.col("vec_id") == F.col("_v")))
    return full.join(queries.select("query_id", "qvec"), "query_id").withColumn("dist", F.round(l2(F.col("qvec"), F.col("embedding")), 9)).select(*candidates.columns, "dist")


def topk(hits: DataFrame, k: int, by: str = "dist", *group: str) -> DataFrame:
    """query_id, rank, vec_id, dist: the k nearest; Spark cuts each task's list to k before the shuffle."""
    w = Window.partitionBy("query_id", *group).orderBy(by, "vec_id")
    return hits.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", *group, "rank", "vec_id", F.col(by).alias("dist"))


def topk_tree(hits: DataFrame, k: int, fan: int = 4) -> DataFrame:
    """The same by levels: lists of partitions are merged in groups of fan until one is left."""
    level = hits.withColumn("node", F.col("part_id"))
    n = (hits.agg(F.max("part_id")).first()[0] or 0) + 1
    while n > 1:
        n = -(-n // fan)
        level = level.withColumn("node", F.floor(F.col("node") / fan))
        level = topk(level, k, "dist", "node")
    return topk(level, k)


def with_predicates(queries: DataFrame, pred: str = "") -> DataFrame:
    return queries if "pred" in queries.columns else queries.withColumn("pred", F.lit(pred))


def reach(index: Index, queries: DataFrame, plan: Plan, k: int) -> DataFrame:
    """The visit plan of all queries."""
    texts = [r["pred"] or "" for r in queries.select("pred").distinct().collect()]  # predicates of a batch are parsed by the driver
    found = counts(index, {t: predicates.parse(t) for t in texts}, plan.mode)
    by_query = queries.select("query_id", F.coalesce("pred", F.lit("")).alias("pred")).join(found, "pred").select("query_id", "part_id", "n_pass")
    ranked = select.rank(queries.select("query_id", "qvec"), index.centroids)
    return select.reach(ranked, by_query, index.threshold if plan.threshold is None else plan.threshold, k, plan.policy, plan.nprobe)


def search(index: Index, queries: DataFrame, k: int = 10, plan: Plan = Plan()) -> DataFrame:
    """query_id, rank, vec_id, dist for queries (query_id, qvec[, pred]).

    A query with fewer than k passing rows gets them all.
    """
    queries = with_predicates(queries)
    reached = reach(index, queries, plan, k)
    found = visit(index, queries, reached, plan, k)
    if not plan.refine:
        return topk(found, k, "bound")
    exact = refined(index, queries, found)
    if plan.exact_stop:
        reached = stored(reached, "reach")
        bound = topk(exact, k).groupBy("query_id").agg(F.when(F.count(F.lit(1)) >= k, F.max("dist")).otherwise(F.lit(float("inf"))).alias("most"))
        limited = queries.join(stored(bound, "bounds"), "query_id")
        exact = refined(index, limited, visit(index, limited, reached, plan, k))
    return topk(exact, k)


def funnel(index: Index, queries: DataFrame, k: int = 10, plan: Plan = Plan()) -> DataFrame:
    """Rows left after each stage, by query: n_rows, n_filter, n_low, n_short, n_visited."""
    queries = with_predicates(queries)
    reached = stored(reach(index, queries, plan, k), "reach")
    found = visit(index, queries, reached, plan, k)
    total = index.rows.count()
    by_part = found.groupBy("query_id", "part_id", "chunk").agg(F.max("n_filter").alias("n_filter"), F.max("n_low").alias("n_low"), F.count(F.lit(1)).alias("n_short"))
    sums = by_part.groupBy("query_id").agg(*[F.sum(c).alias(c) for c in ("n_filter", "n_low", "n_short")])
    visited = reached.groupBy("query_id").agg(F.count(F.lit(1)).alias("n_visited"))
    return sums.join(visited, "query_id").withColumn("n_rows", F.lit(total))
