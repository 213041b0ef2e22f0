"""Queries against rows by matrix products: what brute force, radius joins and bounds over all pairs run on.

Queries and rows are dealt to the cells of a grid, one a task, where every query of a group meets every row of another.
A task holds its queries and takes its rows batch by batch. Products only sift: what they leave within their error is
computed again term by term, in the order of functions.vectors, so answers do not depend on how products are summed.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Queries a task holds at most, and how many of them, and rows, one product takes.
HELD, QUERIES, ROWS = 16_384, 2048, 2048
#: Pairs whose terms are taken at once, few enough for the cache.
PAIRS = 1024
#: Distances this close can be equal once rounded to nine decimals.
NEAR = 1.1e-9


def usable(vector: str):
    """True for vectors without null or non-finite components."""
    bad = F.exists(F.col(vector), lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(F.col(vector).isNotNull() & (F.size(vector) > 0) & ~bad, F.lit(False))


def meet(queries: DataFrame, rows: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str, by: str | None = None) -> DataFrame:
    """run over each cell's batches (kind, by, id, v), all queries (kind 0) before the rows (kind 1): see cells."""
    return cells(queries, rows, by).mapInArrow(run, schema)


def cells(queries: DataFrame, rows: DataFrame, by: str | None = None) -> DataFrame:
    """kind, by, id, v: a cell of the grid in each partition, its queries (kind 0) before its rows (kind 1).

    queries: query_id, qvec[, by]; rows: vec_id, embedding[, by]. With by, only queries and rows of one value meet, and
    rows go only to the cells of their value. Null ids and vectors that are not usable take no part.
    """
    spark = rows.sparkSession
    key = F.col(by).cast("long") if by else F.lit(0).cast("long")
    left = queries.where(usable("qvec") & F.col("query_id").isNotNull()).select(key.alias("by"), F.col("query_id").cast("long").alias("id"), F.col("qvec").alias("v")).where("by IS NOT NULL")
    right = rows.where(usable("embedding") & F.col("vec_id").isNotNull()).select(key.alias("by"), F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("v")).where("by IS NOT NULL")
    sizes = left.groupBy("by").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("all"), F.max("n").alias("most")).first()
    total, most = sizes["all"] or 0, sizes["most"] or 0
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    groups = max(1, -(-total // HELD), min(round((tasks / 10) ** 0.5), total))
    split = max(1, -(-groups * most // max(total, 1)))  # groups over which the queries of one value are spread
    deals = max(1, tasks // groups)
    first = F.xxhash64("by") if by else F.lit(0).cast("long")
    group = lambda s: F.pmod(F.pmod(first, F.lit(groups)) + s, F.lit(groups))
    own = group(F.pmod(F.xxhash64("id"), F.lit(split)))
    left = left.withColumn("deal", F.explode(F.sequence(F.lit(0), F.lit(deals - 1)))).select((own * deals + F.col("deal")).cast("int").alias("cell"), F.lit(0).alias("kind"), "by", "id", "v")
    right = right.withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(split - 1)))).select((group(F.col("s")) * deals + F.pmod(F.xxhash64("id"), F.lit(deals))).cast("int").alias("cell"), F.lit(1).alias("kind"), "by", "id", "v")
    dealt = left.unionByName(right).repartitionById(groups * deals, F.col("cell")).sortWithinPartitions("kind")
    return dealt.select("kind", "by", "id", "v")


@dataclass
class Side:
    """Vectors of one length and one value of by."""

    by: int
    ids: np.ndarray
    x: np.ndarray

    def __post_init__(self):
        self.sq = (self.x * self.x).sum(1)
        self.norm = np.sqrt(self.sq)


def parts(batch: pa.RecordBatch) -> Iterator[tuple[int, tuple[int, int], np.ndarray, np.ndarray]]:
    """(kind, (by, length), ids, matrix) of a batch."""
    kind, by, ids = (np.asarray(batch.column(i)) for i in range(3))
    lists = batch.column(3)
    sizes, values = np.diff(np.asarray(lists.offsets)), np.asarray(lists.flatten(), np.float64)
    firsts = np.cumsum(sizes) - sizes
    names, which = np.unique(np.stack([kind, by, sizes]), axis=1, return_inverse=True)
    if names.shape[1] == 1:
        yield int(kind[0]), (int(by[0]), int(sizes[0])), ids, values.reshape(len(ids), -1)
        return
    order = np.argsort(which.ravel(), kind="stable")
    for (k, b, d), own in zip(names.T, np.split(order, np.cumsum(np.bincount(which.ravel()))[:-1])):
        yield int(k), (int(b), int(d)), ids[own], values[firsts[own][:, None] + np.arange(d)]


def tiles(batches: Iterator[pa.RecordBatch], start: Callable[[Side], object], tile: Callable[[object, Side], Iterator | None], rows: int = ROWS) -> Iterator[tuple[object, object]]:
    """Calls start for each set of queries that are held, then tile with its state for each set of rows; gives (state, what tile gave)."""
    held: dict[tuple[int, int], list] = {}
    states: dict[tuple[int, int], object] = {}
    for batch in batches:
        if not batch.num_rows:
            continue
        for kind, name, ids, x in parts(batch):
            if kind == 0:
                held.setdefault(name, []).append((ids, x))
                continue
            if name in held:
                own = held.pop(name)
                states[name] = start(Side(name[0], np.concatenate([i for i, _ in own]), np.concatenate([m for _, m in own])))
            if name in states:
                for at in range(0, len(ids), rows):
                    yield states[name], tile(states[name], Side(name[0], ids[at : at + rows], x[at : at + rows]))


@dataclass(frozen=True)
class Metric:
    """sift: what products give, for a slice of queries; error: its greatest error; exact: term by term, for pairs."""

    name: str

    def sift(self, q: Side, s: slice, r: Side) -> np.ndarray:
        p = q.x[s] @ r.x.T
        if self.name == "l2":
            p *= -2
            p += q.sq[s, None]
            p += r.sq
            return p
        if self.name == "dot":
            return -p
        with np.errstate(divide="ignore", invalid="ignore"):
            return 1 - p / q.norm[s, None] / r.norm  # NaN for a zero vector, which has no cosine

    def error(self, q: Side, s: slice, r: Side) -> np.ndarray:
        unit = (q.x.shape[1] + 8) * 5e-16
        far = r.norm.max(initial=0)
        if self.name == "l2":
            return unit * (q.norm[s] + far) ** 2
        return unit * q.norm[s] * far if self.name == "dot" else np.full(len(q.norm[s]), 4 * unit)

    def limit(self, worst: np.ndarray) -> np.ndarray:
        """What sift may give for a distance of worst."""
        return worst * worst if self.name == "l2" else worst

    def exact(self, q: Side, r: Side, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out = np.empty(len(i))
        for at in range(0, len(i), PAIRS):
            s = slice(at, at + PAIRS)
            a, b = q.x[i[s]], r.x[j[s]]
            if self.name == "l2":
                a -= b
                a *= a
                out[s] = np.sqrt(_sum(a))
            elif self.name == "dot":
                out[s] = -_sum(a * b)
            else:
                out[s] = 1 - _sum(a * b) / (np.sqrt(_sum(a * a)) * np.sqrt(_sum(b * b)))
        return out


def _sum(terms: np.ndarray) -> np.ndarray:
    """Of each row, added from the first column on."""
    total = np.zeros(len(terms))
    for t in np.ascontiguousarray(terms.T):
        total += t
    return total


class Best:
    """The k nearest of each held query so far, and what may tie with the k-th once rounded. Of equal distances the k smallest ids stay."""

    def __init__(self, queries: Side, k: int, near: float = NEAR):
        self.queries, self.k, self.near = queries, k, near
        self.worst = np.full(len(queries.ids), np.inf)
        self.q, self.dist, self.ids = np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64)

    def add(self, q: np.ndarray, dist: np.ndarray, ids: np.ndarray) -> None:
        if not len(q):
            return
        lo, hi = np.searchsorted(self.q, (q.min(), q.max() + 1))  # what is held of other queries stays as it is
        held = (self.q, self.dist, self.ids)
        q, dist, ids = (np.concatenate([h[lo:hi], new]) for h, new in zip(held, (q, dist, ids)))
        order = np.lexsort((ids, dist, q))
        q, dist, ids = q[order], dist[order], ids[order]
        at = np.arange(len(q))
        first = np.searchsorted(q, q, "left")
        same = np.r_[True, (q[1:] != q[:-1]) | (dist[1:] != dist[:-1])]
        kth = np.flatnonzero(at - first == self.k - 1)
        self.worst[q[kth]] = dist[kth]
        stays = (dist <= self.worst[q] + self.near) & (at - np.maximum.accumulate(np.where(same, at, 0)) < self.k)
        self.q, self.dist, self.ids = (np.concatenate([h[:lo], new[stays], h[hi:]]) for h, new in zip(held, (q, dist, ids)))

    def batches(self) -> Iterator[pa.RecordBatch]:
        for at in range(0, len(self.q), 100_000):
            s = slice(at, at + 100_000)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(self.q[s]), self.queries.by)), pa.array(self.queries.ids[self.q[s]]), pa.array(self.ids[s]), pa.array(self.dist[s])], names=["by", "query_id", "vec_id", "dist"])


FOUND = "by long, query_id long, vec_id long, dist double"


def nearest(k: int, metric: str = "l2", other: bool = False, whole: bool = False, rows: int = ROWS, block: int = QUERIES, among: Callable[[Side], Callable[[slice, Side], np.ndarray]] | None = None):
    """For meet: each query's k nearest rows of a cell and their ties, as FOUND.

    other: a row with the query's id is left out. whole: components are whole numbers, and products of 2 ** 53 or more,
    which double precision does not hold exactly, are refused. rows, block: rows and queries of one product. among: for
    the queries held, a function that says which rows each of a slice of them may have; others get no distance.
    """
    m = Metric(metric)

    def start(q: Side) -> Best:
        best = Best(q, k)
        best.among = among(q) if among else None
        return best

    def tile(best: Best, r: Side) -> None:
        q = best.queries
        if whole and q.norm.max() * r.norm.max(initial=0) >= 2.0**53:
            raise ValueError("a product of 2 ** 53 or more is not exact in double precision")
        for at in range(0, len(q.ids), block):
            s = slice(at, at + block)
            own = best.among(s, r) if best.among else None
            if own is not None and 16 * np.count_nonzero(own) < own.size:  # these few cost less than products of all
                i, j = np.nonzero(own)
                i += at
                best.add(i, m.exact(q, r, i, j), r.ids[j])
                continue
            got, error = m.sift(q, s, r), m.error(q, s, r)
            if other:
                got[q.ids[s, None] == r.ids] = np.nan
            if own is not None:
                np.putmask(got, ~own, np.nan)
            limit = m.limit(best.worst[s] + best.near) + error
            new = np.flatnonzero(np.isinf(limit))
            if len(new) and got.shape[1] > k:
                ends = np.partition(got[new], k - 1, axis=1)[:, k - 1]  # NaN sorts last
                ends = np.sqrt(np.maximum(ends + error[new], 0)) if metric == "l2" else ends + error[new]
                limit[new] = np.where(np.isnan(ends), np.inf, m.limit(ends + best.near) + error[new])
            i, j = np.nonzero(got <= limit[:, None])
            i += at
            best.add(i, m.exact(q, r, i, j), r.ids[j])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done: dict[int, Best] = {}
        for best, _ in tiles(batches, start, tile, rows):
            done[id(best)] = best
        for best in done.values():
            yield from best.batches()

    return run


# Bounds from cells


def looked_up(tables: list[np.ndarray], codes: np.ndarray) -> np.ndarray:
    """(rows, queries): for each row the sum of its codes' entries. tables: (cells, queries) of each dimension."""
    out = np.zeros((len(codes), tables[0].shape[1]))
    entries = np.empty_like(out[:512])
    for at in range(0, len(codes), 512):
        part, own = out[at : at + 512], codes[at : at + 512]
        for j, t in enumerate(tables):
            part += np.take(t, own[:, j], axis=0, out=entries[: len(own)], mode="clip")  # codes lie in the tables
    return out


def rounded(x: np.ndarray, digits: int) -> np.ndarray:
    return np.floor(x * 10.0**digits + 0.5) / 10.0**digits


class Bounds:
    """For meet: lower bounds of the distances from the edges of the cells that a row's components are in.

    Bounds and distances are rounded to seven decimals. Queries are taken in blocks of few enough for their tables to
    stay in the cache.
    """

    BLOCK = 256

    def __init__(self, edges: list[np.ndarray]):
        self.edges = edges

    def tables(self, q: Side, s: slice) -> list[np.ndarray]:
        gaps = [np.maximum(np.maximum(e[:-1, None] - x, x - e[1:, None]), 0.0) for e, x in zip(self.edges, q.x[s].T)]
        return [g * g for g in gaps]

    def codes(self, r: Side) -> np.ndarray:
        return np.stack([np.clip(np.searchsorted(e, x, "right") - 1, 0, len(e) - 2) for e, x in zip(self.edges, r.x.T)], axis=1)

    def blocks(self, q: Side, r: Side) -> Iterator[tuple[slice, np.ndarray]]:
        """(queries, bounds not rounded), block by block."""
        codes = self.codes(r)
        for at in range(0, len(q.ids), self.BLOCK):
            s = slice(at, min(at + self.BLOCK, len(q.ids)))
            yield s, np.sqrt(looked_up(self.tables(q, s), codes)).T

    def pairs(self, q: Side, r: Side) -> Iterator[tuple[slice, np.ndarray, np.ndarray]]:
        """(queries, bounds, distances)."""
        m = Metric("l2")
        for s, bound in self.blocks(q, r):
            square = m.sift(q, s, r)
            dist = np.sqrt(np.maximum(square, 0))
            i, j = np.nonzero(square < 1e-4 * (q.sq[s, None] + r.sq))  # cancelled, so not from products
            dist[i, j] = m.exact(q, r, i + s.start, j)
            yield s, rounded(bound, 7), rounded(dist, 7)

    def all(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """query_id, vec_id, bound of every pair."""

        def tile(q: Side, r: Side):
            for s, bound in self.blocks(q, r):
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(q.ids[s], len(r.ids))), pa.array(np.tile(r.ids, bound.shape[0])), pa.array(rounded(bound, 7).ravel())], names=["query_id", "vec_id", "bound"])

        for _, got in tiles(batches, lambda q: q, tile):
            yield from got

    def shortlist(self, k: int):
        """The k rows of least bound of each query, and what ties with them, as FOUND."""

        def start(q: Side) -> list[Best]:
            return [Best(Side(q.by, q.ids[at : at + self.BLOCK], q.x[at : at + self.BLOCK]), k, 1.1e-7) for at in range(0, len(q.ids), self.BLOCK)]

        def tile(bests: list[Best], r: Side) -> None:
            codes = self.codes(r)
            for best in bests:
                bound = np.sqrt(looked_up(self.tables(best.queries, slice(None)), codes)).T
                limit = best.worst + best.near
                if bound.shape[1] > k:
                    new = np.flatnonzero(np.isinf(limit))
                    limit[new] = np.partition(bound[new], k - 1, axis=1)[:, k - 1] + best.near
                i, j = np.nonzero(bound <= limit[:, None])
                best.add(i, bound[i, j], r.ids[j])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            done = {}
            for bests, _ in tiles(batches, start, tile):
                done[id(bests)] = bests
            for bests in done.values():
                for best in bests:
                    yield from best.batches()

        return run

    TIGHTNESS = "total double, n long, violations long, pairs long"

    def tightness(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Sum and number of bound over distance (0 left out), bounds above their distance, pairs: one row a task."""
        total, n, over, pairs = 0.0, 0, 0, 0

        def tile(q: Side, r: Side):
            yield from self.pairs(q, r)

        for _, got in tiles(batches, lambda q: q, tile):
            for _, bound, dist in got:
                some = dist > 0
                total, n = total + float((bound[some] / dist[some]).sum()), n + int(some.sum())
                over, pairs = over + int((bound > dist + 1e-6).sum()), pairs + bound.size
        yield pa.RecordBatch.from_arrays([pa.array([total]), pa.array([n]), pa.array([over]), pa.array([pairs])], names=["total", "n", "violations", "pairs"])

    MOMENTS = "query_id long, n long, a double, b double, aa double, bb double, ab double"

    def moments(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """For each query and row batch: number, means, sums of squares and of products about them, of bound and distance."""

        def tile(q: Side, r: Side):
            for s, x, y in self.pairs(q, r):
                a, b = x.mean(1), y.mean(1)
                x, y = x - a[:, None], y - b[:, None]
                columns = [q.ids[s], np.full(len(a), x.shape[1]), a, b, (x * x).sum(1), (y * y).sum(1), (x * y).sum(1)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["query_id", "n", "a", "b", "aa", "bb", "ab"])

        for _, got in tiles(batches, lambda q: q, tile):
            yield from got


def correlated(moments: DataFrame) -> DataFrame:
    """query_id, pearson from the parts that Bounds.moments gives; null where a side does not vary."""
    every = Window.partitionBy("query_id")
    mean = lambda c: F.sum(F.col("n") * F.col(c)).over(every) / F.sum("n").over(every)
    off = moments.withColumns({"da": F.col("a") - mean("a"), "db": F.col("b") - mean("b")})
    part = lambda s, u, w: F.sum(F.col(s) + F.col("n") * F.col(u) * F.col(w))
    sums = off.groupBy("query_id").agg(part("aa", "da", "da").alias("aa"), part("bb", "db", "db").alias("bb"), part("ab", "da", "db").alias("ab"))
    return sums.select("query_id", F.try_divide("ab", F.sqrt(F.col("aa") * F.col("bb"))).alias("pearson"))


# The n least of each query


#: Bins of a round; rows in a range that are listed instead; queries and rows whose scores are taken together.
BINS, LISTED, BLOCK, SCORED = 256, 64, 256, 2048
LAST = np.uint64(2**64 - 1)


def places(ids: np.ndarray) -> np.ndarray:
    """Ids as unsigned numbers of the same order."""
    return ids.astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)


@dataclass
class Cuts:
    """For each query (ids, ascending) the last of its n least rows, by score and then by id, or what is known of it.

    score and place: that row's, as unsigned numbers, where done. Otherwise it is the need-th row of low .. high, a range
    of scores or, with tied, of places of rows of that score. listed: that range holds few rows. known: the range is set,
    which it is after the first round for all.
    """

    ids: np.ndarray
    done: np.ndarray
    known: np.ndarray
    tied: np.ndarray
    listed: np.ndarray
    score: np.ndarray
    place: np.ndarray
    low: np.ndarray
    high: np.ndarray
    need: np.ndarray

    @classmethod
    def of(cls, ids: np.ndarray, n: int) -> Cuts:
        ids = np.unique(ids)
        no, full = (lambda: np.zeros(len(ids), bool)), (lambda: np.full(len(ids), LAST))
        return cls(ids, no(), no(), no(), no(), full(), full(), full(), full(), np.full(len(ids), n, np.int64))

    def at(self, ids: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.ids, ids)


def shifts(span: np.ndarray) -> np.ndarray:
    """By how many bits offsets of up to span are shifted to be bins."""
    bits = np.array([int(s).bit_length() for s in span.ravel()], np.int64)
    return np.maximum(bits - (BINS.bit_length() - 1), 0).astype(np.uint64).reshape(span.shape)


@dataclass
class Scores:
    """Scores of pairs, sums of a row's codes' entries in a query's tables, as unsigned numbers of the same order.

    They are made term by term, so a pair has the same score in each pass, whatever it is met with. books: centroids
    (cells, dimensions) of each of parts, sets of dimensions.
    """

    books: list[np.ndarray]
    parts: list[np.ndarray]

    def tables(self, x: np.ndarray) -> list[np.ndarray]:
        """(cells, queries) of each part: squared distances."""
        return [sum((b[:, i, None] - x[:, j]) ** 2 for i, j in enumerate(p)) for b, p in zip(self.books, self.parts)]

    def codes(self, x: np.ndarray) -> np.ndarray:
        """(rows, parts): the nearest centroid, of equally near ones the first."""
        return np.stack([t.argmin(0) for t in self.tables(x)], axis=1)

    @staticmethod
    def span(tables: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """The least and the greatest score that the queries' tables can give."""
        return sum(t.min(0) for t in tables).view(np.uint64), sum(t.max(0) for t in tables).view(np.uint64)

    def least(self, cuts: Cuts) -> Callable[[Side], Callable[[slice, Side], np.ndarray]]:
        """For nearest: the rows up to the cuts."""

        def start(q: Side):
            own, tables, last = cuts.at(q.ids), {}, [None, None]

            def among(s: slice, r: Side) -> np.ndarray:
                if last[0] is not r:
                    last[:] = r, self.codes(r.x)
                if s.start not in tables:
                    tables[s.start] = self.tables(q.x[s])
                score = looked_up(tables[s.start], last[1]).view(np.uint64)
                edge = cuts.score[own[s]]
                up = score < edge
                i, j = np.divmod(np.flatnonzero(score == edge), len(edge))
                up[i, j] = places(r.ids)[i] <= cuts.place[own[s]][j]
                return np.ascontiguousarray(up.T)

            return among

        return start

    COUNTED = "query_id long, low long, high long, bins binary, listed binary"

    def counted(self, cuts: Cuts):
        """For meet: for each query that is not done the rows of a cell in its range, by bin or, where they are few, score and place."""

        def start(q: Side) -> list[list]:
            own, blocks = cuts.at(q.ids), []
            for kind in ((False, False), (False, True), (True, False), (True, True)):
                some = np.flatnonzero(~cuts.done[own] & (cuts.tied[own] == kind[0]) & (cuts.listed[own] == kind[1]))
                for first in range(0, len(some), BLOCK):
                    which = some[first : first + BLOCK]
                    at, tables = own[which], self.tables(q.x[which])
                    low, high = np.where(cuts.known[at], (cuts.low[at], cuts.high[at]), self.span(tables))
                    blocks.append([q.ids[which], cuts.known[at].all(), *kind, cuts.score[at], low, high, shifts(high - low), tables, np.zeros((len(which), BINS), np.uint32), []])
            return blocks

        def tile(blocks: list[list], r: Side) -> None:
            codes, place = self.codes(r.x), places(r.ids)
            for ids, known, tied, listed, score, low, high, shift, tables, bins, few in blocks:
                got = looked_up(tables, codes).view(np.uint64)
                if not known:  # all rows are in the range
                    got -= low
                    got >>= shift
                    flat = got.view(np.int64)
                    flat += np.arange(len(ids)) * BINS
                    bins += np.bincount(flat.ravel(), minlength=bins.size).reshape(bins.shape).astype(np.uint32)
                    continue
                off = (np.broadcast_to(place[:, None], got.shape) if tied else got) - low
                inside = off <= high - low
                if tied:
                    inside &= got == score
                i, j = np.divmod(np.flatnonzero(inside), len(ids))
                if listed:
                    few.append((j, got[i, j], place[i]))
                else:
                    flat = j * BINS + (off[i, j] >> shift[j]).astype(np.int64)
                    bins += np.bincount(flat, minlength=bins.size).reshape(bins.shape).astype(np.uint32)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            done = {}
            for blocks, _ in tiles(batches, start, tile, SCORED):
                done[id(blocks)] = blocks
            for blocks in done.values():
                for ids, _, _, listed, _, low, high, _, _, bins, few in blocks:
                    j, score, place = (np.concatenate(c) for c in zip(*few)) if few else (np.zeros(0, np.uint64),) * 3
                    pairs = [np.stack([score[j == q], place[j == q]]).tobytes() for q in range(len(ids))] if listed else [None] * len(ids)
                    sums = [None] * len(ids) if listed else [b.tobytes() for b in bins]
                    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(low.view(np.int64)), pa.array(high.view(np.int64)), pa.array(sums, pa.binary()), pa.array(pairs, pa.binary())], names=["query_id", "low", "high", "bins", "listed"])

        return run


FOUND_IN = "query_id long, low long, high long, a long, b long, n long"


def placed(cuts: Cuts):
    """Where the cells' counts of a query put its need-th row: its bin, the rows before and in it; or its score and place (n: -1); nothing where fewer rows are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, list] = {}
        for batch in batches:
            for q, low, high, bins, listed in zip(*(batch.column(i).to_pylist() for i in range(5))):
                t = total.setdefault(q, [low, high, np.zeros(BINS, np.int64), []])
                if bins is not None:
                    t[2] += np.frombuffer(bins, np.uint32)
                elif listed:
                    t[3].append(np.frombuffer(listed, np.uint64).reshape(2, -1))
        out: list[tuple] = []
        for q, (low, high, bins, listed) in total.items():
            at = int(cuts.at(np.array([q]))[0])
            need = int(cuts.need[at])
            if cuts.listed[at]:
                score, place = np.concatenate(listed, axis=1)
                last = np.lexsort((place, score))[need - 1]
                out.append((q, low, high, int(score[last].view(np.int64)), int(place[last].view(np.int64)), -1))
            elif need < (upto := np.cumsum(bins))[-1]:
                b = int(np.searchsorted(upto, need))
                out.append((q, low, high, b, int(upto[b] - bins[b]), int(bins[b])))
        names = ["query_id", "low", "high", "a", "b", "n"]
        yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], pa.int64()) for i in range(6)], names=names)

    return run


def cuts(queries: DataFrame, rows: DataFrame, n: int, scores: Scores) -> Cuts:
    """Where each query's n least rows end, by score and then by id; no rows are listed but the last few that are left to choose from.

    Rounds count the rows of a range in bins and go on in the bin where the n-th is; a query is done as soon as a bin ends
    with it. Rows that share a score are told apart by their ids in the same way. The driver holds a few numbers a query.
    """
    found = Cuts.of(queries.select(F.col("query_id").cast("long")).where("query_id IS NOT NULL").toArrow().column(0).to_numpy(), n)
    first, last = rows.agg(F.min("vec_id").cast("long"), F.max("vec_id").cast("long")).first()
    if first is None:
        return found
    ends = places(np.array([first, last]))
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    grid = cells(queries, rows).persist()  # dealt once for all rounds
    while not found.done.all():
        counts = grid.mapInArrow(scores.counted(found), Scores.COUNTED)
        got = counts.repartition(tasks, "query_id").mapInArrow(placed(found), FOUND_IN).toArrow()
        at = found.at(got.column("query_id").to_numpy())
        low, high, a, b = (got.column(c).to_numpy().view(np.uint64) for c in ("low", "high", "a", "b"))
        size = got.column("n").to_numpy()
        whole = ~found.done  # those without an answer have no more than n rows: all of them are taken
        whole[at] = False
        found.done[whole] = True
        ended = size < 0
        found.score[at[ended]], found.place[at[ended]], found.done[at[ended]] = a[ended], b[ended], True
        at, low, high, a, b, size = (c[~ended] for c in (at, low, high, a, b, size))
        shift = shifts(high - low)
        low = low + (a << shift)
        high = low + np.minimum((np.uint64(1) << shift) - np.uint64(1), high - low)
        need, tied = found.need[at] - b.view(np.int64), found.tied[at]
        over = (need == size) | (tied & (low == high))
        found.done[at[over]] = True
        found.score[at[over & ~tied]], found.place[at[over & tied]] = high[over & ~tied], high[over & tied]
        same = ~over & ~tied & (low == high)
        found.tied[at[same]], found.score[at[same]] = True, low[same]
        found.low[at], found.high[at] = np.where(same, ends[0], low), np.where(same, ends[1], high)
        found.need[at], found.listed[at], found.known[at] = need, size <= LISTED, True
    grid.unpersist()
    return found


# Radius


def within(radius: float, inclusive: bool):
    """For meet: the pairs no farther than radius (not inclusive: nearer), as FOUND with the distance not rounded."""
    m = Metric("l2")

    def tile(q: Side, r: Side) -> Iterator[pa.RecordBatch]:
        for at in range(0, len(q.ids), QUERIES):
            s = slice(at, at + QUERIES)
            i, j = np.nonzero(m.sift(q, s, r) <= (m.limit(np.array([radius])) * (1 + 1e-12) + m.error(q, s, r))[:, None])
            i += at
            dist = m.exact(q, r, i, j)
            keep = dist <= radius if inclusive else dist < radius
            yield pa.RecordBatch.from_arrays([pa.array(np.full(int(keep.sum()), q.by)), pa.array(q.ids[i[keep]]), pa.array(r.ids[j[keep]]), pa.array(dist[keep])], names=["by", "query_id", "vec_id", "dist"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, got in tiles(batches, lambda q: q, tile):
            yield from got

    return run


COUNTED = "query_id long, nearest double, n long"


def counted(radius: float):
    """For meet: for each query the rows of a cell no farther than radius and the distance of the nearest of them, as COUNTED."""
    m = Metric("l2")

    def start(q: Side):
        return q, np.full(len(q.ids), np.inf), np.zeros(len(q.ids), np.int64)

    def tile(state, r: Side) -> None:
        q, nearest, n = state
        for at in range(0, len(q.ids), QUERIES):
            s = slice(at, at + QUERIES)
            got, error = m.sift(q, s, r), m.error(q, s, r)[:, None]
            edge = radius * radius * np.array([1 - 1e-12, 1 + 1e-12]) + error * np.array([-1, 1])
            sure = got < edge[:, :1]
            n[s] += sure.sum(1)
            first = np.minimum(got.min(1, keepdims=True) + 2 * error, edge[:, 1:])
            i, j = np.nonzero((got <= first) | ((got <= edge[:, 1:]) & ~sure))
            open_ = ~sure[i, j]
            i += at
            dist = m.exact(q, r, i, j)
            np.add.at(n, i[open_ & (dist <= radius)], 1)
            np.minimum.at(nearest, i[dist <= radius], dist[dist <= radius])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done = {}
        for state, _ in tiles(batches, start, tile):
            done[id(state)] = state
        for q, nearest, n in done.values():
            yield pa.RecordBatch.from_arrays([pa.array(q.ids[n > 0]), pa.array(nearest[n > 0]), pa.array(n[n > 0])], names=["query_id", "nearest", "n"])

    return run
