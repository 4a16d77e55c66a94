"""Approximate nearest neighbours by a forest of sorted hash strings.

Vectors are dealt into blocks of bounded size by a hash of their ids. A block holds a forest: each tree is a sorted array of long hash
strings, whose bits say on which side of a plane a vector lies; planes have random directions and pass through the middle of a
bounded sample of the block. A query descends each tree by bisection to its longest matching prefix, which has another
length in each tree and for each query. From the longest of them on it ascends all trees together, a bit at a time; each step adds,
from every tree, all strings that share the shorter prefix, until it has met ``budget`` vectors. What is met is ranked by exact distances
in double precision, and the best of all blocks are merged.

How many vectors must be met is measured, not guessed: some rows of each block are asked against all of it, and the budget is the
smallest with which the ascent meets their true neighbours with the target recall. So a query in a dense place stops at a long
prefix, one in the open goes on; the share of a block that it meets is given by ``Forest.met``.

Equal vectors of a block are one entry of its trees with their ``k + 1`` smallest ids, since no others can be among the ``k`` nearest. A level is
taken whole, so ties are never cut. The stated queries visit all blocks; queries are dealt into parts, so a task holds
one block and streams a bounded number of queries through it.

Behaviour at the edges: vectors that are null, empty or zero, or hold null or non-finite components, take no part, nor do those with a null id; a query
sees only vectors of its own length; rows of one id are one query, whose vector is any of them, and none is its own neighbour; an id that repeats is a
candidate once for each different vector; with fewer than ``k`` candidates all are returned; ties go to the smaller id; an empty table gives no rows; other columns
are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import map_arrow
from .vectors import by_group, grouped_stream, matrix, usable

TREES, BITS = 128, 32
BLOCK, QUERY_PART = 16_384, 20_000
TARGET_RECALL, PROBES, MEDIAN_ROWS = 0.95, 96, 2_000
AT_ONCE = 128


def bit_length(x: np.ndarray) -> np.ndarray:
    """Bits of each number below 2**53 up to its highest one."""
    return np.frexp(x.astype(np.float64))[1]


class Forest:
    """The sorted hash strings of the rows of one block, all of one length."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, k: int, trees: int = TREES, bits: int = BITS, target: float = TARGET_RECALL):
        self.k, self.trees, self.bits = k, trees, bits
        order = np.argsort(ids, kind="stable")
        x, first, which = np.unique(x[order] + 0.0, axis=0, return_index=True, return_inverse=True)
        self.x, self.owners = x, self._least_ids(ids[order], which.reshape(-1), k + 1)
        rng = np.random.default_rng(977)
        self.planes = rng.standard_normal((x.shape[1], trees * bits))
        some = x[np.argsort((ids[order][first].astype(np.uint64) * np.uint64(2654435761)) % np.uint64(1 << 32), kind="stable")[:MEDIAN_ROWS]]
        self.middle = np.median(some @ self.planes, axis=0)
        strings = self.strings(x)
        self.order = np.argsort(strings, axis=0, kind="stable").T.astype(np.int32).copy()
        self.sorted = np.sort(strings, axis=0).T.copy()
        self.budget = 1
        self.budget = self._calibrate(strings, target)

    @staticmethod
    def _least_ids(ids: np.ndarray, which: np.ndarray, most: int) -> list[np.ndarray]:
        """The distinct ids of each entry, ascending, no more than any answer can hold."""
        order = np.argsort(which, kind="stable")
        cuts = np.flatnonzero(np.diff(which[order])) + 1
        return [np.unique(own)[:most] for own in np.split(ids[order], cuts)]

    def strings(self, x: np.ndarray) -> np.ndarray:
        """(rows, trees) hash strings as integers, the first bit highest."""
        out = np.zeros((len(x), self.trees), dtype=np.int64)
        weights = np.int64(1) << np.arange(self.bits - 1, -1, -1, dtype=np.int64)
        for at in range(0, len(x), 512):
            bits = (x[at : at + 512] @ self.planes >= self.middle).reshape(-1, self.trees, self.bits)
            out[at : at + 512] = bits @ weights
        return out

    def descend(self, strings: np.ndarray) -> np.ndarray:
        """(queries, trees): the length of the longest prefix that each query shares with a string of each tree."""
        out = np.empty(strings.shape, dtype=np.int64)
        for t in range(self.trees):
            own, at = self.sorted[t], np.searchsorted(self.sorted[t], strings[:, t])
            near = np.stack([own[np.maximum(at - 1, 0)], own[np.minimum(at, len(own) - 1)]])
            out[:, t] = self.bits - bit_length(near ^ strings[:, t]).min(axis=0)
        return out

    def _range(self, strings: np.ndarray, level: int) -> tuple[np.ndarray, np.ndarray]:
        """(queries, trees): where the strings that share the first ``level`` bits begin and end in each tree."""
        low = strings >> (self.bits - level) << (self.bits - level)
        high = low + (1 << (self.bits - level))
        begin, end = np.empty(strings.shape, np.int64), np.empty(strings.shape, np.int64)
        for t in range(self.trees):
            begin[:, t], end[:, t] = np.searchsorted(self.sorted[t], low[:, t]), np.searchsorted(self.sorted[t], high[:, t])
        return begin, end

    def _collect(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The distinct entries in these ranges of all trees."""
        seen = np.zeros(len(self.x), dtype=bool)
        for t in np.flatnonzero(end > begin).tolist():
            seen[self.order[t, begin[t] : end[t]]] = True
        return np.flatnonzero(seen)

    def ascend(self, strings: np.ndarray, budget: int | None = None):
        """(query, level, entries) of each step at which a query has met ``budget`` entries or is at the root, and of no earlier one."""
        budget = budget or self.budget
        start = self.descend(strings).max(axis=1)
        waiting = np.ones(len(strings), dtype=bool)
        for level in range(int(start.max(initial=0)), -1, -1):
            now = np.flatnonzero(waiting & (start >= level))
            if not len(now):
                continue
            begin, end = self._range(strings[now], level)
            enough = (end - begin).sum(axis=1) >= min(budget, len(self.x))  # each entry may be met in several trees
            for i in np.flatnonzero(enough).tolist():
                met = self._collect(begin[i], end[i])
                if len(met) >= min(budget, len(self.x)) or not level:
                    waiting[now[i]] = False
                    yield int(now[i]), level, met

    def distances(self, q: np.ndarray, rows: np.ndarray) -> np.ndarray:
        return np.sqrt(((self.x[rows] - q) ** 2).sum(axis=1))

    def _calibrate(self, strings: np.ndarray, target: float) -> int:
        """The smallest number of entries to meet at which probe rows meet enough of their true neighbours."""
        n = len(self.x)
        if n <= self.k + 1:
            return n
        probes = np.linspace(0, n - 1, min(PROBES, n)).astype(int)
        shared, counts = np.empty((len(probes), self.k), np.int64), np.empty((len(probes), self.bits + 1), np.int64)
        for row, i in enumerate(probes.tolist()):
            d = ((self.x - self.x[i]) ** 2).sum(axis=1)
            d[i] = np.inf
            near = np.argpartition(d, self.k)[: self.k]
            shared[row] = (self.bits - bit_length(strings[near] ^ strings[i])).max(axis=1)
        counts[:] = n
        for level in range(self.bits, -1, -1):
            begin, end = self._range(strings[probes], level)
            for row in range(len(probes)):
                counts[row, level] = len(self._collect(begin[row], end[row]))
            if (shared >= level).mean() >= target:  # as soon as one level for all would do, no query need go further
                break
        low, high = 1, n
        while low < high:
            budget = (low + high) // 2
            stop = (counts >= budget).shape[1] - 1 - (counts >= budget)[:, ::-1].argmax(axis=1)
            low, high = (low, budget) if (shared >= stop[:, None]).mean() >= target else (budget + 1, high)
        return low

    def search(self, queries: np.ndarray, own: np.ndarray):
        """(query, ids, distances, entries met) of the nearest rows met by each query, nearest first."""
        for at in range(0, len(queries), AT_ONCE):
            part = queries[at : at + AT_ONCE]
            for i, _, met in self.ascend(self.strings(part)):
                d = self.distances(part[i], met)
                n_met = len(met)
                if len(met) > self.k + 1:  # one entry may hold nothing but the query itself
                    within = d <= np.partition(d, self.k)[self.k]
                    met, d = met[within], d[within]
                ids = np.concatenate([self.owners[m] for m in met])
                d = np.repeat(d, [len(self.owners[m]) for m in met])
                other = ids != own[at + i]
                ids, d = ids[other], d[other]
                order = np.lexsort((ids, d))[: self.k]
                yield at + i, ids[order], d[order], n_met

    def met(self, queries: np.ndarray) -> float:
        """The mean share of the block's entries that queries meet."""
        return float(np.mean([len(m) for _, _, m in self.ascend(self.strings(queries))])) / len(self.x)


def nearest(embeddings: DataFrame, is_query: Column, k: int = 10, block: int = BLOCK, trees: int = TREES, bits: int = BITS, target: float = TARGET_RECALL) -> DataFrame:
    """query_id, rank, vec_id and score (Euclidean distance) of the neighbours found for the rows where ``is_query`` holds."""
    rows = embeddings.select(embeddings["vec_id"].cast("long").alias("vec_id"), embeddings["embedding"].cast("array<double>").alias("embedding"))
    rows = rows.where(usable(F.col("embedding")) & F.col("vec_id").isNotNull())
    queries = rows.where(is_query).dropDuplicates(["vec_id"])
    n, n_queries = rows.agg(F.count("*"), F.sum(is_query.cast("long"))).first()
    blocks, parts = max(1, -(-n // block)), max(1, -(-(n_queries or 0) // QUERY_PART))
    key = (F.col("block") * parts + F.col("part")).alias("key")
    data = rows.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks))).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    asked = queries.withColumn("part", F.pmod(F.xxhash64("vec_id"), F.lit(parts))).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    both = data.select(key, F.lit(0).alias("role"), "vec_id", "embedding").unionByName(asked.select(key, F.lit(1).alias("role"), "vec_id", "embedding"))

    def work(batches):
        group, held, forests = None, [], None
        for name, part in grouped_stream(batches, "key"):
            if name != group:
                group, held, forests = name, [], None
            n_data = int((part.column(1).to_numpy() == 0).sum())
            if n_data:
                held.append(part.slice(0, n_data))
            part = part.slice(n_data)
            if not part.num_rows or not held:
                continue
            if forests is None:
                forests = {}
                table = pa.Table.from_batches(held).combine_chunks()
                sizes = np.array([len(e) for e in table["embedding"]])
                for size in np.unique(sizes):
                    own = table.take(pa.array(np.flatnonzero(sizes == size)))
                    forests[int(size)] = Forest(own["vec_id"].to_numpy(), matrix(own["embedding"].combine_chunks()), k, trees, bits, target)
            out: list[list] = [[], [], []]
            sizes = np.array([len(e) for e in part.column(3)])
            for size in np.unique(sizes):
                forest = forests.get(int(size))
                if forest is None:
                    continue
                asked = part.take(pa.array(np.flatnonzero(sizes == size)))
                own = asked.column(2).to_numpy()
                for i, ids, d, _ in forest.search(matrix(asked.column(3)), own):
                    out[0] += [int(own[i])] * len(ids)
                    out[1] += ids.tolist()
                    out[2] += d.tolist()
            yield pa.record_batch([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64())], ["query_id", "vec_id", "score"])

    found = map_arrow(by_group(both), work, "query_id long, vec_id long, score double")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy("score", "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
