"""Embedding near-duplicates by an inverted multi-index.

Vectors are scaled to length one and cut in halves; each half has its own codebook, and the product of both is a grid of cells. A
vector is stored in the cell of its nearest codewords. A query goes through the cells by the multi-sequence algorithm: the codewords of each half
are sorted by a lower bound of their region's distance, and a heap merges both lists, so that cells come in the order of the sum and only
those that are visited, and their neighbours, are ever looked at. Two vectors of cosine c are at squared distance 2 - 2c, so the traversal
may stop where the sum exceeds that: no link is missed, the target recall is 1. What is met is verified in double precision.

A region's bound comes from the planes that part it from the codewords nearest to the query, so it costs memory in proportion to the
words of one half, not to the cells. As the bound holds from either end of a link, a query goes only to cells from its own on upward.

The codebooks are fitted on a bounded sample (``sample`` rows, in the order of a hash of their content); every vector is stored. The grid has
about ``cell_rows`` vectors of the largest label in a cell, ``LEAST_WORDS`` codewords a half at least, and is no finer than what keeps the visits that are measured on the
sample below ``MOST_VISITS`` cells a vector: that decides how much work is spared, never what is found. Equal vectors are one class with a
count. A cell with many vectors is dealt into chunks and its queries into parts, so that a group in a task is bounded. Within a group
only links of a spanning forest are given out, beside the number of links of each vector.

Behaviour at the edges: vectors that are null, empty or zero, or hold null or non-finite components, and those with a null label, have no
links; vectors of different length are never linked; rows may repeat, each counts; rows of one id are one vertex for reachability; a null
id has links but no component and is kept; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, materialize
from .components import components
from .vectors import by_group, grouped_stream, matrix, usable

THRESHOLD = 0.98
SAMPLE = 20_000
CELL_ROWS, LEAST_WORDS, MOST_WORDS, MOST_VISITS = 64, 8, 512, 48
CHUNK, QUERY_PART, AT_ONCE = 4_096, 50_000, 256
PLANES = 8


def codebook(x: np.ndarray, words: int, rounds: int = 15, seed: int = 5) -> np.ndarray:
    """Lloyd's algorithm from distinct rows."""
    rng = np.random.default_rng(seed)
    x = np.unique(x, axis=0)
    if len(x) <= words:
        return x if len(x) else np.zeros((1, x.shape[1]))
    c = x[rng.choice(len(x), words, replace=False)]
    for _ in range(rounds):
        near = ((c**2).sum(1)[None, :] - 2 * x @ c.T).argmin(1)
        for i in range(words):
            own = x[near == i]
            c[i] = own.mean(0) if len(own) else x[rng.integers(len(x))]
    return c


def region_bounds(x: np.ndarray, c: np.ndarray, planes: int = PLANES) -> tuple[np.ndarray, np.ndarray]:
    """For each row: the nearest codeword, and a lower bound of the squared distance to each codeword's region.

    A region lies on its codeword's side of the plane halfway to any other one; the planes used are those of the codewords nearest to the row.
    """
    d = (x**2).sum(1)[:, None] - 2 * x @ c.T + (c**2).sum(1)[None, :]
    nearest, best = np.argsort(d, axis=1, kind="stable")[:, : min(planes, len(c))], np.zeros_like(d)
    for j in range(nearest.shape[1]):
        other = nearest[:, j]
        apart = np.sqrt(np.maximum((c[other] ** 2).sum(1)[:, None] - 2 * c[other] @ c.T + (c**2).sum(1)[None, :], 0))
        over = d - np.take_along_axis(d, other[:, None], 1) - 1e-12  # for rounding
        np.maximum(best, np.divide(over, 2 * apart, out=np.zeros_like(d), where=apart > 1e-5), out=best)
    return nearest[:, 0], best**2


def multi_sequence(first: np.ndarray, second: np.ndarray, reach: float):
    """(row, column, bound) of grid cells in the order of the sum of their bounds, as long as that is within ``reach``.

    A cell enters the heap when the cells before it in its row and in its column have been visited, so the heap never holds more than one for each row.
    """
    rows, cols = np.argsort(first, kind="stable"), np.argsort(second, kind="stable")
    a, b = first[rows].tolist(), second[cols].tolist()
    heap, reached = [(a[0] + b[0], 0, 0)], [0] * len(a)  # how many cells of each row have been visited
    while heap:
        bound, i, j = heapq.heappop(heap)
        if bound > reach:
            return
        yield int(rows[i]), int(cols[j]), bound
        reached[i] = j + 1
        if j + 1 < len(b) and (i == 0 or reached[i - 1] > j + 1):
            heapq.heappush(heap, (a[i] + b[j + 1], i, j + 1))
        if i + 1 < len(a) and reached[i + 1] == j:
            heapq.heappush(heap, (a[i + 1] + b[j], i + 1, j))


def reach_of(threshold: float) -> float:
    return 2 - 2 * threshold + 1e-9


def place(x: np.ndarray, books: tuple[np.ndarray, np.ndarray], reach: float) -> tuple[np.ndarray, list[list[int]]]:
    """The cell of each row of ``x`` (of length one), and the cells from that one on that its query visits."""
    a, b = books
    half = x.shape[1] // 2
    (near1, first), (near2, second) = region_bounds(x[:, :half], a), region_bounds(x[:, half:], b)
    own = near1 * len(b) + near2
    visits = []
    for c, f, s in zip(own.tolist(), first, second):
        visits.append([c, *(k for i, j, _ in multi_sequence(f, s, reach) if (k := i * len(b) + j) > c)])
    return own, visits


def _grid_sizes(most: int) -> list[int]:
    """Words of a half to try, up to ``most``."""
    out = [LEAST_WORDS]
    while out[-1] * 2 <= most:
        out.append(out[-1] * 2)
    return out


def fit(vectors: DataFrame, threshold: float = THRESHOLD, sample: int = SAMPLE, cell_rows: int = CELL_ROWS) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Codebooks of both halves for each vector length in the bounded sample of ``vectors`` (h1, h2, label, embedding)."""
    largest = vectors.groupBy("label").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
    most = int(min(MOST_WORDS, max(LEAST_WORDS, (largest / cell_rows) ** 0.5)))
    got = vectors.orderBy("h1", "h2").limit(sample).select("embedding").toArrow()["embedding"].to_pylist()
    books = {}
    for size in {len(v) for v in got}:
        x = np.array([v for v in got if len(v) == size], dtype=np.float64)
        x /= np.linalg.norm(x, axis=1)[:, None]
        for words in _grid_sizes(most):
            tried = (codebook(x[:, : size // 2], words), codebook(x[:, size // 2 :], words))
            if size in books and np.mean([len(v) for v in place(x[:: max(1, len(x) // 200)], tried, reach_of(threshold))[1]]) > MOST_VISITS:
                break
            books[size] = tried
    return books


def _stored(classes: DataFrame, books: dict, threshold: float) -> DataFrame:
    """rep, label, mult, embedding, the cell each class is stored in, and the cells its query visits."""
    reach, kind = reach_of(threshold), classes.schema["embedding"].dataType.simpleString()

    def work(batches):
        for batch in batches:
            sizes = np.array([len(x) for x in batch.column(3)], dtype=np.int64)
            cell, visits = np.zeros(len(sizes), np.int64), [None] * len(sizes)
            for size in np.unique(sizes):
                at = np.flatnonzero(sizes == size)
                own = books.get(int(size), (np.zeros((1, size // 2)), np.zeros((1, size - size // 2))))
                for some in np.array_split(at, -(-len(at) // AT_ONCE)):
                    x = matrix(batch.column(3).take(pa.array(some)))
                    x /= np.linalg.norm(x, axis=1)[:, None]
                    cell[some], met = place(x, own, reach)
                    for i, m in zip(some, met):
                        visits[i] = m
            yield pa.record_batch([*batch.columns, pa.array(cell), pa.array(visits, pa.list_(pa.int64()))], ["rep", "label", "mult", "embedding", "cell", "visits"])

    return map_arrow(classes.select("rep", "label", "mult", "embedding"), work, f"rep long, label long, mult long, embedding {kind}, cell long, visits array<long>")


def _links(stored: DataFrame, threshold: float) -> DataFrame:
    """(kind, x, y): kind 0 gives a number y of links of class x met in one group, kind 1 a link."""
    grid = ["label", "size", "cell"]
    data = stored.select("rep", "label", F.size("embedding").alias("size"), "cell", "mult", "embedding", F.lit(True).alias("own"))
    queries = stored.select("rep", "label", F.size("embedding").alias("size"), "mult", "embedding", F.col("cell").alias("home"), F.explode("visits").alias("cell"))
    queries = queries.select("rep", *grid, "mult", "embedding", (F.col("home") == F.col("cell")).alias("own"))
    full = data.groupBy(grid).agg(F.ceil(F.count("*") / CHUNK).cast("int").alias("chunks"))
    asked = queries.groupBy(grid).agg(F.ceil(F.count("*") / QUERY_PART).cast("int").alias("parts"))
    shape = full.join(asked, grid)  # cells that hold vectors; a visit of another one meets nothing
    key = F.concat_ws("/", *grid, "chunk", "part").alias("key")
    dealt = data.join(shape, grid).withColumn("chunk", F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int")).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    posed = queries.join(shape, grid).withColumn("part", F.pmod(F.xxhash64("rep", F.lit(7)), F.col("parts")).cast("int")).withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    columns = ("rep", "mult", "embedding", "own")
    both = dealt.select(key, F.lit(0).alias("role"), *columns).unionByName(posed.select(key, F.lit(1).alias("role"), *columns))

    def work(batches):
        group, held, ready = None, [], None
        for key, part in grouped_stream(batches, "key"):
            if key != group:
                group, held, ready = key, [], None
            roles = part.column(1).to_numpy()
            n_data = int((roles == 0).sum())
            if n_data:
                held.append(part.slice(0, n_data))
            part = part.slice(n_data)
            if not part.num_rows or not held:
                continue
            if ready is None:
                table = pa.Table.from_batches(held)
                x = np.concatenate([matrix(b.column(4)) for b in held])
                ready = (table["rep"].to_numpy(), table["mult"].to_numpy(), x, np.linalg.norm(x, axis=1), list(range(len(x))))
            reps, mult, x, nx, parent = ready

            def root(i):
                while parent[i] != i:
                    parent[i] = i = parent[parent[i]]
                return i

            for at in range(0, part.num_rows, AT_ONCE):
                some = part.slice(at, AT_ONCE)
                q, q_rep, q_mult = matrix(some.column(4)), some.column(2).to_numpy(), some.column(3).to_numpy()
                foreign = ~some.column(5).to_numpy(zero_copy_only=False).astype(bool)
                hit = (q @ x.T) / (np.linalg.norm(q, axis=1)[:, None] * nx[None, :]) >= threshold
                hit &= q_rep[:, None] != reps[None, :]
                count = hit @ mult
                back = (q_mult * foreign) @ hit  # what is stored here does not visit the lower cells that those queries come from
                met, owed = np.flatnonzero(count), np.flatnonzero(back)
                links = []
                for i in met.tolist():
                    own = np.flatnonzero(hit[i]).tolist()
                    links.append((int(q_rep[i]), int(reps[own[0]])))
                    a = root(own[0])
                    for j in own[1:]:
                        b = root(j)
                        if a != b:
                            parent[b] = a
                            links.append((int(reps[own[0]]), int(reps[j])))
                kind = np.concatenate([np.zeros(len(met) + len(owed), np.int32), np.ones(len(links), np.int32)])
                xs = np.concatenate([q_rep[met], reps[owed], np.array([u for u, _ in links], np.int64)])
                ys = np.concatenate([count[met], back[owed], np.array([v for _, v in links], np.int64)])
                yield pa.record_batch([pa.array(kind), pa.array(xs), pa.array(ys)], ["kind", "x", "y"])

    return map_arrow(by_group(both).select("key", "role", *columns), work, "kind int, x long, y long")


def near_duplicates(embeddings: DataFrame, threshold: float = THRESHOLD, sample: int = SAMPLE, cell_rows: int = CELL_ROWS) -> DataFrame:
    """vec_id, n_links, component_id and kept of each row."""
    kind = "float" if embeddings.schema["embedding"].dataType.simpleString() == "array<float>" else "double"
    rows = embeddings.select(embeddings["vec_id"].cast("long").alias("vec_id"), embeddings["label"].cast("long").alias("label"), embeddings["embedding"].cast(f"array<{kind}>").alias("embedding"))
    content = (F.col("label"), F.transform("embedding", lambda x: x + F.lit(0.0).cast(kind)))
    good = usable(F.col("embedding")) & F.col("label").isNotNull()
    rows = rows.withColumn("h1", F.when(good, F.xxhash64(F.lit(1), *content))).withColumn("h2", F.when(good, F.xxhash64(F.lit(2), *content)))
    classes = rows.where(good).groupBy("h1", "h2").agg(F.min("vec_id").alias("least"), F.any_value("label").alias("label"), F.count("*").alias("mult"), F.any_value("embedding").alias("embedding"))
    classes = materialize(classes.withColumn("rep", F.monotonically_increasing_id()), "vectorclasses")  # numbered once, as written
    stored = materialize(_stored(classes, fit(classes, threshold, sample, cell_rows), threshold), "grid")
    links = materialize(_links(stored, threshold), "links")
    counts = links.where("kind = 0").groupBy(F.col("x").alias("rep")).agg(F.sum("y").alias("other"))
    names = classes.select("rep", "least")
    named = links.where("kind = 1").join(names.toDF("x", "u"), "x").join(names.toDF("y", "v"), "y").select("u", "v")
    reach = components(named)
    found = classes.select("h1", "h2", "rep", "least", "mult").join(counts, "rep", "left").join(reach.withColumnRenamed("vertex", "least"), "least", "left")
    found = found.select("h1", "h2", (F.col("mult") - 1 + F.coalesce("other", F.lit(0))).alias("n_links"), F.coalesce("component", "least").alias("component_id"))
    out = rows.select("vec_id", "h1", "h2").join(found, ["h1", "h2"], "left")
    component = F.when(F.col("vec_id").isNotNull(), F.coalesce("component_id", "vec_id"))
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id")).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def oracle(threshold: float = THRESHOLD) -> str:
    """The same rows by comparing all pairs of a label, for small tables."""
    return f"""
with recursive v as materialized (select vec_id, label, embedding::double[] as e from embeddings),
g as materialized (select * from v where label is not null and e is not null and len(e) > 0 and len(list_filter(e, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(e, lambda x: x <> 0)) > 0),
l as materialized (select a.vec_id as u, b.vec_id as v from g a join g b on a.label = b.label and a.vec_id <> b.vec_id and len(a.e) = len(b.e) and list_cosine_similarity(a.e, b.e) >= {threshold}),
r(u, v) as (select u, v from l union select r.u, l.v from r join l on r.v = l.u),
c as (select u, min(least(u, v)) as component from r group by 1),
n as (select u, count(*)::bigint as n_links from l group by 1)
select v.vec_id, coalesce(n.n_links, 0)::bigint as n_links, coalesce(c.component, v.vec_id)::bigint as component_id, v.vec_id = coalesce(c.component, v.vec_id) as kept
from v left join n on v.vec_id = n.u left join c on v.vec_id = c.u
"""
