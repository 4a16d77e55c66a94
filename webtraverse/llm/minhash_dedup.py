"""Near-duplicates by a chosen-path set similarity join over word shingles.

Each document is the set of its distinct shingles of ``k`` words. Documents of equal sets are one class from the start. For each of
several independent trees a class walks down paths: a node picks a minwise hash function, the token it selects in the set leads to the
child; a quarter of the nodes pick two, so that a pair at the threshold shares about one path in expectation at any depth. Nodes with few classes are
compared exhaustively by bit sketches. The trees repeat until pairs at the threshold are met with the target recall, as ``trees_for`` works
out for any threshold: at 0.8 and the starting depth, one tree meets 58 % of them, nine trees 99.96 %. Every class descends to that
depth, as shuffling nodes higher up, too, costs more than comparing them saves; no node is split further down, as a pair would have to stay
together on more levels than the trees are enough for.

Pairs that pass the sketches are confirmed on the full sets. That is done in two rounds, so that groups of copies don't
give all their pairs. First come a spanning forest of each small node and the stars of a few pivots of each large one. What this
connects needs no further look. Then every remaining pair of a small node is tried across components. In a large node, the
component that most of its classes belong to is compared with each class outside it, chunk by chunk: sketches first, then the full sets of what these
let pass, up to the first link; the outsiders among themselves, however many, are compared block against block.

Behaviour at the edges: null text and texts without words have no set, are linked with nothing and kept; a text of fewer than ``k`` words is one
shingle; rows of one id are one document; a null id has no component and is kept; very long texts are hashed in slices; an empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import map_arrow, materialize, runs, text_column
from .components import components, extend
from .vectors import by_group, grouped_stream

START_DEPTH, TARGET_RECALL = 4, 0.9995
LEAF = 256
PIVOTS, STAR_PART, MEMBER_CHUNK, ASKED_PART, PAIRS_AT_ONCE = 16, 5_000, 512, 128, 1_000
FUNCTIONS = 128
AT_ONCE = 256
M31, M27 = np.uint64(0x7FB5D329728EA185), np.uint64(0x81DADEF4BC2DD44D)

_rng = np.random.default_rng(20_011)
_FACTORS = _rng.integers(0, 1 << 63, FUNCTIONS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SHIFTS = _rng.integers(0, 1 << 63, FUNCTIONS, dtype=np.uint64)
_ROOTS = _rng.integers(0, 1 << 63, 64, dtype=np.uint64)  # the first ones; lower thresholds take more
_WHICH, _TWICE, _OTHER, _SIDE = _rng.integers(0, 1 << 63, 4, dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x = x * M31
    x = x ^ (x >> np.uint64(27))
    x = x * M27
    return x ^ (x >> np.uint64(33))


def words_of(text: str) -> list[bytes]:
    """Words with A-Z lowered; ``bytes.lower`` leaves all other bytes alone."""
    return text.encode().lower().split()


def shingle_set(words: list[bytes], k: int) -> set:
    if not words:
        return set()
    return set(zip(*(words[i:] for i in range(k)))) if len(words) >= k else {tuple(words)}


def shingle_hashes(words: list[bytes], k: int) -> np.ndarray:
    """Sorted hashes of the distinct shingles."""
    if not words:
        return np.zeros(0, dtype=np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))
    width = min(k, len(words))
    out = np.full(len(h) - width + 1, np.uint64(width))
    for i in range(width):
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + h[i : i + len(out)])
    return np.unique(out)


def signature(hashes: np.ndarray) -> np.ndarray:
    """The smallest value under each hash function."""
    low = np.full(FUNCTIONS, np.iinfo(np.uint32).max, dtype=np.uint32)
    for a in range(0, len(hashes), 2048):
        part = ((hashes[a : a + 2048, None] * _FACTORS + _SHIFTS) >> np.uint64(32)).astype(np.uint32)
        low = np.minimum(low, part.min(axis=0))
    return low


def sketch(signatures: np.ndarray) -> np.ndarray:
    """One bit of each value, as two 64-bit words for each row."""
    bits = (_mix(signatures.astype(np.uint64)) & np.uint64(1)).astype(np.uint8)
    return np.packbits(bits, axis=1).view(np.int64)


def _descend(nodes: np.ndarray, signatures: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Children of each row's node: (children of the first choice, those of the second or 0)."""
    row = np.arange(len(nodes))
    first = signatures[row, (_mix(nodes ^ _WHICH) % np.uint64(FUNCTIONS)).astype(np.int64)].astype(np.uint64)
    other = signatures[row, (_mix(nodes ^ _OTHER) % np.uint64(FUNCTIONS)).astype(np.int64)].astype(np.uint64)
    a = _mix(nodes + first * np.uint64(0x9E3779B97F4A7C15))
    b = _mix((nodes ^ _SIDE) + other * np.uint64(0xD6E8FEB86659FD93))
    return a, np.where(_mix(nodes ^ _TWICE) & np.uint64(3) == 0, b, np.uint64(0))


def meeting(threshold: float, depth: int = START_DEPTH) -> float:
    """The probability that a pair at the threshold shares a node of one tree at this depth: of a node's choices, one or, in a quarter of them, two."""
    met = 1.0
    for _ in range(depth):
        met = 0.75 * threshold * met + 0.25 * (1 - (1 - threshold * met) ** 2)
    return met


def trees_for(threshold: float, recall: float = TARGET_RECALL) -> int:
    """As many independent trees as meet a pair at the threshold with the target recall."""
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - min(meeting(threshold), 1 - 1e-9))))


def start_nodes(signatures: np.ndarray, trees: int, depth: int = START_DEPTH) -> list[np.ndarray]:
    """The distinct nodes at the starting depth, over all trees, of each row."""
    roots = np.concatenate([_ROOTS, _mix(np.arange(max(0, trees - len(_ROOTS)), dtype=np.uint64) + _ROOTS[0])])[:trees]
    row, node = np.repeat(np.arange(len(signatures)), trees), np.tile(roots, len(signatures))
    for _ in range(depth):
        a, b = _descend(node, signatures[row])
        row, node = np.concatenate([row, row[b != 0]]), np.concatenate([a, b[b != 0]])
    order = np.argsort(row, kind="stable")
    ends = np.cumsum(np.bincount(row, minlength=len(signatures)))[:-1]
    return [np.unique(x).view(np.int64) for x in np.split(node[order], ends)]


def survey(docs: DataFrame, k: int, trees: int) -> DataFrame:
    """doc_id, n_shingles, fp (of the set), s1, s2 and start nodes of each row."""

    def work(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, AT_ONCE):
                part = batch.slice(at, AT_ONCE)
                sets = [shingle_hashes(words_of(t.as_py()), k) for t in part.column(1)]
                sig = np.stack([signature(s) for s in sets])
                bits = sketch(sig)
                n = np.array([len(s) for s in sets], dtype=np.int64)
                nodes = [x if m else x[:0] for x, m in zip(start_nodes(sig, trees), n)]
                fp = [xxhash.xxh3_128_digest(s.tobytes()) for s in sets]
                yield pa.record_batch(
                    [part.column(0), pa.array(n), pa.array(fp, pa.binary()), pa.array(bits[:, 0].copy()), pa.array(bits[:, 1].copy()), pa.array(nodes, pa.list_(pa.int64()))],
                    ["doc_id", "n_shingles", "fp", "s1", "s2", "nodes"],
                )

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_column(docs).alias("text"))
    return map_arrow(rows, work, "doc_id long, n_shingles long, fp binary, s1 long, s2 long, nodes array<long>")


def least_matches(threshold: float) -> int:
    """Equal bits that a pair at the threshold has, but for one in four thousand."""
    p = (1 + threshold) / 2
    return int(FUNCTIONS * p - 3.5 * (FUNCTIONS * p * (1 - p)) ** 0.5)


def _in_leaf(reps: np.ndarray, s: np.ndarray, comps: np.ndarray | None, least: int):
    """First round (no ``comps``): links of a spanning forest, and whether candidate pairs remain. Later: pairs across components."""
    equal = FUNCTIONS - np.bitwise_count(s[:, None, :] ^ s[None, :, :]).sum(axis=2, dtype=np.int64)
    i, j = np.nonzero(np.triu(equal >= least, 1))
    if comps is not None:
        across = comps[i] != comps[j]
        return list(zip(reps[i[across]].tolist(), reps[j[across]].tolist())), False
    if not len(i):
        return [], False
    order = np.argsort(-equal[i, j], kind="stable")
    parent = list(range(len(reps)))

    def root(x):
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    links = []
    for a, b in zip(i[order].tolist(), j[order].tolist()):
        x, y = root(a), root(b)
        if x != y:
            parent[max(x, y)] = min(x, y)
            links.append((int(reps[a]), int(reps[b])))
    return links, len(links) < len(i)


def _leaves(rows: DataFrame, least: int, later: bool, once: bool = True) -> DataFrame:
    """(kind, x, y): links of small nodes (kind 0), and nodes with further candidate pairs (kind 2); ``rows`` are (node, rep, s1, s2[, comp]).

    Later pairs come from the first node alone that both ends share, not from every tree that they meet in; not
    so without ``once``, for rows of so many nodes that each would carry a long list.
    """
    once = once and later
    if once:
        shared = rows.groupBy("rep").agg(F.array_sort(F.collect_set("node")).alias("shared"))
        rows = rows.join(shared, "rep")

    def work(batches):
        for t in runs(batches, "node"):
            reps, at = np.unique(t["rep"].to_numpy(), return_index=True)
            if len(reps) < 2:
                continue
            s = np.stack([t["s1"].to_numpy()[at], t["s2"].to_numpy()[at]], 1).view(np.uint64)
            links, more = _in_leaf(reps, s, t["comp"].to_numpy()[at] if later else None, least)
            if not links:
                continue
            if once:
                place, node = dict(zip(reps.tolist(), at.tolist())), t["node"][0].as_py()
                nodes = {r: set(t["shared"][place[r]].as_py()) for r in {r for link in links for r in link}}
                links = [(x, y) for x, y in links if min(nodes[x] & nodes[y]) == node]
                if not links:
                    continue
            kind, x, y = [0] * len(links), [a for a, _ in links], [b for _, b in links]
            if more:
                kind, x, y = kind + [2], x + [t["node"][0].as_py()], y + [0]
            yield pa.record_batch([pa.array(kind, pa.int32()), pa.array(x, pa.int64()), pa.array(y, pa.int64())], ["kind", "x", "y"])

    cols = ["node", "rep", "s1", "s2"] + ["comp"] * later + ["shared"] * once
    return map_arrow(rows.select(cols).repartition("node").sortWithinPartitions("node"), work, "kind int, x long, y long")


def _stars(large: DataFrame, least: int) -> DataFrame:
    """(kind, x, y) links of large nodes: each class with its most similar pivot, and links that join pivots."""
    drawn = F.row_number().over(W.partitionBy("node").orderBy(F.xxhash64("rep"), "rep"))
    parts = F.ceil(F.col("n") / STAR_PART).cast("int")
    pivots = large.withColumn("drawn", drawn).where(F.col("drawn") <= PIVOTS).withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1)))
    members = large.withColumn("part", F.pmod(F.xxhash64("rep", F.lit(3)), parts).cast("int"))
    key = F.xxhash64("node", "part").alias("key")
    both = pivots.select(key, F.lit(0).alias("role"), "rep", "s1", "s2").unionByName(members.select(key, F.lit(1).alias("role"), "rep", "s1", "s2"))

    def work(batches):
        group, ids, bits, parent = None, [], np.zeros((0, 2), np.uint64), []
        for key, part in grouped_stream(batches, "key"):
            if key != group:
                group, ids, bits, parent = key, [], np.zeros((0, 2), np.uint64), []
            roles, reps = part.column(1).to_numpy(), part.column(2).to_numpy()
            s = np.stack([part.column(3).to_numpy(), part.column(4).to_numpy()], 1).view(np.uint64)
            first = int((roles == 0).sum())
            if first:
                ids, bits = ids + reps[:first].tolist(), np.concatenate([bits, s[:first]])
                parent = list(range(len(ids)))
            if first == len(reps):
                continue
            reps, s = reps[first:], s[first:]
            equal = FUNCTIONS - np.bitwise_count(s[:, None, :] ^ bits[None, :, :]).sum(axis=2, dtype=np.int64)
            equal[reps[:, None] == np.array(ids)[None, :]] = -1
            best = equal.argmax(axis=1)
            near = np.flatnonzero(equal.max(axis=1) >= least)
            links = [(int(reps[i]), ids[best[i]]) for i in near.tolist()]
            for i in near[(equal[near] >= least).sum(axis=1) > 1].tolist():
                own = np.flatnonzero(equal[i] >= least).tolist()
                for j in own:
                    a, b = best[i], j
                    while parent[a] != a:
                        a = parent[a]
                    while parent[b] != b:
                        b = parent[b]
                    if a != b:
                        parent[b] = a
                        links.append((int(reps[i]), ids[j]))
            pairs = np.sort(np.array(links, dtype=np.int64).reshape(-1, 2), axis=1)
            yield pa.record_batch([pa.array(np.zeros(len(pairs), np.int32)), pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], ["kind", "x", "y"])

    return map_arrow(by_group(both), work, "kind int, x long, y long")


def _outsiders(large: DataFrame) -> DataFrame:
    """Rows of classes that are not of their node's main component ``main``, the one that most of its classes belong to."""
    sizes = large.groupBy("node", "comp").agg(F.count("*").alias("m"))
    main = sizes.groupBy("node").agg(F.max(F.struct("m", "comp")).alias("top")).select("node", F.col("top.comp").alias("main"))
    return large.join(main, "node").where("comp <> main")


def _to_main(outside: DataFrame, known: DataFrame, sketches: DataFrame, texts: DataFrame, k: int, threshold: float, least: int) -> DataFrame:
    """(u, v): a confirmed link of an outsider with each chunk of a main component that has one. Only those that sketches let pass are compared by their texts."""
    of100 = round(threshold * 100)
    asked = outside.select("rep", "main").distinct()
    mains = asked.select("main").distinct()
    members = known.select(F.col("vertex").alias("rep"), F.col("component").alias("main")).unionByName(mains.select(F.col("main").alias("rep"), "main")).distinct().join(mains, "main", "left_semi")
    chunks = members.groupBy("main").agg(F.ceil(F.count("*") / MEMBER_CHUNK).cast("int").alias("chunks"))
    parts = asked.groupBy("main").agg(F.ceil(F.count("*") / ASKED_PART).cast("int").alias("parts"))
    chunks = chunks.join(parts, "main")
    key = F.concat_ws("/", "main", "chunk", "part").alias("key")
    data = members.join(chunks, "main").withColumn("chunk", F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int")).join(sketches, "rep").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    posed = asked.join(chunks, "main").join(sketches, "rep").withColumn("part", F.pmod(F.xxhash64("rep", F.lit(5)), F.col("parts")).cast("int")).withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    met = data.select(key, F.lit(0).alias("role"), "rep", "s1", "s2").unionByName(posed.select(key, F.lit(1).alias("role"), "rep", "s1", "s2"))

    def passed(batches):
        group, ids, bits, hit = None, [], [], None
        for key, part in grouped_stream(batches, "key"):
            if key != group:
                group, ids, bits, hit = key, [], [], None
            roles, reps = part.column(1).to_numpy(), part.column(2).to_numpy()
            s = np.stack([part.column(3).to_numpy(), part.column(4).to_numpy()], 1).view(np.uint64)
            n = int((roles == 0).sum())
            ids.append(reps[:n])
            bits.append(s[:n])
            if n == len(reps) or not sum(map(len, ids)):
                continue
            ids, bits = [np.concatenate(ids)], [np.concatenate(bits)]
            hit = np.zeros(len(ids[0]), bool) if hit is None else hit
            near = FUNCTIONS - np.bitwise_count(s[n:, None, :] ^ bits[0][None, :, :]).sum(axis=2, dtype=np.int64) >= least
            own, new = reps[n:][near.any(axis=1)], near.any(axis=0) & ~hit
            hit |= new
            found = np.concatenate([ids[0][new], own])
            role = np.concatenate([np.zeros(int(new.sum()), np.int32), np.ones(len(own), np.int32)])
            yield pa.record_batch([pa.array([key] * len(found), pa.string()), pa.array(role), pa.array(found)], ["key", "role", "rep"])

    left = map_arrow(by_group(met), passed, "key string, role int, rep long")
    both = left.join(sketches, "rep").join(texts.dropDuplicates(["id"]).select(F.col("id").alias("rep"), "text"), "rep").select("key", "role", "rep", "s1", "s2", "text")

    def work(batches):
        group, ids, bits, held = None, [], [], []
        for key, part in grouped_stream(batches, "key"):
            if key != group:
                group, ids, bits, held = key, [], [], []
            u, v = [], []
            for role, rep, s1, s2, text in zip(*(part.column(i).to_pylist() for i in range(1, 6))):
                if role == 0:
                    ids.append(rep)
                    bits.append((s1, s2))
                    held.append(text)
                    continue
                if not ids:
                    continue
                if isinstance(bits, list):
                    bits = np.array(bits, dtype=np.int64).view(np.uint64)
                equal = FUNCTIONS - np.bitwise_count(bits ^ np.array([[s1, s2]], dtype=np.int64).view(np.uint64)).sum(axis=1, dtype=np.int64)
                own = None
                for i in np.argsort(-equal, kind="stable").tolist():
                    if equal[i] < least:
                        break
                    if own is None:
                        own = shingle_set(words_of(text), k)
                    if isinstance(held[i], str):
                        held[i] = shingle_set(words_of(held[i]), k)
                    common = len(own & held[i])
                    if common and 100 * common >= of100 * (len(own) + len(held[i]) - common):
                        u.append(rep)
                        v.append(ids[i])
                        break
            yield pa.record_batch([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    return map_arrow(by_group(both), work, "u long, v long")


def confirm(texts: DataFrame, pairs: DataFrame, k: int, threshold: float) -> DataFrame:
    """The pairs (x, y) whose full sets are as similar as asked; ``texts`` are (id, text). The pairs of one y are dealt to several tasks if they are many."""
    of100 = round(threshold * 100)
    pairs = pairs.select("x", "y").distinct()
    many = pairs.groupBy("y").agg(F.ceil(F.count("*") / PAIRS_AT_ONCE).cast("int").alias("parts")).where("parts > 1")
    parts = F.coalesce("parts", F.lit(1))
    x = texts.select(F.col("id").alias("x"), F.col("text").alias("tx"))
    y = texts.select(F.col("id").alias("y"), F.col("text").alias("ty")).join(many, "y", "left").select("y", "ty", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part"))
    dealt = pairs.join(many, "y", "left").select("x", "y", F.pmod(F.xxhash64("x"), parts).cast("int").alias("part"))
    both = dealt.join(x, "x").join(y, ["y", "part"]).select("x", "y", "tx", "ty")

    def work(batches):
        for batch in batches:
            good, kept, name = [], None, None
            for b, a, tx, ty in zip(batch.column(1).to_pylist(), batch.column(0).to_pylist(), batch.column(2), batch.column(3)):
                text = ty.as_py()
                if name != (b, len(text)) or held != text:
                    kept, name, held = shingle_set(words_of(text), k), (b, len(text)), text
                other = shingle_set(words_of(tx.as_py()), k)
                common = len(kept & other)
                good.append(bool(common) and 100 * common >= of100 * (len(kept) + len(other) - common))
            at = np.flatnonzero(np.array(good, dtype=bool))
            yield pa.record_batch([batch.column(0).take(pa.array(at)), batch.column(1).take(pa.array(at))], ["u", "v"])

    return map_arrow(both, work, "u long, v long")


def _counted(rows: DataFrame) -> DataFrame:
    """(node, rep) with the node's size, of nodes with more than one row."""
    sizes = rows.groupBy("node").agg(F.count("*").alias("n")).where("n > 1")
    return rows.join(sizes, "node")


def _across(rows: DataFrame) -> DataFrame:
    """Rows of nodes that hold classes of more than one component."""
    mixed = rows.groupBy("node").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("node")
    return rows.join(mixed, "node", "left_semi")


def _blocks(rows: DataFrame) -> DataFrame:
    """Every two blocks of a node as a node of their own."""
    n_blocks = F.ceil(F.col("n") / (LEAF // 2)).cast("int")
    dealt = rows.withColumn("own", F.pmod(F.xxhash64("rep"), n_blocks)).withColumn("other", F.explode(F.sequence(F.lit(0), n_blocks - 1)))
    return dealt.withColumn("node", F.xxhash64("node", F.least("own", "other"), F.greatest("own", "other")))


def classes_of(docs: DataFrame, k: int, threshold: float = 0.8, trees: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The survey of all rows, (fp, rep) of each class of equal sets, and (vertex, component) of classes with links."""
    surveyed = materialize(survey(docs, k, trees or trees_for(threshold)), "sets")
    least = least_matches(threshold)
    some = surveyed.where("n_shingles > 0 and doc_id is not null")
    classes = some.groupBy("fp").agg(F.min("doc_id").alias("rep"), *(F.any_value(c).alias(c) for c in ("s1", "s2")))
    firsts = some.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.any_value("nodes").alias("nodes"))
    met = materialize(_counted(firsts.select("rep", F.explode("nodes").alias("node")).distinct()), "nodes")
    sketches = classes.select("rep", "s1", "s2")
    rows = met.join(sketches, "rep")
    small, large = rows.where(F.col("n") <= LEAF), rows.where(F.col("n") > LEAF)

    first = materialize(_leaves(small, least, later=False).unionByName(_stars(large, least)).distinct(), "firstlinks")
    pairs = first.where("kind = 0").select("x", "y")

    involved = pairs.select(F.col("x").alias("id")).unionByName(pairs.select(F.col("y").alias("id"))).unionByName(met.where(F.col("n") > LEAF).select(F.col("rep").alias("id"))).distinct()
    texts = materialize(docs.select(docs["doc_id"].cast("long").alias("id"), text_column(docs).alias("text")).join(involved, "id"), "texts")
    good = materialize(confirm(texts, pairs, k, threshold), "goodlinks")
    known = materialize(components(good), "known")

    labelled = rows.join(known.withColumnRenamed("vertex", "rep"), "rep", "left").withColumn("comp", F.coalesce("component", "rep")).drop("component")
    open_nodes = first.where("kind = 2").select(F.col("x").alias("node"))
    found = [_leaves(_across(labelled.where(F.col("n") <= LEAF).join(open_nodes, "node", "left_semi")), least, later=True)]
    outside = materialize(_outsiders(_across(labelled.where(F.col("n") > LEAF))), "outsiders")
    joined = None
    if not outside.isEmpty():
        joined = _to_main(outside, known, sketches, texts, k, threshold, least)
        left = materialize(_across(_counted(outside.select("node", "rep", "s1", "s2", "comp"))), "left")
        found.append(_leaves(left.where(F.col("n") <= LEAF), least, later=True))
        found.append(_leaves(_blocks(left.where(F.col("n") > LEAF)), least, later=True, once=False))
    later = found[0]
    for f in found[1:]:
        later = later.unionByName(f)
    later = materialize(later.where("kind = 0").select("x", "y").distinct().join(pairs, ["x", "y"], "left_anti"), "laterlinks")
    new = joined
    if not later.isEmpty():
        more = confirm(texts, later, k, threshold)
        new = more if new is None else new.unionByName(more)
    linked = known if new is None else extend(known, new)
    return surveyed, firsts.select("fp", "rep"), linked


def near_duplicates(docs: DataFrame, k: int = 5, threshold: float = 0.8, trees: int | None = None) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of each row."""
    surveyed, firsts, linked = classes_of(docs, k, threshold, trees)
    rows = surveyed.select("doc_id", "n_shingles", "fp").join(firsts, "fp", "left").join(linked.withColumnRenamed("vertex", "rep"), "rep", "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("component", "rep")).otherwise(F.col("doc_id"))
    return rows.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def drop_near_duplicates(docs: DataFrame, k: int = 5, threshold: float = 0.8) -> DataFrame:
    """``docs`` with one document of each group of near-duplicates, all columns kept; rows without an id stay. Of rows that share
    an id, which are one document, the one whose text has the least hash stays."""
    found = near_duplicates(docs, k, threshold)
    stay = found.where("kept and doc_id is not null").select(F.col("doc_id").alias("_id")).distinct()
    row, text = F.struct(*[docs[c] for c in docs.columns]), text_column(docs)
    named = docs.join(stay, docs["doc_id"].cast("long") == stay["_id"]).groupBy("_id").agg(F.min_by(row, F.struct(F.xxhash64(text), text)).alias("_row")).select("_row.*")
    return named.unionByName(docs.where(docs["doc_id"].isNull()))
