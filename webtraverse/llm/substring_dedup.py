"""Removal of passages that an earlier document already holds, by repeated-phrase automata.

A window is ``width`` consecutive words of one document. A word is removed if it lies in a window whose words also start
somewhere in a document of smaller id; windows are judged on the input. The steps:

1. Documents of equal text are one class, whose smallest id stands for it; the others lose all that windows cover.
2. Each window picks the smallest hash of its word grams as its anchor, so equal windows have equal anchors. Anchors that occur
   in two documents make a document a candidate; only candidates are followed further, with their whole texts.
3. Windows of candidates at such anchors are counted by two hashes, with a map-side combine. Windows of several documents are
   confirmed; runs of them in their first document are the recurring passages.
4. Passages are dealt into shards by anchor. Each shard compiles an Aho-Corasick automaton over word numbers: a passage enters as
   blocks of half a window, of which every window holds at least one.
5. The pieces of candidate documents around these anchors stream through the shard; each block found is extended word by word,
   and what reaches a window's length in an earlier document is marked. Passages of a frequent anchor are dealt into splits and its pieces
   into parts, and every two of them meet in one shard; nothing is dropped.

Hashes choose what is compared; a mark itself rests on equal words.

Behaviour at the edges: null text has no words; texts shorter than a window keep all words; a row that repeats an id and text is no copy of itself;
rows that share an id but not the text are told apart by a text hash and never count as earlier than each other; null ids are kept as they are
and match nothing; very long texts are cut into pieces; an empty table gives no rows; other columns are ignored (or kept, in ``clean``).
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, materialize, partitions_for, text_column

WIDTH, GRAM = 50, 10
SHARD_WORDS = 400_000
PIECES_AT_A_SHARD = SOURCES_AT_A_SHARD = 2_000

_BASES = (np.uint64(0x9E3779B97F4A7C15 | 1), np.uint64(0xD6E8FEB86659FD93 | 1))


def _inverse(x: int) -> int:
    return pow(x, -1, 1 << 64)


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_table(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base modulo 2**64, and of its inverse."""
    key = int(base)
    got = _powers.get(key)
    if got is None or len(got[0]) < n:
        size = max(1 << 15, 1 << (n - 1).bit_length())
        up, down = np.full(size, base, dtype=np.uint64), np.full(size, np.uint64(_inverse(key)), dtype=np.uint64)
        up[0] = down[0] = 1
        with np.errstate(over="ignore"):
            got = _powers[key] = (np.multiply.accumulate(up), np.multiply.accumulate(down))
    return got


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))


def rolling(h: np.ndarray, width: int, which: int = 0) -> np.ndarray:
    """A hash of each run of ``width`` words, the same wherever the run stands."""
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    up, down = _power_table(_BASES[which], len(h) + 1)
    with np.errstate(over="ignore"):
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * up[: len(h)], dtype=np.uint64)])
        x = (sums[width:] - sums[:-width]) * down[:n]
        x ^= x >> np.uint64(31)
        x *= np.uint64(0x7FB5D329728EA185)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x81DADEF4BC2DD44D)
        return x ^ (x >> np.uint64(33))


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """The smallest of each ``width`` neighbours, by doubling."""
    span, m = 1, x
    while span * 2 <= width:
        m = np.minimum(m[:-span], m[span:])
        span *= 2
    rest = width - span
    return np.minimum(m[: len(m) - rest], m[rest:]) if rest else m


def window_anchors(h: np.ndarray, width: int, gram: int) -> np.ndarray:
    """The anchor of each window of a document."""
    if len(h) < width:
        return np.zeros(0, dtype=np.int64)
    return sliding_min(rolling(h, gram), width - gram + 1).view(np.int64)


def _keyed(docs: DataFrame) -> DataFrame:
    text = text_column(docs)
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.unhex(F.md5(text.cast("binary"))).alias("key"), text.alias("text"))


def survey(docs: DataFrame, width: int = WIDTH, gram: int = GRAM) -> DataFrame:
    """doc_id, key, n_words, sha (of all words joined) and the distinct anchors of each row."""

    def work(batches):
        for batch in batches:
            n, sha, found = [], [], []
            for text in batch.column(2):
                words = text.as_py().encode().split()
                n.append(len(words))
                sha.append(hashlib.sha256(b" ".join(words)).hexdigest())
                a = window_anchors(word_hashes(words), width, gram) if len(words) >= width else np.zeros(0, np.int64)
                found.append(np.unique(a) if len(a) else a)
            yield pa.record_batch([batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(sha, pa.string()), pa.array(found, pa.list_(pa.int64()))], ["doc_id", "key", "n_words", "sha", "anchors"])

    return map_arrow(_keyed(docs), work, "doc_id long, key binary, n_words long, sha string, anchors array<long>")


def _candidates(docs: DataFrame, surveyed: DataFrame) -> DataFrame:
    """doc_id, key, text and recurring anchors (a, first, n) of the documents that have any; one of each class of equal texts."""
    first = surveyed.where("n_words > 0 and doc_id is not null and size(anchors) > 0").groupBy("key").agg(F.min("doc_id").alias("doc_id"), F.any_value("anchors").alias("anchors"))
    standing = materialize(first.select("doc_id", "key", F.explode("anchors").alias("a")), "anchors")
    counted = standing.groupBy("a").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last"), F.count("*").alias("n")).where("first < last").drop("last")
    mine = standing.join(counted, "a").groupBy("doc_id", "key").agg(F.collect_list(F.struct("a", "first", "n")).alias("recurring"))
    return materialize(_keyed(docs).join(mine, ["doc_id", "key"]).withColumn("k", F.xxhash64("key")), "candidates")


def _runs(mask_or_value: np.ndarray, keep: np.ndarray) -> list[tuple[int, int]]:
    """Maximal runs [i, j) of equal values among kept places."""
    at = np.flatnonzero(keep)
    if not len(at):
        return []
    v = mask_or_value[at]
    cut = np.flatnonzero((at[1:] != at[:-1] + 1) | (v[1:] != v[:-1])) + 1
    edges = [0, *cut.tolist(), len(at)]
    return [(int(at[i]), int(at[j - 1]) + 1) for i, j in zip(edges[:-1], edges[1:])]


def _confirmed(candidates: DataFrame, width: int, gram: int) -> DataFrame:
    """(a, doc_id, k, at): windows that occur in several documents, where they stand first; k tells texts of one id apart."""

    def work(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                h = word_hashes(batch.column(2)[row].as_py().encode().split())
                anchors = window_anchors(h, width, gram)
                rec = np.array([x["a"] for x in batch.column(3)[row].as_py()], dtype=np.int64)
                at = np.flatnonzero(np.isin(anchors, rec))
                if not len(at):
                    continue
                a, w = anchors[at], rolling(h, width, 1).view(np.int64)[at]
                once = np.sort(np.unique(np.stack([a, w], 1), axis=0, return_index=True)[1]) if len(at) > 1 else np.zeros(1, np.int64)
                doc, k = (np.full(len(once), batch.column(i)[row].as_py(), np.int64) for i in (0, 1))
                yield pa.record_batch([pa.array(x) for x in (a[once], w[once], doc, k, at[once].astype(np.int32))], ["a", "w", "doc_id", "k", "at"])

    windows = map_arrow(candidates.select("doc_id", "k", "text", "recurring"), work, "a long, w long, doc_id long, k long, at int")
    seen = windows.groupBy("a", "w").agg(F.min(F.struct("doc_id", "k", "at")).alias("f"), F.max("doc_id").alias("last"))
    return seen.where("f.doc_id < last").select("a", "f.doc_id", "f.k", "f.at")


def _source_pieces(candidates: DataFrame, confirmed: DataFrame, width: int) -> DataFrame:
    """(a, doc_id, start, content): recurring passages, cut where the anchor changes."""
    wanted = confirmed.groupBy("doc_id", "k").agg(F.collect_list(F.struct("at", "a")).alias("windows"))

    def work(batches):
        for batch in batches:
            out: list[list] = [[], [], [], []]
            for doc, text, windows in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2)):
                words = text.as_py().encode().split()
                flat = windows.values
                at, a = flat.field(0).to_numpy(), flat.field(1).to_numpy()
                order = np.argsort(at, kind="stable")
                at, a = at[order], a[order]
                cut = np.flatnonzero((at[1:] != at[:-1] + 1) | (a[1:] != a[:-1])) + 1
                edges = [0, *cut.tolist(), len(at)]
                for i, j in zip(edges[:-1], edges[1:]):
                    s, e = int(at[i]), int(at[j - 1]) + width
                    for col, v in zip(out, (int(a[i]), doc, s, b" ".join(words[s:e]))):
                        col.append(v)
            yield pa.record_batch([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int32()), pa.array(out[3], pa.binary())], ["a", "doc_id", "start", "content"])

    joined = candidates.select("doc_id", "k", "text").join(wanted, ["doc_id", "k"])
    return map_arrow(joined.select("doc_id", "text", "windows"), work, "a long, doc_id long, start int, content binary")


def _target_pieces(candidates: DataFrame, width: int, gram: int) -> DataFrame:
    """(a, n, doc_id, k, start, content): the words around each anchor that an earlier document also has."""

    def work(batches):
        for batch in batches:
            out: list[list] = [[] for _ in range(6)]
            for doc, k, text, recurring in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3)):
                earlier = {x["a"]: x["n"] for x in recurring.as_py() if x["first"] < doc}
                if not earlier:
                    continue
                words = text.as_py().encode().split()
                anchors = window_anchors(word_hashes(words), width, gram)
                for i, j in _runs(anchors, np.isin(anchors, np.fromiter(earlier, dtype=np.int64))):
                    a = int(anchors[i])
                    for col, v in zip(out, (a, earlier[a], doc, k, i, b" ".join(words[i : j - 1 + width]))):
                        col.append(v)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
            yield pa.record_batch([pa.array(c, t) for c, t in zip(out, kinds)], ["a", "n", "doc_id", "k", "start", "content"])

    return map_arrow(candidates.select("doc_id", "k", "text", "recurring"), work, "a long, n long, doc_id long, k long, start int, content binary")


class PassageAutomaton:
    """Finds where passages of at least ``width`` words recur; passages enter with the document they stand in."""

    def __init__(self, width: int):
        self.width, self.half = width, width // 2
        self.numbers: dict[bytes, int] = {}
        self.passages: list[tuple[int, tuple]] = []
        self.blocks: dict[tuple, list[tuple[int, int]]] = {}
        self.machine = None

    def add(self, doc: int, content: bytes) -> None:
        numbers = self.numbers
        ids = tuple(numbers.setdefault(w, len(numbers) + 1) for w in content.split())
        self.passages.append((doc, ids))
        for at in range(0, len(ids) - self.half + 1, self.half):
            self.blocks.setdefault(ids[at : at + self.half], []).append((len(self.passages) - 1, at))

    def compile(self) -> None:
        import ahocorasick

        self.machine = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
        for block, places in self.blocks.items():
            self.machine.add_word(block, places)
        self.machine.make_automaton()

    def covered(self, doc: int, content: bytes) -> list[tuple[int, int]]:
        """Spans of ``content`` in which every window stands in a passage of a document before ``doc``."""
        get = self.numbers.get
        ids = tuple(get(w, 0) for w in content.split())
        spans: list[tuple[int, int]] = []
        reached: dict[tuple[int, int], int] = {}
        n, half = len(ids), self.half
        for end, places in self.machine.iter(ids):
            begin = end - half + 1
            for which, off in places:
                owner, words = self.passages[which]
                if owner >= doc or reached.get((which, begin - off), -1) > end:
                    continue
                i, j = begin, off
                while i and j and ids[i - 1] == words[j - 1]:
                    i, j = i - 1, j - 1
                k, m = end + 1, off + half
                while k < n and m < len(words) and ids[k] == words[m]:
                    k, m = k + 1, m + 1
                reached[which, begin - off] = k
                if k - i >= self.width:
                    spans.append((i, k))
        merged: list[tuple[int, int]] = []
        for i, k in sorted(spans):
            if merged and i <= merged[-1][1]:
                merged[-1] = (merged[-1][0], max(k, merged[-1][1]))
            else:
                merged.append((i, k))
        return merged


def _located(candidates: DataFrame, sources: DataFrame, targets: DataFrame, width: int) -> DataFrame:
    """(doc_id, k, start, stop): spans of documents that passages of earlier documents cover."""
    spark = sources.sparkSession
    n_words = sources.agg(F.sum(F.octet_length("content"))).first()[0] or 0
    shards = max(partitions_for(spark), int(n_words // (6 * SHARD_WORDS)) + 1)
    shard = F.pmod(F.xxhash64("a"), F.lit(shards))
    per = F.lit(PIECES_AT_A_SHARD)
    # Passages of an anchor are dealt into splits and its pieces into parts; every two of them meet in one place.
    splits = sources.groupBy("a").agg(F.ceil(F.count("*") / SOURCES_AT_A_SHARD).cast("int").alias("splits")).where("splits > 1")
    copies = candidates.select(F.explode("recurring").alias("r")).where(F.col("r.n") > per).select("r.a", F.ceil(F.col("r.n") / per).cast("int").alias("parts")).distinct()
    all_of = lambda n: F.explode(F.sequence(F.lit(0), F.coalesce(n, F.lit(1)) - 1))
    place = F.pmod(F.xxhash64("doc_id", "start"), F.coalesce("splits", F.lit(1))).cast("int")
    dealt = sources.join(copies, "a", "left").join(splits, "a", "left").withColumn("split", place)
    dealt = dealt.select("a", "split", all_of("parts").alias("part"), F.lit(0).alias("role"), "doc_id", F.lit(0).cast("long").alias("k"), "start", "content")
    part = F.when(F.col("n") > per, F.pmod(F.xxhash64("doc_id", "start"), F.ceil(F.col("n") / per)).cast("int")).otherwise(0)
    stream = targets.join(splits, "a", "left").select("a", all_of("splits").alias("split"), part.alias("part"), F.lit(1).alias("role"), "doc_id", "k", "start", "content")
    both = dealt.unionByName(stream).withColumn("shard", F.xxhash64(shard, "split", "part"))
    both = both.repartition(shards, "shard").sortWithinPartitions("shard", "role")

    def work(batches):
        now, machine = None, None
        for batch in batches:
            out: list[list] = [[], [], [], []]
            for shard, role, doc, k, start, content in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if shard != now:
                    now, machine = shard, PassageAutomaton(width)
                if role == 0:
                    machine.add(doc, content)
                    continue
                if not machine.passages:
                    continue
                if machine.machine is None:
                    machine.compile()
                for i, j in machine.covered(doc, content):
                    for col, v in zip(out, (doc, k, start + i, start + j)):
                        col.append(v)
            yield pa.record_batch([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int64(), pa.int32(), pa.int32()))], ["doc_id", "k", "start", "stop"])

    return map_arrow(both.select("shard", "role", "doc_id", "k", "start", "content"), work, "doc_id long, k long, start int, stop int")


def _kept(candidates: DataFrame, spans: DataFrame) -> DataFrame:
    """doc_id, key, n_removed, sha and text of the documents that lose words."""
    per_doc = spans.distinct().groupBy("doc_id", "k").agg(F.collect_list(F.struct("start", "stop")).alias("spans"))

    def work(batches):
        for batch in batches:
            out: list[list] = [[], [], []]
            for text, spans in zip(batch.column(2), batch.column(3)):
                words = text.as_py().encode().split()
                keep = np.ones(len(words), dtype=bool)
                flat = spans.values
                for i, j in zip(flat.field(0).to_pylist(), flat.field(1).to_pylist()):
                    keep[i:j] = False
                left = b" ".join([words[i] for i in np.flatnonzero(keep).tolist()])
                for col, v in zip(out, (int(len(words) - keep.sum()), hashlib.sha256(left).hexdigest(), left.decode())):
                    col.append(v)
            yield pa.record_batch([batch.column(0), batch.column(1), pa.array(out[0], pa.int64()), pa.array(out[1], pa.string()), pa.array(out[2], pa.string())], ["doc_id", "key", "n_removed", "cut_sha", "cut_text"])

    return map_arrow(candidates.join(per_doc, ["doc_id", "k"]).select("doc_id", "key", "text", "spans"), work, "doc_id long, key binary, n_removed long, cut_sha string, cut_text string")


def removal_plan(docs: DataFrame, width: int = WIDTH, gram: int = GRAM) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The survey of all rows; the smallest id of each text; the documents that lose words to passages."""
    surveyed = materialize(survey(docs, width, gram), "survey")
    candidates = _candidates(docs, surveyed)
    sources = materialize(_source_pieces(candidates, _confirmed(candidates, width, gram), width), "passages")
    spans = _located(candidates, sources, _target_pieces(candidates, width, gram), width)
    cut = _kept(candidates, spans)
    first = surveyed.where("doc_id is not null").groupBy("key").agg(F.min("doc_id").alias("first_id"))
    return surveyed, first, cut


EMPTY_SHA = hashlib.sha256(b"").hexdigest()


def digest(docs: DataFrame, width: int = WIDTH, gram: int = GRAM) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of each row."""
    surveyed, first, cut = removal_plan(docs, width, gram)
    rows = surveyed.drop("anchors").join(first, "key", "left").join(cut.select("doc_id", "key", "n_removed", "cut_sha").dropDuplicates(["doc_id", "key"]), ["doc_id", "key"], "left")
    copy = (F.col("first_id") < F.col("doc_id")) & (F.col("n_words") >= width)
    return rows.select(
        "doc_id",
        "n_words",
        F.when(copy, F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(copy, F.lit(EMPTY_SHA)).otherwise(F.coalesce("cut_sha", "sha")).alias("kept_sha256"),
    )


def clean(docs: DataFrame, width: int = WIDTH, gram: int = GRAM) -> DataFrame:
    """``docs`` with the removed words cut out of ``text``: untouched texts stay as they are, cut ones are words joined by blanks.

    ``n_chars``, where it exists, follows. A document that loses all its words keeps its row with an empty text.
    """
    surveyed, first, cut = removal_plan(docs, width, gram)
    copies = surveyed.join(first, "key").where((F.col("first_id") < F.col("doc_id")) & (F.col("n_words") >= width)).select("doc_id", "key", F.lit("").alias("cut_text"))
    changed = cut.select("doc_id", "key", "cut_text").unionByName(copies).dropDuplicates(["doc_id", "key"]).select(F.col("doc_id").alias("_doc"), F.col("key").alias("_key"), F.col("cut_text").alias("_cut"))
    held = docs.withColumn("_own_key", F.unhex(F.md5(text_column(docs).cast("binary"))))
    out = held.join(changed, (held["doc_id"] == changed["_doc"]) & (held["_own_key"] == changed["_key"]), "left").withColumn("text", F.coalesce("_cut", "text"))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_cut").isNotNull(), F.length("_cut").cast("long")).otherwise(F.col("n_chars")))
    return out.select(docs.columns)
