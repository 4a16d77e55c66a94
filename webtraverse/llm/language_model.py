"""Cross-entropy difference of two word n-gram models that share one vocabulary.

The vocabulary holds every distinct word of all documents, and a mark for the end of a text, so it grows with the input. Words and word pairs of
every whole text are counted, once for the background (all documents) and once for the target (the documents named by the caller). Both models have
the same form: the probability of a word after another one is smoothed by its probability alone (Dirichlet prior of ``PRIOR`` words), and that by the
uniform one over the vocabulary. They are matched in size: background counts are scaled to the number of target tokens, which
is what a sample of that size holds on average, without drawing one. The score of a document is its mean loss per token under
the target less that under the background: the lower, the more it is like the target. A document is scored by models from which its own
counts are taken off, so a target document is not told by itself, and one that occurs twice by its copy.

Counts are kept as distributed tables and met by key, nothing is gathered. Documents are dealt into groups of about ``GROUP_BYTES``; each
group sends its distinct n-grams, with their counts, to buckets of hashes; a bucket adds them up and returns to each group the sums of what it
sent; the group, whose texts have not moved since, scores its documents with them. A frequent n-gram comes once from a group, so no key is hot. As every
group hears from every bucket, the size of the vocabulary and of the models come along with the sums.

Words are told by 64-bit hashes, A-Z lowered, with ASCII marks as blanks.

Behaviour at the edges: null text is empty text, of which only the end mark is scored; without target documents both models are uniform and all
scores 0; equal texts of the same standing get equal scores; rows of one id are documents of their own; target ids may repeat, be null or unknown; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship_package
from .common import text_column

GROUP_BYTES = 8_000_000
PRIOR, BASE_PRIOR = 4.0, 1.0
SALTS = 8
END = np.uint64(0x5851F42D4C957F2D)
SCORES = "doc_id long, n_tokens long, ce_target double, ce_background double, score double"
_BLANKED = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def words_of(text: str) -> list[bytes]:
    return text.encode().translate(_BLANKED).split()


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


class Tokens:
    """The n-grams of a group of documents: each document's words and its end, and each with what stands before it."""

    def __init__(self, texts: list[str]):
        found = [np.fromiter(map(xxhash.xxh3_64_intdigest, w), np.uint64, len(w)) for w in map(words_of, texts)]
        self.n_words = np.array([len(w) for w in found], dtype=np.int64)
        ends = np.array([END])
        said = np.concatenate([x for w in found for x in (w, ends)]) if found else np.zeros(0, np.uint64)
        self.doc = np.repeat(np.arange(len(texts)), self.n_words + 1)
        self.first = np.cumsum(self.n_words + 1) - self.n_words - 1
        before = np.concatenate([ends, said[:-1]]) if len(said) else said  # a text begins after the end of another one
        single = _mix(said) & ~np.uint64(1)
        pair = _mix(before * np.uint64(0x9E3779B97F4A7C15) + said) | np.uint64(1)
        self.grams, which = np.unique(np.concatenate([single, pair]), return_inverse=True)
        self.single, self.pair = which[: len(said)], which[len(said) :]

    def counts(self, weight: np.ndarray) -> np.ndarray:
        """How often each n-gram occurs, where a document counts by its weight."""
        w = weight[self.doc].astype(np.float64)
        n = len(self.grams)
        return (np.bincount(self.single, w, n) + np.bincount(self.pair, w, n)).astype(np.int64)

    def dealt(self, buckets: int) -> np.ndarray:
        """Where the n-grams of each bucket, a range of hashes, begin."""
        return np.concatenate([np.searchsorted(self.grams, _bounds(buckets)), [len(self.grams)]])

    def own(self, which: np.ndarray) -> np.ndarray:
        """For each token, how often its document holds the same n-gram."""
        _, at, n = np.unique(self.doc * len(self.grams) + which, return_inverse=True, return_counts=True)
        return n[at]

    def losses(self, counts: np.ndarray, total: int, kinds: int, scale: float, inside: np.ndarray) -> np.ndarray:
        """The mean loss of each document under a model from which the document is taken off, if it is ``inside``."""
        part = inside[self.doc].astype(np.int64)
        own1, own2 = self.own(self.single), self.own(self.pair)
        own_before = np.empty_like(own1)
        own_before[1:] = own1[:-1]
        own_before[self.first] = 1
        before = np.empty_like(self.single)
        before[1:] = self.single[:-1]
        before[self.first] = self.single[self.first + self.n_words]
        rest = scale * (total - (self.n_words + 1)[self.doc] * part)
        alone = (scale * (counts[self.single] - own1 * part) + BASE_PRIOR / max(kinds, 1)) / (rest + BASE_PRIOR)
        p = (scale * (counts[self.pair] - own2 * part) + PRIOR * alone) / (scale * (counts[before] - own_before * part) + PRIOR)
        return np.bincount(self.doc, -np.log(p), len(self.n_words)) / (self.n_words + 1)


def _wanted(table: pa.Table) -> tuple[pa.Table, np.ndarray]:
    """The documents of a group, and which of them are targets."""
    roles = table["role"].to_numpy()
    ids = set(table["doc_id"].take(pa.array(np.flatnonzero(roles == 0))).to_pylist())
    docs = table.take(pa.array(np.flatnonzero(roles == 1)))
    return docs, np.array([d is not None and d in ids for d in docs["doc_id"].to_pylist()], dtype=bool)


POSTINGS = "bucket long, grp long, gram binary, background binary, target binary"
SUMS = "grp long, bucket long, background binary, target binary, kinds long, all_background long, all_target long"


def _names(schema: str) -> list[str]:
    return [c.split()[0] for c in schema.split(", ")]


def _bounds(buckets: int) -> np.ndarray:
    return np.array([(b << 64) // buckets for b in range(buckets)], dtype=np.uint64)


def pack_sorted(values: np.ndarray) -> bytes:
    """Ascending 64-bit numbers as steps of as many bytes as the longest one needs."""
    steps = np.diff(values, prepend=np.uint64(0))
    width = max(1, -(-int(steps.max(initial=0)).bit_length() // 8))
    return bytes([width]) + steps.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def unpack_sorted(data: bytes) -> np.ndarray:
    width = data[0]
    short = np.frombuffer(data, np.uint8, offset=1).reshape(-1, width)
    steps = np.zeros((len(short), 8), np.uint8)
    steps[:, :width] = short
    return np.cumsum(steps.view("<u8").ravel(), dtype=np.uint64)


def pack_counts(values: np.ndarray) -> bytes:
    """Numbers of which most are small: a byte each, and eight more behind for those that don't fit."""
    large = values >= 255
    return np.where(large, 255, values).astype(np.uint8).tobytes() + values[large].astype("<i8").tobytes()


def unpack_counts(data: bytes, n: int) -> np.ndarray:
    out = np.frombuffer(data, np.uint8, n).astype(np.int64)
    out[out == 255] = np.frombuffer(data, "<i8", offset=n)
    return out


def _slices(pack, values: np.ndarray, cuts: np.ndarray) -> pa.Array:
    return pa.array([pack(values[i:j]) for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist())], pa.binary())


def add_up(table: pa.Table) -> pa.Table:
    """The postings of a bucket: the sums of each n-gram, given back to each group in the order in which it named them."""
    grams = [unpack_sorted(x) for x in table["gram"].to_pylist()]
    sizes = [len(g) for g in grams]
    cuts = np.cumsum([0, *sizes])
    kinds, which = np.unique(np.concatenate(grams), return_inverse=True)
    sums = []
    for column in ("background", "target"):
        own = np.concatenate([unpack_counts(x, n) for x, n in zip(table[column].to_pylist(), sizes)])
        sums.append(np.bincount(which, own.astype(np.float64), len(kinds)).astype(np.int64))
    word = kinds & np.uint64(1) == 0
    totals = [pa.array(np.full(table.num_rows, x, np.int64)) for x in (word.sum(), sums[0][word].sum(), sums[1][word].sum())]
    return pa.table([table["grp"], table["bucket"], *(_slices(pack_counts, x[which], cuts) for x in sums), *totals], _names(SUMS))


def cross_entropy_difference(docs: DataFrame, targets: DataFrame, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """Score every document against the documents whose ids ``targets`` holds."""
    spark = docs.sparkSession
    ship_package(spark)
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_column(docs).alias("text"))
    groups = int((rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // group_bytes) + 1
    grp = F.pmod(F.xxhash64("doc_id", "salt"), F.lit(groups)).alias("grp")
    # The salt parts rows that share an id; targets are told to all salts.
    said = rows.withColumn("salt", F.floor(F.rand(11) * SALTS * F.when(F.col("doc_id").isNull(), 1 << 20).otherwise(1)).cast("int")).select(grp, F.lit(1).alias("role"), "doc_id", "text")
    named = targets.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id is not null").distinct().withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    grouped = said.unionByName(named.select(grp, F.lit(0).alias("role"), "doc_id", F.lit(None).cast("string").alias("text"))).repartition(groups, "grp")

    def send(table: pa.Table) -> pa.Table:
        own, wanted = _wanted(table)
        tokens = Tokens(own["text"].to_pylist())
        cuts = tokens.dealt(groups)
        counts = (_slices(pack_counts, tokens.counts(weight), cuts) for weight in (np.ones(len(wanted)), wanted))
        name = np.full(groups, table["grp"][0].as_py(), np.int64)
        return pa.table([pa.array(np.arange(groups, dtype=np.int64)), pa.array(name), _slices(pack_sorted, tokens.grams, cuts), *counts], _names(POSTINGS))

    def score(table: pa.Table, sums: pa.Table) -> pa.Table:
        own, wanted = _wanted(table)
        tokens = Tokens(own["text"].to_pylist())
        sizes = np.diff(tokens.dealt(groups)).tolist()
        sums = sums.sort_by("bucket")
        if sums["bucket"].to_pylist() != list(range(groups)):
            raise RuntimeError("a group has not heard from every bucket")
        counts = [np.concatenate([unpack_counts(x, n) for x, n in zip(sums[c].to_pylist(), sizes)]) for c in ("background", "target")]
        kinds, n_background, n_target = (sum(sums[c].to_pylist()) for c in ("kinds", "all_background", "all_target"))
        target = tokens.losses(counts[1], n_target, kinds, 1.0, wanted)
        background = tokens.losses(counts[0], n_background, kinds, n_target / max(n_background, 1), np.ones(len(wanted), bool))
        return pa.table([own["doc_id"], pa.array(tokens.n_words), pa.array(target), pa.array(background), pa.array(target - background)], ["doc_id", "n_tokens", "ce_target", "ce_background", "score"])

    postings = grouped.groupBy("grp").applyInArrow(send, POSTINGS)
    sums = postings.groupBy("bucket").applyInArrow(add_up, SUMS)
    return grouped.groupBy("grp").cogroup(sums.groupBy("grp")).applyInArrow(score, SCORES)
