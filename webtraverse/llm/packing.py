"""Hierarchical multi-length packing of token streams into training sequences.

Every task packs the documents that it reads, so nothing is shuffled. A document longer than the longest window gives
full windows at once; what is left of it, like any shorter document, is routed to the smallest context tier that holds
it. Windows are opened from the longest tier down, each for the longest waiting document of its tier; its gap is
filled from the shorter tiers, longest first, and what no whole document fits is filled by the head of one that is
cut. Each finished window is exactly as long as its tier, a power of two. What a task has left at its end is dealt out
in windows of falling powers of two, so that no id is padding. Finished windows of a tier form step groups of equal
token count, between which the attention cost (the sum of squared piece lengths) is balanced.

Behaviour at the edges: null text is empty text, of which the end id alone remains; equal rows are packed once each, ids of
documents may repeat or be null; documents longer than any window are cut; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import bisect
import unicodedata
import zlib
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .common import TwoAgeCache, map_arrow, text_column

DEFAULT_VOCABULARY = "word_bpe_49k.json"
TIERS = (256, 512, 1024, 2048)
END_ID = 1
STEP_TOKENS = 16_384
MIN_PIECE = 8
BLOCK_TOKENS = 1_500_000
CACHE_ENTRIES = 700_000
MARKS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
TEXTS_AT_ONCE = 256
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier int, sequence_length int, step_group long"


class WordTokenizer:
    """Ids of whole texts by a word-level vocabulary file.

    The vocabulary's own splitting never joins what blanks part, so blank-separated chunks are encoded once and kept. Nor
    does it join letters with the ASCII marks behind them, so many new chunks can be encoded in one string and told apart.
    """

    def __init__(self, path: str | None = None):
        import public_tokenizers
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        file = path or public_tokenizers.path(DEFAULT_VOCABULARY)
        self.model, self.bare, self.ascii = Tokenizer.from_file(file), Tokenizer.from_file(file), Tokenizer.from_file(file)
        self.bare.normalizer = self.ascii.normalizer = normalizers.Sequence([])
        self.ascii.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        self.bare.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        known = self.model.get_vocab(with_added_tokens=True)
        self.ends_word = np.zeros(max(known.values()) + 1, dtype=bool)
        self.ends_word[[i for t, i in known.items() if t.endswith("</w>")]] = True
        self.cache = TwoAgeCache(CACHE_ENTRIES)
        self.others: dict[bytes, bytes] = {}

    def _plain(self, chunks: list[bytes]) -> list[bytes]:
        """Ids of each chunk, encoded by itself."""
        got = self.model.encode_batch_fast([c.decode() for c in chunks], add_special_tokens=False)
        return [np.array(x.ids, dtype="<u4").tobytes() for x in got]

    def _learn(self, chunks: list[bytes]) -> None:
        """Heads of letters, lowered and composed already, are encoded in one string without the vocabulary's own normalising, and
        cut behind each token that ends a word; the few kinds of tails are kept by themselves."""
        stems = [c.rstrip(MARKS) for c in chunks]
        latin = [h.isalpha() for h in stems]
        self._cut(self.ascii, list(compress(chunks, latin)), [h.lower() for h in compress(stems, latin)])
        plain, heads, rest = [], [], []
        for c, head, done in zip(chunks, stems, latin):
            if done:
                continue
            if head and not head.isascii() and (text := head.decode()).lower().isalpha() and "\u03a3" not in text and unicodedata.is_normalized("NFC", text):
                plain.append(c)
                heads.append(text.lower().encode())
            else:
                rest.append(c)
        # Lowering keeps the number of characters of a head but not always that of its bytes.
        self._cut(self.bare, plain, heads, [c[len(c.rstrip(MARKS)) :] for c in plain])
        self.cache.now.update(zip(rest, self._plain(rest)))

    def _cut(self, model, chunks: list[bytes], heads: list[bytes], tails: list[bytes] | None = None) -> None:
        now, others = self.cache.now, self.others
        if tails is None:
            tails = [c[len(h) :] for c, h in zip(chunks, heads)]
        if len(others) > CACHE_ENTRIES:
            others.clear()
        new = [t for t in set(tails) if t not in others]
        others.update(zip(new, self._plain(new)))
        for at in range(0, len(chunks), 50_000):
            part = heads[at : at + 50_000]
            ids = np.array(model.encode_batch_fast([b" ".join(part).decode()], add_special_tokens=False)[0].ids, dtype="<u4")
            cuts, data = (4 * (np.flatnonzero(self.ends_word[ids]) + 1)).tolist(), ids.tobytes()
            if len(cuts) != len(part):
                now.update(zip(chunks[at : at + 50_000], self._plain(chunks[at : at + 50_000])))
                continue
            got = [data[a:b] for a, b in zip([0, *cuts], cuts)]
            now.update(zip(chunks[at : at + 50_000], [g + others[t] if t else g for g, t in zip(got, tails[at : at + 50_000])]))

    def id_bytes(self, texts: list[bytes]) -> list[bytes]:
        """The ids of each text (in UTF-8) as little-endian unsigned 32-bit integers."""
        split = [t.split() for t in texts]
        get = self.cache.now.get
        found = [list(map(get, words)) for words in split]
        gaps = [[i for i, x in enumerate(ids) if x is None] for ids in found]
        absent = {words[i] for words, own in zip(split, gaps) for i in own}
        if absent:
            self._learn(self.cache.missing(absent))
            get = self.cache.now.__getitem__
            for words, ids, own in zip(split, found, gaps):
                for i in own:
                    ids[i] = get(words[i])
        return list(map(b"".join, found))


_tokenizers: dict = {}


def _tokenizer(path) -> WordTokenizer:
    if path not in _tokenizers:
        _tokenizers[path] = WordTokenizer(path)
    return _tokenizers[path]


class Packer:
    """Packs (doc_id, id bytes) of one task. ``finished`` holds windows: (tier, [(doc_id, start, bytes, doc_tokens)])."""

    def __init__(self, tiers=TIERS):
        if any(t & (t - 1) for t in tiers):
            raise ValueError("tiers must be powers of two")
        self.tiers = sorted(tiers)
        self.top = self.tiers[-1]
        self.waiting: list[tuple[int, int]] = []  # (length, key), sorted
        self.pieces: dict[int, tuple] = {}
        self.tokens = 0
        self.key = 0
        self.finished: list[tuple[int, list[tuple]]] = []

    def _put(self, doc, start: int, data: bytes, total: int) -> None:
        if data:
            self.key += 1
            self.pieces[self.key] = (doc, start, data, total)
            bisect.insort(self.waiting, (len(data) // 4, self.key))
            self.tokens += len(data) // 4

    def _take(self, at: int) -> tuple:
        n, key = self.waiting.pop(at)
        self.tokens -= n
        return self.pieces.pop(key)

    def add(self, doc, data: bytes) -> None:
        total, width = len(data) // 4, self.top * 4
        whole = len(data) // width * width
        for a in range(0, whole, width):
            self.finished.append((self.top, [(doc, a // 4, data[a : a + width], total)]))
        self._put(doc, whole // 4, data[whole:], total)

    def _fill(self, size: int) -> list[tuple]:
        """One window of exactly ``size`` ids, from what waits; there must be enough."""
        inside, gap = [], size
        while gap:
            fit = bisect.bisect_right(self.waiting, (gap, float("inf"))) - 1
            while fit >= 0 and 0 < gap - self.waiting[fit][0] < MIN_PIECE:
                fit = bisect.bisect_right(self.waiting, (gap - MIN_PIECE, float("inf"))) - 1
            if fit >= 0:
                piece = self._take(fit)
            else:
                doc, start, data, total = self._take(len(self.waiting) - 1)
                cut = min(gap * 4, len(data))
                piece = (doc, start, data[:cut], total)
                self._put(doc, start + cut // 4, data[cut:], total)
            inside.append(piece)
            gap -= len(piece[2]) // 4
        return inside

    def pack(self) -> None:
        """Close every window that can be filled; the rest waits for more documents."""
        while self.waiting:
            longest = self.waiting[-1][0]
            size = self.tiers[bisect.bisect_left(self.tiers, longest)]
            if self.tokens < size:
                break
            self.finished.append((size, self._fill(size)))

    def close(self) -> None:
        """At the end: windows of falling powers of two."""
        self.pack()
        while self.tokens:
            size = min(self.top, 1 << (self.tokens.bit_length() - 1))
            self.finished.append((size, self._fill(size)))


def step_groups(windows: list[tuple[int, list[tuple]]], first: int, step_tokens: int) -> tuple[list[int], int]:
    """A group number for each window: groups hold one tier and equal tokens; costly windows are dealt back and forth."""
    out = [0] * len(windows)
    by_tier: dict[int, list[int]] = {}
    for i, (tier, _) in enumerate(windows):
        by_tier.setdefault(tier, []).append(i)
    for tier, members in sorted(by_tier.items()):
        groups = -(-len(members) // max(1, step_tokens // tier))
        members.sort(key=lambda i: (-sum((len(p[2]) // 4) ** 2 for p in windows[i][1]), i))
        for n, i in enumerate(members):
            lap, place = divmod(n, groups)
            out[i] = first + (groups - 1 - place if lap % 2 else place)
        first += groups
    return out, first


def pack_documents(docs: DataFrame, vocabulary: str | None = None, tiers=TIERS, end_id: int = END_ID, step_tokens: int = STEP_TOKENS, with_ids: bool = False) -> DataFrame:
    """One row per piece of a document in a sequence; with ``with_ids`` also the ids themselves."""
    schema = PIECES + (", token_ids binary" if with_ids else "")
    end = np.array([end_id], dtype="<u4").tobytes()
    names = [x.split()[0] for x in schema.split(", ")]
    kinds = [pa.int64()] * 7 + [pa.int32()] * 2 + [pa.int64()] + [pa.binary()] * with_ids

    def work(batches):
        task = TaskContext.get()
        base = (task.partitionId() if task else 0) << 36
        tok, packer = _tokenizer(vocabulary), Packer(tiers)
        seq = group = 0

        def flush():
            nonlocal seq, group
            windows, packer.finished = packer.finished, []
            groups, group = step_groups(windows, group, step_tokens)
            rows: list[list] = [[] for _ in names]
            for (size, inside), g in zip(windows, groups):
                at = 0
                for doc, start, data, total in inside:
                    n = len(data) // 4
                    row = (doc, start, n, zlib.crc32(data), total, base + seq, at, size, size, base + g)
                    for col, v in zip(rows, row + ((data,) if with_ids else ())):
                        col.append(v)
                    at += n
                seq += 1
            return pa.record_batch([pa.array(c, k) for c, k in zip(rows, kinds)], names)

        for batch in batches:
            for a in range(0, batch.num_rows, TEXTS_AT_ONCE):
                part = batch.slice(a, TEXTS_AT_ONCE)
                for doc, data in zip(part.column(0).to_pylist(), tok.id_bytes(part.column(1).cast(pa.binary()).to_pylist())):
                    packer.add(doc, data + end)
                if packer.tokens + packer.top * len(packer.finished) > BLOCK_TOKENS:
                    packer.pack()
                    yield flush()
        packer.close()
        tok.cache.old = {}  # an idle worker keeps half at most
        yield flush()

    return map_arrow(docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_column(docs).alias("text")), work, schema)
