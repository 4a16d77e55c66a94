"""Corpus operators over texts, against the libraries they follow and against brute force."""

import hashlib
import random
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from webtraverse.llm import byte_bpe, language_model, licenses, minhash_dedup, packing, quality, substring_dedup

ODD = ["", " \n\t ", "a", "É! É! H̱! ß. DON'T! it's' 5! a5! İ. ΑΣ. 日本。!! ²!", "x" * 3000, "<|endoftext|> the", "a<|endoftext|>b <|startoftext|>. <|ENDOFTEXT|>", "\x1c\x1d a", "the the " * 400]


def frame(spark, rows):
    """Documents with columns whose names clash with those that operators use themselves."""
    full = [(d, t, "en", "s", 1, "x", 2, 3.0) for d, t in rows]
    return spark.createDataFrame(full, "doc_id long, text string, lang string, source string, n_chars long, key string, rep int, score double")


@pytest.fixture(scope="module")
def texts(spark, small):
    return [(r[0], r[1]) for r in spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").collect()]


@pytest.fixture(scope="module")
def rows(texts):
    return texts[:120] + [(10_000 + i, t) for i, t in enumerate(ODD)] + [(20_000, None), (None, "no id at all"), texts[3], texts[3]]


def test_bpe_equals_library(spark, rows):
    import public_tokenizers as P
    import tiktoken

    ranks = byte_bpe.read_ranks(P.path(byte_bpe.DEFAULT_RANKS))
    reference = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    expected = []
    for d, t in rows:
        ids = np.array(reference.encode_ordinary(t or ""), dtype="<u4")
        expected.append((d, len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    got = [tuple(r) for r in byte_bpe.round_trip_digest(frame(spark, rows)).collect()]
    assert sorted(got, key=str) == sorted(expected, key=str)
    assert byte_bpe.round_trip_digest(frame(spark, rows).limit(0)).count() == 0


def test_bpe_join_repairs_any_seam():
    import public_tokenizers as P

    bpe = byte_bpe.ByteBpe(byte_bpe.read_ranks(P.path(byte_bpe.DEFAULT_RANKS)))
    rng = random.Random(4)
    for _ in range(400):
        data = "".join(rng.choice(["a", "b", "é", "th", "in", "er", "ö", "ing"]) for _ in range(rng.randint(2, 60))).encode()
        cut = rng.randint(0, len(data))
        assert bpe.join(bpe.leaf(data[:cut]) if cut else [], bpe.leaf(data[cut:]) if cut < len(data) else []) == bpe.leaf(data) == bpe.encode(data)


def test_bpe_decodes_what_it_encodes(spark, rows):
    encoded = byte_bpe.encode_documents(frame(spark, rows))
    back = {r["doc_id"]: bytes(r["data"]).decode() for r in byte_bpe.decode_documents(encoded).collect()}
    assert all(back[d] == (t or "") for d, t in rows)


def test_packing_is_a_partition_without_padding(spark, rows):
    import public_tokenizers as P
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(P.path(packing.DEFAULT_VOCABULARY))
    pieces = packing.pack_documents(frame(spark, rows).coalesce(2), with_ids=True).collect()
    ids = {d: model.encode(t or "", add_special_tokens=False).ids + [1] for d, t in rows}
    copies = defaultdict(int)
    for d, _ in rows:
        copies[d] += 1
    inside, by_doc = defaultdict(list), defaultdict(list)
    for p in pieces:
        own = np.frombuffer(bytes(p["token_ids"]), dtype="<u4")
        assert own.tolist() == ids[p["doc_id"]][p["start"] : p["start"] + p["length"]] and p["doc_tokens"] == len(ids[p["doc_id"]])
        assert p["ids_crc32"] == zlib.crc32(bytes(p["token_ids"]))
        inside[p["sequence_id"]].append(p)
        by_doc[p["doc_id"]].append((p["start"], p["length"]))
    for d, own in by_doc.items():
        assert sum(n for _, n in own) == copies[d] * len(ids[d])
        places = sorted(own * 1)
        covered = np.zeros(len(ids[d]), dtype=int)
        for a, n in places:
            covered[a : a + n] += 1
        assert (covered == copies[d]).all()
    for own in inside.values():
        own.sort(key=lambda p: p["offset"])
        size = own[0]["sequence_length"]
        assert size <= 2048 and size & (size - 1) == 0 and sum(p["length"] for p in own) == size
        assert [p["offset"] for p in own] == np.cumsum([0] + [p["length"] for p in own[:-1]]).tolist()
    assert packing.pack_documents(frame(spark, rows).limit(0)).count() == 0


def test_step_groups_have_one_tier_and_equal_tokens():
    windows = [(256, [(i, 0, b"\0" * 1024, 256)]) for i in range(64)] + [(2048, [(i, 0, b"\0" * 8192, 2048)]) for i in range(16)]
    groups, end = packing.step_groups(windows, 0, 16_384)
    tokens = defaultdict(int)
    for (tier, _), g in zip(windows, groups):
        tokens[g] += tier
    assert end == 3 and set(tokens.values()) == {16_384}


def brute_repeats(rows, width):
    seen = {}
    for d, t in rows:
        w = (t or "").encode().split()
        for i in range(len(w) - width + 1):
            k = tuple(w[i : i + width])
            if d is not None and seen.get(k, d) >= d:
                seen[k] = d
    out = []
    for d, t in rows:
        w = (t or "").encode().split()
        keep = [True] * len(w)
        for i in range(len(w) - width + 1):
            if d is not None and seen[tuple(w[i : i + width])] < d:
                keep[i : i + width] = [False] * width
        left = [x for x, k in zip(w, keep) if k]
        out.append((d, len(w), len(w) - len(left), hashlib.sha256(b" ".join(left)).hexdigest()))
    return out


@pytest.mark.parametrize("most", [None, 3])
def test_repeated_passages_against_brute_force(spark, monkeypatch, most):
    if most:
        monkeypatch.setattr(substring_dedup, "PIECES_AT_A_SHARD", most)
        monkeypatch.setattr(substring_dedup, "SOURCES_AT_A_SHARD", most - 1)
    rng = random.Random(3)
    words = [f"w{i}" for i in range(6)]
    passages = [[rng.choice(words) for _ in range(rng.randint(5, 30))] for _ in range(4)]
    rows = []
    for d in range(60):
        w = []
        for _ in range(rng.randint(0, 5)):
            w += rng.choice(passages) if rng.random() < 0.6 else [rng.choice(words) for _ in range(rng.randint(1, 15))]
        rows.append((d % 50, " ".join(w) if rng.random() < 0.95 else None))
    rows += [rows[3], rows[7], (None, rows[9][1]), (77, "w1 " * 3000)]
    got = [tuple(r) for r in substring_dedup.digest(frame(spark, rows), 8, 3).collect()]
    assert sorted(got, key=str) == sorted(brute_repeats(rows, 8), key=str)
    cleaned = substring_dedup.clean(frame(spark, rows), 8, 3)
    assert cleaned.columns == frame(spark, rows).columns and cleaned.count() == len(rows)
    assert substring_dedup.digest(frame(spark, rows).limit(0)).count() == 0


def test_repeated_passages_on_the_table(spark, small, texts):
    got = [tuple(r) for r in substring_dedup.digest(spark.read.parquet(f"{small}/documents.parquet")).collect()]
    assert sorted(got) == sorted(brute_repeats(texts, 50))


def brute_groups(rows, k):
    sets = {d: minhash_dedup.shingle_set(minhash_dedup.words_of(t or ""), k) for d, t in rows if d is not None}
    ids = sorted(sets)
    parent = {i: i for i in ids}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    where = defaultdict(list)
    for i in ids:
        met = defaultdict(int)
        for s in sets[i]:
            for j in where[s]:
                met[j] += 1
            where[s].append(i)
        for j, n in met.items():
            if 100 * n >= 80 * (len(sets[i]) + len(sets[j]) - n):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return {d: (len(sets[d]), root(d)) for d in ids}


@pytest.mark.parametrize("k", [2, 5])
def test_near_duplicates_against_brute_force(spark, rows, k):
    got = minhash_dedup.near_duplicates(frame(spark, rows), k).collect()
    expected = brute_groups(rows, k)
    assert len(got) == len(rows)
    for r in got:
        if r["doc_id"] is None:
            assert r["component_id"] is None and r["kept"]
        else:
            assert (r["n_shingles"], r["component_id"]) == expected[r["doc_id"]] and r["kept"] == (r["doc_id"] == r["component_id"])


def test_large_group_of_near_copies(spark):
    rng = random.Random(5)
    base = [rng.choice("abcdefghijklmnop") + str(rng.randint(0, 99)) for _ in range(200)]
    rows = []
    for d in range(260):
        w = list(base)
        for _ in range(rng.randint(0, 22)):
            w[rng.randrange(200)] = f"x{rng.randint(0, 10**6)}"
        rows.append((d, " ".join(w)))
    got = {r["doc_id"]: r["component_id"] for r in minhash_dedup.near_duplicates(frame(spark, rows), 2).collect()}
    assert got == {d: c for d, (_, c) in brute_groups(rows, 2).items()}
    stay = minhash_dedup.drop_near_duplicates(frame(spark, rows), 2)
    assert {r["doc_id"] for r in stay.collect()} == set(got.values()) and stay.columns == frame(spark, rows).columns
    assert minhash_dedup.near_duplicates(frame(spark, rows).limit(0)).count() == 0


def test_pairs_at_the_threshold_in_large_nodes_of_outsiders(spark):
    template = " ".join(f"t{i}" for i in range(100))
    rows = []
    for p in range(800):  # 134 of 166 words are common in a pair, 100 of 200 elsewhere
        for side in "ab":
            own = [f"p{p}_{i}" for i in range(34)] + [f"p{p}{side}{i}" for i in range(16)]
            rows.append((len(rows), f"{template} {' '.join(own)}"))
    got = {r["doc_id"]: r["component_id"] for r in minhash_dedup.near_duplicates(frame(spark, rows), 1).collect()}
    assert all(c in (d, d - d % 2) for d, c in got.items())
    assert sum(got[2 * p + 1] == 2 * p for p in range(800)) >= 799


@pytest.mark.parametrize("leaf", [6, 40])
def test_near_duplicates_where_most_nodes_are_large(spark, rows, monkeypatch, leaf):
    monkeypatch.setattr(minhash_dedup, "LEAF", leaf)
    monkeypatch.setattr(minhash_dedup, "MEMBER_CHUNK", 8)
    monkeypatch.setattr(minhash_dedup, "ASKED_PART", 4)
    monkeypatch.setattr(minhash_dedup, "PAIRS_AT_ONCE", 3)
    rng = random.Random(12)
    near = []
    for d in range(90):  # three templates that share words, of which copies differ in up to a third
        w = [f"c{i}" for i in range(60)] + [f"t{d % 3}_{i}" for i in range(60)]
        for _ in range(rng.randint(0, 30)):
            w[rng.randrange(120)] = f"x{rng.randint(0, 10**6)}"
        near.append((30_000 + d, " ".join(w)))
    table = rows[:60] + near
    got = {r["doc_id"]: r["component_id"] for r in minhash_dedup.near_duplicates(frame(spark, table), 1).collect()}
    assert got == {d: c for d, (_, c) in brute_groups(table, 1).items()}


def test_trees_follow_threshold_and_recall():
    assert minhash_dedup.trees_for(0.8) == 9 and minhash_dedup.trees_for(0.9) < 9 < minhash_dedup.trees_for(0.6) < minhash_dedup.trees_for(0.6, 0.99999)
    rng = np.random.default_rng(3)
    for threshold in (0.6, 0.7):  # sets of 200 with just that similarity
        common = round(400 * threshold / (1 + threshold))
        left = [rng.integers(0, 1 << 63, 200, dtype=np.uint64) for _ in range(300)]
        right = [np.concatenate([x[:common], rng.integers(0, 1 << 63, 200 - common, dtype=np.uint64)]) for x in left]
        nodes = [minhash_dedup.start_nodes(np.stack([minhash_dedup.signature(x) for x in side]), minhash_dedup.trees_for(threshold)) for side in (left, right)]
        assert sum(bool(set(a.tolist()) & set(b.tolist())) for a, b in zip(*nodes)) >= 295


def test_one_row_of_an_id_stays_whatever_the_order(spark):
    rows = [(1, "a b c d e f g"), (1, "other words stand here now today"), (1, "third text of the same id here"), (2, "a b c d e f g h"), (None, "x"), (None, "x")]
    first = sorted(tuple(r) for r in minhash_dedup.drop_near_duplicates(frame(spark, rows).repartition(4)).where("doc_id is not null").collect())
    again = sorted(tuple(r) for r in minhash_dedup.drop_near_duplicates(frame(spark, rows[::-1]).coalesce(1)).where("doc_id is not null").collect())
    assert first == again and len(first) == len({r[0] for r in first})
    assert minhash_dedup.drop_near_duplicates(frame(spark, rows)).where("doc_id is null").count() == 2


def test_quality_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = quality.train(docs, labels.where(~quality.held_out(F.col("doc_id"))))
    scored = quality.score_documents(docs, model).join(labels, "doc_id").where("held_out").collect()
    assert sum(r["predicted"] == r["quality"] for r in scored) >= 0.97 * len(scored)
    good = quality.keep_good(docs, model)
    assert good.columns == docs.columns and 0 < good.count() < docs.count()


def test_quality_without_labels_of_both_kinds(spark, rows):
    labels = spark.createDataFrame([(1, 1), (None, 0), (2, None)], "doc_id long, quality int")
    model = quality.train(frame(spark, rows), labels)
    got = quality.score_documents(frame(spark, rows), model).collect()
    assert len(got) == len(rows) and all(r["score"] == 0.5 and r["predicted"] == 1 for r in got)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in got if r["doc_id"] is not None)


def brute_losses(rows, targets):
    """Both models counted anew for each document, without it."""
    said = [(d, ["", *[w.decode() for w in language_model.words_of(t or "")], ""]) for d, t in rows]
    kinds = len({w for _, s in said for w in s})
    sizes = [sum(len(s) - 1 for d, s in said if mine(d)) for mine in (lambda d: d in targets, lambda d: True)]
    out = []
    for at, (d, own) in enumerate(said):
        losses = []
        for mine, scale in ((lambda d: d in targets, 1.0), (lambda d: True, sizes[0] / sizes[1])):
            one, two, total = defaultdict(int), defaultdict(int), 0
            for i, (e, s) in enumerate(said):
                if i != at and mine(e):
                    for a, b in zip(s, s[1:]):
                        one[b] += 1
                        two[a, b] += 1
                        total += 1
            p1 = lambda w: (scale * one[w] + language_model.BASE_PRIOR / kinds) / (scale * total + language_model.BASE_PRIOR)  # noqa: E731, B023
            losses.append(-sum(np.log((scale * two[a, b] + language_model.PRIOR * p1(b)) / (scale * one[a] + language_model.PRIOR)) for a, b in zip(own, own[1:])) / (len(own) - 1))
        out.append((d, len(own) - 2, *losses))
    return out


def test_packed_numbers():
    for values in ([], [0], [5, 5, 2**64 - 1], sorted(random.Random(1).randrange(2**64) for _ in range(500))):
        assert language_model.unpack_sorted(language_model.pack_sorted(np.array(values, np.uint64))).tolist() == values
    counts = np.array([0, 1, 254, 255, 256, 2**40])
    assert language_model.unpack_counts(language_model.pack_counts(counts), 6).tolist() == counts.tolist()


@pytest.mark.parametrize("group_bytes", [language_model.GROUP_BYTES, 900])
def test_cross_entropy_difference_against_brute_force(spark, texts, group_bytes):
    rows = [(d, t[:400]) for d, t in texts[:25]] + [(900, None), (901, ""), (902, "\u00ff"), (903, "One, two. one TWO!"), (904, "one two one two"), (None, "one"), (None, "one"), (texts[1][0], "a row that shares its id"), (905, "word " * 3000)]
    named = {texts[i][0] for i in (1, 2, 5)} | {904}
    targets = spark.createDataFrame([(d,) for d in named] + [(texts[2][0],), (None,), (12_345,)], "doc_id long")
    got = [tuple(r) for r in language_model.cross_entropy_difference(frame(spark, rows), targets, group_bytes).collect()]
    key = lambda r: (str(r[0]), *np.round(r[1:], 6))
    for r, e in zip(sorted(got, key=key), sorted(brute_losses(rows, named), key=key), strict=True):
        assert r[:2] == e[:2] and abs(r[2] - e[2]) < 1e-9 and abs(r[3] - e[3]) < 1e-9 and abs(r[4] - (e[2] - e[3])) < 1e-9
    assert language_model.cross_entropy_difference(frame(spark, rows).limit(0), targets).count() == 0


def test_cross_entropy_difference_tells_topics_and_copies_apart(spark):
    rng = random.Random(9)
    ours, theirs = [f"a{i}" for i in range(300)], [f"b{i}" for i in range(300)]
    text = lambda words: " ".join(rng.choice(words) for _ in range(120))
    rows = [(i, text(ours if i % 2 else theirs)) for i in range(80)]
    rows += [(1000 + i, t) for i, t in rows[:4]]
    targets = spark.createDataFrame([(i,) for i in range(1, 40, 2)], "doc_id long")
    got = {r["doc_id"]: r for r in language_model.cross_entropy_difference(frame(spark, rows), targets).collect()}
    assert max(got[i]["score"] for i in range(41, 80, 2)) < min(got[i]["score"] for i in range(4, 80, 2))  # targets or not
    twice = [got[i]["ce_background"] for i in (0, 1, 2, 3, 1000, 1001, 1002, 1003)]
    assert max(twice) < min(got[i]["ce_background"] for i in range(4, 80)) - 1
    nothing = language_model.cross_entropy_difference(frame(spark, rows), targets.limit(0)).collect()
    assert all(r["score"] == 0 for r in nothing)


def test_licences(spark):
    notice = "Released under the MIT License."
    files = [
        ("1", "a/LICENSE", notice), ("2", "a/b/x", "plain words only"), ("3", "a/b/y", "many plain words come before it\nLicensed under the Apache License, Version 2.0.\nand many more come after it"), ("4", "c/x", "plain"),
        ("5", "a/b/c/z", None), ("6", "d/n", "This work is licensed under the GNU General Public License, version 3."), ("7", "d/e/f", ""), ("8", None, "licensed"),
    ]
    got = {r["row_id"]: (r["license"], r["origin"]) for r in licenses.scan(spark.createDataFrame(files, "row_id string, path string, text string")).collect()}
    assert got == {"1": ("mit", "own"), "2": ("mit", "inherited"), "3": ("apache-2.0", "own"), "4": (None, None), "5": ("mit", "inherited"), "6": ("gpl-3.0", "own"), "7": ("gpl-3.0", "inherited"), "8": (None, None)}
    assert licenses.scan_documents(frame(spark, [(1, None), (None, notice)])).count() == 2


MIT = """Copyright (c) 2020 A Person

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE."""


def test_licences_that_are_diluted_wrapped_or_whole(spark):
    other = "plain words that say nothing about it"
    cases = {
        "diluted": ("Here some words come first: Released under the MIT License. " + other, "mit"),
        "wrapped": (" * This work is licensed under the GNU General\n * Public License,\n * version 3.\n" + other, "gpl-3.0"),
        "named": (f"{other}; see the Apache License, Version 2.0, for it, {other}", "apache-2.0"),
        "spdx": (f"// SPDX-License-Identifier: Apache-2.0\n{other}", "apache-2.0"),
        "spdx-mit": ("# spdx-license-identifier: MIT", "mit"),
        "nc": ("Licensed under CC BY-NC 4.0.", "cc-by-nc-4.0"),
        "start": ("under the GNU Lesser General Public License", "lgpl-3.0"),
        "none": ("Komm mit. " + other + " the license of a driver, apache helicopters, cc to all, permission slips", None),
    }
    files = [(i, f"p{i}/{k}", t) for i, (k, (t, _)) in enumerate(cases.items())] + [(90, "w/a", MIT), (91, "w/b/c", other), (92, "x/a", MIT + (" " + other) * 60), (93, "x/b", other)]
    got = {r["row_id"]: (r["license"], r["origin"]) for r in licenses.scan(spark.createDataFrame(files, "row_id long, path string, text string")).collect()}
    assert {k: got[i][0] for i, k in enumerate(cases)} == {k: v for k, (_, v) in cases.items()}
    assert got[90] == ("mit", "own") and got[91] == ("mit", "inherited") and got[92] == ("mit", "own") and got[93] == (None, None)


def test_licences_of_rows_without_or_with_shared_ids(spark):
    notice = "Released under the MIT License."
    files = [(None, "a/x", notice), (2, "b/x", notice), (2, "b/y/z", "plain"), (2, "c/x", "plain"), (3, "d/x", notice + " " + "word " * 20), (3, "d/x", notice + " " + "word " * 20)]
    got = [tuple(r) for r in licenses.scan(spark.createDataFrame(files, "row_id long, path string, text string")).collect()]
    shown = sorted(((r[0], r[1], r[2], r[3], r[5]) for r in got), key=str)
    assert shown == sorted([(None, "a/x", "mit", "own", 1), (2, "b/x", "mit", "own", 1), (2, "b/y/z", "mit", "inherited", 0), (2, "c/x", None, None, 0), (3, "d/x", "mit", "own", 1), (3, "d/x", "mit", "own", 1)], key=str)
    assert licenses.scan_documents(frame(spark, []).limit(0)).count() == 0
