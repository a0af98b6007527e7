"""Exact and near duplicates and decontamination against brute force, and their edge cases."""

import hashlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from poolcurator.llm import components, decontamination, exact_dedup, near_dedup, wordhash
from poolcurator.llm.store import write_table

DOCS = "doc_id long, text string, lang string, source string, n_chars long, id string, h long, key string, n int"


def docs(spark, texts, ids=None):
    ids = ids if ids is not None else range(len(texts))
    return spark.createDataFrame([(i, t, "en", "s", 0, "x", 1, "y", 2) for i, t in zip(ids, texts)], DOCS)


EDGES = [None, "", "", " \t\n ", "a b", "a  b", "a\nb", "a b ", "%%%", "one two three four five six", "one two three four five six", "x" * 50_000, "w " * 30_000]


def normal(t):
    return re.sub(r"[\x20\x09-\x0D]+", " ", t or "")


def test_exact_classes(spark):
    got = {r.doc_id: r for r in exact_dedup.exact_duplicates(docs(spark, EDGES)).collect()}
    assert len(got) == len(EDGES)
    for i, t in enumerate(EDGES):
        same = [j for j, u in enumerate(EDGES) if normal(u) == normal(t)]
        assert (got[i].keep_id, got[i].group_size, got[i].kept) == (same[0], len(same), i == same[0])
        assert got[i].text_sha256 == hashlib.sha256(normal(t).encode()).hexdigest()


def weak_hash(c):
    return F.pmod(F.xxhash64(c), F.lit(7)).cast("long") * F.lit(1 << 58)


def test_colliding_hashes_are_chained_and_directory_splits(spark):
    d = docs(spark, [f"text {i % 40}" for i in range(200)])
    index = exact_dedup.build_index(d, bucket_entries=5, max_depth=6, hash_column=weak_hash)
    entries = index.entries.collect()
    assert len(entries) == 40 and len({e.bucket for e in entries}) > 1 and index.directory.depth > 1
    for h in {e.h for e in entries}:
        chain = sorted((e.chain, e.sha) for e in entries if e.h == h)
        assert [c for c, _ in chain] == list(range(len(chain))) and [s for _, s in chain] == sorted(s for _, s in chain)
    found = {r.id: r.keep_id for r in exact_dedup.lookup(d, index).collect()}
    assert found == {i: i % 40 for i in range(200)}


def test_lookups_go_through_directory_and_bucket(spark):
    d = docs(spark, [f"text {i % 40}" for i in range(200)])
    index = exact_dedup.build_index(d, bucket_entries=5, max_depth=6)
    other = index.directory.cells[0]
    lost = {r.keep_id for r in index.entries.where(F.col("bucket") == other).collect()}
    assert lost
    index.directory.cells = [1 if b == other == 0 else 0 if b == other else b for b in index.directory.cells]  # a wrong directory
    found = {r.id: r.keep_id for r in exact_dedup.lookup(d, index).collect()}
    assert set(found) == {i for i in range(200) if i % 40 not in lost}


def test_a_batch_added_gives_the_index_of_all(spark):
    texts = [f"text {i % 70}" for i in range(300)]
    first, then = docs(spark, texts[:100]), docs(spark, texts[100:], list(range(100, 300)))
    index = exact_dedup.build_index(first, bucket_entries=8, max_depth=8)
    depth = index.directory.depth
    index = exact_dedup.add(index, then)
    whole = exact_dedup.build_index(docs(spark, texts), bucket_entries=8, max_depth=8)
    rows = lambda x: sorted(tuple(r) for r in x.entries.select("h", "sha", "keep_id", "group_size", "chain").collect())
    assert rows(index) == rows(whole) and index.n_rows == 300 and index.directory.depth >= depth
    assert {r.id: r.keep_id for r in exact_dedup.lookup(docs(spark, texts), index).collect()} == {i: i % 70 for i in range(300)}


def test_directory_doubles_and_covers_every_prefix():
    counts = {p: (100 if p == 5 else p) for p in range(64)}
    at_once, piecewise = exact_dedup.Directory(60, 6), exact_dedup.Directory(60, 6)
    at_once.add(counts)
    for p, n in counts.items():
        piecewise.add({p: n})
    for d in (at_once, piecewise):
        assert len(d.cells) == 2**d.depth
        assert sum(map(lambda f: sum(f.values()), d.fill)) == sum(counts.values())
        for p in range(64):
            b = d.cells[p >> (6 - d.depth)]
            assert p >> (6 - d.local[b]) == d.bits[b]
        assert all(sum(f.values()) <= 60 or d.local[b] == 6 for b, f in enumerate(d.fill))
    assert {(d, b) for d, b in zip(at_once.local, at_once.bits)} == {(d, b) for d, b in zip(piecewise.local, piecewise.bits)}


@pytest.mark.parametrize("operator", [exact_dedup.exact_duplicates, near_dedup.near_duplicates])
def test_empty_table(spark, operator):
    assert operator(docs(spark, [])).count() == 0


def shingles(t, k=5):
    w = re.findall(r"[0-9a-z\x80-\U0010ffff]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def test_words_follow_the_definition():
    texts = ["Héllo wörld-foo 12", "", "ABC", "abc", "x" * 600_000 + " y", "end", "日本 語"]
    import pyarrow as pa

    raw, off = wordhash.utf8(pa.array(texts))
    word, row, _ = wordhash.words(raw, off)
    assert np.bincount(row, minlength=7).tolist() == [4, 0, 1, 1, 2, 1, 2]
    assert word[row == 2][0] == word[row == 3][0]
    assert len(set(word.tolist())) == len(word) - 1


def near_family(rng, base, n, edits):
    out = []
    for _ in range(n):
        w = base.split()
        for _ in range(edits):
            w[rng.randrange(len(w))] = f"new{rng.randrange(10**9)}"
        out.append(" ".join(w))
    return out


def brute_classes(texts):
    sets = [shingles(t) for t in texts]
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            same = normal_key(texts[i]) == normal_key(texts[j])
            u = len(sets[i] | sets[j])
            if same or (u and len(sets[i] & sets[j]) / u >= 0.8):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(texts))]


def normal_key(t):
    w = re.findall(r"[0-9a-z\x80-\U0010ffff]+", (t or "").lower())
    return tuple(w) if w else ("raw", t or "")


@pytest.mark.parametrize("block", [1000, 16])
def test_near_classes_match_brute_force(spark, block):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    texts = []
    for f in range(12):
        base = " ".join(word() for _ in range(rng.randrange(60, 200)))
        texts += near_family(rng, base, 6, f % 6)
    texts += [" ".join(word() for _ in range(rng.randrange(1, 40))) for _ in range(30)]
    texts += ["a b c", "a b c", "A B C", None, "", "%%%", "%%% ", "x " * 40_000]
    got = {r.doc_id: r for r in near_dedup.near_duplicates(docs(spark, texts), block_docs=block).collect()}
    want = brute_classes(texts)
    assert [got[i].class_id for i in range(len(texts))] == want
    assert all(got[i].kept == (want[i] == i) and got[i].class_size == want.count(want[i]) for i in got)


def test_sketch_estimates_probability_jaccard():
    rng = np.random.default_rng(5)
    items = rng.integers(1, 1 << 44, 300).astype(np.uint64)
    a, b = items[:250], items[50:]
    x, y = rng.random(250) + 0.5, rng.random(250) + 0.5
    y[:200] = x[50:]
    order_a, order_b = np.argsort(a), np.argsort(b)
    exact = near_dedup.probability_jaccard(a[order_a], x[order_a], b[order_b], y[order_b])
    row, item, w = np.repeat([0, 1], 250), np.concatenate([a, b]), np.concatenate([x, y])
    s = near_dedup.sketch(row, item, w, 2, 4096)
    assert abs((s[0] == s[1]).mean() - exact) < 0.04
    naive = 0.0
    wx, wy = dict(zip(a.tolist(), x)), dict(zip(b.tolist(), y))
    for i in set(wx) & set(wy):
        naive += 1 / sum(max(wx.get(j, 0) / wx[i], wy.get(j, 0) / wy[i]) for j in set(wx) | set(wy))
    assert abs(naive - exact) < 1e-9


def test_short_rows_fill_all_slots():
    s = near_dedup.sketch(np.array([0, 1, 1]), np.array([7, 8, 9], dtype=np.uint64), np.ones(3), 3, 64)
    assert (s[0] == 7).all() and set(s[1].tolist()) == {8, 9} and (s[2] == 0).all()


def test_components(spark):
    edges = [(i, i + 1) for i in range(1, 60)] + [(100, 101), (102, 101), (7, 7)]
    got, _ = components.connected_components(spark.createDataFrame(edges, "a long, b long"))
    want = {**{i: 1 for i in range(1, 61)}, 100: 100, 101: 100, 102: 100}
    assert {r.node: r.root for r in got.collect()} == want


def test_contained_items(spark):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    items = [" ".join(word() for _ in range(rng.choice([2, 4, 5, 20, 40]))) for _ in range(40)] + ["", None]
    texts = []
    for i in range(150):
        body = [word() for _ in range(rng.choice([3, 50, 3000]))]
        for _ in range(rng.choice([0, 0, 1, 3, 25])):
            it = (rng.choice(items) or "").split()
            if it and rng.random() < 0.4:
                it[rng.randrange(len(it))] = word()
            at = rng.randrange(len(body))
            body[at:at] = it
        texts.append(" ".join(body))
    texts += [None, "", "%%"]
    its = spark.createDataFrame([(i, t, 1) for i, t in enumerate(items)], "item_id long, text string, doc_id int")
    for block in (8_000_000, 300):
        got = {(r.doc_id, r.item_id): r.shared for r in decontamination.find_items(docs(spark, texts), its, block_chars=block).collect()}
        want = {}
        for j, it in enumerate(items):
            n = min(5, len((it or "").split()))
            q = shingles(it, n) if n else set()
            for i, t in enumerate(texts):
                shared = len(q & shingles(t, n)) if n and len((t or "").split()) >= n else 0
                if q and shared >= 0.8 * len(q) - 1e-9:
                    want[i, j] = shared
        assert got == want
    assert decontamination.find_items(docs(spark, []), its).count() == 0
    assert decontamination.find_items(docs(spark, texts), its.limit(0)).count() == 0
    kept = {r.doc_id for r in decontamination.decontaminate(docs(spark, texts), its).collect()}
    assert kept == set(range(len(texts))) - {i for i, _ in want}


def test_items_that_repeat_or_lack_an_id(spark):
    a, b = "one two three four five six seven eight nine ten", "red blue green gold grey pink teal plum rust sand"
    near = "one two three four five six seven eight nine eleven"
    its = spark.createDataFrame([(7, a), (7, near), (7, b), (None, a), (None, b), (8, b)], "item_id long, text string")
    for block in (8_000_000, 40):
        got = decontamination.find_items(docs(spark, [a, b, "x", f"{a} {b}"]), its, block_chars=block).collect()
        assert sorted((r.doc_id, r.item_id, r.containment) for r in got if r.item_id is not None) == [(0, 7, 1.0), (1, 7, 1.0), (1, 8, 1.0), (3, 7, 1.0), (3, 8, 1.0)]
        assert sorted(r.doc_id for r in got if r.item_id is None) == [0, 1, 3, 3]


def test_rows_without_an_id_stay(spark):
    text = "one two three four five six seven eight nine ten"
    rows = spark.createDataFrame([(1, text), (None, text), (2, text), (None, None)], "doc_id long, text string")
    near = sorted(((r.doc_id, r.class_id, r.class_size, r.kept) for r in near_dedup.near_duplicates(rows).collect()), key=str)
    assert near == sorted([(1, 1, 2, True), (2, 1, 2, False), (None, None, 1, True), (None, None, 1, True)], key=str)
    exact = [(r.doc_id, r.keep_id, r.group_size, r.kept) for r in exact_dedup.exact_duplicates(rows).collect()]
    assert sorted(exact, key=str) == sorted([(1, 1, 3, True), (2, 1, 3, False), (None, 1, 3, False), (None, None, 1, True)], key=str)


def test_components_that_do_not_settle_raise(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)], "a long, b long")
    with pytest.raises(RuntimeError):
        components.connected_components(edges, max_rounds=1)


def test_tables_are_written_to_the_shared_folder(spark):
    df, path = write_table(spark.range(3).toDF("id"), "t")
    assert path.startswith(spark.conf.get("spark.checkpoint.dir")) and df.count() == 3


def test_near_copies_of_which_one_repeats_a_line(spark):
    texts, pairs = [], 60
    for i in range(pairs):
        rng = random.Random(i)
        body = [f"w{i}x{rng.randrange(10**9)}" for _ in range(64)]
        line = body[-10:]
        texts += [" ".join(body), " ".join(body + line * 200)]
    for i in range(pairs):  # plain Jaccard is at least 0.8
        a, b = ({tuple(w[j : j + 5]) for j in range(len(w) - 4)} for w in (t.split() for t in texts[2 * i : 2 * i + 2]))
        assert len(a & b) / len(a | b) >= 0.8
    got = {r.doc_id: r.class_id for r in near_dedup.near_duplicates(docs(spark, texts)).collect()}
    assert all(got[2 * i] == got[2 * i + 1] for i in range(pairs))
