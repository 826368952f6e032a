import random

import numpy as np
import pytest

from temporal_patterns.llm import jaccard_trie as J

from .test_against_brute_force import brute_classes


def near_copies(seed, groups, copies, words, edits):
    rng = random.Random(seed)
    rows = []
    for _ in range(groups):
        base = [f"w{rng.randrange(4000)}" for _ in range(rng.randrange(*words))]
        for _ in range(copies):
            t = list(base)
            for _ in range(rng.randrange(edits)):
                if t:
                    t[rng.randrange(len(t))] = f"x{rng.randrange(10**6)}"
            rows.append(" ".join(t))
    rng.shuffle(rows)
    return list(enumerate(rows))


LIKES = [J.Likeness(3, 90, 100), J.Likeness(5, 80, 100), J.Likeness(1, 1, 2)]


@pytest.mark.parametrize("like,shape,group", list(zip(LIKES, [(6, 60, (30, 120), 9), (40, 8, (1, 12), 3), (2, 150, (60, 90), 14)], [8, 4096, 32])))
def test_classes_of_near_copies(spark, monkeypatch, like, shape, group):
    monkeypatch.setattr(J, "BLOCK", 16)
    monkeypatch.setattr(J, "GROUP", group)
    monkeypatch.setattr(J, "HELD", 20 * group)
    rows = near_copies(sum(shape[:2]), *shape)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in J.document_classes(df, like).collect()}
    assert got == brute_classes(rows, like.size, like.num, like.den)


def test_prefix_tree_finds_what_counting_finds():
    rng = np.random.default_rng(5)
    like = J.Likeness(1, 70, 100)
    sets = []
    for _ in range(30):
        base = rng.integers(0, 60, rng.integers(1, 200)).astype(np.uint64)
        sets += [np.unique(np.where(rng.random(len(base)) < p, rng.integers(0, 60, len(base)).astype(np.uint64), base)) for p in (0, 0.05, 0.2)]
    tree = J.PrefixTree(sets)
    for probe in sets:
        want = {k for k, s in enumerate(sets) if 100 * len(np.intersect1d(s, probe)) >= 70 * len(np.union1d(s, probe))}
        assert set(tree.similar(probe, like)) == want


def test_linked_sets_share_a_signature():
    rng = np.random.default_rng(6)
    for like in (J.Likeness(3, 90, 100), J.Likeness(5, 80, 100)):
        for _ in range(400):
            a = np.unique(rng.integers(0, 1 << 63, rng.integers(1, 300)).astype(np.uint64) * np.uint64(2))
            b = np.unique(np.concatenate([a[rng.random(len(a)) > rng.random() * 0.15], rng.integers(0, 1 << 63, rng.integers(0, 1 + len(a) // 8)).astype(np.uint64)]))
            if len(b) and like.den * len(np.intersect1d(a, b)) >= like.num * len(np.union1d(a, b)):
                sa, sb = (J.signatures(x, like) for x in (a, b))
                assert np.intersect1d(np.concatenate(sa), np.concatenate(sb)).size
                band = [int(np.searchsorted(J._bands(like.num, like.den)[0], len(x), "right")) - 1 for x in (a, b)]
                one, two = (x[max(band) - k] for x, k in zip((sa, sb), band))
                parts = J._bands(like.num, like.den)[1][max(band)]
                unsent = max(parts - len(one), parts - len(two))
                differ = len(a) + len(b) - 2 * like.overlap(len(a), len(b))
                assert len(np.intersect1d(one, two)) >= parts - differ - unsent
                assert len(np.intersect1d(one, two)) >= max(J._least_shared(x, max(band) - k, like) for x, k in zip((a, b), band))


def test_odd_rows(spark):
    rows = [(1, "a b c d e f", 9), (1, "a b c d e f", 9), (2, None, 1), (3, "", 2), (4, " \t\n", 3), (None, "a b c d e f", 4), (5, "A b c D e f", 5), (6, "a b", 6), (7, "A B", 6), (8, "q " * 30000, 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, component long")
    got = sorted((r.doc_id is None, r.doc_id or 0, r.n_shingles, r.component_id) for r in J.document_classes(df, J.Likeness(3, 90, 100)).collect())
    assert got == [(False, 1, 4, 1), (False, 1, 4, 1), (False, 2, 0, 2), (False, 3, 0, 3), (False, 4, 0, 4), (False, 5, 4, 1), (False, 6, 1, 6), (False, 7, 1, 6), (False, 8, 1, 8), (True, 0, 4, None)]
    assert J.document_classes(df.limit(0)).count() == 0
    kept = J.keep_one(df, J.Likeness(3, 90, 100))
    assert kept.columns == df.columns and sorted(r.doc_id or 0 for r in kept.collect()) == [0, 1, 1, 2, 3, 4, 6, 8]
