import hashlib
import random
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecpath.llm import jaccard, substring
from vecpath.llm.components import components
from vecpath.llm.jaccard import jaccard_join
from vecpath.llm.substring import substring_dedup

SCHEMA = "doc_id long, text string, n_removed string"


def word_list(rng, n, size=400):
    return [f"w{rng.randint(0, size)}" for _ in range(n)]


def removed(rows, window):
    first = {}
    for i, t in sorted((r[0], r[1]) for r in rows if r[0] is not None):
        w = (t or "").encode().split()
        for k in range(len(w) - window + 1):
            first.setdefault(tuple(w[k : k + window]), i)
    out = []
    for i, t in rows:
        w = (t or "").encode().split()
        gone = [False] * len(w)
        for k in range(len(w) - window + 1):
            if i is not None and first[tuple(w[k : k + window])] < i:
                gone[k : k + window] = [True] * window
        kept = b" ".join(x for x, g in zip(w, gone) if not g)
        out.append((i, len(w), sum(gone), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def corpus(seed):
    """Texts with shared passages, runs, periods, edits, edges and repeated rows."""
    rng = random.Random(seed)
    passages = [word_list(rng, n) for n in (50, 51, 60, 90, 200)]
    rows = []
    for i in range(60):
        w = word_list(rng, rng.randint(0, 120), 10_000)
        for _ in range(rng.randint(0, 3)):
            p = rng.choice(passages)
            a = rng.randint(0, max(0, len(p) - 50))
            w += p[a : a + rng.choice([49, 50, 55, 300])]
            w += word_list(rng, rng.randint(0, 30), 10_000)
        if rng.random() < 0.2:
            w += ["und"] * rng.choice([40, 51, 300])
        if rng.random() < 0.2:
            w += ["a", "b", "c"] * rng.choice([10, 17, 60])
        sep = rng.choice([" ", "\n", " \t "])
        rows.append((i, sep.join(w)))
    rows += [rows[3], rows[5], (70, rows[7][1]), (71, rows[7][1] + " end"), (80, None), (81, ""), (None, rows[9][1])]
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_substring_dedup_matches_brute_force(spark, seed):
    rows = corpus(seed)
    df = spark.createDataFrame([(a, b, "clash") for a, b in rows], SCHEMA).repartition(5)
    got = substring_dedup(df)
    assert got.columns == ["doc_id", "n_words", "n_removed", "kept_sha256"]
    assert sorted((tuple(r) for r in got.collect()), key=str) == removed(rows, 50)


def test_substring_dedup_with_small_blocks_and_texts(spark, monkeypatch):
    rows = corpus(9)
    df = spark.createDataFrame([(a, b, None) for a, b in rows], SCHEMA)
    got = {(r.doc_id, r.n_words): r.kept_text for r in substring_dedup(df, window=30, keep_text=True).collect()}
    want = {(i, n): sha for i, n, _, sha in removed(rows, 30)}
    assert {k: hashlib.sha256(v.encode()).hexdigest() for k, v in got.items()} == want
    assert substring_dedup(df.where("false")).count() == 0


def test_equal_windows_are_cut_alike():
    rng = np.random.default_rng(5)
    for _ in range(40):
        shared = rng.integers(0, 30, rng.integers(50, 120)).astype(np.uint64)
        cores = []
        for _ in range(2):
            a, b = (rng.integers(0, 30, rng.integers(0, 60)).astype(np.uint64) for _ in range(2))
            h = substring.mixed(np.concatenate([a, shared, b]))
            core, _, s, e = substring.records(h, 50)
            owner = {int(c): int(k) for k, x, y in zip(core, s, e) for c in range(x, y)}
            # names by the centre's place within the shared words
            cores.append([owner[len(a) + c] for c in range(25, len(shared) - 24)])
        assert cores[0] == cores[1]


def jaccard_expected(rows, percent=80):
    sets, by, parent = {}, defaultdict(list), {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets[i] = frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()
        parent[i] = i

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    names = sorted(sets)
    for x in names:
        for y in names:
            if x < y and sets[x] and sets[y]:
                both = len(sets[x] & sets[y])
                if 100 * both >= percent * (len(sets[x]) + len(sets[y]) - both):
                    a, b = find(x), find(y)
                    parent[max(a, b)] = min(a, b)
    return sorted((i, len(sets[i]), find(i)) for i in names)


def near_corpus(seed):
    rng = random.Random(seed)
    rows = []
    for g in range(12):
        base = word_list(rng, rng.choice([3, 6, 12, 40, 150]), 5000)
        for _ in range(rng.choice([1, 2, 3, 8, 40])):
            w = list(base)
            for _ in range(rng.randint(0, 1 + len(w) // 40)):
                w[rng.randrange(len(w))] = f"x{rng.randint(0, 99999)}"
            rows.append((len(rows), rng.choice([" ", "\n"]).join(w if rng.random() < 0.8 else [x.upper() for x in w])))
    line = "one very common line that stands in many documents"
    for _ in range(60):
        rows.append((len(rows), line + " " + " ".join(word_list(rng, rng.choice([1, 2, 3, 60]), 9000))))
    return rows + [(len(rows), None), (len(rows) + 1, ""), (len(rows) + 2, " \n ")]


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_jaccard_join_matches_brute_force(spark, seed, monkeypatch):
    rows = near_corpus(seed)
    df = spark.createDataFrame([(a, b, "clash") for a, b in rows], SCHEMA).repartition(3)
    want = jaccard_expected(rows)
    assert sorted(tuple(r) for r in jaccard_join(df).collect()) == want
    monkeypatch.setattr(jaccard, "PART_SETS", 2 + seed * 10)  # larger parts are joined, not settled in a task
    assert sorted(tuple(r) for r in jaccard_join(df).collect()) == want


def test_large_groups_settled_in_rounds(spark, monkeypatch):
    """Small limits, so that groups are large, give few pairs a round and are looked at again."""
    monkeypatch.setattr(jaccard, "SMALL_GROUP", 3)
    monkeypatch.setattr(jaccard, "TILE", 8)
    rng = random.Random(4)
    base = word_list(rng, 60, 5000)
    rows = []
    for i in range(40):
        w = list(base)
        for at in rng.sample(range(60), rng.randint(0, 4)):
            w[at] = f"y{rng.randint(0, 9999)}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for most in (1_000, 5):
        monkeypatch.setattr(jaccard, "PART_SETS", most)
        assert sorted(tuple(r) for r in jaccard_join(df).collect()) == jaccard_expected(rows)


def test_jaccard_join_of_odd_rows(spark):
    same = "a b c d e f g h"
    rows = [(5, same), (5, same), (3, same.upper()), (None, same), (None, "alone it is"), (9, "x"), (8, "x")]
    got = sorted((tuple(r) for r in jaccard_join(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert got == sorted([(5, 4, 3), (5, 4, 3), (3, 4, 3), (None, 4, 3), (None, 1, None), (9, 1, 8), (8, 1, 8)], key=str)
    assert jaccard_join(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_tiles_of_large_groups_lose_no_link():
    rng = np.random.default_rng(3)
    base = rng.integers(1, 1 << 60, 100).astype(np.uint64)
    sets = []
    for _ in range(40):
        s = base.copy()
        at = rng.choice(100, rng.integers(0, 25), replace=False)
        s[at] = rng.integers(1, 1 << 60, len(at))
        sets.append(np.unique(s))
    middle = np.unique(base)
    others = [np.setxor1d(s, middle) for s in sets]
    n = np.array([len(s) for s in sets])
    both = np.arange(80) % 40  # the first rows against the same ones
    x, y = jaccard._tile_links(both, n[both], [others[i] for i in both], 40, 80)
    got = jaccard.roots(both[x], both[y], 40)
    links = [
        (i, j)
        for i in range(40)
        for j in range(i + 1, 40)
        if 100 * (c := len(np.intersect1d(sets[i], sets[j]))) >= 80 * (len(sets[i]) + len(sets[j]) - c)
    ]
    want = jaccard.roots(np.array([a for a, _ in links]), np.array([b for _, b in links]), 40)
    assert 1 < len(set(want.tolist())) < 40
    assert got.tolist() == want.tolist()


def test_components(spark):
    rng = random.Random(8)
    links = [(rng.randint(0, 400), rng.randint(0, 400)) for _ in range(260)] + [(i, i + 1) for i in range(1000, 1040)]
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    want = {x: find(x) for a, b in links for x in (a, b) if a != b}
    for per_task in (1_000_000, 100):
        got = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long"), per_task=per_task).collect()}
        assert got == want


def test_jaccard_join_of_long_texts_and_clashing_columns(spark):
    rng = random.Random(11)
    long = word_list(rng, 60_000, 40_000)
    near = list(long)
    for at in rng.sample(range(60_000), 300):
        near[at] = f"z{at}"
    rows = [(1, " ".join(long)), (2, " ".join(near)), (3, " ".join(word_list(rng, 60_000, 40_000))), (4, "x"), (5, "w " * 30_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumns(
        {c: F.lit(7) for c in ("node", "n", "component_id", "n_shingles", "bucket", "_id", "_text", "component", "kind", "large")}
    )
    got = {r.doc_id: r for r in jaccard_join(df).collect()}
    assert {i: r.component_id for i, r in got.items()} == {1: 1, 2: 1, 3: 3, 4: 4, 5: 5}
    assert got[5].n_shingles == 1 and got[1].n_shingles == len({tuple(long[i : i + 5]) for i in range(len(long) - 4)})


def test_rows_that_share_an_id_are_compared_each(spark):
    a, b = (" ".join(f"{c}{i}" for i in range(60)) for c in "ab")
    rows = [(1, a), (1, b), (2, a + " more"), (3, b + " more"), (3, b + " more")]
    got = sorted(tuple(r) for r in jaccard_join(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == [(1, 56, 1), (1, 56, 1), (2, 57, 1), (3, 57, 1), (3, 57, 1)]
