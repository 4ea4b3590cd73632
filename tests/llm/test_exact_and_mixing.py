import hashlib
import math
import random

from pyspark.sql import functions as F

from vecpath.llm.bloom import blocks_for, may_hold, present_bits
from vecpath.llm.exact_dedup import exact_dedup
from vecpath.llm.mixing import mix, repeat, source_targets

SCHEMA = "doc_id long, text string, source string, keep_id string"


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def expected(rows):
    groups = {}
    for r in rows:
        groups.setdefault(lower(r[1]), []).append(r[0])
    return groups


def test_exact_dedup_matches_brute_force(spark):
    rng = random.Random(3)
    texts = ["", None, "A", "a", "É", "é", "Straße X", "straße x", "long " * 5000, "LONG " * 5000]
    rows = [(i, rng.choice(texts), "s", "clash") for i in range(300)] + [(1000 + i, f"unique {i}", None, None) for i in range(200)]
    out = exact_dedup(spark.createDataFrame(rows, SCHEMA)).collect()
    groups = expected(rows)
    assert len(out) == len(rows)
    for r in out:
        mine = groups[lower(r.text)]
        assert (r.keep_id, r.group_size, r.kept) == (max(mine), len(mine), r.doc_id == max(mine))
        assert r.text_sha256 == hashlib.sha256(lower(r.text).encode()).hexdigest()


def test_exact_dedup_ties_nulls_and_empty(spark):
    rows = [(5, "x", "a", None), (5, "X", "b", None), (None, "x", "c", None), (None, "only null", "d", None), (None, "only null", "e", None)]
    out = exact_dedup(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sum(r.kept for r in out if lower(r.text) == "x") == 1
    assert sum(r.kept for r in out if r.text == "only null") == 1
    assert exact_dedup(spark.createDataFrame([], SCHEMA)).count() == 0


def test_exact_dedup_without_filter_gives_the_same(spark):
    from vecpath.llm.exact_dedup import digest, mark_copies

    rows = [(i, f"t{i % 40}", None, None) for i in range(2000)]
    df = spark.createDataFrame(rows, SCHEMA).select("doc_id", digest("text").alias("k"))
    one = sorted(map(tuple, mark_copies(df, "k", "doc_id").collect()))
    assert blocks_for(2000, 16) is None
    assert one == sorted(map(tuple, mark_copies(df, "k", "doc_id", max_filter_bytes=16).collect()))


def test_bloom_filter_has_no_false_negatives(spark):
    have = spark.range(0, 3000).select(F.xxhash64("id").alias("h"))
    blocks = blocks_for(3000, 1 << 20)
    maps = present_bits(have, "h", blocks).scalar()
    probe = spark.range(0, 20000).withColumn("hit", may_hold(maps, F.xxhash64("id"), blocks))
    got = probe.groupBy((F.col("id") < 3000).alias("in"), "hit").count().collect()
    counts = {(r["in"], r["hit"]): r["count"] for r in got}
    assert counts.get((True, False), 0) == 0
    assert counts.get((False, True), 0) < 200


def water(sizes, cap=3.0):
    names = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: (1, 2, 3)[i % 3] for i, s in enumerate(names)}
    left, open_, out = float(sum(sizes.values())), set(names), {}
    while open_:
        level = left / sum(weight[s] for s in open_)
        over = [s for s in open_ if level * weight[s] > cap * sizes[s]]
        if not over:
            return out | {s: level * weight[s] for s in open_}
        for s in over:
            out[s] = cap * sizes[s]
            left -= out[s]
            open_.discard(s)
    return out


def test_targets_share_the_total_under_their_caps(spark):
    for seed in range(5):
        rng = random.Random(seed)
        sizes = {s: rng.choice([0, 3, 50, 400, 9000]) for s in [None, "B", "a", "ä", "z", "zz", "c1"]}
        df = spark.createDataFrame([(s, n) for s, n in sizes.items()], "source string, size long")
        got = {r.source: r.target for r in source_targets(df).collect()}
        want = water(sizes)
        assert got.keys() == want.keys()
        assert all(abs(got[s] - want[s]) <= 1e-6 * max(1, want[s]) for s in want)


def test_mix_comes_near_its_targets_and_repeats(spark, sf):
    docs = spark.read.parquet(f"{sf}/../sf0.1/documents.parquet").select("doc_id", "text", "source", F.lit("x").alias("target"))
    one = mix(docs)
    per = one.groupBy("source").agg(F.max("target").alias("t"), F.sum(F.col("copies") * F.col("size")).alias("k"), F.max("copies").alias("c"), F.min("copies").alias("m"), F.max("size").alias("x")).collect()
    assert all(abs(r.k - r.t) <= max(0.01 * r.t, r.x / 2) and 0 <= r.m and r.c <= 3 for r in per)
    rows = lambda df: sorted((r.doc_id, r.copies) for r in df.select("doc_id", "copies").collect())
    assert rows(one) == rows(mix(docs.repartition(7)))
    assert repeat(one).count() == one.agg(F.sum("copies")).first()[0]


def test_mix_of_odd_rows(spark):
    rows = [(1, None, None), (1, None, None), (None, "a b c", "s"), (2, "", "s"), (3, "w " * 50000, "t"), (3, "w " * 50000, "t")]
    out = mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert len(out) == 6
    assert {r.source: r.target for r in out}[None] == 0
    assert mix(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0


def test_copies_cross_whole_numbers(spark):
    """Systematic sampling: any run of the order takes its expected copies but for less than one at either end."""
    rng = random.Random(3)
    rows = [(i, "w " * rng.choice([0, 1, 5, 9, 40, 300]), rng.choice("aaab")) for i in range(900)]
    out = mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    for s in "ab":
        mine = [r for r in out if r.source == s]
        rate = mine[0].target / mine[0].source_size
        assert all(r.copies in (math.floor(rate), math.ceil(rate)) for r in mine)
        assert abs(sum(r.copies for r in mine) - rate * len(mine)) < 1
        for k in range(10):
            some = [r for r in mine if int(math.log2(r.size + 1)) == k]
            assert abs(sum(r.copies for r in some) - rate * len(some)) < 1 + 1e-9 if some else True
