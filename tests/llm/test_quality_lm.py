import math
import random
import sys
import zlib
from collections import Counter
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from vecpath.llm import lm, quality


def test_additive_model_learns_an_interaction():
    rng = np.random.default_rng(1)
    x = rng.uniform(size=(4000, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    model = quality.fit(x, y)
    assert (0, 1) in model.pairs
    assert ((model.score(x) > 0.5) == (y > 0.5)).mean() > 0.95


def test_scores_are_sums_of_table_entries():
    """One row at a time, by comparing with the cut points, against the vectorised look-up."""
    rng = np.random.default_rng(3)
    x = np.round(rng.normal(size=(500, 4)), 1)
    model = quality.fit(x, (x[:, 0] * x[:, 1] + x[:, 2] > 0).astype(float), rounds=20, pair_rounds=10, pairs=3)
    assert len(model.pairs) == 3 and any(t.any() for t in model.pair_tables)
    probe = np.round(rng.normal(size=(200, 4)) * 2, 1)
    for row, got in zip(probe, model.score(probe)):
        z = model.base
        for f, v in enumerate(row):
            z += model.tables[f][sum(v >= c for c in model.cuts[f])]
        for (a, b), table in zip(model.pairs, model.pair_tables):
            z += table[sum(row[a] >= c for c in model.pair_cuts[a]), sum(row[b] >= c for c in model.pair_cuts[b])]
        assert abs(got - 1 / (1 + math.exp(-z))) < 1e-12


def test_gathered_rows_are_bounded_and_repeated_ids_count(spark):
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, quality int")
    docs = spark.createDataFrame([(i % 40, "good prose, told well. " * 9 if i % 2 else "$$$ BUY !!! NOW ||| ") for i in range(400)], "doc_id long, text string")
    model = quality.train(docs, labels, max_labelled=30)
    out = quality.score(docs.distinct(), model).collect()
    assert all((r.predicted == 1) == (r.doc_id % 2 == 1) for r in out)
    assert (quality.train(docs.where("false"), labels).score(np.zeros((1, len(quality.FEATURES)))) > 0.99).all()


def test_model_without_labels_rejects_nothing():
    model = quality.fit(np.zeros((0, len(quality.FEATURES))), np.zeros(0))
    assert (model.score(np.zeros((3, len(quality.FEATURES)))) > 0.99).all()
    one = quality.fit(np.zeros((5, 2)), np.ones(5))
    assert (one.score(np.zeros((1, 2))) > 0.5).all()


def test_held_out_accuracy(spark, sf):
    docs = spark.read.parquet(f"{sf}/../sf0.1/documents.parquet")
    labels = spark.read.parquet(f"{sf}/../sf0.1/labels.parquet")
    model = quality.train(docs, labels.where(quality.fold("doc_id", 4) != 2))
    held = quality.score(docs.where(quality.fold("doc_id", 4) == 2), model).join(labels, "doc_id")
    assert held.agg(F.avg((F.col("predicted") == F.col("quality")).cast("int"))).first()[0] > 0.97


def test_score_of_odd_rows(spark):
    rows = [(1, None, "a"), (2, "", "b"), (3, "word " * 100000, None), (None, "\0\x0b é", "c")]
    df = spark.createDataFrame(rows, "doc_id long, text string, score string")
    model = quality.fit(np.random.default_rng(0).uniform(size=(50, len(quality.FEATURES))), np.arange(50) % 2.0)
    out = quality.score(df, model).collect()
    assert len(out) == 4 and all(0 <= r.score <= 1 for r in out)
    assert quality.score(df.where("false"), model).count() == 0


def small_model(states=2, symbols=4):
    rng = np.random.default_rng(2)
    emit = rng.dirichlet(np.ones(symbols), states).T
    return lm.Model(rng.dirichlet(np.ones(states)), rng.dirichlet(np.ones(states), states), emit)


def paths_probability(model, seq):
    """Sum over all state paths."""
    a = model.start * model.emit[seq[0]]
    total = [(p, s) for s, p in enumerate(a)]
    for x in seq[1:]:
        total = [(p * model.move[s, t] * model.emit[x, t], t) for p, s in total for t in range(len(model.start))]
    return sum(p for p, _ in total)


def test_forward_recursion_is_the_sum_over_paths():
    model = small_model()
    seqs = [np.array(s) for s in ([0], [1, 2], [3, 0, 1, 2], [2, 2, 2, 1, 0, 3, 3])]
    got = lm.log_likelihood(model, seqs)
    assert np.allclose(got, [math.log(paths_probability(model, s)) for s in seqs])


def test_expected_counts_add_up_and_training_never_lowers_the_likelihood():
    rng = np.random.default_rng(4)
    seqs = [rng.integers(0, 4, n) for n in (1, 5, 9, 40, 41)]
    model = small_model()
    before = -math.inf
    for _ in range(5):
        starts, moves, emits, ll = lm.expected_counts(model, seqs)
        assert np.isclose(starts.sum(), len(seqs)) and np.isclose(emits.sum(), sum(map(len, seqs)))
        assert np.isclose(moves.sum(), sum(len(s) - 1 for s in seqs))
        assert ll >= before - 1e-9
        before = ll
        model = lm.Model(starts / starts.sum(), moves / moves.sum(1, keepdims=True), emits / emits.sum(0))


def test_scores_against_brute_force(spark):
    rng = random.Random(6)
    rows = [(i, " ".join(rng.choices(["The", "cat", "sat", "é", f"w{i}"], k=rng.randint(0, 30)))) for i in range(60)]
    rows += [(60, None), (61, ""), (61, ""), (None, "cat new"), (62, "the " * 3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 7 == 2
    counts, ends = Counter(), 0
    for i, t in rows:
        if i is not None and not held(i):
            counts.update((t or "").encode().lower().split())
            ends += 1
    n, v = sum(counts.values()) + ends, len(counts) + 1
    out = lm.score(df, quality.fold("doc_id", 7) != 2, states=3, head=20, symbols=5).collect()
    assert len(out) == len(rows)
    texts = dict(rows)
    for r in out:
        w = (texts[r.doc_id] or "").encode().lower().split()
        base = sum(math.log10((counts[x] + 1) / (n + v + 1)) for x in w) + math.log10((ends + 1) / (n + v + 1))
        assert abs(base - r.base_score) < 1e-6 * max(1, abs(base))
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(w) + 1, sum(counts[x] > 0 for x in w) + 1, n)
        assert math.isfinite(r.score) and r.score < 0


def test_words_looked_up_by_a_join_score_like_those_tasks_hold(spark):
    """Words outside the head are joined; with the same symbols the scores are the same."""
    rng = random.Random(8)
    rows = [(i, " ".join(f"w{int(3400 * rng.random() ** 1.2)}" for _ in range(rng.randint(0, 300)))) for i in range(300)]
    df = spark.createDataFrame(rows + [(300, None), (301, "new w1 w1 newer")], "doc_id long, text string")
    got = [
        {r.doc_id: r for r in lm.score(df.withColumns({"score": F.lit(1), "_row": F.lit(1)}), F.col("doc_id") % 7 != 2, states=3, head=h, symbols=900).collect()}
        for h in (200_000, 1_500)
    ]
    assert got[1].keys() == got[0].keys() == set(range(302))
    for i, r in got[0].items():
        other = got[1][i]
        assert abs(r.score - other.score) < 1e-6 * abs(r.score) and abs(r.base_score - other.base_score) < 1e-6 * abs(r.base_score)
        assert (r.n_tokens, r.n_known) == (other.n_tokens, other.n_known)


def test_long_texts_are_counted_in_stretches(monkeypatch):
    rng = np.random.default_rng(4)
    seqs = [rng.integers(0, 4, n) for n in (1, 700, 40, 41, 3)]
    whole = lm.expected_counts(small_model(), seqs)
    for stretch, block in ((7, 200_000), (100, 30), (1, 1)):
        monkeypatch.setattr(lm, "STRETCH", stretch)
        monkeypatch.setattr(lm, "BLOCK_TOKENS", block)
        for a, b in zip(whole, lm.expected_counts(small_model(), seqs)):
            assert np.allclose(a, b)


def test_no_training_rows(spark):
    df = spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    r = lm.score(df, F.lit(False)).first()
    assert (r.n_known, r.train_tokens) == (0, 0) and math.isfinite(r.score)
    assert lm.score(df.where("false"), F.lit(True)).count() == 0


def test_model_beats_the_base_on_held_out_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = lm.score(docs, quality.fold("doc_id", 7) != 2).where(quality.fold("doc_id", 7) == 2)
    base, score = out.agg(F.sum("base_score"), F.sum("score")).first()
    assert score > base


def test_long_texts_are_stepped_together(monkeypatch):
    lengths = np.array([5_000] * 300 + [40] * 9_000)
    blocks = list(lm._blocks(lengths))
    assert sorted(np.concatenate(blocks).tolist()) == list(range(len(lengths)))
    assert sum(int(lengths[b].max()) for b in blocks) < 12_000  # steps; one block for each 200,000 symbols takes over 40,000
    assert max(int(lengths[b].sum()) for b in blocks) <= lm.BLOCK_MOST
    assert [len(b) for b in lm._blocks(np.array([5_000_000, 3]))] == [1, 1]
    rng = np.random.default_rng(3)
    symbols = [rng.integers(0, 30, n) for n in (700, 650, 9, 1, *[20] * 40)]
    flat = lambda *shape: (lambda x: x / x.sum(-1, keepdims=True))(rng.random(shape))
    model = lm.Model(flat(4), flat(4, 4), flat(4, 30).T.copy())
    whole, likely = lm.expected_counts(model, symbols), lm.log_likelihood(model, symbols)
    for name, n in (("BLOCK_TOKENS", 50), ("BLOCK_ROWS", 2), ("BLOCK_MOST", 1_000), ("STRETCH", 90)):
        monkeypatch.setattr(lm, name, n)
    for x, y in zip(whole, lm.expected_counts(model, symbols)):
        assert np.allclose(x, y)
    assert np.allclose(likely, lm.log_likelihood(model, symbols)) and np.isclose(likely.sum(), whole[3])


def in_tasks(monkeypatch, f, *args):
    """(what the Arrow function of ``f`` gives for a batch, calls it made), without Spark."""
    seen = []

    class Docs:
        schema = {"_id": SimpleNamespace(dataType=SimpleNamespace(simpleString=lambda: "long"))}
        select = groupBy = agg = lambda self, *_: self

        def mapInArrow(self, work, schema):
            seen.append(work)
            return self

    monkeypatch.setattr(lm, "cut", lambda docs: docs)
    monkeypatch.setattr(lm, "F", SimpleNamespace(sum=lambda _: SimpleNamespace(alias=lambda _: None)))
    f(Docs(), *args)

    def run(batch):
        calls = [0]
        before = sys.getprofile()
        sys.setprofile(lambda frame, event, arg: calls.__setitem__(0, calls[0] + event.endswith("call")))
        try:
            got = list(seen[0](iter([batch])))
        finally:
            sys.setprofile(before)
        return [r for b in got for r in b.to_pylist()], calls[0]

    return run


def test_words_are_counted_and_encoded_without_a_call_for_each(monkeypatch):
    rng = random.Random(11)
    odd = [None, "", " ", "A", "\u00c9a\u00c9 a\tB\x0b\x0cb\r\n", "x\x00y \x1f\u00a0 a", "nine", " nine ", "", "\u00df", "ab" * 5_000]
    texts = odd + [" ".join(f"W{int(9_000 * rng.random() ** 2)}" for _ in range(20_000)), *odd[::-1]]
    plain = [(t or "").encode().lower().split() for t in texts]
    counts = Counter(w for ws in plain for w in ws)
    rows, calls = in_tasks(monkeypatch, lm.count_words, "t")(pa.record_batch({"t": pa.array(texts, pa.string())}))
    assert sorted((r["word"], r["n"]) for r in rows) == sorted(counts.items())
    assert calls < 3_000
    head = sorted(counts, key=lambda w: (-counts[w], w))[:4_000]
    total, distinct = np.zeros(lm.CLASSES, np.int64), np.zeros(lm.CLASSES, np.int64)
    for w in counts.keys() - set(head[:900]):
        total[lm.class_of(w)] += counts[w]
        distinct[lm.class_of(w)] += 1
    n = sum(counts.values()) + len(texts)
    v = lm.Vocabulary({w: i for i, w in enumerate(head)}, np.array([counts[w] for w in head]), len(texts), n, len(counts) + 1, total, distinct, 900)
    ids = pa.array(range(len(texts)))
    batch = pa.record_batch({"_row": ids, "_id": ids, "_train": ids.cast(pa.bool_()), "_text": pa.array(texts, pa.string())})
    rows, calls = in_tasks(monkeypatch, lm.encoded, SimpleNamespace(value=v), "_text", "_id")(batch)
    assert calls < 3_000  # one for each word without an emission of its own would be some 13,000
    assert [r["_id"] for r in rows] == ids.to_pylist()
    for r, ws in zip(rows, plain):
        rest = Counter(w for w in ws if w not in v.index)
        assert dict(zip(r["_tail"], r["_times"])) == rest and len(r["_tail"]) == len(rest)
        at = [v.index.get(w, -1) for w in ws]
        symbol = [i if 0 <= i < 900 else 900 + lm.class_of(w) for i, w in zip(at, ws)] + [900 + lm.CLASSES]
        assert np.frombuffer(r["_symbols"], np.uint16).tolist() == symbol
        assert (r["n_tokens"], r["_known"]) == (len(ws) + 1, len(ws) - sum(rest.values()) + 1)
        base = sum(math.log10(counts[w] + 1) for w in ws if w in v.index) + math.log10(len(texts) + 1) - len(symbol) * v.base_denominator()
        share = sum(math.log10(counts[w] + 1) for w, i in zip(ws, at) if i >= 900)
        share -= sum(math.log10(total[s - 900] + distinct[s - 900] + 1) for s in symbol[:-1] if s >= 900)
        assert math.isclose(r["_base"], base, rel_tol=1e-9) and math.isclose(r["_within"], share, rel_tol=1e-9, abs_tol=1e-9)
