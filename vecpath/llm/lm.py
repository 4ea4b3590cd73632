"""Hidden Markov language model over words."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .blocks import flat, pieces
from .common import cut

HEAD = 200_000  # words whose counts every task holds
SYMBOLS = 50_000  # of these, words with an emission of their own; more of them score held-out texts no better
LEAST = 3  # occurrences of a word with an emission of its own
CLASSES = 512  # classes by ending of all other words
STATES = 10
SEED_DOCS = 2_000
GROUP = 4_000_000  # symbols of the texts that are dealt into blocks together, so that long texts meet their like
BLOCK_TOKENS, BLOCK_ROWS = 200_000, 200  # a block has so many symbols, and more where the texts are fewer
BLOCK_MOST = 2_000_000
STRETCH = 400_000  # symbols whose alphas are held at a time
LOG10 = float(np.log(10.0))


def words_of(offsets: np.ndarray, data: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """(all words, number of the first word of each text and of the end); A-Z lower-cased, cut at ASCII white space."""
    lo, hi = int(offsets[0]), int(offsets[-1])
    body = np.frombuffer(data[lo:hi].tobytes().lower(), np.uint8)
    solid = (body != 32) & ((body < 9) | (body > 13))
    # words do not reach over the end of a text
    edges = (offsets - lo)[(offsets > lo) & (offsets < hi)]
    first, last = solid.copy(), solid.copy()
    first[1:] &= ~solid[:-1]
    last[:-1] &= ~solid[1:]
    first[edges], last[edges - 1] = solid[edges], solid[edges - 1]
    starts = np.flatnonzero(first)
    bounds = np.zeros(len(starts) + 1, np.int64)
    np.cumsum(np.flatnonzero(last) + 1 - starts, out=bounds[1:])
    words = pa.LargeBinaryArray.from_buffers(
        pa.large_binary(), len(starts), [None, pa.py_buffer(bounds), pa.py_buffer(body[solid])]
    )
    return words, np.searchsorted(starts, offsets - lo)


def class_of(word: bytes) -> int:
    return zlib.crc32(word[-2:]) % CLASSES


@cache
def _endings() -> tuple[np.ndarray, np.ndarray]:
    """Classes of all endings of one byte and of two, the last but one being the higher."""
    one, high, low = (np.array([zlib.crc32(bytes(e)) for e in ends], np.int64) for ends in (
        [(x,) for x in range(256)], [(x, 0) for x in range(256)], [(0, x) for x in range(256)],
    ))
    # checksums of the same length are affine in their bits
    return one % CLASSES, (high[:, None] ^ low ^ low[0]).ravel() % CLASSES


def classes_of(words: pa.Array) -> np.ndarray:
    """``class_of`` of words that are not empty, in the form that ``words_of`` gives them."""
    bounds, body = flat(words)
    one, two = _endings()
    last = body[bounds[1:] - 1]
    return np.where(np.diff(bounds) == 1, one[last], two[body[np.maximum(bounds[1:] - 2, 0)].astype(np.int64) << 8 | last])


def class_column(word: Column) -> Column:
    ending = F.when(F.octet_length(word) > 2, F.substring(word, -2, F.lit(2))).otherwise(word)
    return (F.crc32(ending) % CLASSES).cast("int")


@dataclass
class Vocabulary:
    """What all tasks know of the counts; its size is bounded by HEAD.

    Symbols: the first SYMBOLS words by count, then the classes of all other
    words, then the end.  A word of a class has, within it, the probability
    (c + 1) / (N + V + 1) of the class's own counts.
    """

    index: dict[bytes, int]
    counts: np.ndarray
    ends: int
    total: int
    distinct: int
    class_total: np.ndarray
    class_distinct: np.ndarray
    symbols: int

    @property
    def size(self) -> int:
        return self.symbols + CLASSES + 1

    def base_denominator(self) -> float:
        return float(np.log10(self.total + self.distinct + 1))


@dataclass
class Model:
    start: np.ndarray  # K
    move: np.ndarray  # K x K
    emit: np.ndarray  # symbols x K


def count_words(docs: DataFrame, text: str) -> DataFrame:
    """(word binary, n) over all rows; tasks add up their own words first."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[pa.Array, np.ndarray]] = []

        def added() -> tuple[pa.Array, np.ndarray]:
            got = pa.concat_arrays([w for w, _ in held]).dictionary_encode()
            n = np.bincount(np.asarray(got.indices), np.concatenate([n for _, n in held]), len(got.dictionary))
            return got.dictionary, n.astype(np.int64)

        def out() -> pa.RecordBatch:
            words, n = held.pop()
            return pa.RecordBatch.from_arrays([words.cast(pa.binary()), pa.array(n)], ["word", "n"])

        for batch in batches:
            offsets, data = flat(batch.column(0))
            for lo, hi in pieces(offsets):
                found = words_of(offsets[lo : hi + 1], data)[0].value_counts()
                held.append((found.field(0), np.asarray(found.field(1))))
                if sum(len(n) for _, n in held) > 600_000:
                    held[:] = [added()]
                    if len(held[0][1]) > 300_000:
                        yield out()
        if held:
            held[:] = [added()]
            yield out()

    return docs.select(text).mapInArrow(work, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def vocabulary(counts: DataFrame, n_docs: int, head: int = HEAD, symbols: int = SYMBOLS) -> Vocabulary:
    """The head is the words from a least count on, so that no more than ``head`` words are gathered."""
    steps = F.floor(F.log2(F.col("n")) * 64).cast("int")
    sizes = sorted(((r[0], r[1]) for r in counts.groupBy(steps.alias("b")).count().collect()), reverse=True)
    least, room = 1 << 30, head
    for b, k in sizes:
        room -= k
        if room < 0:
            break
        least = b
    got = counts.where(steps >= least).select("word", "n").toArrow()
    words, n = got.column("word").to_pylist(), np.asarray(got.column("n"), np.int64)
    order = sorted(range(len(words)), key=lambda i: (-n[i], words[i]))
    index = {words[i]: k for k, i in enumerate(order)}
    known = n[order]
    by_class = counts.groupBy(class_column(F.col("word")).alias("c")).agg(
        F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")
    ).collect()
    total, distinct = np.zeros(CLASSES, np.int64), np.zeros(CLASSES, np.int64)
    for r in by_class:
        total[r["c"]], distinct[r["c"]] = r["n"], r["v"]
    # a symbol has two bytes; rare words say too little of the states to be one
    symbols = min(symbols, int((known >= LEAST).sum()), (1 << 16) - CLASSES - 1)
    everything, v = int(total.sum()), int(distinct.sum())
    for i in order[:symbols]:
        c = class_of(words[i])
        total[c] -= n[i]
        distinct[c] -= 1
    return Vocabulary(
        index, known, n_docs, everything + n_docs, v + (n_docs > 0), total, distinct, symbols
    )


def lookup(vocab: Vocabulary, known: pa.Array, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(symbol of each word, its index or -1); ``known``: the words of the index in their order."""
    at = np.asarray(pc.index_in(words, value_set=known).fill_null(-1))
    own = (at >= 0) & (at < vocab.symbols)
    return np.where(own, at, vocab.symbols + classes_of(words)), at


def _blocks(lengths: np.ndarray) -> Iterator[np.ndarray]:
    """Sequence numbers in blocks of similar length, longest first.

    Steps over few sequences cost as much as over many: a block of long ones
    has more symbols, up to ``BLOCK_MOST``, before it has fewer rows.
    """
    order = np.argsort(-lengths, kind="stable")
    ends = np.cumsum(lengths[order])
    a = 0
    while a < len(order):
        before = ends[a - 1] if a else 0
        few, most = (int(np.searchsorted(ends, before + n, "right")) for n in (BLOCK_TOKENS, BLOCK_MOST))
        b = max(a + 1, few, min(a + BLOCK_ROWS, most))
        yield order[a:b]
        a = b


def _steps(symbols: list[np.ndarray], block: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The block's symbols by time: (symbols, first position of each step, sequences in each step)."""
    lengths = np.array([len(symbols[i]) for i in block])
    active = len(block) - np.searchsorted(lengths[::-1], np.arange(lengths[0]), "right")
    first = np.concatenate([[0], np.cumsum(active)])
    out = np.empty(first[-1], np.int64)
    for r, i in enumerate(block):
        out[first[: len(symbols[i])] + r] = symbols[i]
    return out, first, active


def log_likelihood(model: Model, symbols: list[np.ndarray]) -> np.ndarray:
    """Natural log probability of each sequence by the scaled forward recursion."""
    out = np.zeros(len(symbols))
    lengths, one = np.array([len(s) for s in symbols]), np.ones(len(model.start))
    for block in _blocks(lengths):
        sym, first, active = _steps(symbols, block)
        ll = np.zeros(len(block))
        alpha = None
        for t, n in enumerate(active):
            e = model.emit[sym[first[t] : first[t] + n]]
            alpha = e * model.start if t == 0 else (alpha[:n] @ model.move) * e
            scale = alpha @ one
            alpha /= scale[:, None]
            ll[:n] += np.log(scale)
        out[block] = ll
    return out


def _forward(model: Model, sym: np.ndarray, first: np.ndarray, active: np.ndarray, a: int, b: int, alpha: np.ndarray | None):
    """(emissions, scaled alphas, scales) of the steps a to b - 1, after the alphas of step a - 1."""
    lo, one = int(first[a]), np.ones(len(model.start))
    e = model.emit.take(sym[lo : first[b]], axis=0)
    alphas, scales = np.empty_like(e), np.empty(len(e))
    for t in range(a, b):
        n = int(active[t])
        at = slice(first[t] - lo, first[t] - lo + n)
        alpha = e[at] * model.start if t == 0 else (alpha[:n] @ model.move) * e[at]
        scale = alpha @ one
        alpha /= scale[:, None]
        alphas[at], scales[at] = alpha, scale
    return e, alphas, scales


def expected_counts(model: Model, symbols: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Baum-Welch counts of (starts, moves, emissions) and the log likelihood."""
    k = len(model.start)
    starts, moves = np.zeros(k), np.zeros((k, k))
    emits, total = np.zeros_like(model.emit), 0.0
    lengths = np.array([len(s) for s in symbols])
    back = np.ascontiguousarray(model.move.T)
    for block in _blocks(lengths):
        sym, first, active = _steps(symbols, block)
        # stretches of steps with a bounded number of symbols; their alphas are computed again on the way back
        cuts = [0]
        while cuts[-1] < len(active):
            cuts.append(max(cuts[-1] + 1, int(np.searchsorted(first, first[cuts[-1]] + STRETCH, "right")) - 1))
        cuts[-1] = len(active)
        before, held = [None], None
        for a, b in zip(cuts, cuts[1:]):
            held = _forward(model, sym, first, active, a, b, before[-1])
            n = int(active[b - 1])
            before.append(held[1][len(held[1]) - n :].copy())
            total += float(np.log(held[2]).sum())
        w = None  # of the step after the one at hand
        for i in range(len(cuts) - 2, -1, -1):
            a, b = cuts[i], cuts[i + 1]
            e, alphas, scales = held if i == len(cuts) - 2 else _forward(model, sym, first, active, a, b, before[i])
            lo = int(first[a])
            for t in range(b - 1, a - 1, -1):
                n = int(active[t])
                at = slice(first[t] - lo, first[t] - lo + n)
                if w is None:
                    ahead = np.ones((n, k))
                else:
                    moves += alphas[at][: len(w)].T @ w
                    ahead = w @ back
                    if len(w) < n:  # the others end here
                        ahead = np.concatenate([ahead, np.ones((n - len(w), k))])
                w = ahead * e[at]
                w /= scales[at, None]
                alphas[at] *= ahead  # now the posterior of the states
            if a == 0:
                starts += alphas[: int(active[0])].sum(0)
            for x in range(k):
                emits[:, x] += np.bincount(sym[lo : first[b]], alphas[:, x], len(emits))
    return starts, moves * model.move, emits, total


def initial(vocab: Vocabulary, seeds: list[np.ndarray], states: int, seed: int = 7) -> Model:
    """First model: a mixture fitted to a bounded sample of documents parts their words among the states."""
    rng = np.random.default_rng(seed)
    size = vocab.size
    prior = np.ones(size)
    prior[: vocab.symbols] += vocab.counts[: vocab.symbols]
    prior[vocab.symbols : -1] += vocab.class_total
    prior[-1] += vocab.ends
    prior /= prior.sum()
    few = min(3_000, vocab.symbols)  # words that tell documents apart
    bags = np.zeros((len(seeds), few + CLASSES), np.float32)
    for r, s in enumerate(seeds):
        s = s[:-1]
        cols = np.where(s < few, s, np.where(s >= vocab.symbols, s - vocab.symbols + few, -1))
        np.add.at(bags[r], cols[cols >= 0], 1)
    share = rng.dirichlet(np.ones(states) * 0.3, len(seeds))
    mean = bags.sum(0) + 0.1
    mean /= mean.sum()
    for _ in range(25 if len(seeds) else 0):
        mass = share.T @ bags + 20 * mean
        logs = np.log(mass / mass.sum(1, keepdims=True))
        z = bags @ logs.T + np.log(share.mean(0) + 1e-3)
        z -= z.max(1, keepdims=True)
        share = np.exp(z)
        share /= share.sum(1, keepdims=True)
    emit = np.tile(prior[:, None] * 2e4, (1, states))
    for r, s in enumerate(seeds):
        np.add.at(emit, s, share[r])
    move = np.full((states, states), 0.02 / states) + 0.98 * np.eye(states)
    start = share.mean(0) + 0.01 if len(seeds) else np.ones(states)
    return Model(start / start.sum(), move, emit / emit.sum(0))


def encode(v: Vocabulary, known: pa.Array, offsets: np.ndarray, data: np.ndarray) -> list[pa.Array]:
    """The last seven columns of ``encoded``, of the texts between ``offsets``, all at once."""
    words, first = words_of(offsets, data)
    symbol, at = lookup(v, known, words)
    n, lengths = len(offsets) - 1, np.diff(first)
    text = np.repeat(np.arange(n), lengths)
    log_count = np.append(np.log10(v.counts + 1.0), 0.0)  # of index -1: nothing
    within = np.log10(v.class_total + v.class_distinct + 1.0)
    base = np.bincount(text, log_count[at], n) + np.log10(v.ends + 1.0) - (lengths + 1) * v.base_denominator()
    other = np.flatnonzero(symbol >= v.symbols)
    share = log_count[at[other]] - within[symbol[other] - v.symbols]
    # words without a count at hand, once for each text
    rest = np.flatnonzero(at < 0)
    once = words.take(pa.array(rest)).dictionary_encode()
    size = len(once.dictionary)
    pair, times = np.unique(text[rest] * size + np.asarray(once.indices), return_counts=True)
    ends = pa.array(np.searchsorted(pair, np.arange(n + 1) * size).astype(np.int32))
    tail = once.dictionary.take(pa.array(pair % max(size, 1))).cast(pa.binary())
    # each text's symbols and its end
    symbols = np.full(len(words) + n, v.symbols + CLASSES, np.uint16)
    symbols[np.arange(len(words)) + text] = symbol
    bounds = 2 * (first + np.arange(n + 1))
    packed = pa.LargeBinaryArray.from_buffers(pa.large_binary(), n, [None, pa.py_buffer(bounds), pa.py_buffer(symbols)])
    return [
        pa.array(lengths + 1), pa.array(np.bincount(text[at >= 0], minlength=n) + (v.ends > 0)), pa.array(base),
        pa.array(np.bincount(text[other], share, n)), pa.ListArray.from_arrays(ends, tail),
        pa.ListArray.from_arrays(ends, pa.array(times)), packed.cast(pa.binary()),
    ]


def encoded(docs: DataFrame, vocab, text: str, doc_id: str) -> DataFrame:
    """What the model and the unigram base need of every row, in one pass over the texts.

    (_row, _id, _train, n_tokens, _known, _base, _within, _tail, _times, _symbols):
    symbols of two bytes each; _within is the part of the score that words have
    within their classes; _tail the words without a count at hand, once each.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v: Vocabulary = vocab.value
        words = pa.array(list(v.index), pa.large_binary())
        for batch in batches:
            offsets, data = flat(batch.column("_text"))
            for lo, hi in pieces(offsets):
                got = encode(v, words, offsets[lo : hi + 1], data)
                yield pa.RecordBatch.from_arrays(
                    [*(batch.column(c).slice(lo, hi - lo) for c in ("_row", "_id", "_train")), *got],
                    ["_row", "_id", "_train", "n_tokens", "_known", "_base", "_within", "_tail", "_times", "_symbols"],
                )

    kind = docs.schema["_id"].dataType.simpleString()
    return cut(
        docs.mapInArrow(
            work,
            f"_row long, _id {kind}, _train boolean, n_tokens long, _known long, _base double, _within double, "
            "_tail array<binary>, _times array<long>, _symbols binary",
        )
    )


def _symbols(column: pa.Array) -> Iterator[list[np.ndarray]]:
    """Symbol sequences in groups of bounded size."""
    group, size = [], 0
    for x in column:
        s = np.frombuffer(x.as_py(), np.uint16).astype(np.int64)
        group.append(s)
        size += len(s)
        if size > GROUP:
            yield group
            group, size = [], 0
    if group:
        yield group


def train(
    rows: DataFrame, vocab: Vocabulary, states: int = STATES, iterations: int = 3, seed_docs: int = SEED_DOCS
) -> Model:
    """Baum-Welch over the symbols of all training rows.

    Only the starting point comes from a bounded sample (``seed_docs`` rows
    with the smallest hash of their id).  Every iteration reads all rows;
    tasks emit their expected counts by symbol and Spark adds them up.
    """
    spark = rows.sparkSession
    taught = rows.where("_train").select("_row", "_id", "_symbols")
    # the rows are chosen by their ids alone; then their symbols are fetched
    chosen = taught.select("_row", F.xxhash64("_id").alias("_h"), "_id").orderBy("_h", "_id", "_row").limit(seed_docs).select("_row")
    sample = taught.join(F.broadcast(chosen), "_row", "left_semi").select("_symbols").toArrow()
    seeds = [np.frombuffer(x.as_py(), np.uint16).astype(np.int64) for x in sample.column(0)]
    seeds.sort(key=lambda s: (len(s), s.tobytes()))
    model = initial(vocab, seeds, states)
    names = [f"s{i}" for i in range(states)]
    schema = "symbol long, " + ", ".join(f"{n} double" for n in names)
    prior, smooth = model.emit.mean(1), 0.5 * vocab.symbols + 50
    for _ in range(iterations):
        now = spark.sparkContext.broadcast(model)

        def work(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
            m = now.value
            starts, moves, emits = np.zeros(states), np.zeros((states, states)), np.zeros_like(m.emit)
            any_rows = False
            for batch in batches:
                for group in _symbols(batch.column(0)):
                    a, b, c, _ = expected_counts(m, group)
                    starts, moves, emits, any_rows = starts + a, moves + b, emits + c, True
            if any_rows:
                rows = np.flatnonzero(emits.any(1))
                symbol = np.concatenate([rows, -2 - np.arange(states), [-1]])
                values = np.concatenate([emits[rows], moves, starts[None]])
                yield pa.RecordBatch.from_arrays([pa.array(symbol), *(pa.array(values[:, i]) for i in range(states))], ["symbol", *names])

        summed = taught.select("_symbols").mapInArrow(work, schema).groupBy("symbol").agg(*(F.sum(n).alias(n) for n in names))
        # emissions are smoothed towards the prior by as much as there are symbols seen
        emit, move, start = prior[:, None] * smooth + np.zeros(states), np.eye(states) * 0.5 + 0.05, np.full(states, 0.1)
        got = summed.toArrow()  # one row for each symbol: bounded by the vocabulary
        at = np.asarray(got.column(0), np.int64)
        values = np.stack([np.asarray(got.column(1 + i), float) for i in range(states)], 1)
        emit[at[at >= 0]] += values[at >= 0]
        start += values[at == -1].sum(0)
        move[-2 - at[at < -1]] += values[at < -1]
        model = Model(start / start.sum(), move / move.sum(1, keepdims=True), emit / emit.sum(0))
        now.unpersist()
    return model


def score(
    docs: DataFrame, training: Column, text: str = "text", doc_id: str = "doc_id", states: int = STATES,
    iterations: int = 3, head: int = HEAD, symbols: int = SYMBOLS,
) -> DataFrame:
    """(doc_id, n_tokens, n_known, train_tokens, base_score, score) for every row of ``docs``.

    ``training`` says which rows the model learns from.  Tokens are words with
    A-Z lower-cased and one end; a null text has the end alone.  base_score is
    the add-one unigram log10 probability and score the hidden Markov model's.
    The model emits one of ``symbols`` frequent words, the end, or a class of
    all other words by their ending; within a class a word has its add-one
    share of the class, unknown words together one part.  Emissions and moves
    are never zero, so every text has a finite score.  Null ids stay null;
    repeated rows are scored each; with no training rows all words are
    unknown.

    A text is held in full by one task, with two bytes a word; what training
    holds besides is bounded, however long the text.  Columns of ``docs`` other
    than these two are not looked at.  An empty table gives an empty result.

    Counts cover all training rows.  Words outside the ``head`` most frequent
    ones are looked up by a shuffle on the word, each word of a document once.
    """
    spark = docs.sparkSession
    rows = docs.select(
        F.monotonically_increasing_id().alias("_row"), F.col(doc_id).alias("_id"), F.col(text).cast("string").alias("_text"),
        F.coalesce(training, F.lit(False)).alias("_train"),
    )
    taught = rows.where("_train")
    counts = cut(count_words(taught, "_text"))
    vocab = vocabulary(counts, taught.count(), head, symbols)
    rows = encoded(rows, spark.sparkContext.broadcast(vocab), "_text", "_id")
    held = spark.sparkContext.broadcast(train(rows, vocab, states, iterations))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ll = [np.zeros(0)] + [log_likelihood(held.value, group) / LOG10 for group in _symbols(batch.column("_symbols"))]
            yield pa.RecordBatch.from_arrays(
                [batch.column("_row"), pa.array(np.concatenate(ll))], ["_row", "_ll"]
            )

    likely = rows.select("_row", "_symbols").mapInArrow(work, "_row long, _ll double")
    pairs = rows.select("_row", F.explode(F.arrays_zip("_tail", "_times")).alias("x")).select(
        "_row", F.col("x._tail").alias("word"), F.col("x._times").alias("times")
    )
    found = (
        pairs.join(counts, "word")
        .groupBy("_row")
        .agg(F.sum("times").alias("_more"), F.sum(F.col("times") * F.log10(F.col("n") + 1)).alias("_add"))
    )
    more, add = F.coalesce("_more", F.lit(0)), F.coalesce("_add", F.lit(0.0))
    narrow = rows.select("_row", "_id", "n_tokens", "_known", "_base", "_within")
    return narrow.join(likely, "_row").join(found, "_row", "left").select(
        F.col("_id").alias(doc_id),
        "n_tokens",
        (F.col("_known") + more).cast("long").alias("n_known"),
        F.lit(vocab.total).cast("long").alias("train_tokens"),
        (F.col("_base") + add).alias("base_score"),
        (F.col("_ll") + F.col("_within") + add).alias("score"),
    )
