"""Substring de-duplication by recompression."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bloom import blocks_for, may_hold, present_bits
from .common import cut
from .hashes import Spans, mixed, texts

FLUSH = 400_000  # records held by a task
FEW = 4  # documents for one name that a task passes on


def pair_round(name: np.ndarray, start: np.ndarray, length: np.ndarray, number: int, most: int):
    """One round: adjacent pairs of symbols become one symbol.

    A bit of its name puts each symbol left or right; a left symbol and the
    right one after it are joined, if together they have at most ``most``
    words, and named by their two names.  Equal names have equal sides, so
    equal neighbours (runs) never join here.
    """
    side = (mixed(name, 40 + number) >> np.uint64(17)) & np.uint64(1)
    joins = np.zeros(len(name), bool)
    joins[:-1] = (side[:-1] == 0) & (side[1:] == 1) & (length[:-1] + length[1:] <= most)
    first = np.ones(len(name), bool)
    first[1:] = ~joins[:-1]
    at = np.flatnonzero(first)
    pair = joins[at]
    out, size = name[at].copy(), length[at].copy()
    out[pair] = mixed(name[at[pair]] * np.uint64(0x9FB21C651E98DF25) + mixed(name[at[pair] + 1], 60), 50 + number)
    size[pair] += length[at[pair] + 1]
    return out, start[at], size


class Parse:
    """Cuts a text into gaps so that equal windows are cut alike.

    Two rounds of recompression name pairs (at most 2 words) and pairs of
    pairs (at most 4).  High symbols, those of 3 and 4 words, start a gap.
    Such a symbol depends on one word more on either side, so a gap of at most
    ``window // 2 - 5`` words is cut in the same way wherever the window
    around any of its words occurs.  Longer gaps, in which the high symbols
    are too far apart, are cut at pairs of words (which depend on nothing
    else), and what is still too long, such as long runs of one word, word by
    word.  A gap is long in one text only if it is so wherever the window
    occurs, for the symbols that would shorten it lie within the window.
    """

    def __init__(self, h: np.ndarray, window: int):
        half = window // 2
        self.window, self.half = window, half
        one = pair_round(h, np.arange(len(h)), np.ones(len(h), np.int64), 1, 2)
        two = pair_round(*one, 2, 4)
        high, low = two[1][two[2] > 2], one[1][one[2] == 2]
        n = len(h)
        starts = self._refine(np.concatenate([[0], high]), n, half - 5, low)
        starts = self._refine(starts, n, half - 5, np.arange(n))
        self.start = starts
        self.end = np.append(starts[1:], n)

    @staticmethod
    def _refine(starts: np.ndarray, n: int, most: int, finer: np.ndarray) -> np.ndarray:
        """Add the finer starts within gaps longer than ``most``."""
        starts = np.unique(starts)
        starts = starts[starts < n]
        # the text's own ends cut gaps too; windows do not reach them, so they need no more care
        ends = np.append(starts[1:], n)
        gap = np.searchsorted(starts, finer, "right") - 1
        long = ends[gap] - starts[gap] > most
        return np.unique(np.concatenate([starts, finer[long]]))


def records(h: np.ndarray, window: int) -> tuple[np.ndarray, ...]:
    """(core, span, start, end) of each gap with windows centred in it.

    A window is centred on its word number ``window // 2``.  The core of a
    gap is what all windows centred in it have in common, the span what they
    cover together; both are named by a hash of their words.  Equal windows
    have equal gaps around their centres, and so equal cores.
    """
    n, half = len(h), window // 2
    if n < window:
        none = np.zeros(0, np.int64)
        return none.astype(np.uint64), none.astype(np.uint64), none, none
    parse = Parse(h, window)
    # centres of whole windows: half .. n - (window - half)
    s, e = np.maximum(parse.start, half), np.minimum(parse.end, n - (window - half) + 1)
    some = s < e
    # a gap cut short by the end of the text has fewer windows; its core is still that of the gap
    a0, b0 = parse.start[some], parse.end[some]
    s, e = s[some], e[some]
    spans = Spans(h)
    # no longer than the gap allows, and within the text for every gap that has a window
    core = spans.hash(np.maximum(b0 - 1 - half, 0), np.minimum(a0 + window - half, n))
    core = mixed(core ^ (b0 - a0).astype(np.uint64))
    span = spans.hash(s - half, e - 1 + window - half)
    return core, span, s, e


def _first(*keys: np.ndarray) -> np.ndarray:
    """Where, in sorted rows, any of the keys differs from the row before."""
    out = np.ones(len(keys[0]), bool)
    out[1:] = np.any([k[1:] != k[:-1] for k in keys], axis=0)
    return out


def resolve(core, span, doc, force):
    """(covered, open) for records of some documents.

    A record is covered if a smaller document has its span.  The others are
    open if their core occurs with another span, or ``force`` says so.
    """
    order = np.lexsort((doc, span, core))
    core, span, doc, force = core[order], span[order], doc[order], force[order]
    head = _first(core, span)
    group = np.cumsum(head) - 1
    covered = doc > doc[np.flatnonzero(head)][group]
    block = np.cumsum(_first(core)) - 1
    spans = np.bincount(block, head)
    forced = np.bincount(block, force) > 0
    opened = ~covered & ((spans > 1) | forced)[block]
    back = np.empty_like(order)
    back[order] = np.arange(len(order))
    return covered[back], opened[back], spans[block][back].astype(np.int64)


SCHEMA = (
    "kind int, doc_id long, row long, n_words long, sha string, s long, e long, bucket long, "
    "core binary, span binary, place binary, docs binary, kept string"
)
KINDS = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64(), *[pa.binary()] * 4, pa.string()]
NAMES = [c.split()[0] for c in SCHEMA.split(", ")]
DOC, COVER, OPEN, PACKED = range(4)


def _out(n: int, **given) -> pa.RecordBatch:
    cols = []
    for name, kind in zip(NAMES, KINDS):
        v = given.get(name)
        cols.append(pa.nulls(n, kind) if v is None else pa.array(v, kind) if not np.isscalar(v) else pa.array([v] * n, kind))
    return pa.RecordBatch.from_arrays(cols, NAMES)


def _row(h: np.ndarray) -> int:
    """Name of a whole text."""
    n = np.array([len(h)])
    return int(Spans(h).hash(np.zeros(1, np.int64), n).view(np.int64)[0])


def _parsed(docs: DataFrame, window: int, buckets: int, keep_text: bool) -> DataFrame:
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        keys: list[tuple[int, int]] = []
        count = 0

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal held, keys, count
            core, span, s, e = (np.concatenate([x[k] for x in held]) for k in range(4))
            place = np.repeat(np.arange(len(held), dtype=np.int64), [len(x[0]) for x in held])
            key = np.array(keys, np.int64).reshape(-1, 2)
            held, keys, count = [], [], 0
            doc = key[place, 0]
            covered, opened, spans = resolve(core, span, doc, np.zeros(len(core)))
            hot = opened & (spans > FEW)
            # gaps side by side that are covered are one stretch
            at = np.flatnonzero(covered)
            if len(at):
                new = np.ones(len(at), bool)
                new[1:] = (at[1:] != at[:-1] + 1) | (place[at[1:]] != place[at[:-1]]) | (s[at[1:]] != e[at[:-1]])
                a = np.flatnonzero(new)
                last = np.append(a[1:], len(at)) - 1
                k = key[place[at[a]]]
                yield _out(len(a), kind=COVER, doc_id=k[:, 0], row=k[:, 1], s=s[at[a]], e=e[at[last]])
            at = np.flatnonzero(hot)
            if len(at):
                k = key[place[at]]
                yield _out(len(at), kind=OPEN, doc_id=k[:, 0], row=k[:, 1], s=s[at], e=e[at])
                # one record of each hot core tells the other tasks of it
                order = at[np.lexsort((doc[at], core[at]))]
                one = order[_first(core[order])]
            else:
                one = at
            send = np.concatenate([np.flatnonzero(~covered & ~hot), one])
            force = np.zeros(len(send), np.int64)
            force[len(send) - len(one) :] = 1
            bucket = (mixed(core[send], 70) >> np.uint64(8)) % np.uint64(buckets)
            order = np.argsort(bucket, kind="stable")
            send, force, bucket = send[order], force[order], bucket[order].astype(np.int64)
            cuts = np.flatnonzero(np.diff(bucket, prepend=-1))
            rows = ([], [], [], [], [])
            for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(send)]):
                i = send[a:b]
                mine, local = np.unique(place[i], return_inverse=True)
                packed = np.stack([local, s[i], e[i] - s[i] + (force[a:b] << 16)], 1).astype(np.int32)
                for r, v in zip(rows, (int(bucket[a]), core[i].tobytes(), span[i].tobytes(), packed.tobytes(), key[mine].tobytes())):
                    r.append(v)
            if len(rows[0]):
                yield _out(len(rows[0]), kind=PACKED, bucket=rows[0], core=rows[1], span=rows[2], place=rows[3], docs=rows[4])

        for batch in batches:
            ids = batch.column("doc_id").to_pylist()
            rows, n_words, sha, kept = [], [], [], []
            for k, (doc, (h, part)) in enumerate(zip(ids, texts(batch.column("text"), False))):
                row = _row(h)
                rows.append(row)
                n_words.append(len(h))
                joined = b" ".join(part.tobytes().split())
                sha.append(hashlib.sha256(joined).hexdigest())
                kept.append(joined.decode() if keep_text else None)
                if doc is not None and len(h) >= window:
                    found = records(h, window)
                    held.append(found)
                    keys.append((doc, row))
                    count += len(found[0])
                    if count > FLUSH:
                        yield from flush()
                if len(rows) == 2_000 or k == len(ids) - 1:
                    yield _out(len(rows), kind=DOC, doc_id=ids[k + 1 - len(rows) : k + 1], row=rows, n_words=n_words, sha=sha, kept=kept)
                    rows, n_words, sha, kept = [], [], [], []
        if count:
            yield from flush()

    return docs.mapInArrow(work, SCHEMA)


def _reduce(table):
    """Settles the records of a bucket: covered stretches and open gaps."""
    core, span, place, key = [], [], [], []
    base = 0
    for c, x, p, d in zip(*(table.column(n).to_pylist() for n in ("core", "span", "place", "docs"))):
        d = np.frombuffer(d, np.int64).reshape(-1, 2)
        p = np.frombuffer(p, np.int32).reshape(-1, 3).astype(np.int64)
        p[:, 0] += base
        base += len(d)
        core.append(np.frombuffer(c, np.uint64))
        span.append(np.frombuffer(x, np.uint64))
        place.append(p)
        key.append(d)
    core, span, place, key = map(np.concatenate, (core, span, place, key))
    k = key[place[:, 0]]
    force = place[:, 2] >> 16
    s, e = place[:, 1], place[:, 1] + (place[:, 2] & 0xFFFF)
    covered, opened, _ = resolve(core, span, k[:, 0], force)
    some = covered | opened
    kind = np.where(covered[some], COVER, OPEN)
    return pa.table(
        {"kind": pa.array(kind, pa.int32()), "doc_id": k[some, 0], "row": k[some, 1], "s": s[some], "e": e[some]}
    )


def substring_dedup(
    docs: DataFrame, text: str = "text", doc_id: str = "doc_id", window: int = 50, keep_text: bool = False,
    max_filter_bytes: int = 32 << 20,
) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256) of every row; with ``keep_text`` also kept_text.

    Words are runs of characters other than ASCII white space.  A word goes if
    a window of ``window`` words covers it whose words also stand in a
    document with a smaller id.  Windows are judged on the input.  Null texts
    have no words; rows with a null id are neither changed nor looked at;
    repeated rows, which have the same id, do not change each other.

    Every text is parsed by recompression (``Parse``): rounds name tokens and
    pairs by hashes, the same everywhere, so no table of names is needed.
    Each gap between high symbols is one record with the names of its core and
    its span.  Records meet by core, packed in blocks.  A span that a smaller
    document has too is a repeat as a whole.  Where one core occurs with
    different spans, a repeat begins or ends: only there the windows
    themselves are named, and meet by name.  Cores that many documents of one
    task have go to that last step at once, so no task gathers them.
    """
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    total = rows.count()
    parsed = cut(_parsed(rows, window, max(32, total // 500), keep_text))
    settled = cut(
        parsed.where(F.col("kind") == PACKED).select("bucket", "core", "span", "place", "docs")
        .groupBy("bucket").applyInArrow(_reduce, "kind int, doc_id long, row long, s long, e long")
        .unionByName(parsed.where(F.col("kind").isin(COVER, OPEN)).select("kind", "doc_id", "row", "s", "e"))
    )

    def listed(found: DataFrame) -> DataFrame:
        return found.groupBy("doc_id", "row").agg(F.collect_list(F.struct("s", "e")).alias("found"))

    def with_texts(lists: DataFrame) -> DataFrame:
        """(doc_id, row, found, text); only documents that may be wanted are shuffled."""
        lists = cut(lists)
        source = rows.where("doc_id is not null")
        blocks = blocks_for(lists.count(), max_filter_bytes)
        if blocks is not None:
            maps = cut(present_bits(lists.select(F.xxhash64("doc_id").alias("h")), "h", blocks)).scalar()
            source = source.where(may_hold(maps, F.xxhash64("doc_id"), blocks))
        return source.join(lists, "doc_id")

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        half = window // 2
        for batch in batches:
            listed_rows = zip(*(batch.column(c) for c in ("doc_id", "row", "found")))
            for (doc, row, found), (h, _) in zip(listed_rows, texts(batch.column("text"), False)):
                if _row(h) != row.as_py():
                    continue
                pairs = np.unique(np.array([(x["s"], x["e"]) for x in found.as_py()], np.int64), axis=0)
                centre = np.unique(np.concatenate([np.arange(a, b) for a, b in pairs]))
                name = Spans(h).hash(centre - half, centre - half + window).view(np.int64)
                n = len(centre)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(name), pa.array([doc.as_py()] * n, pa.int64()), pa.array([row.as_py()] * n, pa.int64()), pa.array(centre)],
                    ["name", "doc_id", "row", "s"],
                )

    opened = listed(settled.where(F.col("kind") == OPEN).select("doc_id", "row", "s", "e"))
    named = cut(with_texts(opened).mapInArrow(windows, "name long, doc_id long, row long, s long"))
    first = cut(named.groupBy("name").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b")).where("a < b").drop("b"))
    single = named.join(first, "name").where("doc_id > a").select("doc_id", "row", "s", (F.col("s") + 1).alias("e"))
    covers = listed(settled.where(F.col("kind") == COVER).select("doc_id", "row", "s", "e").unionByName(single))

    def removed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        half = window // 2
        for batch in batches:
            out = ([], [], [], [], [])
            listed_rows = zip(*(batch.column(c) for c in ("doc_id", "row", "found")))
            for (doc, row, found), (h, part) in zip(listed_rows, texts(batch.column("text"), False)):
                if _row(h) != row.as_py():
                    continue
                edge = np.zeros(len(h) + 1, np.int64)
                pairs = np.array([(x["s"], x["e"]) for x in found.as_py()], np.int64)
                np.add.at(edge, pairs[:, 0] - half, 1)
                np.add.at(edge, pairs[:, 1] - 1 - half + window, -1)
                gone = np.cumsum(edge[:-1]) > 0
                all_words = part.tobytes().split()
                kept = b" ".join([w for w, g in zip(all_words, gone.tolist()) if not g])
                for o, v in zip(out, (doc.as_py(), row.as_py(), int(gone.sum()), hashlib.sha256(kept).hexdigest(), kept.decode() if keep_text else None)):
                    o.append(v)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays(
                [pa.array(o, t) for o, t in zip(out, kinds)], ["doc_id", "row", "n_removed", "sha2", "kept2"]
            )

    changed = with_texts(covers).mapInArrow(removed, "doc_id long, row long, n_removed long, sha2 string, kept2 string")
    changed = changed.dropDuplicates(["doc_id", "row"])
    base = parsed.where(F.col("kind") == DOC).select("doc_id", "row", "n_words", "sha", "kept")
    out = base.join(changed, ["doc_id", "row"], "left").select(
        F.col("doc_id").alias(doc_id),
        "n_words",
        F.coalesce("n_removed", F.lit(0)).cast("long").alias("n_removed"),
        F.coalesce("sha2", "sha").alias("kept_sha256"),
        F.coalesce("kept2", "kept").alias("kept_text"),
    )
    return out if keep_text else out.drop("kept_text")
