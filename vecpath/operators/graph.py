"""Sharded layered proximity graphs: build, store, and search with pre- and post-filters."""

from __future__ import annotations

import heapq
from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .scan import QueryBlock, best, densify, scan

PACKED = "shard long, n long, rejected long, dim long, ids binary, vecs binary, levels binary, degrees binary, edges binary"
INDEX_METRICS = ("ip", "cosine")
BLOCK_QUERIES, BLOCK_CELLS = 128, 1 << 22  # of walks that take their steps together: queries, and queries x nodes


def unpacked(x: bytes, n: int, dim: int) -> np.ndarray:
    """n packed vectors, of four or eight bytes a component, in double."""
    return np.frombuffer(x, np.float32 if len(x) == 4 * n * dim else float).reshape(n, dim).astype(float)


class Shard:
    """One layered graph over a few hundred thousand vectors at most.

    Similarity is the inner product (cosine on unit vectors).  Every point is
    in layer 0; a point is in layer l with probability m**-l, drawn from a
    hash of its id, so that a build can be repeated exactly.
    """

    def __init__(self, ids: np.ndarray, vecs: np.ndarray, levels: np.ndarray, links: list[list[np.ndarray]]):
        self.ids, self.vecs, self.levels, self.links = ids, vecs, levels, links
        self.top = int(levels.max()) if len(levels) else 0
        self.entry = int(np.argmax(levels)) if len(levels) else -1
        self._wide, self._reach, self._both = {}, {}, None

    @staticmethod
    def draw_levels(ids: np.ndarray, m: int, seed: int) -> np.ndarray:
        x = ids.astype(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15) & ((1 << 64) - 1))
        for shift, mult in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(mult)
        u = ((x ^ (x >> np.uint64(31))) >> np.uint64(11)).astype(float) / (1 << 53)
        return np.minimum((-np.log(np.maximum(u, 1e-300)) / np.log(max(m, 2))).astype(np.int64), 12)

    @classmethod
    def build(cls, ids: np.ndarray, vecs: np.ndarray, m: int, ef: int, seed: int) -> Shard:
        """Points come in by id; each is linked to up to m of the ``ef`` nearest ones before it in each of its layers.

        The nearest ones come from products of blocks of points with all points
        before them.  A list of links is cut back to its room when it has grown
        to twice as many, and at the end.
        """
        order = np.argsort(ids, kind="stable")
        ids, vecs = ids[order], np.ascontiguousarray(vecs[order])
        levels = cls.draw_levels(ids, m, seed)
        links: list[list[list[int]]] = [[[] for _ in range(int(lv) + 1)] for lv in levels]
        graph = cls(ids[:0], vecs, levels[:0], links)
        for layer in range(int(levels.max(initial=0)) + 1):
            member = np.flatnonzero(levels >= layer)
            x, room = vecs[member], 2 * m if layer == 0 else m
            step = max(1, min(1_024, BLOCK_CELLS // max(1, len(member))))
            for at in range(0, len(member), step):
                block = x[at : at + step] @ x[: at + step].T
                for r, i in enumerate(member[at : at + step].tolist()):
                    s = block[r, : at + r]
                    near = np.argpartition(-s, ef - 1)[:ef] if len(s) > ef else np.arange(len(s))
                    links[i][layer] = chosen = graph._spread(s[near], member[near], m)
                    for j in chosen:
                        mine = links[j][layer]
                        mine.append(i)
                        if len(mine) > 2 * room:
                            links[j][layer] = graph._cut(j, mine, room)
            for i in member.tolist():
                if len(links[i][layer]) > room:
                    links[i][layer] = graph._cut(i, links[i][layer], room)
        return cls(ids, vecs, levels, [[np.array(x, np.int32) for x in node] for node in links])

    def _cut(self, i: int, nodes: list[int], m: int) -> list[int]:
        nodes = np.array(nodes)
        return self._spread(self.vecs[nodes] @ self.vecs[i], nodes, m)

    def _spread(self, s: np.ndarray, nodes: np.ndarray, m: int) -> list[int]:
        """Up to m of ``nodes`` with similarities ``s``: near ones first, those nearer to a chosen one than to the point only to fill up."""
        order = np.lexsort((-nodes, -s))
        s, nodes = s[order], nodes[order]
        if len(nodes) <= m:
            return nodes.tolist()
        near, apart = np.full(len(nodes), -np.inf), self.vecs[nodes]
        chosen, free, at = [], np.ones(len(nodes), bool), 0
        while len(chosen) < m:
            ahead = near[at:] < s[at:]
            at += int(ahead.argmax())
            if not ahead.any():
                break
            chosen.append(at)
            free[at] = False
            np.maximum(near, apart @ apart[at], out=near)
            at += 1
            if at == len(nodes):
                break
        return nodes[np.concatenate([np.array(chosen, np.int64), np.flatnonzero(free)])[:m]].tolist()

    def _walk(self, q: np.ndarray, start: list[tuple[float, int]], ef: int, layer: int, allowed: np.ndarray | None = None, counters: dict | None = None):
        """Best-first walk of a layer; every node is walked, only allowed ones are results.

        It ends when the best open node is worse than the worst of ``ef``
        results; with few allowed nodes the results fill late or never, and the
        walk crosses everything it can reach.
        """
        seen = {j for _, j in start}
        open_ = [(-s, j) for s, j in start]
        heapq.heapify(open_)
        results = [(s, -j) for s, j in start if allowed is None or allowed[j]]
        heapq.heapify(results)
        while len(results) > ef:
            heapq.heappop(results)
        if counters is not None:
            counters["filter_probes"] += len(start) * (allowed is not None)
        while open_:
            s, i = heapq.heappop(open_)
            if len(results) >= ef and -s < results[0][0]:
                break
            links = self.links[i]
            fresh = [j for j in (links[layer].tolist() if isinstance(links[layer], np.ndarray) else links[layer]) if j not in seen] if layer < len(links) else []
            if counters is not None:
                counters["hops"] += 1
            if not fresh:
                continue
            seen.update(fresh)
            scores = (self.vecs[fresh] @ q).tolist()
            if counters is not None:
                counters["distance_evals"] += len(fresh)
                counters["filter_probes"] += len(fresh) * (allowed is not None)
            for j, v in zip(fresh, scores):
                if len(results) < ef or v > results[0][0]:
                    heapq.heappush(open_, (-v, j))
                    if allowed is None or allowed[j]:
                        heapq.heappush(results, (v, -j))
                        if len(results) > ef:
                            heapq.heappop(results)
        if counters is not None:
            counters["reached"] = max(counters["reached"], len(seen))
        return sorted(((s, -j) for s, j in results), reverse=True), len(seen)

    def search(self, q: np.ndarray, k: int, ef: int, allowed: np.ndarray | None = None) -> tuple[list[tuple[float, int]], dict]:
        counters = {"hops": 0, "distance_evals": 0, "filter_probes": 0, "reached": 0}
        if self.entry < 0:
            return [], counters
        at = [(float(self.vecs[self.entry] @ q), self.entry)]
        counters["distance_evals"] += 1
        for layer in range(self.top, 0, -1):
            at = self._walk(q, at, 1, layer, None, counters)[0]
        counters["reached"] = 0
        found, _ = self._walk(q, at, max(ef, k), 0, allowed, counters)
        return [(s, int(self.ids[j])) for s, j in found[:k]], counters

    # ---- all queries of a block together

    def neighbours(self, layer: int) -> np.ndarray:
        """(n, width) neighbours of every node in a layer, filled up with -1."""
        if layer in self._wide:
            return self._wide[layer]
        n, deg = len(self.links), np.array([len(x[layer]) if layer < len(x) else 0 for x in self.links])
        out = np.full((n, max(1, int(deg.max(initial=0)))), -1, np.int64)
        rows = np.repeat(np.arange(n), deg)
        cols = np.arange(deg.sum()) - np.repeat(np.cumsum(deg) - deg, deg)
        out[rows, cols] = np.concatenate([np.zeros(0, np.int64), *(x[layer] for x in self.links if layer < len(x))])
        self._wide[layer] = out
        return out

    def _reached(self, starts: np.ndarray) -> dict[int, np.ndarray]:
        """What walks of layer 0 without an end can reach from each start, breadth first."""
        links = self.neighbours(0)

        def ahead(start: int) -> np.ndarray:
            mask, edge = np.zeros(len(links), bool), np.array([start])
            while len(edge):
                mask[edge] = True
                edge = np.unique(links[edge])
                edge = edge[(edge >= 0)]
                edge = edge[~mask[edge]]
            return mask

        if not self._reach:
            mask = ahead(self.entry)
            back, before = np.arange(len(links)) == self.entry, -1  # nodes that reach the entry: of those it reaches, all reach the same
            while back.sum() != before:
                before = back.sum()
                back |= ((links >= 0) & back[links]).any(1)
            self._reach[-1], self._both = mask, mask & back
        for i in np.unique(starts).tolist():
            if i not in self._reach:
                self._reach[i] = self._reach[-1] if self._both[i] else ahead(i)
        return {i: self._reach[i] for i in np.unique(starts).tolist()}

    def _saturated(self, queries: np.ndarray, k: int, starts: np.ndarray, allowed: np.ndarray | None, cost: dict) -> list:
        """The k best for walks whose width no shard fills: they cross all that their links reach, in whatever order."""
        masks, out = self._reached(starts), [[] for _ in range(len(queries))]
        for start, mask in masks.items():
            own, n = np.flatnonzero(starts == start), int(mask.sum())
            for name, more in (("hops", n), ("distance_evals", n - 1), ("filter_probes", n * (allowed is not None))):
                cost[name][own] += more
            cost["reached"][own] = n
            rows = np.flatnonzero(mask if allowed is None else mask & allowed)
            for at in range(0, len(own) if len(rows) and k else 0, step := max(1, BLOCK_CELLS // len(mask))):
                part = own[at : at + step]
                scores = queries[part] @ self.vecs[rows].T
                for q, s in zip(part.tolist(), scores):
                    least = np.partition(s, len(s) - k)[len(s) - k] if len(s) > k else -np.inf
                    j = rows[s >= least - 1e-9 * (1 + abs(least))] if len(s) > k else rows
                    s = np.einsum("ij,j->i", self.vecs[j], queries[q])  # equal vectors have equal scores
                    order = np.lexsort((self.ids[j], -s))[:k]
                    out[q] = list(zip(s[order].tolist(), self.ids[j[order]].tolist()))
        return out

    def _fresh(self, nodes: np.ndarray, links: np.ndarray, act: np.ndarray, seen: np.ndarray, queries: np.ndarray):
        """(query, slot, node, score) of the neighbours of ``nodes`` that their queries have not seen; they have now."""
        found = links[nodes]
        r, slot = np.nonzero((found >= 0) & ~seen[act[:, None], found])
        node, q = found[r, slot], act[r]
        seen[q, node] = True
        return r, slot, node, np.einsum("ij,ij->i", self.vecs[node], queries[q])

    def search_block(self, queries: np.ndarray, k: int, ef: int, allowed: np.ndarray | None = None) -> tuple[list, list[dict]]:
        """``search`` for many queries: their walks take each step together, scored at once."""
        b, n = len(queries), len(self.ids)
        cost = {c: np.zeros(b, np.int64) for c in ("hops", "distance_evals", "filter_probes", "reached")}
        if self.entry < 0:
            return [[] for _ in range(b)], [{c: 0 for c in cost} for _ in range(b)]
        ef, every = min(max(ef, k), n), np.arange(b)
        node, score = np.full(b, self.entry), queries @ self.vecs[self.entry]
        cost["distance_evals"] += 1
        for layer in range(self.top, 0, -1):  # to the nearest node of each upper layer
            links, act, seen = self.neighbours(layer), every, np.zeros((b, n), bool)
            seen[every, node] = True
            while len(act):
                r, slot, found, s = self._fresh(node[act], links, act, seen, queries)
                best = np.full((len(act), links.shape[1]), -np.inf)
                best[r, slot] = s
                to = np.full(best.shape, -1)
                to[r, slot] = found
                cost["hops"][act] += 1
                cost["distance_evals"] += np.bincount(act[r], minlength=b)
                at = best.argmax(1)
                rows = np.flatnonzero(best[np.arange(len(act)), at] > score[act])
                act, at = act[rows], at[rows]
                node[act], score[act] = to[rows, at], best[rows, at]
        if ef == n or (allowed is not None and int(allowed.sum()) < ef):  # results that never fill end no walk
            return self._saturated(queries, k, node, allowed, cost), [{c: int(v[i]) for c, v in cost.items()} for i in range(b)]
        links, seen = self.neighbours(0), np.zeros((b, n), bool)
        open_, kept, ids = np.full((b, n), -np.inf), np.full((b, ef), -np.inf), np.full((b, ef), -1)
        seen[every, node] = True
        open_[every, node] = score
        first = every if allowed is None else np.flatnonzero(allowed[node])
        kept[first, 0], ids[first, 0] = score[first], node[first]
        worst = kept.min(1)
        cost["filter_probes"] += allowed is not None
        act = every
        while len(act):
            at = open_[act].argmax(1) if len(act) < b else open_.argmax(1)
            best = open_[act, at]
            go = (best > -np.inf) & (best >= worst[act])
            act, at = act[go], at[go]
            open_[act, at] = -np.inf
            cost["hops"][act] += 1
            r, slot, found, s = self._fresh(at, links, act, seen, queries)
            q = act[r]
            evals = np.bincount(q, minlength=b)
            cost["distance_evals"] += evals
            cost["filter_probes"] += evals * (allowed is not None)
            near = s > worst[q]
            open_[q[near], found[near]] = s[near]
            if allowed is not None:
                near &= allowed[found]
            if not near.any():
                continue
            more, names = np.full((len(act), links.shape[1]), -np.inf), np.full((len(act), links.shape[1]), -1)
            more[r[near], slot[near]], names[r[near], slot[near]] = s[near], found[near]
            rows = np.unique(r[near])
            both = np.concatenate([kept[act[rows]], more[rows]], 1)
            top = np.argpartition(-both, ef - 1, axis=1)[:, :ef]
            kept[act[rows]] = np.take_along_axis(both, top, 1)
            ids[act[rows]] = np.take_along_axis(np.concatenate([ids[act[rows]], names[rows]], 1), top, 1)
            worst[act[rows]] = kept[act[rows]].min(1)
        cost["reached"] = seen.sum(1)
        out = []
        for s, j in zip(kept, ids):
            j, s = self.ids[j[s > -np.inf]], s[s > -np.inf]
            order = np.lexsort((j, -s))[:k]
            out.append(list(zip(s[order].tolist(), j[order].tolist())))
        return out, [{c: int(v[i]) for c, v in cost.items()} for i in range(b)]

    def search_all(self, queries: np.ndarray, k: int, ef: int, allowed=None):
        """(found, counters) of each query: in blocks, fewer queries at a time in larger shards; with other callbacks than a bitmap one after the other."""
        bits = allowed.bits if isinstance(allowed, Bitmap) else allowed
        if bits is None or isinstance(bits, np.ndarray):
            step = max(1, min(BLOCK_QUERIES, BLOCK_CELLS // max(1, len(self.ids))))
            for at in range(0, len(queries), step):
                yield from zip(*self.search_block(queries[at : at + step], k, ef, bits))
        else:
            yield from (self.search(q, k, ef, allowed) for q in queries)

    # ---- one row of the stored index

    def pack(self, shard: int) -> tuple:
        flat = [x for node in self.links for x in node]
        degrees = np.array([len(x) for x in flat], np.int32)
        edges = np.concatenate([np.zeros(0, np.int32), *[np.asarray(x, np.int32) for x in flat]])
        return (shard, len(self.ids), 0, self.vecs.shape[1] if len(self.ids) else 0, self.ids.tobytes(), self.vecs.tobytes(), self.levels.tobytes(), degrees.tobytes(), edges.astype(np.int32).tobytes())

    @classmethod
    def unpack(cls, n: int, dim: int, ids: bytes, vecs: bytes, levels: bytes, degrees: bytes, edges: bytes) -> Shard:
        levels_ = np.frombuffer(levels, np.int64)
        ends = np.cumsum(np.frombuffer(degrees, np.int32))
        parts = np.split(np.frombuffer(edges, np.int32), ends[:-1]) if len(ends) else []
        links, at = [], 0
        for lv in levels_.tolist():
            links.append(parts[at : at + lv + 1])
            at += lv + 1
        return cls(np.frombuffer(ids, np.int64), np.frombuffer(vecs, float).reshape(n, dim), levels_, links)


@dataclass
class GraphIndex:
    """A sharded index: a DataFrame with one packed graph for each shard."""

    packed: DataFrame
    metric: str
    shards: int
    m: int
    ef_build: int

    def save(self, path: str) -> None:
        """Shards as Parquet, partitioned by shard, with the build's parameters in the rows."""
        meta = {"metric": self.metric, "shards": self.shards, "m": self.m, "ef_build": self.ef_build}
        rows = self.packed.withColumns({k: F.lit(v) for k, v in meta.items()})
        rows.write.mode("overwrite").partitionBy("shard").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> GraphIndex:
        rows = spark.read.parquet(path)
        meta = rows.select("metric", "shards", "m", "ef_build").first()
        names = [c.split()[0] for c in PACKED.split(", ")]
        return cls(rows.withColumn("shard", F.col("shard").cast("long")).select(names), *meta)

    def rejected(self) -> int:
        """Rows that the index has no node for."""
        return self.packed.agg(F.sum("rejected")).first()[0] or 0

    def nodes(self) -> DataFrame:
        """(shard, node, id, level, vec): the index's points."""

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    g = Shard.unpack(*(row[c] for c in ("n", "dim", "ids", "vecs", "levels", "degrees", "edges")))
                    n = len(g.ids)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([row["shard"]] * n, pa.int64()), pa.array(np.arange(n)), pa.array(g.ids), pa.array(g.levels), pa.array(list(g.vecs), pa.list_(pa.float64()))],
                        ["shard", "node", "id", "level", "vec"],
                    )

        return self.packed.mapInArrow(work, "shard long, node long, id long, level long, vec array<double>")

    def edges(self) -> DataFrame:
        """(shard, level, node, neighbours): the index's links."""

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    g = Shard.unpack(*(row[c] for c in ("n", "dim", "ids", "vecs", "levels", "degrees", "edges")))
                    found = [(lv, i, x.tolist()) for i, node in enumerate(g.links) for lv, x in enumerate(node)]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([row["shard"]] * len(found), pa.int64()), pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64()), pa.array([f[2] for f in found], pa.list_(pa.int32()))],
                        ["shard", "level", "node", "neighbours"],
                    )

        return self.packed.mapInArrow(work, "shard long, level long, node long, neighbours array<int>")


class Bitmap:
    """Filter callback: one bit for each node, made once for a shard."""

    def __init__(self, ids: np.ndarray, allowed: np.ndarray):
        self.bits = np.isin(ids, allowed)

    def __getitem__(self, node: int) -> bool:
        return bool(self.bits[node])


class Hashed:
    """Filter callback: the node's id in a set of qualifying ids."""

    def __init__(self, ids: np.ndarray, allowed: np.ndarray):
        self.ids, self.allowed = ids.tolist(), set(allowed.tolist())

    def __getitem__(self, node: int) -> bool:
        return self.ids[node] in self.allowed


class Sorted:
    """Filter callback: binary search of the node's id among the sorted qualifying ids."""

    def __init__(self, ids: np.ndarray, allowed: np.ndarray):
        self.ids, self.allowed = ids.tolist(), np.sort(allowed).tolist()

    def __getitem__(self, node: int) -> bool:
        at = bisect_left(self.allowed, self.ids[node])
        return at < len(self.allowed) and self.allowed[at] == self.ids[node]


CALLBACKS = {"bitmap": Bitmap, "hash": Hashed, "sorted": Sorted}


def shard_of(row_id: str, shards: int) -> Column:
    return F.pmod(F.xxhash64(F.col(row_id).cast("long")), F.lit(shards))


SHARD_ROWS = 100_000


def graph_build(
    df: DataFrame, row_id: str = "vec_id", vector: str = "embedding", metric: str = "ip", m: int = 16, ef_build: int = 64,
    shards: int | None = None, seed: int = 42, dim: int | None = None, path: str | None = None,
) -> GraphIndex:
    """Build one graph per shard: one shuffle by shard, then local work.

    ``shards`` None gives a shard for every ``SHARD_ROWS`` rows; no shard sees
    another.  ``dim`` is the length of the indexed vectors; without it, the
    one that most rows have (the least of several).  Vectors that are null or
    not whole, of another length or, under cosine, zero are left out and
    counted in ``rejected``.  With ``path`` the index is written there and
    read back, so that searches do not build it again.
    """
    if metric not in INDEX_METRICS:
        raise ValueError(f"the graph is built for one of {INDEX_METRICS}, not {metric!r}")
    if dim is None:
        most = df.where(F.col(vector).isNotNull()).groupBy(F.size(vector).alias("d")).count().orderBy(F.desc("count"), "d").first()
        dim = most["d"] if most else 0
    if shards is None:
        shards = max(1, -(-df.count() // SHARD_ROWS))
    rows = df.select(shard_of(row_id, shards).alias("shard"), F.col(row_id).cast("long").alias("id"), F.col(vector).alias("v"))

    def build(key, table):
        ids, vectors = np.asarray(table.column("id"), np.int64), table.column("v").combine_chunks()
        at, x = densify(vectors, dim)
        if metric == "cosine":
            norm = np.sqrt(np.einsum("ij,ij->i", x, x))
            at, x = at[norm > 0], x[norm > 0] / norm[norm > 0, None]
        packed = list(Shard.build(ids[at], x, m, ef_build, seed).pack(key[0].as_py()))
        packed[2] = table.num_rows - len(at)
        names = [c.split()[0] for c in PACKED.split(", ")]
        return pa.table({n: [v] for n, v in zip(names, packed)})

    index = GraphIndex(rows.where("id is not null").groupBy("shard").applyInArrow(build, PACKED), metric, shards, m, ef_build)
    if path is None:
        return index
    index.save(path)
    return GraphIndex.load(df.sparkSession, path)


def graph_rebuild(index: GraphIndex, df: DataFrame, shard: int, row_id: str = "vec_id", vector: str = "embedding", seed: int = 42, dim: int | None = None) -> GraphIndex:
    """The index with one shard built anew from the rows of ``df`` that belong to it; the others stay as they are."""
    own = df.where(shard_of(row_id, index.shards) == shard)
    new = graph_build(own, row_id, vector, index.metric, index.m, index.ef_build, index.shards, seed, dim)
    kept = index.packed.where(F.col("shard") != shard)
    return replace(index, packed=kept.unionByName(new.packed))


def _allowed_by_shard(index: GraphIndex, qualifying: DataFrame, row_id: str) -> DataFrame:
    """Qualifying ids of each shard as one sorted array: at most a shard's ids."""
    return (
        qualifying.select(shard_of(row_id, index.shards).alias("shard"), F.col(row_id).cast("long").alias("id"))
        .groupBy("shard")
        .agg(F.array_sort(F.collect_set("id")).alias("allowed"))
    )


def graph_search(
    index: GraphIndex, queries: QueryBlock, k: int, ef: int = 64, qualifying: DataFrame | None = None,
    filter_mode: str = "pre", row_id: str = "vec_id", columns: int = 1, counters: bool = False, callback: str = "bitmap",
) -> DataFrame:
    """(query_id, <row_id>, score, rank): the k best found; with ``counters`` what the walks cost.

    ``qualifying`` has the ids that satisfy the relational predicate.  ``pre``:
    the walk passes other nodes but does not return them; each visited node is
    looked up once for each of ``columns`` filter columns, by the ``callback``
    bitmap, hash or sorted, which give the same answers.  ``post``: the k best
    are found first and those that do not qualify are dropped, so fewer than k
    may be left.
    """
    if filter_mode not in ("pre", "post"):
        raise ValueError(f"unknown filter mode {filter_mode!r}")
    look_up = CALLBACKS[callback]
    shards = index.packed
    pre = qualifying is not None and filter_mode == "pre"
    if pre:
        shards = shards.join(_allowed_by_shard(index, qualifying, row_id), "shard", "left").withColumn(
            "allowed", F.coalesce("allowed", F.array().cast("array<long>"))
        )
    matrix = queries.matrix
    if index.metric == "cosine" and len(queries):
        norm = np.sqrt(np.einsum("ij,ij->i", matrix, matrix))[:, None]
        matrix = matrix / np.where(norm > 0, norm, 1)
    kinds = "query_id long, vec_id long, score double" if not counters else "query_id long, hops long, distance_evals long, filter_probes long, results long, reached long, n long"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = {c: batch.column(c)[i] for c in batch.schema.names}
                g = Shard.unpack(*(row[c].as_py() for c in ("n", "dim", "ids", "vecs", "levels", "degrees", "edges")))
                allowed = look_up(g.ids, np.asarray(row["allowed"].values, np.int64)) if pre else None
                out: list[tuple] = []
                for name, (found, c) in zip(queries.ids.tolist(), g.search_all(matrix, k, ef, allowed)):
                    if counters:
                        out.append((name, c["hops"], c["distance_evals"], c["filter_probes"] * columns, len(found), c["reached"], len(g.ids)))
                    else:
                        out += [(name, j, s) for s, j in found]
                if out:
                    names = [x.split()[0] for x in kinds.split(", ")]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out)], names)

    got = shards.mapInArrow(work, kinds)
    if counters:
        return got
    ranked = best(got, k, index.metric, "vec_id").withColumnRenamed("vec_id", row_id)
    if qualifying is not None and filter_mode == "post":
        ranked = ranked.join(qualifying.select(F.col(row_id).cast("long").alias(row_id)), row_id, "left_semi")
    return ranked


def graph_search_blocks(
    index: GraphIndex, blocks: DataFrame, k: int, ef: int = 64, qualifying: DataFrame | None = None, row_id: str = "vec_id"
) -> DataFrame:
    """The pre-filtered search for queries that stay distributed: packed blocks (shard, dim, i_ids, i_x), each once for every shard."""
    shards = index.packed
    if qualifying is not None:
        shards = shards.join(_allowed_by_shard(index, qualifying, row_id), "shard", "left").withColumn(
            "allowed", F.coalesce("allowed", F.array().cast("array<long>"))
        )
    cosine = index.metric == "cosine"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = {c: batch.column(c)[i] for c in batch.schema.names}
                g = Shard.unpack(*(row[c].as_py() for c in ("n", "dim", "ids", "vecs", "levels", "degrees", "edges")))
                allowed = Bitmap(g.ids, np.asarray(row["allowed"].values, np.int64)) if "allowed" in row else None
                names = np.frombuffer(row["i_ids"].as_py(), np.int64)
                x = unpacked(row["i_x"].as_py(), len(names), row["dim"].as_py())
                if cosine:
                    norm = np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]
                    x = x / np.where(norm > 0, norm, 1)
                out = [
                    (name, j, s)
                    for name, (found, _) in zip(names.tolist(), g.search_all(x, k, ef, allowed))
                    for s, j in found
                ]
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out)], ["query_id", row_id, "score"])

    pairs = shards.hint("merge").join(blocks.hint("merge"), ["shard", "dim"])  # the sizes of packed rows are unknown to the optimizer
    return best(pairs.mapInArrow(work, f"query_id long, {row_id} long, score double"), k, index.metric, row_id)


def graph_post_grow(
    index: GraphIndex, queries: QueryBlock, k: int, qualifying: DataFrame, ef: int = 64, growth: int = 2,
    max_rounds: int = 12, row_id: str = "vec_id",
) -> DataFrame:
    """Post-filter with a growing search until k results survive for every query, or all were seen.

    One driver round trip for each round: only ids of queries come back.
    Queries still short after ``max_rounds``, or when the whole index was
    walked, are answered by an exact scan of the index's qualifying rows.
    """
    total = index.packed.agg(F.sum("n")).first()[0] or 0
    passed = qualifying.select(F.col(row_id).cast("long").alias("id")).distinct()
    rows = index.nodes().join(passed, "id", "left_semi").select(F.col("id").alias(row_id), "vec")
    possible = min(k, rows.count())
    wide = k
    for left in reversed(range(max(1, max_rounds))):
        found = graph_search(index, queries, wide, max(ef, wide), qualifying, "post", row_id)
        kept = best(found.drop("rank"), k, index.metric, row_id)
        full = kept.groupBy("query_id").count().where(F.col("count") >= possible)
        short = ~np.isin(queries.ids, [r[0] for r in full.collect()]) & (possible > 0)  # at most one id for each query
        if not short.any():
            return kept
        if wide >= total or not left:
            break
        wide = min(total, wide * growth)
    rest = QueryBlock(queries.ids[short], queries.matrix[short])
    answered = kept.join(full.select("query_id"), "query_id", "left_semi")
    return answered.unionByName(scan(rows, rest, row_id, "vec", index.metric, k=k).select(*answered.columns))
