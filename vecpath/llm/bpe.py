"""BPE encoding and decoding with content-defined chunk reuse."""

from __future__ import annotations

import hashlib
import json
import os
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .blocks import flat, pieces
from .common import free_name

# Fixed values of byte-level BPE: the pattern that splits text before merging.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

WINDOW = 16  # bytes of the rolling hash
MEAN_CHUNK = 512  # bytes, a power of two
CACHE_BYTES = 30 << 20


def _byte_chars() -> dict[str, int]:
    """Byte-level BPE writes every byte as one printable character."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


class Codec:
    """Encodes texts chunk by chunk; chunks and joins seen before are looked up.

    A chunk's encoding is (number of ids, ids as text, bytes they decode to).
    """

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        self.encode_ids, self.decode_bytes = self._engine(path, spec)
        size = 1 + max([*spec["model"]["vocab"].values(), *self.special.values()])
        self.names = [str(k) for k in range(size)]
        self.table = np.random.default_rng(20).integers(0, 1 << 32, 256, dtype=np.uint32)
        self.cache: dict[bytes, tuple] = {}
        self.held = 0
        self.looked = self.encoded = 0

    @staticmethod
    def _engine(path: str, spec: dict):
        vocab, merges, pre = spec["model"]["vocab"], spec["model"]["merges"], spec.get("pre_tokenizer") or {}
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        made = [vocab.get("".join(p), -1) for p in pairs]
        byte_level = (
            pre.get("type") == "ByteLevel"
            and pre.get("use_regex", True)
            and not pre.get("add_prefix_space", True)
            and not spec.get("normalizer")
            and made == sorted(made)
            and -1 not in made
            and all(not x["lstrip"] and not x["rstrip"] for x in spec.get("added_tokens", []))
        )
        if not byte_level:
            raise ValueError("only byte-level BPE whose ids follow the order of its merges is supported")
        import tiktoken

        back, special = _byte_chars(), {x["content"] for x in spec.get("added_tokens", [])}
        ranks = {bytes(back[c] for c in s): k for s, k in vocab.items() if s not in special}
        tool = tiktoken.Encoding(os.path.basename(path), pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})
        return tool.encode_ordinary, tool.decode_bytes

    def _fresh(self, body: bytes) -> tuple[int, str, bytes]:
        ids = self.encode_ids(body.decode("utf-8"))
        return len(ids), ",".join(map(self.names.__getitem__, ids)), self.decode_bytes(ids)

    def _encode(self, body: bytes) -> tuple[int, str, bytes]:
        self.looked += 1
        found = self.cache.get(body)
        if found is None:
            self.encoded += 1
            found = self._fresh(body)
            if self.held > CACHE_BYTES:
                self.cache.clear()
                self.held = 0
            self.cache[body] = found
            self.held += 2 * len(body) + len(found[1]) + 250
        return found

    def cuts(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(chunk cuts, points of certain agreement) in ``data``.

        A rolling hash of the last 16 bytes places the cuts.  A point of
        certain agreement stands before a blank that follows a visible ASCII
        character: no piece of the split pattern reaches across it, and what
        stands before it does not change what is found after it.
        """
        h = self.table[data]
        for step in (1, 2, 4, 8):
            h[step:] += h[:-step] << np.uint32(step)
        cut = (h >> np.uint32(9)) & np.uint32(MEAN_CHUNK - 1) == 0
        before = data[:-1]
        sure = (before > 0x20) & (before < 0x7F) & ((data[1:] == 0x20) | (data[1:] == 0x0A))
        return np.flatnonzero(cut) + 1, np.flatnonzero(sure) + 1

    def plain(self, body: bytes, cuts: np.ndarray, sure: np.ndarray) -> list[tuple[int, str, bytes]]:
        """Encodings that together are the encoding of ``body``.

        Of every chunk, what lies between its first and its last point of
        agreement is encoded once for all documents.  A join reaches from the
        last such point of one chunk to the first of the next; it is encoded
        anew, and grows over chunks that have no such point until both sides
        agree.
        """
        out, start = [], 0
        if len(cuts) and len(sure):
            first = np.searchsorted(sure, np.concatenate([[0], cuts]), "left")
            last = np.searchsorted(sure, np.concatenate([cuts, [len(body)]]), "left") - 1
            some = first < last
            for a, b in zip(sure[first[some]].tolist(), sure[last[some]].tolist()):
                if a > start:
                    out.append(self._encode(body[start:a]))
                out.append(self._encode(body[a:b]))
                start = b
        if start < len(body):
            out.append(self._encode(body[start:]))
        return out

    def text(self, body: bytes, cuts: np.ndarray, sure: np.ndarray) -> tuple[int, str, bytes]:
        """(number of ids, ids joined by commas, decoded bytes) of a text."""
        marks = [s for s in self.special if s.encode() in body]
        if not marks:
            parts = self.plain(body, cuts, sure)
        else:
            parts, rest = [], body
            none = np.zeros(0, np.int64)
            while rest:
                at, mark = min(((p if (p := rest.find(m.encode())) >= 0 else len(rest), m) for m in marks))
                if at:
                    parts += self.plain(rest[:at], none, none)
                if at < len(rest):
                    parts.append((1, str(self.special[mark]), mark.encode()))
                rest = rest[at + len(mark.encode()) :]
        return sum(p[0] for p in parts), ",".join(p[1] for p in parts if p[1]), b"".join(p[2] for p in parts)

    def batch(self, column: pa.Array) -> Iterator[tuple[int, str, bytes]]:
        offsets, data = flat(column)
        for lo, hi in pieces(offsets):
            base = int(offsets[lo])
            part = data[base : int(offsets[hi])]
            raw = part.tobytes()
            cuts, sure = self.cuts(part) if len(part) > WINDOW else (np.zeros(0, np.int64),) * 2
            ends = offsets[lo : hi + 1] - base
            c_at, s_at = np.searchsorted(cuts, ends), np.searchsorted(sure, ends)
            for k in range(hi - lo):
                a, b = int(ends[k]), int(ends[k + 1])
                mine = cuts[c_at[k] : c_at[k + 1]] - a
                points = sure[s_at[k] : s_at[k + 1]] - a
                # near its start the hash has seen the text before
                yield self.text(raw[a:b], mine[mine >= WINDOW], points[points > 0])


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    return Codec(path)


def encode_decode(docs: DataFrame, path: str, text: str = "text", keep_ids: bool = False) -> DataFrame:
    """Every row of ``docs`` with n_tokens, ids_sha256 and decoded_sha256.

    With ``keep_ids`` also ``ids`` (array of int) and ``decoded`` (string).
    The ids are those of the tokenizer file at ``path`` on the whole text with
    no special tokens added; marks of special tokens in the text are taken as
    such.  Null counts as empty; an empty text has no ids.  Columns of
    ``docs`` with the new names are replaced.  One pass without a shuffle;
    repeated chunks are encoded once per worker, in a cache of bounded size.
    """
    new = ["n_tokens", "ids_sha256", "decoded_sha256"] + ["ids", "decoded"] * keep_ids
    held = docs.drop(*[c for c in docs.columns if c.lower() in new and c != text])
    name = text
    if text in new:
        name = free_name(held.columns, "_text")
        held = held.withColumnRenamed(text, name)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in held.schema.fields)
    schema += ", n_tokens long, ids_sha256 string, decoded_sha256 string"
    schema += ", ids array<int>, decoded string" * keep_ids

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool = codec(path)
        for batch in batches:
            n, ids_sha, text_sha, ids, texts = [], [], [], [], []
            for count, joined, decoded in tool.batch(batch.column(name)):
                n.append(count)
                ids_sha.append(hashlib.sha256(joined.encode()).hexdigest())
                text_sha.append(hashlib.sha256(decoded).hexdigest())
                if keep_ids:
                    ids.append([int(x) for x in joined.split(",")] if joined else [])
                    texts.append(decoded.decode("utf-8", "replace"))
            columns = [pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())]
            if keep_ids:
                columns += [pa.array(ids, pa.list_(pa.int32())), pa.array(texts, pa.string())]
            yield pa.RecordBatch.from_arrays([*batch.columns, *columns], [*batch.schema.names, *new])

    out = held.mapInArrow(work, schema)
    return out.drop(name) if name != text else out
