"""Byte-level BPE encoding and decoding with given ranks.

A text is split by the vocabulary's pattern; each match is encoded by itself. A segment tree over the match's byte
positions holds at each leaf the rank and place of the pair that starts there, and at each inner node the lesser of its
two children, so the root is the leftmost pair of least rank; a merge updates the leaves of the live neighbours and the
nodes above them. A match of n bytes costs n log n, however long it is. A match that is a token itself is that token.

Matches of up to ``SHORT`` bytes that a batch has anew are encoded side by side: their trees are the rows of one array,
and every step merges once in each row that still has a pair. Longer ones have a tree of their own. Ids of short matches
are remembered, ``CACHED`` at most, in two arrays (ids, and where each match's begin), so a worker holds a few ten MB.

The split follows the Unicode version of the regular-expression library; code points assigned since an older
version may be split differently there.

Null texts count as empty: no ids, no bytes. Rows are independent: repeated rows, null ids and other columns need
no care, and an empty table gives an empty result. Batches are cut by bytes, and a text longer than a batch is split
a part of its matches at a time.
"""

from __future__ import annotations

import base64
from itertools import islice
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from slicegrad.llm.common import process_cache, ship_by_value

ship_by_value(__name__)

NEVER = 1 << 62
#: Matches of more bytes are encoded one by one.
SHORT = 64
#: Matches remembered by a worker.
CACHED = 150_000
BATCH_BYTES = 2 << 20
#: Matches of a text that are held at once.
PART = 200_000


def read_ranks(path: str) -> dict[bytes, int]:
    return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in Path(path).read_bytes().splitlines() if line)}


def merge_bytes(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The ids of one match. Keys are rank and position in one number, so the least is the leftmost of least rank."""
    if piece in ranks:
        return [ranks[piece]]
    n = len(piece)
    if not n:
        return []
    get = ranks.get
    shift = n.bit_length()
    low = (1 << shift) - 1
    width = 1 << max(1, (n - 1).bit_length())

    def key(i: int, stop: int) -> int:
        rank = get(piece[i:stop])
        return NEVER if rank is None else rank << shift | i

    tree = [NEVER] * (2 * width)
    for i in range(n - 1):
        tree[width + i] = key(i, i + 2)
    for k in range(width - 1, 0, -1):
        tree[k] = min(tree[2 * k], tree[2 * k + 1])
    end = list(range(1, n + 1))  # where the token that starts here ends, and so where the next one starts
    before = list(range(-1, n))

    def put(at: int, value: int) -> None:
        at += width
        tree[at] = value
        at >>= 1
        while at:
            least = min(tree[2 * at], tree[2 * at + 1])
            if tree[at] == least:
                return
            tree[at] = least
            at >>= 1

    while (least := tree[1]) != NEVER:
        i = least & low
        j = end[i]
        stop = end[i] = end[j]
        before[stop] = i
        put(j, NEVER)
        put(i, key(i, end[stop]) if stop < n else NEVER)
        if (h := before[i]) >= 0:
            put(h, key(h, stop))
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : end[i]]])
        i = end[i]
    return out


class Pairs:
    """Which two tokens, side by side, are a third one: every token, cut in two wherever both halves are tokens."""

    def __init__(self, ranks: dict[bytes, int]):
        keys, values = [], []
        for token, rank in ranks.items():
            for k in range(1, len(token)):
                left = ranks.get(token[:k])
                right = ranks.get(token[k:]) if left is not None else None
                if right is not None:
                    keys.append(left << 32 | right)
                    values.append(rank)
        order = np.argsort(np.array(keys, dtype=np.int64), kind="stable")
        self.keys = np.r_[np.array(keys, dtype=np.int64)[order], np.iinfo(np.int64).max]
        self.values = np.r_[np.array(values, dtype=np.int64)[order], 0]

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """-1 if the two are none."""
        want = left << 32 | right
        at = np.searchsorted(self.keys, want)
        return np.where(self.keys[at] == want, self.values[at], -1)


def merge_rows(pieces: list[bytes], single: np.ndarray, pairs: Pairs) -> tuple[np.ndarray, np.ndarray]:
    """The ids of all pieces, one after another, and how many each has. ``single``: the id of every byte."""
    count = len(pieces)
    size = np.fromiter(map(len, pieces), dtype=np.int64, count=count)
    width = 1 << max(1, (int(size.max()) - 1).bit_length())
    low, shift, levels = width - 1, width.bit_length() - 1, width.bit_length() - 1
    place = np.arange(width)
    real = place < size[:, None]
    token = np.zeros((count, width), dtype=np.int64)
    token[real] = single[np.frombuffer(b"".join(pieces), dtype=np.uint8)]
    after = np.tile(np.arange(1, width + 2), (count, 1))
    before = np.tile(np.arange(-1, width), (count, 1))
    tree = np.full((count, 2 * width), NEVER, dtype=np.int64)
    rank = pairs.rank(token[:, :-1].ravel(), token[:, 1:].ravel()).reshape(count, width - 1)
    tree[:, width:-1] = np.where((rank >= 0) & real[:, 1:], rank << shift | place[:-1], NEVER)
    for level in range(levels):
        a, b = width >> level, 2 * width >> level
        tree[:, a // 2 : a] = np.minimum(tree[:, a:b:2], tree[:, a + 1 : b : 2])
    live = real.copy()
    rows = np.flatnonzero(tree[:, 1] != NEVER)
    flat, step = tree.ravel(), 2 * width
    while len(rows):
        least = flat[rows * step + 1]
        i = least & low
        j = after[rows, i]
        stop = after[rows, j]
        token[rows, i] = own = least >> shift
        live[rows, j] = False
        after[rows, i] = stop
        before[rows, stop] = i
        n = size[rows]
        right = pairs.rank(own, token[rows, np.minimum(stop, width - 1)])
        h = before[rows, i]
        left = pairs.rank(token[rows, np.maximum(h, 0)], own)
        base = rows * step
        flat[base + width + j] = NEVER
        flat[base + width + i] = np.where((stop < n) & (right >= 0), right << shift | i, NEVER)
        some = h >= 0
        flat[(base + width + h)[some]] = np.where(left >= 0, left << shift | h, NEVER)[some]
        node = np.r_[width + i, width + j, width + h[some]]
        base = np.r_[base, base, base[some]]
        for _ in range(levels):
            node >>= 1
            at = base + 2 * node
            flat[base + node] = np.minimum(flat[at], flat[at + 1])
        rows = rows[flat[rows * step + 1] != NEVER]
    return token[live], live.sum(1)


class Known(dict):
    """Match to its number; a new one gets the next number and waits in ``fresh``."""

    def __init__(self):
        self.fresh: list[str] = []

    def __missing__(self, piece: str) -> int:
        self[piece] = n = len(self)
        self.fresh.append(piece)
        return n


class Codec:
    def __init__(self, path: str, pattern: str):
        import regex

        self.ranks = read_ranks(path)
        # \s of the split is Unicode white space; this library's own class also has U+001C to U+001F
        self.split = regex.compile(pattern.replace(r"[^\s", r"[^\p{White_Space}").replace(r"\S", r"\P{White_Space}").replace(r"\s", r"\p{White_Space}"))
        self.single = np.array([self.ranks[bytes([b])] for b in range(256)], dtype=np.int64)
        self.pairs = Pairs(self.ranks)
        most = max(self.ranks.values()) + 1
        tokens = [b""] * most
        for token, rank in self.ranks.items():
            tokens[rank] = token
        self.bytes_of = np.frombuffer(b"".join(tokens), dtype=np.uint8)
        self.bytes_n = np.fromiter(map(len, tokens), dtype=np.int64, count=most)
        self.bytes_at = np.cumsum(self.bytes_n) - self.bytes_n
        self.forget()

    def forget(self) -> None:
        self.known = Known()
        self.ids = np.zeros(0, dtype=np.int32)
        self.size = np.zeros(0, dtype=np.int64)
        self.start = np.zeros(0, dtype=np.int64)

    def learn(self) -> None:
        """Encode the matches that wait; ids are appended in any order, as each match knows where its own begin."""
        fresh, self.known.fresh = [p.encode("utf-8") for p in self.known.fresh], []
        count, top = len(fresh), len(self.ids)
        length = np.fromiter(map(len, fresh), dtype=np.int64, count=count)
        rank = np.fromiter((self.ranks.get(p, -1) for p in fresh), dtype=np.int64, count=count)
        size, start, parts = np.ones(count, dtype=np.int64), np.zeros(count, dtype=np.int64), [self.ids]

        def keep(own: np.ndarray, ids: np.ndarray, n: np.ndarray) -> None:
            nonlocal top
            size[own], start[own] = n, top + np.cumsum(n) - n
            parts.append(ids.astype(np.int32))
            top += len(ids)

        whole = np.flatnonzero(rank >= 0)
        keep(whole, rank[whole], np.ones(len(whole), dtype=np.int64))
        for k in np.flatnonzero((rank < 0) & (length > SHORT)):
            ids = np.array(merge_bytes(fresh[k], self.ranks))
            keep(np.array([k]), ids, np.array([len(ids)]))
        least = 0
        for width in (4, 8, 12, 16, 24, 32, SHORT):
            own = np.flatnonzero((rank < 0) & (length > least) & (length <= width))
            least = width
            for lo in range(0, len(own), (1 << 19) // width):
                part = own[lo : lo + (1 << 19) // width]
                keep(part, *merge_rows([fresh[k] for k in part], self.single, self.pairs))
        self.ids = np.concatenate(parts)
        self.size, self.start = np.r_[self.size, size], np.r_[self.start, start]

    def look_up(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all pieces, one after another, and how many each has."""
        if len(self.known) > CACHED:
            self.forget()
        slot = np.fromiter(map(self.known.__getitem__, pieces), dtype=np.int64, count=len(pieces))
        if self.known.fresh:
            self.learn()
        n = self.size[slot]
        return self.ids[spread(self.start[slot], n)], n

    def encode_all(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, one after another, and how many each has."""
        parts, count, held, held_n = [], np.zeros(len(texts), dtype=np.int64), [], []

        def settle() -> None:
            ids, n = self.look_up(held)
            parts.append(ids)
            ends = np.cumsum([0, *[m for _, m in held_n]])
            total = np.r_[0, np.cumsum(n)]
            for (k, _), lo, hi in zip(held_n, ends[:-1], ends[1:]):
                count[k] += total[hi] - total[lo]
            held.clear(), held_n.clear()

        for k, text in enumerate(texts):
            if not text:
                continue
            if len(text) < BATCH_BYTES:
                pieces = self.split.findall(text)
                held_n.append((k, len(pieces)))
                held += pieces
            else:
                found = self.split.finditer(text)
                while pieces := [m.group() for m in islice(found, PART)]:
                    held_n.append((k, len(pieces)))
                    held += pieces
                    settle()
            if len(held) >= PART:
                settle()
        if held:
            settle()
        return np.concatenate(parts) if parts else np.zeros(0, dtype=np.int32), count

    def encode(self, text: str | None) -> list[int]:
        return self.encode_all([text])[0].tolist()

    def bytes_of_all(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes of all ids, one after another, and how many each has."""
        n = self.bytes_n[ids]
        return self.bytes_of[spread(self.bytes_at[ids], n)], n

    def decode(self, ids) -> bytes:
        return self.bytes_of_all(np.asarray(ids, dtype=np.int64))[0].tobytes()


def spread(start: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The places start, start + 1, ... of each range, one range after another."""
    ends = np.cumsum(n)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(start - (ends - n), n)


def codec(path: str, pattern: str) -> Codec:
    """One for each worker process; the vocabulary is read from the machine's own installation."""
    held = process_cache("bpe")
    if (path, pattern) not in held:
        held[path, pattern] = Codec(path, pattern)
    return held[path, pattern]


def _offsets(n: np.ndarray) -> np.ndarray:
    return np.r_[0, np.cumsum(n)].astype(np.int32)


def _coded(path: str, pattern: str, ids: str, decoded: str | None):
    def batches(source):
        for batch in source:
            column = batch.column("_text")
            lo, size = 0, 0
            for i in range(len(column)):
                size += len(column[i].as_buffer() or b"") if column[i].is_valid else 0
                if size >= BATCH_BYTES or i + 1 == len(column):
                    yield batch.slice(lo, i + 1 - lo)
                    lo, size = i + 1, 0

    def run(source):
        own = codec(path, pattern)
        for batch in batches(source):
            flat, n = own.encode_all(batch.column("_text").to_pylist())
            arrays = [batch.column("_row"), pa.ListArray.from_arrays(pa.array(_offsets(n)), pa.array(flat))]
            names = ["_row", ids]
            if decoded is not None:
                data, of_id = own.bytes_of_all(flat)
                ends = np.r_[0, np.cumsum(of_id)][_offsets(n)]
                arrays.append(pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(data)]))
                names.append(decoded)
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    return run


def bpe_encode(docs: DataFrame, path: str, pattern: str, text: str = "text", carry: list[str] | None = None, ids: str = "ids", decoded: str | None = "decoded") -> DataFrame:
    """The columns ``carry`` (all, if None), then ``ids`` and, unless None, their bytes ``decoded`` by the same table.

    A carried column of such a name gives way to the new one.
    """
    carry = [c for c in (docs.columns if carry is None else carry) if c not in (ids, decoded)]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in carry]).alias("_row"), F.col(f"`{text}`").cast("string").alias("_text"))
    fields = [T.StructField("_row", rows.schema["_row"].dataType), T.StructField(ids, T.ArrayType(T.IntegerType()))]
    if decoded is not None:
        fields.append(T.StructField(decoded, T.BinaryType()))
    coded = rows.mapInArrow(_coded(path, pattern, ids, decoded), T.StructType(fields))
    return coded.select(*[F.col("_row").getField(c).alias(c) for c in carry], *[f.name for f in fields[1:]])
