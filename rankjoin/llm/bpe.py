"""Byte-level BPE encoding and decoding in length-bucketed padded numpy matrices.

Each distinct piece of text (a match of the split pattern) is one row of a matrix
of token ids, padded on the right; rows of similar length share a matrix. In each
round every row merges its leftmost minimum-rank pair: the ranks of neighbouring
pairs are looked up in an open-addressing hash table, and both the ids and the ranks are
compacted by one column. Rows without a mergeable pair leave the matrix.

Distinct pieces are encoded once per batch and kept in a bounded cache in each Python
worker, so that the matrices see new pieces only. Pieces over `LONG` bytes
(a word without any break, thousands of letters long) take a heap over a linked
list instead: a row of length L needs up to L rounds over L columns, which for such
rows would be quadratic. Both give the same merges.

The classes of letters, numbers and white space in the split pattern are those of the tiktoken library
(`as_library`), whose Unicode tables may be of another year than the regex module's.

Defined results: a null text is an empty one and gets no ids; rows are encoded one
by one, so repeated rows get equal ids; all other columns pass through untouched.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from rankjoin.llm.common import free_name, releasing, runs, table

NONE = np.int32(2**31 - 1)  # the rank of a pair that cannot merge
LONG = 1024  # bytes
CELLS = 1 << 20  # of a matrix
CACHE = 200_000  # entries of each cache
BATCH_CHARS = 1_000_000


class PairTable:
    """Hashed lookup from two neighbouring ids to the id (= rank) they merge into."""

    def __init__(self, left: np.ndarray, right: np.ndarray, merged: np.ndarray) -> None:
        bits = max(4, int(len(left) * 3).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), np.uint64((1 << bits) - 1)
        self.keys = np.full(1 << bits, np.uint64(2**64 - 1))
        self.values = np.full(1 << bits, NONE, np.int32)
        key = self._key(left, right)
        slot, rest = self._slot(key), np.arange(len(key))
        while len(rest):
            free = self.keys[slot[rest]] == np.uint64(2**64 - 1)
            first, at = np.unique(slot[rest][free], return_index=True)
            taken = rest[free][at]
            self.keys[first], self.values[first] = key[taken], merged[taken]
            rest = rest[~np.isin(rest, taken, assume_unique=True)]
            slot[rest] = (slot[rest] + np.uint64(1)) & self.mask

    @staticmethod
    def _key(left: np.ndarray, right: np.ndarray) -> np.ndarray:
        return (left.astype(np.uint32).astype(np.uint64) << np.uint64(32)) | right.astype(np.uint32).astype(np.uint64)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return (key * np.uint64(0x9E3779B97F4A7C15)) >> self.shift

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The rank of each pair, NONE where the two cannot merge. Padding is -1."""
        key = self._key(left, right)
        slot = self._slot(key)
        found = self.keys[slot]
        out = np.where(found == key, self.values[slot], NONE)
        open_ = np.nonzero((found != key) & (found != np.uint64(2**64 - 1)))
        while len(open_[0]):
            slot[open_] = (slot[open_] + np.uint64(1)) & self.mask
            there, want = self.keys[slot[open_]], key[open_]
            out[open_] = np.where(there == want, self.values[slot[open_]], NONE)
            more = (there != want) & (there != np.uint64(2**64 - 1))
            open_ = tuple(x[more] for x in open_)
        return out


class MatrixBpe:
    """An encoder and decoder for one vocabulary (bytes to rank) and split pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        self.ids = ranks
        self.size = max(ranks.values(), default=-1) + 1
        self.bytes_of: list[bytes] = [b""] * self.size
        for token, i in ranks.items():
            self.bytes_of[i] = token
        cuts = [(ranks[t[:k]], ranks[t[k:]], i) for t, i in ranks.items() for k in range(1, len(t)) if t[:k] in ranks and t[k:] in ranks]
        left, right, merged = np.array(cuts, np.int64).reshape(-1, 3).T
        self.pairs = PairTable(left, right, merged.astype(np.int32))
        self.merge = {(a, b): i for a, b, i in cuts}
        self.of_byte = np.array([ranks.get(bytes([b]), -1) for b in range(256)], np.int32)
        self.find = regex.compile(pattern).findall
        self.pieces: dict[str, bytes] = {}
        self.first: dict[str, bytes] = {}  # chunks at the start of a line
        self.rest: dict[str, bytes] = {}  # chunks after one space

    # -- pieces ---------------------------------------------------------------
    def encode_pieces(self, pieces: list[bytes]) -> list[bytes]:
        """The ids of each piece, as little-endian unsigned 32-bit integers."""
        out: list[bytes] = [b""] * len(pieces)
        open_: list[int] = []
        for k, p in enumerate(pieces):
            if (i := self.ids.get(p)) is not None:
                out[k] = i.to_bytes(4, "little")
            elif len(p) > LONG:
                out[k] = self._long(p)
            elif p:
                open_.append(k)
        open_.sort(key=lambda k: len(pieces[k]))
        start = 0
        while start < len(open_):
            shortest = len(pieces[open_[start]])
            most, end = shortest + max(2, shortest // 4), start
            while end < len(open_) and len(pieces[open_[end]]) <= most and (end - start + 1) * most <= CELLS:
                end += 1
            end = max(end, start + 1)
            self._matrix([pieces[k] for k in open_[start:end]], open_[start:end], out)
            start = end
        return out

    def _matrix(self, rows: list[bytes], at: list[int], out: list[bytes]) -> None:
        sizes, where = np.array([len(r) for r in rows]), np.array(at)
        ids = np.full((len(rows), sizes.max()), -1, np.int32)
        ids[np.arange(ids.shape[1]) < sizes[:, None]] = self.of_byte[np.frombuffer(b"".join(rows), np.uint8)]
        ranks = self.pairs.ranks(ids[:, :-1], ids[:, 1:])
        while len(ids):
            row = np.arange(len(ids))
            if ranks.shape[1]:
                at_ = ranks.argmin(1)
                best = ranks[row, at_]
                live = best < NONE
            else:
                live = np.zeros(len(ids), bool)
            if not live.all():
                done = ids[~live].astype("<u4")
                for k, n, full in zip(where[~live], (ids[~live] >= 0).sum(1), done, strict=True):
                    out[k] = full[:n].tobytes()
                if not live.any():
                    return
                ids, ranks, where, at_, best = ids[live], ranks[live], where[live], at_[live], best[live]
                row = np.arange(len(ids))
            n, width = ids.shape
            ids[row, at_] = best
            keep = np.ones((n, width), bool)
            keep[row, at_ + 1] = False
            ids = ids[keep].reshape(n, width - 1)
            keep = np.ones((n, width - 1), bool)
            keep[row, at_] = False
            ranks = ranks[keep].reshape(n, width - 2)
            if left := (at_ > 0).nonzero()[0].tolist():
                k = at_[left]
                ranks[left, k - 1] = self.pairs.ranks(ids[left, k - 1], ids[left, k])
            if right := (at_ < width - 2).nonzero()[0].tolist():
                k = at_[right]
                ranks[right, k] = self.pairs.ranks(ids[right, k], ids[right, k + 1])

    def _long(self, piece: bytes) -> bytes:
        ids = self.of_byte[np.frombuffer(piece, np.uint8)].tolist()
        n = len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, k, ids[k], ids[k + 1]) for k in range(n - 1) if (r := self.merge.get((ids[k], ids[k + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            r, k, a, b = heapq.heappop(heap)
            j = after[k]
            if ids[k] != a or j >= n or ids[j] != b:
                continue
            ids[k], ids[j] = r, -1
            after[k] = after[j]
            if after[k] < n:
                before[after[k]] = k
                if (q := self.merge.get((r, ids[after[k]]))) is not None:
                    heapq.heappush(heap, (q, k, r, ids[after[k]]))
            if (p := before[k]) >= 0 and (q := self.merge.get((ids[p], r))) is not None:
                heapq.heappush(heap, (q, p, ids[p], r))
        return np.array([i for i in ids if i >= 0], "<u4").tobytes()

    # -- texts ----------------------------------------------------------------
    def _learn(self, chunks: set[str], cache: dict[str, bytes], before: str) -> None:
        if len(cache) > CACHE:
            cache.clear()
        if len(self.pieces) > CACHE:
            self.pieces.clear()
        new = [c for c in chunks if c not in cache]
        split = [self.find(before + c) for c in new]
        unknown = list({p for s in split for p in s} - self.pieces.keys())
        self.pieces.update(zip(unknown, self.encode_pieces([p.encode() for p in unknown]), strict=True))
        get = self.pieces.__getitem__
        cache.update((c, b"".join(map(get, s))) for c, s in zip(new, split, strict=True))

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, as little-endian unsigned 32-bit integers.

        A text is cut where no match of the pattern can reach across: at a single
        line break and before a single space that stand between characters other
        than white space. Each distinct chunk is split by the pattern once.
        """
        cut, first, rest = [], set(), set()
        for text in texts:
            lines = text.split("\n")
            if not all(x and not x[0].isspace() and not x[-1].isspace() for x in lines):
                lines = [text]
            parts = [x.split(" ") for x in lines]
            cut.append(parts)
            for p in parts:
                first.add(p[0])
                rest.update(p[1:])
        if bad := {x for x in first | rest if not x or x[-1].isspace()}:
            first, rest = set(), set()
            for parts in cut:
                for k, p in enumerate(parts):
                    if not bad.isdisjoint(p):
                        parts[k] = p = _joined(p)
                    first.add(p[0])
                    rest.update(p[1:])
        line_break = first | {"\n"} if any(len(p) > 1 for p in cut) else first
        self._learn(line_break, self.first, "")
        self._learn(rest, self.rest, " ")
        head, tail = self.first, self.rest.__getitem__
        between = head.get("\n", b"")
        return [between.join([head[p[0]] + b"".join(map(tail, p[1:])) for p in parts]) for parts in cut]

    def decode(self, ids: bytes) -> bytes:
        """The bytes of a text, from its ids as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def _joined(parts: list[str]) -> list[str]:
    """Parts of a split at spaces, joined again where a part is empty or ends in white space."""
    out, open_ = [], None
    for p in parts:
        open_ = p if open_ is None else f"{open_} {p}"
        if open_ and not open_[-1].isspace():
            out.append(open_)
            open_ = None
    return out if open_ is None else [*out, open_]


def read_ranks(path: str) -> dict[bytes, int]:
    """A rank file: on each line a token in base 64, and its rank."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def _ranges(points: set[int]) -> str:
    """A set of code points as ranges of a character class."""
    ordered, out = sorted(points), []
    for p in ordered:
        if out and out[-1][1] == p - 1:
            out[-1][1] = p
        else:
            out.append([p, p])
    return "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in out)


@lru_cache(maxsize=8)
def as_library(pattern: str) -> str:
    """The pattern with its classes as the tiktoken library reads them: each one is asked for all code points."""
    every = "".join(map(chr, (*range(0xD800), *range(0xE000, 0x110000))))
    single = {bytes([b]): b for b in range(256)}
    changed = False
    for name, opposite in ((r"\p{L}", r"\P{L}"), (r"\p{N}", r"\P{N}"), (r"\s", r"\S")):
        probe = tiktoken.Encoding("probe", pat_str=name, mergeable_ranks=single, special_tokens={})
        theirs, ours = set(map(ord, probe.decode(probe.encode_ordinary(every)))), set(map(ord, regex.findall(name, every)))
        less, more = _ranges(ours - theirs), _ranges(theirs - ours)
        if less or more:
            own = f"[{name}{f'--[{less}]' if less else ''}]"
            own = f"[{own}[{more}]]" if more else own
            pattern = pattern.replace(name, own).replace(opposite, f"[^{own}]")
            changed = True
    return f"(?V1){pattern}" if changed else pattern


@lru_cache(maxsize=2)
def encoder(path: str, pattern: str) -> MatrixBpe:
    """The encoder of this process for a vocabulary file that every worker has at `path`."""
    return MatrixBpe(read_ranks(path), pattern)


def encode(docs: DataFrame, vocabulary: str, pattern: str, *, digests: bool = False, only: list[str] | None = None) -> DataFrame:
    """docs with its texts encoded, and decoded again.

    Adds n_tokens, then ids (array of int) and intact (whether they decode to the text), or with `digests` the columns ids_sha256 and
    decoded_sha256 (hex digests of the ids as little-endian unsigned 32-bit integers
    and of the decoded bytes). Where docs has a column of such a name, the new one
    gets a trailing underscore. only: the columns of docs to keep.
    """
    pattern = as_library(pattern)
    docs = docs if only is None else docs.select(*only, *(["text"] if "text" not in only else []))
    names = free_name(docs, "n_tokens", *(["ids_sha256", "decoded_sha256"] if digests else ["ids", "intact"]))
    kept = docs.columns if only is None else only
    kinds = [T.LongType(), *([T.StringType()] * 2 if digests else [T.ArrayType(T.IntegerType(), False), T.BooleanType()])]
    schema = T.StructType([docs.schema[c] for c in kept] + [T.StructField(n, k) for n, k in zip(names, kinds, strict=True)])

    at = {c: k for k, c in enumerate(docs.columns)}

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(vocabulary, pattern)
        for batch in batches:
            sizes = pc.fill_null(pc.binary_length(batch.column(at["text"])), 0).to_numpy(zero_copy_only=False)
            for a, b in runs(sizes, BATCH_CHARS):
                part = batch.slice(a, b - a)
                texts = [x or "" for x in part.column(at["text"]).to_pylist()]
                ids = bpe.encode(texts)
                counts = np.array([len(x) // 4 for x in ids], np.int64)
                if digests:
                    made = [pa.array([hashlib.sha256(x).hexdigest() for x in ids]), pa.array([hashlib.sha256(bpe.decode(x)).hexdigest() for x in ids])]
                else:
                    flat = np.frombuffer(b"".join(ids), "<u4").astype(np.int32)
                    made = [pa.ListArray.from_arrays(pa.array(np.concatenate([[0], counts.cumsum()]).astype(np.int32)), pa.array(flat)), pa.array([bpe.decode(x) == t.encode() for x, t in zip(ids, texts, strict=True)])]
                yield pa.RecordBatch.from_arrays([*(part.column(at[c]) for c in kept), pa.array(counts), *made], names=[*kept, *names])

    return docs.mapInArrow(work, schema)


def op1_byte_bpe(spark, sf_dir: str) -> DataFrame:
    """Ids and decoded bytes of every whole text, as digests."""
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return encode(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, digests=True, only=["doc_id"])
