"""Token ids in wavelet-matrix files: token access, counting and occurrence lookup
from one compressed file per shard.

File format, all little-endian. Header: 8 bytes magic, then unsigned 64-bit n (ids),
documents, planes. Then for each document its id (signed 64-bit) and its number of ids
(unsigned 64-bit); then for each plane, highest bit first, the number of zero bits
(unsigned 64-bit) and the byte length of its rank directory and bits, both zstandard
compressed. A plane holds one bit of every id; behind it the ids are
reordered, those with a zero bit first, both groups in their old order. The rank directory
holds the number of ones before every 512 bits (unsigned 32-bit).

Documents are written in ascending order of (doc_id, text): one range shuffle, a
sort within each range, and shards of at most `SHARD` ids cut from it (a longer
document is a shard alone). The shards are
rows (range, number, one file image) of a table that Spark commits to the shared
folder, so lost tasks and executors leave no partial file and any store that Spark
can write will do; `export` writes the images as plain files.

Defined results: a null text is an empty one, with the end id alone; null doc_ids
come first and are written as the smallest 64-bit integer; repeated rows are all written.
"""

from __future__ import annotations

import os
import struct
import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache
from itertools import compress, pairwise
from string import punctuation

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.llm.common import releasing, runs, shared_folder, table

MAGIC = b"WAVELET1"
BLOCK = 512
SHARD = 1 << 21
NULL_ID = -(2**63)
END_ID = 2
CACHE = 600_000  # words, about 170 bytes each
BATCH_CHARS = 4_000_000


class WaveletMatrix:
    """Bit planes with rank and select over a sequence of unsigned ids."""

    def __init__(self, n: int, zeros: list[int], planes: list[np.ndarray], ranks: list[np.ndarray]) -> None:
        self.n, self.zeros, self.planes, self.ranks = n, zeros, planes, ranks

    @classmethod
    def build(cls, ids: np.ndarray) -> WaveletMatrix:
        n, depth = len(ids), int(ids.max(initial=0)).bit_length()
        ids = ids.astype(np.uint16 if depth <= 16 else np.uint32)
        zeros, planes, ranks = [], [], []
        for b in range(depth - 1, -1, -1):
            bit = (ids >> b) & 1 == 1
            packed = np.packbits(bit, bitorder="little")
            padded = np.zeros(-(-max(n, 1) // BLOCK) * BLOCK // 8, np.uint8)
            padded[: len(packed)] = packed
            ones = np.bitwise_count(padded.view(np.uint64)).reshape(-1, BLOCK // 64).sum(1)
            ranks.append(np.concatenate([[0], ones.cumsum()]).astype(np.uint32))
            planes.append(padded)
            low, high = ids.take(np.flatnonzero(~bit)), ids.take(np.flatnonzero(bit))
            zeros.append(len(low))
            ids = np.concatenate([low, high])
        return cls(n, zeros, planes, ranks)

    def _bit(self, level: int, i: int) -> int:
        return int(self.planes[level][i >> 3] >> (i & 7)) & 1

    def _ones(self, level: int, i: int) -> int:
        """Ones among the first i bits of a plane."""
        block, rest = divmod(i, BLOCK)
        total = int(self.ranks[level][block])
        if rest:
            part = np.unpackbits(self.planes[level][block * BLOCK // 8 : (block * BLOCK + rest + 7) // 8], bitorder="little")
            total += int(part[:rest].sum())
        return total

    def _step(self, level: int, i: int, bit: int) -> int:
        ones = self._ones(level, i)
        return self.zeros[level] + ones if bit else i - ones

    def access(self, i: int) -> int:
        """The id at position i."""
        value = 0
        for level in range(len(self.planes)):
            bit = self._bit(level, i)
            value = value << 1 | bit
            i = self._step(level, i, bit)
        return value

    def _range(self, value: int, end: int) -> tuple[int, int]:
        """Where, behind the last plane, the occurrences of value before `end` lie."""
        a, depth = 0, len(self.planes)
        if value >> depth:
            return 0, 0
        for level in range(depth):
            bit = value >> (depth - 1 - level) & 1
            a, end = self._step(level, a, bit), self._step(level, end, bit)
        return a, end

    def rank(self, value: int, end: int) -> int:
        """Occurrences of value among the first `end` ids."""
        a, b = self._range(value, end)
        return b - a

    def count(self, value: int) -> int:
        return self.rank(value, self.n)

    def select(self, value: int, k: int) -> int:
        """Position of the occurrence number k (from 0) of value."""
        a, b = self._range(value, self.n)
        if not 0 <= k < b - a:
            raise IndexError(k)
        i = a + k
        for level in range(len(self.planes) - 1, -1, -1):
            bit = value >> (len(self.planes) - 1 - level) & 1
            i = self._nth(level, bit, i - self.zeros[level] if bit else i)
        return i

    def _nth(self, level: int, bit: int, k: int) -> int:
        """Position of the k-th (from 0) bit of this kind in a plane."""
        before = self.ranks[level].astype(np.int64)
        if not bit:
            before = np.arange(len(before)) * BLOCK - before
        block = int(np.searchsorted(before, k, "right")) - 1
        bits = np.unpackbits(self.planes[level][block * BLOCK // 8 : (block + 1) * BLOCK // 8], bitorder="little")
        return block * BLOCK + int(np.nonzero(bits == bit)[0][k - int(before[block])])

    def positions(self, value: int) -> list[int]:
        """All positions of value, in order."""
        return [self.select(value, k) for k in range(self.count(value))]

    def ids(self) -> np.ndarray:
        """The whole sequence, from the last plane up."""
        depth = len(self.planes)
        out = np.zeros(self.n, np.uint16 if depth <= 16 else np.uint32)
        for level in range(depth - 1, -1, -1):
            bit = np.unpackbits(self.planes[level], count=self.n, bitorder="little").view(bool)
            z, up = self.zeros[level], np.empty_like(out)
            up[np.flatnonzero(~bit)] = out[:z]
            up[np.flatnonzero(bit)] = out[z:] | out.dtype.type(1 << (depth - 1 - level))
            out = up
        return out


def to_file(doc_ids: list[int], sizes: list[int], ids: np.ndarray) -> bytes:
    """The image of one shard's file."""
    m, pack = WaveletMatrix.build(ids), zstandard.ZstdCompressor(level=1).compress
    out = [MAGIC, struct.pack("<QQQ", m.n, len(doc_ids), len(m.planes)), np.array(doc_ids, "<i8").tobytes(), np.array(sizes, "<u8").tobytes()]
    for zeros, plane, ranks in zip(m.zeros, m.planes, m.ranks, strict=True):
        a, b = pack(ranks.astype("<u4").tobytes()), pack(plane.tobytes())
        out += [struct.pack("<QQQ", zeros, len(a), len(b)), a, b]
    return b"".join(out)


def from_file(image: bytes) -> tuple[np.ndarray, np.ndarray, WaveletMatrix]:
    """Document ids, numbers of ids and the ids of one shard."""
    if image[:8] != MAGIC:
        raise ValueError("not a wavelet-matrix file")
    n, docs, depth = struct.unpack_from("<QQQ", image, 8)
    at, unpack = 32 + 16 * docs, zstandard.ZstdDecompressor().decompress
    doc_ids, sizes = np.frombuffer(image, "<i8", docs, 32), np.frombuffer(image, "<u8", docs, 32 + 8 * docs)
    zeros, planes, ranks = [], [], []
    for _ in range(depth):
        z, a, b = struct.unpack_from("<QQQ", image, at)
        at += 24
        zeros.append(z)
        ranks.append(np.frombuffer(unpack(image[at : at + a]), "<u4"))
        planes.append(np.frombuffer(unpack(image[at + a : at + a + b]), np.uint8))
        at += a + b
    return doc_ids, sizes, WaveletMatrix(n, zeros, planes, ranks)


class CachedTokenizer:
    """A tokenizers-library file whose ids never depend on text across a blank or line break.

    Such a tokenizer drops white space before anything else, so a text's ids are its
    words' ids in a row, and each distinct word of a batch is encoded once. Where the file also
    lower-cases, and sets ASCII punctuation apart from letters, forms that differ in these
    alone share one encoding. Where its tokens mark word ends, words made of letters are encoded
    many in a string, which costs half, and cut at those marks. At `CACHE` words the
    cache starts anew, and takes what is still used from the one before.
    """

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings in a text are ordinary text
        self.cache: dict[str, bytes] = {"": b""}
        self.old: dict[str, bytes] = {}
        vocabulary = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocabulary.values(), default=0) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        lower, upper, whole, stem, tail = self._each(["qzé", "QzÉ", "ab'.-", "ab", "'.-"])
        self.lowers, self.splits = lower == upper, whole == stem + tail

    def _each(self, words: list[str]) -> list[bytes]:
        return [array("I", x.ids).tobytes() for x in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]

    def _strung(self, words: list[str]) -> list[bytes]:
        """_each for words of letters only."""
        out: list[bytes] = []
        for k in range(0, len(words), 500):
            some = words[k : k + 500]
            ids = np.array(self.tokenizer.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids, "<u4")
            ends = np.flatnonzero(self.ends[ids]) + 1
            if len(ends) != len(some) or ends[-1] != len(ids):
                out += self._each(some)
                continue
            raw, at = ids.tobytes(), [0, *(4 * ends).tolist()]
            out += [raw[a:b] for a, b in pairwise(at)]
        return out

    def _learn(self, words: list[str]) -> None:
        cache, old = self.cache, self.old
        if old:
            cache.update((w, old[w]) for w in words if w in old)
            words = [w for w in words if w not in cache]
        # "Σ" has two lower cases, by its place in the word
        low = [w.lower() if "Σ" not in w else w for w in words] if self.lowers else words
        stems = [x.rstrip(punctuation) for x in low] if self.splits else low
        letters = list(map(str.isalpha, stems))
        cut = [(w, stem, x[len(stem) :]) for w, x, stem, yes in zip(words, low, stems, letters, strict=True) if yes and stem != w]
        other = {w for w, yes in zip(words, letters, strict=True) if not yes}.union(tail for _, _, tail in cut).difference(cache)
        plain = list(set(compress(stems, letters)).difference(cache))
        cache.update(zip(plain, self._strung(plain), strict=True))
        cache.update(zip(other, self._each(list(other)), strict=True))
        cache.update((w, cache[stem] + cache[tail]) for w, stem, tail in cut)

    def encode(self, texts: list[str] | pa.Array) -> list[bytes]:
        """The ids of each text (none of them null), as little-endian unsigned 32-bit integers.

        Arrow splits the texts, finds the distinct words and puts their ids in the texts' order, so Python sees each distinct word once.
        """
        if len(self.cache) > CACHE:
            self.cache, self.old = {"": b""}, self.cache
        cells = pc.split_pattern(pc.replace_substring(pa.array(texts, pa.large_string()) if isinstance(texts, list) else texts.cast(pa.large_string()), "\n", " "), " ")
        coded = cells.flatten().dictionary_encode()
        if not len(coded):
            return [b""] * len(texts)
        # words hold no blank, so one string carries them all to Python
        words = pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(coded.dictionary)], pa.int32()), coded.dictionary.cast(pa.string())), " ")[0].as_py().split(" ")
        found = list(map(self.cache.get, words))
        if unknown := [w for w, x in zip(words, found, strict=True) if x is None]:
            self._learn(unknown)
            found = [self.cache[w] if x is None else x for w, x in zip(words, found, strict=True)]
        ends = np.cumsum([0, *map(len, found)], dtype="<i8")
        ids = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(words), [None, pa.py_buffer(ends), pa.py_buffer(b"".join(found))]).take(coded.indices)
        _, starts, data = ids.buffers()
        # flatten() begins at the first text's first word, wherever its slice begins
        at = np.frombuffer(starts, "<i8", len(ids) + 1)[cells.offsets.to_numpy() - cells.offsets[0].as_py()].tolist()
        raw = memoryview(data or b"")
        return [bytes(raw[a:b]) for a, b in pairwise(at)]


@lru_cache(maxsize=2)
def tokenizer(path: str) -> CachedTokenizer:
    return CachedTokenizer(path)


def write_shards(docs: DataFrame, path: str, folder: str, *, end_id: int = END_ID, shard: int = SHARD) -> DataFrame:
    """Encode docs (doc_id, text) by the tokenizer at `path` and write the shards into `folder`.

    Returns the table read back: range, number, n_docs, n_tokens, image.
    """
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    end = np.array([end_id], "<u4").tobytes()

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, part = tokenizer(path), TaskContext.get().partitionId()
        held: list[tuple[int, bytes]] = []
        total = number = 0

        def flush() -> pa.RecordBatch:
            nonlocal held, total, number
            image = to_file([d for d, _ in held], [len(x) // 4 for _, x in held], np.frombuffer(b"".join(x for _, x in held), "<u4"))
            row = pa.RecordBatch.from_pydict({"range": pa.array([part], pa.int32()), "number": pa.array([number], pa.int32()), "n_docs": pa.array([len(held)], pa.int64()), "n_tokens": pa.array([total], pa.int64()), "image": pa.array([image], pa.binary())})
            held, total, number = [], 0, number + 1
            return row

        for batch in batches:
            sizes = pc.fill_null(pc.binary_length(batch.column(1)), 0).to_numpy(zero_copy_only=False)
            for a, b in runs(sizes, BATCH_CHARS):
                piece = batch.slice(a, b - a)
                for d, x in zip(piece.column(0).to_pylist(), tok.encode(pc.fill_null(piece.column(1), "")), strict=True):
                    n = len(x) // 4 + 1
                    if held and total + n > shard:
                        yield flush()
                    held.append((NULL_ID if d is None else d, x + end))
                    total += n
        if held:
            yield flush()

    out = ordered.mapInArrow(work, "range int, number int, n_docs bigint, n_tokens bigint, image binary")
    out.write.option("compression", "uncompressed").parquet(folder)
    return docs.sparkSession.read.parquet(folder)


def starts(shards: DataFrame) -> DataFrame:
    """range, number, start: the number of ids in all earlier shards."""
    sizes = shards.select("range", "number", "n_tokens")
    whole = sizes.groupBy("range").agg(F.sum("n_tokens").alias("n"))  # a row per range: as many as that shuffle had partitions
    base = whole.select("range", (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("base"))
    inside = F.sum("n_tokens").over(Window.partitionBy("range").orderBy("number")) - F.col("n_tokens")
    return sizes.withColumn("inside", inside).join(base, "range").select("range", "number", (F.col("base") + F.col("inside")).alias("start"))


def read_documents(shards: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, read from the file images."""
    rows = shards.select("range", "number", "image").join(F.broadcast(starts(shards)) if shards.count() <= 1_000_000 else starts(shards), ["range", "number"]).select("start", "image")

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                start, image = batch.column(0)[k].as_py(), batch.column(1)[k].as_py()
                doc_ids, sizes, matrix = from_file(image)
                raw = memoryview(matrix.ids().astype("<u4").tobytes())
                ends = sizes.astype(np.int64).cumsum()
                begins = ends - sizes.astype(np.int64)
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(begins.tolist(), ends.tolist(), strict=True)]
                yield pa.RecordBatch.from_pydict({"doc_id": pa.array(doc_ids, pa.int64(), mask=doc_ids == NULL_ID), "start": pa.array(begins + start), "n_tokens": pa.array(sizes.astype(np.int64)), "ids_crc32": pa.array(crc, pa.int64())})

    return rows.mapInArrow(work, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def export(shards: DataFrame, folder: str) -> DataFrame:
    """Write every image as a plain file into a folder that all workers share; returns their paths.

    A file appears under its name only when complete, so repeated tasks do no harm.
    """

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.makedirs(folder, exist_ok=True)
        for batch in batches:
            for r in batch.to_pylist():
                path = f"{folder}/{r['range']:06d}-{r['number']:06d}.wm"
                part = f"{path}.{os.getpid()}"
                with open(part, "wb") as f:
                    f.write(r["image"])
                os.replace(part, path)
                yield pa.RecordBatch.from_pydict({"path": [path]})

    return shards.select("range", "number", "image").mapInArrow(work, "path string")


def op9_wavelet_ids(spark, sf_dir: str) -> DataFrame:
    """Every document's ids, written to and read back from wavelet-matrix files."""
    import public_tokenizers

    shards = write_shards(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), shared_folder(spark, "wavelet"))
    return read_documents(shards)
