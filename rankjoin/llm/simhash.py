"""SimHash near-duplicates through deletion-variant signatures.

A 64-bit fingerprint is cut into two segments of 32 bits. Of two fingerprints that
differ in 2 bits or fewer, one segment differs in one bit at most, so the two share
that segment with one of its bits deleted. Each distinct fingerprint is indexed under
its 64 one-wildcard variants, equal variants meet, and pairs are verified.

A variant shared by more than `BUCKET` fingerprints is not paired. Its members are cut
into 16 segments of 4 bits instead and indexed under the 120 variants with two segments
deleted: two differing bits lie in two segments at most, so no link is lost, and
as the fingerprints are distinct, 2^8 of them at most can share such a variant.
Copies meet as one fingerprint before any of this.

Words are the runs of characters other than white space after A-Z are
lower-cased; a text of fewer words than a shingle is one shingle, a text without words has
fingerprint zero. Null texts are empty. Null doc_ids take part; a group with no other id
has a null component. Rows with equal doc_ids are fingerprinted one by one.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from rankjoin.llm.common import releasing, runs, table, written
from rankjoin.llm.components import components

BITS = 2
SEED = 42
BUCKET = 32
BATCH_BYTES = 2_000_000


def hashes(text: bytes, size: int) -> list[int]:
    """XXH64 of every shingle of a text, repeats included."""
    words = text.lower().split()  # bytes: lowers A-Z and splits at ASCII white space only
    if not words:
        return []
    joined = b" ".join(words)
    if len(words) < size:
        return [xxhash.xxh64_intdigest(joined, SEED)]
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    begins = np.concatenate([[0], ends[:-1]])
    return list(map(xxhash.xxh64_intdigest, [joined[a:b] for a, b in zip(begins[: len(words) - size + 1].tolist(), (ends[size - 1 :] - 1).tolist(), strict=True)], repeat(SEED)))


def majority(each: list[list[int]]) -> np.ndarray:
    """Fingerprints: a bit is 1 if it is set in over half of a text's hashes."""
    sizes = np.array([len(x) for x in each], np.int64)
    out = np.zeros(len(each), np.uint64)
    if not (full := sizes > 0).any():
        return out
    flat = np.fromiter((h for x in each for h in x), np.uint64, int(sizes.sum()))
    bits = np.unpackbits(flat.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    starts = np.concatenate([[0], sizes[full].cumsum()[:-1]])
    counts = np.add.reduceat(bits, starts, axis=0, dtype=np.int32)
    set_ = 2 * counts > sizes[full][:, None]
    out[full] = np.packbits(set_, axis=1, bitorder="little").view(np.uint64)[:, 0]
    return out


def fingerprints(docs: DataFrame, *, size: int, into: str = "fp") -> DataFrame:
    """doc_id and the fingerprint, as a signed 64-bit integer."""

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = batch.column(1).cast(pa.binary())
            lengths = pc.fill_null(pc.binary_length(text), 0).to_numpy(zero_copy_only=False)
            for a, b in runs(lengths, BATCH_BYTES):
                fp = majority([hashes(x or b"", size) for x in text.slice(a, b - a).to_pylist()])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(fp.view(np.int64))], names=["doc_id", into])

    schema = T.StructType([docs.schema["doc_id"], T.StructField(into, T.LongType(), False)])
    return docs.select("doc_id", "text").mapInArrow(work, schema)


def _pairs(buckets: DataFrame, *key: str) -> DataFrame:
    """Verified pairs (u < v) within each bucket; buckets are small by construction."""
    sets = buckets.groupBy(*key).agg(F.sort_array(F.collect_list("fp")).alias("fps")).select("fps", F.explode("fps").alias("u"))
    near = F.filter("fps", lambda v: (v > F.col("u")) & (F.bit_count(v.bitwiseXOR(F.col("u"))) <= BITS))
    return sets.select("u", F.explode(near).alias("v"))


def near_links(fps: DataFrame) -> DataFrame:
    """All pairs of distinct fingerprints (column fp) that differ in BITS bits or fewer."""
    i = F.col("i")
    segment = F.expr("shiftrightunsigned(fp, if(i < 32, 0, 32)) & 4294967295 & ~shiftleft(1L, i % 32)")
    keyed = fps.select("fp").distinct().select("fp", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("i")).select("fp", F.shiftleft(i.cast("long"), 32).bitwiseOR(segment).alias("k"))
    met = written(keyed.withColumn("n", F.count("*").over(Window.partitionBy("k"))).where("n > 1"), "variants")
    light = _pairs(met.where(F.col("n") <= BUCKET), "k")
    heavy = met.where(F.col("n") > BUCKET).select("fp").distinct()
    cuts = [(a, b) for a in range(16) for b in range(a)]
    masks = F.array(*(F.lit(_signed(~(15 << 4 * a | 15 << 4 * b))) for a, b in cuts))
    wide = heavy.select("fp", F.posexplode(masks).alias("cut", "mask")).select("fp", "cut", F.col("fp").bitwiseAND(F.col("mask")).alias("rest"))
    return light.union(_pairs(wide, "cut", "rest")).distinct()


def _signed(x: int) -> int:
    x &= 2**64 - 1
    return x - 2**64 if x >> 63 else x


def near_duplicates(docs: DataFrame, *, size: int) -> DataFrame:
    """doc_id, fp, component_id of every row of docs (doc_id, text)."""
    prints = written(fingerprints(docs, size=size), "fingerprints")
    least = prints.groupBy("fp").agg(F.min("doc_id").alias("low"))
    roots = components(near_links(prints.select("fp")))
    named = least.join(roots, F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root"), "low")
    groups = named.groupBy("root").agg(F.min("low").alias("component_id"), F.count("*").alias("n"))
    label = named.join(groups, "root").select(F.col("fp").alias("_fp"), "component_id")
    return prints.join(label, F.col("fp") == F.col("_fp")).select("doc_id", "fp", "component_id")


def hex_of(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def keep_one(docs: DataFrame, *, size: int) -> DataFrame:
    """One row of each group of near-duplicates (see near.keep_one, which takes fingerprints from here)."""
    from rankjoin.llm.near import keep_one

    return keep_one(docs, size=size)


def op6_simhash(spark, sf_dir: str) -> DataFrame:
    """Fingerprint and component of every document, over shingles of three words."""
    out = near_duplicates(table(spark, sf_dir, "documents"), size=3)
    return out.select("doc_id", hex_of(F.col("fp")).alias("fingerprint"), "component_id")
