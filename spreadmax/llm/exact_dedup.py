"""Exact duplicates through counting quotient filters.

Every partition builds a counting quotient filter of its text fingerprints, cut
into blocks of quotients. Filters of one block merge without loss: both hold
their (quotient, remainder) pairs in order, so a merge interleaves the sorted
remainders and adds the counters. Fingerprints whose merged counter exceeds one
route their documents to a comparison of the whole texts; all other documents
are unique without having moved.

Defined cases: a null text counts as the empty text; rows with equal texts form
one group, whose largest doc_id stays (null ids stay only where the whole group
has none); rows that repeat a doc_id within a group are one document, so they
are kept or dropped together; an empty table gives an empty result; further
columns of the input are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadmax.session import written

#: Merged filters hold about this many fingerprints a block.
BLOCK_ROWS = 1 << 20
#: Fingerprints that a filter under construction collects before they are sorted in, at least.
FOLD_ROWS = 1 << 16
#: Classes of equal texts up to this number are broadcast (about 130 bytes each); more are joined by a salted shuffle.
BROADCAST_ROWS = 200_000
#: Rows of one group that go to one task in the salted join.
SALT_ROWS = 16_384


class QuotientFilter:
    """A block of a counting quotient filter in serial form.

    occupied: a bit for each quotient that has a run; ends: a bit for each
    remainder that closes its run; remainders in order, `width` bytes each;
    counters beside them.
    """

    def __init__(self, remainder_bits: int, local_bits: int):
        self.remainder_bits, self.local_bits = remainder_bits, local_bits
        self.width = -(-remainder_bits // 8)

    def encode(self, keys: np.ndarray, counts: np.ndarray) -> bytes:
        """keys: sorted distinct uint64 below 2**(local_bits + remainder_bits)."""
        quotients = (keys >> np.uint64(self.remainder_bits)).astype(np.int64)
        remainders = keys & np.uint64((1 << self.remainder_bits) - 1)
        occupied = np.zeros(1 << self.local_bits, np.uint8)
        occupied[quotients] = 1
        ends = np.ones(len(keys), np.uint8)
        ends[:-1] = quotients[1:] != quotients[:-1]
        body = remainders.astype("<u8").view(np.uint8).reshape(-1, 8)[:, : self.width]
        head = np.array([len(keys)], "<u8").tobytes()
        return b"".join(
            (head, np.packbits(occupied).tobytes(), np.packbits(ends).tobytes(), body.tobytes(), counts.astype("<u8").tobytes())
        )

    def decode(self, data: bytes) -> tuple[np.ndarray, np.ndarray]:
        n = int(np.frombuffer(data, "<u8", 1)[0])
        at = 8
        size = max(1, (1 << self.local_bits) // 8)
        occupied = np.unpackbits(np.frombuffer(data, np.uint8, size, at))[: 1 << self.local_bits]
        at += size
        size = -(-n // 8)
        ends = np.unpackbits(np.frombuffer(data, np.uint8, size, at))[:n]
        at += size
        body = np.zeros((n, 8), np.uint8)
        body[:, : self.width] = np.frombuffer(data, np.uint8, n * self.width, at).reshape(n, self.width)
        at += n * self.width
        counts = np.frombuffer(data, "<u8", n, at)
        run = np.cumsum(np.concatenate(([0], ends[:-1]))).astype(np.int64)
        quotients = np.flatnonzero(occupied).astype(np.uint64)[run]
        return (quotients << np.uint64(self.remainder_bits)) | body.view("<u8").reshape(-1), counts

    def merge(self, parts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The multiset union, again in order."""
        decoded = [self.decode(p) for p in parts]
        return _summed(np.concatenate([k for k, _ in decoded]), np.concatenate([c for _, c in decoded]))


def _summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[first], np.add.reduceat(counts, first)


def repeated_fingerprints(docs: DataFrame, fp: str = "fp", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(fp long) -> (fp, copies): fingerprints that more than one row has."""
    rows = docs.count()
    quotient_bits = max(12, math.ceil(math.log2(max(rows, 2))))
    block_bits = max(6, math.ceil(math.log2(max(rows, 2) / block_rows)))
    local_bits = min(20, max(3, quotient_bits - block_bits))
    codec = QuotientFilter(64 - block_bits - local_bits, local_bits)
    cut, low = np.uint64(64 - block_bits), np.uint64((1 << (64 - block_bits)) - 1)

    def build(batches):
        keys, counts = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
        held, size = [], 0

        def folded():
            new = np.concatenate(held) if held else np.zeros(0, np.uint64)
            return _summed(np.concatenate((keys, new)), np.concatenate((counts, np.ones(len(new), np.uint64)))) if len(new) else (keys, counts)

        for batch in batches:
            held.append(batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64))
            size += len(held[-1])
            if size > max(len(keys), FOLD_ROWS):  # sorted again only when the keys have doubled
                keys, counts = folded()
                held, size = [], 0
        keys, counts = folded()
        blocks = (keys >> cut).astype(np.int64)
        starts = np.flatnonzero(np.concatenate(([True], blocks[1:] != blocks[:-1]))) if len(keys) else np.zeros(0, int)
        for a, b in zip(starts, [*starts[1:], len(keys)], strict=True):
            yield pa.RecordBatch.from_arrays(
                [pa.array([int(blocks[a])], pa.int64()), pa.array([codec.encode(keys[a:b] & low, counts[a:b])], pa.binary())],
                names=["block", "part"],
            )

    def merge(key, group: pd.DataFrame) -> pd.DataFrame:
        keys, counts = codec.merge(list(group["part"]))
        many = counts > 1
        whole = keys[many] | (np.uint64(key[0]) << cut)
        return pd.DataFrame({"fp": whole.view(np.int64), "copies": counts[many].astype(np.int64)})

    parts = docs.select(F.col(fp).alias("fp")).mapInArrow(build, "block long, part binary")
    return parts.groupBy("block").applyInPandas(merge, "fp long, copies long")


def exact_dedup(docs: DataFrame, broadcast_rows: int = BROADCAST_ROWS, salt_rows: int = SALT_ROWS) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    base = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text")
    ).withColumn("fp", F.xxhash64("text"))
    repeated = written(repeated_fingerprints(base.select("fp")), "fingerprints")
    small = repeated.count() <= broadcast_rows
    near = F.broadcast if small else (lambda df: df.hint("merge"))
    # The whole texts of one fingerprint meet here: equal bytes give one class.
    classes = (
        base.join(near(repeated), "fp")
        .groupBy("fp", "copies", "text")
        .agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        .select("fp", "copies", F.sha2("text", 256).alias("text_sha256"), "keep_id", "group_size")
    )
    classes = written(classes, "classes")
    if small:
        out = _narrow(base).join(near(classes.drop("copies")), ["fp", "text_sha256"], "left")
    else:
        salts = F.greatest(F.lit(1), F.ceil(F.col("copies") / salt_rows)).cast("int")
        known = _narrow(base).join(repeated.hint("merge"), "fp", "left").withColumn(
            "salt", F.pmod(F.xxhash64("doc_id"), F.coalesce(salts, F.lit(1))).cast("int")
        )
        spread = classes.withColumn("salt", F.explode(F.sequence(F.lit(0), salts - 1))).drop("copies")
        out = known.join(spread, ["fp", "text_sha256", "salt"], "left")
    alone = F.col("group_size").isNull()
    keep = F.when(alone, F.col("doc_id")).otherwise(F.col("keep_id"))
    return out.select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        F.when(alone, True).otherwise(F.col("doc_id").eqNullSafe(F.col("keep_id"))).alias("kept"),
        "text_sha256",
    )


def _narrow(base: DataFrame) -> DataFrame:
    return base.select("doc_id", "fp", F.sha2("text", 256).alias("text_sha256"))
