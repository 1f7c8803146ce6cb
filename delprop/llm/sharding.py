"""Shards of near equal bytes by sampled splitters.

The sort key of a row is (hash of its text, doc_id), so equal texts lie side
by side.  A sample in which a row's chance is proportional to its size gives
the splitters: its quantiles cut the key space into many more ranges than
shards.  Ranges that turn out overfull are cut again from a denser sample of
their own rows.  A splitter that falls among equal texts moves to the first of
them; only a text whose copies overfill several ranges is cut between copies.
The exact bytes of the ranges (a bounded number of rows on the driver) then
go to the shards, largest first, each to the shard with the fewest bytes.
Ranges of one over-long run of copies stay together while the run fits a
shard.  Rows never move with their texts: only (key, size, checksum) is
shuffled.

Law: ``bytes``.  Sizes differ by at most about one range.

Edge cases: a null text counts as empty (size 16, checksum of nothing); rows
with null ids sort first, by a number of their own, so a run of copies without
ids is cut like any other (rows equal in text and id stay in one range); repeated rows are rows of their own; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from delprop.llm.common import map_arrow, materialise, unsigned_crc32

LOW = -(1 << 63)
#: Rounds of subdivision at most; each cuts every overfull range into near equal parts.
TURNS = 8


def _ranges(keys: np.ndarray, ids: np.ndarray, splitters: np.ndarray) -> np.ndarray:
    """Number of splitters at or below each (key, id); ``splitters`` is sorted, with fields k and d."""
    left = np.searchsorted(splitters["k"], keys, "left")
    out = np.searchsorted(splitters["k"], keys, "right")
    tied = np.flatnonzero(left < out)
    # keys that are splitters themselves also need the id; a key with several splitters is a large group of equal texts
    for key in np.unique(keys[tied]).tolist():
        rows = tied[keys[tied] == key]
        a, b = left[rows[0]], out[rows[0]]
        out[rows] = a + np.searchsorted(splitters["d"][a:b], ids[rows], "right")
    return out


def _with_range(rows: DataFrame, splitters: np.ndarray) -> DataFrame:
    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        keys = batch.column("k").to_numpy(zero_copy_only=False)
        ids = batch.column("d").to_numpy(zero_copy_only=False)
        return batch.append_column("range", pa.array(_ranges(keys, ids, splitters).astype(np.int32)))

    return map_arrow(rows, kernel, "doc_id long, size long, text_crc32 long, k long, d long, range int")


def _splitters(sample: list[tuple[int, int]], count: int) -> set[tuple[int, int]]:
    """Quantiles of a sorted sample; the first that falls on a text's copies moves to the first copy."""
    picked = sorted({sample[len(sample) * i // count] for i in range(1, count)}) if sample else []
    seen: set[int] = set()
    out = set()
    for k, d in picked:
        out.add((k, d if k in seen else LOW))
        seen.add(k)
    return out


def _array(splitters: set[tuple[int, int]]) -> np.ndarray:
    return np.array(sorted(splitters), dtype=[("k", np.int64), ("d", np.int64)])


def shard(documents: DataFrame, shards: int = 40, ranges_per_shard: int = 64, oversample: int = 12, rows_per_range: int = 1 << 20) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) for every row of ``documents``.

    There are ``ranges_per_shard`` ranges a shard, more where a range would
    hold over ``rows_per_range`` rows; the driver holds ``oversample`` keys a
    range, whatever the input.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = documents.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text) + 16).cast("long").alias("size"),
        unsigned_crc32(text).alias("text_crc32"),
        F.xxhash64(text).alias("k"),
        # the numbers are fixed by the table below
        F.coalesce(F.col("doc_id").cast("long"), F.lit(LOW + 1) + F.monotonically_increasing_id()).alias("d"),
    )
    rows = materialise(rows, "shard-keys")
    total, n = rows.agg(F.sum("size"), F.count("*")).first()
    total = total or 0
    ranges = max(shards * ranges_per_shard, math.ceil(n / rows_per_range))
    target = max(1, total // ranges)

    def sampled(frame: DataFrame, step: int, salt: str) -> list[tuple[int, int]]:
        """Each row is drawn size / step times on average."""
        luck = F.pmod(F.xxhash64(F.lit(salt), "k", "d"), F.lit(step))
        times = F.floor(F.col("size") / step) + F.when(luck < F.pmod("size", F.lit(step)), 1).otherwise(0)
        drawn = frame.withColumn("times", times).where("times > 0").select("k", "d", "times").collect()
        return sorted(key for r in drawn for key in [(r.k, r.d)] * r.times)

    cuts = _splitters(sampled(rows, max(1, target // oversample), "first"), ranges)
    for turn in range(TURNS):
        placed = _with_range(rows, _array(cuts))
        sizes = {r["range"]: (r["bytes"], r["n"]) for r in placed.groupBy("range").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).collect()}
        overfull = {i: s for i, s in sizes.items() if s[0] > 1.5 * target and s[1] > 1}
        if not overfull or turn == TURNS - 1:
            break
        before = len(cuts)
        dense = sampled(placed.where(F.col("range").isin(list(overfull))), max(1, target // (4 * oversample)), f"again{turn}")
        own = _array(cuts)
        keys = np.array([k for k, _ in dense], np.int64)
        at = _ranges(keys, np.array([d for _, d in dense], np.int64), own) if len(dense) else keys
        held = {k for k, _ in cuts}
        for i, s in overfull.items():
            part = [dense[j] for j in np.flatnonzero(at == i).tolist()]
            for k, d in _splitters(part, math.ceil(s[0] / target)):
                # a run of copies that already starts a range is cut between copies
                copies = [e for q, e in part if q == k] if d == LOW and k in held else []
                cuts.add((k, copies[len(copies) // 2] if copies else d))
        if len(cuts) == before:  # what is left overfull holds rows of one key
            break
    where = _assign(_array(cuts), sizes, shards)
    layout = documents.sparkSession.createDataFrame([(int(i), *w) for i, w in where.items()] or [], "range int, shard int, base long")
    turn_of = F.row_number().over(Window.partitionBy("range").orderBy("k", "d", "size")) - 1
    # one row a range: bounded by the number of splitters, which the driver holds anyway
    return (
        placed.withColumn("turn", turn_of)
        .join(F.broadcast(layout), "range")
        .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("base") + F.col("turn")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
    )


def _assign(splitters: np.ndarray, sizes: dict[int, tuple[int, int]], shards: int) -> dict[int, tuple[int, int]]:
    """range -> (shard, first slot): largest first, each to the emptiest shard; ranges of one run of copies go together while they fit."""
    fair = sum(b for b, _ in sizes.values()) / shards
    bundles: list[list[int]] = []
    for i in sorted(sizes):
        # range i starts at splitter i - 1: within a run of copies if that splitter has an id
        joined = i and splitters["d"][i - 1] != LOW and bundles and bundles[-1][-1] == i - 1
        if joined and sum(sizes[j][0] for j in bundles[-1]) + sizes[i][0] <= fair:
            bundles[-1].append(i)
        else:
            bundles.append([i])
    heap = [(0, s) for s in range(shards)]
    rows = [0] * shards
    where: dict[int, tuple[int, int]] = {}
    for bundle in sorted(bundles, key=lambda b: (-sum(sizes[j][0] for j in b), b[0])):
        load, s = heapq.heappop(heap)
        for i in bundle:
            where[i] = (s, rows[s])
            rows[s] += sizes[i][1]
            load += sizes[i][0]
        heapq.heappush(heap, (load, s))
    return where
