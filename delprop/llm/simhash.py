"""Near-duplicate detection with 64-bit fingerprints and pigeonhole blocks.

Two fingerprints at Hamming distance <= ``radius`` agree on at least
``blocks - radius`` of ``blocks`` bit blocks.  Every choice of that many
blocks gives one bucket key, so each close pair meets in some bucket and is
then verified exactly.  Buckets are pre-counted: buckets of at most
``bucket_bound`` distinct fingerprints are verified side by side with
vectorised population counts and give a spanning forest, never all pairs.
Members of larger buckets go another, still exact and linear way: every
fingerprint is spread to all words within ``radius / 2`` flipped bits; two
fingerprints are linked iff they share such a word, and everything that meets
in one word is linked to its smallest member.  Distinct fingerprints are the
graph's nodes, so a group of equal texts costs one node.

Edge cases: null or blank text has fingerprint zero and is linked like any
other; a null doc_id gets its component's smallest id (null if there is none);
repeated rows stay rows (:func:`deduplicate` keeps one of them, and drops no
row for having no id or an id that repeats); extra columns are ignored; an empty table gives an
empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from delprop.llm.common import map_arrow, materialise, union_all

NO_ID = (1 << 63) - 1
SEED = 42
#: Nodes that a task holds while it contracts edges.
FOREST = 1 << 18


def fingerprint(text: str | None, words: int = 4) -> int:
    """Majority bits of the XXH64 of every run of ``words`` words (ASCII lower-cased), repeats included."""
    tokens = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not tokens:
        return 0
    joined = b" ".join(tokens)
    if len(tokens) <= words:
        return xxhash.xxh64_intdigest(joined, SEED)
    lengths = np.fromiter(map(len, tokens), np.int64, len(tokens))
    ends = np.cumsum(lengths + 1) - 1
    starts = (ends - lengths)[: len(tokens) - words + 1].tolist()
    digest = xxhash.xxh64_digest
    hashes = b"".join([digest(joined[a:b], SEED) for a, b in zip(starts, ends[words - 1 :].tolist(), strict=True)])
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 19):
        part = np.unpackbits(np.frombuffer(hashes[at : at + (1 << 19)], np.uint8)).reshape(-1, 64)
        counts += part.sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(counts * 2 > len(starts)).tobytes(), "big")


def fingerprints(documents: DataFrame, words: int = 4) -> DataFrame:
    """(doc_id, fp): one row per row of ``documents``; fp is the fingerprint as a signed long."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        values = [fingerprint(x, words) for x in batch.column("text").to_pylist()]
        signed = np.array(values, np.uint64).view(np.int64)
        return pa.record_batch([batch.column("doc_id").cast(pa.int64()), pa.array(signed)], ["doc_id", "fp"])

    return map_arrow(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), kernel, "doc_id long, fp long")


def block_masks(blocks: int, radius: int) -> list[int]:
    """One mask per choice of ``blocks - radius`` of the blocks of a 64-bit word, as signed longs."""
    cuts = [64 * k // blocks for k in range(blocks + 1)]
    parts = [((1 << (b - a)) - 1) << a for a, b in zip(cuts, cuts[1:], strict=False)]
    masks = [sum(chosen) for chosen in combinations(parts, blocks - radius)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def blocks_for(nodes: int, radius: int) -> int:
    """Fewest blocks whose agreed bits outnumber log2 of the nodes by two, so random buckets stay small at any size."""
    need = max(18, nodes.bit_length() + 2)
    for blocks in range(radius + 1, 17):
        if 64 * (blocks - radius) // blocks >= need:
            return blocks
    return 16


def forest(fps: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Spanning forest edges (member, smaller root) of the graph of close pairs among ``fps`` (unsigned)."""
    fps = np.unique(fps)
    n = len(fps)
    left, root = np.ones(n, bool), np.arange(n)
    for start in range(n):
        if not left[start]:
            continue
        left[start] = False
        front = np.array([start])
        while len(front) and left.any():
            rest = np.flatnonzero(left)
            near = np.zeros(len(rest), bool)
            for at in range(0, len(front), 256):
                near |= (np.bitwise_count(fps[rest][None, :] ^ fps[front[at : at + 256]][:, None]) <= radius).any(0)
            front = rest[near]
            left[front] = False
            root[front] = start
    return [(int(fps[i]), int(fps[r])) for i, r in enumerate(root) if i != r]


def _forests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges (a, b) of a task contracted, ``FOREST`` nodes at a time, to forests (member, smaller root)."""
    parent: dict[int, int] = {}

    def find(x: int) -> int:
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = parent[up]
            x = up
        return x

    def forest() -> Iterator[pa.RecordBatch]:
        out = [(x, r) for x in list(parent) if (r := find(x)) != x]
        parent.clear()
        if out:
            yield pa.record_batch([pa.array([x for x, _ in out], pa.int64()), pa.array([r for _, r in out], pa.int64())], ["a", "b"])

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            ra, rb = find(a), find(b)
            if ra != rb:
                parent[max(ra, rb)] = min(ra, rb)
        if len(parent) >= FOREST:
            yield from forest()
    yield from forest()


def _verify_buckets(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def edges(keys: np.ndarray, fps: np.ndarray) -> pa.RecordBatch | None:
            cuts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1], True])
            sizes = np.diff(cuts)
            found: list[tuple[int, int]] = []
            pairs = cuts[:-1][sizes == 2]
            close = np.bitwise_count(fps[pairs] ^ fps[pairs + 1]) <= radius
            for i in pairs[close].tolist():
                found.append((int(fps[i]), int(fps[i + 1])))
            for a, size in zip(cuts[:-1][sizes > 2].tolist(), sizes[sizes > 2].tolist(), strict=True):
                found += forest(fps[a : a + size], radius)
            if not found:
                return None
            ends = np.array(found, np.uint64).view(np.int64)
            return pa.record_batch([pa.array(ends[:, 0]), pa.array(ends[:, 1])], ["a", "b"])

        held_k, held_f = np.zeros(0, np.int64), np.zeros(0, np.uint64)
        for batch in batches:
            keys = np.r_[held_k, batch.column(0).to_numpy(zero_copy_only=False)]
            fps = np.r_[held_f, batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)]
            if not len(keys):
                continue
            cut = np.searchsorted(keys, keys[-1])
            if (out := edges(keys[:cut], fps[:cut]) if cut else None) is not None:
                yield out
            held_k, held_f = keys[cut:], fps[cut:]
        if len(held_k) and (out := edges(held_k, held_f)) is not None:
            yield out

    return run


def _flips(reach: int) -> list[int]:
    words = [sum(1 << bit for bit in chosen) for k in range(reach + 1) for chosen in combinations(range(64), k)]
    return [w - (1 << 64) if w >> 63 else w for w in words]


def close_links(nodes: DataFrame, radius: int = 4, blocks: int | None = None, bucket_bound: int = 4096) -> DataFrame:
    """(a, b): forest edges, a above b, whose connected components equal those of all pairs of ``nodes.fp`` within ``radius`` bits."""
    nodes = nodes.select("fp")
    size = nodes.count()
    masks = block_masks(blocks or blocks_for(size, radius), radius)
    keys = F.array(*[F.xxhash64(F.lit(k), F.col("fp").bitwiseAND(F.lit(mask).cast("long"))) for k, mask in enumerate(masks)])
    rows = nodes.select(F.explode(keys).alias("key"), "fp")
    large = materialise(rows.groupBy("key").count().where(F.col("count") > bucket_bound).select("key"), "large-buckets", size)
    n_large = large.count()
    cold = rows
    if n_large:
        # at most nodes * masks / bucket_bound keys; a broadcast only within a checked number of rows
        side = F.broadcast(large) if n_large <= 100_000 else large
        cold = rows.join(side, "key", "left_anti")
        hot = rows.join(side, "key", "left_semi").select("fp").distinct()
    shuffled = cold.repartition("key").sortWithinPartitions("key")
    verify = _verify_buckets(radius)
    # verified and contracted in one go: one Python worker a task
    links = [shuffled.mapInArrow(lambda batches: _forests(verify(batches)), "a long, b long")]
    if n_large:
        hot = materialise(hot, "large-bucket-members", size)
        flips = F.array(*[F.lit(w).cast("long") for w in _flips(radius // 2)])
        spread = hot.select("fp", F.explode(flips).alias("w")).select(F.col("fp").bitwiseXOR(F.col("w")).alias("meet"), "fp")
        least = spread.groupBy("meet").agg(F.min("fp").alias("b"), F.max("fp").alias("top")).where("b < top").select("meet", "b")
        links.append(spread.join(least, "meet").where("fp > b").select(F.col("fp").alias("a"), "b").mapInArrow(_forests, "a long, b long"))
    return union_all(links)


def connected(edges: DataFrame, nodes: int | None = None) -> DataFrame:
    """(node, root): the smallest node of the component for every node of ``edges``, by alternating stars.

    Every node links its larger neighbours to its smallest one, and its
    smaller ones to the smallest, until nothing changes.  ``nodes`` bounds
    their number, if known.  Each round is written to the shared
    scratch folder, so lineage stays short.
    """

    # a is always the larger end
    current = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")), "edges", None if nodes is None else 4 * nodes)
    size = current.count() if nodes is None else nodes
    salts, mark = 16, None

    def meet(links: DataFrame, least: DataFrame) -> DataFrame:
        """Join links (a, b) with one row per a; the links of a hub are dealt over salts."""
        dealt = links.withColumn("salt", F.pmod(F.xxhash64("b"), F.lit(salts)).cast("int"))
        return dealt.join(least.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))), ["a", "salt"]).drop("salt")

    while True:
        both = union_all([current, current.select(F.col("b").alias("a"), F.col("a").alias("b"))])
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = meet(both.where("b > a"), least).select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = meet(large, low).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")
        current = materialise(union_all([small, low.select("a", F.col("m").alias("b"))]).distinct(), "stars", size)
        now = current.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(now) == mark:
            return current.select(F.col("a").alias("node"), F.col("b").alias("root"))
        mark = tuple(now)


def members(documents: DataFrame, words: int = 4, radius: int = 4, bucket_bound: int = 4096) -> DataFrame:
    """(doc_id, fp, component_id, keeper) for every row of ``documents``.

    component_id is the smallest doc_id reachable, ``NO_ID`` if there is none;
    keeper is the fingerprint of the node that has it (the smallest of several).
    """
    prints = materialise(fingerprints(documents, words), "fingerprints")
    rows = prints.count()
    keyed = prints.select("fp", F.coalesce("doc_id", F.lit(NO_ID)).alias("id"))
    nodes = materialise(keyed.groupBy("fp").agg(F.min("id").alias("least"), F.count("*").alias("n")), "nodes", rows)
    roots = connected(close_links(nodes, radius, bucket_bound=bucket_bound), nodes.count())
    labelled = nodes.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "n", "least", F.coalesce("root", "fp").alias("root"))
    first = labelled.groupBy("root").agg(F.min(F.struct("least", "fp")).alias("first"))
    smallest = first.select("root", F.col("first.least").alias("component_id"), F.col("first.fp").alias("keeper"))
    owned = materialise(labelled.join(smallest, "root").select("fp", "n", "component_id", "keeper"), "labels", rows)
    # at most a thousand fingerprints can each hold over a thousandth of the rows: that side is small by proof
    heavy = F.col("n") > F.lit(max(1, rows // 1000))
    names = ["doc_id", "fp", "component_id", "keeper"]
    hot = F.broadcast(owned.where(heavy).drop("n"))
    of_hot = prints.join(hot, "fp").select(*names)
    of_rest = prints.join(hot, "fp", "left_anti").join(owned.where(~heavy).drop("n"), "fp").select(*names)
    return union_all([of_hot, of_rest])


def components(documents: DataFrame, words: int = 4, radius: int = 4, bucket_bound: int = 4096) -> DataFrame:
    """(doc_id, fp, component_id) for every row of ``documents``; component_id is the smallest doc_id reachable."""
    out = members(documents, words, radius, bucket_bound).select("doc_id", "fp", "component_id")
    return out.withColumn("component_id", F.when(F.col("component_id") != NO_ID, F.col("component_id")))


def _with_prints(rows: DataFrame, words: int) -> DataFrame:
    """``rows`` with their fingerprints as ``__fp``."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        values = np.array([fingerprint(x, words) for x in batch.column("text").to_pylist()], np.uint64).view(np.int64)
        return pa.RecordBatch.from_arrays([*batch.columns, pa.array(values)], [*batch.schema.names, "__fp"])

    return map_arrow(rows, kernel, StructType([*rows.schema.fields, StructField("__fp", LongType())]))


def deduplicate(documents: DataFrame, words: int = 4, radius: int = 4) -> DataFrame:
    """One document of each group of near copies stays: the one with the smallest id (null last); all its columns stay.

    Rows are told apart by id where an id has one fingerprint.  Rows without
    an id, and rows of an id that stands for different texts, are told apart by id and fingerprint.
    """
    mine = F.coalesce("doc_id", F.lit(NO_ID))
    found = members(documents, words, radius).select(
        mine.alias("__id"), F.col("fp").alias("__fp"), ((mine == F.col("component_id")) & (F.col("fp") == F.col("keeper"))).alias("stays"), F.col("doc_id").isNull().alias("null_id")
    )
    found = materialise(found, "components")
    rows = found.count()
    by_id = found.where("not null_id").groupBy("__id").agg(F.max("stays").alias("stays"), F.count("*").alias("n"), F.min("__fp").alias("low"), F.max("__fp").alias("high"))
    kind = F.when(~F.col("stays"), "gone").when(F.col("low") != F.col("high"), "mixed").when(F.col("n") > 1, "again")
    special = materialise(by_id.select("__id", kind.alias("kind")).where("kind is not null"), "near-copies", rows)
    sizes = {r["kind"]: r["count"] for r in special.groupBy("kind").count().collect()}  # three rows at most

    def side(frame: DataFrame, size: int) -> DataFrame:
        """Ids of eight bytes: broadcast only within a checked number of rows, else both sides are shuffled."""
        return F.broadcast(frame) if size <= 1_000_000 else frame

    def of(kind: str) -> DataFrame:
        return side(special.where(F.col("kind") == kind).select("__id"), sizes[kind])

    whole = documents.withColumn("__id", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)))
    has_id = F.col("doc_id").cast("long").isNotNull()
    named = whole.where(has_id)
    kept = [named.join(side(special.select("__id"), sum(sizes.values())), "__id", "left_anti")]
    if "again" in sizes:
        kept.append(named.join(of("again"), "__id", "left_semi").dropDuplicates(["__id"]))
    if "mixed" in sizes:
        kept.append(_survivors(named.join(of("mixed"), "__id", "left_semi"), found.where("stays and not null_id").join(of("mixed"), "__id", "left_semi"), words, side))
    if found.where("null_id").limit(1).count():
        kept.append(_survivors(whole.where(~has_id), found.where("stays and null_id"), words, side))
    return union_all([k.select(*documents.columns) for k in kept])


def _survivors(rows: DataFrame, stay: DataFrame, words: int, side) -> DataFrame:
    """One row for each (id, fingerprint) of ``stay``."""
    stay = materialise(stay.select("__id", "__fp").distinct(), "survivors")
    return _with_prints(rows, words).join(side(stay, stay.count()), ["__id", "__fp"], "left_semi").dropDuplicates(["__id", "__fp"])
