"""Maximum inner product search with score-aware (anisotropic) product quantisation.

Codebooks of 16 entries a subspace (four-bit codes) are learnt on a bounded
sample under a loss that weighs the residual's part parallel to the vector
``eta`` times its orthogonal part, because only the parallel part moves large
inner products.  Codes are chosen by coordinate descent on the same loss.

Queries and candidates are dealt into blocks; a task scans one block of codes
for one block of queries with lookup tables (two four-bit codes share a table
of 256 sums), keeps the ``depth`` best a query, reranks these exactly in
double precision on the original vectors, and returns its ``k`` best.  A last
step takes the best ``k`` of the blocks' results.

Vectors that are null, zero, of another length than most, or that hold null or
non-finite components take no part.  Equal vectors have equal codes and equal
scores; ties go to the smaller vec_id in the scan, the rerank and the merge.
A query without candidates returns no rows; a null vec_id takes no part.
Every row is a candidate: rows are told apart by a number of their own, so
rows that share a vec_id are all found, and each is a query of its own if the
id is one's; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from delprop.llm.common import map_arrow, materialise

CENTRES = 16


@dataclass
class Quantiser:
    books: np.ndarray  # (subspaces, 16, width)
    eta: float

    def _pad(self, x: np.ndarray) -> np.ndarray:
        s, _, w = self.books.shape
        return np.pad(x, ((0, 0), (0, s * w - x.shape[1]))).reshape(len(x), s, w)

    def encode(self, x: np.ndarray, sweeps: int = 2) -> np.ndarray:
        """Codes (rows, subspaces) by coordinate descent on the anisotropic loss, from the nearest centres."""
        parts = self._pad(x)
        norm = np.maximum((x**2).sum(1), 1e-30)
        codes = np.empty(parts.shape[:2], np.uint8)
        along = np.empty(parts.shape[:2])  # residual's inner product with the vector, by subspace
        for j, book in enumerate(self.books):
            gap = parts[:, j, None, :] - book
            codes[:, j] = (gap**2).sum(2).argmin(1)
            along[:, j] = ((parts[:, j] - book[codes[:, j]]) * parts[:, j]).sum(1)
        total = along.sum(1)
        for _ in range(sweeps):
            for j, book in enumerate(self.books):
                gap = parts[:, j, None, :] - book
                dots = (gap * parts[:, j, None, :]).sum(2)
                rest = total - along[:, j]
                loss = (gap**2).sum(2) + (self.eta - 1) * (rest[:, None] + dots) ** 2 / norm[:, None]
                best = loss.argmin(1)
                codes[:, j] = best
                along[:, j] = dots[np.arange(len(x)), best]
                total = rest + along[:, j]
        return codes

    def tables(self, queries: np.ndarray) -> np.ndarray:
        """(pairs, 256, queries) sums of two subspaces' inner products, in single precision."""
        parts = self._pad(queries)
        single = np.einsum("qsw,scw->scq", parts, self.books)
        if len(single) % 2:
            single = np.concatenate([single, np.zeros_like(single[:1])])
        pair = single[0::2, :, None, :] + single[1::2, None, :, :]
        return pair.reshape(len(pair), CENTRES * CENTRES, -1).astype(np.float32)


def fit(x: np.ndarray, width: int = 2, threshold: float = 0.2, turns: int = 6, seed: int = 3) -> Quantiser:
    """Alternate anisotropic assignment with the least-squares codebook update of each subspace."""
    dim = x.shape[1]
    subspaces = math.ceil(dim / width)
    eta = max(1.0, (dim - 1) * threshold**2 / (1 - threshold**2))
    draw = np.random.default_rng(seed)
    model = Quantiser(np.zeros((subspaces, CENTRES, width)), eta)
    parts = model._pad(x)
    picked = draw.choice(len(x), CENTRES, replace=len(x) < CENTRES)
    model.books[:] = parts[picked].transpose(1, 0, 2)
    weight = (eta - 1) / np.maximum((x**2).sum(1), 1e-30)
    for _ in range(turns):
        codes = model.encode(x, 1)
        along = np.stack([((parts[:, j] - model.books[j][codes[:, j]]) * parts[:, j]).sum(1) for j in range(subspaces)], 1)
        total = along.sum(1)
        for j in range(subspaces):
            v = parts[:, j]
            pull = weight * (total - along[:, j] + (v**2).sum(1))
            for c in range(CENTRES):
                own = codes[:, j] == c
                if own.any():
                    u = v[own]
                    left = own.sum() * np.eye(width) + (u * weight[own, None]).T @ u
                    model.books[j, c] = np.linalg.solve(left, (u * (1 + pull[own])[:, None]).sum(0))
    return model


def scan_block(model: Quantiser, codes: np.ndarray, vectors: np.ndarray, ids: np.ndarray, numbers: np.ndarray, queries: np.ndarray, query_numbers: np.ndarray, k: int, depth: int) -> pd.DataFrame:
    """The exact best ``k`` among the ``depth`` best by codes, for each query but the row of its own number; rows come sorted by id."""
    if codes.shape[1] % 2:
        codes = np.c_[codes, np.zeros(len(codes), np.uint8)]
    packed = codes[:, 0::2].astype(np.int64) * CENTRES + codes[:, 1::2]
    out = []
    for at in range(0, len(queries), 64):
        q, names = queries[at : at + 64], query_numbers[at : at + 64]
        table = model.tables(q)
        rough = np.zeros((len(codes), len(q)), np.float32)
        for j in range(packed.shape[1]):
            rough += table[j][packed[:, j]]
        rough = rough.T
        for i, name in enumerate(names.tolist()):
            row = np.where(numbers == name, -np.inf, rough[i])
            if len(row) > depth:
                floor = -np.partition(-row, depth - 1)[depth - 1]
                over = np.flatnonzero(row > floor)
                level = np.flatnonzero(row == floor)[: depth - len(over)]
                pool = np.sort(np.r_[over, level])
            else:
                pool = np.arange(len(row))
            pool = pool[numbers[pool] != name]
            exact = (vectors[pool] * q[i]).sum(1)
            best = np.lexsort((numbers[pool], ids[pool], -exact))[:k]
            out.append(pd.DataFrame({"query": name, "vec_id": ids[pool][best], "score": exact[best]}))
    return pd.concat(out) if out else pd.DataFrame({"query": np.zeros(0, np.int64), "vec_id": np.zeros(0, np.int64), "score": np.zeros(0)})


def usable(embeddings: DataFrame) -> DataFrame:
    """(vec_id, v, number): the rows that take part, with a number of their own; single-precision vectors travel as they are, others as doubles."""
    v = F.col("embedding")
    if dict(embeddings.dtypes)["embedding"] != "array<float>":
        v = v.cast("array<double>")
    sound = F.col("vec_id").isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    return embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v")).where(sound).withColumn("number", F.monotonically_increasing_id())


def search(embeddings: DataFrame, every: int = 20, k: int = 20, depth: int = 400, sample_rows: int = 4000, block_rows: int = 8192, block_queries: int = 2048, least_blocks: int = 8) -> DataFrame:
    """(query_id, rank, vec_id, score): the ``k`` nearest found of every row whose id is divisible by ``every``.

    Codebooks are fitted on about ``sample_rows`` rows; every row is indexed.
    The numbers of rows are fixed by a table in the scratch folder.
    """
    rows = materialise(usable(embeddings), "vectors")
    spark = rows.sparkSession
    shape = rows.groupBy(F.size("v").alias("dim")).count().orderBy(F.desc("count"), F.desc("dim")).first()
    empty = "query_id long, rank int, vec_id long, score double"
    if shape is None:
        return spark.createDataFrame([], empty)
    rows, n = rows.where(F.size("v") == shape["dim"]), shape["count"]
    bound = int(min(1.0, sample_rows / n) * (1 << 30))
    drawn = rows.where(F.pmod(F.xxhash64(F.lit("fit"), "vec_id", "number"), F.lit(1 << 30)) <= bound).select("v").collect()
    model = fit(np.array([r.v for r in drawn])) if drawn else fit(np.array([rows.first().v]))
    is_query = F.pmod(F.col("vec_id"), F.lit(every)) == 0
    n_queries = rows.where(is_query).count()
    n_blocks, n_sides = max(least_blocks, math.ceil(n / block_rows)), max(1, math.ceil(n_queries / block_queries))
    mixed = F.xxhash64("number")

    def encode(batch: pa.RecordBatch) -> pa.RecordBatch:
        codes = model.encode(np.array(batch.column("v").to_pylist(), float))
        return batch.append_column("code", pa.array([c.tobytes() for c in codes], pa.binary()))

    coded = materialise(map_arrow(rows, encode, f"vec_id long, v {dict(rows.dtypes)['v']}, number long, code binary"), "codes")
    left = coded.withColumn("c", F.pmod(mixed, F.lit(n_blocks)).cast("int")).withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(n_sides - 1))))
    right = rows.where(is_query).withColumn("q", F.pmod(F.xxhash64(F.lit("q"), "number"), F.lit(n_sides)).cast("int")).withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(n_blocks - 1))))

    def task(block: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        if not len(block) or not len(asked):
            return pd.DataFrame({"query": np.zeros(0, np.int64), "vec_id": np.zeros(0, np.int64), "score": np.zeros(0), "query_id": np.zeros(0, np.int64)})
        block, asked = block.sort_values(["vec_id", "number"]), asked.sort_values(["vec_id", "number"])
        vectors, queries = (np.array(x.v.tolist(), float) for x in (block, asked))
        codes = np.frombuffer(b"".join(block.code), np.uint8).reshape(len(block), -1)
        out = scan_block(model, codes, vectors, block.vec_id.to_numpy(), block.number.to_numpy(), queries, asked.number.to_numpy(), k, depth)
        return out.assign(query_id=out["query"].map(dict(zip(asked.number, asked.vec_id, strict=True))).astype("int64"))

    found = left.groupBy("q", "c").cogroup(right.groupBy("q", "c")).applyInPandas(task, "query long, vec_id long, score double, query_id long")
    order = Window.partitionBy("query").orderBy(F.desc("score"), F.asc("vec_id"))
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
