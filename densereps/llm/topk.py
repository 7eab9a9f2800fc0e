"""Exact top-k by inner product: term-at-a-time accumulation over postings, block by block.

Candidates are packed, where they are read, into blocks of at most ROWS vectors; so are queries. Candidate blocks
are dealt to as many groups as there are shuffle partitions, query blocks to PARTS parts, and each group and part meet, so
that few blocks too spread over the tasks. For each pair of blocks, a dense score array is filled one term (dimension) at a time: the weights of the queries that have the term are scattered over its
postings. The k best of each block are selected and merged over all blocks by a window that ranks in each task first.

Defined results: vectors that are null, empty of non-zero terms, or hold null or non-finite components: the first
and last take no part, all-zero vectors score 0; vectors of different lengths meet on the terms they share; ties
go to the smaller id; a row meets every row but those with its own id; a repeated query row returns its results
once for each; a null id takes no part; scores are 64-bit integers; empty tables give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SCALE, K = 256, 5
ROWS, QUERY_ROWS, PARTS = 2048, 256, 4
_PACKED = "block long, rows array<long>, ids array<long>, at array<int>, terms array<int>, weights array<long>"


def sparse_rows(vectors: DataFrame, id_col: str, vec_col: str, scale: int) -> DataFrame:
    """(row, id, vec): integer components of the vectors that take part."""
    usable = vectors.filter(F.col(id_col).isNotNull() & F.col(vec_col).isNotNull()).select(
        F.monotonically_increasing_id().alias("row"), F.col(id_col).cast("long").alias("id"),
        F.transform(vec_col, lambda x: x.cast("double")).alias("v"),
    )
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    return usable.filter(~bad).select("row", "id", F.transform("v", lambda x: F.floor(x * scale).cast("long")).alias("v"))


def _pack(rows_of_block: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, rows_of_block):
                part = batch.slice(at, rows_of_block)
                rows = np.asarray(part.column("row"))
                vec = part.column("v")
                lengths = np.asarray(vec.value_lengths())
                flat = np.asarray(vec.flatten())
                terms = np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
                own = np.repeat(np.arange(len(lengths)), lengths)
                full = flat != 0
                sizes = np.bincount(own[full], minlength=len(lengths))
                yield pa.RecordBatch.from_pydict(
                    {
                        "block": pa.array([int(rows[0])], pa.int64()), "rows": pa.array([rows], pa.list_(pa.int64())),
                        "ids": pa.array([np.asarray(part.column("id"))], pa.list_(pa.int64())),
                        "at": pa.array([np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)], pa.list_(pa.int32())),
                        "terms": pa.array([terms[full].astype(np.int32)], pa.list_(pa.int32())),
                        "weights": pa.array([flat[full].astype(np.int64)], pa.list_(pa.int64())),
                    }
                )

    return run


def _postings(at: np.ndarray, terms: np.ndarray, weights: np.ndarray) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By term: positions of the rows that have it, and their weights."""
    order = np.argsort(terms, kind="stable")
    rows = np.repeat(np.arange(len(at) - 1), np.diff(at))[order]
    kinds, first = np.unique(terms[order], return_index=True)
    return {int(t): (r, w) for t, r, w in zip(kinds, np.split(rows, first[1:]), np.split(weights[order], first[1:]), strict=True)} if len(kinds) else {}


def accumulate(queries: tuple, postings: dict, n: int) -> np.ndarray:
    """Scores of a block of queries (at, terms, weights) against all n rows of the postings, a term at a time."""
    scores = np.zeros((len(queries[0]) - 1, n), np.int64)
    for term, (q, qw) in _postings(*queries).items():
        if term in postings:
            rows, weights = postings[term]
            if len(rows) == n:
                for i, w in zip(q.tolist(), qw.tolist(), strict=True):
                    scores[i] += w * weights
            else:
                for i, w in zip(q.tolist(), qw.tolist(), strict=True):
                    scores[i, rows] += w * weights
    return scores


def _search(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, postings = None, {}
        for batch in batches:
            for i in range(batch.num_rows):
                row = lambda name: np.asarray(batch.column(name)[i].values)  # noqa: B023, E731
                ids = row("ids")
                if last != (block := batch.column("block")[i].as_py()):
                    last, postings = block, _postings(row("at"), row("terms"), row("weights"))
                q_rows, q_ids = row("q_rows"), row("q_ids")
                scores = accumulate((row("q_at"), row("q_terms"), row("q_weights")), postings, len(ids))
                order = np.argsort(ids, kind="stable")
                sorted_ids, scores = ids[order], scores[:, order]
                out: list[np.ndarray] = []
                for q in range(len(q_ids)):
                    s = scores[q]
                    others = np.flatnonzero(sorted_ids != q_ids[q])
                    if len(others) > k:
                        own = s[others]
                        least = np.partition(own, len(own) - k)[len(own) - k]  # ties stay until ids rank them
                        others = others[own >= least]
                        others = others[np.argsort(-s[others], kind="stable")[:k]]
                    out.append(np.stack([np.full(len(others), q_rows[q]), np.full(len(others), q_ids[q]), sorted_ids[others], s[others]]))
                found = np.concatenate(out, axis=1) if out else np.zeros((4, 0), np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in found], names=["q_row", "query_id", "vec_id", "score"])

    return run


def top_k(
    vectors: DataFrame, queries: DataFrame, k: int = K, scale: int = SCALE, id_col: str = "vec_id", vec_col: str = "embedding"
) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query its k best of all vectors but itself."""
    groups = int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    packed = sparse_rows(vectors, id_col, vec_col, scale).mapInArrow(_pack(ROWS), _PACKED)
    up_to = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    packed = packed.select("*", F.pmod(F.xxhash64("block"), F.lit(groups)).cast("int").alias("g"), up_to(PARTS).alias("part"))
    asked = sparse_rows(queries, id_col, vec_col, scale).mapInArrow(_pack(QUERY_ROWS), _PACKED)
    part = F.pmod(F.xxhash64("block"), F.lit(PARTS)).cast("int").alias("part")
    asked = asked.select(*[F.col(c).alias(f"q_{c}") for c in asked.columns], part, up_to(groups).alias("g"))
    pairs = packed.repartition(groups, "g", "part").join(asked.repartition(groups, "g", "part"), ["g", "part"]).drop("g", "part", "q_block")
    best = pairs.mapInArrow(_search(k), "q_row long, query_id long, vec_id long, score long")
    ranked = best.withColumn("rank", F.row_number().over(W.partitionBy("q_row").orderBy(F.desc("score"), "vec_id")))
    return ranked.filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
