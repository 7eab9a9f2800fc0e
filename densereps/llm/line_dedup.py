"""Line dedup: range-partitioned line hashes, sorted by document and position, decide which lines stay.

A line's key is the line stripped of ASCII white space with A-Z lower-cased. Keys of at least min_chars code
points that at least min_docs documents hold lose all their lines except those in the largest document id.

Lines travel as 128-bit hashes. They are range-partitioned by (hash, document descending, position), so that a key
held by a third of all documents is spread over many partitions, and each partition is streamed once: the first
document of a key keeps it, later ones lose it. A key that crosses partitions is settled from two rows for each
partition. What returns to the documents is a compressed bitmap for each one that loses lines, never the lines.

Defined results: a null or empty text is one empty line; a null document id counts as no document, and its lines
go wherever the key is held by min_docs others; rows that repeat an id are one document. Texts that lose nothing
pass unchanged, a null as null. Other columns pass through, whatever their names.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.llm.url_filter import LOWER, UPPER
from densereps.plans.broadcasts import fits
from densereps.plans.lineage import cut

SPACE = " \t\n\x0b\f\r"
MIN_CHARS, MIN_DOCS = 20, 3
#: Bitmaps up to which they are broadcast to the documents; beyond it both sides are shuffled.
MAX_BITMAPS = 200_000

_EDGE = "part int, h1 long, h2 long, docs array<long>, last boolean"
_DROPPED = "doc long, whole long, pos int"


def line_rows(docs: DataFrame, id_col: str, text_col: str, min_chars: int) -> DataFrame:
    """(h1, h2, doc, whole, pos) of each line long enough to count; whole is a hash of its text."""
    lines = docs.select(
        F.col(id_col).cast("long").alias("doc"),
        F.xxhash64(text_col).alias("whole"),
        F.posexplode(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n", -1)).alias("pos", "line"),
    )
    key = F.translate(F.btrim("line", F.lit(SPACE)), UPPER, LOWER)
    return (
        lines.select("doc", "whole", "pos", key.alias("key"))
        .filter(F.length("key") >= min_chars)
        .select(F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(1), "key").alias("h2"), "doc", "whole", "pos")
    )


def _columns(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    doc = batch.column("doc")
    held = ~np.asarray(doc.is_null())
    ids = np.asarray(doc.fill_null(0))
    return np.asarray(batch.column("h1")), np.asarray(batch.column("h2")), ids, held


def _first_docs(ids: np.ndarray, held: np.ndarray, n: int) -> list[int]:
    """The first n distinct ids of rows sorted by id."""
    return list(dict.fromkeys(ids[held].tolist()))[:n] if len(ids) <= 64 else np.unique(ids[held])[::-1][:n].tolist()


def _edges(n: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, first, last = None, None, None  # each [key, docs]
        for batch in batches:
            if not batch.num_rows:
                continue
            h1, h2, ids, held = _columns(batch)
            part = batch.column("part")[0].as_py()
            for at, edge in ((0, first), (-1, last)):
                key = (int(h1[at]), int(h2[at]))
                same = (h1 == key[0]) & (h2 == key[1])
                docs = _first_docs(ids[same], held[same], n)
                if edge is not None and edge[0] == key:
                    edge[1] = list(dict.fromkeys(edge[1] + docs))[:n]
                elif at == 0 and first is None:
                    first = [key, docs]
                elif at == -1:
                    last = [key, docs]
        if part is None:
            return
        rows = [(part, *first[0], first[1], False), (part, *last[0], last[1], True)]
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64()),
                pa.array([r[3] for r in rows], pa.list_(pa.int64())), pa.array([r[4] for r in rows], pa.bool_()),
            ],
            names=["part", "h1", "h2", "docs", "last"],
        )

    return run


def _settle(edges: list, n: int) -> dict[tuple[int, int], tuple[int | None, bool]]:
    """For each key at a partition's edge: its first document, and whether n documents hold it."""
    docs: dict[tuple[int, int], list[int]] = {}
    for e in sorted(edges, key=lambda e: (e["part"], e["last"])):
        key = (e["h1"], e["h2"])
        docs[key] = list(dict.fromkeys(docs.get(key, []) + e["docs"]))[:n]
    return {k: (d[0] if d else None, len(d) >= n) for k, d in docs.items()}


def _dropped(n: int, settled: dict):
    """Streams sorted rows; yields those whose key n documents hold and another document keeps."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, docs, waiting = None, [], []  # of the run that may go on: its first n documents, rows not yet decided

        def out(doc: list, whole: list, pos: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays(
                [pa.concat_arrays(doc), pa.concat_arrays(whole), pa.concat_arrays(pos)], names=["doc", "whole", "pos"]
            )

        for batch in batches:
            if not batch.num_rows:
                continue
            h1, h2, ids, held = _columns(batch)
            new = np.ones(len(h1), bool)
            new[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
            starts = np.flatnonzero(new)
            run_of = np.cumsum(new) - 1
            fresh = held.copy()
            fresh[1:] &= new[1:] | (ids[1:] != ids[:-1]) | ~held[:-1]
            count = np.add.reduceat(fresh, starts, dtype=np.int64)
            top = ids[starts].copy()
            has_top = held[starts].copy()
            goes_on = key == (int(h1[0]), int(h2[0]))
            end = starts[1] if len(starts) > 1 else len(h1)
            first_docs = _first_docs(ids[:end], held[:end], n)
            if goes_on:
                first_docs = list(dict.fromkeys(docs + first_docs))[:n]
                count[0] = len(first_docs)
                if docs:
                    top[0], has_top[0] = docs[0], True
            parts: list[list] = [[], [], []]
            if waiting and goes_on and count[0] >= n:
                for w in waiting:
                    for p, c in zip(parts, w, strict=True):
                        p.append(c)
            if not goes_on or count[0] >= n or len(starts) > 1:
                waiting = []
            decided = np.ones(len(starts), bool)
            for r in {0, len(starts) - 1}:
                if (known := settled.get((int(h1[starts[r]]), int(h2[starts[r]])))) is not None:
                    count[r] = n if known[1] else 0
                    top[r], has_top[r] = (known[0], True) if known[0] is not None else (0, False)
                elif r == len(starts) - 1 and count[r] < n:
                    decided[r] = False
            differs = ~held | ~has_top[run_of] | (ids != top[run_of])
            goes = differs & (count >= n)[run_of] & decided[run_of]
            pick = pa.array(np.flatnonzero(goes))
            for p, name in zip(parts, ("doc", "whole", "pos"), strict=True):
                p.append(batch.column(name).take(pick))
            last = len(starts) - 1
            key = (int(h1[-1]), int(h2[-1]))
            docs = first_docs if last == 0 else _first_docs(ids[starts[last] :], held[starts[last] :], n)
            if not decided[last]:
                pick = pa.array(np.flatnonzero(differs & (run_of == last)))
                waiting.append([batch.column(name).take(pick) for name in ("doc", "whole", "pos")])
            yield out(*parts)

    return run


def _bitmap(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
    for positions in batches:
        out = []
        for p in positions.to_pylist():
            keep = np.ones((max(p) // 8 + 1) * 8, bool)
            keep[p] = False
            out.append(zlib.compress(np.packbits(keep, bitorder="little").tobytes()))
        yield pa.array(out, pa.binary())


def read_bitmap(packed: bytes, n_lines: int) -> np.ndarray:
    """Whether each line stays; lines beyond the bitmap do."""
    bits = np.unpackbits(np.frombuffer(zlib.decompress(packed), np.uint8), bitorder="little").astype(bool)[:n_lines]
    return np.concatenate([bits, np.ones(n_lines - len(bits), bool)])


def _apply(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
    for texts, bitmaps in batches:
        kept, gone = [], []
        for text, packed in zip(texts, bitmaps, strict=True):
            if not packed.is_valid:
                kept.append(None)
                gone.append(0)
                continue
            lines = (text.as_py() or "").split("\n")
            keep = read_bitmap(packed.as_py(), len(lines))
            kept.append("\n".join([x for x, k in zip(lines, keep.tolist(), strict=True) if k]))
            gone.append(int((~keep).sum()))
        yield pa.StructArray.from_arrays([pa.array(kept, pa.string()), pa.array(gone, pa.int64())], names=["text", "n_dropped"])


def keep_bitmaps(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS
) -> DataFrame:
    """(doc, whole, bitmap): for each document that loses lines, and each of its texts by hash, the lines that stay."""
    order = ["h1", "h2", F.col("doc").desc_nulls_last(), "whole", "pos"]
    lines = line_rows(docs, id_col, text_col, min_chars)
    dealt = lines.repartitionByRange(*order).sortWithinPartitions(*order)
    rows = cut(dealt).withColumn("part", F.spark_partition_id())
    edges = rows.select("part", "h1", "h2", "doc").mapInArrow(_edges(min_docs), _EDGE).collect()  # two for each partition
    settled = _settle(edges, min_docs)
    dropped = rows.mapInArrow(_dropped(min_docs, settled), _DROPPED)
    gathered = dropped.groupBy("doc", "whole").agg(F.collect_set("pos").alias("pos"))
    return gathered.select("doc", "whole", F.arrow_udf(_bitmap, "binary")("pos").alias("bitmap"))


def drop_lines(
    docs: DataFrame, n_lines: str | None = None, n_dropped: str | None = None, id_col: str = "doc_id", text_col: str = "text", **options
) -> DataFrame:
    """docs with texts that lost their repeated lines, and, where named, columns with the counts before and of drops."""
    bitmaps = cut(keep_bitmaps(docs, id_col, text_col, **options))
    own = {x: f"__line_dedup_{x}" for x in ("doc", "whole", "bitmap", "out")}
    side = bitmaps.select(*[F.col(x).alias(own[x]) for x in ("doc", "whole", "bitmap")])
    if fits(side, MAX_BITMAPS):
        side = F.broadcast(side)
    met = docs.join(
        side, docs[id_col].cast("long").eqNullSafe(side[own["doc"]]) & (F.xxhash64(docs[text_col]) == side[own["whole"]]), "left"
    )
    loses = F.col(own["bitmap"]).isNotNull()
    met = met.withColumn(own["out"], F.arrow_udf(_apply, "struct<text: string, n_dropped: long>")(F.when(loses, F.col(text_col)), F.col(own["bitmap"])))
    counted = F.size(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n", -1)).cast("long")
    text = F.when(loses, F.col(own["out"])["text"]).otherwise(F.col(text_col))
    named = [(counted, n_lines), (F.col(own["out"])["n_dropped"], n_dropped)]
    return met.select(
        *[text.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns],
        *[column.alias(name) for column, name in named if name],
    )
