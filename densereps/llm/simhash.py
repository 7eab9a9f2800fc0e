"""SimHash near-dedup: fingerprints, pivot distance tables, and components of close fingerprints.

A fingerprint bit is 1 when it is set in more than half of the shingles' XXH64 hashes. Fingerprints link at
max_bits or fewer differing bits. Copies share one fingerprint and are folded first. Distinct fingerprints then
meet in blocks that agree on all but max_bits of a few equal bit ranges, which no linked pair can miss. In a
block, the Hamming distances of each fingerprint to PIVOTS reference fingerprints are tabulated once; a pair
whose distances to any pivot differ by more than max_bits can't link and is discarded, and survivors are
verified bit by bit. A block emits a spanning forest of its links, never its pairs; a large block is cut into
chunks that meet in pairs, so no task holds more than two chunks. Links are joined to components by star
contraction. Nothing grows with the data on the driver.

Defined results: a null, empty or white text has fingerprint zero and links like any other; fewer words than a
shingle make one shingle of the whole; a null id counts only where no other id is reached (the component is then
null); rows that repeat an id and a text are one document. Texts are read whole; only the id and text columns are
read, so other columns never clash.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.llm.textbytes import buffers
from densereps.operators.components import connected_components
from densereps.plans.lineage import cut

SHINGLE, SEED, MAX_BITS = 3, 42, 3
PIVOTS = 16
#: Fingerprints of one chunk of a large block.
CHUNK = 2048
#: Bits that blocks agree on at least, and expected fingerprints of a block that decides whether they agree on more.
AGREED, BLOCK = 16, 256

_ALL = (1 << 64) - 1


def references(n: int = PIVOTS) -> np.ndarray:
    """The reference fingerprints: hashes of 0, 1, 2, ..."""
    return np.array([xxhash.xxh64_intdigest(i.to_bytes(8, "little"), SEED) for i in range(n)], np.uint64)


_LANES = np.array([sum(((b >> j) & 1) << (8 * j) for j in range(8)) for b in range(256)], np.uint64)


def majority(hashes: np.ndarray) -> int:
    """The bits set in more than half of the hashes."""
    n = len(hashes)
    lanes = _LANES[hashes.astype("<u8").view(np.uint8).reshape(n, 8)]  # a byte-wide counter for each bit
    counts = np.zeros(64, np.int64)
    for at in range(0, n, 255):
        counts += np.ascontiguousarray(lanes[at : at + 255].sum(axis=0)).astype("<u8").view(np.uint8)
    return int(np.packbits(counts * 2 > n, bitorder="little").view("<u8")[0])


def fingerprint(text: bytes, shingle: int = SHINGLE, seed: int = SEED, step: int = 1 << 16) -> int:
    ws = text.lower().split()
    if not ws:
        return 0
    if len(ws) < shingle:
        return xxhash.xxh64_intdigest(b" ".join(ws), seed)
    n = len(ws) - shingle + 1
    parts = []
    for at in range(0, n, step):
        runs = [ws[at + j : min(n, at + step) + j] for j in range(shingle)]
        parts.append(np.fromiter(map(xxhash.xxh64_intdigest, map(b" ".join, zip(*runs, strict=True)), repeat(seed)), np.uint64, len(runs[0])))
    return majority(np.concatenate(parts))


def _fingerprints(shingle: int):
    @F.arrow_udf("long")
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            data, at = buffers(texts)
            out = np.fromiter((fingerprint(data[a:b].tobytes(), shingle) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)), np.uint64, len(at) - 1)
            yield pa.array(out.view(np.int64))

    return run


def block_masks(n: int, max_bits: int = MAX_BITS) -> list[int]:
    """Bit masks, as signed longs; fingerprints within max_bits agree on one of them at least, at any n."""
    agreed = lambda ranges: 64 * (ranges - max_bits) // ranges
    ranges = max_bits + 1
    while (agreed(ranges) < AGREED or n / 2 ** agreed(ranges) > BLOCK) and ranges < 8:
        ranges += 1
    edges = [64 * i // ranges for i in range(ranges + 1)]
    bits = [(1 << edges[i + 1]) - (1 << edges[i]) for i in range(ranges)]
    masks = [sum(bits[i] for i in agreed) & _ALL for agreed in combinations(range(ranges), ranges - max_bits)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


class _Forest:
    """Union-find over the rows of one block."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        a, b = self.root(i), self.root(j)
        self.up[max(a, b)] = min(a, b)
        return a != b


def _survivors(i: np.ndarray, j: np.ndarray, fps: np.ndarray, far: np.ndarray, max_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs that no pivot discards and that differ in max_bits bits at most."""
    for p in range(far.shape[1]):
        near = np.abs(far[i, p] - far[j, p]) <= max_bits
        i, j = i[near], j[near]
    near = np.bitwise_count(fps[i] ^ fps[j]) <= max_bits
    return i[near], j[near]


def _small_blocks(fps: np.ndarray, far: np.ndarray, sizes: np.ndarray, starts: np.ndarray, max_bits: int) -> list[tuple[int, int]]:
    """Links, as rows, of many small blocks at once, a forest for each."""
    links: list[tuple[int, int]] = []
    forest = _Forest(len(fps))
    for shift in range(1, int(sizes.max())):
        wide = sizes > shift
        lengths = sizes[wide] - shift
        i = np.repeat(starts[wide], lengths) + np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)
        a, b = _survivors(i, i + shift, fps, far, max_bits)
        links += [(x, y) for x, y in zip(a.tolist(), b.tolist(), strict=True) if forest.join(x, y)]
    return links


def _large_block(fps: np.ndarray, far: np.ndarray, max_bits: int, rows: int = 64) -> list[tuple[int, int]]:
    """Links of one block. Rows in the order of their first pivot distance meet only rows within max_bits of it."""
    order = np.argsort(far[:, 0], kind="stable")
    fps, far = fps[order], far[order]
    n, links, forest, label, at, step = len(fps), [], _Forest(len(fps)), np.arange(len(fps)), 0, 1
    while at < n:
        end = min(n, at + step)
        reach = int(np.searchsorted(far[:, 0], far[end - 1, 0] + max_bits, "right"))
        i, j = np.divmod(np.arange((end - at) * (reach - at)), reach - at)
        i, j = i + at, j + at
        open_ = (i < j) & (label[i] != label[j])
        a, b = _survivors(i[open_], j[open_], fps, far, max_bits)
        if len(a):
            pairs = label[a].astype(np.int64) * n + label[b]
            _, one = np.unique(pairs, return_index=True)
            links += [(x, y) for x, y in zip(a[one].tolist(), b[one].tolist(), strict=True) if forest.join(x, y)]
            label = np.fromiter(map(forest.root, range(n)), np.int64, n)
            if not label.any():
                break
        at, step = end, min(rows, step * 4)
    return [(int(order[x]), int(order[y])) for x, y in links]


def _links(max_bits: int, pivots: np.ndarray, small: int = 48):
    """Rows sorted by block to links; a block may go on in the next batch."""

    def handle(fps: np.ndarray, starts: np.ndarray) -> pa.RecordBatch:
        sizes = np.diff(np.append(starts, len(fps)))
        own = np.repeat(sizes, sizes) > 1
        at = np.cumsum(own) - own
        fps, starts, sizes = fps[own], at[starts[sizes > 1]], sizes[sizes > 1]
        links: list[tuple[int, int]] = []
        if len(fps):
            far = np.bitwise_count(fps[:, None] ^ pivots[None, :]).astype(np.int8)
            few = np.repeat(sizes <= small, sizes)
            if few.any():
                where = np.flatnonzero(few)
                counts = sizes[sizes <= small]
                links += [(where[a], where[b]) for a, b in _small_blocks(fps[few], far[few], counts, np.cumsum(counts) - counts, max_bits)]
            for s, k in zip(starts[sizes > small].tolist(), sizes[sizes > small].tolist(), strict=True):
                links += [(s + a, s + b) for a, b in _large_block(fps[s : s + k], far[s : s + k], max_bits)]
        ends = np.array(links, np.int64).reshape(-1, 2)
        return pa.RecordBatch.from_arrays([pa.array(fps[ends[:, k]].view(np.int64)) for k in (0, 1)], names=["src", "dst"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            columns = [np.asarray(batch.column(x)) for x in ("mask", "bits", "low", "high", "fp")]
            if held is not None:
                columns = [np.concatenate(x) for x in zip(held, columns, strict=True)]
            if not len(columns[0]):
                continue
            new = np.ones(len(columns[0]), bool)
            new[1:] = np.any([c[1:] != c[:-1] for c in columns[:4]], axis=0)
            starts = np.flatnonzero(new)
            held = [c[starts[-1] :] for c in columns]
            if len(starts) > 1:
                yield handle(columns[4][: starts[-1]].view(np.uint64), starts[:-1])
        if held is not None:
            yield handle(held[4].view(np.uint64), np.zeros(1, np.int64))

    return run


def close_pairs(fps: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(src, dst): links that join all of the distinct fingerprints fps(fp) within max_bits of each other."""
    masks = block_masks(fps.count(), max_bits)
    blocks = fps.select(
        "fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(m).cast("long")) for m in masks])).alias("mask", "bits")
    )
    large = blocks.groupBy("mask", "bits").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > CHUNK)
    large = cut(large.select("mask", "bits", F.ceil(F.col("n") / CHUNK).cast("int").alias("chunks")))
    dealt = (
        blocks.join(large, ["mask", "bits"], "left")
        .withColumn("chunks", F.coalesce("chunks", F.lit(1)))
        .withColumn("own", F.pmod(F.xxhash64("fp"), F.col("chunks")).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
        .filter("chunks = 1 OR own <> other")
        .select("mask", "bits", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "fp")
    )
    key = ["mask", "bits", "low", "high"]
    return dealt.repartition(*key).sortWithinPartitions(*key).mapInArrow(_links(max_bits, references()), "src long, dst long")


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, max_bits: int = MAX_BITS
) -> DataFrame:
    """(id, whole, fp, root, component) for each row: a hash of its text, its fingerprint, its component by id and by fingerprint."""
    rows = docs.select(
        F.col(id_col).cast("long").alias("id"), F.xxhash64(text_col).alias("whole"), _fingerprints(shingle)(F.col(text_col)).alias("fp")
    )
    rows = cut(rows)
    fps = cut(rows.groupBy("fp").agg(F.min("id").alias("least")))
    linked = connected_components(close_pairs(fps.select("fp"), max_bits)).select(F.col("id").alias("fp"), F.col("component").alias("root"))
    classes = cut(fps.join(linked, "fp", "left").withColumn("root", F.coalesce("root", "fp")))
    least = classes.groupBy("root").agg(F.min("least").alias("component"))
    named = cut(classes.join(least, "root").select("fp", "root", "component"))
    return rows.join(named, "fp").select("id", "whole", "fp", "root", "component")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs with one row of each group of near copies: its least id."""
    return keep_least(docs, near_duplicates(docs, id_col, text_col, **options), id_col, text_col)


def keep_least(docs: DataFrame, found: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one row of each component of found(id, whole, root, component): its least id."""
    kept = found.filter(F.col("id").eqNullSafe(F.col("component"))).groupBy("root", "id").agg(F.min("whole").alias("whole"))
    # a null id as (0, true), so that the join and the fold below share one exchange
    own = {x: f"__simhash_{x}" for x in ("id", "none", "whole")}
    key = lambda c: (F.coalesce(c, F.lit(0)).alias(own["id"]), c.isNull().alias(own["none"]))
    side = cut(kept.select(*key(F.col("id")), F.col("whole").alias(own["whole"])))
    tagged = docs.select("*", *key(F.col(id_col).cast("long")), F.xxhash64(text_col).alias(own["whole"]))
    met = tagged.join(side, list(own.values()), "left_semi")
    return met.dropDuplicates(list(own.values())).select(*[F.col(f"`{c}`") for c in docs.columns])
