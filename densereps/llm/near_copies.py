"""Near copies by word shingles: components of texts whose sets of shingles have a Jaccard similarity of 4/5 or more.

Texts with equal sets are folded first. Fingerprints of the sets (simhash.py) meet next: distance tables of pivots discard
pairs in blocks, survivors within BITS bits make forests, and those of their links that the whole sets confirm join sets.
At this similarity fingerprints differ in about ten of 64 bits on average and often in more, too many for blocks; so set
prefixes give the pairs that are left, of which only those that no fingerprint has joined are checked. In any order of all hashes, two sets of that similarity share one of the first
hashes of each, as many as a near copy may lack, plus one (a prefix); so postings of prefix hashes miss no pair. Hashes
that a sample of the texts holds often come last in the order, so that common passages make few postings; which
hashes those are changes no result. A posting of a rarer hash, or of up to CROWD sets, gives all of its pairs, less those that can't reach
the similarity by the prefix hashes they share. A longer one first gives the pairs of each set with its neighbour and
with one leader; the longer postings that still hold several components are then dealt into chunks that meet in pairs,
and each meeting emits a spanning forest of its links. Every pair is checked on the whole sets before it links.

Defined results: words are parted and lower-cased as for fingerprints; a null, empty or white text has the empty set,
and empty sets are equal; fewer words than a shingle make one shingle of the whole; null and repeated ids as in simhash.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.llm import simhash
from densereps.llm.textbytes import buffers
from densereps.operators.components import connected_components
from densereps.plans.broadcasts import fits
from densereps.plans.lineage import cut, forget_unused, stored

SHINGLE, SEED = 5, 42
#: The least similarity, as a fraction.
OVER, UNDER = 4, 5
#: Differing bits up to which fingerprints meet.
BITS = 6
#: Sets of a common hash's posting that still gives all of its pairs, and sets of one chunk of a longer one.
CROWD, CHUNK = 48, 512
#: One text in so many is looked at for common hashes; how many of those, the commonest, come last in the order.
SAMPLE, COMMON = 8, 1_000_000


def shingles(text: bytes, shingle: int = SHINGLE) -> np.ndarray:
    """The distinct hashes of a text's shingles, in order."""
    ws = text.lower().split()
    if len(ws) < shingle:
        return np.array([xxhash.xxh64_intdigest(b" ".join(ws), SEED)] if ws else [], np.uint64)
    runs = [ws[j : len(ws) - shingle + 1 + j] for j in range(shingle)]
    return np.unique(np.fromiter(map(xxhash.xxh64_intdigest, map(b" ".join, zip(*runs, strict=True)), repeat(SEED)), np.uint64, len(runs[0])))


def prefix(n: int) -> int:
    """How many of the least hashes of a set of n meet those of every near copy."""
    return n - (OVER * n + UNDER - 1) // UNDER + 1 if n else 0


def ordered(held: np.ndarray, common: np.ndarray) -> np.ndarray:
    """A sorted set in the common order: the hashes of common (sorted) come last."""
    if not len(common):
        return held
    late = common[np.minimum(np.searchsorted(common, held), len(common) - 1)] == held
    return np.concatenate([held[~late], held[late]])


def _sets(shingle: int, common=None):
    """Texts to (key of the set, its size, its fingerprint, its hashes).

    Where common is a broadcast of hashes, the hashes are those of the prefix; else the whole set, and there is no fingerprint.
    """

    @F.arrow_udf("struct<key: bigint, size: int, fp: bigint, grams: array<bigint>>")
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        last = None if common is None else np.frombuffer(common.value, np.uint64)
        for texts in batches:
            data, at = buffers(texts)
            keys, sizes, fps, grams = [], [], [], []
            for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                held = shingles(data[a:b].tobytes(), shingle)
                keys.append(xxhash.xxh64_intdigest(held.tobytes(), SEED) if len(held) else 0)
                sizes.append(len(held))
                fps.append(simhash.majority(held) if len(held) and last is not None else 0)
                grams.append(held if last is None else ordered(held, last)[: prefix(len(held))])
            flat = np.concatenate([*grams, np.zeros(0, np.uint64)]).view(np.int64)
            ends = np.concatenate([[0], np.cumsum([len(g) for g in grams])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))
            key, fp = (pa.array(np.array(x, np.uint64).view(np.int64)) for x in (keys, fps))
            yield pa.StructArray.from_arrays([key, pa.array(sizes, pa.int32()), fp, lists], ["key", "size", "fp", "grams"])

    return run


def _runs(columns: tuple[str, ...], heads: int, handle):
    """mapInArrow over rows sorted by the first heads columns: handle(columns, starts of runs); a run may go on in the next batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for batch in batches:
            now = pa.Table.from_batches([batch]).select(list(columns))
            now = now if held is None else pa.concat_tables([held, now])
            if not now.num_rows:
                continue
            starts = _starts(now, columns[:heads])
            if len(starts) > 1:
                yield handle(now.slice(0, int(starts[-1])).combine_chunks(), starts[:-1])
            held = now.slice(int(starts[-1]))
        if held is not None and held.num_rows:
            yield handle(held.combine_chunks(), np.zeros(1, np.int64))

    return run


def _starts(table: pa.Table, heads: tuple[str, ...]) -> np.ndarray:
    new = np.ones(table.num_rows, bool)
    new[1:] = np.any([(c := table[x].to_numpy())[1:] != c[:-1] for x in heads], axis=0)
    return np.flatnonzero(new)


def _ends(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    both = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]).astype(np.int64), axis=1)
    return pa.RecordBatch.from_arrays([pa.array(x) for x in both], names=["src", "dst"])


def _candidates(table: pa.Table, starts: np.ndarray) -> pa.RecordBatch:
    """Pairs of sizes that may be near copies, with the places of the hash; few: from a posting that gives all of its pairs."""
    key, packed, crowd = table["key"].to_numpy(), table["at"].to_numpy(), table["own"].to_numpy() >= 0
    size, place = packed >> 32, packed & 0xFFFFFFFF
    lengths = np.diff(np.append(starts, len(key)))
    at = np.arange(len(key)) - np.repeat(starts, lengths)
    i, j = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for shift in range(1, max(2, int(np.max(lengths, initial=1, where=~crowd[starts])))):
        b = np.flatnonzero((at >= shift) & (~crowd | (shift == 1)))
        i.append(b - shift)
        j.append(b)
    b = np.flatnonzero(crowd & (at > 1))
    i.append(b - at[b])
    j.append(b)
    a, b = np.concatenate(i), np.concatenate(j)
    near = UNDER * np.minimum(size[a], size[b]) >= OVER * np.maximum(size[a], size[b])
    a, b = a[near], b[near]
    turned = key[a] > key[b]
    a, b = np.where(turned, b, a), np.where(turned, a, b)
    columns = (key[a], key[b], size[a], size[b], place[a], place[b], ~crowd[a])
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["src", "dst", "n", "m", "i", "j", "few"])


def forest(sets: list[np.ndarray], roots: np.ndarray) -> list[tuple[int, int]]:
    """Links that join the near copies among sets, but for those that roots has joined."""
    sizes = np.array([len(s) for s in sets])
    _, code = np.unique(np.concatenate(sets), return_inverse=True)
    begin = np.cumsum(sizes) - sizes
    label, links = np.unique(roots, return_inverse=True)[1], []
    mark = np.zeros(int(code.max()) + 1, np.int64)
    for i in range(len(sets)):
        rest = np.flatnonzero((label != label[i]) & (np.arange(len(sets)) > i) & (UNDER * np.minimum(sizes, sizes[i]) >= OVER * np.maximum(sizes, sizes[i])))
        if not len(rest):
            continue
        mine = code[begin[i] : begin[i] + sizes[i]]
        mark[mine] = 1
        both = np.array([int(mark[code[begin[j] : begin[j] + sizes[j]]].sum()) for j in rest.tolist()])
        mark[mine] = 0
        for j in rest[UNDER * both >= OVER * (sizes[i] + sizes[rest] - both)].tolist():
            if label[i] != label[j]:
                links.append((i, j))
                label[label == label[j]] = label[i]
    return links


def _meetings(table: pa.Table, starts: np.ndarray) -> pa.RecordBatch:
    key, root = table["key"].to_numpy(), table["root"].to_numpy()
    ends, found = np.append(starts[1:], len(key)), [np.zeros((0, 2), np.int64)]
    grams = table["grams"].combine_chunks()
    for a, b in zip(starts.tolist(), ends.tolist(), strict=True):
        if len(set(root[a:b].tolist())) > 1:
            links = forest([grams[i].values.to_numpy() for i in range(a, b)], root[a:b])
            found.append(key[a:b][np.array(links, np.int64).reshape(-1, 2)])
    both = np.concatenate(found)
    return _ends(both[:, 0], both[:, 1])


def _joined(keys: DataFrame, links: DataFrame) -> DataFrame:
    """(key, root) of each key."""
    roots = connected_components(links).select(F.col("id").alias("key"), F.col("component").alias("linked"))
    return cut(keys.join(roots, "key", "left").select("key", F.coalesce("linked", "key").alias("root")))


def close_sets(sets: DataFrame, max_bits: int = BITS) -> DataFrame:
    """(src, dst): pairs of sets(key, fp) that join all whose fingerprints are within max_bits, over others too."""
    prints = cut(sets.groupBy("fp").agg(F.min("key").alias("key")))
    met = simhash.close_pairs(prints.select("fp"), max_bits)
    for end, to in (("src", "a"), ("dst", "b")):
        met = met.join(prints.select(F.col("fp").alias(end), F.col("key").alias(to)), end)
    same = sets.join(prints.select("fp", F.col("key").alias("a")), "fp").filter("key <> a").select("a", F.col("key").alias("b"))
    both = met.select("a", "b").unionByName(same)
    return both.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """(id, whole, key, root, component) for each row: a hash of its text, its set, its component by id and by set."""
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text_col).alias("whole"), F.col(text_col).alias("text"))
    some = source.filter(F.pmod("whole", F.lit(SAMPLE)) == 0).select("text").distinct()
    often = some.select(F.explode(_sets(shingle)("text")["grams"]).alias("gram")).groupBy("gram").agg(F.count(F.lit(1)).alias("n"))
    often = cut(often.filter(F.col("n") > max(1, CROWD // SAMPLE)).orderBy(F.desc("n"), "gram").limit(COMMON).select("gram"))
    late = np.sort(np.array(often.toPandas()["gram"], np.int64).view(np.uint64))
    common = docs.sparkSession.sparkContext.broadcast(late.tobytes())
    rows = stored(source.withColumn("s", _sets(shingle, common)("text")).select("id", "whole", "s.key", "s.size", "s.fp", "s.grams"))
    sets = stored(
        rows.groupBy("key").agg(
            F.min("id").alias("least"), F.min(F.struct("id", "whole")).alias("one"), *[F.any_value(c).alias(c) for c in ("size", "fp", "grams")]
        )
    )
    close = cut(close_sets(sets.select("key", "fp")))
    forget_unused(docs.sparkSession)
    # size and place in one number, which sorts by size
    packed = F.shiftleft(F.col("size").cast("long"), 32) + F.col("place")
    postings = sets.select("key", "size", F.posexplode("grams").alias("place", "gram")).select("key", "gram", packed.alias("at"))
    held = postings.join(F.broadcast(often), "gram").groupBy("gram").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > CROWD)
    crowds = cut(held.select("gram", F.ceil(F.col("n") / CHUNK).cast("int").alias("chunks")))
    own = F.coalesce(F.pmod(F.xxhash64("key"), F.col("chunks")).cast("int"), F.lit(-1))  # -1: no crowd
    dealt = postings.join(F.broadcast(crowds), "gram", "left").select("gram", own.alias("own"), "at", "key")
    order = dealt.repartition("gram", "own").sortWithinPartitions("gram", "own", "at", "key")
    met = order.mapInArrow(_runs(("gram", "own", "at", "key"), 2, _candidates), "src long, dst long, n long, m long, i long, j long, few boolean")
    crowded = cut(postings.join(F.broadcast(crowds), "gram").select("gram", "chunks", "key"))
    unseen = cut(crowded.groupBy("key").agg(F.count(F.lit(1)).alias("unseen")))
    shared = met.groupBy("src", "dst", "n", "m").agg(
        F.sum(F.col("few").cast("int")).alias("both"), F.max(F.when(F.col("few"), F.col("i"))).alias("i"), F.max(F.when(F.col("few"), F.col("j"))).alias("j")
    )
    for end in ("src", "dst"):
        shared = shared.join(unseen.select(F.col("key").alias(end), F.col("unseen").alias(f"{end}_unseen")), end, "left")
    rest = F.least(F.col("n") - F.coalesce("i", F.lit(-1)), F.col("m") - F.coalesce("j", F.lit(-1))) - 1
    most = F.col("both") + F.least(F.coalesce("src_unseen", F.lit(0)), F.coalesce("dst_unseen", F.lit(0))) + rest
    pairs = cut(shared.filter(UNDER * most >= OVER * (F.col("n") + F.col("m") - most)).select("src", "dst"))
    del postings, held, dealt, order, met, shared
    forget_unused(docs.sparkSession)

    met = pairs.unionByName(close).select(F.explode(F.array("src", "dst")).alias("key")).unionByName(crowded.select("key")).distinct()
    named = met.join(sets.select("key", "one"), "key").select("key", F.col("one.id").alias("one_id"), F.col("one.whole").alias("one_whole"))
    named = F.broadcast(named) if fits(named, 200_000) else named
    texts = source.join(named, F.col("id").eqNullSafe(F.col("one_id")) & (F.col("whole") == F.col("one_whole")))
    full = stored(texts.dropDuplicates(["key"]).select("key", _sets(shingle)("text").alias("s")).select("key", "s.grams"))
    del met, named, texts
    forget_unused(docs.sparkSession)
    a, b = (full.select(F.col("key").alias(x), F.col("grams").alias(g)) for x, g in (("src", "left"), ("dst", "right")))
    both = F.size(F.array_intersect("left", "right"))
    alike = UNDER * both >= OVER * (F.size("left") + F.size("right") - both)
    confirmed = lambda met: cut(met.join(a, "src").join(b, "dst").filter(alike).select("src", "dst"))
    sure = confirmed(close)
    roots = _joined(sets.select("key"), sure)
    for end in ("src", "dst"):
        pairs = pairs.join(roots.select(F.col("key").alias(end), F.col("root").alias(f"{end}_root")), end)
    links = cut(sure.unionByName(confirmed(pairs.filter("src_root <> dst_root").select("src", "dst"))))
    del a, b, pairs
    forget_unused(docs.sparkSession)
    roots = _joined(sets.select("key"), links)
    forget_unused(docs.sparkSession)

    tagged = crowded.join(roots, "key")
    parted = cut(tagged.groupBy("gram").agg(F.min("root").alias("a"), F.max("root").alias("b")).filter("a <> b").select("gram"))
    last = F.col("chunks") - 1
    chunked = (
        tagged.join(parted, "gram", "left_semi")
        .withColumn("own", F.pmod(F.xxhash64("key"), F.col("chunks")).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), last)))
        .filter("chunks = 1 OR own <> other")
        .select("gram", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "key", "root")
    )
    meet = ["gram", "low", "high"]
    carried = chunked.join(full, "key").repartition(*meet).sortWithinPartitions(*meet)
    late = cut(carried.mapInArrow(_runs((*meet, "key", "root", "grams"), 3, _meetings), "src long, dst long").distinct())
    if not late.isEmpty():
        roots = _joined(sets.select("key"), links.unionByName(late))
    least = sets.select("key", "least").join(roots, "key").groupBy("root").agg(F.min("least").alias("component"))
    classes = cut(roots.join(least, "root").select("key", "root", "component"))
    return rows.select("id", "whole", "key").join(classes, "key").select("id", "whole", "key", "root", "component")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """docs with one row of each group of near copies: its least id."""
    return simhash.keep_least(docs, near_copies(docs, id_col, text_col, shingle), id_col, text_col)
