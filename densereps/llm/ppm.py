"""LM scoring: prediction by partial matching over bytes, and a unigram base over words.

Pretrained: the trie is a set of tables, one for each context length, of all byte grams of the training texts and their
counts; nothing is left out, so it grows with the corpus. A context's escape weight is the number of its symbols (escape
method C). A symbol that a longer context holds is excluded from the shorter ones; as a longer context's symbols are
among a shorter one's, the excluded sums belong to contexts and are worked out once. The last resort is uniform over the
bytes the root lacks. A text is ORDER start bytes, its lower-cased UTF-8 bytes, and an end byte (255, which UTF-8 never
has); its score is the log10 probability of all that follows the start.

The texts are cut into blocks of about BLOCK bytes, in one pass that stores each block's texts and its distinct grams of
ORDER + 1 bytes with their counts in training texts, the grams as packed sorted runs, one for each bucket of grams. A
bucket has all grams of its contexts. Its runs are summed one after another; the sums are the longest table, and shorter
tables are sums of longer ones. A gram of some training text costs what its own context says. Any other gram meets all its
shorter grams and contexts in one join and pays its escapes. Then each run gets the costs of its bucket, and each block's
texts the costs of its runs. A task holds one bucket or one block, never the model; buckets grow in number with the texts.

Adaptive: code_length() starts from an empty trie and learns each byte after coding it; one text at a time.

The base score sums log10((c + 0.1) / (N + 0.1 (V + 1))) over a text's words and one end. The counts of the
MAX_WORDS most frequent words are broadcast; a text's other words meet their counts in a shuffled join, one row for
each text and distinct word, so no word is hot there.

Defined results: a null or empty text scores its end alone; a null id is held out, like remainder 0; with no
training text the trie is empty and each byte costs log10 of 256, while every word counts as unknown with N = 0
and V = 0. Texts are read whole; only the id and text columns are read.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from densereps.llm.hashtable import find_slot, hash_table
from densereps.llm.textbytes import LOWER, buffers, chunks, give_back
from densereps.plans.lineage import stored

ORDER, MAX_WORDS = 5, 1 << 17
#: Bytes of text of a block, and of all texts for each bucket of grams.
BLOCK, BYTES_A_BUCKET = 16 << 20, 32 << 20
EDGE = 255
SMOOTH = 0.1


def _sequence(data: np.ndarray, at: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes with start and end bytes, places of the predicted bytes, the text of each)."""
    n = len(at) - 1
    sizes = np.diff(at)
    text = np.repeat(np.arange(n), sizes + 1)
    place = np.arange(len(text)) + order * (text + 1)
    out = np.full(len(text) + order * n, EDGE, np.uint8)
    ends = np.zeros(len(text), bool)
    if n:
        ends[np.cumsum(sizes + 1) - 1] = True
    out[place[~ends]] = LOWER[data]
    return out, place, text


def _keys(seq: np.ndarray, place: np.ndarray, order: int) -> np.ndarray:
    """For each place, its byte and the order bytes before it as one number, the byte lowest."""
    key = np.zeros(len(place), np.uint64)
    for back in range(order, -1, -1):
        key = (key << np.uint64(8)) | seq[place - back].astype(np.uint64)
    return key


def _distinct(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(distinct keys in order, the sum of n of each)."""
    by = np.argsort(keys, kind="stable")
    keys, n = keys[by], n[by]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[first], np.add.reduceat(n, first) if len(first) else n


def _merged(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    if len(parts) == 1:
        return parts[0]
    return _distinct(*[np.concatenate(x) for x in zip(*parts, strict=True)])


class Tally:
    """Sums by key, of which only the distinct keys and a limited number of new ones are held."""

    def __init__(self, spare: int = 1 << 20):
        self.parts, self.spare, self.new = [], spare, 0

    def add(self, keys: np.ndarray, n: np.ndarray) -> None:
        self.parts.append((keys, n))
        self.new += len(keys)
        if self.new > self.spare:
            self.parts = [_merged(self.parts)]
            self.new = 0

    def sums(self) -> tuple[np.ndarray, np.ndarray]:
        return _merged(self.parts)


def pack(x: np.ndarray, sort_of: bool = False) -> bytes:
    """Numbers, byte by byte of each, compressed; sort_of: ascending ones, by their differences."""
    x = np.diff(x, prepend=x[:1] * 0) if sort_of else x
    planes = np.ascontiguousarray(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.itemsize).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def unpack(raw: bytes, kind, sort_of: bool = False) -> np.ndarray:
    size = np.dtype(kind).itemsize
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8).reshape(size, -1)
    x = np.ascontiguousarray(planes.T).view(kind).reshape(-1)
    return np.cumsum(x, dtype=kind) if sort_of else x


def _bucket(gram, buckets: int):
    """The bucket of a gram, by its context; the same for arrays and columns."""
    if isinstance(gram, Column):
        context = F.shiftright(gram, 8)
        mixed = context.bitwiseXOR(F.shiftright(context, 13)).bitwiseXOR(F.shiftright(context, 29))
        return F.pmod(mixed, F.lit(buckets)).cast("int")
    context = gram >> np.uint64(8)
    mixed = context ^ (context >> np.uint64(13)) ^ (context >> np.uint64(29))
    return (mixed % np.uint64(buckets)).astype(np.int32)


def _by_bucket(grams: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """(order of ascending distinct grams by bucket, where each bucket begins)."""
    kind = _bucket(grams, buckets)
    by = np.argsort(kind, kind="stable")
    return by, np.searchsorted(kind[by], np.arange(buckets + 1))


def _text_keys(data: np.ndarray, at: np.ndarray, order: int, size: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(keys, the text of each) of a run of texts, about size at once."""
    seq, place, text = _sequence(data, at, order)
    for k in range(0, len(place), size):
        yield _keys(seq, place[k : k + size], order), text[k : k + size]


def _ipc(parts: list[pa.RecordBatch]) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, parts[0].schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        for part in parts:
            out.write_batch(part)
    return sink.getvalue().to_pybytes()


BLOCKS = "block long, bucket int, grams binary, n binary, docs binary"


def _cut_blocks(order: int, buckets: int, block: int, size: int = 1 << 19):
    """Rows (id, held_out, text) to blocks: a row with the block's rows, bucket -1, and one for each run of its grams."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = TaskContext.get().partitionId() << 32
        tally, parts, filled, k = Tally(), [], 0, 0

        def out() -> pa.RecordBatch:
            keys, n = tally.sums()
            tally.parts.clear()
            grams, n = _distinct(keys >> np.uint64(1), np.where(keys & np.uint64(1), 0, n))  # the lowest bit tells a held-out text
            del keys
            by, at = _by_bucket(grams, buckets)
            runs = [(b, grams[by[i:j]], n[by[i:j]]) for b, (i, j) in enumerate(zip(at[:-1], at[1:], strict=True)) if i < j]
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([first + k] * (1 + len(runs)), pa.int64()), pa.array([-1, *[b for b, _, _ in runs]], pa.int32()),
                    pa.array([None, *[pack(g, True) for _, g, _ in runs]], pa.binary()), pa.array([None, *[pack(x) for _, _, x in runs]], pa.binary()),
                    pa.array([_ipc(parts), *[None] * len(runs)], pa.binary()),
                ],
                names=["block", "bucket", "grams", "n", "docs"],
            )

        for batch in batches:
            out_of = batch.column("held_out").to_numpy(zero_copy_only=False).astype(np.uint64)
            for i, j, data, at in chunks(batch.column("text"), size):
                for keys, text in _text_keys(data, at, order, size):
                    keys = keys << np.uint64(1) | out_of[i + text]
                    keys.sort()
                    new = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
                    tally.add(keys[new], np.diff(np.append(new, len(keys))))
                parts.append(batch.slice(i, j - i))
                filled += len(data)
                if filled >= block:
                    yield out()
                    tally, parts, filled, k = Tally(), [], 0, k + 1
                    give_back()
        if parts:
            yield out()
        tally, parts = Tally(), []
        give_back()

    return run


def in_blocks(rows: DataFrame, order: int = ORDER, block: int = BLOCK, bytes_a_bucket: int = BYTES_A_BUCKET) -> tuple[DataFrame, int]:
    """Blocks of rows (id, held_out, text), stored, and the number of buckets."""
    total = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("b")).first()["b"]
    buckets = 2 * (total // bytes_a_bucket) + 1  # odd, so that no byte of a gram decides alone
    return stored(rows.mapInArrow(_cut_blocks(order, buckets, block), BLOCKS)), buckets


def _contexts(grams: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each of ascending grams: the sum of n over its context, how many have any, and whether some have none."""
    context = grams >> np.uint64(8)
    first = np.flatnonzero(np.concatenate([[True], context[1:] != context[:-1]])) if len(grams) else np.zeros(0, np.int64)
    size = np.diff(np.append(first, len(grams)))
    over = lambda x: np.repeat(np.add.reduceat(x, first), size) if len(first) else np.zeros(0, np.int64)
    return over(n), over((n > 0).astype(np.int64)), over((n == 0).astype(np.int64)) > 0


def _sum_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Runs (bucket, grams, n) in the order of their buckets to distinct grams and what _contexts() tells of them."""
    now, tally = None, Tally()

    def out() -> Iterator[pa.RecordBatch]:
        grams, n = tally.sums()
        columns = [grams.view(np.int64), n, *_contexts(grams, n)]
        for k in range(0, len(grams), 1 << 17):
            yield pa.RecordBatch.from_arrays([pa.array(c[k : k + (1 << 17)]) for c in columns], names=["gram", "n", "whole", "symbols", "asked"])

    for batch in batches:
        for bucket, grams, n in zip(*[batch.column(c).to_pylist() for c in ("bucket", "grams", "n")], strict=True):
            if bucket != now:
                yield from out()
                now, tally = bucket, Tally()
            tally.add(unpack(grams, np.uint64, True), unpack(n, np.int64))
    yield from out()
    tally = Tally()
    give_back()


def count_grams(blocks: DataFrame) -> DataFrame:
    """(gram, n, whole, symbols, asked): the distinct grams of all blocks; n leaves out held-out texts. Stored.

    whole and symbols are the gram's context's; asked tells that the context has a gram without training text.
    """
    runs = blocks.filter("bucket >= 0").select("bucket", "grams", "n")
    sums = runs.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_sum_runs, "gram long, n long, whole long, symbols long, asked boolean")
    return stored(sums)


def _low(x: Column, size: int) -> Column:
    """The last size bytes of a gram."""
    return x.bitwiseAND(F.lit((1 << (8 * size)) - 1))


def level_tables(grams: DataFrame, order: int = ORDER) -> list[DataFrame]:
    """By context length: (gram, n, whole, symbols) of all grams in training texts, whole and symbols of the gram's context."""
    levels = [grams.filter("n > 0")]
    for j in range(order, 0, -1):
        sums = levels[0].groupBy(_low(F.col("gram"), j).alias("gram")).agg(F.sum("n").alias("n"))
        mates = Window.partitionBy(F.shiftrightunsigned("gram", 8))  # at most 256 rows
        levels.insert(0, stored(sums.select("gram", "n", F.sum("n").over(mates).alias("whole"), F.count("n").over(mates).alias("symbols"))))
    return levels


def _model(levels: list[DataFrame]) -> DataFrame:
    """(key, a, b, c, d): what an escaping gram needs, in one table.

    A gram's key has its context's length in the highest byte; a is log10 of its count. A context's has 8 more there; a is
    the log10 of its whole weight and b the log10 probability of its escape; c and d are the same of the next shorter
    context without the symbols that this one holds.
    """
    parts = []
    for j, table in enumerate(levels):
        if j < len(levels) - 1:
            parts.append(table.select((F.col("gram") + F.lit(j << 56)).alias("key"), F.log10("n").alias("a"), *[F.lit(None).cast("double").alias(x) for x in "bcd"]))
        if j:
            up = levels[j - 1].select(F.col("gram").alias("shorter"), F.col("n").alias("m"), F.col("whole").alias("w"), F.col("symbols").alias("s"))
            asked = table.filter("asked") if j == len(levels) - 1 else table
            met = asked.join(up, _low(F.col("gram"), j) == F.col("shorter"))
            each = met.groupBy(F.shiftrightunsigned("gram", 8).alias("context")).agg(
                F.first("whole").alias("whole"), F.first("symbols").alias("symbols"), F.sum("m").alias("gone"), F.first("w").alias("w"), F.first("s").alias("s")
            )
            norm, rest, left = F.log10(F.col("whole") + F.col("symbols")), F.col("w") - F.col("gone"), F.col("s") - F.col("symbols")
            norm_x = F.when(rest + left > 0, F.log10(rest + left)).otherwise(0.0)
            parts.append(
                each.select(
                    (F.col("context") + F.lit((8 + j) << 56)).alias("key"), norm.alias("a"), (F.log10("symbols") - norm).alias("b"),
                    norm_x.alias("c"), F.when(left > 0, F.log10(left) - norm_x).otherwise(0.0).alias("d"),
                )
            )
    return reduce(DataFrame.unionByName, parts)


def escaped_costs(grams: DataFrame, levels: list[DataFrame]) -> DataFrame:
    """(gram, cost) of grams that no training text has: log10 probability of the last byte after the ones before it."""
    order = len(levels) - 1
    root = levels[0].agg(F.coalesce(F.sum("n"), F.lit(0)).alias("whole"), F.count("n").alias("symbols")).first()
    last = -math.log10(max(1, 256 - root["symbols"]))
    gram = F.col("gram")
    keys = {f"g{j}": _low(gram, j + 1) + F.lit(j << 56) for j in range(order)}
    keys |= {f"c{j}": _low(F.shiftrightunsigned(gram, 8), j) + F.lit((8 + j) << 56) for j in range(1, order + 1)}
    asked = grams.select("gram", F.explode(F.array(*[F.struct(F.lit(name).alias("name"), key.alias("key")) for name, key in keys.items()])).alias("q"))
    met = asked.select("gram", "q.name", "q.key").join(_model(levels), "key")
    got = met.groupBy("gram").agg(*[F.max(F.when(F.col("name") == name, F.struct("a", "b", "c", "d"))).alias(name) for name in keys])
    # below[j]: from the context of length j on, after an escape from the next longer one
    below = F.lit(last)
    first = F.lit(last)
    if root["symbols"]:
        norm = math.log10(root["whole"] + root["symbols"])
        first = F.when(F.col("g0.a").isNotNull(), F.col("g0.a") - norm).otherwise(math.log10(root["symbols"]) - norm + last)
    for j in range(order):
        longer = F.col(f"c{j + 1}")
        step = F.when(F.col(f"g{j}.a").isNotNull(), F.col(f"g{j}.a") - longer["c"]).otherwise(longer["d"] + below)
        below = step
        own = F.col(f"g{j + 1}.a") if j + 1 < order else F.lit(None).cast("double")
        first = F.when(longer.isNotNull(), F.when(own.isNotNull(), own - longer["a"]).otherwise(longer["b"] + below)).otherwise(first)
    return grams.select("gram").join(got, "gram", "left").select("gram", first.alias("cost"))


def _cost_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each bucket's rows (gram, cost) of escaping grams and after them its runs, to the costs of each run's grams, in their order."""
    now, new, runs = None, [], []

    def out() -> Iterator[pa.RecordBatch]:
        tally = Tally()
        for _, grams, n in runs:
            tally.add(unpack(grams, np.uint64, True), unpack(n, np.int64))
        grams, n = tally.sums()
        whole, symbols, _ = _contexts(grams, n)
        with np.errstate(divide="ignore"):
            cost = (np.log10(n) - np.log10(whole + symbols)).astype(np.float32)
        if new:
            gram, escaped = (np.concatenate(x) for x in zip(*new, strict=True))
            cost[np.searchsorted(grams, gram)] = escaped
        for k in range(0, len(runs), 64):
            part = runs[k : k + 64]
            costs = [pack(cost[np.searchsorted(grams, unpack(g, np.uint64, True))]) for _, g, _ in part]
            yield pa.RecordBatch.from_arrays(
                [pa.array([b for b, _, _ in part], pa.int64()), pa.array([now] * len(part), pa.int32()), pa.array(costs, pa.binary())],
                names=["block", "bucket", "costs"],
            )

    for batch in batches:
        buckets, blocks = batch.column("bucket").to_numpy(), batch.column("block").fill_null(-1).to_numpy()
        rows = blocks < 0
        edges = np.flatnonzero(np.concatenate([[True], (buckets[1:] != buckets[:-1]) | (rows[1:] != rows[:-1]), [True]])) if len(buckets) else []
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            if buckets[a] != now:
                yield from out()
                now, new, runs = int(buckets[a]), [], []
            if rows[a]:
                new.append((batch.column("gram").slice(a, b - a).to_numpy().view(np.uint64), batch.column("cost").slice(a, b - a).to_numpy()))
            else:
                runs += zip(blocks[a:b].tolist(), *[batch.column(c).slice(a, b - a).to_pylist() for c in ("grams", "n")], strict=True)
    yield from out()
    new, runs = [], []
    give_back()


def cost_runs(blocks: DataFrame, escaped: DataFrame, buckets: int) -> DataFrame:
    """(block, bucket, costs): of each run's grams in ascending order; escaped are the costs of grams without training text."""
    none = lambda kind, name: F.lit(None).cast(kind).alias(name)
    runs = blocks.filter("bucket >= 0").select("bucket", "block", "grams", "n", none("long", "gram"), none("float", "cost"))
    rows = escaped.select(
        _bucket(F.col("gram"), buckets).alias("bucket"), none("long", "block"), none("binary", "grams"), none("binary", "n"), "gram", F.col("cost").cast("float").alias("cost")
    )
    both = runs.unionByName(rows).repartition("bucket").sortWithinPartitions("bucket", F.col("block").asc_nulls_first())
    return both.mapInArrow(_cost_runs, "block long, bucket int, costs binary")


def frequent(counts: DataFrame, most: int, n: str = "n") -> DataFrame:
    """The rows of counts with so high an n that there are most of them at most.

    n falls into classes of equal ratio; the driver gets the sizes of the classes.
    """
    kind = F.floor(F.log2(n) * 8)
    sizes = {r["k"]: r["m"] for r in counts.groupBy(kind.alias("k")).agg(F.count(F.lit(1)).alias("m")).collect()}
    total, least = 0, max(sizes, default=0) + 1
    for k in sorted(sizes, reverse=True):
        total += sizes[k]
        if total > most:
            break
        least = k
    return counts.filter(kind >= least)


def score_texts(texts: pa.Array, costs: list[tuple[int, np.ndarray]], order: int, buckets: int, size: int = 1 << 19) -> np.ndarray:
    """log10 probability of each text of a block and its end; costs are those of the block's runs by bucket."""
    tally = Tally()
    for _, _, data, at in chunks(texts, size):
        for keys, _ in _text_keys(data, at, order, size):
            keys.sort()
            keys = keys[np.concatenate([[True], keys[1:] != keys[:-1]])]
            tally.add(keys, np.ones(len(keys), np.int64))
    grams, _ = tally.sums()
    by, _ = _by_bucket(grams, buckets)
    slots, rows = hash_table(grams[by])
    del tally, grams, by
    cost = np.concatenate([np.zeros(0, np.float32), *[c for _, c in sorted(costs, key=lambda x: x[0])], np.zeros(1, np.float32)])[rows]
    del rows
    parts = []
    for _, _, data, at in chunks(texts, size):
        total = np.zeros(len(at) - 1)
        for keys, text in _text_keys(data, at, order, size):
            total += np.bincount(text, weights=cost[find_slot(slots, keys)], minlength=len(total))
        parts.append(total)
    return np.concatenate(parts) if parts else np.zeros(0)


def code_length(text: str | None, order: int = ORDER) -> float:
    """Adaptive: log10 probability of a text, with its end, by a trie that learns each byte after coding it."""
    seen: dict[bytes, Counter[int]] = defaultdict(Counter)
    symbols = [EDGE] * order + list((text or "").encode().translate(bytes(LOWER))) + [EDGE]
    total = 0.0
    for i in range(order, len(symbols)):
        symbol, excluded = symbols[i], set()
        for j in range(order, -1, -1):
            counts = {s: c for s, c in seen[bytes(symbols[i - j : i])].items() if s not in excluded}
            if counts:
                whole = sum(counts.values()) + len(counts)
                if symbol in counts:
                    total += math.log10(counts[symbol] / whole)
                    break
                total += math.log10(len(counts) / whole)
                excluded |= counts.keys()
        else:
            total -= math.log10(256 - len(excluded))
        for j in range(order + 1):
            seen[bytes(symbols[i - j : i])][symbol] += 1
    return total


def _word_counts(flush: int = 1 << 18):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter[bytes] = Counter()

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays(
                [pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["word", "n"]
            )

        for batch in batches:
            data, at = buffers(batch.column(0))
            for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                seen.update(data[a:b].tobytes().lower().split())
                if len(seen) > flush:
                    yield out()
                    seen.clear()
        if seen:
            yield out()
            seen.clear()
            give_back()

    return run


def _scorer(context, word_costs: dict[bytes, float], order: int, buckets: int):
    """A function of a block's rows: its texts, and the costs of its runs."""
    held = context.broadcast(word_costs)

    def words(texts: pa.Array) -> pa.Table:
        cost = held.value
        data, at = buffers(texts)
        n_tokens, n_known, base, found, times, rare_at = [], [], [], [], [], [0]
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            ws = data[a:b].tobytes().lower().split()
            known = [x for x in map(cost.get, ws) if x is not None]
            n_tokens.append(len(ws) + 1)
            n_known.append(len(known))
            base.append(math.fsum(known))
            if len(known) < len(ws):
                rare = Counter([w for w in ws if w not in cost])
                found += rare.keys()
                times += rare.values()
            rare_at.append(len(found))
        rare = pa.StructArray.from_arrays([pa.array(found, pa.binary()), pa.array(times, pa.int32())], names=["word", "m"])
        return pa.table(
            {
                "n_tokens": pa.array(n_tokens, pa.int64()), "n_known": pa.array(n_known, pa.int64()), "base": pa.array(base, pa.float64()),
                "rare": pa.ListArray.from_arrays(pa.array(rare_at, pa.int32()), rare),
            }
        )

    def run(rows: pa.Table) -> pa.Table:
        runs = [(r["bucket"], unpack(r["costs"], np.float32)) for r in rows.select(["bucket", "costs"]).to_pylist() if r["bucket"] >= 0]
        docs = pa.ipc.open_stream(next(x for x in rows.column("docs") if x.is_valid).as_buffer()).read_all()
        block, n = rows.column("block")[0].as_py(), len(docs)
        del rows
        text = docs.column("text").combine_chunks()
        score = score_texts(text, runs, order, buckets)
        told = pa.concat_tables([words(text.slice(a, b - a)) for a, b, _, _ in chunks(text)])
        give_back()
        return pa.table(
            {
                "block": pa.array([block] * n, pa.int64()), "row": pa.array(np.arange(n, dtype=np.int32)), "id": docs.column("id"),
                "held_out": docs.column("held_out"), **{c: told.column(c) for c in told.column_names}, "score": pa.array(score),
            }
        )

    return run


def score_documents(
    docs: DataFrame, held_out: Column, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER, max_words: int = MAX_WORDS, block: int = BLOCK,
    bytes_a_bucket: int = BYTES_A_BUCKET,
) -> DataFrame:
    """(id, held_out, n_tokens, n_known, train_tokens, base_score, score) for each row; learns from rows not held out."""
    rows = docs.select(F.col(id_col).alias("id"), held_out.alias("held_out"), F.col(text_col).alias("text"))
    train = rows.filter(~F.col("held_out"))
    counts = stored(train.select("text").mapInArrow(_word_counts(), "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")))
    sums = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("v")).first()
    ends = train.count()
    tokens, kinds = sums["n"] + ends, sums["v"] + (ends > 0)
    below = math.log10(tokens + SMOOTH * (kinds + 1))
    cost = lambda n: math.log10(n + SMOOTH) - below
    common = frequent(counts, max_words)
    word_costs = {bytes(r["word"]): cost(r["n"]) for r in common.collect()}  # at most max_words rows
    blocks, buckets = in_blocks(rows, order, block, bytes_a_bucket)
    grams = count_grams(blocks)
    runs = cost_runs(blocks, escaped_costs(grams.filter("n = 0").select("gram"), level_tables(grams, order)), buckets)
    both = runs.select("block", "bucket", "costs", F.lit(None).cast("binary").alias("docs")).unionByName(
        blocks.filter("bucket < 0").select("block", "bucket", F.lit(None).cast("binary").alias("costs"), "docs")
    )
    kind = rows.schema["id"].dataType.simpleString()
    schema = f"block long, row int, id {kind}, held_out boolean, n_tokens long, n_known long, base double, rare array<struct<word: binary, m: int>>, score double"
    scored = stored(both.groupBy("block").applyInArrow(_scorer(docs.sparkSession.sparkContext, word_costs, order, buckets), schema))
    rare = scored.select("block", "row", F.explode("rare").alias("r")).select("block", "row", "r.word", "r.m")
    met = rare.join(counts, "word", "left").select(
        "block", "row", F.when(F.col("n").isNotNull(), F.col("m")).otherwise(0).cast("long").alias("known"),
        (F.col("m") * (F.log10(F.coalesce("n", F.lit(0)) + F.lit(SMOOTH)) - F.lit(below))).alias("part"),
    )
    tail = met.groupBy("block", "row").agg(F.sum("known").alias("known"), F.sum("part").alias("part"))
    return scored.drop("rare").join(tail, ["block", "row"], "left").select(
        F.col("id").alias(id_col), "held_out", "n_tokens",
        (F.col("n_known") + F.coalesce("known", F.lit(0)) + F.lit(int(ends > 0))).alias("n_known"),
        F.lit(tokens).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("part", F.lit(0.0)) + F.lit(cost(ends))).alias("base_score"), "score",
    )
