"""Byte-level BPE: ranked merges folded over the byte arrays of distinct words; decoding joins the pieces.

A text is cut into words by the pattern; a word that is itself a piece has that piece's id. All merges of other words are
folds of Spark higher-order functions: a word is an array of bytes, then of ids, and each step of the fold joins the
leftmost neighbours of least rank. The rank map is a literal: an array of buckets, by the pair of ids, of what the pair
becomes, or for the corpus's words a row of such arrays that is joined to groups of words, since Spark keeps each plan's text, literals
included, on the driver. The corpus's words are counted over all texts, and the MAX_WORDS most frequent distinct ones are folded once. With rare="fold", every
text's other distinct words are folded with their text, and decoding looks up each id's piece and concatenates the binary
pieces, in Spark as well; only words of over MAX_FOLD bytes, for which arrays that are copied in each step take time by the
square of their length, get the same merges with a heap. With rare="merge", all other words get the same merges on arrays
where they occur, those of a stretch of texts together, one pair of each word in a step. Both give the same ids.

Defined results: a null or empty text has no ids and decodes to nothing; special tokens are ordinary text; texts
are read whole; columns besides the text pass through.
"""

from __future__ import annotations

import base64
import contextlib
import heapq
import json
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densereps.llm.hashtable import find_slot, hash_table
from densereps.plans.lineage import cut, forget_unused

#: Frequent distinct words whose merges are folded once, and the longest word in bytes that is folded.
MAX_WORDS, MAX_FOLD = 1 << 16, 256
#: Codes from here on are ids of pieces; below, places of frequent words.
_PIECES = 1 << 30
#: Buckets of pairs: a prime. No rank.
_BUCKETS, _NONE = 262_139, 2**62
#: Groups that words are folded in; each meets the rank map once.
_GROUPS = 64
#: Rarer words that a task keeps at once, and the bytes of the longest one that is merged together with others.
CACHE, MAX_TOGETHER = 1 << 16, 64
_NO_PAIR = 2**31 - 1


def read_ranks(path: str) -> dict[bytes, int]:
    """A rank file of lines "base64 rank"."""
    with open(path, "rb") as lines:
        return {base64.b64decode(piece): int(rank) for piece, rank in (x.split() for x in lines if x.strip())}


def merge(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one word: the leftmost pair of least rank is joined until none has a rank."""
    if (whole := ranks.get(word)) is not None:
        return [whole]
    n = len(word)
    after, before, end = list(range(1, n + 1)), list(range(-1, n - 1)), list(range(1, n + 1))
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
    heapq.heapify(heap)
    alive = [True] * n
    while heap:
        _, i, stop = heapq.heappop(heap)
        j = after[i] if alive[i] else n
        if j >= n or end[j] != stop:
            continue
        alive[j] = False
        end[i], after[i] = stop, after[j]
        if after[i] < n:
            before[after[i]] = i
        for a, b in ((before[i], i), (i, after[i])):
            if a >= 0 and b < n and (r := ranks.get(word[a : end[b]])) is not None:
                heapq.heappush(heap, (r, a, end[b]))
    return [ranks[word[i : end[i]]] for i in range(n) if alive[i]]


def pair_table(ranks: dict[bytes, int]) -> dict:
    """For merging many words at once: single bytes' ids, and the id that each pair of ids becomes, by hashed pair."""
    pairs: dict[int, int] = {}
    for piece, rank in ranks.items():
        for k in range(1, len(piece)):
            if (a := ranks.get(piece[:k])) is not None and (b := ranks.get(piece[k:])) is not None:
                pairs[a << 32 | b] = rank
    keys = np.fromiter(pairs, np.uint64, len(pairs))
    slots, rows = hash_table(keys)
    joined = np.append(np.fromiter(pairs.values(), np.int64, len(pairs)), _NO_PAIR).astype(np.int32)
    single = np.array([ranks.get(bytes([b]), -1) for b in range(256)], np.int32)
    return {"slots": slots, "joined": joined[rows], "single": single}


def _rank_pairs(table: dict, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """What each pair of ids becomes, _NO_PAIR if nothing."""
    at = find_slot(table["slots"], a.astype(np.uint64) << np.uint64(32) | b.astype(np.uint64))
    return np.where(at >= 0, table["joined"][at], _NO_PAIR)


def merge_many(words: list[bytes], table: dict) -> list[bytes]:
    """merge() of many words of similar length at once, as little-endian 32-bit ids: a step joins one pair in each word."""
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    width = int(sizes.max())
    column = np.arange(width)
    inside = column < sizes[:, None]
    ids = np.full((len(words), width), -1, np.int32)
    ids[inside] = table["single"][np.frombuffer(b"".join(words), np.uint8)]
    ranks = np.full((len(words), width), _NO_PAIR, np.int32)
    pair = inside[:, 1:]
    ranks[:, :-1][pair] = _rank_pairs(table, ids[:, :-1][pair], ids[:, 1:][pair])
    left = np.flatnonzero(ranks.min(axis=1) < _NO_PAIR)
    live, rank = ids[left], ranks[left]
    while len(left):
        row = np.arange(len(left))
        at = rank.argmin(axis=1)  # leftmost
        live[row, at] = rank[row, at]
        shifted = np.minimum(column + (column > at[:, None]), width - 1)
        sizes[left] -= 1
        n = sizes[left]
        live = np.take_along_axis(live, shifted, axis=1)
        rank = np.take_along_axis(rank, np.minimum(column + (column >= at[:, None]), width - 1), axis=1)
        rank[row, n - 1] = _NO_PAIR
        for place in (at - 1, at):
            ok = np.flatnonzero((place >= 0) & (place + 1 < n))
            rank[ok, place[ok]] = _rank_pairs(table, live[ok, place[ok]], live[ok, place[ok] + 1])
        done = rank.min(axis=1) == _NO_PAIR
        ids[left[done]] = live[done]
        left, live, rank = left[~done], live[~done], rank[~done]
    flat = ids[column < sizes[:, None]].astype("<u4").tobytes()
    ends = (np.cumsum(sizes) * 4).tolist()
    return [flat[b - 4 * k : b] for b, k in zip(ends, sizes.tolist(), strict=True)]


def _literal(rows: list, kind: str) -> Column:
    """A literal, once the optimizer has folded it."""
    return F.from_json(F.lit(json.dumps(rows, separators=(",", ":"))), kind)


def _let(value: Column, then) -> Column:
    """then(value), with value worked out once and not copied."""
    return F.aggregate(F.array().cast("array<int>"), value, lambda held, _: held, then)


class RankMap:
    """For folding: what two ids become, the same for two bytes, and the ids of single bytes."""

    def __init__(self, ranks: dict[bytes, int]):
        self.bits = max(1, max(ranks.values(), default=0).bit_length())
        if self.bits > 20:
            raise ValueError("a pair and what it becomes must fit into 62 bits")
        buckets: list[list[int]] = [[] for _ in range(_BUCKETS)]
        first = [_NONE] * 65_536
        for piece, rank in ranks.items():
            if len(piece) == 2:
                first[piece[0] * 256 + piece[1]] = rank
            for k in range(1, len(piece)):
                if (x := ranks.get(piece[:k])) is not None and (y := ranks.get(piece[k:])) is not None:
                    pair = x << self.bits | y
                    buckets[pair % _BUCKETS].append(pair << self.bits | rank)
        self.held = {"pairs": buckets, "first": first, "single": [ranks.get(bytes([i]), -1) for i in range(256)]}

    def literals(self) -> list[Column]:
        return [_literal(self.held[c], kind) for c, kind in (("pairs", "array<array<long>>"), ("first", "array<long>"), ("single", "array<long>"))]

    def table(self, spark: SparkSession) -> DataFrame:
        """One row (pairs, first, single)."""
        longs = pa.list_(pa.int64())
        kinds = {"pairs": pa.list_(longs), "first": longs, "single": longs}
        return spark.createDataFrame(pa.table({c: pa.array([self.held[c]], kind) for c, kind in kinds.items()}))

    def folder(self, then, tables: list[Column] | None = None) -> Column:
        """then(f), where f(bytes) are the ids of an array of bytes, merged by higher-order functions; tables: columns of table(), else literals."""
        bits, long = self.bits, lambda n: F.lit(n).cast("long")
        empty = F.array().cast("array<long>")

        def with_tables(pairs: Column, first: Column, single: Column) -> Column:
            def rank(x: Column, y: Column) -> Column:
                def find(pair: Column) -> Column:
                    met = F.filter(F.get(pairs, (pair % long(_BUCKETS)).cast("int")), lambda e: F.shiftright(e, bits) == pair)
                    return F.coalesce(F.get(met, F.lit(0)).bitwiseAND(long((1 << bits) - 1)), long(_NONE))

                return _let(x * long(1 << bits) + y, find)

            def step(state: Column, _: Column) -> Column:
                """ids, and the rank of each with its right neighbour; the rank of a pair is the id that it becomes."""
                ids, rs = state["ids"], state["rs"]

                def join(low: Column) -> Column:
                    def put(at: Column) -> Column:  # from 1
                        n = F.size(ids)
                        left = F.when(at > 1, F.array(rank(F.get(ids, at - 2), low))).otherwise(empty)
                        right = F.when(at + 1 < n, rank(low, F.get(ids, at + 1))).otherwise(long(_NONE))
                        return F.struct(
                            F.concat(F.slice(ids, F.lit(1), at - 1), F.array(low), F.slice(ids, at + 2, n)).alias("ids"),
                            F.concat(F.slice(rs, F.lit(1), F.greatest(at - 2, F.lit(0))), left, F.array(right), F.slice(rs, at + 2, n)).alias("rs"),
                        )

                    return F.when(low < long(_NONE), _let(F.array_position(rs, low).cast("int"), put))

                return F.coalesce(_let(F.array_min(rs), join), state)

            def fold(word: Column) -> Column:
                n = F.size(word)
                pair = lambda x, i: (x * long(256) + F.get(word, i + 1)).cast("int")
                rs = F.transform(word, lambda x, i: F.when(i < n - 1, F.get(first, pair(x, i))).otherwise(long(_NONE)))
                ids = F.transform(word, lambda x: F.get(single, x.cast("int")))
                return F.aggregate(F.slice(word, F.lit(2), n), F.struct(ids.alias("ids"), rs.alias("rs")), step)["ids"]

            return then(fold)

        pairs, first, single = tables or self.literals()
        return _let(pairs, lambda p: _let(first, lambda f: _let(single, lambda s: with_tables(p, f, s))))


def bytes_of(word: Column) -> Column:
    """A binary as an array of its bytes."""
    n = F.octet_length(word)
    places = F.when(n > 0, F.sequence(F.lit(1), n)).otherwise(F.array().cast("array<int>"))
    return F.transform(places, lambda i: F.conv(F.hex(F.substring(word, i, F.lit(1))), 16, 10).cast("long"))


def fold_words(words: DataFrame, ranks: dict[bytes, int], word: str = "word") -> DataFrame:
    """words(word binary) with ids."""
    ranked = RankMap(ranks)
    group = F.pmod(F.xxhash64(word), F.lit(_GROUPS)).alias("group")
    groups = words.select(group, F.col(word).alias("word")).repartition(_GROUPS, "group").groupBy("group").agg(F.collect_list("word").alias("words"))
    ids = ranked.folder(lambda fold: F.transform("words", lambda w: fold(bytes_of(w)).cast("array<int>")), [F.col(c) for c in ranked.held])
    folded = groups.crossJoin(F.broadcast(ranked.table(words.sparkSession))).select("words", ids.alias("ids"))  # the table is one row
    return folded.select(F.explode(F.arrays_zip("words", "ids")).alias("w")).select(F.col("w.words").alias(word), "w.ids")


def _texts_of(ranks: dict[bytes, int]) -> dict[str, int]:
    """The pieces that are whole words of text."""
    out = {}
    for piece, rank in ranks.items():
        with contextlib.suppress(UnicodeDecodeError):
            out[piece.decode()] = rank
    return out


def _counts(held, pattern: str, max_fold: int, flush: int = 1 << 18):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find, pieces = regex.compile(pattern).findall, held.value
        seen: Counter[str] = Counter()

        def out() -> pa.RecordBatch:
            kept = [(k, n) for w, n in seen.items() if w not in pieces and len(k := w.encode()) <= max_fold]
            return pa.RecordBatch.from_arrays(
                [pa.array([k for k, _ in kept], pa.binary()), pa.array([n for _, n in kept], pa.int64())], names=["word", "n"]
            )

        for batch in batches:
            for text in batch.column(0).to_pylist():
                if text:
                    seen.update(find(text))
                if len(seen) > flush:
                    yield out()
                    seen.clear()
        if seen:
            yield out()

    return run


def frequent_words(
    docs: DataFrame, pattern: str, ranks: dict[bytes, int], text_col: str = "text", max_words: int = MAX_WORDS, max_fold: int = MAX_FOLD
) -> DataFrame:
    """(word): those of at least so high a count over all texts that there are max_words at most; no pieces, none that occurs once.

    Counted in each task before the shuffle. Counts fall into classes of equal ratio, of which the driver gets the sizes.
    """
    held = docs.sparkSession.sparkContext.broadcast(_texts_of(ranks))
    partial = docs.select(text_col).mapInArrow(_counts(held, pattern, max_fold), "word binary, n long")
    counts = cut(partial.groupBy("word").agg(F.sum("n").alias("n")).filter("n > 1"))
    kind = F.floor(F.log2("n") * 8)
    sizes = {r["k"]: r["m"] for r in counts.groupBy(kind.alias("k")).agg(F.count(F.lit(1)).alias("m")).collect()}
    total, least = 0, max(sizes, default=0) + 1
    for k in sorted(sizes, reverse=True):
        total += sizes[k]
        if total > max_words:
            break
        least = k
    return counts.filter(kind >= least).select("word")


def _cutter(spark: SparkSession, known: dict[str, int], ranks: dict[bytes, int], pattern: str, max_fold: int):
    """A column function: text to codes of its words, in order, and the distinct words that the codes below zero stand for.

    Words are arrays of bytes; those over max_fold bytes are empty, and come with their ids in long.
    """
    held = spark.sparkContext.broadcast((known, ranks))
    lists = lambda at, flat: pa.ListArray.from_arrays(pa.array(at, pa.int32()), flat)

    @F.arrow_udf("codes array<int>, words array<array<long>>, long array<array<int>>")
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        find = regex.compile(pattern).findall
        place, ranked = held.value

        class Codes(dict):
            """Codes of a text's words; a word that isn't known gets the next one below zero."""

            def __missing__(self, word: str) -> int:
                code = place.get(word)
                if code is None:
                    code = -1 - len(new)
                    new.append(word)
                self[word] = code
                return code

        for texts in batches:
            codes, code_at, words, word_at, long, long_at = [], [0], [], [0], [], [0]
            for text in texts.to_pylist():
                new: list[str] = []
                codes.append(np.fromiter(map(Codes().__getitem__, find(text) if text else ()), np.int32))
                code_at.append(code_at[-1] + len(codes[-1]))
                raw = [w.encode() for w in new]
                if any(len(w) > max_fold for w in raw):
                    long += [merge(w, ranked) if len(w) > max_fold else None for w in raw]
                    raw = [w if len(w) <= max_fold else b"" for w in raw]
                words += raw
                word_at.append(len(words))
                long_at.append(len(long))
            flat = np.frombuffer(b"".join(words), np.uint8).astype(np.int64)
            ends = np.cumsum([0, *map(len, words)])
            yield pa.StructArray.from_arrays(
                [
                    lists(code_at, pa.array(np.concatenate([np.zeros(0, np.int32), *codes]))), lists(word_at, lists(ends, pa.array(flat))),
                    lists(long_at, pa.array(long, pa.list_(pa.int32()))),
                ],
                names=["codes", "words", "long"],
            )

    return run


def _bytes_table(rows: list[bytes]) -> Column:
    """A literal array of binary values, once the optimizer has folded it."""
    return _literal([base64.b64encode(x).decode() for x in rows], "array<binary>")


def _joined(parts: Column) -> Column:
    """The binary values of an array, concatenated."""
    return F.array_join(F.transform(parts, lambda x: x.cast("string")), "").cast("binary")


def pack_ids(ids: Column, ranks: dict[bytes, int]) -> Column:
    """An array of ids as little-endian unsigned 32-bit integers."""
    table = _bytes_table([i.to_bytes(4, "little") for i in range(max(ranks.values(), default=-1) + 1)])
    return _let(table, lambda t: _joined(F.transform(ids, lambda i: F.get(t, i))))


def decode(ids: Column, ranks: dict[bytes, int]) -> Column:
    """The pieces of an array of ids, concatenated."""
    pieces = [b""] * (max(ranks.values(), default=-1) + 1)
    for piece, i in ranks.items():
        pieces[i] = piece
    return _let(_bytes_table(pieces), lambda t: _joined(F.transform(ids, lambda i: F.get(t, i))))


def encode(docs: DataFrame, into: str, path: str, pattern: str, text_col: str = "text", max_words: int = MAX_WORDS, max_fold: int = MAX_FOLD) -> DataFrame:
    """docs with an array column into: the ids of each text."""
    ranks = read_ranks(path)
    words = frequent_words(docs, pattern, ranks, text_col, max_words, max_fold)
    folded = fold_words(words, ranks).collect()  # at most max_words short words
    known = {bytes(r["word"]).decode(): k for k, r in enumerate(folded)} | {w: _PIECES + rank for w, rank in _texts_of(ranks).items()}
    frequent = _literal([r["ids"] for r in folded], "array<array<int>>")
    del folded
    cut_up = f"{into}__cut"
    while cut_up in docs.columns:
        cut_up += "_"
    coded = docs.withColumn(cut_up, _cutter(docs.sparkSession, known, ranks, pattern, max_fold)(F.col(text_col)))
    codes, rare, long = (F.col(cut_up)[x] for x in ("codes", "words", "long"))
    own = RankMap(ranks).folder(
        lambda fold: F.transform(rare, lambda w, k: F.when(F.size(w) > 0, fold(w).cast("array<int>")).otherwise(F.get(long, k)))
    )

    def told(frequent: Column, own: Column) -> Column:
        one = lambda c: F.when(c >= _PIECES, F.array(c - F.lit(_PIECES))).when(c >= 0, F.get(frequent, c)).otherwise(F.get(own, -1 - c))
        return F.flatten(F.transform(codes, one))

    return coded.withColumn(into, _let(frequent, lambda f: _let(own, lambda o: told(f, o)))).drop(cut_up)


CODES = "ids binary, n_tokens long, decoded binary"


def _coder(spark: SparkSession, packed: dict[str, bytes], ranks: dict[bytes, int], pattern: str, size: int = 1 << 19):
    held = spark.sparkContext.broadcast((packed, ranks, pair_table(ranks)))

    @F.arrow_udf(CODES)
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        find = regex.compile(pattern).findall
        packed, ranked, table = held.value
        pieces = [b""] * (max(ranked.values(), default=-1) + 1)
        for piece, rank in ranked.items():
            pieces[rank] = piece
        rare: dict[str, bytes] = {}

        def learn(words: set[str]) -> None:
            """Merges words in groups of similar length; long ones one by one."""
            groups: dict[int, list[tuple[str, bytes]]] = {}
            for word in words:
                raw = word.encode()
                whole = ranked.get(raw)
                if whole is not None:
                    rare[word] = whole.to_bytes(4, "little")
                elif len(raw) > MAX_TOGETHER:
                    rare[word] = b"".join([i.to_bytes(4, "little") for i in merge(raw, ranked)])
                else:
                    groups.setdefault(-(-len(raw) // 4), []).append((word, raw))
            for group in groups.values():
                for at in range(0, len(group), 1 << 14):
                    part = group[at : at + (1 << 14)]
                    rare.update(zip([w for w, _ in part], merge_many([r for _, r in part], table), strict=True))

        for texts in batches:
            ids, back, at, all_texts = [], [], 0, texts.to_pylist()
            while at < len(all_texts):
                end, held_size = at, 0
                while end < len(all_texts) and (end == at or held_size < size):
                    held_size += len(all_texts[end] or "")
                    end += 1
                found = [find(t) if t else [] for t in all_texts[at:end]]
                needed = set().union(*found).difference(packed)
                if len(rare) + len(needed) > CACHE:
                    rare.clear()
                learn(needed.difference(rare))
                for words in found:
                    raw = b"".join([packed.get(w) or rare[w] for w in words])
                    ids.append(raw)
                    back.append(decode_ids(raw, pieces))
                at = end
            yield pa.StructArray.from_arrays(
                [pa.array(ids, pa.binary()), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(back, pa.binary())],
                names=["ids", "n_tokens", "decoded"],
            )

    return run


def decode_ids(raw: bytes, pieces: list[bytes]) -> bytes:
    """The pieces of little-endian 32-bit ids, concatenated."""
    return b"".join(map(pieces.__getitem__, np.frombuffer(raw, "<u4").tolist()))


def encode_and_decode(
    docs: DataFrame, into: str, path: str, pattern: str, text_col: str = "text", max_words: int = MAX_WORDS, max_fold: int = MAX_FOLD, rare: str = "merge"
) -> DataFrame:
    """docs with a struct column into: ids as little-endian unsigned 32-bit integers, n_tokens, and the decoded bytes.

    rare: what becomes of words beyond the max_words most frequent. fold: they are folded with their text, and ids are
    packed and decoded by Spark functions. merge: a task merges them by the same rule on arrays, and packs and decodes.
    """
    if rare not in ("fold", "merge"):
        raise ValueError("rare is fold or merge")
    ranks = read_ranks(path)
    if rare == "merge":
        forget_unused(docs.sparkSession)  # the fold's literals are large on the driver: before and after them its heap shrinks
        words = frequent_words(docs, pattern, ranks, text_col, max_words, min(max_fold, 24))
        packed = {w: rank.to_bytes(4, "little") for w, rank in _texts_of(ranks).items()}
        for r in fold_words(words, ranks).collect():  # at most max_words short words
            packed[bytes(r["word"]).decode()] = b"".join(i.to_bytes(4, "little") for i in r["ids"])
        del words
        forget_unused(docs.sparkSession)
        return docs.withColumn(into, _coder(docs.sparkSession, packed, ranks, pattern)(F.col(text_col)))
    made = lambda ids: F.struct(pack_ids(ids, ranks).alias("ids"), F.size(ids).cast("long").alias("n_tokens"), decode(ids, ranks).alias("decoded"))
    own = f"{into}__ids"
    while own in docs.columns:
        own += "_"
    coded = encode(docs, own, path, pattern, text_col, max_words, max_fold)
    return coded.withColumn(into, _let(F.col(own), made)).drop(own)
