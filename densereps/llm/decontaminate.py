"""Benchmark decontamination: test n-grams in a broadcast hash set, token windows of the training texts against it.

A window is n consecutive words of an item (all of a shorter, non-empty one). Window hashes are looked up in a
bitmap and a set; each hit is then verified word by word. The set is broadcast while the benchmark is within
max_bytes; a larger benchmark is taken in blocks of at most that size, one pass of the texts for each block.

Defined results: a null or empty text has no words and is clean; an item with a null text has no windows; an
item with a null id marks words but has no id to report; items with the same id count once. Texts are read
whole. Only the id and text columns are read, so other columns never clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from densereps.llm.textbytes import Words, buffers, chunks, per_text, powers, words
from densereps.plans.lineage import cut

N = 13
#: Bytes of benchmark text in one broadcast set.
MAX_BYTES = 32 << 20
_FACTOR = np.uint64(0xC2B2AE3D27D4EB4F)
_BITS = 20

RESULT = "n_words long, n_hit long, item_ids array<string>, spans array<struct<word: int, words: int, start: int, bytes: int>>"


def _joined(w: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The words with one space between, and where each begins and ends."""
    lengths = w.end - w.start
    begins = np.cumsum(lengths + 1) - (lengths + 1)
    out = np.full(int((lengths + 1).sum()), 32, np.uint8)
    inner = np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    out[np.repeat(begins, lengths) + inner] = w.lowered[np.repeat(w.start, lengths) + inner]
    return out, begins, begins + lengths


def _hashes(w: Words, length: int) -> np.ndarray:
    """Hash of each window of so many words, crossing texts or not."""
    n = len(w.hash) - length + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    with np.errstate(over="ignore"):
        for j, p in enumerate(powers(_FACTOR, length)):
            total += w.hash[j : j + n] * p
    return total


def window_set(items: list[tuple[str | None, str | None]], n: int = N) -> dict:
    """All windows of a block of items, plain data for a broadcast.

    ids: of the items; exact: by window length, each window's words and the items that hold it; bitmap: by
    window length, the leading bits of the hashes.
    """
    exact: dict[int, dict[bytes, set[int]]] = {}
    for first, _, data, at in chunks(pa.array([t for _, t in items], pa.string())):
        w = words(data, at)
        text, begins, ends = _joined(w)
        whole = text.tobytes()
        start = 0
        for k, count in enumerate(np.bincount(w.text, minlength=len(at) - 1).tolist()):
            length = min(n, count)
            for i in range(start, start + count - length + 1) if length else ():
                key = whole[begins[i] : ends[i + length - 1]]
                exact.setdefault(length, {}).setdefault(key, set()).add(first + k)
            start += count
    bitmap: dict[int, np.ndarray] = {}
    for length, known in exact.items():
        w = words(*buffers(pa.array([k.decode() for k in known], pa.string())))
        bitmap[length] = np.zeros(1 << _BITS, bool)
        bitmap[length][(_hashes(w, length)[::length] >> np.uint64(64 - _BITS)).astype(np.int64)] = True
    return {"ids": [i for i, _ in items], "exact": exact, "bitmap": bitmap}


def _scan(texts: pa.Array, windows: dict) -> pa.Array:
    n_words: list[np.ndarray] = []
    n_hit: list[np.ndarray] = []
    found: list[list[str]] = []
    spans: list[list[dict]] = []
    for first, last, data, at in chunks(texts):
        w = words(data, at)
        n = last - first
        mark = np.zeros(len(w.hash) + 1, np.int32)
        items: dict[int, set[int]] = {}
        joined: tuple[bytes, np.ndarray, np.ndarray] | None = None
        for length, known in windows["exact"].items():
            h = _hashes(w, length)
            near = np.flatnonzero(windows["bitmap"][length][(h >> np.uint64(64 - _BITS)).astype(np.int64)])
            near = near[w.text[near] == w.text[near + length - 1]]
            if len(near) and joined is None:
                text, begins, ends = _joined(w)
                joined = text.tobytes(), begins, ends
            for i in near.tolist():
                whole, begins, ends = joined
                if (holders := known.get(whole[begins[i] : ends[i + length - 1]])) is not None:
                    mark[i] += 1
                    mark[i + length] -= 1
                    items.setdefault(int(w.text[i]), set()).update(holders)
        hit = np.cumsum(mark[:-1]) > 0
        n_words.append(per_text(np.ones(len(w.text)), w.text, n))
        n_hit.append(per_text(hit.astype(np.float64), w.text, n))
        own: list[list[dict]] = [[] for _ in range(n)]
        if hit.any():
            base = np.searchsorted(w.text, np.arange(n))
            new = hit.copy()
            new[1:] &= ~hit[:-1] | (w.text[1:] != w.text[:-1])
            end = hit.copy()
            end[:-1] &= ~hit[1:] | (w.text[1:] != w.text[:-1])
            for a, b in zip(np.flatnonzero(new).tolist(), np.flatnonzero(end).tolist(), strict=True):
                t = int(w.text[a])
                own[t].append({"word": a - int(base[t]), "words": b + 1 - a, "start": int(w.start[a] - at[t]), "bytes": int(w.end[b] - w.start[a])})
        spans += own
        found += [sorted({x for i in items.get(t, ()) if (x := windows["ids"][i]) is not None}) for t in range(n)]
    flat = lambda parts: np.concatenate(parts).astype(np.int64) if parts else np.zeros(0, np.int64)
    return pa.StructArray.from_arrays(
        [
            pa.array(flat(n_words)), pa.array(flat(n_hit)), pa.array(found, pa.list_(pa.string())),
            pa.array(spans, pa.list_(pa.struct([(x, pa.int32()) for x in ("word", "words", "start", "bytes")]))),
        ],
        names=["n_words", "n_hit", "item_ids", "spans"],
    )


def _scanner(docs: DataFrame, items: list[tuple[str | None, str | None]], n: int):
    held = docs.sparkSession.sparkContext.broadcast(window_set(items, n))

    @F.arrow_udf(RESULT)
    def scan(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield _scan(texts, held.value)

    return scan


def is_contaminated(scan: Column, share: int = 20) -> Column:
    """At least one word in share is hit."""
    return (scan["n_hit"] > 0) & (scan["n_hit"] * share >= scan["n_words"])


def scan_contamination(
    docs: DataFrame, benchmark: DataFrame, into: str, id_col: str = "item_id", item_text: str = "text",
    text_col: str = "text", n: int = N, max_bytes: int = MAX_BYTES,
) -> DataFrame:
    """docs with a struct column into: n_words, n_hit, item_ids (sorted as strings), spans of hit words."""
    items = benchmark.select(F.col(id_col).cast("string").alias("i"), F.col(item_text).alias("t"))
    total = items.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0)).alias("b")).first()["b"]
    blocks = max(1, -(-total // max_bytes))
    if blocks == 1:
        rows = [tuple(r) for r in items.collect()]
        return docs.withColumn(into, _scanner(docs, rows, n)(F.col(text_col)))
    block = F.pmod(F.xxhash64("i", "t"), F.lit(2 * blocks))
    for k in range(2 * blocks):
        rows = [tuple(r) for r in items.filter(block == k).collect()]
        one = _scanner(docs, rows, n)(F.col(text_col))
        if k == 0:
            docs = cut(docs.withColumn(into, one))
            continue
        fresh = f"{into}_{k}"
        both = cut(docs.withColumn(fresh, one))
        every = F.array_sort(F.array_union(f"`{into}`.spans", f"`{fresh}`.spans"))
        hit = F.array_distinct(
            F.flatten(F.transform(every, lambda s: F.sequence(s["word"], s["word"] + s["words"] - 1)))
        )
        merged = F.struct(
            F.col(into)["n_words"].alias("n_words"), F.size(hit).cast("long").alias("n_hit"),
            F.array_sort(F.array_union(f"`{into}`.item_ids", f"`{fresh}`.item_ids")).alias("item_ids"), every.alias("spans"),
        )
        docs = both.withColumn(into, merged).drop(fresh)
    return docs


def _without(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
    for texts, spans in batches:
        out = []
        for text, cuts in zip(texts.to_pylist(), spans.to_pylist(), strict=True):
            if text is not None and cuts:
                raw, kept, at = text.encode(), [], 0
                for s in sorted(cuts, key=lambda x: x["start"]):
                    kept.append(raw[at : max(at, s["start"])])
                    at = max(at, s["start"] + s["bytes"])
                text = b"".join([*kept, raw[at:]]).decode()
            out.append(text)
        yield pa.array(out, pa.string())


def remove_contamination(docs: DataFrame, benchmark: DataFrame, how: str = "documents", text_col: str = "text", **options) -> DataFrame:
    """docs without contaminated rows (how="documents"), or with the hit spans cut out of the texts (how="spans")."""
    own = "__contamination"
    while own in docs.columns:
        own += "_"
    seen = scan_contamination(docs, benchmark, own, text_col=text_col, **options)
    if how == "documents":
        return seen.filter(~is_contaminated(F.col(own))).drop(own)
    if how == "spans":
        return seen.withColumn(text_col, F.arrow_udf(_without, "string")(F.col(text_col), F.col(own)["spans"])).drop(own)
    raise ValueError(f"how is documents or spans, not {how!r}")
