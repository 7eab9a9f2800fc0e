"""Language ID: an interpolated Kneser-Ney character model per language, in sorted hash arrays.

Characters are the lower-cased letters of a text; any run of other characters is one space; a text starts with
marks and ends with a space. Grams of 1 to ORDER characters are 64-bit hashes in one sorted array, with a row of
interpolated log-probabilities, one for each language, and the backoff weights of contexts in another. The
language with the lowest cross-entropy per character wins. The confidence is a softmax over cross-entropies, whose
sharpness and dependence on length are fitted on labelled texts kept from training; there, too, each language gets
the cross-entropy above which a text is rejected as none of the learned ones (column rejected; lang_pred still
names the nearest).

The models are fitted on a bounded sample of the labelled texts: about MAX_DOCS for each language, chosen by a
hash of the id, one in KEPT of them for calibration. Prediction reads whole texts and nothing but the text.

Defined results: a null text, or one without a letter, is "und" with score 0; ties go to the language that sorts
first; labelled rows with a null language teach nothing; with nothing to learn from, all is "und".
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ORDER = 4
#: Bound of the sample: labelled texts of a language. One in KEPT calibrates.
MAX_DOCS, KEPT = 4000, 8
#: Share of calibration texts that are rejected.
REJECTED = 0.005
CHUNK = 1 << 20
START, SPACE = 1, 32

_MIX = np.uint64(0x9E3779B97F4A7C15)
_STIR = np.uint64(0xBF58476D1CE4E5B9)


def _letters() -> np.ndarray:
    """Each code point below 65536: itself if a letter, else a space."""
    return np.array([c if chr(c).isalpha() else SPACE for c in range(1 << 16)], np.uint32)


def symbols(texts: list[str | None], letters: np.ndarray, order: int = ORDER) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(symbols of all texts, text of each symbol, letters of each text)."""
    low = [(t or "").lower() for t in texts]
    sizes = np.fromiter((len(t) + order for t in low), np.int64, len(low))  # order - 1 marks before, a space after
    marks = " " * (order - 1)
    raw = np.frombuffer((marks + (" " + marks).join(low) + " ").encode("utf-32-le", "surrogatepass"), "<u4")
    out = letters[np.minimum(raw, 0xFFFF)]
    high = np.flatnonzero(raw > 0xFFFF)
    if len(high):
        kinds, own = np.unique(raw[high], return_inverse=True)
        out[high] = np.array([c if chr(c).isalpha() else SPACE for c in kinds.tolist()], np.uint32)[own]
    begin = np.cumsum(sizes) - sizes
    text = np.repeat(np.arange(len(low)), sizes)
    for j in range(order - 1):
        out[begin + j] = START
    again = np.zeros(len(out), bool)
    again[1:] = (out[1:] == SPACE) & ((out[:-1] == SPACE) | (out[:-1] == START))
    n_letters = np.bincount(text, weights=(out > SPACE), minlength=len(low)).astype(np.int64)
    return out[~again], text[~again], n_letters


def hashes(sym: np.ndarray, order: int = ORDER) -> list[np.ndarray]:
    """For 1 to order: at each place, the hash of so many symbols that end there. Places short of that wrap round."""
    wide = sym.astype(np.uint64) * _STIR
    out, total = [], np.zeros(len(sym), np.uint64)
    with np.errstate(over="ignore"):
        factor = np.uint64(1)
        for j in range(order):
            total = total + (np.roll(wide, j) + np.uint64(j + 1)) * factor
            factor = factor * _MIX
            h = total ^ (total >> np.uint64(31))
            out.append(h * _STIR)
    return out


def _grams(languages: list[str], order: int):
    """Counts of the grams of each language: (lang, size, gram, context, shorter, n)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        letters = _letters()
        place = {x: i for i, x in enumerate(languages)}
        for batch in batches:
            texts = batch.column("text").to_pylist()
            langs = np.array([place[x] for x in batch.column("lang").to_pylist()])
            for lang in np.unique(langs).tolist():
                own = [texts[i] for i in np.flatnonzero(langs == lang).tolist()]
                at = 0
                while at < len(own):
                    end, size = at, 0
                    while end < len(own) and (end == at or size < CHUNK):
                        size += len(own[end] or "")
                        end += 1
                    sym, _, _ = symbols(own[at:end], letters, order)
                    h = hashes(sym, order)
                    real = np.flatnonzero(sym != START)
                    at = end
                    for size in range(1, order + 1):
                        if not len(real):
                            continue
                        gram, first, n = np.unique(h[size - 1][real], return_index=True, return_counts=True)
                        where = real[first]
                        none = np.zeros(len(gram), np.uint64)
                        yield pa.RecordBatch.from_arrays(
                            [
                                pa.array(np.full(len(gram), lang, np.int32)), pa.array(np.full(len(gram), size, np.int32)), pa.array(gram.view(np.int64)),
                                pa.array((h[size - 2][where - 1] if size > 1 else none).view(np.int64)),
                                pa.array((h[size - 2][where] if size > 1 else none).view(np.int64)), pa.array(n.astype(np.int64)),
                            ],
                            names=["lang", "size", "gram", "context", "shorter", "n"],
                        )

    return run


def _row(keys: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Row of each wanted hash in sorted keys, or -1."""
    if not len(keys):
        return np.full(len(wanted), -1)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where(keys[at] == wanted, at, -1)


def fit(size: np.ndarray, lang: np.ndarray, gram: np.ndarray, context: np.ndarray, shorter: np.ndarray, n: np.ndarray, n_langs: int, order: int = ORDER) -> dict:
    """Interpolated Kneser-Ney of every language over all their grams, as sorted hash arrays."""
    model: dict = {"grams": [], "logs": [], "contexts": [], "backoff": [], "order": order}
    below: np.ndarray | None = None  # probabilities of the next shorter grams, by row
    for k in range(1, order + 1):
        here = size == k
        keys, row = np.unique(gram[here], return_inverse=True)
        count = np.zeros((len(keys), n_langs))
        if k == order:
            np.add.at(count, (row, lang[here]), n[here])
        else:  # in how many longer grams of the language it ends
            longer = size == k + 1
            at = _row(keys, shorter[longer])
            np.add.at(count, (at[at >= 0], lang[longer][at >= 0]), 1)
        any_row = np.zeros(len(keys), np.int64)
        any_row[row] = np.flatnonzero(here)
        if k == 1:
            contexts, own = np.zeros(1, np.uint64), np.zeros(len(keys), np.int64)
        else:
            contexts, own = np.unique(context[any_row], return_inverse=True)
        total, kinds = np.zeros((len(contexts), n_langs)), np.zeros((len(contexts), n_langs))
        np.add.at(total, own, count)
        np.add.at(kinds, own, count > 0)
        once, twice = (count == 1).sum(axis=0), (count == 2).sum(axis=0)
        discount = np.where(once + twice > 0, once / np.maximum(once + 2 * twice, 1), 0.5).clip(0.1, 0.95)
        with np.errstate(divide="ignore", invalid="ignore"):
            rest = np.where(total > 0, discount * kinds / total, 1.0)
            seen = np.where(total[own] > 0, np.maximum(count - discount, 0) / total[own], 0.0)
        if k == 1:
            p = seen + rest[own] / (len(keys) + 1)
            model["unknown"] = np.log(rest[0] / (len(keys) + 1)).astype(np.float32)
        else:
            p = seen + rest[own] * below[_row(model["grams"][-1], shorter[any_row])]
        model["grams"].append(keys)
        model["logs"].append(np.log(p).astype(np.float32))
        model["contexts"].append(contexts)
        model["backoff"].append(np.log(rest).astype(np.float32))
        below = p
    return model


def with_index(model: dict) -> dict:
    """Adds, to each sorted array, where the hashes with the same leading bits begin."""

    def index(keys: np.ndarray) -> tuple[int, np.ndarray, int]:
        bits = max(1, min(22, len(keys).bit_length() + 1))
        edges = np.searchsorted(keys >> np.uint64(64 - bits), np.arange((1 << bits) + 1, dtype=np.uint64)).astype(np.int32)
        return bits, edges, int(np.diff(edges).max()) if len(keys) else 0

    return model | {"gram_index": [index(k) for k in model["grams"]], "context_index": [index(k) for k in model["contexts"]]}


def _find(keys: np.ndarray, index: tuple[int, np.ndarray, int], wanted: np.ndarray) -> np.ndarray:
    """Row of each wanted hash, or -1: from the place of its leading bits on."""
    bits, edges, most = index
    if not len(keys):
        return np.full(len(wanted), -1)
    at = edges[(wanted >> np.uint64(64 - bits)).astype(np.int64)].astype(np.int64)
    top = len(keys) - 1
    found = np.full(len(wanted), -1)
    left = np.arange(len(wanted))
    for _ in range(most):
        got = keys[np.minimum(at, top)]
        same = got == wanted[left]
        found[left[same]] = at[same]
        on = (got < wanted[left]) & (at < top)
        if not on.any():
            break
        left, at = left[on], at[on] + 1
    return found


def log_sums(model: dict, sym: np.ndarray, text: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(log-probability of each text by each language, symbols of each text)."""
    order = model["order"]
    h = hashes(sym, order)
    left = np.flatnonzero(sym != START)
    counted = np.bincount(text[left], minlength=n)
    sums = np.zeros((n, len(model["unknown"])))

    def add(where: np.ndarray, logs: np.ndarray) -> None:
        for j in range(sums.shape[1]):
            sums[:, j] += np.bincount(text[where], weights=logs[:, j], minlength=n)

    for k in range(order, 0, -1):
        if not len(left):
            return sums, counted
        row = _find(model["grams"][k - 1], model["gram_index"][k - 1], h[k - 1][left])
        hit = row >= 0
        add(left[hit], model["logs"][k - 1][row[hit]])
        left = left[~hit]
        if k > 1 and len(left):
            row = _find(model["contexts"][k - 1], model["context_index"][k - 1], h[k - 2][left - 1])
            add(left[row >= 0], model["backoff"][k - 1][row[row >= 0]])
    add(left, np.broadcast_to(model["unknown"], (len(left), sums.shape[1])))
    return sums, counted


def _entropies(model: dict, letters: np.ndarray, texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For runs of texts: (cross-entropy per symbol by language, symbols, letters)."""
    at = 0
    while at < len(texts):
        end, size = at, 0
        while end < len(texts) and (end == at or size < CHUNK):
            size += len(texts[end] or "")
            end += 1
        sym, text, n_letters = symbols(texts[at:end], letters, model["order"])
        sums, counted = log_sums(model, sym, text, end - at)
        yield -sums / np.maximum(counted, 1)[:, None], counted, n_letters
        at = end


def confidence(entropy: np.ndarray, counted: np.ndarray, sharpness: tuple[float, float]) -> np.ndarray:
    """Softmax over languages of minus the entropies, times a scale that grows with length."""
    z = -entropy * (sharpness[0] * np.maximum(counted, 1)[:, None] ** sharpness[1])
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def calibrate(entropy: np.ndarray, counted: np.ndarray, truth: np.ndarray) -> tuple[tuple[float, float], np.ndarray]:
    """The scale with the least log loss, and each language's cross-entropy above which a text is rejected."""
    if not len(truth):
        return (1.0, 0.5), np.full(entropy.shape[1], np.inf)
    best = min(
        ((a, b) for a in (0.25, 0.5, 1, 2, 4, 8) for b in (0, 0.25, 0.5, 0.75, 1)),
        key=lambda s: -np.log(np.maximum(confidence(entropy, counted, s)[np.arange(len(truth)), truth], 1e-9)).mean(),
    )
    own = entropy[np.arange(len(truth)), truth]
    cut_at = [np.quantile(own[truth == j], 1 - REJECTED) if (truth == j).any() else np.inf for j in range(entropy.shape[1])]
    return best, np.array(cut_at)


_PREDICTED = "lang_pred string, score double, cross_entropy double, rejected boolean"


def train(labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", max_docs: int = MAX_DOCS, order: int = ORDER) -> dict:
    """A model from about max_docs texts of each language."""
    rows = labelled.select(
        F.col(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang"),
        F.pmod(F.xxhash64(F.lit(7), F.col(id_col)), F.lit(1 << 20)).alias("draw"), F.pmod(F.xxhash64(F.lit(8), F.col(id_col)), F.lit(KEPT)).alias("fold"),
    ).filter("lang IS NOT NULL AND text IS NOT NULL")
    sizes = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}  # a row for each language
    languages = sorted(sizes)
    share = F.coalesce(*[F.when(F.col("lang") == x, F.lit(int((1 << 20) * min(1.0, max_docs / sizes[x])))) for x in languages], F.lit(0)) if languages else F.lit(0)
    sample = rows.filter(F.col("draw") < share)
    spread = sample.filter("fold <> 0 OR draw IS NULL").select("text", "lang")
    counted = spread.mapInArrow(_grams(languages, order), "lang int, size int, gram long, context long, shorter long, n long")
    found = counted.groupBy("lang", "size", "gram").agg(F.min("context").alias("context"), F.min("shorter").alias("shorter"), F.sum("n").alias("n")).toArrow()
    column = lambda name: found.column(name).to_numpy()
    hashed = lambda name: column(name).astype(np.int64).view(np.uint64)
    model = fit(column("size"), column("lang"), hashed("gram"), hashed("context"), hashed("shorter"), column("n"), len(languages), order)
    model = with_index(model) | {"languages": languages, "sharpness": (1.0, 0.5), "limits": np.full(len(languages), np.inf)}
    if languages:
        held = labelled.sparkSession.sparkContext.broadcast(model)

        def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            letters = _letters()
            for batch in batches:
                entropy, counted, n_letters = (np.concatenate(x) for x in zip(*_entropies(held.value, letters, batch.column("text").to_pylist()), strict=True))
                real = np.flatnonzero(n_letters > 0)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("lang").take(pa.array(real)), pa.array(list(entropy[real]), pa.list_(pa.float64())), pa.array(counted[real].astype(np.int64))],
                    names=["lang", "entropy", "counted"],
                )

        tried = sample.filter("fold = 0").select("text", "lang").mapInArrow(measure, "lang string, entropy array<double>, counted long").toArrow()
        if tried.num_rows:
            place = {x: i for i, x in enumerate(languages)}
            truth = np.array([place[x] for x in tried.column("lang").to_pylist()])
            entropy = np.array(tried.column("entropy").to_pylist())
            model["sharpness"], model["limits"] = calibrate(entropy, tried.column("counted").to_numpy(), truth)
    return model


def predictor(context, model: dict):
    """A column function: text to lang_pred, score, cross_entropy, rejected."""
    held = context.broadcast(model)

    @F.arrow_udf(_PREDICTED)
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        model, letters = held.value, _letters()
        names = np.array([*model["languages"], "und"], dtype=object)
        for texts in batches:
            langs, scores, entropies, rejected = [], [], [], []
            for entropy, counted, n_letters in _entropies(model, letters, texts.to_pylist()):
                if entropy.shape[1] == 0:
                    entropy = np.zeros((len(n_letters), 1))
                    n_letters = np.zeros_like(n_letters)
                best = entropy.argmin(axis=1)
                real = n_letters > 0
                least = entropy[np.arange(len(best)), best]
                langs += names[np.where(real, best, len(names) - 1)].tolist()
                scores += np.where(real, confidence(entropy, counted, model["sharpness"])[np.arange(len(best)), best], 0.0).tolist()
                entropies += [x if r else None for x, r in zip(least.tolist(), real.tolist(), strict=True)]
                limits = model["limits"] if len(model["limits"]) else np.zeros(1)
                rejected += (~real | (least > limits[best])).tolist()
            yield pa.StructArray.from_arrays(
                [pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(entropies, pa.float64()), pa.array(rejected, pa.bool_())],
                names=["lang_pred", "score", "cross_entropy", "rejected"],
            )

    return run


def identify(docs: DataFrame, learn: Column, into: str, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **options) -> DataFrame:
    """docs with a struct column into; the models learn from the rows where learn holds."""
    model = train(docs.filter(learn), id_col, text_col, lang_col, **options)
    return docs.withColumn(into, predictor(docs.sparkSession.sparkContext, model)(F.col(text_col)))
