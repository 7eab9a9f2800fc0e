"""Toxicity: a chain of linear classifiers, each fed the probabilities of the categories before it.

Features of a text are the presence of its lower-cased words and of their first STEMS bytes. For each category,
in order, the features whose presence differs most between the classes are selected and a ridge logistic model is
fitted on them and on the probabilities of the earlier categories. In training those are out-of-fold: each row's
comes from a model, features selected anew, that has not seen the row. The threshold of each category is the one
with the best F1 out of fold.

The chain is fitted on a bounded sample of labelled rows: about MAX_ROWS, chosen by a hash of the id. Spark counts each
feature's rows by fold and class and selects the features; the driver gets the selected ones and the rows that have them.
Scoring reads whole texts.

Defined results: a null or empty text has no features, so it gets the models' intercepts; labels that repeat an id
count as their maximum; labels with a null in a category teach that chain nothing; a category with one class in
the sample gets its constant share, and with no labels at all probability 0, so nothing is rejected.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from densereps.llm.textbytes import chunks, words
from densereps.plans.lineage import stored

#: Bound of the labelled sample, of the selected features, and the folds.
MAX_ROWS, MAX_FEATURES, FOLDS = 6000, 384, 5
STEMS = (3, 4, 5, 6)
#: A category's name, its label column, and the label that means it.
CATEGORIES = (("low_quality", "quality", 0), ("toxic", "toxic", 1))
RIDGE, MIN_ROWS, MIN_SCORE = 1.0, 4, 4.0
_BITS = 18


def features(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text, feature) of all words and stems, repeats included."""
    w = words(data, at, stems=STEMS)
    return np.tile(w.text, 1 + len(STEMS)), np.concatenate([w.hash, *[w.stems[k] for k in STEMS]])


def _distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = []
        for _, _, data, at in chunks(batch.column("text")):
            text, feature = features(data, at)
            by = np.lexsort((feature, text))
            text, feature = text[by], feature[by]
            new = np.ones(len(text), bool)
            new[1:] = (text[1:] != text[:-1]) | (feature[1:] != feature[:-1])
            text, feature = text[new], feature[new].view(np.int64)
            sets += np.split(feature, np.searchsorted(text, np.arange(1, len(at) - 1)))
        yield pa.RecordBatch.from_arrays(
            [*[batch.column(i) for i in range(batch.num_columns - 1)], pa.array(sets, pa.list_(pa.int64()))],
            names=[*batch.schema.names[:-1], "features"],
        )


def select(rows: DataFrame, names: list[str], folds: int = FOLDS, most: int = MAX_FEATURES) -> DataFrame:
    """(category, fold, feature) of rows(fold, features, a boolean for each category): what the models of fold may use.

    Fold k's come from the rows of the other folds, fold `folds`' from all. A feature counts if its presence among the
    positives differs enough from chance, in units of its deviation; the most telling ones are kept.
    """
    counted = ["true", *[f"`{name}`" for name in names]]
    spread = lambda: [F.sum(F.expr(f"int(fold = {k} AND {c})")).alias(f"n{j}_{k}") for j, c in enumerate(counted) for k in range(folds)]
    whole = rows.agg(*spread())
    each = rows.select("fold", *names, F.explode("features").alias("feature")).groupBy("feature").agg(*spread())
    every = [f"n0_{k}" for k in range(folds)]
    each = each.filter(F.expr("+".join(every)) >= MIN_ROWS)
    total = whole.select([F.coalesce(c, F.lit(0)).alias(f"t{c}") for c in whole.columns])

    def left(prefix: str, k: int) -> Column:
        return F.expr(" + ".join(f"{prefix}_{f}" for f in range(folds) if f != k)).cast("double")

    cases = []
    for j, name in enumerate(names):
        for k in range(folds + 1):
            df, hits, n = left("n0", k), left(f"n{j + 1}", k), left("tn0", k)
            positive = left(f"tn{j + 1}", k) / F.greatest(n, F.lit(1.0))
            deviation = F.sqrt(F.greatest(df * positive * (1 - positive) * (1 - df / (n + 1)), F.lit(1e-9)))
            cases.append(F.struct(F.lit(name).alias("category"), F.lit(k).alias("fold"), df.alias("df"), (F.abs(hits - df * positive) / deviation).alias("score")))
    scored = each.crossJoin(F.broadcast(total)).select("feature", F.explode(F.array(*cases)).alias("c")).select("feature", "c.*")  # total is one row
    rank = F.row_number().over(Window.partitionBy("category", "fold").orderBy(F.desc("score"), "feature"))
    told = scored.filter((F.col("df") >= MIN_ROWS) & (F.col("score") >= MIN_SCORE))
    return told.withColumn("rank", rank).filter(F.col("rank") <= most).select("category", "fold", "feature")


def design(row: np.ndarray, feature: np.ndarray, chosen: np.ndarray, earlier: np.ndarray) -> np.ndarray:
    """Presence of the chosen features, sorted, in every row, then the earlier categories' probabilities, then one."""
    x = np.zeros((len(earlier), len(chosen) + earlier.shape[1] + 1))
    if len(chosen):
        at = np.minimum(np.searchsorted(chosen, feature), len(chosen) - 1)
        hit = chosen[at] == feature
        x[row[hit], at[hit]] = 1
    x[:, len(chosen) : -1] = earlier
    x[:, -1] = 1
    return x


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = RIDGE, steps: int = 25, part: int = 1000) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the intercept is free. Sums go by parts of the rows, to spare memory."""
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    w[-1] = np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))
    for _ in range(steps):
        p = sigmoid(x @ w)
        curve = np.diag(penalty)
        for at in range(0, len(y), part):
            rows, q = x[at : at + part], p[at : at + part]
            curve += (rows * (q * (1 - q))[:, None]).T @ rows
        step = np.linalg.solve(curve, x.T @ (y - p) - penalty * w)
        w += step
        if np.abs(step).max() < 1e-4:
            break
    return w


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit_chain(row: np.ndarray, feature: np.ndarray, labels: np.ndarray, fold: np.ndarray, chosen: list[list[np.ndarray]]) -> list[dict]:
    """One model for each column of labels: features, weights (earlier probabilities and one last), threshold.

    (row, feature) are the selected features that the rows have; chosen[j][k] the sorted features of category j that
    fold k may use, the last those of all rows.
    """
    n, folds = len(labels), len(chosen[0]) - 1
    earlier, chain = np.zeros((n, 0)), []
    for j in range(labels.shape[1]):
        y = labels[:, j].astype(np.float64)
        if n == 0 or y.min() == y.max():
            share = float(y.mean()) if n else 0.0
            chain.append({"features": np.zeros(0, np.int64), "weights": np.zeros(earlier.shape[1] + 1), "constant": share, "threshold": 0.5})
            earlier = np.column_stack([earlier, np.full(n, share)])
            continue
        out = np.zeros(n)
        for k in range(folds):
            fit, held = fold != k, fold == k
            if not held.any() or not fit.any() or y[fit].min() == y[fit].max():
                out[held] = y[fit].mean() if fit.any() else 0.5
                continue
            x = design(row, feature, chosen[j][k], earlier)
            out[held] = sigmoid(x[held] @ logistic(x[fit], y[fit]))
        x = design(row, feature, chosen[j][folds], earlier)
        w = logistic(x, y)
        by = np.argsort(-out, kind="stable")
        right = np.cumsum(y[by])
        f1 = 2 * right / (np.arange(1, n + 1) + y.sum())
        last = np.append(out[by][1:] < out[by][:-1], True)  # a threshold keeps ties together
        best = int(np.argmax(np.where(last, f1, -1)))
        threshold = (out[by][best] + (out[by][best + 1] if best + 1 < n else 0)) / 2
        chain.append({"features": chosen[j][folds], "weights": w, "constant": None, "threshold": float(np.clip(threshold, 0.05, 0.95))})
        earlier = np.column_stack([earlier, out])
    return chain


def train(docs: DataFrame, labels: DataFrame, categories=CATEGORIES, id_col: str = "doc_id", text_col: str = "text", max_rows: int = MAX_ROWS, folds: int = FOLDS) -> list[dict]:
    """A chain fitted on about max_rows labelled texts."""
    columns, names = [c for _, c, _ in categories], [name for name, _, _ in categories]
    known = labels.groupBy(F.col(id_col).alias("i")).agg(*[F.max(c).alias(c) for c in columns]).na.drop()
    total = known.count()
    share = int((1 << 20) * min(1.0, max_rows / max(total, 1)))
    sample = known.filter(F.pmod(F.xxhash64(F.lit(6), F.col("i")), F.lit(1 << 20)) < share)  # bounded, so broadcast
    texts = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("text")).join(F.broadcast(sample), "i")
    fold = F.pmod(F.xxhash64(F.lit(7), F.col("i")), F.lit(folds)).cast("int")  # rows of one id stay together
    rows = texts.select(F.xxhash64("i", "text").alias("key"), fold.alias("fold"), *[(F.col(c) == v).alias(name) for name, c, v in categories], "text")
    schema = ", ".join(["key long, fold int", *[f"`{name}` boolean" for name in names], "features array<long>"])
    held = stored(rows.mapInArrow(_distinct, schema))
    chosen = {}
    for r in select(held, names, folds).collect():  # at most MAX_FEATURES for each category and fold
        chosen.setdefault((r["category"], r["fold"]), []).append(r["feature"])
    used = [[np.sort(np.array(chosen.get((name, k), []), np.int64)) for k in range(folds + 1)] for name in names]
    wanted = np.unique(np.concatenate([x for per in used for x in per])).tolist()
    own = F.array_intersect("features", F.lit(wanted)) if wanted else F.array().cast("array<long>")
    found = held.select("key", "fold", *names, own.alias("features")).orderBy("key").toArrow()
    lists = found.column("features").combine_chunks()
    row = np.repeat(np.arange(len(found)), np.asarray(lists.value_lengths()) if len(found) else 0)
    values = np.column_stack([found.column(name).to_numpy() for name in names])
    return fit_chain(row, np.asarray(lists.flatten()), values, found.column("fold").to_numpy(), used)


def probabilities(chain: list[dict], bitmap: np.ndarray, data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Of each text, by category in the chain's order."""
    n = len(at) - 1
    text, feature = features(data, at)
    maybe = bitmap[(feature >> np.uint64(64 - _BITS)).astype(np.int64)]
    text, feature = text[maybe], feature[maybe].view(np.int64)
    out = np.zeros((n, 0))
    for model in chain:
        if model["constant"] is not None:
            p = np.full(n, model["constant"])
        else:
            chosen, w = model["features"], model["weights"]
            z = w[-1] + out @ w[len(chosen) : -1]
            if len(chosen) and len(feature):
                place = np.minimum(np.searchsorted(chosen, feature), len(chosen) - 1)
                hit = chosen[place] == feature
                pair = np.unique(text[hit] * len(chosen) + place[hit])
                z = z + np.bincount(pair // len(chosen), weights=w[pair % len(chosen)], minlength=n)
            p = sigmoid(z)
        out = np.column_stack([out, p])
    return out


def scorer(context, chain: list[dict], names: list[str]):
    """A column function: text to a struct of the categories' probabilities."""
    bitmap = np.zeros(1 << _BITS, bool)
    for model in chain:
        bitmap[(model["features"].view(np.uint64) >> np.uint64(64 - _BITS)).astype(np.int64)] = True
    held = context.broadcast((chain, bitmap))

    @F.arrow_udf(", ".join(f"`{x}` double" for x in names))
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            parts = [probabilities(*held.value, data, at) for _, _, data, at in chunks(texts)]
            p = np.concatenate([np.zeros((0, len(names))), *parts])
            yield pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(p[:, j])) for j in range(len(names))], names=names)

    return run


def score(docs: DataFrame, labels: DataFrame, into: str, categories=CATEGORIES, id_col: str = "doc_id", text_col: str = "text", **options) -> tuple[DataFrame, dict[str, float]]:
    """docs with a struct column into of the categories' probabilities, and the thresholds."""
    chain = train(docs, labels, categories, id_col, text_col, **options)
    names = [name for name, _, _ in categories]
    column = scorer(docs.sparkSession.sparkContext, chain, names)(F.col(text_col))
    return docs.withColumn(into, column), {name: model["threshold"] for name, model in zip(names, chain, strict=True)}


def remove_toxic(docs: DataFrame, labels: DataFrame, category: str = "toxic", **options) -> DataFrame:
    """docs without the texts whose probability of the category reaches its threshold."""
    own = "__toxicity"
    while own in docs.columns:
        own += "_"
    scored, thresholds = score(docs, labels, own, **options)
    return scored.filter(F.col(own)[category] < thresholds[category]).drop(own)
