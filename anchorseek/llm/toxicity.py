r"""Toxicity by a classifier chain.

Categories are predicted one after another: each has a linear model over features of a text's words, and
the models after the first also get the probabilities of the categories before. While learning, those
probabilities come from models fitted on the other folds, so that a later model never sees a probability
that was fitted to its own row.

Features are the distinct words, their beginnings and their character n-grams, hashed; a model keeps those
whose share of texts differs between the classes by `MIN_Z` standard errors, and takes the logarithm of the
number of distinct words that have one, and of all distinct words. Texts are read whole.

Learning takes a bounded sample of labelled rows (`train_rows`, chosen by a hash of the id, half of them
positive in the last category where there are as many); only their hashed features come to the driver, those of
their whole texts. The label table of the given tables has two columns, so the registered query's chain goes
from poor quality to toxic; any list of categories may be given to `fitted`.

Defined results: null text and text without words get the probability of a text without features; a label
that is null in a category leaves the row out of that category's model; without labels of both kinds a
category's probability is the share of positive labels (0 without any); repeated documents each get a row.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, parts_of, table

BINS = 1 << 20
GRAMS = (4, 5)
STARTS = (3, 4, 5, 6, 7, 8)
MIN_Z = 4.0
TRAIN_ROWS = 3000
FOLDS = 3
MEMORY_WORDS = 200_000
#: Letters that remembered words hold at most before all are forgotten.
MEMORY_LETTERS = 4_000_000
WORDS = re.compile(r"[^\W\d_]+")


def words_of_text(text: str | None) -> set[str]:
    return set(WORDS.findall((text or "").lower()))


def features_of(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(feature numbers, number of the word that has each): words, their starts and n-grams, hashed; repeats
    inside a word may occur twice."""
    marked = [f"^{w}$" for w in words]
    sizes = np.fromiter(map(len, marked), np.int64, len(marked))
    raw = np.frombuffer("".join(marked).encode("utf-32-le"), np.uint32).astype(np.uint64)
    begins = np.cumsum(sizes) - sizes
    owner = np.repeat(np.arange(len(marked)), sizes)
    left = np.repeat(begins + sizes, sizes) - np.arange(len(raw))  # symbols from here to the word's end
    bins, owners = [np.fromiter((xxhash.xxh64_intdigest(w.encode()) % BINS for w in words), np.int64, len(words))], [np.arange(len(words))]
    h = np.zeros(len(raw), np.uint64)
    for n in range(1, max(*STARTS, *GRAMS) + 1):  # h at a place: the hash of n symbols from there
        h = h[: max(0, len(raw) - n + 1)]
        h = (h ^ raw[n - 1 : n - 1 + len(h)]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        if n in GRAMS:
            at = np.flatnonzero(left[: len(h)] >= n)
            bins.append((h[at] % np.uint64(BINS)).astype(np.int64))
            owners.append(owner[at])
        if n in STARTS:
            own = np.flatnonzero(sizes > n)
            bins.append(((h[begins[own]] ^ np.uint64(n)) % np.uint64(BINS)).astype(np.int64))
            owners.append(own)
    return np.concatenate(bins), np.concatenate(owners)


def _featurizer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for rows in parts_of(batch, "_t", 200):
            ids, counts, sizes = [], [], []
            for t in rows.column("_t"):
                words = sorted(words_of_text(t.as_py()))
                feats, n = np.empty(0, np.int64), np.empty(0, np.int64)
                if words:
                    bins, owner = features_of(words)
                    pairs = np.unique(owner * BINS + bins)  # a word has a feature once
                    feats, n = np.unique(pairs % BINS, return_counts=True)
                ids.append(feats.astype("<i4").tobytes())
                counts.append(n.astype("<f4").tobytes())
                sizes.append(len(words))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.binary()), pa.array(counts, pa.binary()), pa.array(sizes, pa.int64()), rows.column("_y"), rows.column("_h")], names=["ids", "counts", "n", "y", "h"])


class Sparse:
    """Rows of hashed features with the number of distinct words that have them."""

    def __init__(self, rows):
        self.n = len(rows)
        self.words = np.array([m for _, _, m in rows], np.float64)
        self.row = np.repeat(np.arange(self.n, dtype=np.int32), [len(i) for i, _, _ in rows])
        self.col = np.concatenate([i for i, _, _ in rows]) if rows else np.empty(0, np.int32)
        self.count = np.concatenate([c for _, c, _ in rows]) if rows else np.empty(0, np.float32)

    def only(self, rows: np.ndarray) -> Sparse:
        """The rows flagged."""
        out, at = Sparse([]), rows[self.row]
        out.n, out.words, out.row = int(rows.sum()), self.words[rows], (np.cumsum(rows) - 1).astype(np.int32)[self.row[at]]
        out.col, out.count = self.col[at], self.count[at]
        return out

    def telling(self, y: np.ndarray) -> np.ndarray:
        """Features whose share of rows differs between y = 1 and y = 0 by MIN_Z standard errors."""
        if not self.n or not 0 < y.mean() < 1:
            return np.empty(0, np.int64)
        n1, n0 = y.sum(), (1 - y).sum()
        has1 = np.bincount(self.col, y[self.row], BINS)
        has = np.bincount(self.col, minlength=BINS)
        share = has / self.n
        with np.errstate(divide="ignore", invalid="ignore"):
            z = (has1 / n1 - (has - has1) / n0) / np.sqrt(share * (1 - share) * (1 / n1 + 1 / n0))
        return np.flatnonzero((np.abs(z) >= MIN_Z) & (has >= 5))

    def dense(self, features: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Logarithmic counts of the features and of the words, for the rows flagged."""
        place = np.full(BINS, -1)
        place[features] = np.arange(len(features))
        number = np.where(rows, np.cumsum(rows) - 1, -1)
        at = (place[self.col] >= 0) & rows[self.row]
        out = np.zeros((int(rows.sum()), len(features)), np.float32)
        out[number[self.row[at]], place[self.col[at]]] = np.log1p(self.count[at])
        return np.column_stack([out, np.log1p(self.words[rows]).astype(np.float32) / 10])


def sigmoid(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit_linear(x: np.ndarray, y: np.ndarray, steps=250, ridge=1e-3, rate=0.05) -> np.ndarray:
    """Weights and intercept of a ridge logistic model (Adam, fixed steps)."""
    share = y.mean() if len(y) else 0.0
    p = np.zeros(x.shape[1] + 1)
    p[-1] = np.log((share + 1e-9) / (1 - share + 1e-9))
    if not 0 < share < 1:
        return p
    m, v = np.zeros_like(p), np.zeros_like(p)
    for t in range(1, steps + 1):
        g = (sigmoid(x @ p[:-1] + p[-1]) - y) / len(y)
        grad = np.concatenate([x.T @ g + ridge * p[:-1], [g.sum()]])
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad * grad
        p -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-6)
    return p


class Chain:
    """Linear models in a fixed order of categories."""

    def __init__(self, categories: list[str]):
        self.categories, self.models, self.cutoffs = categories, [], []

    def fit(self, x: Sparse, labels: np.ndarray, fold: np.ndarray) -> Chain:
        """labels: one column a category, NaN where unknown."""
        earlier = np.zeros((x.n, 0))

        def model(rows: np.ndarray, y: np.ndarray):
            features = x.only(rows).telling(y[rows])
            return features, fit_linear(np.column_stack([x.dense(features, rows), earlier[rows]]), y[rows])

        for c in range(len(self.categories)):
            y = labels[:, c]
            known = ~np.isnan(y)
            self.models.append(model(known, y))
            out = np.zeros(x.n)
            for f in range(FOLDS):
                features, p = model(known & (fold != f), y)
                rows = fold == f
                out[rows] = sigmoid(np.column_stack([x.dense(features, rows), earlier[rows]]) @ p[:-1] + p[-1])
            self.cutoffs.append(_best_cutoff(out[known], y[known]))
            earlier = np.column_stack([earlier, out])
        return self


def _best_cutoff(p: np.ndarray, y: np.ndarray) -> float:
    """The probability that gives the best F1 on out-of-fold predictions, midway to the next."""
    if not len(y) or not 0 < y.mean() < 1:
        return 0.5
    order = np.argsort(-p)
    hit = np.cumsum(y[order])
    f1 = 2 * hit / (np.arange(1, len(y) + 1) + y.sum())
    i = int(f1.argmax())
    return float((p[order[i]] + p[order[min(i + 1, len(y) - 1)]]) / 2)


def fitted(docs: DataFrame, labels: DataFrame, categories: dict, text="text", doc_id="doc_id", train_rows=TRAIN_ROWS) -> Chain:
    """A chain over the categories: name -> boolean column of labels, in the chain's order."""
    names = list(categories)
    wanted = labels.where(F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("_id"), F.array(*[c.cast("double") for c in categories.values()]).alias("_y"))
    wanted = wanted.groupBy("_id").agg(F.max("_y").alias("_y")).withColumn("_h", F.xxhash64("_id", F.lit(6)))
    positive = F.coalesce(F.get("_y", len(names) - 1), F.lit(0.0)) > 0
    n_pos, n = wanted.agg(F.coalesce(F.sum(positive.cast("long")), F.lit(0)), F.count(F.lit(1))).first()
    take_pos = min(1.0, train_rows / 2 / n_pos) if n_pos else 0.0
    take_rest = min(1.0, (train_rows - min(n_pos, train_rows / 2)) / (n - n_pos)) if n > n_pos else 0.0
    scale = 1 << 30
    wanted = wanted.where(F.pmod("_h", F.lit(scale)) < F.when(positive, int(take_pos * scale)).otherwise(int(take_rest * scale)))
    rows = docs.select(F.col(doc_id).alias("_id"), F.col(text).alias("_t")).join(F.broadcast(wanted), "_id").select("_t", "_y", "_h")
    got = rows.mapInArrow(lean(_featurizer), "ids binary, counts binary, n bigint, y array<double>, h bigint").toLocalIterator()
    kept = sorted(((r.h, r.n, r.ids, r.counts, r.y) for r in got), key=lambda r: (r[0], r[1], r[2]))
    x = Sparse([(np.frombuffer(i, "<i4"), np.frombuffer(c, "<f4"), n_) for _, n_, i, c, _ in kept])
    y = np.array([[np.nan if v is None else v for v in r[4]] for r in kept], float).reshape(len(kept), len(names))
    fold = np.array([(r[0] >> 32) % FOLDS for r in kept], np.int64)
    return Chain(names).fit(x, y, fold)


class _Known(dict):
    """The kept features of remembered words, as places in the models' common list; None for most words."""

    def __init__(self, features: np.ndarray):
        super().__init__()
        self.place = np.full(BINS, -1, np.int32)
        self.place[features] = np.arange(len(features))
        self.letters = 0

    def learn(self, words: list[str]) -> None:
        self.letters += sum(map(len, words))
        self.update(dict.fromkeys(words))
        bins, owner = features_of(words)
        place = self.place[bins]
        hit = np.flatnonzero(place >= 0)
        pairs = np.unique(owner[hit] * BINS + place[hit])
        for w, f in zip((pairs // BINS).tolist(), (pairs % BINS).tolist()):
            word = words[w]
            self[word] = (*(self[word] or ()), f)


def _scorer(chain: Chain, text: str, carry: list[str]):
    kept = np.unique(np.concatenate([f for f, _ in chain.models]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _Known(kept)
        at = [np.searchsorted(kept, f) for f, _ in chain.models]
        for batch in batches:
            for rows in parts_of(batch, text, 500):
                p = np.zeros((rows.num_rows, len(chain.models)))
                sets = [words_of_text(t.as_py()) for t in rows.column(text)]
                if new := sorted(set().union(*sets).difference(known)):
                    known.learn(new)
                for i, words in enumerate(sets):
                    hits = [f for found in map(known.__getitem__, words) if found for f in found]
                    x = np.log1p(np.bincount(hits, minlength=len(kept))) if hits else np.zeros(len(kept))
                    for c, (f, w) in enumerate(chain.models):
                        n = len(f)
                        p[i, c] = sigmoid(x[at[c]] @ w[:n] + np.log1p(len(words)) / 10 * w[n] + p[i, :c] @ w[n + 1 : -1] + w[-1])
                if len(known) > MEMORY_WORDS or known.letters > MEMORY_LETTERS:
                    known.clear()
                    known.letters = 0
                yield pa.RecordBatch.from_arrays([*(rows.column(c) for c in carry), *(pa.array(p[:, c]) for c in range(p.shape[1]))], names=[*carry, *(f"p_{c}" for c in chain.categories)])

    return lean(run)


def scored(docs: DataFrame, chain: Chain, text="text", carry=None) -> DataFrame:
    """The carried columns (all by default) and p_<category> of every document."""
    carry = [c for c in docs.columns if c not in [f"p_{x}" for x in chain.categories]] if carry is None else list(carry)
    schema = [f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in carry] + [f"p_{c} double" for c in chain.categories]
    return docs.select(*dict.fromkeys([*carry, text])).mapInArrow(_scorer(chain, text, carry), ", ".join(schema))


def contract_chain(spark, sf_dir: str) -> Chain:
    """The label table's categories: poor quality first, then toxic."""
    return fitted(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), {"poor": F.col("quality") == 0, "toxic": F.col("toxic") == 1})


def op6_toxicity(spark, sf_dir: str) -> DataFrame:
    chain = contract_chain(spark, sf_dir)
    got = scored(table(spark, sf_dir, "documents"), chain, carry=["doc_id"])
    return got.select("doc_id", F.col("p_poor").alias("poor_score"), F.col("p_toxic").alias("score"), (F.col("p_toxic") >= chain.cutoffs[-1]).alias("toxic"))
