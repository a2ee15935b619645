"""Sparse rule ensemble for document quality.

Small trees are grown on statistics of the text; every path from a root to a node is a conjunctive rule. A logistic
model over the rules is fitted with an absolute-value penalty, which leaves few rules with a weight, and those are
compiled into one Spark column expression over the statistics.

Only text statistics enter a score. The model is fitted on at most ``MAX_TRAIN`` labelled rows, the first by a hash
of the id; all statistics and scores cover all rows and whole texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import any_names, bounded_batches, table, tidy

MAX_TRAIN = 20_000
THRESHOLD = 0.3
TREES, DEPTH, LEAST_LEAF, BINS = 40, 3, 5, 24
PENALTY, ROUNDS = 0.002, 1500
FOLDS = 5

STATS = (
    "log_bytes", "log_words", "word_bytes", "upper_share", "lower_share", "digit_share", "space_share", "line_share", "high_share",
    "stop_share", "bang_share", "pipe_share", "star_share", "dollar_share", "percent_share", "amp_share", "hash_share", "mark_share",
    "distinct_share", "repeat_share", "symbol_end_share",
)
_CLASS = {
    "upper_share": bytes(range(65, 91)), "lower_share": bytes(range(97, 123)), "digit_share": b"0123456789", "space_share": b" \t", "line_share": b"\n", "high_share": bytes(range(128, 256)),
    "stop_share": b".,;:?", "bang_share": b"!", "pipe_share": b"|", "star_share": b"*", "dollar_share": b"$", "percent_share": b"%", "amp_share": b"&", "hash_share": b"#", "mark_share": b"\"'()[]{}<>/\\=+-_@^~`",
}
_MATRIX = np.zeros((256, len(_CLASS)))
for _k, _chars in enumerate(_CLASS.values()):
    _MATRIX[list(_chars), _k] = 1
_SYMBOLS = frozenset(b"!|*$%&#^~=+")


def statistics_of(text: bytes | None) -> list[float]:
    text = text or b""
    n = len(text)
    shares = (np.bincount(np.frombuffer(text, np.uint8), minlength=256) @ _MATRIX / max(n, 1)).tolist()
    words = text.split()
    w = len(words)
    distinct = len(set(words))
    again = sum(map(eq, words, words[1:]))
    ends = sum(x[-1] in _SYMBOLS for x in words)
    return [float(np.log1p(n)), float(np.log1p(w)), sum(map(len, words)) / max(w, 1), *shares, distinct / max(w, 1), again / max(w - 1, 1), ends / max(w, 1)]


def with_statistics(docs: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",), prefix: str = "") -> DataFrame:
    """The columns of keep and the statistics of the whole text, named prefix and STATS; null texts count as empty.

    A text is read at once, whatever its length; a task holds an Arrow batch of bounded size or one text.
    """
    cols = [*keep, *([] if text_col in keep else [text_col])]
    rows, at_text, n = docs.select(*cols), cols.index(text_col), len(keep)
    names = [prefix + x for x in STATS]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                got = np.array([statistics_of(t) for t in part.column(at_text).cast(pa.binary()).to_pylist()]).reshape(-1, len(STATS))
                yield pa.RecordBatch.from_arrays([*part.columns[:n], *(pa.array(np.ascontiguousarray(got[:, k])) for k in range(len(STATS)))], names=[*keep, *names])

    fields = [*rows.schema.fields[:n], *(StructField(x, DoubleType()) for x in names)]
    return bounded_batches(rows).mapInArrow(tidy(run), StructType(fields))


Condition = tuple[int, bool, float]  # statistic, above, threshold


@dataclass(frozen=True)
class RuleModel:
    bias: float
    rules: tuple[tuple[tuple[Condition, ...], float], ...]

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.bias + sum((w * _holds(x, r) for r, w in self.rules), np.zeros(len(x)))

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x), -40, 40)))

    def column(self, prefix: str = "") -> Column:
        """The score as an expression over the columns of STATS."""
        total = F.lit(self.bias)
        for rule, w in self.rules:
            test = F.lit(True)
            for k, above, at in rule:
                stat = F.col(prefix + STATS[k])
                test = test & (stat > F.lit(at) if above else stat <= F.lit(at))
            total = total + F.when(test, F.lit(float(w))).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-F.greatest(F.least(total, F.lit(40.0)), F.lit(-40.0))))


def _holds(x: np.ndarray, rule: tuple[Condition, ...]) -> np.ndarray:
    out = np.ones(len(x), bool)
    for k, above, at in rule:
        out &= (x[:, k] > at) if above else (x[:, k] <= at)
    return out


def tree_paths(x: np.ndarray, y: np.ndarray, cuts: list[np.ndarray], rng: np.random.Generator) -> set[tuple[Condition, ...]]:
    """Paths to all nodes but the root of one tree on a bootstrap sample, half of the statistics tried at each node."""
    rows = rng.integers(0, len(y), len(y))
    found: set[tuple[Condition, ...]] = set()
    todo = [(rows, ())]
    while todo:
        at, path = todo.pop()
        if path:
            found.add(tuple(sorted(path)))
        if len(path) == DEPTH or len(at) < 2 * LEAST_LEAF or y[at].min() == y[at].max():
            continue
        best = (1e-9, None)
        total, ones = len(at), y[at].sum()
        for k in rng.permutation(len(cuts))[: (len(cuts) + 1) // 2]:
            if not len(cuts[k]):
                continue
            place = np.searchsorted(cuts[k], x[at, k])
            n = np.cumsum(np.bincount(place, minlength=len(cuts[k]) + 1))[:-1]
            p = np.cumsum(np.bincount(place, weights=y[at], minlength=len(cuts[k]) + 1))[:-1]
            ok = (n >= LEAST_LEAF) & (total - n >= LEAST_LEAF)
            gain = np.where(ok, p * p / np.maximum(n, 1) + (ones - p) ** 2 / np.maximum(total - n, 1) - ones * ones / total, -1)
            if gain.max() > best[0]:
                best = (gain.max(), (int(k), float(cuts[k][gain.argmax()])))
        if best[1]:
            k, cut = best[1]
            above = x[at, k] > cut
            todo += [(at[~above], (*path, (k, False, cut))), (at[above], (*path, (k, True, cut)))]
    return found


def lasso_logistic(z: np.ndarray, y: np.ndarray, penalty: float = PENALTY, rounds: int = ROUNDS) -> tuple[float, np.ndarray]:
    """Bias and weights by accelerated proximal steps on standardised columns; the bias carries no penalty."""
    mean, scale = z.mean(axis=0), np.maximum(z.std(axis=0), 1e-6)
    a = (z - mean) / scale
    n, d = a.shape
    step = 4 * n / max(np.linalg.norm(a.T @ a / 1.0, 2) + n, 1e-9)
    w, b, t = np.zeros(d), float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))), 1.0
    v, c = w.copy(), b
    for _ in range(rounds):
        g = 1 / (1 + np.exp(-np.clip(a @ v + c, -40, 40))) - y
        new = v - step * (a.T @ g) / n
        new = np.sign(new) * np.maximum(np.abs(new) - step * penalty, 0)
        bias = c - step * g.mean()
        after = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, c = new + (t - 1) / after * (new - w), bias + (t - 1) / after * (bias - b)
        if np.abs(new - w).max(initial=0) < 1e-7 and abs(bias - b) < 1e-7:
            w, b = new, bias
            break
        w, b, t = new, bias, after
    return float(b - (w / scale) @ mean), w / scale


def fit(x: np.ndarray, y: np.ndarray, seed: int = 11) -> RuleModel:
    """One class alone, or no row at all, gives a constant score."""
    if not len(y) or y.min() == y.max():
        p = float(np.clip(y.mean() if len(y) else 0.5, 0.01, 0.99))
        return RuleModel(float(np.log(p / (1 - p))), ())
    rng = np.random.default_rng(seed)
    cuts = []
    for k in range(x.shape[1]):
        q = np.unique(np.quantile(x[:, k], np.linspace(0, 1, BINS + 1)[1:-1]))
        q = np.unique(np.concatenate((q, [0.0]))) if (x[:, k] == 0).any() else q
        cuts.append(q[q < x[:, k].max()])
    rules: dict[bytes, tuple[Condition, ...]] = {}
    for _ in range(TREES):
        for r in sorted(tree_paths(x, y, cuts, rng), key=lambda r: (len(r), r)):
            hold = _holds(x, r)
            if LEAST_LEAF <= hold.sum() <= len(y) - LEAST_LEAF:
                rules.setdefault(min(np.packbits(hold).tobytes(), np.packbits(~hold).tobytes()), r)
    kept = list(rules.values())
    if not kept:
        return fit(x[:0], y[:0])
    bias, w = lasso_logistic(np.stack([_holds(x, r) for r in kept], axis=1).astype(float), y.astype(float))
    return RuleModel(bias, tuple((r, float(k)) for r, k in zip(kept, w, strict=True) if k))


def fold(id_col: str = "doc_id") -> Column:
    return F.crc32(F.col(id_col).cast("string")) % FOLDS


def train(docs: DataFrame, labels: DataFrame, text_col: str = "text", label: str = "quality", max_rows: int = MAX_TRAIN) -> RuleModel:
    """Fit on labelled rows outside fold 0: the first max_rows ids by hash; of repeated ids the mean label and one text count.

    Rows without a label or an id teach nothing; whole texts are measured, however long.
    """
    some = labels.where(F.col(label).isNotNull() & (fold() != 0)).groupBy("doc_id").agg(F.avg(label).alias("sw__y"))
    some = some.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    rows = docs.select("doc_id", text_col).join(F.broadcast(some), "doc_id")
    got = with_statistics(rows, text_col, ("doc_id", "sw__y")).groupBy("doc_id").agg(*[F.min(c).alias(c) for c in ("sw__y", *STATS)]).toPandas().sort_values("doc_id")
    return fit(got[list(STATS)].to_numpy(), (got["sw__y"].to_numpy() >= 0.5).astype(float))


def scores(docs: DataFrame, model: RuleModel, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",), score: str = "score", predicted: str = "predicted") -> DataFrame:
    """keep, score and predicted of every row, empty and null texts, repeated rows and rows without an id included.

    Columns of keep may have any name but those of score and predicted, which can be chosen.
    """
    own = with_statistics(docs, text_col, keep, "sw__")
    out = own.select(*keep, model.column("sw__").alias(score))
    return out.withColumn(predicted, (F.col(score) >= THRESHOLD).cast("int"))


def op10_rule_ensemble_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = scores(docs, train(docs, table(spark, sf_dir, "labels")))
    return out.select("doc_id", F.coalesce(fold() == 0, F.lit(False)).alias("held_out"), "score", "predicted")


@any_names
def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows of docs that the model predicts good; columns and order of columns as in docs, whatever their names."""
    out = scores(docs, train(docs, labels), "text", tuple(docs.columns), "sw__score", "sw__predicted")
    return out.where("sw__predicted = 1").select(*docs.columns)
