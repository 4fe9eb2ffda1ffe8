"""Quality classifier: a sparse rule ensemble over text statistics.

``text_statistics`` measures every whole text.  On a bounded sample of labelled documents
small boosted trees are grown; every path from a root to a node is a conjunction of
comparisons, and these rules are the inputs of a logistic regression with an L1 penalty,
which leaves few of them.  The rules that keep a weight are compiled into one Spark column
expression, so that scoring is a projection over the statistics.

Only the text goes to Python and only its statistics come back; documents are filtered where
they are.  Null and empty texts have all statistics zero (but ``word_richness``, which is one
below two words) and are scored like others.  Columns other than doc_id and text, whatever their
names, are ignored or kept as they are.  Repeated rows and ids and null ids are scored row by
row; empty tables give empty results.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nearcohort.llm.rows import fresh
from nearcohort.llm.textblocks import blocks, release, words
from nearcohort.plans.runtime import ship

#: Labelled documents that the model is fitted on, at most (those of least hash).
MAX_LABELLED = 20_000
THRESHOLD = 0.3

_KINDS = ("lower", "upper", "digit", "space", "newline", "bang", "decor", "pipe", "stop", "high", "other")
FEATURES = ("log_bytes", "log_words", *(f"{k}_share" for k in _KINDS), "mean_word", "distinct_words",
            "word_richness", "distinct_lines", "mean_line")


def _kind_table() -> np.ndarray:
    t = np.full(256, _KINDS.index("other"), np.int64)
    for kind, chars in {"lower": range(97, 123), "upper": range(65, 91), "digit": range(48, 58),
                        "space": b" \t\r\v\f", "newline": b"\n", "bang": b"!?", "decor": b"*#$%&~^",
                        "pipe": b"|\\/<>[]{}", "stop": b".,;:'\"()-", "high": range(128, 256)}.items():
        t[list(chars)] = _KINDS.index(kind)
    return t


def _distinct(owner: np.ndarray, h: np.ndarray, n: int) -> np.ndarray:
    """Distinct hashes per owner."""
    if not len(h):
        return np.zeros(n)
    order = np.lexsort((h, owner))
    o, v = owner[order], h[order]
    new = np.ones(len(o), bool)
    new[1:] = (o[1:] != o[:-1]) | (v[1:] != v[:-1])
    return np.bincount(o[new], minlength=n)


def block_statistics(off: np.ndarray, data: np.ndarray) -> np.ndarray:
    """One row of ``FEATURES`` per text of a block."""
    n = len(off) - 1
    size = np.diff(off)
    owner = np.repeat(np.arange(n), size)
    k = len(_KINDS)
    counts = np.bincount(owner * k + _kind_table()[data], minlength=n * k).reshape(n, k)
    starts, ends, h, first = words(off, data)
    n_words = np.diff(first)
    who = np.repeat(np.arange(n), n_words)
    letters = np.bincount(who, (ends - starts), minlength=n) if len(starts) else np.zeros(n)
    # a line is known by its words: the sum of their hashes, each turned by its place
    line = np.searchsorted(np.flatnonzero(data == 10), starts) + who * 1_000_003
    if len(h):
        cut = np.ones(len(line), bool)
        cut[1:] = line[1:] != line[:-1]
        at = np.flatnonzero(cut)
        with np.errstate(over="ignore"):
            place = (np.arange(len(h)) - np.repeat(at, np.diff(np.append(at, len(h))))).astype(np.uint64)
            line_h = np.add.reduceat(h * (place * np.uint64(2) + np.uint64(1)), at)
        n_lines, d_lines = np.bincount(who[at], minlength=n), _distinct(who[at], line_h, n)
    else:
        n_lines = d_lines = np.zeros(n)
    one = np.maximum
    kinds = _distinct(who, h, n)
    # log(distinct) / log(words) hardly depends on the length of the text
    richness = np.where(n_words > 1, np.log(one(kinds, 1)) / np.log(one(n_words, 2)), 1.0)
    return np.column_stack([
        np.log1p(size), np.log1p(n_words), counts / one(size, 1)[:, None], letters / one(n_words, 1),
        kinds / one(n_words, 1), richness, d_lines / one(n_lines, 1), np.log1p(n_words / one(n_lines, 1)),
    ]).round(6)


def _measure(texts: pa.Array) -> pa.Array:
    release()
    got = [block_statistics(off, data) for _, off, data in blocks(texts)]
    m = np.concatenate(got) if got else np.zeros((0, len(FEATURES)))
    return pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(c)) for c in m.T], list(FEATURES))


def statistics(text: str = "text") -> Column:
    """A struct of ``FEATURES`` of a text column."""
    return F.arrow_udf(_measure, ", ".join(f"{f} double" for f in FEATURES))(F.col(text))


def text_statistics(docs: DataFrame) -> DataFrame:
    """``doc_id`` and ``FEATURES`` of every whole text."""
    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), statistics().alias("s")).select("doc_id", "s.*")


@dataclass(frozen=True)
class Rule:
    """A conjunction of (feature, is '<=', bound)."""

    terms: tuple[tuple[str, bool, float], ...]

    def holds(self, x: np.ndarray) -> np.ndarray:
        ok = np.ones(len(x), bool)
        for f, below, bound in self.terms:
            v = x[:, FEATURES.index(f)]
            ok &= (v <= bound) if below else (v > bound)
        return ok

    def column(self, prefix: str = "") -> Column:
        out = F.lit(True)
        for f, below, bound in self.terms:
            v = F.col(prefix + f)
            out = out & ((v <= bound) if below else (v > bound))
        return out


@dataclass
class RuleModel:
    """Weighted rules and a bias: the logit of label 1."""

    bias: float
    rules: list[tuple[Rule, float]] = field(default_factory=list)

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.bias)
        for r, w in self.rules:
            z += w * r.holds(x)
        return 1 / (1 + np.exp(-z))

    def column(self, prefix: str = "") -> Column:
        """The score as an expression over columns ``prefix + feature``."""
        z = F.lit(float(self.bias))
        for r, w in self.rules:
            z = z + F.when(r.column(prefix), F.lit(float(w))).otherwise(F.lit(0.0))
        return 1.0 / (1.0 + F.exp(-z))


def _grow(x, g, h, rows, depth, least, path, out, value):
    """A regression tree on gradients g and curvatures h; appends the rules of its nodes."""
    value[rows] = -g[rows].sum() / (h[rows].sum() + 1.0)
    if depth == 0 or len(rows) < 2 * least:
        return
    best = (1e-6, None, None)
    total_g, total_h = g[rows].sum(), h[rows].sum()
    for f in range(x.shape[1]):
        order = rows[np.argsort(x[rows, f], kind="stable")]
        v = x[order, f]
        cg, ch = np.cumsum(g[order])[:-1], np.cumsum(h[order])[:-1]
        gain = cg**2 / (ch + 1) + (total_g - cg)**2 / (total_h - ch + 1) - total_g**2 / (total_h + 1)
        gain[(v[1:] <= v[:-1])] = 0
        gain[:least - 1] = gain[len(gain) - least + 1:] = 0
        i = int(np.argmax(gain)) if len(gain) else 0
        if len(gain) and gain[i] > best[0]:
            best = (gain[i], f, float((v[i] + v[i + 1]) / 2))
    if best[1] is None:
        return
    _, f, bound = best
    for below in (True, False):
        side = rows[(x[rows, f] <= bound) == below]
        step = (*path, (FEATURES[f], below, bound))
        out.append(Rule(step))
        _grow(x, g, h, side, depth - 1, least, step, out, value)


def tree_rules(x: np.ndarray, y: np.ndarray, trees: int = 12, depth: int = 3, rate: float = 0.3) -> list[Rule]:
    """The distinct rules of a boosted ensemble."""
    z, out = np.zeros(len(y)), []
    least = max(3, len(y) // 500)
    for _ in range(trees):
        p = 1 / (1 + np.exp(-z))
        value = np.zeros(len(y))
        _grow(x, p - y, p * (1 - p), np.arange(len(y)), depth, least, (), out, value)
        z += rate * value
    return list(dict.fromkeys(out))


def lasso_logistic(r: np.ndarray, y: np.ndarray, penalty: float, steps: int = 400) -> tuple[float, np.ndarray]:
    """L1-penalised logistic weights by accelerated proximal gradients; the bias is free."""
    n, m = r.shape
    a = np.column_stack([np.ones(n), r])
    rate = 4.0 / max(1e-9, np.linalg.eigvalsh(a.T @ a / n)[-1])
    w = np.zeros(m + 1)
    ahead, t = w.copy(), 1.0
    for _ in range(steps):
        grad = a.T @ (1 / (1 + np.exp(-(a @ ahead))) - y) / n
        nxt = ahead - rate * grad
        nxt[1:] = np.sign(nxt[1:]) * np.maximum(np.abs(nxt[1:]) - rate * penalty, 0)
        t2 = (1 + math.sqrt(1 + 4 * t * t)) / 2
        ahead, w, t = nxt + (t - 1) / t2 * (nxt - w), nxt, t2
    return float(w[0]), w[1:]


def fit_rules(x: np.ndarray, y: np.ndarray) -> RuleModel:
    """Rules from trees, weights by lasso; the penalty of least held-out loss (3 folds)."""
    if len(y) == 0:
        return RuleModel(0.0)
    if y.min() == y.max():  # one class only: its frequency with one pseudo-count each
        p = (y.sum() + 1) / (len(y) + 2)
        return RuleModel(math.log(p / (1 - p)))
    rules = tree_rules(x, y)
    if not rules:
        p = y.mean()
        return RuleModel(math.log(p / (1 - p)))
    r = np.column_stack([q.holds(x) for q in rules]).astype(float)
    fold = np.arange(len(y)) % 3
    loss = {}
    for penalty in (0.03, 0.01, 0.003, 0.001):
        loss[penalty] = 0.0
        for f in range(3):
            t = fold != f
            if y[t].min() == y[t].max():
                continue
            b, w = lasso_logistic(r[t], y[t], penalty, 150)
            p = np.clip(1 / (1 + np.exp(-(b + r[~t] @ w))), 1e-6, 1 - 1e-6)
            loss[penalty] -= (y[~t] * np.log(p) + (1 - y[~t]) * np.log(1 - p)).sum()
    b, w = lasso_logistic(r, y, min(loss, key=loss.get))
    return RuleModel(b, [(q, float(v)) for q, v in zip(rules, w, strict=True) if abs(v) > 1e-6])


def held_out() -> Column:
    """Documents that no label is learnt from: crc32 of the id's text divisible by 5."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_LABELLED) -> RuleModel:
    """Fit on at most ``max_rows`` labelled documents that are not held out.

    Without any label the model scores 0.5; of several labels of a document the greatest counts.
    """
    ids = (labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality"))
           .where("doc_id is not null and quality is not null").where(~held_out())
           .groupBy("doc_id").agg(F.max("quality").alias("quality"))
           .orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows))
    ids = F.broadcast(docs.sparkSession.createDataFrame(ids.toPandas(), "doc_id long, quality int"))
    got = text_statistics(docs.join(ids, "doc_id", "left_semi")).join(ids, "doc_id").toPandas().sort_values("doc_id")
    return fit_rules(got[list(FEATURES)].to_numpy(float), got["quality"].to_numpy(float))


def score(docs: DataFrame, model: RuleModel) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every document (null text: as empty)."""
    return (text_statistics(docs).withColumn("score", model.column())
            .select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score",
                    (F.col("score") >= THRESHOLD).cast("int").alias("predicted")))


def keep_good(docs: DataFrame, model: RuleModel) -> DataFrame:
    """``docs`` without the rejected ones, by the same expression (no join, no shuffle)."""
    ship(docs.sparkSession)
    own = fresh("statistics", docs.columns)
    return (docs.withColumn(own, statistics()).where(model.column(own + ".") >= THRESHOLD)
            .select(*[f"`{c}`" for c in docs.columns]))
