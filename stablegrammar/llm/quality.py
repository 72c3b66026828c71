"""Quality classifier: a sparse rule ensemble over text statistics, compiled into Spark column expressions.

Small boosted trees are grown on a bounded sample of labelled rows; each path becomes a conjunctive rule; a lasso logistic fit keeps
few of them; the score is one column expression, so scoring is a narrow scan in the JVM.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stablegrammar.llm.common import crc_bucket, settled, unused

#: Bound of the labelled sample that the driver fits on.
SAMPLE_ROWS = 10_000


#: Statistics of a whole text, all defined for empty texts.
FEATURES = ("log_chars", "chars_per_word", "upper", "digits", "marks", "marked_words", "sentence_ends", "repeats", "lines", "distinct_words")

_LETTER, _UPPER, _DIGIT, _PLAIN, _SPACE, _MARK = range(6)


def _byte_classes() -> np.ndarray:
    """Classes of bytes; those beyond ASCII count as letters, and continuation bytes as nothing (class 7)."""
    out = np.full(256, _LETTER, np.uint8)
    out[:128] = _MARK
    for chars, kind in ((b"abcdefghijklmnopqrstuvwxyz", _LETTER), (b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", _UPPER), (b"0123456789", _DIGIT), (b".,'-", _PLAIN), (b" \t\n\r\x0b\x0c", _SPACE)):
        out[list(chars)] = kind
    out[0x80:0xC0] = 7
    return out


def text_statistics(text: str, classes: np.ndarray) -> tuple[float, ...]:
    raw = text.encode()
    kind = classes[np.frombuffer(raw, np.uint8)]
    count = np.bincount(kind, minlength=8)
    words = raw.split()
    chars, n = max(1, len(text)), max(1, len(words))
    marked = int(np.count_nonzero((kind[:-1] == _MARK) & (kind[1:] == _SPACE)))
    repeats = sum(map(bytes.__eq__, words, words[1:]))
    ends = raw.count(b". ") + raw.count(b"! ") + raw.count(b"? ") + raw.count(b".\n")
    return (float(np.log2(chars + 1)), chars / n, count[_UPPER] / chars, count[_DIGIT] / chars, count[_MARK] / chars, marked / n, ends / n, repeats / n, raw.count(b"\n") / n, len(set(words)) / n)


def _statistics(texts: pa.Array) -> pa.Array:
    classes = _byte_classes()
    rows = np.array([text_statistics(t.as_py() or "", classes) for t in texts], float).reshape(-1, len(FEATURES))
    return pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(c)) for c in rows.T], list(FEATURES))


@dataclass(frozen=True)
class Rule:
    """A conjunction of (feature, is_above, threshold) with its weight."""

    terms: tuple[tuple[str, bool, float], ...]
    weight: float = 0.0

    def column(self, stats: str = "_stats") -> Column:
        out = None
        for name, above, at in self.terms:
            term = F.col(f"{stats}.{name}") > at if above else F.col(f"{stats}.{name}") <= at
            out = term if out is None else out & term
        return out

    def holds(self, x: np.ndarray, names: tuple[str, ...]) -> np.ndarray:
        out = np.ones(len(x), bool)
        for name, above, at in self.terms:
            v = x[:, names.index(name)]
            out &= v > at if above else v <= at
        return out


def _grow(x: np.ndarray, bins: np.ndarray, edges: list[np.ndarray], g: np.ndarray, h: np.ndarray, rows: np.ndarray, depth: int, path: tuple, names: tuple[str, ...], out: list, step: np.ndarray, least: int = 10) -> None:
    """Best split by second-order gain on binned features; every node below the root gives a rule."""
    if path:
        out.append(path)
    best = (1e-3, -1, -1)
    total_g, total_h = g[rows].sum(), h[rows].sum()
    if depth and len(rows) >= 2 * least:
        for k in range(x.shape[1]):
            if not len(edges[k]):
                continue
            b, m = bins[rows, k], len(edges[k]) + 1
            left_g, left_h, left_n = (np.cumsum(np.bincount(b, w, m))[:-1] for w in (g[rows], h[rows], np.ones(len(rows))))
            gain = left_g**2 / (left_h + 1) + (total_g - left_g) ** 2 / (total_h - left_h + 1) - total_g**2 / (total_h + 1)
            gain[(left_n < least) | (len(rows) - left_n < least)] = -1
            if (i := int(np.argmax(gain))) >= 0 and gain[i] > best[0]:
                best = (gain[i], k, i)
    _, k, i = best
    if k < 0:
        step[rows] = -total_g / (total_h + 1)
        return
    at, low = float(edges[k][i]), bins[rows, k] <= i
    for side, above in ((rows[low], False), (rows[~low], True)):
        _grow(x, bins, edges, g, h, side, depth - 1, (*path, (names[k], above, at)), names, out, step, least)


def tree_rules(x: np.ndarray, y: np.ndarray, names: tuple[str, ...], trees: int = 25, depth: int = 3, rate: float = 0.3, levels: int = 64) -> list[Rule]:
    """Distinct paths of boosted trees, each a conjunction of thresholds."""
    edges = [np.unique(np.quantile(v, np.linspace(0, 1, levels + 1)[1:-1])) for v in x.T]
    bins = np.stack([np.searchsorted(e, v, side="left") for e, v in zip(edges, x.T, strict=True)], 1)
    score = np.full(len(y), np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
    paths: list[tuple] = []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-score))
        step = np.zeros(len(y))
        _grow(x, bins, edges, p - y, p * (1 - p), np.arange(len(y)), depth, (), names, paths, step)
        score += rate * step
    return [Rule(t) for t in dict.fromkeys(tuple(sorted(p)) for p in paths)]


def lasso_logistic(z: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 150) -> tuple[float, np.ndarray]:
    """Accelerated proximal gradient with labels weighted to balance; the intercept is not penalised."""
    n, k = z.shape
    z1 = np.hstack([np.ones((n, 1)), z])
    v = np.ones(k + 1)
    for _ in range(15):
        v = z1.T @ (z1 @ v)
        v /= np.linalg.norm(v)
    size = 1 / (0.25 * np.linalg.norm(z1 @ v) ** 2 / n + 1e-9)
    weight = np.where(y > 0.5, 0.5 / max(y.mean(), 1e-9), 0.5 / max(1 - y.mean(), 1e-9))
    size /= weight.max()
    w = np.zeros(k + 1)
    u, t = w.copy(), 1.0
    for _ in range(rounds):
        new = u - size * (z1.T @ (weight * (1 / (1 + np.exp(-(z1 @ u))) - y))) / n
        new[1:] = np.sign(new[1:]) * np.maximum(np.abs(new[1:]) - size * penalty, 0)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        u, w, t = new + (t - 1) / t2 * (new - w), new, t2
    return float(w[0]), w[1:]


@dataclass(frozen=True)
class RuleEnsemble:
    intercept: float
    rules: tuple[Rule, ...]

    def score(self, stats: str = "_stats") -> Column:
        """The probability of label 1, over a column of statistics."""
        total = F.lit(self.intercept)
        for r in self.rules:
            total = total + F.when(r.column(stats), F.lit(r.weight)).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-total))


def fit_rules(x: np.ndarray, y: np.ndarray, names: tuple[str, ...] = FEATURES) -> RuleEnsemble:
    """Trees, rules, and lasso weights; the penalty is the largest whose log loss on every fifth row is near the least, and the rules
    it keeps are fitted again with hardly any. Without both labels: a constant."""
    if len(y) < 20 or y.min() == y.max():
        return RuleEnsemble(float(np.log((y.sum() + 1) / (len(y) - y.sum() + 1))), ())
    test = np.arange(len(y)) % 5 == 0
    rules = list({r.holds(x, names).tobytes(): r for r in reversed(tree_rules(x[~test], y[~test], names))}.values())[::-1]
    z = np.stack([r.holds(x, names) for r in rules], 1).astype(float)
    losses, penalties = [], (0.02, 0.01, 0.005, 0.002, 0.001)
    for penalty in penalties:
        b, w = lasso_logistic(z[~test], y[~test], penalty)
        p = np.clip(1 / (1 + np.exp(-(b + z[test] @ w))), 1e-6, 1 - 1e-6)
        losses.append(-np.mean(y[test] * np.log(p) + (1 - y[test]) * np.log(1 - p)))
    chosen = next(p for p, loss in zip(penalties, losses, strict=True) if loss <= 1.1 * min(losses) + 0.002)
    keep = np.flatnonzero(np.abs(lasso_logistic(z, y, chosen, 300)[1]) > 1e-3)
    b, w = lasso_logistic(z[:, keep], y, 1e-4, 600)
    return RuleEnsemble(b, tuple(Rule(rules[k].terms, float(v)) for k, v in zip(keep, w, strict=True) if abs(v) > 1e-4))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(crc_bucket(doc_id, 5) == 0, F.lit(False))


def with_statistics(docs: DataFrame, text_col: str = "text", name: str = "_stats") -> DataFrame:
    """With a struct column `name` of the text's statistics, which one Arrow function computes; callers choose an unused name."""
    kind = "struct<" + ", ".join(f"{x}:double" for x in FEATURES) + ">"
    return docs.withColumn(name, F.arrow_udf(_statistics, kind)(F.col(text_col)))


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> RuleEnsemble:
    """Fit on labelled rows outside the held-out fold: `sample_rows` ids and 2 * `sample_rows` rows of theirs at most, both chosen by hash.

    An id may have several rows; of several labels the largest counts.
    """
    ids = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    chosen = ids.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("_y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("doc_id", "text").alias("_order"))
    rows = with_statistics(own.join(F.broadcast(settled(chosen)), "doc_id")).select("_order", "doc_id", "_y", "_stats.*")  # bounded by sample_rows
    got = rows.orderBy("_order", "doc_id", *FEATURES).limit(2 * sample_rows).toPandas().sort_values(["doc_id", "_order"])
    return fit_rules(got[list(FEATURES)].to_numpy(float), got["_y"].to_numpy(float))


def with_score(docs: DataFrame, model: RuleEnsemble, name: str, text_col: str = "text") -> DataFrame:
    """The same rows and columns, and the score as a column `name`, which the caller makes sure is unused."""
    stats = unused([*docs.columns, name], "_stats")
    return with_statistics(docs, text_col, stats).withColumn(name, model.score(stats)).drop(stats)


def quality_scores(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.3, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, score (0 to 1, higher: label 1 likelier), predicted (1 if score >= threshold).

    Fits first (labels and the documents of at most `sample_rows` of them), then scores every row in one narrow scan. Scores depend on the text only;
    null and empty texts get the score of the empty text's statistics; a null id is never held out; without usable labels the score is a
    constant. Repeated rows give repeated rows; other columns are ignored; an empty table gives an empty result.
    """
    model = train(docs, labels, sample_rows)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    scored = with_score(own, model, "score").select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score")
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
