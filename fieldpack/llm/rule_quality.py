"""Quality classifier: a sparse ensemble of rules over text statistics.

Statistics are Spark columns. Small boosted trees are grown on a bounded sample of labelled rows;
every path of a tree is a conjunctive rule; a lasso logistic fit keeps few rules; those that are
left are compiled into one Spark column, so scoring runs inside whole-stage code.

Cases: null and empty texts have statistics of 0 and get a score like any other; without two kinds
of labels the score is the share of label 1 (0.5 without labels); repeated rows get equal scores.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_split, labelled_sample, read_table

#: Bound of the training sample, in documents.
SAMPLE_ROWS = 8000
WORD = r"[^\x20\x09-\x0D]+"


def text_statistics(df: DataFrame, text_col: str = "text", prefix: str = "stat_") -> DataFrame:
    """`df` with one double for each statistic. Every text is read whole."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    per = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    raw = df.withColumns({
        f"{prefix}_chars": F.length(text), f"{prefix}_words": F.split(F.trim(F.regexp_replace(text, r"[\x20\x09-\x0D]+", " ")), " "),
        f"{prefix}_lines": F.filter(F.split(text, "\n"), lambda x: x != ""),
        f"{prefix}_symbols": F.regexp_count(text, F.lit(r"[#*$%&<>]")), f"{prefix}_bars": F.regexp_count(text, F.lit(r"\|")),
        f"{prefix}_upper": F.regexp_count(text, F.lit("[A-Z]")), f"{prefix}_digits": F.regexp_count(text, F.lit("[0-9]")),
        f"{prefix}_marks": F.regexp_count(text, F.lit("[!?]")), f"{prefix}_stops": F.regexp_count(text, F.lit(r"[.,;:]")),
    })
    c = lambda name: F.col(f"{prefix}_{name}")
    n_words = F.when(c("chars") > 0, F.size(c("words"))).otherwise(F.lit(0))
    stats = {
        "log_words": F.log1p(n_words.cast("double")),
        "symbols_per_char": per(c("symbols"), c("chars")), "bars_per_word": per(c("bars"), n_words), "upper_per_char": per(c("upper"), c("chars")),
        "digits_per_char": per(c("digits"), c("chars")), "marks_per_word": per(c("marks"), n_words), "stops_per_word": per(c("stops"), n_words),
        "chars_per_word": per(c("chars"), n_words), "distinct_words": per(F.size(F.array_distinct(c("words"))), n_words),
        "distinct_lines": per(F.size(F.array_distinct(c("lines"))), F.size(c("lines"))), "words_per_line": per(n_words, F.size(c("lines"))),
    }
    own = [x for x in raw.columns if x.startswith(f"{prefix}_")]
    return raw.withColumns({f"{prefix}{k}": v.cast("double") for k, v in stats.items()}).drop(*own)


STATISTICS = ["log_words", "symbols_per_char", "bars_per_word", "upper_per_char", "digits_per_char", "marks_per_word", "stops_per_word", "chars_per_word", "distinct_words", "distinct_lines", "words_per_line"]


@dataclass(frozen=True)
class Rule:
    """A conjunction of (statistic, is above, threshold)."""

    terms: tuple[tuple[int, bool, float], ...]

    def holds(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), dtype=bool)
        for j, above, cut in self.terms:
            out &= (x[:, j] > cut) == above
        return out

    def column(self, names: list[str]) -> Column:
        out = None
        for j, above, cut in self.terms:
            term = F.col(names[j]) > F.lit(cut) if above else F.col(names[j]) <= F.lit(cut)
            out = term if out is None else out & term
        return out


@dataclass
class RuleModel:
    rules: list[Rule] = field(default_factory=list)
    weights: list[float] = field(default_factory=list)
    bias: float = 0.0

    def logit(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.bias)
        for r, w in zip(self.rules, self.weights):
            out += w * r.holds(x)
        return out

    def column(self, names: list[str]) -> Column:
        """The score as one expression."""
        logit = F.lit(float(self.bias))
        for r, w in zip(self.rules, self.weights):
            logit = logit + F.when(r.column(names), F.lit(float(w))).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-logit))


def simplified(terms: list[tuple[int, bool, float]]) -> Rule:
    """Terms on one statistic and side are merged to the tightest."""
    tight: dict[tuple[int, bool], float] = {}
    for j, above, cut in terms:
        old = tight.get((j, above))
        tight[(j, above)] = cut if old is None else (max(old, cut) if above else min(old, cut))
    return Rule(tuple((j, above, cut) for (j, above), cut in sorted(tight.items())))


def grow_tree(x: np.ndarray, residual: np.ndarray, weight: np.ndarray, depth: int, least: int, cuts: list[np.ndarray], path: list | None = None) -> tuple[list[Rule], np.ndarray]:
    """A regression tree on Newton residuals: its paths as rules (inner nodes too), and its fitted values."""
    path = path or []
    value = residual.sum() / (weight.sum() + 1.0)
    fitted, rules = np.full(len(x), value), [simplified(path)] if path else []
    if depth == 0 or len(x) < 2 * least:
        return rules, fitted
    best = (1e-9, None)
    base = residual.sum() ** 2 / (weight.sum() + 1.0)
    for j, at in enumerate(cuts):
        if not len(at):
            continue
        bin_of = np.searchsorted(at, x[:, j], side="left")
        g, h, n = (np.bincount(bin_of, weights=w, minlength=len(at) + 1) for w in (residual, weight, np.ones(len(x))))
        gl, hl, nl = np.cumsum(g)[:-1], np.cumsum(h)[:-1], np.cumsum(n)[:-1]
        gain = gl**2 / (hl + 1.0) + (g.sum() - gl) ** 2 / (h.sum() - hl + 1.0) - base
        gain[(nl < least) | (len(x) - nl < least)] = -1
        k = int(np.argmax(gain))
        if gain[k] > best[0]:
            best = (float(gain[k]), (j, float(at[k])))
    if best[1] is None:
        return rules, fitted
    j, cut = best[1]
    above = x[:, j] > cut
    for side in (False, True):
        part = above == side
        more, values = grow_tree(x[part], residual[part], weight[part], depth - 1, least, cuts, [*path, (j, side, cut)])
        rules += more
        fitted[part] = values
    return rules, fitted


def boosted_rules(x: np.ndarray, y: np.ndarray, trees: int = 40, depth: int = 3, rate: float = 0.3, seed: int = 5) -> list[Rule]:
    rng = np.random.default_rng(seed)
    cuts = [np.unique(np.quantile(c, np.linspace(0.01, 0.99, 64))) for c in x.T]
    logit, rules = np.full(len(y), np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))), {}
    least = max(2, len(y) // 400)
    for _ in range(trees):
        part = rng.random(len(y)) < 0.7
        p = 1 / (1 + np.exp(-logit))
        got, fitted = grow_tree(x, np.where(part, y - p, 0.0), np.where(part, p * (1 - p), 0.0), depth, least, cuts)  # rows left out have no say
        logit += rate * fitted
        rules |= dict.fromkeys(got)
    return list(rules)


def lasso_logistic(z: np.ndarray, y: np.ndarray, l1: float, steps: int = 400) -> tuple[np.ndarray, float]:
    """Accelerated proximal gradient; the bias is not penalised."""
    n, d = z.shape
    mean, scale = z.mean(axis=0), np.maximum(z.std(axis=0), 0.05)
    u = (z - mean) / scale
    rate = 4 * n / (np.linalg.norm(np.column_stack([u, np.ones(n)]), 2) ** 2)
    w, b, v, vb, t = np.zeros(d), 0.0, np.zeros(d), 0.0, 1.0
    for _ in range(steps):
        e = 1 / (1 + np.exp(-(u @ v + vb))) - y
        nw = v - rate * (u.T @ e) / n
        nw = np.sign(nw) * np.maximum(np.abs(nw) - rate * l1, 0)
        nb = vb - rate * e.mean()
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, vb, w, b, t = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b), nw, nb, nt
    return w / scale, float(b - (w / scale) @ mean)


def fit_rules(x: np.ndarray, y: np.ndarray, strengths: tuple[float, ...] = (0.02, 0.01, 0.004, 0.0015, 0.0005)) -> RuleModel:
    """Rules from trees, weights from a lasso path; the strength with the least loss on a fifth of the rows wins."""
    if len(y) == 0:
        return RuleModel()
    if len(set(y.tolist())) < 2:
        p = (y.sum() + 0.5) / (len(y) + 1)
        return RuleModel(bias=float(np.log(p / (1 - p))))
    rules = boosted_rules(x, y)
    z = np.column_stack([r.holds(x) for r in rules]).astype(float)
    keep = np.flatnonzero((z.mean(axis=0) > 0) & (z.mean(axis=0) < 1))
    rules, z = [rules[i] for i in keep], z[:, keep]
    if not rules:
        return RuleModel(bias=float(np.log(y.mean() / (1 - y.mean()))))
    aside = np.arange(len(y)) % 5 == 0
    best = (np.inf, strengths[-1])
    for l1 in strengths:
        if len(set(y[~aside].tolist())) < 2:
            break
        w, b = lasso_logistic(z[~aside], y[~aside], l1)
        m = z[aside] @ w + b
        loss = float(np.mean(np.logaddexp(0, m) - y[aside] * m))
        if loss < best[0]:
            best = (loss, l1)
    w, b = lasso_logistic(z, y, best[1])
    used = np.flatnonzero(np.abs(w) > 1e-6)
    return RuleModel([rules[i] for i in used], [float(w[i]) for i in used], b)


def fit(docs: DataFrame, labels: DataFrame, held_out: Column) -> RuleModel:
    """Trains on at most SAMPLE_ROWS labelled rows; only their statistics reach the driver."""
    sample = text_statistics(labelled_sample(docs, labels, "quality", held_out, SAMPLE_ROWS)).select("label", *[f"stat_{s}" for s in STATISTICS]).toPandas()
    return fit_rules(sample[[f"stat_{s}" for s in STATISTICS]].to_numpy(float), sample["label"].to_numpy(float))


def op2_rule_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    held = crc_split(F.col("doc_id"), 3, 1)
    model = fit(docs, read_table(spark, sf_dir, "labels", "doc_id", "quality"), held)
    names = [f"stat_{s}" for s in STATISTICS]
    scored = text_statistics(docs).select("doc_id", held.alias("held_out"), model.column(names).alias("score"))
    return scored.withColumn("predicted", F.when(F.col("score") >= 0.5, 1).otherwise(0))
