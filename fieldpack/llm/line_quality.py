"""Quality rules: a linear-chain conditional random field labels each line content or boilerplate.

Line features come from byte counts over whole batches of texts (no per-character Python). The two
states' emission weights and the transition weights are trained here on a bounded sample of
labelled documents; Viterbi decoding labels the lines of every whole text, and the share of words
in content lines decides retention. Plain counts (words, symbols, repeated lines and repeated
three-word windows) are returned beside the verdict.

Cases: null and empty texts have no words, fail the base rule and are not kept; a line without a
word is labelled but has no weight in the share; repeated rows give repeated results; without any
labelled rows the prior weights below are used.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from itertools import count

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, LongType, StringType, StructField, StructType

from .common import bound_batches, labelled_sample, read_table

#: The white space and the symbols of the contract, as bytes.
SPACE, SYMBOLS = b" \t\n\x0b\x0c\r", b"#*$%&|<>"
#: A batch of texts is worked on in parts of about so many bytes.
PART_BYTES = 1 << 20
FEATURES = ["bias", "symbols", "upper", "bars", "digits", "marks", "repeated_line", "repeated_words", "short", "long_words", "unended", "edge"]
#: Used where no labelled rows exist: emission weights for content, then stay and switch scores.
PRIOR = {"w": [1.5, -3.0, -4.0, -3.0, -2.0, -8.0, -1.5, -4.0, -0.3, -0.5, -0.3, 0.0], "trans": [[0.7, -0.7], [-0.7, 0.7]]}
#: Bound of the training sample, in documents, and of the lines of a training sequence.
SAMPLE_DOCS, SAMPLE_BYTES, SAMPLE_LINES = 3000, 16 << 20, 32
MIN_CONTENT_SHARE = 0.5


def _flags(chars: bytes) -> np.ndarray:
    out = np.zeros(256, dtype=np.uint8)
    out[list(chars)] = 1
    return out


_SPACE, _SYMBOL, _BAR = _flags(SPACE), _flags(SYMBOLS), _flags(b"|")
_UPPER, _DIGIT, _MARK = _flags(bytes(range(65, 91))), _flags(bytes(range(48, 58))), _flags(b"!?")
_LETTER = _flags(bytes(range(65, 91)) + bytes(range(97, 123)) + bytes(range(0xC2, 0xF5)))
_POINT = np.ones(256, dtype=np.uint8)
_POINT[0x80:0xC0] = 0
_END = _flags(b".!?:;\"')")


def repeated_windows(codes: np.ndarray, doc: np.ndarray, n_codes: int) -> np.ndarray:
    """Which words lie in a three-word window that its text holds twice or more."""
    flag = np.zeros(len(codes), dtype=bool)
    if len(codes) < 3:
        return flag
    a, b, c = codes[:-2], codes[1:-1], codes[2:]
    bits = max(1, int(n_codes).bit_length())
    n_docs = int(doc[-1]) + 1
    if 3 * bits + n_docs.bit_length() <= 62:
        key = ((doc[:-2] << (3 * bits)) | (a << (2 * bits)) | (b << bits)) | c
    else:
        pair = np.unique((a << bits) | b, return_inverse=True)[1].astype(np.int64)
        pair = np.unique((pair << bits) | c, return_inverse=True)[1].astype(np.int64)
        key = pair * n_docs + doc[:-2]
    inside = np.flatnonzero(doc[:-2] == doc[2:])
    key = key[inside]
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    same = ranked[1:] == ranked[:-1]
    twice = np.zeros(len(ranked), dtype=bool)
    twice[1:] |= same
    twice[:-1] |= same
    at = inside[order[twice]]
    for shift in range(3):
        flag[at + shift] = True
    return flag


def line_table(texts: list[str]) -> dict[str, np.ndarray]:
    """Counts and features by line, with each line's document, for a list of non-null texts."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    buf = np.frombuffer(b"\n".join(raw) + b"\n", dtype=np.uint8)
    breaks = np.flatnonzero(buf == 10)
    starts = np.concatenate([[0], breaks[:-1] + 1])
    per_doc = np.array([t.count(b"\n") + 1 for t in raw], dtype=np.int64)
    doc = np.repeat(np.arange(len(raw), dtype=np.int64), per_doc)
    total = lambda flags: np.add.reduceat(flags, starts, dtype=np.int64)
    solid = 1 - _SPACE[buf]
    first = solid.copy()
    first[1:] &= 1 - solid[:-1]
    out = {"doc": doc, "words": total(first), "word_chars": total(solid & _POINT[buf]), "symbols": total(_SYMBOL[buf])}
    bars, upper, digits, marks, letters = (total(x[buf]) for x in (_BAR, _UPPER, _DIGIT, _MARK, _LETTER))
    ids: dict[bytes, int] = defaultdict(count().__next__)
    words = buf.tobytes().split()
    codes = np.fromiter(map(ids.__getitem__, words), dtype=np.int64, count=len(words))
    line_of = np.repeat(np.arange(len(doc)), out["words"])
    flag = repeated_windows(codes, doc[line_of], len(ids))
    out["repeat_words"] = np.bincount(line_of[flag], minlength=len(doc)).astype(np.int64)
    again = np.zeros(len(doc), dtype=np.int64)
    at = 0
    for t in raw:
        lines = t.split(b"\n")
        if len(set(lines)) < len(lines):
            seen: set[bytes] = set()
            for i, line in enumerate(lines):
                if line in seen and out["words"][at + i]:
                    again[at + i] = 1
                seen.add(line)
        at += len(lines)
    out["dup_line"] = again
    chars, words_in = np.maximum(out["word_chars"], 1), np.maximum(out["words"], 1)
    last = buf[np.maximum(breaks - 1, 0)]
    edge = np.zeros(len(doc))
    edge[np.cumsum(per_doc) - 1] = 1
    edge[np.cumsum(per_doc) - per_doc] = 1
    out["x"] = np.column_stack([
        np.ones(len(doc)), np.minimum(5 * out["symbols"] / chars, 2), upper / np.maximum(letters, 1), np.minimum(2 * bars / words_in, 2), 2 * digits / chars,
        np.minimum(marks / words_in, 2), again, out["repeat_words"] / words_in, out["words"] < 4, np.clip(chars / words_in / 8 - 1, 0, 2), 1 - _END[last], edge,
    ]).astype(np.float64)
    return out


def viterbi(content: np.ndarray, trans: list[list[float]]) -> list[int]:
    """The best states of a chain whose state 1 scores `content[t]` at t and state 0 scores nothing."""
    (t00, t01), (t10, t11) = trans
    s0, s1, back = 0.0, float(content[0]), []
    for e in content[1:].tolist():
        from0, from1 = s1 + t10 > s0 + t00, s1 + t11 >= s0 + t01
        back.append((from0, from1))
        s0, s1 = (s1 + t10 if from0 else s0 + t00), (s1 + t11 if from1 else s0 + t01) + e
    state = int(s1 >= s0)
    path = [state]
    for step in reversed(back):
        state = int(step[state])
        path.append(state)
    return path[::-1]


def chain_gradient(e: np.ndarray, y: np.ndarray, mask: np.ndarray, trans: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Negative log-likelihood of padded chains, and its gradients by content emission and by transition."""
    n, steps = e.shape
    emit = np.stack([np.zeros_like(e), e], axis=2)
    alpha, beta = np.zeros((steps, n, 2)), np.zeros((steps, n, 2))
    alpha[0] = emit[:, 0]
    for t in range(1, steps):
        nxt = np.logaddexp(alpha[t - 1][:, :1] + trans[0], alpha[t - 1][:, 1:] + trans[1]) + emit[:, t]
        alpha[t] = np.where(mask[:, t, None], nxt, alpha[t - 1])
    for t in range(steps - 2, -1, -1):
        ahead = beta[t + 1] + emit[:, t + 1]
        nxt = np.stack([np.logaddexp(trans[0, 0] + ahead[:, 0], trans[0, 1] + ahead[:, 1]), np.logaddexp(trans[1, 0] + ahead[:, 0], trans[1, 1] + ahead[:, 1])], axis=1)
        beta[t] = np.where(mask[:, t + 1, None], nxt, 0.0)
    z = np.logaddexp(alpha[-1][:, 0], alpha[-1][:, 1])
    p1 = np.exp(alpha[:, :, 1].T + beta[:, :, 1].T - z[:, None])
    g_e = np.where(mask, p1 - y, 0.0)
    g_t = np.zeros((2, 2))
    pair = mask[:, 1:]
    gold = float(np.sum(np.where(mask, e * y, 0.0)))
    for a in (0, 1):
        for b in (0, 1):
            logp = alpha[:-1, :, a].T + trans[a, b] + emit[:, 1:, b] + beta[1:, :, b].T - z[:, None]
            hit = (y[:, :-1] == a) & (y[:, 1:] == b) & pair
            g_t[a, b] = np.sum(np.where(pair, np.exp(np.minimum(logp, 0.0)), 0.0)) - np.sum(hit)
            gold += trans[a, b] * np.sum(hit)
    return float(np.sum(z) - gold), g_e, g_t


def train_chain(texts: list[str], good: list[int], epochs: int = 200, rate: float = 0.15, l2: float = 1e-3) -> dict:
    """Fits the chain on weak labels. First the emissions alone are fitted, every line with its
    document's label; then the lines of bad documents that look like content become content, and
    the whole chain is fitted on the lines so labelled."""
    if not texts or len(set(good)) < 2:
        return PRIOR
    table = line_table(texts)
    x, doc = table["x"], table["doc"]
    seqs = []
    for d in range(len(texts)):
        at = np.flatnonzero((doc == d)) if len(texts) < 50 else np.arange(*np.searchsorted(doc, [d, d + 1]))
        seqs += [(at[i : i + SAMPLE_LINES], good[d]) for i in range(0, len(at), SAMPLE_LINES)]
    steps = max(len(s) for s, _ in seqs)
    rows, mask, y = np.zeros((len(seqs), steps), dtype=np.int64), np.zeros((len(seqs), steps), dtype=bool), np.zeros((len(seqs), steps))
    for i, (s, label) in enumerate(seqs):
        rows[i, : len(s)], mask[i, : len(s)], y[i, : len(s)] = s, True, label
    w = _descend(x, rows, mask, y, np.array(PRIOR["w"]), np.zeros((2, 2)), False, epochs, rate, l2)[0]
    alike = ((x @ w)[rows] > 0) & mask & (y == 0)
    alike[(alike == mask).all(axis=1)] = False  # at least one line of a bad sequence is bad
    y = np.where(alike, 1.0, y)
    w, trans = _descend(x, rows, mask, y, w, np.array(PRIOR["trans"]), True, epochs, rate, l2)
    return {"w": w.tolist(), "trans": trans.tolist()}


def _descend(x, rows, mask, y, w, trans, chained, epochs, rate, l2):
    """Adam on the likelihood of the chain; without `chained`, the transitions stay as they are."""
    m, v = np.zeros(len(w) + 4), np.zeros(len(w) + 4)
    scale = 1 / max(1, int(mask.sum()))
    for step in range(1, epochs + 1):
        e = np.where(mask, (x @ w)[rows], 0.0)
        if chained:
            _, g_e, g_t = chain_gradient(e, y, mask, trans)
        else:
            g_e, g_t = np.where(mask, 1 / (1 + np.exp(-e)) - y, 0.0), np.zeros((2, 2))
        g_line = np.bincount(rows[mask], weights=g_e[mask], minlength=len(x))
        g = np.concatenate([x.T @ g_line * scale + l2 * w, (g_t.ravel() * scale + l2 * trans.ravel()) * chained])
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        w, trans = w - move[: len(w)], trans - move[len(w) :].reshape(2, 2)
    return w, trans


VERDICT = StructType(
    [StructField(k, LongType()) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
    + [StructField("base_failed", BooleanType()), StructField("kept", BooleanType()), StructField("content_share", DoubleType()), StructField("line_labels", StringType())]
)


def judge(texts: list[str], model: dict) -> list[tuple]:
    """One verdict for each text; `line_labels` has C for content and B for boilerplate."""
    table = line_table(texts)
    n = len(texts)
    sums = {k: np.bincount(table["doc"], weights=table[k], minlength=n).astype(np.int64) for k in ("words", "word_chars", "symbols", "dup_line", "repeat_words")}
    content = table["x"] @ np.array(model["w"])
    bounds = np.searchsorted(table["doc"], np.arange(n + 1))
    rows = []
    for d in range(n):
        a, b = bounds[d], bounds[d + 1]
        states = viterbi(content[a:b], model["trans"])
        words = int(sums["words"][d])
        share = float(np.dot(table["words"][a:b], states)) / words if words else 0.0
        failed = words < 50 or 100 * int(sums["repeat_words"][d]) > 50 * words
        rows.append((words, int(sums["word_chars"][d]), int(sums["symbols"][d]), int(sums["dup_line"][d]), int(sums["repeat_words"][d]), failed, not failed and share >= MIN_CONTENT_SHARE, share, "".join("BC"[s] for s in states)))
    return rows


def line_verdict(text: Column, model: dict) -> Column:
    """A struct column with the counts, the lines' labels and the verdict of every whole text."""

    @F.pandas_udf(VERDICT)
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for col in batches:
            rows, part, size = [], [], 0
            for t in col:
                part.append(t or "")
                size += len(part[-1])
                if size >= PART_BYTES:
                    rows += judge(part, model)
                    part, size = [], 0
            if part:
                rows += judge(part, model)
            yield pd.DataFrame(rows, columns=VERDICT.names)

    return run(text)


def fit(docs: DataFrame, labels: DataFrame) -> dict:
    """Trains on at most SAMPLE_DOCS labelled documents of at most SAMPLE_BYTES bytes together."""
    rows = sorted(labelled_sample(docs, labels, "quality", F.lit(False), SAMPLE_DOCS, SAMPLE_BYTES).collect())
    return train_chain([r["text"] for r in rows], [r["label"] for r in rows])


def judge_documents(docs: DataFrame, model: dict, text_col: str = "text", into: str = "quality_verdict") -> DataFrame:
    """`docs` with the verdict struct in column `into`."""
    bound_batches(docs.sparkSession)
    return docs.withColumn(into, line_verdict(F.col(text_col), model))


def op8_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    model = fit(docs, read_table(spark, sf_dir, "labels"))
    cols = [f"quality_verdict.{k}" for k in VERDICT.names if k != "line_labels"]
    return judge_documents(docs, model).select("doc_id", *cols)
