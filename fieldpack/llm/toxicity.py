"""Toxicity: a bidirectional gated recurrent network with attention pooling, trained in numpy.

Every word enters with two learned inputs: a word embedding (words that enough training documents
hold; all others share one row) and a character embedding, the mean of learned vectors of its
character n-grams in hashed rows, so unknown words are read by their characters. Both start from how much more
often toxic documents hold the word or the n-gram and are then learned with the network. The network reads
all overlapping windows of every whole text, WINDOW words each, STEP words apart; attention pools
the states of both directions. A text's score is a logistic function of its most toxic windows and
of how many of its windows are toxic.

Training learns from bounded samples of labelled documents (bounded in documents and in bytes).
Which windows of a toxic document are toxic is not given, so training goes in turns: first the windows
with the n-grams that lean most to toxic in the other documents, then those that the network itself
finds most toxic. The logistic
function is fitted on a quarter of the sample that the network has not seen.

Cases: null and empty texts are one window of padding and get that window's score; texts shorter
than a window are padded and the padding is masked; repeated rows get equal scores; without both
labels the score is the share of label 1 (0 without labels).
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import count

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, crc_split, labelled_sample, read_table

WINDOW, STEP, HIDDEN = 16, 8, 10
#: Bounds of the training sample: documents with and without the label, and bytes of text of each side.
SAMPLE_TOXIC, SAMPLE_CLEAN, SAMPLE_BYTES = 1500, 2000, 12 << 20
#: Width of both embeddings, rows of the n-gram table, lengths of n-grams, and the least documents of a known word.
WORD_DIM, CHAR_DIM, GRAM_ROWS, NGRAMS, LEAST_DOCS = 6, 10, 1 << 17, (3, 4, 5, 6), 4
INPUTS = WORD_DIM + CHAR_DIM
MARKS = '.,;:!?*#$%&|()"'
CHUNK = 8192
_MIX = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: str | None) -> list[str]:
    return (text or "").lower().split()


def bare(word: str) -> str:
    """The word without marks around it; a word of marks only stays as it is."""
    return word.strip(MARKS) or word


def gram_rows(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the n-gram table of all words, and the word that each belongs to. ^ and $ mark a word's ends."""
    joined = "".join(f"^{w}$" for w in words)
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint64)
    sizes = np.fromiter((len(w) + 2 for w in words), dtype=np.int64, count=len(words))
    owner = np.repeat(np.arange(len(words), dtype=np.int32), sizes)
    rows, owners = [], []
    with np.errstate(over="ignore"):
        for n in NGRAMS:
            m = len(points) - n + 1
            if m <= 0:
                continue
            h = np.full(m, np.uint64(n))
            for i in range(n):
                h = (h * np.uint64(1099511628211)) ^ points[i : i + m]
            whole = np.flatnonzero(owner[:m] == owner[n - 1 :])
            rows.append((((h[whole] * _MIX) >> np.uint64(40)) % np.uint64(GRAM_ROWS)).astype(np.int32))
            owners.append(owner[whole])
    if not rows:
        return np.empty(0, dtype=np.int32), np.empty(0, dtype=np.int32)
    return np.concatenate(rows), np.concatenate(owners)


@dataclass
class Embeddings:
    """Learned inputs of words: `known` gives a word's row in `words` (row 0 is for all others)."""

    known: dict[str, int]
    words: np.ndarray
    grams: np.ndarray

    def parts(self, vocabulary: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Word rows, n-gram rows, their owners, and 1 / n-grams of each word."""
        cores = [bare(w) for w in vocabulary]
        at = np.fromiter((self.known.get(w, 0) for w in cores), dtype=np.int64, count=len(cores))
        rows, owner = gram_rows(cores)
        share = 1.0 / np.maximum(1, np.bincount(owner, minlength=len(cores)))
        return at, rows, owner, share

    def inputs(self, vocabulary: list[str]) -> np.ndarray:
        """(words + 1, INPUTS); the last row is padding."""
        out = np.zeros((len(vocabulary) + 1, INPUTS), dtype=np.float32)
        for i in range(0, len(vocabulary), CHUNK):
            at, rows, owner, share = self.parts(vocabulary[i : i + CHUNK])
            out[i : i + len(at), :WORD_DIM] = self.words[at]
            out[i : i + len(at), WORD_DIM:] = mean_rows(self.grams, rows, owner, share)
        return out


def mean_rows(grams: np.ndarray, rows: np.ndarray, owner: np.ndarray, share: np.ndarray) -> np.ndarray:
    got = np.stack([np.bincount(owner, weights=grams[rows, d], minlength=len(share)) for d in range(grams.shape[1])], axis=1) if len(rows) else np.zeros((len(share), grams.shape[1]))
    return (got * share[:, None]).astype(np.float32)


def _sigmoid(x):
    return 0.5 * np.tanh(0.5 * x) + 0.5


def new_network(seed: int = 3) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    net = {}
    for side in ("f", "b"):
        net[f"W{side}"] = rng.normal(0, 0.4, (INPUTS, 3 * HIDDEN))
        net[f"U{side}"] = rng.normal(0, 0.3, (HIDDEN, 3 * HIDDEN))
        net[f"c{side}"] = np.zeros(3 * HIDDEN)
    net |= {"v": rng.normal(0, 0.3, 2 * HIDDEN), "o": rng.normal(0, 0.3, 2 * HIDDEN), "k": np.zeros(1)}
    return net


def run_side(proj: np.ndarray, codes: np.ndarray, u: np.ndarray, backward: bool, keep: list | None = None) -> np.ndarray:
    """States of one direction, (steps, windows, HIDDEN). `proj` are the projected inputs by word code."""
    h_n = HIDDEN
    n, steps = codes.shape
    out = np.empty((steps, n, h_n), dtype=proj.dtype)
    h = np.zeros((n, h_n), dtype=proj.dtype)
    for t in range(steps - 1, -1, -1) if backward else range(steps):
        a = proj[codes[:, t]]
        gates = _sigmoid(a[:, : 2 * h_n] + h @ u[:, : 2 * h_n])
        z, r = gates[:, :h_n], gates[:, h_n:]
        rh = r * h
        new = np.tanh(a[:, 2 * h_n :] + rh @ u[:, 2 * h_n :])
        if keep is not None:
            keep.append((t, h, z, r, rh, new))
        h = new + z * (h - new)
        out[t] = h
    return out


def attend(net: dict, hf: np.ndarray, hb: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Logits, attention (steps, windows) and the pooled states."""
    v, o = net["v"].astype(hf.dtype), net["o"].astype(hf.dtype)
    s = hf @ v[:HIDDEN] + hb @ v[HIDDEN:]
    s = np.where(mask.T, s, hf.dtype.type(-1e9))
    s = np.exp(s - s.max(axis=0))
    alpha = s / s.sum(axis=0)
    pooled = np.concatenate([(alpha[:, :, None] * hf).sum(axis=0), (alpha[:, :, None] * hb).sum(axis=0)], axis=1)
    return pooled @ o + net["k"][0].astype(hf.dtype), alpha, pooled


def logits(net: dict, feats: np.ndarray, codes: np.ndarray, starts: np.ndarray, sizes: np.ndarray, dtype=np.float32) -> np.ndarray:
    """Logits of the windows that begin at `starts` in a row of word codes; the projections are made once per
    distinct word, and windows are laid out a chunk at a time."""
    side = {s: ((feats @ net[f"W{s}"] + net[f"c{s}"]).astype(dtype), net[f"U{s}"].astype(dtype)) for s in ("f", "b")}
    out = np.empty(len(starts), dtype=np.float64)
    for i in range(0, len(starts), CHUNK):
        part, mask = lay_out(codes, starts[i : i + CHUNK], sizes[i : i + CHUNK])
        hf, hb = (run_side(side[s][0], part, side[s][1], s == "b") for s in ("f", "b"))
        out[i : i + CHUNK] = attend(net, hf, hb, mask)[0]
    return out


def gradients(net: dict, feats: np.ndarray, codes: np.ndarray, mask: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray], np.ndarray]:
    """Mean logistic loss of windows, its gradients by backpropagation through time, and those by `feats`."""
    n = len(codes)
    kept: dict[str, list] = {"f": [], "b": []}
    states = {}
    for s in ("f", "b"):
        states[s] = run_side(feats @ net[f"W{s}"] + net[f"c{s}"], codes, net[f"U{s}"], s == "b", kept[s])
    logit, alpha, pooled = attend(net, states["f"], states["b"], mask)
    loss = float(np.mean(np.logaddexp(0, logit) - y * logit))
    g = {k: np.zeros_like(v) for k, v in net.items()}
    d_feats = np.zeros_like(feats)
    d_logit = (_sigmoid(logit) - y) / n
    g["o"], g["k"][0] = pooled.T @ d_logit, d_logit.sum()
    d_pool = d_logit[:, None] * net["o"]
    both = np.concatenate([states["f"], states["b"]], axis=2)
    d_alpha = np.einsum("tnh,nh->tn", both, d_pool)
    d_s = alpha * (d_alpha - (alpha * d_alpha).sum(axis=0))
    g["v"] = np.einsum("tn,tnh->h", d_s, both)
    d_both = alpha[:, :, None] * d_pool + d_s[:, :, None] * net["v"]
    for s, lo in (("f", 0), ("b", HIDDEN)):
        u, d_h = net[f"U{s}"], np.zeros((n, HIDDEN))
        d_proj = np.zeros((len(feats), 3 * HIDDEN))
        for t, h, z, r, rh, new in reversed(kept[s]):
            d_h = d_h + d_both[t][:, lo : lo + HIDDEN]
            d_new, d_z = d_h * (1 - z) * (1 - new * new), d_h * (h - new) * z * (1 - z)
            d_rh = d_new @ u[:, 2 * HIDDEN :].T
            d_r = d_rh * h * r * (1 - r)
            d_a = np.concatenate([d_z, d_r, d_new], axis=1)
            g[f"U{s}"][:, : 2 * HIDDEN] += h.T @ d_a[:, : 2 * HIDDEN]
            g[f"U{s}"][:, 2 * HIDDEN :] += rh.T @ d_new
            np.add.at(d_proj, codes[:, t], d_a)
            d_h = d_h * z + d_rh * r + d_a[:, : 2 * HIDDEN] @ u[:, : 2 * HIDDEN].T
        g[f"W{s}"], g[f"c{s}"] = feats.T @ d_proj, d_proj.sum(axis=0)
        d_feats += d_proj @ net[f"W{s}"].T
    return loss, g, d_feats


def window_table(lengths: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All overlapping windows of consecutive texts: where each begins, how many words it has, and its text.

    The last window of a text ends with the text; a text without words has one window without words."""
    n = np.asarray(lengths, dtype=np.int64)
    per = np.maximum(1, -(-(n - WINDOW) // STEP) + 1)
    owner = np.repeat(np.arange(len(n)), per)
    first = np.arange(per.sum()) - np.repeat(np.cumsum(per) - per, per)
    start = np.minimum(first * STEP, np.maximum(n[owner] - WINDOW, 0))
    return start + offsets[owner], np.minimum(n[owner] - start, WINDOW).astype(np.int32), owner


def lay_out(codes: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Word codes (windows, WINDOW), -1 where there is no word, and the mask of the attention."""
    step = np.arange(WINDOW)
    inside = step < sizes[:, None]
    at = np.where(inside, starts[:, None] + step, 0)
    got = np.where(inside, codes[at] if len(codes) else -1, -1)
    inside[:, 0] |= sizes == 0
    return got, inside


class Read:
    """Texts as codes in one vocabulary, with all their windows."""

    def __init__(self, texts: list[str | None]):
        ids: dict[str, int] = defaultdict(count().__next__)
        parts, lengths = [], np.zeros(len(texts), dtype=np.int64)
        for i, t in enumerate(texts):
            words = words_of(t)
            lengths[i] = len(words)
            parts.append(np.fromiter(map(ids.__getitem__, words), dtype=np.int32, count=len(words)))
        self.vocabulary = list(ids)
        self.codes = np.concatenate(parts) if parts else np.empty(0, dtype=np.int32)
        self.offsets, self.lengths = np.cumsum(lengths) - lengths, lengths
        self.starts, self.sizes, self.owner = window_table(lengths, self.offsets)

    def text(self, i: int) -> np.ndarray:
        return self.codes[self.offsets[i] : self.offsets[i] + self.lengths[i]]


def text_evidence(got: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """By text: the best window's logit, the mean of its three best, how many windows are toxic, and how many there are."""
    order = np.lexsort((-got, owner))
    first = np.searchsorted(owner[order], np.arange(n))
    many = np.bincount(owner, minlength=n)
    best = np.stack([got[order][first + np.minimum(i, many - 1)] for i in range(3)])
    hot = np.bincount(owner, weights=_sigmoid(np.clip(got, -30, 30)), minlength=n)
    return np.column_stack([best[0], best.mean(axis=0), np.log1p(hot), np.log(many), np.ones(n)])


@dataclass
class ToxicModel:
    embeddings: Embeddings | None = None
    net: dict[str, np.ndarray] | None = None
    scale: np.ndarray | None = None
    share: float = 0.0
    history: list[float] = field(default_factory=list)

    def evidence(self, texts: list[str | None]) -> np.ndarray:
        read = Read(texts)
        got = logits(self.net, self.embeddings.inputs(read.vocabulary), read.codes, read.starts, read.sizes)
        return text_evidence(got, read.owner, len(texts))

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.net is None:
            return np.full(len(texts), self.share)
        return _sigmoid(np.clip(self.evidence(texts) @ self.scale, -40, 40))


def without_copies(read: Read, bands: int = 6) -> list[int]:
    """Positions of the documents that share no band of minima over word pairs with an earlier one: copies would make any word of theirs look common."""
    seen: set[tuple] = set()
    keep = []
    with np.errstate(over="ignore"):
        word = np.fromiter(map(hash_word, read.vocabulary), dtype=np.uint64, count=len(read.vocabulary))
        for i in range(len(read.lengths)):
            w = word[read.text(i)]
            h = w[:-1] * _MIX ^ (w[1:] << np.uint64(1))
            marks = {(b, *(int(np.min((h * np.uint64(2 * (2 * b + r) + 2654435761)) >> np.uint64(20))) for r in (0, 1))) for b in range(bands)} if len(h) else set()
            if not marks & seen:
                keep.append(i)
            seen |= marks
    return keep


def hash_word(word: str) -> int:
    """A stable 64-bit hash (FNV-1a): the same in every process."""
    h = 0xCBF29CE484222325
    for b in word.encode("utf-8", "surrogatepass"):
        h = ((h ^ b) * 0x100000001B3) & 0xFFFFFFFFFFFFFFFF
    return h


@dataclass(frozen=True)
class Training:
    """Turns of choosing windows, steps of each, windows of a document (toxic, clean), windows of a step, the share of toxic ones, and rates."""

    turns: int = 3
    steps: int = 60
    toxic_windows: int = 2
    clean_windows: int = 4
    batch: int = 256
    toxic_share: float = 0.25
    rate: float = 0.01
    embedding_rate: float = 0.005
    hidden_words: float = 0.3
    seed: int = 11


def leaning(toxic: np.ndarray, clean: np.ndarray, n_toxic: float, n_clean: float) -> np.ndarray:
    """Log-odds of document counts towards toxic, of what chance alone leaves of the count; 0 where there is none."""
    sure = np.maximum(0.0, toxic - 1.64 * np.sqrt(np.maximum(toxic, 0)))
    odds = np.log((sure + 0.5) / (n_toxic + 1)) - np.log((np.maximum(clean, 0) + 0.5) / (n_clean + 1))
    return np.maximum(0.0, odds) / 4


class Counts:
    """In how many of the chosen documents of either label a core word and an n-gram row occur."""

    def __init__(self, read: Read, use: np.ndarray, labels: np.ndarray):
        cores = [bare(w) for w in read.vocabulary]
        number: dict[str, int] = defaultdict(count().__next__)
        core = np.fromiter(map(number.__getitem__, cores), dtype=np.int32, count=len(cores))
        self.names, self.rows, owner = list(number), *gram_rows(cores)
        order = np.argsort(owner, kind="stable")
        self.rows = self.rows[order]
        self.ends = np.cumsum(np.bincount(owner, minlength=len(cores)))
        begin = np.concatenate([[0], self.ends[:-1]]) if len(cores) else self.ends
        self.n = [float((~labels[use]).sum()), float(labels[use].sum())]
        self.words, self.grams = np.zeros((2, len(self.names))), np.zeros((2, GRAM_ROWS))
        for i in np.flatnonzero(use):
            mine = np.unique(read.text(i))
            self.words[int(labels[i]), np.unique(core[mine])] += 1
            if len(mine):
                self.grams[int(labels[i]), np.unique(np.concatenate([self.rows[begin[j] : self.ends[j]] for j in mine]))] += 1

    def known(self) -> dict[str, int]:
        """Rows of the words that at least LEAST_DOCS of the documents hold."""
        return {self.names[j]: row + 1 for row, j in enumerate(np.flatnonzero(self.words.sum(axis=0) >= LEAST_DOCS))}

    def starting_rows(self, table: np.ndarray, counts: np.ndarray) -> np.ndarray:
        table[:, 0] += leaning(counts[1], counts[0], self.n[1], self.n[0])
        return table

    def by_word(self, toxic: bool) -> np.ndarray:
        """The most leaning n-gram of each word of the vocabulary, for a document of that label, whose own share of the counts is taken out."""
        own = np.array([0.0 if toxic else 1.0, 1.0 if toxic else 0.0])
        lean = leaning(self.grams[1] - own[1], self.grams[0] - own[0], self.n[1] - own[1], self.n[0] - own[0])
        return np.maximum.reduceat(lean[self.rows], np.concatenate([[0], self.ends[:-1]])) if len(self.ends) else np.empty(0)

    def window_ranks(self, read: Read, labels: np.ndarray) -> np.ndarray:
        out = np.zeros(len(read.starts))
        for side in (False, True):
            lean = np.append(self.by_word(side), 0.0)
            mine = np.flatnonzero(labels[read.owner] == side)
            for i in range(0, len(mine), CHUNK):
                at = mine[i : i + CHUNK]
                got = lean[lay_out(read.codes, read.starts[at], read.sizes[at])[0]]
                out[at] = got.max(axis=1) + 1e-2 * got.sum(axis=1)
        return out


def choose(read: Read, toxic: np.ndarray, use: np.ndarray, rank: np.ndarray, p: Training, rng: np.random.Generator) -> np.ndarray:
    """Windows to learn from: those of every document that rank highest, and some other clean ones."""
    order = np.lexsort((-rank, read.owner))
    order = order[use[read.owner[order]]]
    place = np.arange(len(order)) - np.searchsorted(read.owner[order], read.owner[order])
    take = order[place < np.where(toxic[read.owner[order]], p.toxic_windows, p.clean_windows)]
    others = order[~toxic[read.owner[order]]]
    return np.concatenate([take, rng.permutation(others)[: len(take) // 2]])


def train(texts: list[str], toxic: list[int], p: Training = Training()) -> ToxicModel:
    """Fits embeddings, network and the probability scale."""
    read = Read(texts)
    alone = without_copies(read)
    labels = np.array(toxic, dtype=bool)
    if len(set(labels[alone].tolist())) < 2:
        return ToxicModel(share=float(labels[alone].mean()) if alone else 0.0)
    rng = np.random.default_rng(p.seed)
    use, scaled = np.zeros(len(labels), dtype=bool), np.zeros(len(labels), dtype=bool)
    for side in (False, True):  # every fourth of each label fits the scale
        own = rng.permutation(np.array([i for i in alone if labels[i] == side]))
        scaled[own[::4]], use[own[::4]] = True, False
        use[np.setdiff1d(own, own[::4])] = True
    if not (labels[use].any() and (~labels[use]).any()):
        use = use | scaled
    counts = Counts(read, use, labels)
    known = counts.known()
    held = np.array([counts.words[:, 0] * 0, *(counts.words[:, j] for j in np.flatnonzero(counts.words.sum(axis=0) >= LEAST_DOCS))]).T
    emb = Embeddings(known, counts.starting_rows(rng.normal(0, 0.1, (len(known) + 1, WORD_DIM)), held), counts.starting_rows(rng.normal(0, 0.1, (GRAM_ROWS, CHAR_DIM)), counts.grams))
    seen_w, seen_g = np.full(emb.words.shape, 1e-6), np.full(emb.grams.shape, 1e-6)
    net = new_network()
    m, v = {k: np.zeros_like(x) for k, x in net.items()}, {k: np.zeros_like(x) for k, x in net.items()}
    step, history = 0, []
    for turn in range(p.turns):
        rank = logits(net, emb.inputs(read.vocabulary), read.codes, read.starts, read.sizes) if turn else counts.window_ranks(read, labels)
        chosen = choose(read, labels, use, rank, p, rng)
        y = labels[read.owner[chosen]].astype(float)
        hot, cold = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
        n_hot = int(p.batch * p.toxic_share)
        losses = []
        for _ in range(p.steps):
            at = np.concatenate([rng.choice(hot, n_hot), rng.choice(cold, p.batch - n_hot)])
            step += 1
            part, mask = lay_out(read.codes, read.starts[chosen[at]], read.sizes[chosen[at]])
            named, codes = np.unique(part, return_inverse=True)
            codes = codes.reshape(part.shape)
            pad = int(len(named) and named[0] < 0)
            rows_w, rows_g, owner, share = emb.parts([read.vocabulary[j] for j in named[pad:]])
            rows_w = np.where(rng.random(len(rows_w)) < p.hidden_words, 0, rows_w)  # some words are hidden, so that characters are learned
            feats = np.zeros((len(named), INPUTS))
            feats[pad:, :WORD_DIM], feats[pad:, WORD_DIM:] = emb.words[rows_w], mean_rows(emb.grams, rows_g, owner, share)
            loss, g, d_feats = gradients(net, feats, codes, mask, y[at])
            losses.append(loss)
            rate = p.rate * 0.5 ** (step / 300)
            for k in net:
                m[k], v[k] = 0.9 * m[k] + 0.1 * g[k], 0.999 * v[k] + 0.001 * g[k] ** 2
                net[k] = net[k] - rate * ((m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8) + 1e-4 * net[k])
            d_word, d_gram = d_feats[pad:, :WORD_DIM], (d_feats[pad:, WORD_DIM:] * share[:, None])[owner]
            for table, seen, at_row, grad in ((emb.words, seen_w, rows_w, d_word), (emb.grams, seen_g, rows_g, d_gram)):
                rows, place = np.unique(at_row, return_inverse=True)
                total = np.stack([np.bincount(place, weights=grad[:, d], minlength=len(rows)) for d in range(grad.shape[1])], axis=1)
                total += 1e-6 * table[rows]
                seen[rows] += total**2
                table[rows] -= p.embedding_rate * total / np.sqrt(seen[rows])
        history.append(float(np.mean(losses)))
    emb = Embeddings(emb.known, emb.words.astype(np.float32), emb.grams.astype(np.float32))
    model = ToxicModel(emb, net, history=history)
    got = text_evidence(logits(net, emb.inputs(read.vocabulary), read.codes, read.starts, read.sizes), read.owner, len(labels))
    fit_on = scaled if labels[scaled].any() and (~labels[scaled]).any() else use
    model.scale = fit_scale(got[fit_on], labels[fit_on].astype(float))
    return model


def fit_scale(x: np.ndarray, y: np.ndarray, steps: int = 100, ridge: float = 0.3) -> np.ndarray:
    """Newton steps of a logistic fit with a little shrinkage."""
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = _sigmoid(np.clip(x @ w, -30, 30))
        g = x.T @ (p - y) + ridge * w
        h = (x * (p * (1 - p) + 1e-6)[:, None]).T @ x + ridge * np.eye(len(w))
        w = w - np.clip(np.linalg.solve(h, g), -0.5, 0.5)
    return w


def toxic_score(text: Column, model: ToxicModel) -> Column:
    @F.pandas_udf("double")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for col in batches:
            out, part, size = [], [], 0
            for t in col:
                part.append(t)
                size += len(t or "")
                if size >= 1 << 20:
                    out.append(model.scores(part))
                    part, size = [], 0
            if part:
                out.append(model.scores(part))
            yield pd.Series(np.concatenate(out) if out else np.empty(0))

    return run(text)


def fit(docs: DataFrame, labels: DataFrame, held_out: Column) -> ToxicModel:
    """Trains on bounded samples of labelled rows of either label."""
    sides = ((1, SAMPLE_TOXIC), (0, SAMPLE_CLEAN))
    rows = [tuple(r) for side, most in sides for r in labelled_sample(docs, labels.where(F.col("toxic") == side), "toxic", held_out, most, SAMPLE_BYTES).select("doc_id", "text", "label").collect()]
    rows.sort()
    return train([r[1] for r in rows], [r[2] for r in rows])


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    bound_batches(spark)
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    held = crc_split(F.col("doc_id"), 4, 2)
    model = fit(docs, read_table(spark, sf_dir, "labels", "doc_id", "toxic"), held)
    scored = docs.select("doc_id", held.alias("held_out"), toxic_score(F.col("text"), model).alias("score"))
    return scored.withColumn("predicted", F.when(F.col("score") >= 0.3, 1).otherwise(0))
