"""Toxicity by a bidirectional gated recurrent network with attention pooling, trained in numpy.

A word's input is an embedding of the word beside the mean embedding of its character n-grams
(both hashed). The network reads windows of ``WINDOW`` words, every ``STRIDE`` words, so all
windows overlap; attention pools the states of both directions to one logit, and a text's score
is that of its most toxic window. Labels are of whole texts, so learning picks the windows: first
by the log odds of their features, then by the network itself.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.llm import kernels as K
from corpus_audit.llm.common import fit_in_task, held_out, learning_sample, small_side, whole_text

WINDOW, STRIDE = 24, 12
WORD_ROWS, CHAR_ROWS, WORD_DIM, CHAR_DIM, HIDDEN = 1 << 18, 1 << 16, 8, 12, 8
#: Learning rows per label, and the longest text among them.
MAX_LEARN, MAX_LEARN_CHARS = 2000, 60_000
THRESHOLD = 0.7
#: Weight of the words' start in their embeddings, and the learning texts that a feature must be in to have one.
START, MIN_TEXTS = 0.5, 3
BLOCK = 2048


class Inputs:
    """Distinct words of some texts, their feature numbers, and the windows over the texts."""

    def __init__(self, data: np.ndarray, off: np.ndarray):
        words = K.Words.whole(data, off, folded=True)
        _, at, self.word_id = np.unique(words.hash, return_index=True, return_inverse=True)
        self.word_row = (words.hash[at] >> np.uint64(20)).astype(np.int64) % WORD_ROWS
        self.grams, self.gram_start = char_grams(data, words.start[at], words.end[at])
        self.first = words.first
        counts = np.diff(words.first)
        per_text = np.where(counts > 0, np.maximum(1, -(-(counts - (WINDOW - STRIDE)) // STRIDE)), 0)
        self.window_start = np.concatenate([[0], np.cumsum(per_text)])
        text = np.repeat(np.arange(len(counts)), per_text)
        step = np.arange(len(text)) - self.window_start[text]
        self.begin = words.first[text] + step * STRIDE
        self.length = np.minimum(WINDOW, words.first[text + 1] - self.begin)

    def windows(self, pick: np.ndarray | slice) -> tuple[np.ndarray, np.ndarray]:
        """Word numbers (padded by the number of words) and lengths of the picked windows."""
        begin, length = self.begin[pick], self.length[pick]
        inside = np.arange(WINDOW)[None, :] < length[:, None]
        at = np.where(inside, begin[:, None] + np.arange(WINDOW)[None, :], 0)
        return np.where(inside, self.word_id[at] if len(self.word_id) else 0, len(self.word_row)), length


def char_grams(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashed byte n-grams of each word: all of 4 and 5 bytes, and its first 3, 4 and 5 bytes; A-Z folded."""
    size = end - start
    owners, codes = [], []

    def gram(at: np.ndarray, n: int, salt: int) -> np.ndarray:
        total = np.zeros(len(at), dtype=np.uint64)
        for k in range(n):
            total = total * np.uint64(0x9E3779B97F4A7C15) + K.FOLDED_VALUES[data[at + k]]
        return (K.mix(total + np.uint64(salt)) % np.uint64(CHAR_ROWS)).astype(np.int64)

    for n in (4, 5):
        count = np.maximum(0, size - n + 1)
        owner = np.repeat(np.arange(len(start)), count)
        place = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
        owners.append(owner)
        codes.append(gram(start[owner] + place, n, n))
    for n in (3, 4, 5):
        owner = np.flatnonzero(size >= n)
        owners.append(owner)
        codes.append(gram(start[owner], n, 100 + n))
    owner = np.concatenate(owners)
    order = np.argsort(owner, kind="stable")
    return np.concatenate(codes)[order], np.searchsorted(owner[order], np.arange(len(start) + 1))


def _means(table: np.ndarray, grams: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Mean row of the table over each word's n-grams, some words at a time."""
    out = np.zeros((len(start) - 1, table.shape[1]), dtype=np.float32)
    for i in range(0, len(out), 8192):
        cut = start[i : i + 8193]
        sums = np.zeros((cut[-1] - cut[0] + 1, table.shape[1]))
        np.cumsum(table[grams[cut[0] : cut[-1]]], axis=0, out=sums[1:])
        out[i : i + 8192] = (sums[cut[1:] - cut[0]] - sums[cut[:-1] - cut[0]]) / np.maximum(1, np.diff(cut))[:, None]
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


class Network:
    """Parameters, forward and backward passes."""

    def __init__(self, seed: int = 3):
        rng = np.random.default_rng(seed)
        draw = lambda *shape, scale: (rng.standard_normal(shape) * scale).astype(np.float32)
        d, h = WORD_DIM + CHAR_DIM, HIDDEN
        self.p = {
            "word": draw(WORD_ROWS, WORD_DIM, scale=0.1), "char": draw(CHAR_ROWS, CHAR_DIM, scale=0.3),
            "input": draw(d, 6 * h, scale=d**-0.5), "bias": np.zeros(6 * h, dtype=np.float32),
            "fore": draw(h, 3 * h, scale=h**-0.5), "back": draw(h, 3 * h, scale=h**-0.5),
            "query": draw(2 * h, scale=0.5), "out": draw(2 * h, scale=0.5), "out_bias": np.zeros(1, dtype=np.float32),
        }
        self.shift = 0.0

    def vectors(self, rows: np.ndarray, grams: np.ndarray, start: np.ndarray) -> np.ndarray:
        return np.concatenate([self.p["word"][rows], _means(self.p["char"], grams, start)], axis=1)

    def project(self, vectors: np.ndarray) -> np.ndarray:
        """Both directions' gate inputs of each word; the last row is the padding."""
        return np.concatenate([vectors @ self.p["input"] + self.p["bias"], np.zeros((1, 6 * HIDDEN), dtype=np.float32)])

    def states(self, projected: np.ndarray, ids: np.ndarray, inside: np.ndarray, keep: list | None = None) -> np.ndarray:
        """(steps, windows, 2 * HIDDEN); ``keep`` collects what the backward pass needs."""
        h, (n, steps) = HIDDEN, ids.shape
        out = np.empty((steps, n, 2 * h), dtype=np.float32)
        full = inside.all(axis=0)
        for side, u in enumerate((self.p["fore"], self.p["back"])):
            state = np.zeros((n, h), dtype=np.float32)
            for t in range(steps) if side == 0 else range(steps - 1, -1, -1):
                x = projected[ids[:, t], side * 3 * h : (side + 1) * 3 * h]
                g = state @ u
                zr = _sigmoid(x[:, : 2 * h] + g[:, : 2 * h])
                new = np.tanh(x[:, 2 * h :] + zr[:, h:] * g[:, 2 * h :])
                if keep is not None:
                    keep.append((side, t, state, zr, new, g[:, 2 * h :]))
                moved = new + zr[:, :h] * (state - new)
                state = moved if full[t] else np.where(inside[:, t, None], moved, state)
                out[t, :, side * h : (side + 1) * h] = state
        return out

    def pool(self, states: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        scores = np.where(inside.T, states @ self.p["query"], -1e9)
        weight = np.exp(scores - scores.max(axis=0))
        weight /= weight.sum(axis=0)
        context = np.einsum("tn,tnh->nh", weight, states)
        return context @ self.p["out"] + self.p["out_bias"], context, weight

    def logits(self, inputs: Inputs, pick: np.ndarray | None = None) -> np.ndarray:
        """The logit of each (picked) window."""
        projected = self.project(self.vectors(inputs.word_row, inputs.grams, inputs.gram_start))
        pick = np.arange(len(inputs.begin)) if pick is None else pick
        out = np.empty(len(pick), dtype=np.float32)
        for i in range(0, len(pick), BLOCK):
            ids, length = inputs.windows(pick[i : i + BLOCK])
            inside = np.arange(WINDOW)[None, :] < length[:, None]
            out[i : i + BLOCK] = self.pool(self.states(projected, ids, inside), inside)[0]
        return out

    def gradients(self, inputs: Inputs, pick: np.ndarray, label: np.ndarray) -> tuple[dict, dict]:
        """Gradients of the mean log loss: dense ones, and (rows, values) of the embedding tables."""
        p, h = self.p, HIDDEN
        ids, length = inputs.windows(pick)
        used, ids = np.unique(ids, return_inverse=True)
        ids = ids.reshape(len(pick), WINDOW)
        real = used[used < len(inputs.word_row)]
        if len(real) == len(used):  # no padding among them
            used = np.append(used, len(inputs.word_row))
        size = np.diff(inputs.gram_start)[real]
        start = np.concatenate([[0], np.cumsum(size)])
        grams = inputs.grams[np.repeat(inputs.gram_start[real] - start[:-1], size) + np.arange(start[-1])]
        vectors = self.vectors(inputs.word_row[real], grams, start)
        projected = self.project(vectors)
        inside, kept = np.arange(WINDOW)[None, :] < length[:, None], []
        states = self.states(projected, ids, inside, kept)
        logit, context, weight = self.pool(states, inside)
        d_logit = ((_sigmoid(logit) - label) / len(pick)).astype(np.float32)
        g = {"out": context.T @ d_logit, "out_bias": d_logit.sum(keepdims=True)}
        d_context = d_logit[:, None] * p["out"]
        d_weight = np.einsum("nh,tnh->tn", d_context, states)
        d_score = weight * (d_weight - (weight * d_weight).sum(axis=0))
        g["query"] = np.einsum("tn,tnh->h", d_score, states)
        d_states = weight[:, :, None] * d_context + d_score[:, :, None] * p["query"]
        d_projected = np.zeros_like(projected)
        g["fore"], g["back"] = np.zeros_like(p["fore"]), np.zeros_like(p["back"])
        carry = [np.zeros((len(pick), h), dtype=np.float32) for _ in range(2)]
        for side, t, before, zr, new, gn in reversed(kept):
            name = ("fore", "back")[side]
            z, r, live = zr[:, :h], zr[:, h:], inside[:, t, None]
            total = carry[side] + d_states[t, :, side * h : (side + 1) * h]
            d = np.where(live, total, 0)
            d_new = d * (1 - z) * (1 - new * new)
            d_z, d_r = d * (before - new) * z * (1 - z), d_new * gn * r * (1 - r)
            d_g = np.concatenate([d_z, d_r, d_new * r], axis=1)
            g[name] += before.T @ d_g
            carry[side] = np.where(live, d * z + d_g @ p[name].T, total)
            np.add.at(d_projected[:, side * 3 * h : (side + 1) * 3 * h], ids[:, t], np.concatenate([d_z, d_r, d_new], axis=1))
        d_projected = d_projected[: len(real)]
        g["bias"], g["input"] = d_projected.sum(axis=0), vectors.T @ d_projected
        d_vectors = d_projected @ p["input"].T
        d_gram = np.repeat(d_vectors[:, WORD_DIM:] / np.maximum(1, size)[:, None], size, axis=0)
        return g, {"word": (inputs.word_row[real], d_vectors[:, :WORD_DIM]), "char": (grams, d_gram)}


def _first_choice(inputs: Inputs, toxic: np.ndarray, block: int = 200) -> tuple[np.ndarray, list[np.ndarray]]:
    """A window weight from feature log odds over texts, the highest of any feature in the window; and a start for the word embeddings.

    The start is by how many standard deviations more toxic texts hold the word than its texts in all let
    expect, so a word of a single text says little.
    """
    weights, marks = [], []
    n_words = len(inputs.word_row)
    n_pos, n_neg = max(1, int(toxic.sum())), max(1, int((1 - toxic).sum()))
    for rows, start, size in ((inputs.word_row, np.arange(n_words + 1), WORD_ROWS), (inputs.grams, inputs.gram_start, CHAR_ROWS)):
        seen_in = np.zeros((2, size))
        for i in range(0, len(toxic), block):
            first = inputs.first[i : i + block + 1]
            text_of = np.repeat(np.arange(len(first) - 1), np.diff(first))
            text, word = np.divmod(np.unique(text_of * np.int64(n_words) + inputs.word_id[first[0] : first[-1]]), max(1, n_words))
            count = np.diff(start)[word]
            flat = rows[np.repeat(start[word] - (np.cumsum(count) - count), count) + np.arange(count.sum())]
            text, row = np.divmod(np.unique(np.repeat(text, count) * np.int64(size) + flat), size)
            for k in (0, 1):
                seen_in[k] += np.bincount(row[toxic[i + text] == k], minlength=size)
        share = n_pos / (n_pos + n_neg)
        known = seen_in.sum(axis=0) >= MIN_TEXTS
        marks.append(np.where(known, np.clip((seen_in[1] - share * seen_in.sum(axis=0)) / np.sqrt(1 + share * seen_in.sum(axis=0)), -4, 4), np.nan))
        odds = np.log((seen_in[1] + 0.5) / (n_pos + 1)) - np.log((seen_in[0] + 0.5) / (n_neg + 1))
        odds = np.where(known, odds, odds.min())
        best = np.full(n_words + 1, -np.inf)
        filled = np.diff(start) > 0
        if filled.any():
            best[:-1][filled] = np.maximum.reduceat(odds[rows], start[:-1][filled])
        weights.append(best)
    best = np.maximum(*weights)
    scores = np.concatenate([best[inputs.windows(np.arange(i, min(i + BLOCK, len(inputs.begin))))[0]].max(axis=1) for i in range(0, len(inputs.begin), BLOCK)] or [np.zeros(0)])
    return scores, marks


def _top(scores: np.ndarray, inputs: Inputs, texts: np.ndarray, k: int) -> np.ndarray:
    """The k best windows of each given text."""
    out = []
    for t in texts:
        a, b = inputs.window_start[t], inputs.window_start[t + 1]
        out.append(a + np.argsort(-scores[a:b], kind="stable")[:k])
    return np.concatenate(out) if out else np.zeros(0, dtype=np.int64)


def train(texts: list[str], labels: list[int], rounds: int = 4, batch: int = 192, steps: int = 440, seed: int = 5) -> Network:
    """Fit on whole texts with labels 0 and 1. Without both labels the network scores by its start alone."""
    net, rng = Network(), np.random.default_rng(seed)
    column = pa.array(texts, type=pa.string())
    inputs = Inputs(*K.text_buffer(column))
    toxic = np.asarray(labels, dtype=np.int64)
    some = np.diff(inputs.window_start) > 0
    pos, neg = np.flatnonzero(some & (toxic == 1)), np.flatnonzero(some & (toxic == 0))
    if not len(pos) or not len(neg):
        net.shift = -10.0
        return net
    scores, (start, gram_start) = _first_choice(inputs, toxic)
    known = {"word": ~np.isnan(start), "char": ~np.isnan(gram_start)}
    net.p["word"][:, 0] = START * start
    for name, has in known.items():  # a feature of few texts is left out, or the network would learn these texts by heart
        net.p[name][~has] = 0
    all_neg = np.concatenate([np.arange(inputs.window_start[t], inputs.window_start[t + 1]) for t in neg])
    moments = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in net.p.items() if k not in ("word", "char")}
    squares = {k: np.full(len(net.p[k]), 1e-6) for k in ("word", "char")}
    step = 0
    for _ in range(rounds):
        chosen = _top(scores, inputs, pos, 2)
        hard = _top(scores, inputs, neg, 2)
        for _ in range(-(-steps // rounds)):
            k = batch // 2
            pick = np.concatenate([rng.choice(chosen, k), rng.choice(hard, k // 2), rng.choice(all_neg, k - k // 2)])
            label = np.concatenate([np.ones(k), np.zeros(k)])
            dense, sparse = net.gradients(inputs, pick, label)
            step += 1
            for name, g in dense.items():
                m, v = moments[name]
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                net.p[name] -= (0.01 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
            for name, (rows, g) in sparse.items():
                rows, g = rows[known[name][rows]], g[known[name][rows]]
                used, back = np.unique(rows, return_inverse=True)
                total = np.zeros((len(used), g.shape[1]))
                np.add.at(total, back, g)
                squares[name][used] += (total * total).mean(axis=1)
                net.p[name][used] -= (0.1 * total / np.sqrt(squares[name][used])[:, None]).astype(np.float32)
        scores = net.logits(inputs)
    # The logit that parts the learning texts best becomes THRESHOLD.
    best = np.asarray([scores[inputs.window_start[t] : inputs.window_start[t + 1]].max() for t in np.concatenate([pos, neg])])
    truth = np.concatenate([np.ones(len(pos)), np.zeros(len(neg))])
    order = np.argsort(-best, kind="stable")
    hits = np.cumsum(truth[order])
    f1 = 2 * hits / (np.arange(len(order)) + 1 + len(pos))
    k = int(f1.argmax())
    cut = (best[order[k]] + best[order[min(k + 1, len(order) - 1)]]) / 2
    net.shift = float(np.log(THRESHOLD / (1 - THRESHOLD)) - cut)
    return net


def learn(docs: DataFrame, labels: DataFrame, limit: int = MAX_LEARN) -> Network:
    """Fit on labelled rows outside the held-out fold: about ``limit`` of each label at most, found from ids alone.

    Repeated labels of an id count once, toxic if any is; rows without text and texts of more than
    MAX_LEARN_CHARS characters are left out of the sample.
    """
    known = labels.filter(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    chosen = learning_sample(known, "doc_id", "toxic", limit)
    rows = docs.select("doc_id", "text").filter(F.length("text") <= MAX_LEARN_CHARS).join(small_side(chosen), "doc_id")
    return fit_in_task(rows, "text", "toxic", ["doc_id", "text"], train)


def score(docs: DataFrame, net: Network, key: str = "doc_id") -> DataFrame:
    """``key, score`` per row: the score of the most toxic window; 0 for null texts and texts without words."""
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            data, off = K.text_buffer(batch.column("text"))
            found = np.zeros(batch.num_rows)
            for i, j in K.slices(off):
                inputs = Inputs(data[off[i] : off[j]], off[i : j + 1] - off[i])
                filled = np.diff(inputs.window_start) > 0
                if filled.any():
                    best = np.maximum.reduceat(model.logits(inputs), inputs.window_start[:-1][filled])
                    found[i:j][filled] = _sigmoid(best.astype(np.float64) + model.shift)
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(found)], names=[key, "score"])

    kind = dict(docs.dtypes)[key]
    return docs.select(F.col(key).alias("key"), whole_text().alias("text")).mapInArrow(run, f"`{key}` {kind}, score double")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The toxicity of every document.

    Null texts and those without a word score 0; texts of any length are read whole; repeated rows repeat; an empty table gives
    an empty result, and without labels of both kinds all scores are near 0; columns other than doc_id and text are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    net = learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic"))
    out = score(docs, net)
    return out.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
