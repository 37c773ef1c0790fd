"""Soft-membership mixing: document rates that bring expected domain token totals to targets.

A classifier fitted on the labelled table gives each document a posterior over domains (pairs of
quality and toxicity). With t the document's tokens and p its posterior, the rates r >= 0 minimise

    1/2 (A r - b)' M (A r - b) + REGULAR / 2 * sum w (r - 1)^2,   A_kd = t_d p_dk,  b_k = target_k * sum t,

by projected gradient steps, where b is raised or lowered by the gaps of earlier rounds (a multiplier), so that the
pull towards rate 1 decides among the rates that meet the targets and does not keep totals from them. M, the inverse of A A', makes the few domains' directions alike, so
that a fixed step converges in a few rounds. One round is one pass over the narrow table of tokens
and posteriors that returns one number per domain; rates are never stored on the way, since each
row replays its own steps from the domain vectors of the rounds before.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.llm import kernels as K
from corpus_audit.llm.common import fit_in_task, held_out, learning_sample, materialize, small_side, whole_text

BUCKETS = 1 << 16
#: Learning rows per domain, and the longest text among them.
MAX_LEARN, MAX_LEARN_CHARS = 1000, 60_000
#: Share of tokens that each domain shall have; domains not named share what is left by their present size.
TARGETS = {"q1t0": 0.90}
REGULAR, STEP, MULTIPLIER, ROUNDS = 0.02, 0.9, 0.3, 60
#: The largest gap between a domain's share and its target at which the rounds end, and rounds without a smaller one.
TOLERANCE, PATIENCE = 1e-3, 20


class Classifier:
    """Softmax regression over hashed words, weighted by 1 / sqrt(words of the text)."""

    def __init__(self, domains: list[str], weights: np.ndarray, bias: np.ndarray):
        self.domains, self.weights, self.bias = domains, weights, bias

    @staticmethod
    def rows(hashes: np.ndarray) -> np.ndarray:
        return (hashes >> np.uint64(24)).astype(np.int64) % BUCKETS

    def posteriors(self, words: K.Words) -> np.ndarray:
        counts = np.diff(words.first)
        total = np.zeros((len(counts), len(self.domains)))
        if len(words.hash):
            sums = np.concatenate([np.zeros((1, total.shape[1])), np.cumsum(self.weights[self.rows(words.hash)], axis=0, dtype=np.float64)])
            total = sums[words.first[1:]] - sums[words.first[:-1]]
        return _softmax(total / np.sqrt(np.maximum(1, counts))[:, None] + self.bias)


def _softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def fit(texts: list[str], domains: list[str], shares: dict[str, float], epochs: int = 12, rate: float = 0.5, batch: int = 64, seed: int = 7) -> Classifier:
    """Fit on texts and their domains; the bias is moved to the given prior shares, as the sample is balanced."""
    names = sorted(shares)
    words = K.Words.whole(*K.text_buffer(pa.array(texts, type=pa.string())), folded=True)
    rows, counts = Classifier.rows(words.hash), np.diff(words.first)
    label = np.asarray([names.index(d) for d in domains], dtype=np.int64)
    weights, bias = np.zeros((BUCKETS, len(names)), dtype=np.float32), np.zeros(len(names))
    squares, rng = np.full(BUCKETS, 1e-3), np.random.default_rng(seed)
    for _ in range(epochs):
        order = rng.permutation(len(texts))
        for i in range(0, len(order), batch):
            pick = order[i : i + batch]
            count = counts[pick]
            begin = np.cumsum(count) - count
            flat = rows[np.repeat(words.first[pick] - begin, count) + np.arange(count.sum())]
            owner = np.repeat(np.arange(len(pick)), count)
            scale = 1 / np.sqrt(np.maximum(1, count))
            logit = np.zeros((len(pick), len(names)))
            np.add.at(logit, owner, weights[flat])
            error = _softmax(logit * scale[:, None] + bias)
            error[np.arange(len(pick)), label[pick]] -= 1
            used, back = np.unique(flat, return_inverse=True)
            grad = np.zeros((len(used), len(names)))
            np.add.at(grad, back, (error * scale[:, None])[owner])
            squares[used] += (grad**2).mean(axis=1)
            weights[used] -= (rate * grad / np.sqrt(squares[used])[:, None]).astype(np.float32)
            bias -= 0.05 * error.mean(axis=0)
    seen = np.bincount(label, minlength=len(names)) / max(1, len(label))
    prior = np.asarray([shares[d] for d in names])
    return Classifier(names, weights, bias + np.log(np.maximum(prior, 1e-6)) - np.log(np.maximum(seen, 1e-6)))


def learn(docs: DataFrame, labels: DataFrame, limit: int = MAX_LEARN) -> Classifier:
    """Fit on labelled rows outside the held-out fold. Repeated labels of an id count once (the lowest).

    With no usable label there is one domain, ``all``.
    """
    named = F.concat(F.lit("q"), F.col("quality").cast("string"), F.lit("t"), F.col("toxic").cast("string"))
    known = labels.filter(F.col("doc_id").isNotNull() & ~held_out()).select("doc_id", named.alias("domain")).filter(F.col("domain").isNotNull()).groupBy("doc_id").agg(F.min("domain").alias("domain"))
    shares = dict(known.groupBy("domain").count().collect())  # one row per domain
    chosen = learning_sample(known, "doc_id", "domain", limit)
    rows = docs.select("doc_id", "text").filter(F.length("text") <= MAX_LEARN_CHARS).join(small_side(chosen), "doc_id")
    if not shares:
        return Classifier(["all"], np.zeros((BUCKETS, 1), dtype=np.float32), np.zeros(1))
    total = sum(shares.values())
    share_of = {d: n / total for d, n in shares.items()}
    return fit_in_task(rows, "text", "domain", ["doc_id", "text"], lambda texts, domains: fit(texts, domains, share_of))


def memberships(docs: DataFrame, model: Classifier) -> DataFrame:
    """``doc_id, u, n_tokens, p``: words (null text: none), a number in [0, 1) from the row, and posteriors."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = K.text_buffer(batch.column("text"))
            tokens, p = np.zeros(batch.num_rows, dtype=np.int64), np.zeros((batch.num_rows, len(shared.value.domains)))
            for i, j in K.slices(off):
                words = K.Words(data[off[i] : off[j]], off[i : j + 1] - off[i], folded=True)
                tokens[i:j], p[i:j] = np.diff(words.first), shared.value.posteriors(words)
            flat = pa.ListArray.from_arrays(np.arange(len(p) + 1, dtype=np.int32) * p.shape[1], pa.array(p.reshape(-1)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("u"), pa.array(tokens), flat], names=["doc_id", "u", "n_tokens", "p"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), _uniform().alias("u"), whole_text().alias("text")).mapInArrow(run, "doc_id long, u double, n_tokens long, p array<double>")


def _uniform() -> F.Column:
    """A number in [0, 1) that depends on the id and the text alone."""
    return F.pmod(F.xxhash64("doc_id", whole_text(), F.lit(41)), F.lit(1 << 30)) / (1 << 30)


def _replay(load: np.ndarray, steps: list[np.ndarray]) -> np.ndarray:
    """A block's rates after the given steps: r <- max(0, r - a.v + shrink (1 - r)) from r = 1."""
    rate = np.ones(len(load))
    for v in steps:
        rate = np.maximum(0.0, rate - STEP * (load @ v + REGULAR * (rate - 1)))
    return rate


def _load(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    p = batch.column("p").flatten().to_numpy().reshape(batch.num_rows, -1)
    return p, batch.column("n_tokens").to_numpy().astype(float)


def _pass(members: DataFrame, steps: list[np.ndarray], domains: int) -> np.ndarray:
    """Expected token totals per domain under the rates after ``steps``: one row per task, summed by Spark."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(domains)
        for batch in batches:
            p, tokens = _load(batch)
            total += (p * (_replay(p, steps) * tokens)[:, None]).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array([total[k]]) for k in range(domains)], names=[f"s{k}" for k in range(domains)])

    sums = members.mapInArrow(run, ", ".join(f"s{k} double" for k in range(domains)))
    return np.asarray(sums.agg(*(F.sum(f"s{k}") for k in range(domains))).first(), dtype=float)


def solve(members: DataFrame, domains: list[str], targets: dict[str, float] | None = None) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """The steps of the projected gradient, and the target and reached token totals by domain (those of these steps).

    Rows are weighted by their tokens (w = t), so a step moves a rate by its posterior times the
    domain vector: long and short documents with equal posteriors get equal rates.
    """
    k = len(domains)

    def gram(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(k * k)
        for batch in batches:
            p, tokens = _load(batch)
            total += ((p * tokens[:, None]).T @ p).reshape(-1)
        yield pa.RecordBatch.from_arrays([pa.array([x]) for x in total], names=[f"g{i}" for i in range(k * k)])

    sums = members.mapInArrow(gram, ", ".join(f"g{i} double" for i in range(k * k)))
    second = np.asarray(sums.agg(*(F.sum(f"g{i}") for i in range(k * k))).first(), dtype=object)
    second = np.asarray([x or 0.0 for x in second], dtype=float).reshape(k, k)
    now = second.sum(axis=1)  # posteriors sum to one
    total = now.sum()
    if not total:
        return [], np.zeros(k), np.zeros(k)
    wanted = {d: s for d, s in (TARGETS if targets is None else targets).items() if d in domains}
    left, rest = max(0.0, 1 - sum(wanted.values())), sum(n for d, n in zip(domains, now, strict=True) if d not in wanted)
    goal = np.asarray([wanted[d] if d in wanted else left * n / max(rest, 1e-12) for d, n in zip(domains, now, strict=True)])
    goal = goal / goal.sum() * total
    inverse = np.linalg.pinv(second + 1e-9 * total * np.eye(k))
    steps: list[np.ndarray] = []
    debt, best = np.zeros(k), (np.inf, [], now)
    for _ in range(ROUNDS):
        reached = _pass(members, steps, k)
        gap = reached - goal
        if np.abs(gap).max() < best[0]:
            best = (float(np.abs(gap).max()), list(steps), reached)
        # Targets that no rates can meet end the rounds too; then the nearest totals count.
        if best[0] < TOLERANCE * total or len(steps) - len(best[1]) >= PATIENCE:
            break
        steps.append(inverse @ (gap + debt))
        debt += MULTIPLIER * gap
    return best[1], goal, best[2]


def mixed(spark: SparkSession, docs: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None) -> tuple[DataFrame, list[str], dict[str, tuple[float, float]]]:
    """``doc_id, u, n_tokens, p, rate, copies`` per row of docs, the domains of ``p``, and the goal and the reached share of tokens of each.

    ``copies`` is the rate rounded down or up by the row's own number u, so its mean is the rate.
    Texts without words have the prior as posterior. An empty table gives an empty result.
    """
    model = learn(docs, labels)
    members = materialize(memberships(docs, model), "members")
    steps, goal, reached = solve(members, model.domains, targets)
    shares = {d: (goal[k] / max(1e-9, goal.sum()), reached[k] / max(1e-9, reached.sum())) for k, d in enumerate(model.domains)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rate = _replay(_load(batch)[0], steps)
            copies = np.floor(rate + batch.column("u").to_numpy()).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(rate), pa.array(copies)], names=[*batch.schema.names, "rate", "copies"])

    return members.mapInArrow(run, "doc_id long, u double, n_tokens long, p array<double>, rate double, copies long"), model.domains, shares


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens, posteriors, rate and copies of every document; ``goal_`` and ``reached_`` are the domains' shares of all expected tokens.

    Null and empty texts have no tokens and the prior as posterior; texts of any length are read whole; repeated rows
    get equal rates and copies; an empty table gives an empty result, and one without labels a single domain; columns other
    than doc_id and text are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out, domains, shares = mixed(spark, docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    balance = [F.lit(round(x, 6)).alias(f"{name}_{d}") for d in domains for name, x in zip(("goal", "reached"), shares[d], strict=True)]
    return out.select("doc_id", "n_tokens", *(F.get("p", F.lit(k)).alias(f"p_{d}") for k, d in enumerate(domains)), "rate", "copies", *balance)


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its copies say, which may be never.

    Null and empty texts have the prior as posterior; repeated rows get equal copies; an empty table stays empty; other columns are
    carried along untouched.
    """
    model = learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    members = materialize(memberships(docs, model), "members")
    steps, _, _ = solve(members, model.domains)
    shared = spark.sparkContext.broadcast(model)
    columns = docs.columns
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = K.text_buffer(batch.column("text"))
            copies = np.zeros(batch.num_rows, dtype=np.int64)
            for i, j in K.slices(off):
                words = K.Words(data[off[i] : off[j]], off[i : j + 1] - off[i], folded=True)
                copies[i:j] = np.floor(_replay(shared.value.posteriors(words), steps) + batch.column("__u").to_numpy()[i:j])
            at = np.repeat(np.arange(batch.num_rows), copies)
            yield batch.select(columns).take(pa.array(at))

    return docs.select(*columns, _uniform().alias("__u")).mapInArrow(run, schema)
