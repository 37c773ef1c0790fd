"""Packing token pieces into fixed-size sequences by a configuration linear program.

Texts become token pieces of at most ``CAPACITY``; only their length histogram (at most CAPACITY
numbers) reaches the driver. There the covering program over packing patterns is solved by
multiplicative weights: a knapsack dynamic program prices the patterns, all those near the best price
take a step, and this is repeated until every length is covered. A dual feasible function
bounds the number of sequences from below; patterns that are worth much less than one sequence by
it are left out, the others are rounded down. What that leaves, which depends on the number of
patterns and not of pieces, is priced again in whole steps, and the rest of it is packed best-fit
by counts. Pieces then find their place by the rank that they have among pieces of their length.

Texts of any length are encoded whole; null and empty texts are the single end id, repeated rows are
packed as often as they come, an empty table gives an empty result, and columns other than
doc_id and text are not read.
"""

from __future__ import annotations

import json
import re
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.llm.common import materialize, whole_text

CAPACITY, END_ID = 1024, 2
#: Share of a length's demand that one round covers at most, how fast prices fall with the share covered, and how
#: near to the best price a pattern must be to take a step.
STEP, FALL, NEAR = 0.2, 3.0, 0.02
#: What a pattern may be worth less than one sequence, by the dual bound; two places of a sequence at least.
SLACK = 0.008
#: Passes in whole steps over what rounding leaves.
WHOLE_PASSES = 3
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: White space as the encoder's pattern has it; longer runs are cut off before the pattern sees them.
_SPACES = re.compile("[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]{1000,}")
_encoders: dict = {}


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class Encoder:
    """Byte-level BPE from a tokenizers JSON file (merge rank = id).

    The ids are those that the tokenizers library gives without special tokens added, at about five
    times its speed: added tokens that a text spells out keep their own id.
    """

    def __init__(self, path: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            held = json.load(f)
        # The byte-level alphabet: printable Latin-1 bytes stand for themselves, the others follow from 256 on.
        shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
        hidden = [b for b in range(256) if b not in shown]
        byte_of = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}
        self.added = {x["content"]: x["id"] for x in held["added_tokens"]}
        ranks = {bytes(byte_of[c] for c in word): i for word, i in held["model"]["vocab"].items() if word not in self.added and all(c in byte_of for c in word)}
        self.bpe = tiktoken.Encoding("byte_level", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})
        longest_first = sorted(self.added, key=len, reverse=True)
        self.marks = re.compile("(" + "|".join(map(re.escape, longest_first)) + ")") if longest_first else None

    def ids(self, text: str) -> list[int]:
        if self.marks is None or not self.marks.search(text):
            return self._plain(text)
        out: list[int] = []
        for k, part in enumerate(self.marks.split(text)):  # every second part is an added token
            out += [self.added[part]] if k % 2 else self._plain(part)
        return out

    def _plain(self, text: str) -> list[int]:
        """Ids of a text without added tokens.

        The pattern steps back once per character of white space and gives up on very long runs. A run is one
        word of its own but for its last character, which belongs to the word behind it, so it can be cut off.
        """
        out: list[int] = []
        at = 0
        while run := _SPACES.search(text, at):
            end = run.end() if run.end() == len(text) else run.end() - 1
            out += self.bpe.encode_ordinary(text[at : run.start()])
            out += self.bpe._encode_single_piece(text[run.start() : end])
            at = end
        return out + self.bpe.encode_ordinary(text[at:] if at else text)


def encoder(path: str) -> Encoder:
    """The encoder of a vocabulary file, one per process."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: full ones, the remainder first."""
    if n <= capacity:
        return [(0, n)]
    head = n % capacity
    return ([(0, head)] if head else []) + [(i, capacity) for i in range(head, n, capacity)]


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, local long"


def pieces(docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """The token pieces of ``docs(doc_id, text)``; (part, length, local) identifies each.

    A null text is empty and gives the single end id. Repeated rows give repeated pieces.
    """
    path = vocabulary or default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, seen = encoder(path).ids, TaskContext.get().partitionId(), Counter()
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
                ids = encode(text.as_py())
                ids.append(END_ID)
                raw = np.asarray(ids, dtype="<u4")
                for k, (start, length) in enumerate(cut(len(raw), capacity)):
                    rows.append((doc_id, k, start, length, zlib.crc32(raw[start : start + length].tobytes()), part, seen[length]))
                    seen[length] += 1
            columns = list(zip(*rows, strict=True)) if rows else [()] * 7
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(columns, kinds, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32", "part", "local"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")).mapInArrow(run, _PIECES)


def knapsack(price: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every capacity c the highest total price of lengths that fit, and how it is made.

    ``price[x]`` is that of length x (-inf: not for use). ``made[c]`` is 0 if c is as good as c - 1, c if one
    piece of that length is best, else a capacity a such that the best of a and of c - a together are.
    """
    size = len(price)
    best, made = np.zeros(size), np.zeros(size, dtype=np.int64)
    for c in range(1, size):
        value, how = best[c - 1], 0
        if price[c] > value:
            value, how = price[c], c
        half = c // 2
        if half:
            both = best[1 : half + 1] + best[c - 1 : c - half - 1 : -1]
            a = int(both.argmax())
            if both[a] > value + 1e-12:
                value, how = both[a], a + 1
        best[c], made[c] = value, how
    return best, made


def pieces_of(made: np.ndarray, capacity: int) -> Counter:
    """The multiset of lengths that the knapsack table has for a capacity."""
    out, open_ = Counter(), [capacity]
    while open_:
        c = open_.pop()
        while c and not made[c]:
            c -= 1
        if c:
            a = int(made[c])
            if a == c:
                out[c] += 1
            else:
                open_ += [a, c - a]
    return out


def best_pattern(lengths: np.ndarray, prices: np.ndarray, capacity: int) -> dict[int, int]:
    """The multiset of lengths of total at most ``capacity`` with the highest total price (unbounded knapsack)."""
    price = np.full(capacity + 1, -np.inf)
    price[lengths] = prices
    return dict(pieces_of(knapsack(price)[1], capacity))


def best_fit(demand: dict[int, int], capacity: int) -> Counter:
    """Patterns of a best-fit decreasing packing of a histogram, by counts: equal bins are filled together."""
    room: dict[int, Counter] = {capacity: Counter()}
    for length in sorted((x for x, n in demand.items() if n > 0), reverse=True):
        left = demand[length]
        while left:
            # The tightest bin stays the tightest while it can take another piece, so it is filled at once.
            tight = min((r for r, held in room.items() if r >= length and (held or r == capacity)))
            each = tight // length
            if room[tight]:
                held, bins = room[tight].popitem()
            else:
                held, bins = (), left // each + 1
            full = min(bins, left // each)
            if full:
                room.setdefault(tight - each * length, Counter())[held + (length,) * each] += full
                left -= full * each
            if full < bins and left:
                room.setdefault(tight - left * length, Counter())[held + (length,) * left] += 1
                full, left = full + 1, 0
            if held and full < bins:
                room[tight][held] += bins - full
    return sum(room.values(), Counter())


def dual_values(demand: np.ndarray) -> tuple[np.ndarray, float]:
    """A value of each length such that no pattern is worth more than 1, and the demand's worth: a lower bound of the sequences.

    The best of the family that counts lengths above capacity - e as 1, those below e as 0, and others by their size.
    """
    size = np.arange(len(demand))
    capacity = len(demand) - 1
    found = [size / capacity]
    found += [np.where(size > capacity - e, 1.0, np.where(size < e, 0.0, size / capacity)) for e in range(1, capacity // 2 + 1)]
    worth = [float(x @ demand) for x in found]
    k = int(np.argmax(worth))
    return found[k], worth[k]


def priced_patterns(demand: np.ndarray, rounds: int | None = None, step: float = STEP, whole: bool = False) -> dict[tuple[int, ...], float]:
    """A nearly least cover of the demand (by length, index 0 unused) by patterns, by multiplicative weights.

    A length's weight falls exponentially with the share of it that is covered; its price is the weight times its
    size to the power 1.5, so that among equally full patterns those of long pieces come first and short
    ones are left to fill gaps. Each round prices all capacities by one knapsack program and takes, for each length,
    the best pattern that holds it. Those within NEAR of the best price are used until one of their lengths has gained
    a ``step``-th of its demand in this round, or is covered. A covered length has no price, and none is planned beyond
    its demand. Every round covers a step of some length, so they end; ``rounds`` ends them sooner. With ``whole`` all
    steps are whole numbers of sequences.
    """
    capacity = len(demand) - 1
    size = (np.arange(capacity + 1) / capacity) ** 1.5
    covered = np.where(demand > 0, 0.0, np.inf)
    used: dict[tuple[int, ...], float] = {}
    turn = 0
    while rounds is None or turn < rounds:
        live = np.flatnonzero(covered < 1 - 1e-9)
        if whole:
            live = live[np.rint((1 - covered[live]) * demand[live]) >= 1]
        if not len(live):
            break
        turn += 1
        price = np.full(capacity + 1, -np.inf)
        price[live] = size[live] * np.exp(-FALL * (covered[live] - covered[live].min()))
        best, made = knapsack(price)
        with_it = price[live] + best[capacity - live]
        quota = {int(x): min(max(step * demand[x], 1.0 if whole else 0.0), (1 - covered[x]) * demand[x]) for x in live}
        gained = dict.fromkeys(quota, 0.0)
        moved = False
        for i in np.argsort(-with_it, kind="stable"):
            if with_it[i] < (1 - NEAR) * best[capacity] and moved:
                break
            length = int(live[i])
            if gained[length] >= quota[length] * (1 - 1e-9):
                continue
            pattern = pieces_of(made, capacity - length)
            pattern[length] += 1
            if whole:  # a piece that is not there leaves its place empty
                pattern = Counter({x: min(n, int(quota[x] - gained[x] + 1e-6)) for x, n in pattern.items() if quota[x] - gained[x] > 1 - 1e-6})
                if sum(x * n for x, n in pattern.items()) < (1 - NEAR) * capacity and moved:
                    continue
            amount = min((quota[x] - gained[x]) / n for x, n in pattern.items())
            if whole:
                amount = float(int(amount + 1e-6))
            if amount <= 1e-9:
                continue
            moved = True
            for x, n in pattern.items():
                gained[x] += amount * n
                covered[x] += amount * n / demand[x]
            key = tuple(sorted(pattern.elements(), reverse=True))
            used[key] = used.get(key, 0.0) + amount
        if not moved:
            break
    return used


def _take(plan: Counter, left: Counter, used: dict[tuple[int, ...], float], value: np.ndarray, least: float) -> None:
    """Move whole multiples of the patterns that are worth enough from ``left`` to ``plan``."""
    for pattern, x in sorted(used.items(), key=lambda kv: (-kv[1], kv[0])):
        if value[list(pattern)].sum() >= least:
            count = Counter(pattern)
            n = min([int(x + 1e-9), *(left[y] // k for y, k in count.items())])
            if n > 0:
                plan[pattern] += n
                for y, k in count.items():
                    left[y] -= n * k


def program(histogram: dict[int, int], capacity: int = CAPACITY, rounds: int | None = None, step: float = STEP) -> tuple[Counter, Counter, float]:
    """Patterns with multiplicities, the pieces that they leave, and a lower bound of the sequences that any packing needs."""
    left = Counter({x: n for x, n in histogram.items() if n > 0})
    plan: Counter = Counter()
    full = left.pop(capacity, 0)
    if full:
        plan[(capacity,)] = full
    if not left:
        return plan, left, float(full)

    def array(counts: Counter) -> np.ndarray:
        out = np.zeros(capacity + 1)
        for x, n in counts.items():
            out[x] = n
        return out

    value, bound = dual_values(array(left))
    used = priced_patterns(array(left), rounds, step)
    # Where the bound is loose, no pattern comes near it; then the mean of the program's own patterns is the measure.
    least = min(1.0, bound / max(1e-9, sum(used.values()))) - max(SLACK, 2 / capacity)
    _take(plan, left, used, value, least)
    for _ in range(WHOLE_PASSES):
        if +left:
            _take(plan, left, priced_patterns(array(+left), rounds, step, whole=True), value, least)
    return plan, +left, bound + full


def plan_patterns(histogram: dict[int, int], capacity: int = CAPACITY, rounds: int | None = None, step: float = STEP) -> list[tuple[tuple[int, ...], int]]:
    """(pattern, multiplicity) pairs that hold every piece of the histogram exactly once."""
    plan, left, _ = program(histogram, capacity, rounds, step)
    if left:
        plan = plan + best_fit(dict(left), capacity)
    return sorted(plan.items(), reverse=True)


def placements(plan: list[tuple[tuple[int, ...], int]]) -> np.ndarray:
    """Rows (length, first rank, pieces per sequence, first sequence, offset), sorted by length and rank."""
    rows, rank, sequence = [], Counter(), 0
    for pattern, n in plan:
        offset = 0
        for length, k in sorted(Counter(pattern).items(), reverse=True):
            rows.append((length, rank[length], k, sequence, offset))
            rank[length] += n * k
            offset += length * k
        sequence += n
    return np.asarray(sorted(rows), dtype=np.int64).reshape(-1, 5)


def pack(spark: SparkSession, docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Every piece of ``docs`` with its sequence and its offset there."""
    cutting = materialize(pieces(docs, vocabulary, capacity), "pieces")
    tallies = cutting.groupBy("part", "length").agg(F.count("*").alias("n"))
    histogram = dict(tallies.groupBy("length").agg(F.sum("n").alias("n")).collect())  # at most `capacity` rows
    table = placements(plan_patterns(histogram, capacity))
    before = F.sum("n").over(W.partitionBy("length").orderBy("part")) - F.col("n")
    ranked = cutting.join(tallies.select("part", "length", before.alias("before")), ["part", "length"])

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = (table[:, 0] << 44) | table[:, 1]
        for batch in batches:
            length, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
            at = table[np.searchsorted(keys, (length << 44) | rank, side="right") - 1]
            run, k = rank - at[:, 1], at[:, 2]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(at[:, 3] + run // k), pa.array(at[:, 4] + run % k * length)], names=[*names, "sequence_id", "offset"])

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("before") + F.col("local")).alias("rank")).mapInArrow(place, schema)


def op10_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every token piece of every document with its sequence and offset; see the module for odd rows."""
    return pack(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The packed pieces of all documents that the stages before kept; see the module for odd rows."""
    return pack(spark, docs)
