"""Language identification with hyperdimensional profiles.

Each letter has a random vector of +1 and -1. An n-gram of letters is bound by multiplying the
letters' vectors, each rotated by its place; a text's vector is the sum (bundle) of its n-grams.
A language's prototype is the bundle of its learning texts, and a text takes the language whose
prototype has the highest cosine with it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.llm.common import fit_in_task, held_out, learning_sample, small_side, whole_text
from corpus_audit.llm.kernels import slices, text_buffer

DIMENSIONS, N = 512, 3
#: Letters whose n-grams are bound beforehand; rarer ones have vectors as well, bound as they occur. Number 0 is the gap between words.
ALPHABET = 48
#: Learning rows per language, and the longest text among them: together they bound the sample that is fitted in one task.
MAX_LEARN, MAX_LEARN_CHARS = 1500, 60_000
UNKNOWN = "und"
#: N-grams whose vectors are summed at a time, and bits of a letter's number.
BLOCK, _BITS = 4096, 21


def _letter_numbers(letters: list[int]) -> np.ndarray:
    """Letter number of each code point: 0 no letter, 1.. the given letters, ALPHABET + code point any other letter; upper case as lower."""
    table = np.zeros(0x110000, dtype=np.int32)
    given = {c: i + 1 for i, c in enumerate(letters)}
    for c in range(0x110000):
        x = chr(c)
        if x.isalpha():
            low = x.lower()
            own = ord(low) if len(low) == 1 else c
            table[c] = given.get(own, ALPHABET + own)
    return table


def _grams(text: np.ndarray, table: np.ndarray) -> np.ndarray:
    """The n-grams of one text's code points as rows of letter numbers; gaps between words count as one letter."""
    ids = table[text]
    gap = ids == 0
    keep = np.ones(len(ids), dtype=bool)
    keep[1:] = ~(gap[1:] & gap[:-1])
    ids = np.concatenate([[0], ids[keep], [0]]).astype(np.int64)
    return np.lib.stride_tricks.sliding_window_view(ids, N) if len(ids) >= N else np.zeros((0, N), dtype=np.int64)


class Profiles:
    """Letter vectors, n-gram vectors and language prototypes, from texts and their languages."""

    def __init__(self, texts: list[str], langs: list[str], seed: int = 11):
        seen: dict[str, int] = {}
        for t in texts:
            for c in t.lower():
                seen[c] = seen.get(c, 0) + 1
        common = sorted((c for c in seen if c.isalpha()), key=lambda c: (-seen[c], c))[: ALPHABET - 2]
        self.letters, self.seed, self.langs = [ord(c) for c in common], seed, sorted(set(langs))
        self._open()
        sums = np.zeros((len(self.langs), DIMENSIONS))
        for t, lang in zip(texts, langs, strict=True):
            vector, _ = self.bundle(np.frombuffer(t.encode("utf-32-le", "surrogatepass"), dtype=np.uint32))
            sums[self.langs.index(lang)] += vector
        norms = np.linalg.norm(sums, axis=1, keepdims=True)
        self.prototypes = (sums / np.where(norms > 0, norms, 1)).astype(np.float32)

    def _open(self) -> None:
        self.table = _letter_numbers(self.letters)
        vectors = np.random.default_rng(self.seed).choice(np.array([-1, 1], dtype=np.int8), (ALPHABET, DIMENSIONS))
        self.vectors = dict(enumerate(vectors))
        grams = vectors
        for _ in range(1, N):
            # All earlier letters turn by one place more, then the next letter is bound.
            grams = (np.roll(grams, 1, axis=-1)[..., None, :] * vectors).reshape(-1, DIMENSIONS)
        self.grams = grams

    def _vector(self, number: int) -> np.ndarray:
        """A letter's vector; that of a rare one is drawn by its code point."""
        if number not in self.vectors:
            if len(self.vectors) > 4 * BLOCK:
                self.vectors = {k: v for k, v in self.vectors.items() if k < ALPHABET}
            self.vectors[number] = np.random.default_rng([self.seed, number]).choice(np.array([-1, 1], dtype=np.int8), DIMENSIONS)
        return self.vectors[number]

    def _bound(self, rows: np.ndarray) -> np.ndarray:
        """The vectors of n-grams with rare letters."""
        out = np.ones((len(rows), DIMENSIONS), dtype=np.int8)
        for k in range(N):
            out *= np.stack([np.roll(self._vector(x), N - 1 - k) for x in rows[:, k].tolist()])
        return out

    def __getstate__(self) -> dict:
        return {k: v for k, v in vars(self).items() if k not in ("table", "grams", "vectors")}

    def __setstate__(self, state: dict) -> None:
        vars(self).update(state)
        self._open()

    def bundle(self, code_points: np.ndarray) -> tuple[np.ndarray, bool]:
        """A text's vector, and whether it has a letter."""
        grams = _grams(code_points, self.table)
        plain = (grams < ALPHABET).all(axis=1)
        power = ALPHABET ** np.arange(N - 1, -1, -1)
        counts = np.bincount(grams[plain] @ power, minlength=1)
        counts[0] = 0  # nothing but gaps
        at = np.flatnonzero(counts)
        total = np.zeros(DIMENSIONS, dtype=np.float32)
        for i in range(0, len(at), BLOCK):
            total += counts[at[i : i + BLOCK]].astype(np.float32) @ self.grams[at[i : i + BLOCK]].astype(np.float32)
        if not plain.all():
            rare, times = np.unique(grams[~plain] @ (1 << _BITS * np.arange(N - 1, -1, -1)), return_counts=True)
            rows = np.stack([rare >> _BITS * k & (1 << _BITS) - 1 for k in range(N - 1, -1, -1)], axis=1)
            for i in range(0, len(rows), BLOCK):
                total += times[i : i + BLOCK].astype(np.float32) @ self._bound(rows[i : i + BLOCK]).astype(np.float32)
        return total, len(at) > 0 or not plain.all()

    def predict(self, code_points: np.ndarray) -> tuple[str, float]:
        vector, any_letter = self.bundle(code_points)
        norm = float(np.linalg.norm(vector))
        if not any_letter or not self.langs:
            return UNKNOWN, 0.0
        cosines = self.prototypes @ vector / max(norm, 1e-9)
        best = int(np.argmax(cosines))
        return self.langs[best], float(min(1.0, max(0.0, cosines[best])))


def learn(docs: DataFrame, text: str = "text", label: str = "lang", key: str = "doc_id", limit: int = MAX_LEARN) -> Profiles:
    """Prototypes from rows outside the held-out fold with a language: about ``limit`` rows of each at most.

    The rows are found from ids and labels alone; texts of more than MAX_LEARN_CHARS are left out of the sample.
    """
    fold = docs.filter(~held_out(key) & F.col(label).isNotNull() & F.col(text).isNotNull())
    chosen = learning_sample(fold, key, label, limit).select(key).distinct()
    rows = fold.filter(F.length(text) <= MAX_LEARN_CHARS).join(small_side(chosen), key, "left_semi")
    return fit_in_task(rows.select(key, text, label), text, label, [key, text], Profiles)


def identify(docs: DataFrame, profiles: Profiles, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``key, lang_pred, score`` per row; a null text or one without letters is ``und`` with score 0."""
    shared = docs.sparkSession.sparkContext.broadcast(profiles)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            data, off = text_buffer(batch.column("text"))
            found = []
            for i, j in slices(off):
                raw = data[off[i] : off[j]]
                # One decoding for the slice; a row's code points begin where its bytes do.
                points = np.frombuffer(raw.tobytes().decode("utf-8", "replace").encode("utf-32-le"), dtype=np.uint32)
                starts = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])[off[i : j + 1] - off[i]]
                found += [model.predict(points[starts[k] : starts[k + 1]]) for k in range(j - i)]
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array([x[0] for x in found], type=pa.string()), pa.array([x[1] for x in found], type=pa.float64())], names=[key, "lang_pred", "score"])

    kind = dict(docs.dtypes)[key]
    return docs.select(F.col(key).alias("key"), whole_text(text).alias("text")).mapInArrow(run, f"`{key}` {kind}, lang_pred string, score double")


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document.

    Null texts and those without a letter are ``und`` with score 0; texts of any length are read whole; ties go to the language
    that sorts first; repeated rows repeat; an empty table gives an empty result, and one without languages to learn
    gives ``und``; columns other than doc_id, text and lang are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    out = identify(docs, learn(docs))
    return out.select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
