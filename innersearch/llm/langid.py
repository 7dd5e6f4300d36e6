"""Language identification with hyperdimensional profiles.

Each letter gets a random vector of +1 and -1; an n-gram's vector binds (multiplies) the vectors of its
letters, each permuted (rotated) by its place; a text's vector bundles (sums) those of its n-grams; a
language's prototype bundles the texts of that language, each scaled to unit length; a text gets the language
of the prototype with the greatest cosine.

Bundling and the inner product are linear, so the prototypes are kept twice: as vectors, and as the
table <n-gram vector, prototype> of every n-gram, with which a text's inner products are sums of table
rows - the same cosine without building the text's vector.  Text lengths use the near-orthogonality of the
bound vectors: |sum c_g v_g|^2 = D * sum c_g^2 up to noise of order 1/sqrt(D) (`exact_vector` gives the exact one).

Symbols are 64: space, a-z, and 37 classes of all other letters by code point; so there are 64^3 3-grams,
whatever the input, and the training statistic has at most languages * 64^3 rows.

Defined cases: null text and text without a letter give `und` with score 0; a language value is any non-null
string seen in training; ties go to the first in code point order; without training rows all is `und`;
repeated rows are rows of their own; an empty table gives no rows; other columns are ignored."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from innersearch.llm.common import annotate, bound_batches, fresh, tidy

SYMBOLS = 64
DIM = 1024
MAX_LANGUAGES = 1_000
#: Texts from this length on have enough 3-grams for a cosine well above that of a language not learned.
LONG_CHARS = 200


def symbol_table() -> np.ndarray:
    """Symbol of each code point: 0 for all but letters, 1-26 a-z in either case, 27-63 other letters."""
    import sys

    table = np.zeros(sys.maxunicode + 1, np.uint8)
    for c in range(sys.maxunicode + 1):
        ch = chr(c)
        if ch.isalpha():
            low = ch.lower()
            low = ord(low[0])
            table[c] = low - 96 if 97 <= low <= 122 else 27 + (low * 7919 % 65521) % 37
    return table


_TABLE: list[np.ndarray] = []


def symbols_of(text: str) -> np.ndarray:
    """Symbols of a text between two spaces, runs of non-letters as one space."""
    if not _TABLE:
        _TABLE.append(symbol_table())
    s = _TABLE[0][np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")]
    s = np.concatenate([[0], s, [0]]).astype(np.int32)
    return s[np.concatenate([[True], (s[1:] != 0) | (s[:-1] != 0)])]


def grams_of(text: str) -> np.ndarray:
    s = symbols_of(text)
    return (s[:-2] * SYMBOLS + s[1:-1]) * SYMBOLS + s[2:] if len(s) > 2 else np.zeros(0, np.int32)


def gram_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    return np.unique(grams_of(text), return_counts=True)


def letter_vectors(dim: int = DIM, seed: int = 11) -> np.ndarray:
    return np.random.default_rng(seed).choice(np.array([-1, 1], np.int8), (SYMBOLS, dim))


def gram_vectors(grams: np.ndarray, letters: np.ndarray) -> np.ndarray:
    """Bound vectors: the first letter rotated twice, the second once."""
    a, b, c = grams // SYMBOLS**2, grams // SYMBOLS % SYMBOLS, grams % SYMBOLS
    return np.roll(letters, 2, 1)[a] * np.roll(letters, 1, 1)[b] * letters[c]


def exact_vector(text: str, letters: np.ndarray) -> np.ndarray:
    g, n = gram_counts(text)
    return n.astype(np.float64) @ gram_vectors(g, letters).astype(np.float64)


class Profiles:
    """Language names, prototype vectors and the inner product of every 3-gram with each."""

    def __init__(self, names: list[str], stats: dict[str, tuple[np.ndarray, np.ndarray]], dim: int = DIM):
        self.names = sorted(names)
        self.letters = letter_vectors(dim)
        self.vectors = np.zeros((len(self.names), dim))
        for i, name in enumerate(self.names):
            grams, weights = stats[name]
            for at in range(0, len(grams), 8192):
                self.vectors[i] += weights[at : at + 8192] @ gram_vectors(grams[at : at + 8192], self.letters).astype(np.float32)
        unit = self.vectors / np.maximum(np.linalg.norm(self.vectors, axis=1, keepdims=True), 1e-12)
        self.table = np.zeros((SYMBOLS**3, len(self.names)), np.float32)
        every = np.arange(SYMBOLS**3, dtype=np.int32)
        for at in range(0, len(every), 8192):
            self.table[at : at + 8192] = gram_vectors(every[at : at + 8192], self.letters).astype(np.float32) @ unit.T.astype(np.float32)
        self.dim = dim

    def predict(self, texts: list[str]) -> tuple[list[str], list[float]]:
        names, scores = [], []
        for t in texts:
            grams = grams_of(t)
            if not len(grams) or not self.names:
                names.append("und")
                scores.append(0.0)
                continue
            length = np.sqrt(self.dim * _square_sum(grams))
            cos = self.table[grams].sum(0, dtype=np.float64) / length
            best = int(cos.argmax())
            names.append(self.names[best])
            scores.append(float(min(1.0, max(0.0, cos[best]))))
        return names, scores


def _square_sum(grams: np.ndarray) -> float:
    s = np.sort(grams)
    edge = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1], [True]]))
    n = np.diff(edge).astype(np.float64)
    return float(n @ n)


def train(docs: DataFrame) -> Profiles:
    """Profiles of all rows of docs(text, lang) with non-null lang.

    Partial sums over 3-grams are made in the tasks, so at most tasks * languages * 64^3 small rows are shuffled
    and languages * 64^3 reach the driver."""
    bound_batches(docs.sparkSession)
    rows = docs.where("lang is not null and text is not null").select("text", "lang")

    def sums(batches):
        import pyarrow as pa

        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for text, lang in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                g, n = gram_counts(text.as_py())
                if len(g):
                    if lang not in total:
                        if len(total) >= MAX_LANGUAGES:
                            raise ValueError(f"more than {MAX_LANGUAGES} languages")
                        total[lang] = np.zeros(SYMBOLS**3, np.float32)
                    total[lang][g] += n / np.sqrt(float(n @ n))
        for lang, w in total.items():
            at = np.flatnonzero(w).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at), pa.array(w[at].astype(np.float64))], names=["lang", "gram", "weight"])

    stats = rows.mapInArrow(tidy(sums), "lang string, gram int, weight double").groupBy("lang", "gram").agg(F.sum("weight").alias("weight")).toPandas()
    return Profiles(sorted(stats["lang"].unique()), {k: (v["gram"].to_numpy(np.int32), v["weight"].to_numpy(np.float64)) for k, v in stats.groupby("lang")})


def identify(docs: DataFrame, profiles: Profiles, keep: list[str], pred: str = "__lang_pred", score: str = "__lang_score") -> DataFrame:
    """Columns `keep` with the predicted language and its cosine."""
    shared = docs.sparkSession.sparkContext.broadcast(profiles)

    def make():
        model = shared.value

        def work(texts):
            return list(model.predict([t.decode() if t else "" for t in texts]))

        return work

    return annotate(docs, keep, f"`{pred}` string, `{score}` double", make)


def held_out() -> Column:
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) == 1


def language_digest(docs: DataFrame) -> DataFrame:
    """Learns from the rows that are not held out; doc_id, held_out, lang_pred, score of all rows."""
    profiles = train(docs.where(~F.coalesce(held_out(), F.lit(False))))
    found = identify(docs, profiles, ["doc_id"])
    return found.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), F.col("__lang_pred").alias("lang_pred"), F.col("__lang_score").alias("score"))


def keep_languages(docs: DataFrame, profiles: Profiles, allowed: list[str] | None = None, least: float = 0.2, least_long: float | None = None) -> DataFrame:
    """docs whose predicted language is allowed (None: any learned one) with a cosine of at least `least`, or of
    `least_long` for texts of LONG_CHARS characters or more (None: `least`)."""
    pred, score = fresh(docs.columns, "lang_pred"), fresh(docs.columns, "lang_score")
    found = identify(docs, profiles, docs.columns, pred, score)
    bar = F.lit(least) if least_long is None else F.when(F.length("text") >= LONG_CHARS, least_long).otherwise(least)
    ok = (F.col(pred) != "und") & (F.col(score) >= bar)
    if allowed is not None:
        ok &= F.col(pred).isin(allowed)
    return found.where(ok).select(*[F.col(f"`{c}`") for c in docs.columns])
