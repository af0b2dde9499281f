"""Language identification by interpolated Kneser-Ney character models in sorted hash arrays, with calibrated rejection.

Fitting takes a bounded sample of labelled rows (at most `per_language` whole documents of each language, those whose id
hashes lowest) and counts character n-grams of lower-cased letters, other characters being one blank. Each order keeps the
union of all languages' n-grams as one ascending array of 64-bit hashes, with a row of interpolated log probabilities, a
column for each language; a second array holds the back-off weights of contexts. A text is scored over its whole length:
one look-up a character, lower orders only where the n-gram is in no language. The language of lowest length-normalised
cross-entropy wins; its score is a softmax of the cross-entropies whose sharpness is calibrated on sample rows that
counting left out, and rejection thresholds come from the same rows. A symbol has 16 bits, which hold every letter of the
scripts in use (65,533; were a sample to have more, the rarest would count as one). `order` is 4 at most.

`und` and score 0 for a null text or one without a letter, and for all texts where no labelled row exists. Repeated rows
are predicted alike. Ties between languages fall to the first in alphabetical order.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cutstream.llm.common import batched, mix

ORDER = 4
PER_LANGUAGE = 400
#: Symbols are 16 bits wide, so ORDER of them fill a 64-bit code: letters that counting saw are 2 and up, others are OTHER.
BITS = 16
PAD, BLANK, OTHER = 0, 1, (1 << BITS) - 1
UNDETERMINED = "und"


@dataclass
class HashArray:
    """Ascending 64-bit hashes; a bucket index on their high bits finds a key in a few reads."""

    hashes: np.ndarray
    bits: int = 0
    first: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    most: int = 0

    @classmethod
    def of(cls, codes: np.ndarray) -> tuple[HashArray, np.ndarray]:
        h = mix(codes)
        order = np.argsort(h)
        out = cls(h[order])
        out.bits = max(8, int(np.ceil(np.log2(max(1, len(h))))) + 2)
        out.first = np.searchsorted(out.hashes >> np.uint64(64 - out.bits), np.arange((1 << out.bits) + 1, dtype=np.uint64)).astype(np.int32)
        out.most = int(np.diff(out.first).max(initial=0))
        return out, order

    def find(self, codes: np.ndarray) -> np.ndarray:
        """Place of each code, -1 if absent."""
        if not len(self.hashes):
            return np.full(len(codes), -1, np.int64)
        h = mix(codes)
        bucket = (h >> np.uint64(64 - self.bits)).astype(np.int64)
        at = self.first[bucket]
        last = len(self.hashes) - 1
        out = np.where(self.hashes[np.minimum(at, last)] == h, at, -1).astype(np.int64)
        open_ = np.flatnonzero((out < 0) & (self.first[bucket + 1] > at + 1))
        for step in range(1, self.most):
            if not len(open_):
                break
            place = at[open_] + step
            hit = self.hashes[np.minimum(place, last)] == h[open_]
            out[open_[hit]] = place[hit]
            open_ = open_[~hit & (self.first[bucket[open_] + 1] > place + 1)]
        return out


@dataclass
class Model:
    languages: list[str]
    order: int
    alphabet: str = ""
    grams: list[HashArray] = field(default_factory=list)  # by order, from 1
    logp: list[np.ndarray] = field(default_factory=list)
    contexts: list[HashArray] = field(default_factory=list)
    backoff: list[np.ndarray] = field(default_factory=list)
    sharpness: float = 1.0
    least_score: float = 0.0
    most_entropy: float = np.inf
    _symbol: np.ndarray | None = None

    def symbols(self) -> np.ndarray:
        if self._symbol is None:
            letters = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)
            table = np.where(letters, OTHER, BLANK).astype(np.uint16)
            table[[ord(c) for c in self.alphabet]] = np.arange(2, 2 + len(self.alphabet))
            table[0] = PAD
            self._symbol = table
        return self._symbol

    def __getstate__(self):
        return self.__dict__ | {"_symbol": None}

    def read(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Symbols of all texts, PAD between them and before each, blanks collapsed; and the text of each symbol."""
        gap = "\0" * self.order
        clean = [t.lower().replace("\0", " ") for t in texts]
        flat = np.frombuffer((gap + gap.join(clean) + gap).encode("utf-32-le", "surrogatepass"), "<u4")
        begins = np.cumsum([self.order + len(t) for t in clean], dtype=np.int64) - [len(t) for t in clean]
        sym = self.symbols()[flat]
        keep = np.ones(len(sym), bool)
        keep[1:] = (sym[1:] != BLANK) | ((sym[:-1] != BLANK) & (sym[:-1] != PAD))
        return sym[keep], np.concatenate([[0], np.cumsum(keep)])[np.concatenate([begins, [len(sym)]])]

    def cross_entropies(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(texts x languages) nats a character; characters counted (0 where a text has no letter)."""
        sym, begins = self.read(texts)
        has_letter = np.concatenate([[0], np.cumsum(sym > BLANK)])
        letters = has_letter[begins[1:]] - has_letter[begins[:-1]]
        real = np.flatnonzero(sym != PAD)
        codes = _codes(sym, real, self.order)
        score = self._logp(codes, self.order)
        at = np.searchsorted(real, begins)
        n = np.diff(at)
        total, full = np.zeros((len(texts), score.shape[1])), np.flatnonzero(n)
        if len(full):
            total[full] = np.add.reduceat(score, at[:-1][full], axis=0, dtype=np.float64)
        return -total / np.maximum(n, 1)[:, None], np.where(letters > 0, n, 0)

    def _logp(self, codes: np.ndarray, order: int) -> np.ndarray:
        at = self.grams[order - 1].find(codes)
        out = self.logp[order - 1][at]
        miss = np.flatnonzero(at < 0)
        if len(miss):
            if order == 1:
                out[miss] = self.logp[0][-1]  # the row of a symbol that no language has
            else:
                own = codes[miss]
                weight = self.backoff[order - 1][self.contexts[order - 1].find(own >> np.uint64(BITS))]
                out[miss] = weight + self._logp(own & np.uint64((1 << BITS * (order - 1)) - 1), order - 1)
        return out

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score and whether it is rejected, for each text."""
        if not self.languages:
            return [UNDETERMINED] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        h, n = self.cross_entropies(texts)
        best = h.argmin(axis=1)
        low = h[np.arange(len(h)), best]
        p = 1 / np.exp(-self.sharpness * (h - low[:, None])).sum(axis=1)
        none = n == 0
        return [UNDETERMINED if z else self.languages[i] for i, z in zip(best.tolist(), none.tolist(), strict=True)], np.where(none, 0.0, p), none | (p < self.least_score) | (low > self.most_entropy * (1 + 4 / np.sqrt(np.maximum(n, 1))))


def _codes(sym: np.ndarray, at: np.ndarray, order: int) -> np.ndarray:
    """The last `order` symbols up to each place, packed BITS each, the newest lowest."""
    wide = sym.astype(np.uint64)
    code = wide.copy()
    for j in range(1, order):
        code[j:] |= wide[:-j] << np.uint64(BITS * j)
    return code[at]


def _lookup(sorted_codes: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    at = np.minimum(np.searchsorted(sorted_codes, wanted), len(sorted_codes) - 1)
    return np.where(sorted_codes[at] == wanted, at, -1)


def fit(samples: dict[str, list[str]], order: int = ORDER) -> Model:
    """Fit on texts by language; every fifth text calibrates scores and thresholds instead of being counted."""
    if order * BITS > 64:
        raise ValueError("a code holds four symbols at most")
    languages = sorted(samples)
    model = Model(languages, order)
    if not languages:
        return model
    counted = {k: [t for i, t in enumerate(samples[k]) if i % 5 or len(samples[k]) < 5] for k in languages}
    seen: dict[str, int] = {}
    for texts in counted.values():
        for c in "".join(texts).lower():
            seen[c] = seen.get(c, 0) + 1
    model.alphabet = "".join(sorted((c for c in seen if c.isalpha() and c != "\0"), key=lambda c: (-seen[c], c))[: OTHER - 2])

    tables = []  # by language: [(codes, counts)] by order from 1; continuation counts below the highest
    for k in languages:
        sym, _ = model.read(counted[k])
        codes, n = np.unique(_codes(sym, np.flatnonzero(sym != PAD), order), return_counts=True)
        own = [(codes, n)]
        for m in range(order - 1, 0, -1):
            own.insert(0, np.unique(own[0][0] & np.uint64((1 << BITS * m) - 1), return_counts=True))
        tables.append(own)

    width = len(languages)
    below, below_codes = np.zeros((0, 0)), np.zeros(0, np.uint64)
    symbols = len(model.alphabet) + 2  # the blank and all other letters
    for m in range(1, order + 1):
        union = np.unique(np.concatenate([t[m - 1][0] for t in tables]))
        contexts = np.unique(union >> np.uint64(BITS))
        p = np.zeros((len(union), width))
        weight = np.ones((len(contexts), width))
        for j, t in enumerate(tables):
            codes, n = t[m - 1]
            once, twice = (n == 1).sum(), (n == 2).sum()
            d = min(0.95, max(0.1, once / max(1, once + 2 * twice)))
            of, inverse = np.unique(codes >> np.uint64(BITS), return_inverse=True)
            total = np.bincount(inverse, n)
            weight[np.searchsorted(contexts, of), j] = d * np.bincount(inverse) / total
            p[np.searchsorted(union, codes), j] = np.maximum(n - d, 0) / total[inverse]
        w = weight[np.searchsorted(contexts, union >> np.uint64(BITS))]
        lower = np.full((len(union), width), 1 / symbols) if m == 1 else below[_lookup(below_codes, union & np.uint64((1 << BITS * (m - 1)) - 1))]
        p += w * lower
        below, below_codes = p, union
        grams, at = HashArray.of(union)
        places, at_context = HashArray.of(contexts)
        unseen = np.log(weight[:1] / symbols) if m == 1 else np.zeros((1, width))
        model.grams.append(grams)
        model.logp.append(np.concatenate([np.log(p[at]), unseen]).astype(np.float32))
        model.contexts.append(places)
        model.backoff.append(np.concatenate([np.log(weight[at_context]), np.zeros((1, width))]).astype(np.float32))
    _calibrate(model, samples)
    return model


def _calibrate(model: Model, samples: dict[str, list[str]]) -> None:
    held = [(j, t) for j, k in enumerate(model.languages) for t in samples[k][:: 5 if len(samples[k]) >= 5 else 1]]
    h, n = model.cross_entropies([t for _, t in held])
    truth, use = np.array([j for j, _ in held]), n > 0
    if not use.any():
        return
    h, truth = h[use], truth[use]
    gap = h - h.min(axis=1, keepdims=True)

    def loss(s: float) -> float:
        z = -s * gap
        return float(np.mean(np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(z)), truth]))

    model.sharpness = min((2.0**i for i in range(-1, 6)), key=loss)
    best = h.argmin(axis=1)
    right = best == truth
    if right.any():
        score = 1 / np.exp(-model.sharpness * gap).sum(axis=1)
        low = h.min(axis=1)
        # No right calibration row is rejected: a score is too low only where languages tie, and entropy is too high only
        # towards that of random letters, with more room for short texts.
        model.least_score = float(min(1 / len(model.languages) + 0.005, score[right].min()))
        model.most_entropy = float(max(low[right].max() * 1.25, 0.9 * np.log(len(model.alphabet) + 3)))


def sample_texts(docs: DataFrame, per_language: int = PER_LANGUAGE) -> dict[str, list[str]]:
    """At most per_language labelled texts of each language, those whose doc_id hashes lowest."""
    rows = docs.where("lang is not null and text is not null").select("doc_id", "lang", "text")
    counts = rows.groupBy("lang").count()
    hashed = rows.withColumn("u", F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)) / F.lit(float(1 << 40)))
    near = hashed.join(F.broadcast(counts), "lang").where(F.col("u") < F.lit(2.0 * per_language) / F.col("count") + F.lit(20.0) / F.col("count"))
    first = near.withColumn("i", F.row_number().over(Window.partitionBy("lang").orderBy("u", "doc_id", "text"))).where(F.col("i") <= per_language)
    out: dict[str, list[str]] = {}
    for r in sorted(first.select("lang", "i", "text").collect(), key=lambda r: (r.lang, r.i)):
        out.setdefault(r.lang, []).append(r.text)
    return out


def held_out() -> F.Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))


def identify(spark: SparkSession, docs: DataFrame, train: DataFrame, per_language: int = PER_LANGUAGE, order: int = ORDER) -> DataFrame:
    """docs' doc_id, held_out, lang_pred, score and rejected; learns from `train` only."""
    model = spark.sparkContext.broadcast(fit(sample_texts(train, per_language), order))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, texts in batched(batches):
            lang, score, no = model.value.predict(texts)
            yield pa.RecordBatch.from_arrays([rows.column("doc_id"), rows.column("held_out"), pa.array(lang), pa.array(score), pa.array(no)], ["doc_id", "held_out", "lang_pred", "score", "rejected"])

    return docs.select(F.col("doc_id").cast("long"), "text", held_out().alias("held_out")).mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean")


def keep_identified(spark: SparkSession, docs: DataFrame, train: DataFrame) -> DataFrame:
    """docs without those that the model rejects; columns as they were."""
    model = spark.sparkContext.broadcast(fit(sample_texts(train)))
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, texts in batched(batches):
            yield rows.filter(pa.array(~model.value.predict(texts)[2]))

    return docs.select(*names).mapInArrow(run, docs.schema)


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of every document, learned from the training fold."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(spark, docs, docs.where(~held_out()))
