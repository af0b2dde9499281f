"""Benchmark decontamination by latent semantic retrieval, then longest-common-subsequence and answer checks.

Words (lower-cased runs of letters and digits) are hashed to `FEATURES` features and weighed by TF-IDF with document
frequencies counted over all documents; no word weighs nothing. Items are cut to passages of at most `PASSAGE` words. A
randomised SVD of these passages, computed over partitions (each adds A^T A Q for its rows, only sums come to the driver),
gives the latent space, of as many directions as leave no passage more than `LOSS` of its norm outside. Each `SPACE_ITEMS`
items have a space of their own; all spaces of a pass over the documents (`PASS_ITEMS` items) are computed at once.

Corpus text is cut to blocks of `STEP` words, and what stands around each (as much as the later test looks at) is projected
and compared with every passage by cosine. The least cosine that makes a candidate follows from the test: an item of which
at most the share 1 - `SHARE` is missing has a passage of which at most that share is missing, and whatever words those are,
the product of the two vectors is at least the weight of the lightest others; what the latent space leaves out of a passage
is allowed for. So long and short items, items of common words and items beside rare words are all found: no pair that the
test accepts is lost, and the cosine decides which pairs the test sees.

A candidate that has too few of the item's rarer words, counted exactly, goes; one of the others leaks if the longest common subsequence of words between item and text
(from half a passage before the block to as much after it, more for long items) covers `SHARE` of the item, and of its
answer (the last sentence, or the last quarter where that is too short) `ANSWER_SHARE`. Items of under `SHORT` words must be
there whole. Of equal results for a text and an item the first block's cosine is reported, of better ones the best.
A null or empty text has no leak; a null or empty item matches nothing; repeated rows and items are judged alike.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.llm.common import batched, materialise, utf8, word_hashes

BITS = 18
FEATURES = 1 << BITS
STEP, PASSAGE, EXTRA, ITERATIONS, LOSS = 32, 64, 16, 2, 0.02
SHARE, ANSWER_SHARE, SHORT = 0.7, 0.5, 8
#: The check of a candidate counts words in at most these shares of the documents, and the rarest others where they are too
#: few. Each share by itself loses nothing; a candidate must have enough words by all of them, which leaves few for the last test.
RARE = (1 / 50, 1 / 10)
#: Items that share one latent space, and items searched in one pass.
SPACE_ITEMS, PASS_ITEMS = 128, 2048

_WORD = np.zeros(256, bool)
_WORD[[*range(48, 58), *range(97, 123), *range(128, 256)]] = True
_SENTENCE = re.compile(r"[.!?]+\s*|\n+")


def words_of(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words of all texts, and the first word of each text (and the end)."""
    raw = [utf8(t.lower()) for t in texts]
    data = np.frombuffer(b" ".join(raw) + b" ", np.uint8)
    word = _WORD[data]
    edge = np.flatnonzero(word[1:] != word[:-1]) + 1
    if word[0]:
        edge = np.concatenate([[0], edge])
    begin, end = edge[0::2], edge[1::2]
    starts = np.concatenate([[0], np.cumsum([len(r) + 1 for r in raw])])
    return word_hashes(data, begin, end), np.searchsorted(begin, starts)


def feature(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(64 - BITS)).astype(np.int64)


def document_frequencies(docs: DataFrame) -> tuple[np.ndarray, int]:
    """Documents that have each feature (over all documents) and the number of documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(FEATURES + 1, np.int64), 0
        for _, texts in batched(batches):
            h, first = words_of(texts)
            key = np.unique(np.repeat(np.arange(len(texts)), np.diff(first)) * FEATURES + feature(h))
            total[:FEATURES] += np.bincount(key % FEATURES, minlength=FEATURES)
            n += len(texts)
        total[FEATURES] = n
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["f", "n"])

    out = np.zeros(FEATURES + 1, np.int64)
    for f, n in docs.select("text").mapInArrow(run, "f long, n long").groupBy("f").agg(F.sum("n")).collect():  # at most FEATURES + 1 rows
        out[f] = n
    return out[:FEATURES], int(out[FEATURES])


def inverse_frequencies(df: np.ndarray, n: int) -> np.ndarray:
    """Weights of the features; positive, so that words of all documents count too."""
    return np.log1p(n / np.maximum(df, 1)).astype(np.float32)


def least_common(n: int) -> int:
    """Words that the common subsequence with an item of n words must have."""
    return n if n < SHORT else next(m for m in range(int(SHARE * n), n + 1) if m / n >= SHARE)


def margin_of(n: int) -> int:
    """Words before and after a passage that are held against an item of n words; a long item needs as much text."""
    return max(STEP, n - STEP)


def passages_of(n: int) -> list[tuple[int, int]]:
    """Item words cut to equal passages of at most PASSAGE words."""
    parts = max(1, -(-n // PASSAGE))
    cut = [n * i // parts for i in range(parts + 1)]
    return list(zip(cut[:-1], cut[1:], strict=True))


@dataclass
class Items:
    """The items of one space as tasks need them. Arrays by passage: its item, latent vector, norm, what the space leaves
    out of it, the least product with a text that has enough of it, and how many blocks around are looked at."""

    ids: list[int | None]
    words: list[np.ndarray]
    answers: list[np.ndarray]
    place: np.ndarray
    basis: np.ndarray
    idf: np.ndarray
    owner: np.ndarray
    latent: np.ndarray
    norm: np.ndarray
    outside: np.ndarray
    least: np.ndarray
    reach: np.ndarray
    anchors: list[Anchors]


@dataclass
class Anchors:
    """Counted words of each item: sorted hashes, the items of each hash, and how many each item needs around a passage."""

    keys: np.ndarray
    begin: np.ndarray
    who: np.ndarray
    need: np.ndarray
    reach: np.ndarray
    known: np.ndarray


def anchors_of(words: list[np.ndarray], df: np.ndarray, n: int, rare: float) -> Anchors:
    pairs, need = [], np.full(len(words), np.iinfo(np.int32).max, np.int32)  # an item without words is never found
    for i, w in enumerate(words):
        if len(w):
            often = df[feature(w)]
            missing = len(w) - least_common(len(w))
            count = max(missing + 1, int((often <= n * rare).sum()))
            need[i] = count - missing
            pairs += [(x, i) for x in np.unique(w[np.argsort(often, kind="stable")[:count]]).tolist()]
    pairs.sort()
    keys, begin = np.unique(np.array([x for x, _ in pairs], np.uint64), return_index=True)
    known = np.zeros(FEATURES, bool)
    known[feature(keys)] = True
    reach = np.array([-(-margin_of(len(w)) // STEP) for w in words], np.int64)
    return Anchors(keys, np.append(begin, len(pairs)), np.array([i for _, i in pairs], np.int64), need, reach, known)


def enough_words(h: np.ndarray, f: np.ndarray, block: np.ndarray, first: np.ndarray, end: np.ndarray, a: Anchors) -> np.ndarray:
    """Whether the text around each block (of its text's blocks first to end) has as many counted words as each item needs."""
    n, items = len(first), len(a.need)
    at = np.flatnonzero(a.known[f])
    if not len(at):
        return np.zeros((n, items), bool)
    key = np.minimum(np.searchsorted(a.keys, h[at]), len(a.keys) - 1)
    same = a.keys[key] == h[at]
    at, key = at[same], key[same]
    each = a.begin[key + 1] - a.begin[key]
    within = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
    who = a.who[np.repeat(a.begin[key], each) + within]
    total = np.zeros((n + 1, items), np.int32)
    np.cumsum(np.bincount(np.repeat(block[at], each) * items + who, minlength=n * items).reshape(n, items), axis=0, out=total[1:])
    out, here = np.zeros((n, items), bool), np.arange(n)
    for reach in np.unique(a.reach):
        own = np.flatnonzero(a.reach == reach)
        part = total if len(own) == items else total[:, own]
        out[:, own] = part[np.minimum(end, here + 2 + reach)] - part[np.maximum(first, here - reach)] >= a.need[own]
    return out


def _rows(words: list[np.ndarray], idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(feature, weight, passage of each word; item of each passage) of all items' passages."""
    cuts = [(i, a, b) for i, w in enumerate(words) for a, b in passages_of(len(w))]
    f = np.concatenate([np.zeros(0, np.int64), *[feature(words[i][a:b]) for i, a, b in cuts]])
    return f, idf[f], np.repeat(np.arange(len(cuts)), [b - a for _, a, b in cuts]), np.array([i for i, _, _ in cuts], np.int64)


def latent_spaces(items: DataFrame, idf: np.ndarray) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By space: (row of each feature or -1, right singular vectors by falling value) of its items' passages.

    items(space, text). A randomised SVD over partitions; the spaces share the jobs, one for each iteration.
    """
    spark = items.sparkSession

    def spaces_in(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, int]]:
        for rows, texts in batched(batches):
            space = rows.column("space").to_numpy()
            for x in np.unique(space).tolist():
                f, w, row, owner = _rows(_split([texts[i] for i in np.flatnonzero(space == x).tolist()]), idf)
                yield x, f, w, row, len(owner)

    def vocabulary(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x, f, _, _, n in spaces_in(batches):
            u = np.unique(f)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(u) + 1, x)), pa.array(np.append(u, -1)), pa.array(np.append(np.zeros(len(u), np.int64), n))], ["space", "f", "n"])

    used: dict[int, list[int]] = {}
    passages: dict[int, int] = {}
    for x, f, n in items.mapInArrow(vocabulary, "space long, f long, n long").groupBy("space", "f").agg(F.sum("n")).collect():  # at most FEATURES + 1 rows a space
        if f < 0:
            passages[x] = n
        else:
            used.setdefault(x, []).append(f)
    place, q = {}, {}
    for x in used:
        place[x] = np.full(FEATURES, -1, np.int32)
        place[x][sorted(used[x])] = np.arange(len(used[x]))
        width = min(len(used[x]), passages[x] + EXTRA)
        q[x] = np.linalg.qr(np.random.default_rng(5).standard_normal((len(used[x]), width)))[0].astype(np.float32)
    block = 1024

    def product() -> dict[int, np.ndarray]:
        """A^T A q of every space."""
        shared = spark.sparkContext.broadcast((place, q))

        def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[int, np.ndarray] = {}
            for x, f, w, row, n in spaces_in(batches):
                at, own = shared.value[0][x][f], shared.value[1][x]
                y = np.zeros((n, own.shape[1]), np.float32)
                np.add.at(y, row, w[:, None] * own[at])
                total.setdefault(x, np.zeros_like(own))
                np.add.at(total[x], at, w[:, None] * y[row])
            for x, t in total.items():
                parts = [t[i : i + block].tobytes() for i in range(0, len(t), block)]
                yield pa.RecordBatch.from_arrays([pa.array([x] * len(parts), pa.int64()), pa.array(range(len(parts)), pa.int64()), pa.array(parts, pa.binary())], ["space", "part", "sums"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[tuple[int, int], np.ndarray] = {}
            for b in batches:
                for x, part, raw in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                    y = np.frombuffer(raw, np.float32)
                    held[x, part] = held[x, part] + y if (x, part) in held else y
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in held], pa.int64()), pa.array([k[1] for k in held], pa.int64()), pa.array([y.tobytes() for y in held.values()], pa.binary())], ["space", "part", "sums"])

        kind = "space long, part long, sums binary"
        parts: dict[int, list] = {}
        for r in sorted(items.mapInArrow(partial, kind).repartition("space", "part").mapInArrow(add, kind).collect(), key=lambda r: (r.space, r.part)):
            parts.setdefault(r.space, []).append(np.frombuffer(r.sums, np.float32))
        shared.destroy()
        return {x: np.concatenate(y).reshape(q[x].shape) for x, y in parts.items()}

    for _ in range(ITERATIONS):
        q = {x: np.linalg.qr(y)[0].astype(np.float32) for x, y in product().items()}
    out = {}
    for x, y in product().items():
        gram = q[x].T @ y
        value, vector = np.linalg.eigh((gram + gram.T) / 2)
        order = np.argsort(-value)
        out[x] = place[x], (q[x] @ vector[:, order]).astype(np.float32)
    return out


def items_of(rows: list[tuple[int | None, str]], space: tuple[np.ndarray, np.ndarray], idf: np.ndarray, df: np.ndarray, n_docs: int) -> Items:
    """The items of a space, its basis cut to the directions that every passage needs."""
    place, basis = space
    words = _split([t for _, t in rows])
    f, w, row, owner = _rows(words, idf)
    latent = np.zeros((len(owner), basis.shape[1]))
    np.add.at(latent, row, w[:, None] * basis[place[f]])
    key, n = np.unique(row * FEATURES + f, return_counts=True)
    square = np.bincount(key // FEATURES, (n * idf[key % FEATURES].astype(np.float64)) ** 2, minlength=len(owner))
    left = np.maximum(square[:, None] - np.cumsum(latent**2, axis=1), 0)
    enough = np.flatnonzero((left <= (LOSS**2) * square[:, None]).all(axis=0))
    rank = int(enough[0]) + 1 if len(enough) else basis.shape[1]
    least = np.zeros(len(owner))
    for p, i in enumerate(owner.tolist()):
        own, share = np.sort(w[row == p].astype(np.float64) ** 2), least_common(len(words[i])) / max(1, len(words[i]))
        least[p] = own[: max(1, int(np.ceil(share * len(own) - 1e-9)))].sum() if len(own) else np.inf
    reach = np.array([-(-margin_of(len(words[i])) // STEP) for i in owner.tolist()], np.int64)
    answers = _split([answer_of(t) for _, t in rows])
    return Items([i for i, _ in rows], words, answers, place, basis[:, :rank], idf, owner, latent[:, :rank].astype(np.float32), np.sqrt(square), np.sqrt(left[:, rank - 1]), least, reach, [anchors_of(words, df, n_docs, x) for x in RARE])


def answer_of(text: str) -> str:
    parts = [p for p in _SENTENCE.split(text) if p.strip()]
    if len(parts) > 1 and len(parts[-1].split()) >= 3:
        return parts[-1]
    words = text.split()
    return " ".join(words[-max(3, len(words) // 4) :])


def prepare(spark: SparkSession, docs: DataFrame, benchmark: DataFrame) -> Iterator[list[Items]]:
    """For each pass over the documents, its items by latent space; nothing without item texts."""
    named = benchmark.where("length(trim(text)) > 0").select(F.col("item_id").cast("long").alias("item_id"), "text").distinct()
    n_items = named.count()
    if not n_items:
        return
    spaces = -(-n_items // SPACE_ITEMS)
    items = materialise(spark, named.withColumn("space", F.pmod(F.xxhash64("item_id", "text"), F.lit(spaces))), "items")
    df, n = document_frequencies(docs)
    idf = inverse_frequencies(df, n)
    per = max(1, PASS_ITEMS // SPACE_ITEMS)
    for low in range(0, spaces, per):
        own = items.where(F.col("space").between(low, low + per - 1))
        found = latent_spaces(own.select("space", "text"), idf)
        rows: dict[int, list[tuple[int | None, str]]] = {}
        for r in own.orderBy("space", "item_id", "text").collect():  # a pass's items, about PASS_ITEMS
            if r.space in found:
                rows.setdefault(r.space, []).append((r.item_id, r.text))
        if rows:
            yield [items_of(x, found[space], idf, df, n) for space, x in rows.items()]


def _split(texts: list[str]) -> list[np.ndarray]:
    h, first = words_of(texts)
    return [h[a:b] for a, b in zip(first[:-1], first[1:], strict=True)]


def common_subsequence(a: np.ndarray, b: np.ndarray) -> int:
    """Length of the longest common subsequence, a machine word or more of positions of a at a time."""
    masks: dict[int, int] = {}
    for i, x in enumerate(a.tolist()):
        masks[x] = masks.get(x, 0) | 1 << i
    full = (1 << len(a)) - 1
    v = full
    for x in b.tolist():
        u = v & masks.get(x, 0)
        v = ((v + u) | (v - u)) & full
    return len(a) - v.bit_count()


def candidates(items: Items, block: np.ndarray, f: np.ndarray, text: np.ndarray, base: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(block, passage, cosine) of the pairs that pass the least cosine. block, f: of each word; text, base: of each block
    its text, of each text its first block (and the end)."""
    n = int(base[-1])
    at = items.place[f]
    keep = np.flatnonzero(at >= 0)
    own, w = block[keep], items.idf[f[keep]]
    total, size = np.zeros((n + 1, items.basis.shape[1])), np.zeros(n + 1)
    if len(keep):
        begin = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
        total[1 + own[begin]] = np.add.reduceat(w[:, None] * items.basis[at[keep]], begin, axis=0)
        key, times = np.unique(own * FEATURES + f[keep], return_counts=True)
        size[1:] = np.sqrt(np.bincount(key // FEATURES, (times * items.idf[key % FEATURES].astype(np.float64)) ** 2, minlength=n))
    np.cumsum(total, axis=0, out=total)
    np.cumsum(size, out=size)
    here, out = np.arange(n), []
    for reach in np.unique(items.reach).tolist():
        mine = np.flatnonzero(items.reach == reach)
        low, high = np.maximum(base[text], here - reach), np.minimum(base[text + 1], here + 2 + reach)
        around, most = (total[high] - total[low]).astype(np.float32), size[high] - size[low]  # most: not below the norm
        product = around @ items.latent[mine].T
        p, c = np.nonzero(product >= items.least[mine] * 0.999 - 1.001 * most[:, None] * items.outside[mine] - 1e-3)
        out.append((p, mine[c], product[p, c] / np.maximum(most[p] * items.norm[mine[c]], 1e-9)))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def leaks(texts: list[str], items: Items, words: tuple[np.ndarray, np.ndarray] | None = None) -> list[tuple[int, int, float, float, float]]:
    """(text, item, cosine, share of the item, share of its answer) of each leak, the best place of each pair."""
    h, first = words or words_of(texts)
    counts = np.diff(first)
    blocks = -(-counts // STEP)
    base = np.concatenate([[0], np.cumsum(blocks)])
    if not base[-1]:
        return []
    owner = np.repeat(np.arange(len(texts)), counts)
    block = base[owner] + (np.arange(len(h)) - first[owner]) // STEP
    text = np.repeat(np.arange(len(texts)), blocks)
    f = feature(h)
    at, passage, cosine = candidates(items, block, f, text, base)
    item_of = items.owner[passage]
    if len(at):
        counted = np.logical_and.reduce([enough_words(h, f, block, base[:-1][text], base[1:][text], a) for a in items.anchors])
        held = counted[at, item_of]
        at, item_of, cosine = at[held], item_of[held], cosine[held]
    order = np.lexsort((at, -cosine, item_of, text[at]))  # so no later place is better than a whole copy
    found: dict[tuple[int, int], tuple[float, float, float]] = {}
    tried: set[tuple[int, int]] = set()
    for p, i, c in zip(at[order].tolist(), item_of[order].tolist(), cosine[order].tolist(), strict=True):
        t = int(text[p])
        if (p, i) in tried or found.get((t, i), (0, 0, 0))[:2] == (1, 1):
            continue
        tried.add((p, i))
        start = int(first[t]) + (p - int(base[t])) * STEP
        item, answer = items.words[i], items.answers[i]
        margin = margin_of(len(item))
        near = h[max(int(first[t]), start - margin) : min(int(first[t + 1]), start + 2 * STEP + margin)]
        share = common_subsequence(item, near) / max(1, len(item))
        if share < (SHARE if len(item) >= SHORT else 1):
            continue
        said = common_subsequence(answer, near) / max(1, len(answer))
        if said >= ANSWER_SHARE and (share, said, c) > found.get((t, i), (0, 0, 0)):
            found[t, i] = (share, said, c)
    return [(t, i, c, share, said) for (t, i), (share, said, c) in sorted(found.items())]


def search(spark: SparkSession, docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, cosine, item_share, answer_share of every leak."""
    kind = "doc_id long, item_id long, cosine double, item_share double, answer_share double"
    out = spark.createDataFrame([], kind)
    for spaces in prepare(spark, docs, benchmark):
        shared = spark.sparkContext.broadcast(spaces)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for rows, texts in batched(batches):
                words, ids = words_of(texts), rows.column("doc_id").to_pylist()
                for items in shared.value:
                    if hits := leaks(texts, items, words):
                        yield pa.RecordBatch.from_arrays([pa.array([ids[x[0]] for x in hits], pa.int64()), pa.array([items.ids[x[1]] for x in hits], pa.int64()), *[pa.array([x[j] for x in hits], pa.float64()) for j in (2, 3, 4)]], ["doc_id", "item_id", "cosine", "item_share", "answer_share"])

        out = out.union(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, kind))
    return out


def clean(spark: SparkSession, docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without those that leak an item; columns as they were."""
    out = docs
    for spaces in prepare(spark, docs, benchmark):
        shared = spark.sparkContext.broadcast(spaces)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for rows, texts in batched(batches):
                keep, words = np.ones(len(texts), bool), words_of(texts)
                for items in shared.value:
                    keep[[x[0] for x in leaks(texts, items, words)]] = False
                yield rows.filter(pa.array(keep))

        out = out.mapInArrow(run, docs.schema)
    return out


def op9_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every leak of a benchmark item in a document."""
    return search(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
