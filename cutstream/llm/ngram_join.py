"""Jaccard metric-space join of documents on word shingles, exact, by pivots, Voronoi regions and triangle windows.

Distance is 1 - Jaccard. Documents of a corpus are almost all at distance 1 from any sampled document, so document pivots
cannot split a whole corpus; sets of a few shingles are points of the same space and can. Three levels follow each other:

1. Pivots {s}, for every shingle s. A document's nearest pivots are its own shingles; equal distances are ordered by how
   common a shingle is, then by hash (the commonest are counted first, `frequent`). The region of {s} takes the documents
   that have s in their boundary window: a pair within the radius may differ in at most (1 - t)|x| shingles of x, so one of
   the first floor((1 - t)|x|) + 1 is common to both. Rare shingles come first, so a passage that many documents have, or a
   frequent phrase, opens no region for them.
2. A region with more than `BLOCK_ROWS` documents outside its prevailing component takes pivots {s, s'}: the shingles that a
   document lacks before s count against its window, so the next common one stands within a window that is one longer. Two
   different sets within the radius share t / (1 - t) shingles or more, which allows pivots of so many shingles; `DEPTH`
   is the number of such steps.
3. What is left joins by documents as pivots (`pivot_join`): members within the radius of a pivot are in its component at
   once, the others go to the region of their nearest pivot and, where the distances to two pivots differ by no more than
   two radii, to both; regions recurse as long as they shrink, and the rest compares the pairs that the windows
   |d(x, p) - d(y, p)| <= radius of all pivots leave.

Before all that, documents whose least hash is the same (chance: their Jaccard) join by documents as pivots, in blocks of
bounded bytes. That settles most copies, so later regions only look at those with several components. In a region where one
component prevails, its members are not compared with each other: the others are dealt to each block of all. Sizes and
class-count sketches (lower bounds of the symmetric difference) discard pairs without their sets.

Null or blank texts have the empty set and are linked with nothing. Equal sets form one class before any join, so copies
are never expanded to pairs. Rows that repeat a doc_id are separate rows; a component is named by its smallest doc_id.
A null doc_id takes part in links but never names a component (a component of null ids alone has a null name).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cutstream.llm.common import BROADCAST_ROWS, batched, bounded_broadcast, connected, joined, materialise, mix, remove, scratch_path, trim, utf8, word_hashes, words_of

#: Least number of classes of a sketch (a large set has one for each four to eight shingles), and the largest count it keeps.
CLASSES, MOST = 64, 15
#: Rows and bytes of sets that one task joins at once: of equal least hashes, and of a region's block.
REGION_ROWS, BLOCK_ROWS, BLOCK_BYTES = 512, 1024, 1 << 26
#: Further shingles that pivots of a crowded region get (0 or 1).
DEPTH = 1
#: The commonest shingles, which are ordered last. Any list gives right results; it only makes regions even.
COMMON, COMMON_OF_TASK, COMMON_ROWS = 1 << 16, 1 << 14, 16


def shingle_sets(texts: list[str], k: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of the k-word shingles of each text; fewer words make one shingle of them all."""
    data, starts = joined([utf8(t).lower() for t in texts])
    begin, end = words_of(data)
    h = word_hashes(data, begin, end)
    first = np.searchsorted(begin, starts)
    with np.errstate(over="ignore"):
        rolled = np.zeros(max(0, len(h) - k + 1), np.uint64)
        for j in range(k):
            rolled += mix(h[j : len(h) - k + 1 + j] + np.uint64(0x9E3779B97F4A7C15 * (j + 1) & (1 << 64) - 1))
    rolled = mix(rolled).view(np.int64)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= k:
            out.append(np.unique(rolled[a : b - k + 1]))
        elif b > a:
            out.append(np.frombuffer(hashlib.blake2b(h[a:b].tobytes(), digest_size=8).digest(), np.int64))
        else:
            out.append(np.zeros(0, np.int64))
    return out


def digest(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def classes_of(n: int) -> int:
    return max(CLASSES, 1 << max(0, (n // 4).bit_length() - 1))


def sketch(s: np.ndarray, classes: int = 0) -> np.ndarray:
    """Counts of the hashes by their low bits, MOST at most; halves of a sketch add up to that of half the classes."""
    classes = classes or classes_of(len(s))
    return np.minimum(np.bincount(s & (classes - 1), minlength=classes), MOST).astype(np.uint8)


def packed(counts: np.ndarray) -> bytes:
    """Two counts a byte."""
    return (counts[0::2] | (counts[1::2] << 4)).tobytes()


def unpacked(raw: bytes) -> np.ndarray:
    x = np.frombuffer(raw, np.uint8)
    return np.stack([x & 15, x >> 4], axis=1).ravel()


class Sketches:
    """Sketches of sets in order of size, compared at the coarser of two resolutions."""

    def __init__(self, raw: list[bytes]):
        parts = [unpacked(x) for x in raw]
        self.width = np.array([len(x) for x in parts])
        self.row = np.zeros(len(parts), np.int64)
        self.full: dict[int, np.ndarray] = {}
        self.half: dict[int, np.ndarray] = {}
        for w in np.unique(self.width).tolist():
            own = np.flatnonzero(self.width == w)
            self.row[own] = np.arange(len(own))
            self.full[w] = np.stack([parts[i] for i in own.tolist()]).astype(np.int16)
            self.half[w] = np.minimum(self.full[w][:, : w // 2] + self.full[w][:, w // 2 :], MOST)

    def gaps(self, i: int, others: np.ndarray) -> np.ndarray:
        """Lower bounds of the symmetric differences between set i and others that are as large or up to twice as large."""
        w = int(self.width[i])
        mine, out = self.full[w][self.row[i]], np.zeros(len(others), np.int64)
        for table, width in ((self.full, w), (self.half, 2 * w)):
            at = np.flatnonzero(self.width[others] == width)
            if len(at):
                out[at] = np.abs(table[width][self.row[others[at]]] - mine).sum(axis=1, dtype=np.int64)
        return out


def is_link(both: int, a: int, b: int, percent: int) -> bool:
    return both > 0 and 100 * both >= percent * (a + b - both)


def frequent(docs: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ascending hashes, counts) of at most COMMON shingles that the most documents have, counted over all documents.

    A task keeps a bounded table, from which the rarest fall out when it is full, and hands on its commonest.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, counts, held, n = np.zeros(0, np.int64), np.zeros(0), [], 0

        def folded() -> tuple[np.ndarray, np.ndarray]:
            u, at = np.unique(np.concatenate([keys, *held]), return_inverse=True)
            c = np.bincount(at, np.concatenate([counts, np.ones(n)]), len(u))
            if len(u) > 8 * COMMON_OF_TASK:
                own = c > max(1, np.partition(c, -4 * COMMON_OF_TASK)[-4 * COMMON_OF_TASK])
                u, c = u[own], c[own]
            return u, c

        for _, texts in batched(batches):
            sets = shingle_sets(texts, k)
            held += sets
            n += sum(len(x) for x in sets)
            if n > 1 << 20:
                keys, counts = folded()
                held, n = [], 0
        keys, counts = folded()
        top = np.argsort(-counts, kind="stable")[:COMMON_OF_TASK]
        top = top[counts[top] > 3]
        yield pa.RecordBatch.from_arrays([pa.array(keys[top]), pa.array(counts[top].astype(np.int64))], ["s", "n"])

    found = docs.select("text").mapInArrow(run, "s long, n long").groupBy("s").agg(F.sum("n").alias("n")).where(F.col("n") >= COMMON_ROWS)
    rows = found.orderBy(F.desc("n"), "s").limit(COMMON).collect()  # a bounded list
    rows.sort(key=lambda r: r.s)
    return np.array([r.s for r in rows], np.int64), np.array([r.n for r in rows], np.int64)


def rare_first(sets: list[np.ndarray], sizes: list[int], common: tuple[np.ndarray, np.ndarray]) -> list[np.ndarray]:
    """The first sizes[i] shingles of each set, the rarest first, equally rare ones by hash."""
    keys, counts = common
    if not len(keys):
        return [s[:w] for s, w in zip(sets, sizes, strict=True)]
    flat = np.concatenate(sets)
    at = np.minimum(np.searchsorted(keys, flat), len(keys) - 1)
    often = np.where(keys[at] == flat, counts[at], 0)
    out, a = [], 0
    for s, w in zip(sets, sizes, strict=True):
        f = often[a : a + len(s)]
        a += len(s)
        out.append(s[np.lexsort((s, f))[:w]] if f.any() else s[:w])
    return out


def signatures(docs: DataFrame, k: int, percent: int, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(doc_id, t, n, c, home, win, sk): hash of the text, set size, digest of the set, its least hash, the boundary window
    with DEPTH shingles more (a set of fewer has them all), the class-count sketch."""
    shared = docs.sparkSession.sparkContext.broadcast(common)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, texts in batched(batches):
            sets = shingle_sets(texts, k)
            windows = rare_first(sets, [len(s) * (100 - percent) // 100 + 1 + DEPTH if len(s) else 0 for s in sets], shared.value)
            offsets = np.zeros(len(sets) + 1, np.int32)
            np.cumsum([len(w) for w in windows], out=offsets[1:])
            columns = [
                rows.column("doc_id").cast(pa.int64()),
                rows.column("t"),
                pa.array([len(s) for s in sets], pa.int64()),
                pa.array([digest(s) for s in sets], pa.binary()),
                pa.array([int(s[0]) if len(s) else None for s in sets], pa.int64()),
                pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(windows))),
                pa.array([packed(sketch(s)) for s in sets], pa.binary()),
            ]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "t", "n", "c", "home", "win", "sk"])

    rows = docs.select("doc_id", F.xxhash64("text").alias("t"), "text")
    return rows.mapInArrow(run, "doc_id long, t long, n long, c binary, home long, win array<long>, sk binary")


def fetch_sets(docs: DataFrame, wanted: DataFrame, k: int, extra: str = "") -> DataFrame:
    """Sets of the wanted classes (rep, rep_t, k, c, ...), computed again from the text of the row (rep, rep_t).

    Rows that repeat both id and text come once a task.
    """
    names = [x.split()[0] for x in extra.split(",") if x]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple] = set()
        for rows, texts in batched(batches):
            sets, keep = shingle_sets(texts, k), []
            key = list(zip(rows.column("k").to_pylist(), *(rows.column(x).to_pylist() for x in names), strict=True))
            for i, (s, c) in enumerate(zip(sets, rows.column("c").to_pylist(), strict=True)):
                if key[i] not in seen and digest(s) == c:
                    seen.add(key[i])
                    keep.append(i)
            if keep:
                own = rows.take(pa.array(keep))
                yield pa.RecordBatch.from_arrays([own.column("k"), pa.array([sets[i].tobytes() for i in keep], pa.binary()), *[own.column(x) for x in names]], ["k", "set", *names])

    texts = docs.select(F.col("doc_id").alias("own"), F.xxhash64("text").alias("t"), "text").join(bounded_broadcast(wanted), F.expr("own <=> rep AND t = rep_t"))
    return texts.select("text", "k", "c", *names).mapInArrow(run, "k long, set binary" + (", " + extra if extra else ""))


class _Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, a: int, b: int) -> None:
        a, b = self.find(a), self.find(b)
        if a != b:
            self.up[max(a, b)] = min(a, b)


def pivot_join(sets: list[np.ndarray], percent: int, labels: list[int] | None = None, pivots: int = 8, leaf: int = 64) -> list[int]:
    """Local component (index of its first member) of each set: pivots, Voronoi regions, triangle windows, exact overlaps.

    Sets of equal labels, if given, are in one component already. A region that no pivots make smaller, or of at most
    `leaf` sets, compares the pairs in its windows.
    """
    m = len(sets)
    size = np.array([len(s) for s in sets], np.int64)
    ends = np.cumsum(size)
    begins = ends - size
    _, codes = np.unique(np.concatenate(sets), return_inverse=True)
    mark = np.zeros(codes.max() + 1, bool)
    forest, first = _Forest(m), {}
    for i, x in enumerate(labels or ()):
        forest.join(first.setdefault(x, i), i)
    radius = (100 - percent) / 100
    counts = np.stack([sketch(s, 128) for s in sets]).astype(np.int16)

    def overlaps(p: int, others: np.ndarray) -> np.ndarray:
        mine = codes[begins[p] : ends[p]]
        mark[mine] = True
        n = size[others]
        before = np.concatenate([[0], np.cumsum(n)[:-1]])
        at = np.repeat(begins[others] - before, n) + np.arange(n.sum())
        out = np.add.reduceat(mark[codes[at]], before, dtype=np.int64)
        mark[mine] = False
        return out

    def compare(own: np.ndarray, distance: np.ndarray) -> None:
        """Link all pairs of `own` that sizes, windows and sketches leave; distance: rows for pivots, columns as own."""
        root = np.array([forest.find(i) for i in own.tolist()])
        if (root == root[0]).all():
            return
        order = np.argsort(size[own], kind="stable")
        own, root, distance = own[order], root[order], distance[:, order]
        n = size[own]
        for i, x in enumerate(own.tolist()):
            stop = int(np.searchsorted(n, n[i] * 100 // percent, "right"))
            at = i + 1 + np.flatnonzero(root[i + 1 : stop] != root[i])
            if len(at) and len(distance):
                at = at[(np.abs(distance[:, at] - distance[:, i : i + 1]) <= radius + 1e-9).all(axis=0)]
            if len(at):
                gap = np.abs(counts[own[at]] - counts[x]).sum(axis=1)
                at = at[(100 + percent) * gap.astype(np.int64) <= (100 - percent) * (n[at] + n[i])]
            if len(at):
                both = overlaps(x, own[at])
                near = at[100 * both >= percent * (n[i] + n[at] - both)]
                for y in own[near].tolist():
                    forest.join(x, y)
                if len(near):
                    met = np.unique(np.append(root[near], root[i]))
                    root[np.isin(root, met)] = forest.find(x)

    regions = [np.arange(m)]
    while regions:
        own = regions.pop()
        held, rows = np.zeros(len(own), bool), []
        while len(own) > leaf and len(rows) < pivots and not held.all():
            at = int(np.flatnonzero(~held)[0])  # the next pivot: the first set that no ball holds
            both = overlaps(int(own[at]), own)
            union = size[own[at]] + size[own] - both
            rows.append(1 - both / union)
            ball = 100 * both >= percent * union
            held |= ball
            held[at] = True
            for x in own[ball].tolist():
                forest.join(int(own[at]), x)
        distance = np.stack(rows) if rows else np.zeros((0, len(own)))
        near = distance <= distance.min(axis=0) + 2 * radius + 1e-9 if rows else np.zeros((0, 0), bool)
        if len(rows) > 1 and near.sum(axis=1).max() <= 0.8 * len(own):
            regions += [own[r] for r in near if r.sum() > 1]
        else:
            compare(own, distance)
    return [forest.find(i) for i in range(m)]


def _groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Runs of equal keys of a sorted stream, one at a time."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(x).to_numpy(zero_copy_only=False) for x in keys]
        cut = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
        edges = [0, *cut.tolist(), batch.num_rows]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            key = tuple(c[a] for c in cols)
            if last is not None and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = key
    if held:
        yield pa.Table.from_batches(held)
    trim()


def _in_blocks(rows: DataFrame, key: str, sizes: DataFrame, salt: int) -> DataFrame:
    """rows of keys that several have, dealt to blocks: sizes(key, m, nb) over all keys; adds nb and b < nb.

    The crowded keys (nb > 1: few, as each has a block's rows or bytes) meet the rows in memory, so none is one task's work.
    """
    crowded = bounded_broadcast(sizes.where("nb > 1").select(key, "nb"))
    few = sizes.where("nb = 1 AND m > 1").select(key)
    hot = rows.join(crowded, key)
    rest = rows.join(crowded, key, "left_anti").join(few, key, "left_semi").withColumn("nb", F.lit(1))
    return hot.select(*rows.columns, "nb").unionByName(rest).withColumn("b", F.pmod(F.xxhash64("k", F.lit(salt)), F.col("nb")).cast("int"))


def _blocks_of(m: Column, n: Column, rows: int) -> Column:
    """Blocks that m rows with n shingles in all need."""
    return F.greatest(F.ceil(m / F.lit(rows)), F.ceil(n * 8 / F.lit(BLOCK_BYTES))).cast("int")


def _mixed(spark: SparkSession, entries: DataFrame, labels: DataFrame) -> DataFrame:
    """(s, k, label, anchor, m) of the regions s that hold several components; entries(s, k), labels(k, label) of some.

    Most regions have one member. Two narrow columns are shuffled to find the others, whose labels then join.
    """
    cell = Window.partitionBy("s")
    shared = materialise(spark, entries.select("s", "k", F.count("*").over(cell).alias("m")).where("m > 1").select("s", "k"), "shared")
    named = shared.join(bounded_broadcast(labels), "k", "left").select("s", "k", F.coalesce("label", "k").alias("label"))
    wide = named.select("s", "k", "label", F.min("k").over(cell).alias("anchor"), F.count("*").over(cell).alias("m"), F.min("label").over(cell).alias("low"), F.max("label").over(cell).alias("high"))
    return materialise(spark, wide.where("low <> high").select("s", "k", "label", "anchor", "m"), "mixed")


def _regions(spark: SparkSession, classes: DataFrame, labels: DataFrame, percent: int) -> DataFrame:
    """(anchor, k, label): members of each region of singleton pivots, crowded ones by pivots of more shingles; only
    regions with several components, each named by its smallest member."""
    window = F.floor(F.col("n") * (100 - percent) / 100).cast("int")
    entries = classes.select("k", F.explode(F.slice("win", F.lit(1), window + 1)).alias("s"))
    out, steps = None, DEPTH if percent == 100 else min(DEPTH, -(-percent // (100 - percent)) - 1)
    for depth in range(steps + 1):
        mixed = _mixed(spark, entries, labels)
        large = mixed.where(F.col("m") > BLOCK_ROWS)
        crowded = None
        if depth < steps and large.limit(1).count():
            own = large.groupBy("s", "label").agg(F.count("*").alias("m"))
            crowded = materialise(spark, own.groupBy("s").agg((F.sum("m") - F.max("m")).alias("outside")).where(F.col("outside") > BLOCK_ROWS).select("s"), "crowded")
        found = mixed if crowded is None else mixed.join(bounded_broadcast(crowded), "s", "left_anti")
        found = found.select("anchor", "k", "label")
        out = found if out is None else out.unionByName(found)
        if crowded is None or not crowded.limit(1).count():
            break
        more = large.join(bounded_broadcast(crowded), "s").select("s", "k").join(classes.select("k", "n", "win"), "k")
        # The last pivot shingle's place in the window; further ones stand behind it.
        at = F.array_position("win", F.col("s")).cast("int")
        nexts = more.select("s", "k", F.explode(F.slice("win", at + 1, F.greatest(F.lit(0), window + 2 - at))).alias("next"))
        entries = materialise(spark, nexts.select(F.xxhash64("s", "next").alias("s"), "k"), "entries")
    return materialise(spark, out.groupBy("anchor", "k").agg(F.first("label").alias("label")), "anchored")


def _tasks(anchored: DataFrame) -> DataFrame:
    """(task, k, side, cross): what is compared together. A region within a block is a task; in a larger one every member is
    on a row side and those outside its prevailing component are dealt to each block on the column side too."""
    blocks = lambda m: F.ceil(m / F.lit(BLOCK_ROWS)).cast("int")
    per = anchored.groupBy("anchor", "label").agg(F.count("*").alias("m"))
    whole = per.groupBy("anchor").agg(F.sum("m").alias("m"), F.max(F.struct("m", "label")).alias("top"))
    large = whole.where(F.col("m") > BLOCK_ROWS).select("anchor", blocks(F.col("m")).alias("nb"), F.col("top.label").alias("most"), blocks(F.col("m") - F.col("top.m")).alias("no"))
    rows = anchored.join(bounded_broadcast(large), "anchor", "left").select("anchor", "k", "label", F.coalesce("nb", F.lit(1)).alias("nb"), F.coalesce("no", F.lit(1)).alias("no"), "most")
    block = lambda n, salt: F.pmod(F.xxhash64("k", F.lit(salt)), F.col(n)).cast("int")
    upto = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    task = F.xxhash64("anchor", "i", "j").alias("task")
    across = rows.select("anchor", "k", "nb", block("nb", "row").alias("i"), F.explode(upto("no")).alias("j")).select(task, "k", F.lit(0).alias("side"), (F.col("nb") > 1).alias("cross"))
    down = rows.where("nb > 1 AND label <> most").select("anchor", "k", F.explode(upto("nb")).alias("i"), block("no", "column").alias("j")).select(task, "k", F.lit(1).alias("side"), F.lit(True).alias("cross"))
    return across.unionByName(down)


def _settled(spark: SparkSession, docs: DataFrame, classes: DataFrame, k: int, percent: int) -> DataFrame:
    """(k, label) of classes that meet a near one among those of the same least hash, in blocks.

    Where one least hash fills several blocks, one member of each component goes to the next round, until one block holds
    them or a round leaves more than half. This only saves work: what is not joined here is left to the closing pass.
    """
    home = classes.select("k", "c", "rep", "rep_t", "home", "n")

    def regional(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _groups(batches, ["region"]):
            ids, first = np.unique(t.column("k").to_numpy(), return_index=True)
            raw = t.column("set").to_pylist()
            sets = [np.frombuffer(raw[i], np.int64) for i in first.tolist()]
            if len(sets) > 1:
                up = pivot_join(sets, percent)
                rows = [(int(ids[i]), int(ids[r])) for i, r in enumerate(up) if r != i]
                yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in rows], pa.int64()), pa.array([x[1] for x in rows], pa.int64())], ["k", "label"])

    rounds: list[DataFrame] = []
    while True:
        sizes = home.groupBy("home").agg(F.count("*").alias("m"), F.sum("n").alias("n")).where("m > 1")
        sizes = materialise(spark, sizes.select("home", "m", _blocks_of(F.col("m"), F.col("n"), REGION_ROWS).alias("nb")), "homes")
        dealt = _in_blocks(home.drop("n"), "home", sizes, len(rounds))
        wanted = materialise(spark, dealt.select("k", "c", "rep", "rep_t", F.xxhash64("home", "b").alias("region")), "regions")
        found = fetch_sets(docs, wanted, k, "region long").repartition("region").sortWithinPartitions("region").mapInArrow(regional, "k long, label long")
        rounds.append(materialise(spark, found, "labels"))
        crowded = sizes.where("nb > 1").select("home")
        if not crowded.limit(1).count() or not rounds[-1].limit(1).count():
            break
        before = home.join(bounded_broadcast(crowded), "home", "left_semi")
        left = before.join(bounded_broadcast(rounds[-1].select("k")), "k", "left_anti")
        home = materialise(spark, left.select("k", "c", "rep", "rep_t", "home", "n"), "roots")
        if 2 * home.count() > before.count():
            break
    if len(rounds) == 1:
        return rounds[0]
    links = reduce(DataFrame.unionByName, rounds)
    return materialise(spark, connected(spark, links.select(F.col("k").alias("a"), F.col("label").alias("b"))).select(F.col("id").alias("k"), F.col("root").alias("label")), "labels")


def grouped(spark: SparkSession, docs: DataFrame, k: int = 3, percent: int = 90) -> DataFrame:
    """(doc_id, t, n, c, component_id) for every row of docs: hash of the text, set size, digest of the set, component."""
    wide = scratch_path(spark, "signatures")
    signatures(docs, k, percent, frequent(docs, k)).write.parquet(wide)
    signed = spark.read.parquet(wide)
    row = F.min(F.struct(F.col("doc_id").isNull(), F.col("doc_id"), F.col("t"))).alias("row")
    one = signed.where("n > 0").groupBy("c").agg(row, *[F.first(x).alias(x) for x in ("n", "home", "win", "sk")])
    classes = materialise(spark, one.select("c", F.col("row.doc_id").alias("rep"), F.col("row.t").alias("rep_t"), "n", "home", "win", "sk").withColumn("k", F.monotonically_increasing_id()), "classes")
    signed = materialise(spark, signed.select("doc_id", "t", "n", "c"), "documents")
    remove(spark, wide)

    links = _settled(spark, docs, classes, k, percent)
    named = classes.select("k", "c", "rep", "rep_t", "n", "sk").join(bounded_broadcast(links), "k", "left")
    named = materialise(spark, named.withColumn("label", F.coalesce("label", "k")), "named")

    # Closing pass: regions of the boundary windows that hold more than one component.
    anchored = _regions(spark, classes.select("k", "n", "win"), links, percent)
    slim = named.select("k", F.col("n").cast("int").alias("n"), "sk", "label")
    tasks = _tasks(anchored).join(slim, "k").repartition("task").sortWithinPartitions("task", "n")

    def close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _groups(batches, ["task"]):
            n, ids, label, side = (t.column(x).to_numpy() for x in ("n", "k", "label", "side"))
            n = n.astype(np.int64)
            counts, near = Sketches(t.column("sk").to_pylist()), _Forest(len(n))
            cross, hit = t.column("cross")[0].as_py(), np.zeros(len(n), bool)
            for i in range(len(n) - 1):
                stop = np.searchsorted(n, n[i] * 100 // percent, "right")
                others = np.arange(i + 1, stop)
                others = others[(label[others] != label[i]) & ((side[others] != side[i]) | (not cross))]
                if len(others):
                    others = others[(100 + percent) * counts.gaps(i, others) <= (100 - percent) * (n[others] + n[i])]
                for x in others.tolist():
                    near.join(i, x)
                hit[others] = True
                hit[i] |= len(others) > 0
            groups: dict[int, set[int]] = {}
            for i in np.flatnonzero(hit).tolist():
                groups.setdefault(near.find(i), set()).add(int(ids[i]))
            if groups:
                lists = [sorted(x) for x in groups.values()]
                names = [int.from_bytes(hashlib.blake2b(np.array(x).tobytes(), digest_size=8).digest(), "little", signed=True) for x in lists]
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(lists, pa.list_(pa.int64()))], ["region", "ks"])

    # What may still be linked forms regions again, each of which joins by pivots on whole sets; a region that several
    # tasks find is joined once.
    last = materialise(spark, tasks.mapInArrow(close, "region long, ks array<long>").groupBy("region").agg(F.first("ks").alias("ks")), "last-regions")
    members = materialise(spark, last.select("region", F.explode("ks").alias("k")).join(named.select("k", "c", "rep", "rep_t", "label"), "k"), "members")

    def rejoin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _groups(batches, ["region"]):
            labels = t.column("label").to_pylist()
            up = pivot_join([np.frombuffer(s, np.int64) for s in t.column("set").to_pylist()], percent, labels)
            links = {(labels[i], labels[r]) for i, r in enumerate(up) if labels[i] != labels[r]}
            if links:
                yield pa.RecordBatch.from_arrays([pa.array(z, pa.int64()) for z in zip(*sorted(links), strict=True)], ["a", "b"])

    found = fetch_sets(docs, members, k, "region long, label long").repartition("region").sortWithinPartitions("region").mapInArrow(rejoin, "a long, b long")
    roots = connected(spark, found)

    final = named.select("c", "rep", "label").join(bounded_broadcast(roots), F.col("label") == F.col("id"), "left").select("c", "rep", F.coalesce("root", "label").alias("root"))
    final = materialise(spark, final, "final")
    names = final.groupBy("root").agg(F.min("rep").alias("component_id"))
    whole = final.join(names, "root").select("c", "root", "component_id")
    out = signed.join(whole, "c", "left")
    return out.select("doc_id", "t", "n", "c", "root", F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def components(spark: SparkSession, docs: DataFrame, k: int = 3, percent: int = 90) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of docs."""
    return grouped(spark, docs, k, percent).select("doc_id", F.col("n").alias("n_shingles"), "component_id")


def one_of_each(spark: SparkSession, docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """docs with one row of each component, columns as they were: that of the smallest doc_id (a null one only if there is no
    other), of rows that repeat it that of the least text hash.

    Decisions are on rows (doc_id and text), not on ids: of two rows that repeat an id each stays or goes by its own
    component. Rows without words are all kept.
    """
    rows = materialise(spark, grouped(spark, docs, k, percent).where("n > 0").select("doc_id", "t", "root"), "groups")
    # Only components of several rows are judged; most have one.
    first = rows.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull(), F.col("doc_id"), F.col("t"))).alias("x"), F.count("*").alias("m")).where("m > 1")
    kept = materialise(spark, first.select(F.col("root").alias("of"), F.col("x.doc_id").alias("first_id"), F.col("x.t").alias("first_t")), "kept")
    judged = rows.join(bounded_broadcast(kept), F.col("root") == F.col("of")).select("doc_id", "t", F.expr("doc_id <=> first_id AND t = first_t").alias("stays"))
    # Repeats of a row that stays are told from it by nothing, so its repeats are dropped by their columns.
    verdict = judged.groupBy("doc_id", "t").agg(F.bool_and("stays").alias("stays"), F.count("*").alias("m")).where("NOT stays OR m > 1")
    verdict = materialise(spark, verdict.select(F.col("doc_id").alias("_id"), F.col("t").alias("_t"), F.col("stays").alias("_stays")), "verdict")
    same = F.expr("doc_id <=> _id AND xxhash64(text) = _t")
    out = docs.join(bounded_broadcast(verdict), same, "left_anti").select(*docs.columns)
    if verdict.where("_stays").limit(1).count():
        out = out.unionByName(docs.join(bounded_broadcast(verdict.where("_stays")), same, "left_semi").select(*docs.columns).dropDuplicates(["doc_id", "text"]))
    return out


def op6_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of all documents: three-word shingles, Jaccard of 0.9 or more."""
    return components(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"), 3, 90)


__all__ = ["BROADCAST_ROWS", "components", "one_of_each", "op6_ngram_jaccard_join", "pivot_join", "shingle_sets"]
