"""Near duplicates by order MinHash.

K-mers are runs of five words, each labelled with its occurrence number, so repeats count. A sketch takes, under one hash
order, the ``TAKE`` smallest labelled k-mers and keeps them in text order: two texts get the same sketch only if the
same k-mers are smallest *and* stand in the same order, which follows edit similarity rather than set overlap. Each of
``SKETCHES`` orders gives one bucket key. Texts of at most ``SHORT`` words get further sketches of shorter k-mers.

Links. Texts with the same words are one text from the start. In each bucket every text is compared with the leader, the
one of the smallest id. A pair links if its alignment similarity, 1 - edits / longer length, reaches the threshold: a
banded bit-parallel alignment of the words decides, with the band as wide as the threshold allows edits. What fails is
compared with a second leader, of the smallest hash. Similarity isn't transitive, so a text that failed against its leader may still link with any other. Edits are a metric, so two texts whose
edits to their leader differ by more than the threshold allows can't link, and most of a leader's own class needs no
further look. The others are compared among themselves, in blocks against blocks, each pair of different classes once, in
whichever bucket names it first; lengths and shared words rule out, exactly, nearly all pairs before any is aligned. No
link between texts that share a bucket is lost, other than those inside a class. Classes are connected components, by
alternating stars.

Scale: one pass reads the texts and leaves less than a kilobyte of keys for each; copies are combined by digest before they
move. Words are fetched only for texts in shared buckets. Leaders with many members are dealt to several tasks with a copy
of the leader's words. What is left of a bucket is cut into blocks by length and hash, bounded in rows and bytes, without
ranking it in one task; only blocks of neighbouring lengths and different classes meet. Nodes with many links, at most
200,000, are looked up in a broadcast, so a star's centre isn't one task. Each step of the components ends in a shared
table, and the one before it is removed.

Defined results: null and empty texts are classes of their own; case and punctuation don't matter, but texts without any
words are copies if they are equal; texts of any length are compared whole; rows that repeat an id share its class; null
ids keep a null class.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

WORD = re.compile(r"\w+")
K, TAKE, SKETCHES = 5, 2, 80
SHORT, SHORT_K, SHORT_SKETCHES = 40, 3, 24
#: A block's texts and bytes of words, and the texts of one class from which it has blocks of its own.
BLOCK, BLOCK_BYTES, CLASS_BLOCK = 2048, 8 << 20, 256
#: Texts compared with one copy of their leader's words.
CHUNK = 256
ODD = np.random.default_rng(7).integers(1 << 62, 1 << 63, SKETCHES + SHORT_SKETCHES, np.uint64) * np.uint64(2) + np.uint64(1)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


class Words(dict):
    """64-bit digests of words, remembered up to a bound."""

    def __missing__(self, word: str) -> int:
        if len(self) > 120_000:
            self.clear()
        self[word] = out = int.from_bytes(hashlib.blake2b(word.encode(), digest_size=8).digest(), "little")
        return out

    def of(self, text: str) -> np.ndarray:
        words = WORD.findall(text.lower())
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def kmers(words: np.ndarray, k: int = K) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each run of k words (of all words, where there are fewer), without and with its occurrence number."""
    n = max(1, len(words) - k + 1)
    plain = np.zeros(n, np.uint64)
    for i in range(min(k, len(words))):
        plain = mixed(plain + words[i : i + n])
    order = np.argsort(plain, kind="stable")
    ranked = plain[order]
    first = np.r_[True, ranked[1:] != ranked[:-1]]
    at = np.arange(n)
    seen = np.empty(n, np.uint64)
    seen[order] = at - np.maximum.accumulate(np.where(first, at, 0))
    return plain, mixed(plain + seen * np.uint64(0xD6E8FEB86659FD93))


def smallest(values: np.ndarray, take: int) -> np.ndarray:
    """Positions of each row's ``take`` smallest values, in text order. Overwrites ``values``."""
    rows, n = values.shape
    if n <= take:
        return np.tile(np.arange(n), (rows, 1))
    found, each = np.empty((rows, take), np.int64), np.arange(rows)
    for i in range(take):
        found[:, i] = at = values.argmin(1)
        values[each, at] = np.iinfo(np.uint64).max
    return np.sort(found, axis=1)


def sketch(words: np.ndarray) -> list[int]:
    """Bucket keys, signed 64 bit."""
    keys: list[int] = []
    for lo, hi, k in [(0, SKETCHES, K)] + ([(SKETCHES, SKETCHES + SHORT_SKETCHES, SHORT_K)] if len(words) <= SHORT else []):
        plain, labelled = kmers(words, k)
        step = max(1, min(hi - lo, (1 << 19) // len(plain)))
        for a in range(lo, hi, step):
            b = min(hi, a + step)
            at = smallest(labelled[None, :] * ODD[a:b, None], TAKE)
            key = np.arange(a, b, dtype=np.uint64)
            for column in plain[at].T:
                key = mixed(key * np.uint64(31) + column)
            keys += key.view(np.int64).tolist()
    return keys


def edits(a: np.ndarray, b: np.ndarray, most: int) -> int:
    """Word edits between ``a`` and ``b``, or ``most + 1`` if there are more.

    After equal ends are cut off, a bit vector of the 2 * most + 1 diagonals around the main one walks down the rows: it
    holds where the cost rises and falls from one cell to the next, and one addition finds all the cells of a row.
    """
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > most:
        return most + 1
    n = len(a)
    differ = np.flatnonzero(a != b[:n])
    head = int(differ[0]) if len(differ) else n
    a, b = a[head:], b[head:]
    n = len(a)
    differ = np.flatnonzero(a[::-1] != b[len(b) - n :][::-1])
    tail = int(differ[0]) if len(differ) else n
    a, b = a[: n - tail], b[: len(b) - tail]
    m, n = len(a), len(b)
    if not m:
        return n
    # Columns are words of b, rows words of a; bit d of column j is row j - most + d, and every column moves down by one.
    width = 2 * most + 1
    full = (1 << width) - 1
    places: dict[int, int] = {}
    for i, w in enumerate(a.tolist()):
        places[w] = places.get(w, 0) | 1 << i
    up, down = full & ~((1 << most) - 1), 0
    cost = min(most, m)  # along the lowest diagonal while that is inside, then along the last row
    top = 1 << (width - 1)
    for j, w in enumerate(b.tolist()):
        shift, spots = j - most, places.get(w, 0)
        here = (spots >> shift if shift >= 0 else spots << -shift) & full
        level = (((((here & up) + up) ^ up) | here | down)) & full
        right = down | (full & ~(level | up))
        left = level & up
        if j + most < m:
            cost += not level & top
            if cost > 2 * most + n - m:
                break
        else:
            bit = 1 << (m - 1 - shift)
            cost += bool(right & bit) - bool(left & bit)
            if cost - (n - 1 - j) > most:
                break
        slid = level >> 1
        up = left | (full & ~(slid | right))
        down = slid & right
    return min(cost, most + 1)


def most_edits(longer: int, threshold: float) -> int:
    """Edits that a pair may have, given the longer one's length."""
    return int((1 - threshold) * longer + 1e-9)


class Bag:
    """A text's words with their counts."""

    def __init__(self, words: np.ndarray) -> None:
        self.words = words
        self.kinds, self.counts = np.unique(words, return_counts=True)

    def apart(self, other: Bag) -> int:
        """Edits that two texts have at least: words of the longer one that the other hasn't, counted with repeats."""
        _, i, j = np.intersect1d(self.kinds, other.kinds, assume_unique=True, return_indices=True)
        return max(len(self.words), len(other.words)) - int(np.minimum(self.counts[i], other.counts[j]).sum())


def linked_by(a: Bag, b: Bag, threshold: float) -> tuple[float, int]:
    """Alignment similarity of two texts and their edits; where that is below the threshold, 0 and a lower bound of the edits."""
    longer = max(len(a.words), len(b.words))
    most = most_edits(longer, threshold)
    least = a.apart(b)
    if least > most:
        return 0.0, least
    e = edits(a.words, b.words, most)
    return (1 - e / longer, e) if e <= most else (0.0, most + 1)


def similarity(a: np.ndarray, b: np.ndarray, threshold: float) -> float:
    """Alignment similarity of two word sequences, or 0 if below the threshold."""
    return linked_by(Bag(a), Bag(b), threshold)[0]


def sketched(docs: DataFrame, id_col: str, text: str) -> DataFrame:
    """id, digest of the words and keys of each document with words; of others that aren't empty the digest of the text and no keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words()
        for part in common.pieces(batches, 1, 1 << 20):
            ids, digests, keys = [], [], []
            for i, t in zip(part.column(0).to_pylist(), common.texts_of(part.column(1)), strict=True):
                w = words.of(t)
                if len(w) or t:
                    ids.append(i)
                    digests.append(hashlib.blake2b(w.tobytes() if len(w) else t.encode(), digest_size=16, person=b"words" if len(w) else b"text").digest())
                    keys.append(sketch(w) if len(w) else [])
            yield pa.RecordBatch.from_arrays([pa.array(ids, part.column(0).type), pa.array(digests, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], names=["id", "digest", "keys"])

    kind = docs.schema[id_col].dataType.simpleString()
    source = docs.where(F.col(f"`{id_col}`").isNotNull() & F.col(f"`{text}`").isNotNull()).select(F.col(f"`{id_col}`"), F.col(f"`{text}`"))
    return source.mapInArrow(run, f"id {kind}, digest binary, keys array<bigint>")


def contents(docs: DataFrame, ids: DataFrame, id_col: str, text: str) -> DataFrame:
    """Word digests (32 bit) of the wanted documents."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words()
        for part in common.pieces(batches, 1, 1 << 20):
            found = [(words.of(t) >> np.uint64(32)).astype(np.uint32).tobytes() for t in common.texts_of(part.column(1))]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(found, pa.binary())], names=["id", "words"])

    wanted = docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text}`").alias("t")).where(F.col("t").isNotNull()).join(ids, "id", "left_semi")
    return wanted.mapInArrow(run, f"id {kind}, words binary").dropDuplicates(["id"])


def compared(pairs: DataFrame, known: DataFrame, threshold: float) -> DataFrame:
    """``pairs`` (a, b) with their similarity, 0 for those below the threshold, their edits (then a lower bound) and the
    length of b. ``known``: id, words."""
    kind = known.schema["id"].dataType.simpleString()
    counts = pairs.groupBy("a").agg(F.ceil(F.count("*") / CHUNK).cast("int").alias("chunks"))
    left = known.withColumnRenamed("id", "a").join(counts, "a").select("a", F.col("words").alias("words_a"), F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"))
    right = pairs.join(counts, "a").withColumn("chunk", F.pmod(F.xxhash64("b"), F.col("chunks")).cast("int")).drop("chunks").join(known.withColumnRenamed("id", "b"), "b")
    both = right.join(left, ["a", "chunk"]).select("a", "b", "words_a", "words")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, leader = b"", Bag(np.empty(0, np.uint32))
        for batch in batches:
            out = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                if (mine := x.as_py()) != held:
                    held, leader = mine, Bag(np.frombuffer(mine, np.uint32))
                other = Bag(np.frombuffer(y.as_py(), np.uint32))
                out.append((*linked_by(leader, other, threshold), len(other.words)))
            columns = [pa.array([o[i] for o in out], t) for i, t in enumerate((pa.float64(), pa.int64(), pa.int64()))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], names=["a", "b", "similarity", "edits", "n"])

    return both.mapInArrow(run, f"a {kind}, b {kind}, similarity double, edits bigint, n bigint")


def still_open(classed: DataFrame, threshold: float) -> DataFrame:
    """What the leaders leave open of each bucket: key, id, class, n. ``classed``: key, id, class, n (words), the class of the
    bucket's leader, and the similarity and edits to it.

    Texts outside the leader's class may link with any others. One inside it, x, is needed only if some y outside may be near
    enough: edits(y, leader) - edits(x, leader) <= allowed, where what is allowed grows with the longer one's length. The
    least edits of the texts outside, with and without what their own length allows, stand for all of them.
    """
    outside = classed.where("class <> leader_class")
    allowed = F.floor((1 - threshold) * F.col("n") + 1e-9)
    least = outside.groupBy("key").agg(F.min("edits").alias("far"), F.min(F.col("edits") - allowed).alias("near"))
    unsure = F.col("similarity") == 0  # in the class by another way: its edits to the leader are a lower bound only
    needed = unsure | (F.col("near") <= F.col("edits")) | (F.col("far") <= F.col("edits") + allowed)
    inside = classed.where("class = leader_class").join(least, "key").where(needed)
    rest = outside.select("key", "id", "class", "n").unionAll(inside.select("key", "id", "class", "n"))
    several = rest.groupBy("key").agg(F.min("class").alias("lo"), F.max("class").alias("hi")).where("lo <> hi").select("key")
    return rest.join(several, "key", "left_semi")


def compared_in_blocks(left: DataFrame, known: DataFrame, threshold: float) -> DataFrame:
    """Links among the texts of each bucket, as many as join them. ``left``: key, id, class that the text is in already, n (words).

    A bucket's texts are dealt to cells: by length, in steps of the threshold, so that only neighbouring cells can hold
    links, and a class with many texts in a cell has one of its own, which needs no look inside. Cells are cut into blocks
    by hash. Texts move once per block they meet, not once per pair, and a pair in one class by earlier links or by those
    of its blocks needs none of its own.
    """
    kind = known.schema["id"].dataType.simpleString()
    step = F.floor(F.log(F.col("n").cast("double")) / -math.log(threshold) + 1e-9).cast("int")
    whole = left.groupBy("key").agg(((F.count("*") <= BLOCK) & (F.sum("n") * 4 <= BLOCK_BYTES)).alias("one"))
    binned = left.join(whole, "key").withColumn("bin", F.when(F.col("one"), 0).otherwise(step)).drop("one")  # what fits one block stays one
    binned = common.stored(binned, "binned")  # counted, cut and dealt from: the look-up is made once
    sizes = binned.groupBy("key", "bin", "class").agg(F.count("*").alias("n"), F.sum("n").alias("words"))
    sizes = sizes.withColumn("own", F.when(F.col("n") >= CLASS_BLOCK, F.col("class")))
    cells = sizes.groupBy("key", "bin", "own").agg(F.greatest(F.ceil(F.sum("n") / BLOCK), F.ceil(F.sum("words") * 4 / BLOCK_BYTES)).cast("int").alias("blocks"))
    blocks = common.stored(cells.withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks"), "blocks")
    place = lambda side: F.struct(F.col("bin"), F.coalesce(F.col("own").cast("string"), F.lit("")).alias("own"), F.col("block")).alias(side)
    pairs = blocks.select("key", place("x")).join(blocks.select("key", place("y")), "key")
    pairs = pairs.where((F.col("x") <= F.col("y")) & (F.col("y.bin") - F.col("x.bin") <= 1) & ((F.col("x.own") != F.col("y.own")) | (F.col("x.own") == "")))
    sides = F.array_distinct(F.array("x", "y"))
    meets = pairs.withColumn("at", F.explode(sides)).select("key", "at.bin", "at.own", "at.block", "x", "y")
    big = sizes.where("own is not null").select("key", "bin", "class", F.col("own").cast("string").alias("own"))
    dealt = binned.join(big, ["key", "bin", "class"], "left").withColumn("own", F.coalesce("own", F.lit("")))
    dealt = dealt.join(cells.withColumn("own", F.coalesce(F.col("own").cast("string"), F.lit(""))), ["key", "bin", "own"]).withColumn("block", F.pmod(F.xxhash64("id", F.lit("block")), F.col("blocks")).cast("int"))
    dealt = dealt.join(meets, ["key", "bin", "own", "block"]).select("key", "x", "y", "id", "class", (F.struct("bin", "own", "block") == F.col("x")).alias("first"))
    own_keys = left.groupBy("id").agg(F.collect_set("key").alias("keys"))  # at most one per sketch
    dealt = dealt.join(known.join(own_keys, "id"), "id")  # words and keys meet once a text, not once a place it is dealt to

    def run(t: pa.Table) -> pa.Table:
        key = t["key"][0].as_py()
        ids, first = t["id"].to_pylist(), t["first"].to_numpy()
        same = t["x"][0].as_py() == t["y"][0].as_py()
        keys = [set(k) for k in t["keys"].to_pylist()]
        bags = [Bag(np.frombuffer(w, np.uint32)) for w in t["words"].to_pylist()]
        n = np.array([len(b.words) for b in bags])
        wide = int(2 ** np.clip(np.round(np.log2(1.5 * np.median(n))), 6, 11))
        folded = np.zeros((len(bags), wide), np.uint16)
        for x, b in enumerate(bags):  # words by a few bits of their digest: what two texts share here is never less than what they share
            folded[x] = np.minimum(np.bincount(b.words % wide, minlength=wide), 65535)
        number: dict = {}
        label = np.array([number.setdefault(c, len(number)) for c in t["class"].to_pylist()])  # classes, joined as links are found
        out: list[tuple] = []
        for x in range(len(ids)):
            if not (same or first[x]):
                continue
            rest = np.arange(x + 1, len(ids)) if same else np.flatnonzero(~first)
            rest = rest[label[rest] != label[x]]
            longer = np.maximum(n[rest], n[x])
            most = np.floor((1 - threshold) * longer + 1e-9)
            near = longer - np.minimum(n[rest], n[x]) <= most
            rest, longer, most = rest[near], longer[near], most[near]
            shared = np.minimum(folded[rest], folded[x]).sum(1, dtype=np.int64) + (0 if n[x] < 65535 else n[x])
            for y in rest[longer - shared <= most].tolist():
                if label[x] != label[y] and min(keys[x] & keys[y]) == key:
                    s, _ = linked_by(bags[x], bags[y], threshold)
                    if s:
                        label[label == label[y]] = label[x]
                        out.append((min(ids[x], ids[y]), max(ids[x], ids[y]), s))
        return pa.table({"a": pa.array([o[0] for o in out], t["id"].type), "b": pa.array([o[1] for o in out], t["id"].type), "similarity": pa.array([o[2] for o in out], pa.float64())})

    return dealt.groupBy("key", "x", "y").applyInArrow(run, f"a {kind}, b {kind}, similarity double")


def with_low(edges: DataFrame, low: DataFrame, n_edges: int) -> DataFrame:
    """``edges`` (v, u) with v's ``low``. Of ``low`` (v, low, n links) the nodes with a hundred-thousandth of all links, and a
    thousand at least, come as a broadcast of 200,000 rows at most: a centre's links then need not meet in one task."""
    hot = F.col("n") >= max(1000, n_edges // 100_000)
    found = edges.join(F.broadcast(low.where(hot).select("v", F.col("low").alias("hot"))), "v", "left")
    return found.where("hot is not null").select("v", "u", F.col("hot").alias("low")).unionAll(found.where("hot is null").join(low.where(~hot).select("v", "low"), "v").select("v", "u", "low"))


def components(edges: DataFrame) -> DataFrame:
    """(id, class) of every node: alternating large and small stars around the smallest neighbour until all are stars."""
    edges = common.stored(edges.where("a <> b").select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).distinct(), "edges")
    state, n_edges = None, edges.count()
    if not n_edges:
        return edges.select(F.col("v").alias("id"), F.col("u").alias("class"))
    while True:
        both = edges.select("v", "u").unionAll(edges.select(F.col("u").alias("v"), F.col("v").alias("u")))
        low = common.stored(both.groupBy("v").agg(F.least(F.min("u"), F.col("v")).alias("low"), F.count("*").alias("n")), "low")
        large = common.stored(with_low(both, low, n_edges).where("u > v").select(F.col("u").alias("v"), F.col("low").alias("u")).where("u <> v").distinct(), "large-star")
        common.discard(edges, low)
        low = common.stored(large.groupBy("v").agg(F.min("u").alias("low"), F.count("*").alias("n")), "low")
        small = with_low(large, low, n_edges).select(F.when(F.col("u") == F.col("low"), F.col("v")).otherwise(F.col("u")).alias("v"), F.col("low").alias("u")).where("u <> v").distinct()
        edges = common.stored(small, "small-star")
        common.discard(large, low)
        now = edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("v", "u").cast("decimal(38,0)")), F.lit(0))).first()
        n_edges = now[0]
        if now == state:
            return edges.select(F.col("v").alias("id"), F.col("u").alias("class"))
        state = now


def linked(bands: DataFrame, known: DataFrame, threshold: float) -> DataFrame:
    """Links (a, b) that join the texts that share a bucket: those between texts and the class their leaders put them in, and
    those between such classes. ``bands``: key, id and the leader a, the smallest id, of buckets with several texts."""
    members = bands.where("id <> a")
    pairs = common.stored(compared(members.select("a", F.col("id").alias("b")).distinct(), known, threshold), "compared")
    # A leader may be an outlier of a large family: what failed it gets a second one, the same in all buckets it can be.
    failed = members.join(pairs.where("similarity = 0").select("a", F.col("b").alias("id")), ["a", "id"]).select("key", "id")
    second = failed.groupBy("key").agg(F.min_by("id", F.xxhash64("id")).alias("a"), F.count("*").alias("n")).where("n > 1").select("key", "a")
    again = failed.join(second, "key").where("id <> a").select("a", F.col("id").alias("b")).distinct()
    more = compared(again, known, threshold).where("similarity > 0").select("a", "b")
    stars = components(pairs.where("similarity > 0").select("a", "b").unionAll(more))
    lead = stars.select(F.col("id").alias("a"), F.col("class").alias("leader_class"))
    classed = members.join(pairs.withColumnRenamed("b", "id"), ["a", "id"]).join(stars, "id", "left").join(lead, "a", "left")
    classed = common.stored(classed.select("key", "id", F.coalesce("class", "id").alias("class"), F.coalesce("leader_class", "a").alias("leader_class"), "n", "similarity", "edits"), "classed")
    left = common.stored(still_open(classed, threshold), "left")
    common.discard(classed, pairs)
    return stars.select(F.col("class").alias("a"), F.col("id").alias("b")).unionAll(compared_in_blocks(left, known, threshold).select("a", "b"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", threshold: float = 0.8) -> DataFrame:
    """One row per row of ``docs``: id and class_id, the smallest id of its class."""
    rows = common.stored(sketched(docs, id_col, text), "sketches")
    texts = common.stored(rows.groupBy("digest").agg(F.min("id").alias("rep"), F.first("keys").alias("keys")), "texts")  # equal words have equal keys
    bands = texts.select(F.col("rep").alias("id"), F.explode("keys").alias("key"))
    shared = bands.groupBy("key").agg(F.count("*").alias("n"), F.min("id").alias("a")).where("n > 1").select("key", "a")
    bands = common.stored(bands.join(shared, "key").select("key", "id", "a"), "bands")
    known = common.stored(contents(docs, bands.select("id").distinct(), id_col, text), "contents")
    classes = components(linked(bands, known, threshold))
    member = rows.select("id", "digest").distinct().join(texts.select("digest", "rep"), "digest").join(classes.withColumnRenamed("id", "rep"), "rep", "left").select("id", F.coalesce("class", "rep").alias("c"))
    member = member.groupBy("id").agg(F.min("c").alias("c"))
    every = docs.select(F.col(f"`{id_col}`"))
    return every.join(member.withColumnRenamed("id", id_col), id_col, "left").select(id_col, F.coalesce("c", id_col).alias("class_id"))


def op5_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class of every document; the document whose id is the class id is the one that stays."""
    out = near_duplicates(common.table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.withColumn("stays", F.col("doc_id") == F.col("class_id"))
