"""Benchmark decontamination: every training passage queries a BM25 index of the test items.

Index. Terms are lower-case words. An item's impact for a term is its BM25 weight divided by the item's own total, so a
passage that holds all words of an item scores 1 and one threshold serves items of all lengths. Postings run in item
order; for every term and block of ``BLOCK`` items the largest impact is kept.

Search. Each item has a width, the power of two that holds its words, 32 at least. Its passages are twice as wide and a new
one starts every width, so an item that occurs lies whole in a passage, and what it is compared with doesn't depend on
other items. The words of the whole document bound the scores of each item in all its passages: first block maxima alone,
then, in the blocks that these leave, the items. Block-max WAND then walks a passage's lists in item order, jumps over blocks
whose maxima can't reach the threshold and scores the rest. The bounds are never below the true score: everything at or
above the threshold is retrieved.

Verification. A hit counts if the passage covers, by shared word n-grams, enough of the item's question and enough of its
answer. Items without columns of their own for these are split at the last sentence. Items of under ``exact_words`` words
would pass by chance; they count where they stand whole, as a run of words, with a BM25 of 0.

Scale: the index is the only thing broadcast. Items are loaded in shards of ``shard_items`` items and ``shard_words`` words at
most (an item of more is a shard), with document frequencies over all items, and each shard is one map-only pass over the
documents: no shuffle, and hot copies cost nothing extra. The driver holds one shard at a time and the counts of the items'
words.

Defined results: null and empty texts and items match nothing; repeated rows each give their hits; ties between passages go to
the first.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from operator import itemgetter

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

WORD = re.compile(r"\w+")
BLOCK = 32
K1, B = 0.9, 0.4


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def question_answer(text: str) -> tuple[list[str], list[str]]:
    """The last sentence is the answer; where it is under 4 words or all there is, the last quarter of the words."""
    parts = [w for s in re.split(r"(?<=[.!?])\s+|\n+", text or "") if (w := words_of(s))]
    everything = [w for p in parts for w in p]
    if len(parts) > 1 and len(parts[-1]) >= 4:
        return everything[: -len(parts[-1])], parts[-1]
    cut = len(everything) - max(4, len(everything) // 4)
    return everything[:cut], everything[cut:]


def covered(part: list[str], passage: list[str]) -> float:
    """Share of the words of ``part`` inside n-grams that the passage has too: 3 words, or 2 for parts of under 12."""
    n = min(len(part), 3 if len(part) >= 12 else 2)
    if not n:
        return 1.0
    there = {tuple(passage[i : i + n]) for i in range(len(passage) - n + 1)}
    hit = [False] * len(part)
    for i in range(len(part) - n + 1):
        if tuple(part[i : i + n]) in there:
            hit[i : i + n] = [True] * n
    return sum(hit) / len(part)


@dataclass
class Index:
    """Postings by term id: items ``items[starts[t]:starts[t + 1]]`` with their impacts. Runs of a term's items in one block:
    ``run_starts`` by term, the block, largest impact and first posting of each. ``short``: items sought whole, by their words."""

    item_ids: list[int]
    parts: list[tuple[list[str], list[str]]]
    widths: np.ndarray
    selves: list[float]
    terms: dict[str, int]
    starts: np.ndarray
    items: np.ndarray
    impacts: np.ndarray
    run_starts: np.ndarray
    run_block: np.ndarray
    run_most: np.ndarray
    run_first: np.ndarray
    short: dict[tuple[str, ...], list[int]]

    def live(self, ids: np.ndarray, floor: float) -> tuple[np.ndarray, np.ndarray]:
        """Items that may reach ``floor`` with these distinct terms, and the places of their postings."""
        runs = spread(self.run_starts[ids], self.run_starts[ids + 1])
        blocks = np.bincount(self.run_block[runs], self.run_most[runs], minlength=-(-len(self.item_ids) // BLOCK)) >= floor
        runs = runs[blocks[self.run_block[runs]]]
        at = spread(self.run_first[runs], self.run_first[runs + 1])
        items = np.bincount(self.items[at], self.impacts[at], minlength=len(self.item_ids)) >= floor
        return np.flatnonzero(items), at[items[self.items[at]]]

    def lists(self, at: np.ndarray) -> dict[int, Postings]:
        """Posting lists of the given postings, by term."""
        out: dict[int, Postings] = {}
        for t, i, v in zip((np.searchsorted(self.starts, at, "right") - 1).tolist(), self.items[at].tolist(), self.impacts[at].tolist(), strict=True):
            if t not in out:
                out[t] = Postings([], [], {}, 0.0)
            p = out[t]
            p.items.append(i)
            p.impacts.append(v)
            p.maxima[i // BLOCK] = max(v, p.maxima.get(i // BLOCK, 0.0))
            p.maximum = max(v, p.maximum)
        return out


def spread(starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """All places of some ranges, one range after the other."""
    n = ends - starts
    return np.repeat(starts - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum()) if len(n) else np.empty(0, np.int64)


@dataclass
class Postings:
    """One term's items in order, their impacts, the largest in each block and of all."""

    items: list[int]
    impacts: list[float]
    maxima: dict[int, float]
    maximum: float


def build(items: list[tuple[int, list[str], list[str]]], totals: Totals, exact_words: int) -> Index:
    """``items``: (id, question words, answer words). Items of a width stand side by side."""
    short: dict[tuple[str, ...], list[int]] = {}
    for i, q, a in items:
        if len(q) + len(a) < exact_words:
            short.setdefault((*q, *a), []).append(i)
    width = lambda q, a: max(32, 1 << (len(q) + len(a) - 1).bit_length())
    items = sorted((x for x in items if len(x[1]) + len(x[2]) >= exact_words), key=lambda x: width(x[1], x[2]))
    terms: dict[str, int] = {}
    rows, selves = [], []
    for i, (_, question, answer) in enumerate(items):
        words = question + answer
        norm = K1 * (1 - B + B * len(words) / totals.mean_words)
        weights = {w: math.log(1 + (totals.items - totals.frequency[w] + 0.5) / (totals.frequency[w] + 0.5)) * tf * (K1 + 1) / (tf + norm) for w, tf in Counter(words).items()}
        own = sum(weights.values())
        selves.append(own)
        rows += [(terms.setdefault(w, len(terms)), i, v / own) for w, v in weights.items()]
    rows.sort()
    term, item = (np.array([r[k] for r in rows], np.int64) for k in (0, 1))
    value = np.array([r[2] for r in rows], float)
    every = np.arange(len(terms) + 1)
    first = np.flatnonzero(np.r_[True, (term[1:] != term[:-1]) | (item[1:] // BLOCK != item[:-1] // BLOCK)]) if len(term) else np.empty(0, np.int64)
    return Index(
        [i for i, _, _ in items], [(q, a) for _, q, a in items], np.array([width(q, a) for _, q, a in items], np.int64), selves,
        terms, np.searchsorted(term, every), item, value,
        np.searchsorted(term[first], every), item[first] // BLOCK, np.maximum.reduceat(value, first) if len(first) else value, np.r_[first, len(term)], short,
    )


@dataclass
class Totals:
    """Of all items that BM25 scores: in how many each word stands, their number and that of their words."""

    frequency: Counter
    items: int = 0
    words: int = 0

    @property
    def mean_words(self) -> float:
        return self.words / max(1, self.items)


EPS = 1e-9
NEVER = 1 << 60
ITEM = itemgetter(2)


def block_max_wand(postings: list[Postings], threshold: float) -> list[tuple[int, float]]:
    """All (item number, score) of at least the threshold, in item order."""
    lists = [[p, 0, p.items[0]] for p in postings]  # with the place reached and the item there
    found, floor = [], threshold - EPS
    while lists:
        lists.sort(key=ITEM)
        total, pivot = 0.0, None
        for p, _, item in lists:  # the first item that could reach the threshold if each list gave its maximum
            total += p.maximum
            if total >= floor:
                pivot = item
                break
        if pivot is None:
            break
        before = [x for x in lists if x[2] <= pivot]
        block = pivot // BLOCK
        if sum(p.maxima.get(block, 0.0) for p, _, _ in before) < floor:
            # Up to the block's end or the next list's item only these lists have items, under these maxima.
            target = min((block + 1) * BLOCK, lists[len(before)][2] if len(before) < len(lists) else NEVER)
        elif before[0][2] == pivot:
            score = sum(p.impacts[at] for p, at, _ in before)
            if score >= floor:
                found.append((pivot, score))
            target = pivot + 1
        else:
            target = pivot
        for x in before:
            p, at = x[0], bisect_left(x[0].items, target, x[1])
            x[1], x[2] = at, p.items[at] if at < len(p.items) else NEVER
        lists = [x for x in lists if x[2] < NEVER]
    return found


def hits(index: Index, text: str, threshold: float, overlap: float) -> list[tuple]:
    """Verified (item id, first word of the passage, BM25, share of the item's own score, question and answer overlap): the best passage of each item."""
    words = words_of(text)
    get = index.terms.get
    ids = np.array([get(w, -1) for w in words], np.int64)
    known = np.unique(ids[ids >= 0])
    best: dict[int, tuple] = {}
    live, at = index.live(known, threshold - EPS) if len(known) else ([], [])
    for width in np.unique(index.widths[live]).tolist() if len(live) else []:
        lists = index.lists(at[index.widths[index.items[at]] == width])
        for start in range(0, max(1, len(words) - width), width):
            some = [p for t in set(ids[start : start + 2 * width].tolist()) if (p := lists.get(t))]
            if sum(p.maximum for p in some) < threshold - EPS:
                continue
            passage = words[start : start + 2 * width]
            for i, score in block_max_wand(some, threshold):
                q, a = (covered(p, passage) for p in index.parts[i])
                if q >= overlap and a >= overlap and (i not in best or score > best[i][3] + EPS):
                    best[i] = (index.item_ids[i], start, score * index.selves[i], score, q, a)
    return [best[i] for i in sorted(best)] + whole(index.short, words)


def whole(short: dict[tuple[str, ...], list[int]], words: list[str]) -> list[tuple]:
    """Hits of the items that stand in the text as a run of words, each where it stands first."""
    found: dict[tuple[str, ...], int] = {}
    for n in sorted({len(k) for k in short} - {0}):
        for start in range(len(words) - n + 1):
            run = tuple(words[start : start + n])
            if run in short:
                found.setdefault(run, start)
    return [(i, start, 0.0, 1.0, 1.0, 1.0) for run, start in found.items() for i in short[run]]


def find_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text: str = "text", threshold: float = 0.6, overlap: float = 0.6, exact_words: int = 6, shard_items: int = 50_000, shard_words: int = 500_000) -> DataFrame:
    """One row per document and benchmark item it leaks. ``benchmark``: item_id and text, or item_id, question and answer."""
    spark = docs.sparkSession
    own = {"question", "answer"} <= set(benchmark.columns)
    columns = ["question", "answer"] if own else ["text"]
    wanted = benchmark.where(F.col("item_id").isNotNull()).select("item_id", *columns).orderBy("item_id", *columns)

    def items() -> Iterator[tuple[int, list[str], list[str]]]:
        for r in wanted.toLocalIterator():  # the benchmark, not the corpus
            q, a = (words_of(r["question"]), words_of(r["answer"])) if own else question_answer(r["text"])
            if q or a:
                yield r["item_id"], q, a

    def shards() -> Iterator[list[tuple[int, list[str], list[str]]]]:
        held, n = [], 0
        for x in items():
            more = len(x[1]) + len(x[2])
            if held and (len(held) >= shard_items or n + more > shard_words):
                yield held
                held, n = [], 0
            held.append(x)
            n += more
        if held:
            yield held

    totals = Totals(Counter())
    for _, q, a in items():
        if len(q) + len(a) >= exact_words:
            totals.frequency.update({*q, *a})
            totals.items, totals.words = totals.items + 1, totals.words + len(q) + len(a)
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), *(T.StructField(n, t) for n, t in (("item_id", T.LongType()), ("first_word", T.LongType()), ("bm25", T.DoubleType()), ("share", T.DoubleType()), ("question_overlap", T.DoubleType()), ("answer_overlap", T.DoubleType())))])
    source = docs.select(F.col(f"`{id_col}`"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("__text"))

    def search(index: Broadcast) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part in common.pieces(batches, 1):
                rows = [(i, h) for i, t in zip(part.column(0).to_pylist(), common.texts_of(part.column(1)), strict=True) for h in hits(index.value, t, threshold, overlap)]
                columns = [[i for i, _ in rows], *([h[k] for _, h in rows] for k in range(6))]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (part.column(0).type, pa.int64(), pa.int64(), *[pa.float64()] * 4), strict=True)], names=schema.fieldNames())

        return source.mapInArrow(run, schema)

    out, rest = spark.createDataFrame([], schema), shards()
    shard, following = next(rest, None), next(rest, None)
    if shard and not following:
        return search(spark.sparkContext.broadcast(build(shard, totals, exact_words)))
    while shard:  # one shard after the other: each is written, and then forgotten
        index = spark.sparkContext.broadcast(build(shard, totals, exact_words))
        out = out.unionAll(common.stored(search(index), "leaks"))
        index.destroy()
        shard, following = following, next(rest, None)
    return out


def op6_bm25_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Leaked benchmark items of every document."""
    return find_leaks(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))
