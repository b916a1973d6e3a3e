"""Language-model scores by class-based n-grams.

Every word has a class; a token then costs

    P(class | class before) * P(word | class)

where transitions back off to class frequencies in proportion to how many different classes follow (Witten-Bell), and words
have ``ADD`` added to their counts. Words never seen have the class of their ending, which keeps one place for them. The
probabilities of all words, the end of a text and an unseen word of each ending sum to 1 in every context, so scores
compare with the base, an add-half unigram model.

Classes by exchange, in two steps. First *units* are exchanged on the driver: the ``top_words`` most frequent words, the
``endings`` most frequent last three bytes of other words, one unit of the rest and the end of a text. From a start by
frequency, each in turn goes to the class that raises the likelihood of the class bigrams most, until a sweep moves
nothing. Then, on the executors and side by side, every other training word leaves the class of its ending for the one
that its own neighbours make best, by the same likelihood, if that gains more than naming a class costs (``margin``, by
default the logarithm of their number). So each word has the class of its own counts as soon as these say enough, however
large the vocabulary; the numbers of units only bound what the driver does.

Scale. Counts of all words, and of the units beside each, come from one pass each, combined before the shuffle; they live in
shared tables and grow with the corpus. Workers hold the ``head_words`` most frequent words only (counted over all rows, so a
word that is hot anywhere is in the head); all rarer words of a text meet their counts and classes in a join that no key can
dominate. From then on a text is a byte a token, its classes; class bigrams are counted from those.

Defined results: null and empty texts are one end token; bytes decide, A-Z are lower-cased and only ASCII white space
separates; rows that repeat an id keep their rows; null ids train; with no training rows counts are 0 and every token is an
end or unseen.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

ADD = 0.5
END, REST = 0, 1  # units
TAIL = 255  # in a path: a word whose class is not known yet
SMALL = 16  # counts up to which gains are looked up


def xlogx(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1e-300))


def exchange(pairs: np.ndarray, classes: int, sweeps: int = 12) -> np.ndarray:
    """Class of each unit. ``pairs[u, v]``: how often v follows u. Units without any count stay where they start."""
    n = len(pairs)
    weight = pairs.sum(0) + pairs.sum(1)
    order = np.argsort(-weight, kind="stable")
    cls = np.empty(n, int)
    cls[order] = np.arange(n) % classes
    one = np.eye(classes)[cls]
    table = one.T @ pairs @ one
    for _ in range(sweeps):
        moved = 0
        for u in order:
            if not weight[u]:
                break
            a, own = cls[u], pairs[u, u]
            out = np.bincount(cls, pairs[u], classes)
            into = np.bincount(cls, pairs[:, u], classes)
            out[a] -= own
            into[a] -= own
            table[a] -= out
            table[:, a] -= into
            table[a, a] -= own
            rows, cols = table.sum(1), table.sum(0)
            s, p = out.sum() + own, into.sum() + own
            gain = (xlogx(table + out) - xlogx(table)).sum(1) + (xlogx(table.T + into) - xlogx(table.T)).sum(1)
            d = np.diagonal(table)  # the cell of b with itself gets all three parts at once
            gain += xlogx(d + out + into + own) - xlogx(d + out) - xlogx(d + into) + xlogx(d)
            gain -= xlogx(rows + s) - xlogx(rows) + xlogx(cols + p) - xlogx(cols)
            b = int(gain.argmax())
            if gain[b] <= gain[a] + 1e-9:
                b = a
            table[b] += out
            table[:, b] += into
            table[b, b] += own
            moved += b != a
            cls[u] = b
        if not moved:
            break
    return cls


@dataclass
class Contexts:
    """Where a word with known neighbours belongs. ``table``: class bigrams; ``cls``: class of each unit; ``homes``: unit of each
    ending; ``margin``: what a word must gain to leave the class of its ending."""

    table: np.ndarray
    cls: np.ndarray
    homes: dict[bytes, int]
    margin: float

    def home(self, word: bytes) -> int:
        return int(self.cls[self.homes.get(word[-3:], REST)])

    def gains(self, side: int, cell: np.ndarray, n: np.ndarray) -> np.ndarray:
        """What n neighbours of a class, before (side 0) or after a word, add to the likelihood for each class it may join."""
        known = (self.table if side == 0 else self.table.T)[cell]
        return xlogx(known + n[:, None]) - xlogx(known)

    def best(self, word: np.ndarray, code: np.ndarray, n: np.ndarray, homes: np.ndarray) -> np.ndarray:
        """Class of each word, ``homes`` being those of their endings, from entries (word, side * units + unit, count), sorted by word."""
        classes, units, words = len(self.table), len(self.cls), len(homes)
        key, at = np.unique((word * 2 + code // units) * classes + self.cls[code % units], return_inverse=True)
        n = np.bincount(at, n)
        word, side, cell = key // classes // 2, key // classes % 2, key % classes
        small = np.stack([np.stack([self.gains(s, np.arange(classes), np.full(classes, k)) for k in range(SMALL + 1)]) for s in (0, 1)])
        gain = np.zeros((words, classes))
        starts = np.searchsorted(word, np.arange(words + 1))
        for lo in range(0, words, 10_000):
            hi = min(words, lo + 10_000)
            own = slice(starts[lo], starts[hi])
            part = small[side[own], np.minimum(n[own], SMALL).astype(np.int64), cell[own]]
            for s in (0, 1):
                large = np.flatnonzero((n[own] > SMALL) & (side[own] == s))
                part[large] = self.gains(s, cell[own][large], n[own][large])
            gain[lo:hi] = np.add.reduceat(part, starts[lo:hi] - starts[lo])
        for s, total in ((0, self.table.sum(0)), (1, self.table.sum(1))):  # as a follower, and as one that is followed
            mass, which = np.unique(np.bincount(word[side == s], n[side == s], words), return_inverse=True)
            gain -= (xlogx(total + mass[:, None]) - xlogx(total))[which]
        found, every = gain.argmax(1), np.arange(words)
        return np.where(gain[every, found] > gain[every, homes] + self.margin, found, homes)


@dataclass
class ClassModel:
    """log10 of ``step[c, d]``, from class to class, and ``room[c]``, what a class's words share: a word's factor is
    (count + ADD) / room of its class."""

    step: np.ndarray
    room: np.ndarray

    @staticmethod
    def of(table: np.ndarray, room: np.ndarray) -> ClassModel:
        """``table``: class bigrams of training texts; ``room``: of each class, its words' counts and ADD for each place."""
        follow = np.maximum((table > 0).sum(1), 1)[:, None]
        step = (table + follow * room / room.sum()) / (table.sum(1)[:, None] + follow)
        return ClassModel(np.log10(np.maximum(step, 1e-300)), np.log10(np.maximum(room, 1e-300)))


def tokens(text: str) -> list[bytes]:
    return text.encode().lower().split()


def word_counts(docs: DataFrame, train: str, text: str, flush: int = 300_000) -> DataFrame:
    """word (bytes), n in training rows, m in other rows; the end of texts is the null word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: tuple[Counter, Counter] = (Counter(), Counter())
        ends = [0, 0]

        def emptied(last: bool) -> pa.RecordBatch:
            words = list(counts[0].keys() | counts[1].keys())
            n, m = (list(map(c.get, words, repeat(0))) for c in counts)
            for c in counts:
                c.clear()
            extra = [None] if last else []
            return pa.RecordBatch.from_arrays([pa.array(words + extra, pa.binary()), pa.array(n + ends[:1] * last, pa.int64()), pa.array(m + ends[1:] * last, pa.int64())], names=["word", "n", "m"])

        for part in common.pieces(batches, 0):
            for t, learns in zip(common.texts_of(part.column(0)), part.column(1).to_pylist(), strict=True):
                counts[not learns].update(tokens(t))
                ends[not learns] += 1
            if len(counts[0]) + len(counts[1]) > flush:
                yield emptied(False)
        yield emptied(True)

    return docs.select(text, train).mapInArrow(run, "word binary, n bigint, m bigint").groupBy("word").agg(F.sum("n").alias("n"), F.sum("m").alias("m"))


class Local(dict):
    """Number of each word of a worker: its unit, or, from ``n_units`` on, the order in which it came; ``rest`` lists the latter."""

    def __init__(self, units: dict[bytes, int], n_units: int) -> None:
        super().__init__(units)
        self.n_units, self.rest = n_units, []

    def __missing__(self, word: bytes) -> int:
        self[word] = out = self.n_units + len(self.rest)
        self.rest.append(word)
        return out


def beside(docs: DataFrame, train: str, text: str, units: dict[bytes, int], endings: dict[bytes, int], flush: int = 400_000, most: int = 6_000_000) -> DataFrame:
    """What stands side by side in training rows. Rows with a null word: (u * units + v, how often unit v follows u). Others: of each
    word that is no unit of its own, (unit before) and (units + unit after) with their counts."""
    spark, n_units = docs.sparkSession, 2 + len(units) + len(endings)
    held_units = spark.sparkContext.broadcast((units, endings))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, ends = held_units.value
        local = Local(known, n_units)
        pairs = np.zeros(n_units * n_units, np.int64)
        near: list[np.ndarray] = []

        def lists(words: list[bytes | None], starts: np.ndarray, code: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
            at = pa.array(starts, pa.int32())
            return pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), *(pa.ListArray.from_arrays(at, pa.array(x.astype(np.int32), pa.int32())) for x in (code, n))], names=["word", "codes", "ns"])

        def emptied() -> Iterator[pa.RecordBatch]:
            if near:
                key, n = np.unique(np.concatenate(near), return_counts=True)
                owner, code = key // (2 * n_units), key % (2 * n_units)
                for lo in range(0, len(local.rest), 50_000):
                    some = local.rest[lo : lo + 50_000]
                    starts = np.searchsorted(owner, np.arange(lo, lo + len(some) + 1))
                    yield lists(some, starts - starts[0], code[starts[0] : starts[-1]], n[starts[0] : starts[-1]])
            near.clear()

        homes: list[int] = []  # unit of each word of local.rest
        for part in common.pieces(batches, 0):
            flat = [END]
            for t in common.texts_of(part.column(0)):
                flat += map(local.__getitem__, tokens(t))
                flat.append(END)
            homes += [ends.get(w[-3:], REST) for w in local.rest[len(homes) :]]
            codes = np.array(flat, np.int64)
            unit = np.r_[np.arange(n_units), np.array(homes, np.int64)][codes]
            pairs += np.bincount(unit[:-1] * n_units + unit[1:], minlength=len(pairs))
            at = np.flatnonzero(codes >= n_units)
            owner = (codes[at] - n_units) * (2 * n_units)
            near += [owner + unit[at - 1], owner + n_units + unit[at + 1]]
            if len(local.rest) > flush or sum(map(len, near)) > most:
                yield from emptied()
                local, homes = Local(known, n_units), []
        yield from emptied()
        code = np.flatnonzero(pairs)
        for lo in range(0, len(code), 100_000):
            some = code[lo : lo + 100_000]
            yield lists([None], np.array([0, len(some)]), some, pairs[some])

    return docs.where(train).select(text).mapInArrow(run, "word binary, codes array<int>, ns array<int>")


def assigned(near: DataFrame, contexts: Contexts) -> DataFrame:
    """word and class of every word of ``near`` (word, codes, ns). A word's rows meet in one task, as one from each task before."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def classes_of(t: pa.RecordBatch) -> pa.RecordBatch:
            word = t.column(0)
            new = np.r_[True, pc.not_equal(word.slice(1), word.slice(0, len(word) - 1)).to_numpy(zero_copy_only=False)]
            lengths = t.column(1).value_lengths().to_numpy()
            entry = np.repeat(np.cumsum(new) - 1, lengths)
            words = word.filter(pa.array(new))
            homes = np.array([contexts.home(w) for w in words.to_pylist()])
            best = contexts.best(entry, t.column(1).flatten().to_numpy().astype(np.int64), t.column(2).flatten().to_numpy().astype(float), homes)
            return pa.RecordBatch.from_arrays([words, pa.array(best, pa.int32())], names=["word", "class"])

        rest = None
        for batch in batches:
            for at in range(0, batch.num_rows, 20_000):
                t = batch.slice(at, 20_000)
                t = t if rest is None else pa.concat_batches([rest, t])
                word = t.column(0)
                same = pc.equal(word, word[-1]).to_numpy(zero_copy_only=False)
                done = len(same) - int(same.sum())  # rows come sorted: those of the last word may go on in the next batch
                if done:
                    yield classes_of(t.slice(0, done))
                rest = t.slice(done)
        if rest is not None:
            yield classes_of(rest)

    return near.repartition("word").sortWithinPartitions("word").mapInArrow(run, "word binary, class int")


@dataclass
class Lexicon:
    """What workers hold: place of each head word, and by place its class and the log10 of its factors; ``end``: the same of the end."""

    places: dict[bytes, int]
    cls: np.ndarray
    known: np.ndarray
    log_word: np.ndarray
    log_base: np.ndarray
    end: tuple[int, bool, float, float]


@dataclass
class Fitted:
    """``words``: word, n, m, class of all words, those not in training rows with the class of their ending; ``homes``: class of
    each ending, None for the others; ``room``: what a class's words share; what scoring needs besides."""

    words: DataFrame
    total: int
    distinct: int
    ends: int
    end_class: int
    homes: dict[bytes | None, int]
    room: np.ndarray
    floor: int

    def base(self, n):  # noqa: ANN001, ANN201
        """Of a count (or array, or column): its share in the base model."""
        return (n + ADD) / (self.total + ADD * (self.distinct + 1))


def fit(source: DataFrame, head_words: int, top_words: int, endings: int, classes: int, margin: float | None = None) -> Fitted:
    """``source``: text and train. Counts, classes and rooms."""
    spark = source.sparkSession
    counts = common.stored(word_counts(source, "train", "text"), "word-counts")
    words = counts.where(F.col("word").isNotNull())
    total, distinct, ends = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count_if(F.col("n") > 0), F.coalesce(F.sum(F.when(F.col("word").isNull(), F.col("n"))), F.lit(0))).first()
    # The head: all words above the count that at most head_words words exceed.
    floor, seen = 0, 0
    for r in words.groupBy((F.col("n") + F.col("m")).alias("c")).count().orderBy(F.desc("c")).limit(head_words + 1).collect():
        seen += r["count"]
        if seen > head_words:
            floor = r["c"]
            break
    ending = F.unhex(F.expr("right(hex(word), 6)"))
    top = [bytes(r["word"]) for r in words.where("n > 0").orderBy(F.desc("n"), "word").limit(top_words).select("word").collect()]
    units = {w: 2 + i for i, w in enumerate(top)}
    others = words.where("n > 0").join(spark.createDataFrame([(w,) for w in top], "word binary"), "word", "left_anti")
    last = [bytes(r["ending"]) for r in others.groupBy(ending.alias("ending")).agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "ending").limit(endings).select("ending").collect()]
    ending_units = {e: 2 + len(top) + i for i, e in enumerate(last)}
    n_units = 2 + len(top) + len(last)
    found = common.stored(beside(source, "train", "text", units, ending_units), "beside")
    pairs = np.zeros(n_units * n_units)
    rows = found.where(F.col("word").isNull()).select(F.explode(F.arrays_zip("codes", "ns")).alias("p")).groupBy("p.codes").agg(F.sum("p.ns").alias("n")).toArrow()
    pairs[rows["codes"].to_numpy()] = rows["n"].to_numpy()
    pairs = pairs.reshape(n_units, n_units)
    cls = exchange(pairs, classes)
    one = np.eye(classes)[cls]
    contexts = Contexts(one.T @ pairs @ one, cls, ending_units, math.log(classes) if margin is None else margin)
    near = assigned(found.where(F.col("word").isNotNull()), contexts)
    own = spark.createDataFrame([(w, int(cls[u])) for w, u in units.items()], "word binary, class int")
    homes: dict[bytes | None, int] = {e: int(cls[u]) for e, u in ending_units.items()} | {None: int(cls[REST])}
    by_ending = spark.createDataFrame([(e, c) for e, c in homes.items() if e is not None], "ending binary, home int")  # at most ``endings`` rows
    both = words.join(near.unionAll(own), "word", "left").withColumn("ending", ending).join(F.broadcast(by_ending), "ending", "left")
    both = common.stored(both.select("word", "n", "m", F.coalesce("class", "home", F.lit(homes[None])).alias("class")), "classed-words")
    common.discard(found, counts)
    room = np.zeros(classes)
    for r in both.where("n > 0").groupBy("class").agg(F.sum("n").alias("n"), F.count("*").alias("k")).collect():
        room[r["class"]] = r["n"] + ADD * r["k"]
    room[cls[END]] += ends + ADD
    for c in homes.values():
        room[c] += ADD
    return Fitted(both, total, distinct, ends, int(cls[END]), homes, room, floor)


def lexicon_of(model: Fitted) -> Lexicon:
    """The head words with all that a token of theirs costs, but for its step."""
    rows = model.words.where(F.col("n") + F.col("m") > model.floor).select("word", "n", "class").toArrow()
    n, cls = rows["n"].to_numpy().astype(float), rows["class"].to_numpy().astype(np.uint8)
    end = (model.end_class, model.ends > 0, math.log10((model.ends + ADD) / model.room[model.end_class]), math.log10(model.base(model.ends)))
    return Lexicon(dict(zip(rows["word"].to_pylist(), range(len(n)), strict=True)), cls, n > 0, np.log10((n + ADD) / model.room[cls]), np.log10(model.base(n)), end)


def paths(source: DataFrame, model: Fitted) -> DataFrame:
    """id, train, n_tokens, n_known, base, words (log10 of all words in their classes) and path (a byte a token, its class) of every row."""
    spark = source.sparkSession
    lexicon = spark.sparkContext.broadcast(lexicon_of(model))
    kind = source.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lex = lexicon.value
        get = lex.places.get
        end_class, end_known, end_word, end_base = lex.end
        for part in common.pieces(batches, 1):
            out: list[tuple] = []
            for t in common.texts_of(part.column(1)):
                own = tokens(t)
                places = np.fromiter(map(get, own, repeat(-1)), np.int64, len(own))
                there = places >= 0
                at = places[there]
                path = np.full(len(own) + 1, TAIL, np.uint8)
                path[:-1][there] = lex.cls[at]
                path[-1] = end_class
                out.append((len(own) + 1, int(lex.known[at].sum()) + end_known, float(lex.log_base[at].sum()) + end_base, float(lex.log_word[at].sum()) + end_word, path.tobytes(), [own[i] for i in np.flatnonzero(~there).tolist()]))
            kinds = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary(), pa.list_(pa.binary()))
            columns = [pa.array([o[i] for o in out], k) for i, k in enumerate(kinds)]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), *columns], names=["id", "train", "n_tokens", "n_known", "base", "words", "path", "tail"])

    head = source.select("id", "text", "train").mapInArrow(run, f"id {kind}, train boolean, n_tokens bigint, n_known bigint, base double, words double, path binary, tail array<binary>")
    head = common.stored(head.withColumn("row", F.monotonically_increasing_id()), "head-paths")
    rare = model.words.where(F.col("n") + F.col("m") <= model.floor).select("word", F.col("n").alias("c"), "class")
    rooms = F.array(*(F.lit(float(x)) for x in model.room))
    met = head.select("row", F.posexplode("tail").alias("at", "word")).join(rare, "word")
    sums = met.groupBy("row").agg(
        F.count_if(F.col("c") > 0).alias("t_known"),
        F.sum(F.log10(model.base(F.col("c")))).alias("t_base"),
        F.sum(F.log10((F.col("c") + ADD) / rooms[F.col("class")])).alias("t_words"),
        F.array_sort(F.collect_list(F.col("at").cast("long") * 256 + F.col("class"))).alias("fill"),
    )
    zero = F.lit(0.0)
    whole = head.join(sums, "row", "left").select("id", "train", "n_tokens", (F.col("n_known") + F.coalesce("t_known", F.lit(0))).alias("n_known"), (F.col("base") + F.coalesce("t_base", zero)).alias("base"), (F.col("words") + F.coalesce("t_words", zero)).alias("words"), "path", "fill")

    def filled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for path, fill in zip(b.column(6).to_pylist(), b.column(7).to_pylist(), strict=True):
                if fill:
                    own = np.frombuffer(path, np.uint8).copy()
                    own[own == TAIL] = np.array(fill) & 255  # places and classes, in the places' order
                    path = own.tobytes()
                out.append(path)
            yield pa.RecordBatch.from_arrays([*b.columns[:6], pa.array(out, pa.binary())], names=["id", "train", "n_tokens", "n_known", "base", "words", "path"])

    out = common.stored(whole.mapInArrow(filled, f"id {kind}, train boolean, n_tokens bigint, n_known bigint, base double, words double, path binary"), "paths")
    common.discard(head)
    return out


def class_bigrams(texts: DataFrame, classes: int, end_class: int) -> np.ndarray:
    """How often each class follows each other one in training rows; texts begin after an end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = np.zeros(classes * classes, np.int64)
        for b in batches:
            for path in b.column(0).to_pylist():
                own = np.frombuffer(path, np.uint8).astype(np.int64)
                table += np.bincount(np.r_[end_class, own[:-1]] * classes + own, minlength=len(table))
        there = np.flatnonzero(table)
        yield pa.RecordBatch.from_arrays([pa.array(there), pa.array(table[there])], names=["code", "n"])

    rows = texts.where("train").select("path").mapInArrow(run, "code bigint, n bigint").groupBy("code").agg(F.sum("n").alias("n")).toArrow()
    table = np.zeros(classes * classes)
    table[rows["code"].to_numpy()] = rows["n"].to_numpy()
    return table.reshape(classes, classes)


def score_texts(docs: DataFrame, train: str, id_col: str = "doc_id", text: str = "text", head_words: int = 200_000, top_words: int = 1022, endings: int = 512, classes: int = 96) -> DataFrame:
    """id, n_tokens, n_known, train_tokens, base_score and score (log10) of every row. ``train``: boolean column of ``docs``."""
    if classes >= TAIL:
        raise ValueError(f"a path holds at most {TAIL - 1} classes")
    source = docs.select(F.col(f"`{id_col}`").alias("id"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text"), F.col(f"`{train}`").alias("train"))
    return scored(source, fit(source, head_words, top_words, endings, classes)).withColumnRenamed("id", id_col)


def scored(source: DataFrame, fitted: Fitted) -> DataFrame:
    """Scores of ``source`` (id, text, train) by the model, its class bigrams taken from the training rows."""
    texts = paths(source, fitted)
    kind = source.schema["id"].dataType.simpleString()
    model, start = ClassModel.of(class_bigrams(texts, len(fitted.room), fitted.end_class), fitted.room), fitted.end_class

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            steps = []
            for path in b.column(5).to_pylist():
                own = np.frombuffer(path, np.uint8)
                steps.append(float(model.step[np.r_[start, own[:-1]], own].sum()))
            score = pc.add(b.column(4), pa.array(steps, pa.float64()))
            yield pa.RecordBatch.from_arrays([*b.columns[:3], b.column(3), score], names=["id", "n_tokens", "n_known", "base_score", "score"])

    out = texts.select("id", "n_tokens", "n_known", "base", "words", "path").mapInArrow(run, f"id {kind}, n_tokens bigint, n_known bigint, base_score double, score double")
    return out.select("id", "n_tokens", "n_known", F.lit(fitted.total).cast("long").alias("train_tokens"), "base_score", "score")


def op4_class_ngrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of every document by a model of those whose crc32(doc_id) mod 5 isn't 1."""
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    held = F.coalesce(common.bucket_of("doc_id", 5) == 1, F.lit(False))
    out = score_texts(docs.withColumn("train", ~held), "train")
    return out.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score", (-F.col("score") / F.col("n_tokens")).alias("log10_perplexity"))
