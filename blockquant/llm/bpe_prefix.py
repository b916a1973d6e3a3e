"""BPE encoding by dynamic programming over prefixes, and decoding.

For merge-ordered vocabularies the BPE encoding of a prefix ends in one token only, and what stands before that token is
the encoding of a shorter prefix. So one pass over a word stores the last token of every prefix:

* an automaton of all substrings of the vocabulary (a suffix automaton) reads the word and names, at each position, every
  token that ends there;
* such a token is the last one exactly if it encodes to itself and it and the last token of the prefix before it are
  *compatible*: while both grow through their merges, no merge ever joins what touches at their boundary.

The ids are read off by going back from the end. Words repeat, so a bounded memo keeps the ids of white-space chunks.

Defined results: null and empty texts have no ids; texts of any length are encoded whole; special strings inside texts
become their special token, as the tokenizers library does by default; columns of the input that clash with the
outputs are replaced.
"""

from __future__ import annotations

import json
import re
from array import array
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from tokenizers import Tokenizer

from . import common

NEVER = 1 << 60
#: Control characters that str.split() takes for white space and the vocabulary's pattern does not.
UNLIKE_SPACE = re.compile("[\x1c-\x1f]")
#: Fixed value: the word pattern of the vocabulary file that ``LATIN_WORDS`` stands for.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Words of chunks whose letters all lie in Latin-1, in lower case: there every Unicode version agrees with the vocabulary's pattern.
LATIN_WORDS = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-z\xaa\xb5\xba\xdf-\xf6\xf8-\xff]+|[0-9\xb2\xb3\xb9\xbc-\xbe]|[^\\sa-z0-9\xaa\xb2\xb3\xb5\xb9\xba\xbc-\xbe\xdf-\xf6\xf8-\xff]+")
BEYOND_LATIN = re.compile("[^\x21-\x7e\xa1-\xff]")
SPACES = re.compile("[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+")


def byte_letters() -> list[str]:
    """The printable letter of each byte in byte-level vocabularies: printable Latin-1 stands for itself, the rest from 256 on."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b if b in own else next(rest)) for b in range(256)]


class SubstringAutomaton:
    """Suffix automaton of a set of symbol sequences, built one sequence at a time."""

    def __init__(self) -> None:
        self.moves: list[dict[int, int]] = [{}]
        self.link, self.length, self.token = [-1], [0], [-1]

    def _state(self, moves: dict[int, int], link: int, length: int) -> int:
        self.moves.append(moves)
        self.link.append(link)
        self.length.append(length)
        self.token.append(-1)
        return len(self.moves) - 1

    def _split(self, state: int, via: int, symbol: int) -> int:
        """Take the strings of at most ``via``'s length + 1 out of ``state`` into a state of their own."""
        copy = self._state(dict(self.moves[state]), self.link[state], self.length[via] + 1)
        self.link[state] = copy
        while via >= 0 and self.moves[via].get(symbol) == state:
            self.moves[via][symbol] = copy
            via = self.link[via]
        return copy

    def _step(self, last: int, symbol: int) -> int:
        known = self.moves[last].get(symbol)
        if known is not None:
            return known if self.length[known] == self.length[last] + 1 else self._split(known, last, symbol)
        new, at = self._state({}, 0, self.length[last] + 1), last
        while at >= 0 and symbol not in self.moves[at]:
            self.moves[at][symbol] = new
            at = self.link[at]
        if at >= 0:
            to = self.moves[at][symbol]
            self.link[new] = to if self.length[to] == self.length[at] + 1 else self._split(to, at, symbol)
        return new

    def add(self, symbols: list[int], token: int) -> None:
        state = 0
        for s in symbols:
            state = self._step(state, s)
        self.token[state] = token

    def close(self) -> None:
        """``ending``: for each state the nearest state on its suffix links, itself included, whose string is a token."""
        order = sorted(range(len(self.moves)), key=self.length.__getitem__)
        self.ending = [-1] * len(order)
        for s in order[1:]:
            self.ending[s] = s if self.token[s] >= 0 else self.ending[self.link[s]]


class PrefixBpe:
    """Exact ids of a word-level byte BPE vocabulary with word-end marks (lower case, white space dropped)."""

    def __init__(self, path: str, memo_words: int = 220_000) -> None:
        spec = json.load(open(path, encoding="utf-8"))
        model, split = spec["model"], ((spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0]
        steps = [n["type"] for n in (spec.get("normalizer") or {}).get("normalizers", [])]
        if steps != ["NFC", "Replace", "Lowercase"] or not split.get("invert") or split["behavior"] != "Removed" or not model["end_of_word_suffix"]:
            raise ValueError(f"{path} is not a lower-case word vocabulary with word ends")
        rules = Tokenizer.from_file(path)  # for its normaliser and word pattern, whose Unicode tables are its own
        self.normal, self.words = rules.normalizer.normalize_str, rules.pre_tokenizer.pre_tokenize_str
        self.latin = split["pattern"]["Regex"] == WORD_PATTERN
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.special_split = re.compile("(" + "|".join(map(re.escape, self.special)) + ")")
        vocab, end = model["vocab"], model["end_of_word_suffix"]
        self.names = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        letters = byte_letters()
        self.byte_of = {x: b for b, x in enumerate(letters)}
        self.inner = [vocab[x] for x in letters]
        self.final = [vocab[x + end] for x in letters]
        self.halves: dict[int, tuple[int, int]] = {}
        self.born: dict[int, int] = {}
        self.joined: dict[tuple[int, int], int] = {}
        for rank, (a, b) in enumerate(model["merges"]):
            left, right, whole = vocab[a], vocab[b], vocab[a + b]
            self.joined[left, right] = rank
            if whole not in self.halves:
                self.halves[whole], self.born[whole] = (left, right), rank
        self._sound: dict[int, bool] = {}
        self.automaton = SubstringAutomaton()
        for token in sorted(vocab.values()):
            if self.sound(token):
                self.automaton.add(self._symbols(token), token)
        self.automaton.close()
        self.span = {t: len(self._symbols(t)) for t in vocab.values()}
        self.pairs: dict[int, bool] = {}
        self.memo_words, self.memo = memo_words, _Memo(self)

    def _symbols(self, token: int) -> list[int]:
        out, todo = [], [token]
        while todo:
            t = todo.pop()
            if t in self.halves:
                todo += self.halves[t][::-1]
            else:
                out.append(t)
        return out

    def sound(self, token: int) -> bool:
        """Whether the token's own string encodes to the token."""
        known = self._sound.get(token)
        if known is None:
            known = True
            if token in self.halves:
                left, right = self.halves[token]
                known = self.sound(left) and self.sound(right) and self.compatible(left, right, self.born[token])
            self._sound[token] = known
        return known

    def compatible(self, left: int, right: int, until: int = NEVER) -> bool:
        """Whether nothing merges across the boundary before ``until``.

        The piece at each side of the boundary is a chain of ever smaller halves, each with the rank at which it ends.
        Ranks tie only for the same pair, and equal pairs merge from the left: so the left piece ends before a join of
        its own rank, the right piece after it.
        """
        left_ends = right_ends = until
        while True:
            rank = self.joined.get((left, right), NEVER)
            if rank < left_ends and (rank <= right_ends if right_ends < until else rank < until):
                return False
            left_born, right_born = self.born.get(left, -1), self.born.get(right, -1)
            if left_born < 0 and right_born < 0:
                return True
            if left_born >= right_born:
                left, left_ends = self.halves[left][1], left_born
            else:
                right, right_ends = self.halves[right][0], right_born

    def word(self, data: bytes) -> list[int]:
        """Ids of one word of the pattern, in UTF-8."""
        auto, pairs = self.automaton, self.pairs
        moves, link, length, token, ending = auto.moves, auto.link, auto.length, auto.token, auto.ending
        end = len(data) - 1
        symbols = [self.inner[b] for b in data]
        symbols[end] = self.final[data[end]]
        last: list[int] = []
        state = matched = 0
        for i, symbol in enumerate(symbols):
            step = moves[state].get(symbol)
            while step is None:
                state = link[state]
                matched = length[state]
                step = moves[state].get(symbol)
            state, matched = step, matched + 1
            at = ending[state if matched == length[state] else link[state]]
            while True:
                t, before = token[at], i - length[at]
                if before < 0:
                    break
                pair = last[before] << 20 | t
                fits = pairs.get(pair)
                if fits is None:
                    fits = pairs[pair] = self.compatible(last[before], t)
                if fits:
                    break
                at = ending[link[at]]
            last.append(t)
        span, ids = self.span, []
        while end >= 0:
            ids.append(last[end])
            end -= span[last[end]]
        ids.reverse()
        return ids

    def _chunk(self, chunk: str) -> bytes:
        if self.latin and BEYOND_LATIN.search(chunk) is None:
            parts = LATIN_WORDS.findall(chunk.lower())
            if parts != [chunk]:
                return b"".join([self.memo[w] for w in parts])
            words = [chunk.encode()]
        else:
            words = [bytes(map(self.byte_of.__getitem__, w)) for w, _ in self.words(self.normal(chunk))]
        if len(self.pairs) > 400_000:
            self.pairs.clear()
        out = array("I")
        for w in words:
            out.extend(self.word(w))
        return out.tobytes()

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        self.memo.age()
        out = []
        for part in self.special_split.split(text) if "<" in text else (text,):
            if part in self.special:
                out.append(self.special[part].to_bytes(4, "little"))
                continue
            out += map(self.memo.__getitem__, SPACES.split(part) if UNLIKE_SPACE.search(part) else part.split())
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        """Token strings with blanks between: these vocabulary files name no decoder."""
        return " ".join(map(self.names.__getitem__, array("I", ids)))


class _Memo(dict):
    """Ids of white-space chunks; no token and no rule reaches over white space. What wasn't met since the last change of generation goes."""

    def __init__(self, bpe: PrefixBpe) -> None:
        super().__init__()
        self.bpe, self.older = bpe, {}

    def __missing__(self, chunk: str) -> bytes:
        ids = self.older.get(chunk)
        if ids is None:
            ids = self.bpe._chunk(chunk)
        if len(chunk) < 64:
            self[chunk] = ids
        return ids

    def age(self) -> None:
        if len(self) > self.bpe.memo_words:
            self.older = dict(self)
            self.clear()


@lru_cache(maxsize=2)
def tokenizer(path: str) -> PrefixBpe:
    return PrefixBpe(path)


def encode(docs: DataFrame, path: str, text: str = "text", ids: str = "ids", decoded: str | None = None) -> DataFrame:
    """Add ``ids`` (binary, little-endian uint32) and, if named, the text decoded from them."""
    out = [ids] + ([decoded] if decoded else [])
    kept = [c for c in docs.columns if c.lower() not in {x.lower() for x in out}]
    source = docs.select(*(docs[f"`{c}`"] for c in kept), F.coalesce(docs[f"`{text}`"], F.lit("")).alias("__text"))
    schema = T.StructType([*source.schema.fields[:-1], T.StructField(ids, T.BinaryType()), *([T.StructField(decoded, T.StringType())] if decoded else [])])
    at = len(kept)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(path)
        for part in common.pieces(batches, at, 1 << 20):
            coded = [bpe.encode(t) for t in common.texts_of(part.column(at))]
            columns = [*part.columns[:at], pa.array(coded, pa.binary())]
            if decoded:
                columns.append(pa.array([bpe.decode(x) for x in coded], pa.string()))
            yield pa.RecordBatch.from_arrays(columns, names=schema.fieldNames())

    return source.mapInArrow(run, schema)


def n_ids(ids: str | Column) -> Column:
    return F.expr(f"cast(octet_length({ids}) div 4 as bigint)") if isinstance(ids, str) else (F.octet_length(ids) / 4).cast("long")


def op8_bpe_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of ids and decoded text of every document."""
    import public_tokenizers

    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = encode(docs, public_tokenizers.path("word_bpe_49k.json"), decoded="decoded")
    return out.select("doc_id", n_ids("ids").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))
