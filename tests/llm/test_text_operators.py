"""Token ids and counts, personal data, quality, chat: exact results, round trips, edges."""

import datetime
import hashlib
import random
import re
import zlib
from array import array

import duckdb
import numpy as np
import public_tokenizers
import pytest
import zstandard
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from blockquant.llm import bpe_prefix, chat_schemas, common, compression_quality, pii_feistel, token_cache
from blockquant.llm.queries import ORACLES, QUERIES

WORD_BPE = public_tokenizers.path("word_bpe_49k.json")
EDGES = [None, "", " \n\t ", "a", "don't <|endoftext|> <|ENDOFTEXT|> x", "\x1c\x1d a\x1fb\x85c\xa0d", "É́ ß ΣΑΣ İ 漢字 🎉", "x" * 5000, "the " * 30000, "2024-02-30 '' ''s !!?"]


@pytest.fixture(scope="module")
def edge_docs(spark):
    rows = [(i, t, "en", "src0", 1) for i, t in enumerate(EDGES)] + [(3, "a", "en", "src0", 1), (None, "null id", None, None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(WORD_BPE)


def test_prefix_encoding_equals_the_library(library):
    bpe, rnd = bpe_prefix.tokenizer(WORD_BPE), random.Random(5)
    texts = [t or "" for t in EDGES]
    texts += ["".join(rnd.choice("aab bcdeinthesrogg") for _ in range(rnd.randint(0, 60))) for _ in range(800)]
    texts += ["".join(rnd.choice("aAéèñß'sdtre12 !?<|>.\t́İΣ漢字한🎉\x1c\x85​") for _ in range(rnd.randint(0, 30))) for _ in range(800)]
    texts += ["a" + chr(c) + "b" for c in range(0x20, 0x3000, 7)]
    for t in texts:
        want = library.encode(t, add_special_tokens=False).ids
        ids = bpe.encode(t)
        assert array("I", ids).tolist() == want
        assert bpe.decode(ids) == library.decode(want, skip_special_tokens=False)


def test_prefix_encoding_rejects_other_vocabularies():
    with pytest.raises(ValueError):
        bpe_prefix.PrefixBpe(public_tokenizers.path("byte_bpe_50k.json"))


def test_encode_edges(spark, edge_docs, library):
    clash = edge_docs.withColumn("ids", F.lit(1)).withColumn("IDS2", F.lit(2))
    out = bpe_prefix.encode(clash, WORD_BPE, decoded="decoded").collect()
    assert len(out) == len(EDGES) + 2
    for r in out:
        assert array("I", r["ids"]).tolist() == library.encode(r["text"] or "", add_special_tokens=False).ids
    assert bpe_prefix.encode(edge_docs.limit(0), WORD_BPE).count() == 0


def test_op8_against_the_library(spark, sf, library):
    docs = {r["doc_id"]: r["text"] or "" for r in common.table(spark, sf, "documents").collect()}
    for r in QUERIES["op8_bpe_prefix"](spark, sf).collect():
        ids = library.encode(docs[r["doc_id"]], add_special_tokens=False).ids
        assert r["n_tokens"] == len(ids) and r["ids_sha256"] == hashlib.sha256(array("I", ids).tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json", "piece_bpe_32k.model"])
def test_counts_equal_the_library_and_hit_the_cache(spark, edge_docs, name, monkeypatch):
    path, cache = public_tokenizers.path(name), common.shared_dir(spark, "counts")
    got = [(r["doc_id"], r["n_bytes"], r["n_tokens"]) for r in token_cache.count_tokens(edge_docs, path, cache).collect()]
    if name.endswith(".model"):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        count = lambda t: len(m.encode(t))
    else:
        m = Tokenizer.from_file(path)
        count = lambda t: len(m.encode(t, add_special_tokens=False).ids)
    want = [(r["doc_id"], len((r["text"] or "").encode()), count(r["text"] or "")) for r in edge_docs.collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    stored = spark.read.parquet(cache).count()
    token_cache.count_tokens(edge_docs.unionAll(edge_docs.withColumn("text", F.lit("new text"))), path, cache).count()
    assert spark.read.parquet(cache).count() == stored + 1
    assert token_cache.count_tokens(edge_docs.limit(0), path, cache).count() == 0


def test_op2_against_the_library(spark, sf, library):
    docs = {r["doc_id"]: r["text"] or "" for r in common.table(spark, sf, "documents").collect()}
    out = QUERIES["op2_token_cache"](spark, sf).collect()
    assert len(out) == len(docs)
    for r in out:
        n = len(library.encode(docs[r["doc_id"]], add_special_tokens=False).ids)
        assert (r["n_tokens"], r["n_bytes"], r["over_limit"]) == (n, len(docs[r["doc_id"]].encode()), n > 2048)


PRIVATE = {
    "card": "4111 1111 1111 1111", "iban": "DE89 3704 0044 0532 0130 00", "ip": "42.144.35.254", "ssn": "078-05-1120", "nanp": "+1 (988) 555-2485", "nanp_outside": "+1 (139) 555-2766",
    "phone": "+44 20 7946 0958", "date": "2024-02-29", "date_dots": "31.12.1999", "date_us": "12/31/1999", "email": "Ann.lee42@mail8.example.com", "secret": "b7db7aa4a5fcc78305",
}


def sentence(kind, value):
    return f"word {'password=' if kind == 'secret' else ''}{value} and more"


@pytest.mark.parametrize("kind", PRIVATE)
def test_values_change_inside_their_format_and_come_back(kind):
    make, undo = pii_feistel.Pseudonyms(b"k"), pii_feistel.Pseudonyms(b"k", reveal=True)
    text = sentence(kind, PRIVATE[kind])
    out, n = make.replace(text)
    assert n == 1 and PRIVATE[kind] not in out and len(out) >= len(text) - 12
    shape = lambda s: re.sub(r"[a-z]", "a", re.sub(r"[A-Z]", "A", re.sub(r"\d", "9", s)))
    if kind not in ("ip", "date", "date_dots", "date_us", "secret"):
        assert shape(out) == shape(text)
    assert undo.replace(out) == (text, 1)
    assert make.replace(f"{out}") != (out, 0)
    assert make.replace(text * 2)[0] == out * 2
    assert pii_feistel.Pseudonyms(b"other").replace(text)[0] != out


def test_pseudonyms_validate_again():
    make = pii_feistel.Pseudonyms(b"k")
    rnd = random.Random(2)
    for _ in range(200):
        body = "".join(rnd.choice("0123456789") for _ in range(15))
        card = make.card(body + str(pii_feistel.luhn(body)))
        assert card and int(card[-1]) == pii_feistel.luhn(card[:-1]) and card[0] == body[0]
        day = datetime.date(1900, 1, 1) + datetime.timedelta(rnd.randrange(73_000))
        datetime.date.fromisoformat(make.date(day.isoformat()))


def test_permutations_are_permutations():
    make, undo = pii_feistel.Pseudonyms(b"k"), pii_feistel.Pseudonyms(b"k", reveal=True)
    for size in (1, 2, 3, 10, 97, 1000):
        image = [make.permuted(i, size, "t") for i in range(size)]
        assert sorted(image) == list(range(size)) and [undo.permuted(i, size, "t") for i in image] == list(range(size))


@pytest.mark.parametrize("text", ["4111 1111 1111 1112", "999.1.1.1", "2023-02-29", "000-12-3456", "DE00 3704 0044 0532 0130 00", "version 1.2.3.4.5", "call 12345", "a = b", "x@y", "price = 10"])
def test_what_does_not_validate_stays(text):
    assert pii_feistel.Pseudonyms(b"k").replace(text) == (text, 0)


@pytest.mark.parametrize("text", ["a 4451718024887799 27.65.93.188 b", "12 4451718024887799, c", "+1 (836) 555-9331 4913187196670932 53.121.55.90 d", "4451718024887799 4913187196670932"])
def test_values_side_by_side(text):
    out, n = pii_feistel.Pseudonyms(b"k").replace(text)
    assert n >= 2 or text.startswith("12")
    assert not [v for v in ("4451718024887799", "4913187196670932", "27.65.93.188", "53.121.55.90", "555-9331") if v in text and v in out]
    assert pii_feistel.Pseudonyms(b"k", reveal=True).replace(out)[0] == text


@pytest.mark.parametrize("secret", ["password: correcthorse", "{'secret': 'abcdefgh'}", "token:" + "x" * 150 + "1y", "api_key :  " + "abcde" * 30, "pwd = correcthorse", "passphrase\n=\nabcdefgh"])
def test_secrets_are_found_whatever_stands_around_them(secret):
    make, undo = pii_feistel.Pseudonyms(b"k"), pii_feistel.Pseudonyms(b"k", reveal=True)
    new, n = make.replace(secret)
    assert n == 1 and new != secret
    for before in ("", "1 ", "at 7: "):
        for filler in range(130):
            text = f"{before}{'w' * filler} {secret} and so on"
            out = make.replace(text)
            assert out == (text.replace(secret, new), 1)
            assert undo.replace(out[0])[0] == text


@pytest.mark.parametrize("alphabet", ["abcdefghijklmnopqrstuvwxyz", "0123456789abcdef", "abcXYZ019", "aB3._-"])
@pytest.mark.parametrize("length", [8, 64, 65, 150, 200, 201, 300, 1000, 5000])
def test_long_secrets_change_from_end_to_end(alphabet, length):
    """No stretch of a secret stays in clear, whatever its length, and two that differ in one place differ everywhere."""
    make, undo = pii_feistel.Pseudonyms(b"k"), pii_feistel.Pseudonyms(b"k", reveal=True)
    rnd = random.Random(length)
    value = "".join(rnd.choice(alphabet) for _ in range(length - 1)) + alphabet[0]
    text = f"so db_password: {value} and more"
    out, n = make.replace(text)
    new = out.removeprefix("so db_password: ").removesuffix(" and more")
    assert n == 1 and len(new) == length and undo.replace(out) == (text, 1)
    same = lambda x, y: [a == b for a, b in zip(x, y, strict=True) if a.isalnum()]
    window = 12 if alphabet.isdecimal() else 20
    kept = same(value, new)
    assert not any(all(kept[i : i + window]) for i in range(max(1, len(kept) - window)))
    if length > 60:
        for part in (kept[: len(kept) // 4], kept[-(len(kept) // 4) :]):
            assert sum(part) < 0.5 * len(part)
        for place in (0, length // 2, length - 1):
            other = value[:place] + next(c for c in alphabet if c.isalnum() and c != value[place]) + value[place + 1 :]
            if [c.isalnum() for c in other] == [c.isalnum() for c in value] and not other.isdecimal():
                assert sum(same(new, make.secret(other))) < 0.6 * length


def replaced_everywhere(text, names):
    """Brute force: the pattern runs over the whole text, and after a value that doesn't validate again from the next character."""
    out, done, at, n = [], 0, 0, 0
    while (m := pii_feistel.FOUND.search(text, at)) is not None:
        kind = next(k for k in ("email", "secret", "iban", "date", "ip", "ssn", "nanp", "phone", "card") if m[k] is not None)
        start, end = m.span("value" if kind == "secret" else kind)
        tries = [end]
        if kind in ("phone", "card"):
            least = {"phone": 0, "card": 13}[kind]
            tries += [i for i in range(end - 1, start + 7, -1) if text[i] in " -." and sum(c.isdigit() for c in text[start:i]) >= least]
        for stop in tries:
            if (new := getattr(names, kind)(text[start:stop])) is not None:
                out.append(text[done:start] + new)
                done, at, n = stop, stop, n + 1
                break
        else:
            at = m.start() + 1
    return "".join(out) + text[done:], n


def test_op1_equals_a_search_of_whole_texts(spark):
    """Every document of the table: no value is missed because of where the search starts and stops."""
    sf, names = "/root/testdata/sf0.01", pii_feistel.Pseudonyms(pii_feistel.DEMO_KEY)
    texts = {r["doc_id"]: r["text"] for r in common.table(spark, sf, "documents").collect()}
    got = QUERIES["op1_pii_feistel"](spark, sf).collect()
    assert len(got) == len(texts) and sum(r["n_pii"] for r in got) > 20
    for r in got:
        assert (r["text"], r["n_pii"]) == replaced_everywhere(texts[r["doc_id"]], names)


def test_equal_dates_stay_linked_across_layouts():
    make = pii_feistel.Pseudonyms(b"k")
    assert datetime.date.fromisoformat(make.date("1999-12-31")).strftime("%d.%m.%Y") == make.date("31.12.1999")


def test_pii_edges(spark, edge_docs):
    out = pii_feistel.pseudonymise(edge_docs.withColumn("n_pii", F.lit("x")), b"k")
    rows = {r["doc_id"]: r for r in out.collect()}
    assert rows[0]["text"] is None and rows[1]["text"] == "" and rows[7]["text"] == "x" * 5000 and rows[4]["n_pii"] == 0
    assert pii_feistel.pseudonymise(edge_docs.limit(0), b"k").count() == 0


def test_op1_leaves_no_planted_value(spark, sf):
    before = {r["doc_id"]: r["text"] for r in common.table(spark, sf, "documents").collect()}
    out = QUERIES["op1_pii_feistel"](spark, sf).collect()
    assert len(out) == len(before)
    for r in out:
        for value in re.findall(r"[\w.]+@[\w.]+\w|\+1 \(\d{3}\) \d{3}-\d{4}|\b4\d{15}\b|(?<==)[0-9a-f]{12,}", before[r["doc_id"]] or ""):
            assert value not in r["text"]
        if not r["n_pii"]:
            assert r["text"] == before[r["doc_id"]]


def plain_quality(texts, labels, id_hash):
    """Brute force: the same sample by its rule, dictionaries, sizes and a curve found by plain gradient ascent."""
    train = {i: q for i, q in labels.items() if q in (0, 1) and zlib.crc32(str(i).encode()) % 3 != 1}
    base, words, curve = sum(train.values()) / len(train), {0: [], 1: []}, []
    for y in (0, 1):
        own = sorted((i for i in train if train[i] == y), key=lambda i: (id_hash[i], i))
        take = min(1000, max(1, len(own) // 3))
        words[y] = [texts[i] for i in own[:take] if texts.get(i)]
        curve += [(texts[i], y) for i in own[take : take + 3000] if texts.get(i)]
    dicts = {}
    for y, own in words.items():
        parts = [t.encode()[k : k + 2048] for t in sorted(own) for k in range(0, len(t.encode()), 2048)]
        dicts[y] = zstandard.ZstdCompressionDict(zstandard.train_dictionary(112_640, parts, level=3).as_bytes())

    def signal(text):
        data, size = text.encode(), {}
        for y, d in dicts.items():
            c = zstandard.ZstdCompressor(level=3, dict_data=d, write_checksum=False, write_content_size=False)
            size[y] = sum(len(c.compress(data[k : k + 1024])) for k in range(0, len(data), 1024))
        return (size[0] - size[1]) / len(data)

    x, y = np.array([signal(t) for t, _ in curve]), np.array([q for _, q in curve], float)
    z, w = np.column_stack([np.ones(len(x)), (x - x.mean()) / x.std()]), np.zeros(2)
    for _ in range(20000):
        w += 2.0 * (z.T @ (y - 1 / (1 + np.exp(-z @ w))) - 0.01 * w) / len(x)
    shift = np.log(base / (1 - base)) - np.log(y.mean() / (1 - y.mean()))
    return {i: base if not t else float(1 / (1 + np.exp(-(w[0] + shift + w[1] * (signal(t) - x.mean()) / x.std())))) for i, t in texts.items()}


def test_op9_equals_a_plain_version(spark):
    sf = "/root/testdata/sf0.01"
    texts = {r["doc_id"]: r["text"] for r in common.table(spark, sf, "documents").collect()}
    rows = common.table(spark, sf, "labels").select("doc_id", "quality", F.xxhash64(F.col("doc_id").cast("string"), F.lit("quality")).alias("h")).collect()
    want = plain_quality(texts, {r["doc_id"]: r["quality"] for r in rows}, {r["doc_id"]: r["h"] for r in rows})
    got = QUERIES["op9_compression_quality"](spark, sf).collect()
    assert len(got) == len(texts)
    for r in got:
        assert abs(r["score"] - want[r["doc_id"]]) < 1e-3 and r["predicted"] == (r["score"] >= 0.5)
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1)


def test_quality_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.01"
    out = QUERIES["op9_compression_quality"](spark, sf).join(common.table(spark, sf, "labels"), "doc_id").where("held_out").toPandas()
    assert (out.predicted == out.quality).mean() > 0.95
    assert out.predicted[out.quality == 1].mean() > 0.97


def test_quality_fit_takes_whole_texts_within_its_bytes(spark, edge_docs):
    labels = spark.createDataFrame([(i, i % 2) for i in range(9)], "doc_id long, quality int")
    model = compression_quality.fit(edge_docs, labels, dict_text_bytes=64)
    assert len(model.good) <= 64 and len(model.bad) <= 64 and all(0 <= r["score"] <= 1 for r in compression_quality.score(edge_docs, model).collect())


def test_quality_edges(spark, edge_docs):
    empty = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    model = compression_quality.fit_on_labels(edge_docs, empty)
    assert {r["score"] for r in compression_quality.score(edge_docs, model).collect()} == {1.0}
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(9)] + [(3, None, 0)], "doc_id long, quality int, toxic int")
    model = compression_quality.fit_on_labels(edge_docs, labels)
    rows = compression_quality.score(edge_docs.withColumn("SCORE", F.lit(9)), model).collect()
    assert len(rows) == len(EDGES) + 2 and all(0 <= r["score"] <= 1 for r in rows)
    assert compression_quality.score(edge_docs.limit(0), model).count() == 0


def test_op10_against_sql(spark, sf):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW conversations AS SELECT * FROM read_parquet('{sf}/conversations.parquet')")
    want = con.execute(ORACLES["op10_chat_schemas"]).fetchdf().sort_values("conv_id").reset_index(drop=True)
    got = QUERIES["op10_chat_schemas"](spark, sf).toPandas().sort_values("conv_id").reset_index(drop=True)
    assert got[sorted(got.columns)].astype(str).equals(want[sorted(want.columns)].astype(str))
    own = got[got.conv_id == -7].iloc[0]
    said = "</s>[INST] ok [/INST]"
    assert own.n_turns == 2 and own.loss_chars == len(said) and own.loss_sha256 == hashlib.sha256(said.encode()).hexdigest()


def conversations(df):
    return [(r["conv_id"], [(t["role"], t["text"]) for t in r["turns"]]) for r in df.collect()]


def test_chat_layouts_and_escapes(spark):
    nasty = ["<|turn|>x<|text|>", "a\\pb\\s\\", "<|end|>\n<|turn|>assistant<|text|>no", "### ### [INST [INST] </s><s>", "", "<", "<\\p|"]
    rows = [
        '{"id": 1, "messages": [{"role": "User", "content": "q"}, {"content": "r", "role": "assistant"}]}',
        '{"conversations": [{"value": "hi", "from": "human"}, {"from": "gpt", "value": "yo"}], "id": 2}',
        '{"id": 3, "prompt": "p", "completion": null}',
        '{"id": 4, "instruction": "i", "input": "n", "output": "o"}',
        '{"id": 5, "odd": 1}', "not json", None, "[1]", '{"id": 7, "prompt": {"text": "p"}, "completion": "c"}',
        '{"id": 8, "messages": [{"role": "user", "content": [{"text": "in parts"}]}, {"role": "user", "content": "plain"}]}',
    ]
    found, rest = chat_schemas.conversations_of_records(spark.createDataFrame([(r,) for r in rows], "json string"))
    assert sorted(conversations(found)) == [("1", [("user", "q"), ("assistant", "r")]), ("2", [("user", "hi"), ("assistant", "yo")]), ("3", [("user", "p"), ("assistant", "")]), ("4", [("system", "i"), ("user", "n"), ("assistant", "o")])]
    assert sorted(r["json"] or "" for r in rest.collect()) == sorted(r or "" for r in rows[4:])
    t = spark.createDataFrame([(i, k, r, x) for i, x in enumerate(nasty) for k, r in enumerate(("user", "assistant", x))], "conv_id long, turn long, role string, text string")
    back = {r["conv_id"]: r for r in chat_schemas.read_back(chat_schemas.formatted(chat_schemas.conversations_of_table(t))).collect()}
    for i, x in enumerate(nasty):
        assert [(y["role"], y["text"], y["in_loss"]) for y in back[i]["turns"]] == [("user", x, False), ("assistant", x, True), (x, x, False)]


def test_chat_records_never_mix(spark):
    """Ids that aren't numbers, that several records share, of different layouts or none at all."""
    one = lambda i, t: f'{{"id": {i}, "messages": [{{"role": "user", "content": "{t} asks"}}, {{"role": "bot", "content": "{t} says"}}]}}'
    rows = [one('"abc-1"', "a"), one('"xyz-2"', "b"), one(5, "c"), '{"id": 5, "prompt": "d asks", "completion": "d says"}', one(5, "e"), one('"abc-1"', "a"), '{"prompt": "f asks", "completion": "f says"}', one("null", "g")]
    found, rest = chat_schemas.conversations_of_records(spark.createDataFrame([(r,) for r in rows], "json string"))
    want = [("abc-1", "a"), ("xyz-2", "b"), ("5", "c"), ("5", "d"), ("5", "e"), ("abc-1", "a"), (None, "f"), (None, "g")]
    assert sorted(conversations(found), key=str) == sorted([(i, [("user", t + " asks"), ("assistant", t + " says")]) for i, t in want], key=str)
    assert rest.isEmpty()
    back = chat_schemas.read_back(chat_schemas.formatted(found))
    assert sorted(map(str, conversations(back))) == sorted(map(str, conversations(found)))


def test_chat_fields_that_come_and_go(spark):
    rows = [
        '{"id": 1, "messages": [{"role": "user", "content": "q", "name": "n", "tool": {"a": [1]}}, {"role": "assistant", "content": "r"}], "source": "web", "meta": {"k": 1}}',
        '{"messages": []}', '{"id": 3, "messages": [{"role": "assistant"}]}', '{"id": 4, "prompt": "p", "completion": "c", "a.b": 1, "x<y,z": [2], "messages": "none"}',
    ]
    found, rest = chat_schemas.conversations_of_records(spark.createDataFrame([(r, 1) for r in rows], "json string, conv_id int"))
    assert sorted(conversations(found), key=str) == sorted([("1", [("user", "q"), ("assistant", "r")]), (None, []), ("3", [("assistant", "")]), ("4", [("user", "p"), ("assistant", "c")])], key=str) and rest.isEmpty()
    assert [len(t) for _, t in conversations(chat_schemas.read_back(chat_schemas.formatted(found))) if _ is None] == [0]
    two = '{"id": 5, "prompt": "p", "completion": "c", "messages": [{"role": "user", "content": "q"}]}'
    found, rest = chat_schemas.conversations_of_records(spark.createDataFrame([(two,)], "json string"))
    assert found.isEmpty() and rest.count() == 1  # it fits two layouts, so it fits none


def test_chat_mapping_is_chosen_by_fingerprint(spark):
    """Each layout's shapes have fingerprints of their own, and a registry without a layout doesn't know its records."""
    every = [names for x in chat_schemas.LAYOUTS for names in x.shapes]
    prints = spark.range(1).select(*map(chat_schemas.of_names, every)).first()
    assert len(set(prints)) == len(every)
    row = spark.createDataFrame([('{"id": 1, "question": "q", "answer": "a"}',)], "json string")
    fewer = tuple(x for x in chat_schemas.LAYOUTS if x.name != "question")
    assert chat_schemas.conversations_of_records(row, layouts=fewer)[0].isEmpty() and chat_schemas.conversations_of_records(row)[0].count() == 1


def test_chat_tables_with_nulls_ties_and_extra_columns(spark):
    t = spark.createDataFrame([(1, 1, "user", None, 5), (1, 1, "user", None, 5), (1, None, None, "z", 5), (None, 0, "user", "n", 5)], "conv_id long, turn long, role string, text string, line long")
    back = dict(conversations(chat_schemas.read_back(chat_schemas.formatted(chat_schemas.conversations_of_table(t)))))
    assert back == {1: [("", "z"), ("user", ""), ("user", "")], None: [("user", "n")]}
    named = spark.createDataFrame([("b", 0, "user", "x"), ("a", 0, "user", "y")], "conv_id string, turn int, role string, text string")
    assert dict(conversations(chat_schemas.conversations_of_table(named))) == {"a": [("user", "y")], "b": [("user", "x")]}
    assert chat_schemas.conversations_of_table(t.limit(0)).count() == 0
    with pytest.raises(ValueError):
        chat_schemas.conversations_of_table(t.drop("role"))


def test_chat_tables_of_nested_values_are_reported(spark):
    """Same column names, but a nested text: no mapping's fingerprint, so not a result without rows."""
    t = spark.createDataFrame([(1, 0, "user", ("x",))], "conv_id long, turn long, role string, text struct<parts:string>")
    with pytest.raises(ValueError, match="text.parts"):
        chat_schemas.conversations_of_table(t)
    with pytest.raises(ValueError):
        chat_schemas.conversations_of_table(t.withColumn("text", F.lit("x")).withColumn("role", F.array(F.lit("x"))))
    with pytest.raises(ValueError):
        chat_schemas.conversations_of_table(t.select(F.lit(1).alias("other")))
    other = spark.createDataFrame([(1, 0, "user", "x", 2)], "conversation_id long, position long, speaker string, content string, more long")
    assert conversations(chat_schemas.conversations_of_table(other)) == [(1, [("user", "x")])]
