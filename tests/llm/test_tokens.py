"""Encoders against the library; files against what went in."""

import hashlib
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from bitplane.llm import token_output, tokenizing
from bitplane.llm.bpe import BatchMerger, MergeList, OpenWord, TokenDecoder, WordEncoder, symbols
from bitplane.llm.common import scratch, vocabulary_path
from bitplane.llm.token_counts import TokenCounter, prove_whole

WORDS, BYTES = vocabulary_path("word_bpe_49k.json"), vocabulary_path("byte_bpe_50k.json")
ALPHABET = [*"abcdeE ÉéßΣς'’stremvld0129.,!?<|>_-\n\t \u0085\x1c", "́", "İ", "中", "文", "한", "ᄒ", "ᅡ", "ᆫ", "😀", "<|endoftext|>", "<|startoftext|>", "'s", "'re", "²", "Ⅷ", "ǅ", "ﬁ", "  ", " \n"]
ROWS = [(1, "Hello  world's <|endoftext|> test"), (2, None), (3, ""), (4, "a" * 30000), (5, "Hello  world's <|endoftext|> test"), (None, "null id"), (5, "tie"), (6, "\n \t")]


@pytest.fixture(scope="module")
def texts():
    rnd = random.Random(2)
    return ["".join(rnd.choices(ALPHABET, k=rnd.randint(0, 40))) for _ in range(3000)]


@pytest.fixture(scope="module")
def rules():
    return MergeList.load(WORDS)


def flat(parts):
    return [i for p in parts for i in np.asarray(p).tolist()]


@pytest.mark.parametrize("window", [1, 7, 40, 1000, 1 << 16])
def test_word_encoder(texts, rules, window):
    lib, enc = Tokenizer.from_file(WORDS), WordEncoder(rules, window)
    long = ["the" * 3000, "ab" * 40000, "中" * 40000, "x!" * 20000, "!" * 5000]
    many = [flat(p) for p in enc.encode_many(texts + long)]
    for t, m in zip(texts + long, many):
        want = lib.encode(t, add_special_tokens=False).ids
        assert flat(enc.encode(t)) == want == m, t[:80]
    assert rules.proper and rules.lookahead < 2000


def test_every_text_goes_through_the_transducer(texts, rules, monkeypatch):
    fed, opened = [], []
    feed, push = WordEncoder.feed, OpenWord.push
    monkeypatch.setattr(WordEncoder, "feed", lambda self, text: fed.append(text) or feed(self, text))
    monkeypatch.setattr(OpenWord, "push", lambda self, syms: opened.append(syms) or push(self, syms))
    lib, enc = Tokenizer.from_file(WORDS), WordEncoder(rules)
    some = [*texts[:40], "the " * 40000]
    got = [flat(p) for p in enc.encode_many(some)]
    assert "".join(fed) == "".join(some) and got == [lib.encode(t, add_special_tokens=False).ids for t in some]
    monkeypatch.setattr(WordEncoder, "learn", lambda self, new: None)  # without the batches every word is a stream of its own
    bare = WordEncoder(rules)
    assert [flat(p) for p in bare.encode_many(some)] == got and len(opened) > 100


def test_lookahead_is_enough(rules):
    rnd = random.Random(6)
    for _ in range(30):
        word = "".join(rnd.choices(["th", "e", "ing", "a", "n", "d", "er", "re"], k=3000))
        stream = OpenWord(rules, step=100)
        got = flat(stream.push(symbols(word[i : i + 37])) for i in range(0, len(word), 37)) + stream.close()
        assert got == rules.word_ids(symbols(word))
        assert len(stream.held) == 0


def test_batch_merges(texts, rules):
    words = [w for t in texts[:300] for w in t.lower().split() if w and len(w) < 60] + ["a", "aaaaaaa", "aaaaaaaa"]
    ids, begins = BatchMerger(rules).ids(words)
    assert [ids[a:b].tolist() for a, b in zip(begins, begins[1:])] == [rules.word_ids(symbols(w)) for w in words]


def test_decoder(texts, rules):
    lib, enc = Tokenizer.from_file(WORDS), WordEncoder(rules)
    for t in texts[:500]:
        ids = flat(enc.encode(t))
        dec = TokenDecoder(rules)
        assert "".join(dec.push(ids[i : i + 3]) for i in range(0, len(ids), 3)) + dec.finish() == lib.decode(ids, skip_special_tokens=False)
    plain = TokenDecoder(rules, surface=False)
    ids = flat(enc.encode("Ünder 中文 don't stop"))
    assert (plain.push(ids[:2]) + plain.push(ids[2:]) + plain.finish()).split() == ["ünder", "中文", "don", "'t", "stop"]
    assert plain.push([rules.vocab["Ã"]]) == "" and plain.finish() == "�"


def test_counts(texts):
    lib, counter = Tokenizer.from_file(BYTES), TokenCounter(MergeList.load(BYTES))
    counter.learn(texts)
    for t in [*texts, "word " * 3000, "a" * 20000]:
        assert counter.count(t) == len(lib.encode(t, add_special_tokens=False).ids), t[:60]


def test_proven_tokens_are_whole():
    lib, rules = Tokenizer.from_file(BYTES), MergeList.load(BYTES)
    whole = sorted(prove_whole(rules))
    assert len(whole) > 45000
    for t in random.Random(1).sample(whole, 2000):
        assert len(lib.encode(t, add_special_tokens=False).ids) == 1


def frame(spark, rows=ROWS):
    return spark.createDataFrame([(i, t, "c", 1) for i, t in rows], "doc_id long, text string, n_tokens string, token_ids int")


def test_operators_on_edge_rows(spark):
    lw, lb = Tokenizer.from_file(WORDS), Tokenizer.from_file(BYTES)
    want_trip, want_count = [], []
    for i, t in ROWS:
        ids = lw.encode(t or "", add_special_tokens=False).ids
        want_trip.append((i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(lw.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
        n = len(lb.encode(t or "", add_special_tokens=False).ids)
        want_count.append((i, len((t or "").encode()), n, n > 512))
    got = [tuple(r) for r in tokenizing.round_trip(frame(spark), WORDS).collect()]
    assert sorted(got, key=repr) == sorted(want_trip, key=repr)
    got = [tuple(r) for r in tokenizing.count_tokens(frame(spark), BYTES).collect()]
    assert sorted(got, key=repr) == sorted(want_count, key=repr)
    assert tokenizing.round_trip(frame(spark, []), WORDS).collect() == [] == tokenizing.count_tokens(frame(spark, []), BYTES).collect()
    enc = tokenizing.encode(frame(spark), WORDS)
    assert enc.columns == ["doc_id", "text", "n_tokens", "token_ids"]
    assert {r.doc_id: r.decoded for r in tokenizing.decode(enc, WORDS, surface=True).collect()}[2] == ""


def test_sequence_files(spark):
    lib = Tokenizer.from_file(WORDS)
    path = scratch(spark, "test-sequences")
    token_output.write_sequences(frame(spark), path, WORDS, seq_len=16, batch_rows=4)
    want, start = [], 0
    for i, t in sorted(ROWS, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or "")):
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 1]
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    got = [tuple(r) for r in token_output.read_documents(spark, path).collect()]
    assert sorted(got, key=lambda r: r[1]) == want
    files = spark.read.parquet(f"{path}/manifest").collect()
    for f in files:
        table = pa.ipc.open_file(token_output.open_source(f"{path}/{f.file}")).read_all()
        assert table.schema.field("ids").type == pa.list_(pa.uint16(), 16)
        mask = np.concatenate([c.values.to_numpy(zero_copy_only=False) for c in table["mask"].chunks])
        assert int(mask.sum()) == f.tokens and not mask[f.tokens :].any()
        reader = token_output.SequenceReader(token_output.open_source(f"{path}/{f.file}"), 16, 4)
        assert reader.sequence(0).tolist() == table["ids"][0].as_py()
    empty = scratch(spark, "test-sequences")
    token_output.write_sequences(frame(spark, []), empty, WORDS)
    assert token_output.read_documents(spark, empty).collect() == []


def test_workers_keep_no_memo(spark):
    """An executor's Python workers live on: what a round trip learned is gone when its tasks end."""
    docs = spark.range(0, 4000, 1, 8).selectExpr("id AS doc_id", "concat_ws(' ', transform(sequence(0, 20), i -> sha2(concat(id, i), 256))) AS text")
    assert tokenizing.round_trip(docs, WORDS).agg({"n_tokens": "sum"}).first()[0] > 0

    def held(batches):
        for _ in batches:
            pass
        yield pa.RecordBatch.from_arrays([pa.array([len(tokenizing.encoder(WORDS).memo)])], ["n"])

    assert [r.n for r in spark.range(0, 8, 1, 8).mapInArrow(held, "n long").collect()] == [0] * 8
