import hashlib
import random

import public_tokenizers
import pytest
import regex
from tokenizers import Tokenizer

from spanfocus.llm import bpe_codec, token_counts
from tests.llm.fixtures import edge_docs, no_docs

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")


@pytest.fixture(scope="module")
def texts():
    rnd = random.Random(5)
    made = ["", "a" * 3000, "ab" * 999, "<|endoftext|>x <|startoftext|>y<|endoftext|>", " \t  q\n\n", "日本語テキスト 12345 x\x1cy\x85z \xa0 's don't ΑΣ İ é"]
    made += ["".join(rnd.choice("abcdetion  \n'sé1日\x1c　") for _ in range(rnd.randint(0, 200))) for _ in range(200)]
    made += ["".join(rnd.choice(["the", "ing", "er", "tion", "a", "b", "s"]) for _ in range(rnd.randint(100, 900))) for _ in range(30)]
    return made


def test_counts_equal_the_library(texts):
    library = Tokenizer.from_file(BYTE)
    table = token_counts.MergeTable(BYTE)
    assert table.count_texts(texts) == [len(e.ids) for e in library.encode_batch(texts, add_special_tokens=False)]


def test_counts_in_small_pieces(texts, monkeypatch):
    whole = token_counts.MergeTable(BYTE).count_texts(texts)
    monkeypatch.setattr(token_counts, "HELD", 50)
    monkeypatch.setattr(token_counts, "REMEMBERED", 100)
    assert token_counts.MergeTable(BYTE).count_texts(texts) == whole


def test_codec_equals_the_library(texts):
    library, c = Tokenizer.from_file(WORD), bpe_codec.Codec(WORD)
    for text, e in zip(texts, library.encode_batch(texts, add_special_tokens=False), strict=True):
        assert [i for ids in c.encode(text) for i in ids] == e.ids
        decoder = bpe_codec.Decoder(c)
        pieces = "".join(decoder.feed(e.ids[a : a + 3]) for a in range(0, len(e.ids), 3))
        assert pieces + decoder.finish() == library.decode(e.ids, skip_special_tokens=False)


def test_stream_equals_whole_word():
    """Tokens are emitted before the word's end, from bounded memory, and equal those of the whole word."""
    c, rnd = bpe_codec.Codec(WORD), random.Random(9)
    assert c.lookahead == max(map(c.lookahead_of, c.vocab)) >= c.longest // 2
    for _ in range(5):
        word = "".join(rnd.choice(["th", "in", "a", "e", "tion", "s", "qu"]) for _ in range(3000))
        symbols, taken, held = list(c.symbols(word)), 0, 0

        def source(symbols=symbols):
            nonlocal taken
            for s in symbols:
                taken += 1
                yield s

        made = []
        for t in c.stream(source()):
            made.append(t)
            held = max(held, taken - sum(len(x.removesuffix(c.end)) for x in made))
        assert held <= c.longest + c.lookahead + c.reading < len(symbols)
        assert made == c.merged(symbols)


def test_stable_tokens_do_not_wait_for_the_word_to_end():
    """Read symbol by symbol, words of the vocabulary's own pieces give the same tokens, some of them early."""
    c, rnd, early = bpe_codec.Codec(WORD, reading=1), random.Random(1), 0
    parts = [t.removesuffix(c.end) for t in c.vocab if t.removesuffix(c.end).isalpha()]
    for _ in range(400):
        symbols = list(c.symbols("".join(rnd.choice(parts) for _ in range(rnd.randint(1, 12)))))
        left = iter(symbols)
        stream = c.stream(left)
        first = next(stream)
        early += next(left, None) is not None
        assert list(c.stream(iter(symbols))) == c.merged(symbols) and c.merged(symbols)[0] == first
    assert early > 0


def test_every_word_goes_through_the_transducer(monkeypatch):
    c, seen = bpe_codec.Codec(WORD), []
    stream = bpe_codec.Codec.stream
    monkeypatch.setattr(bpe_codec.Codec, "stream", lambda self, symbols: stream(self, (seen.append(s) or s for s in symbols)))
    assert [i for part in c.encode("two words two") for i in part]
    assert "".join(seen) == f"two{c.end}words{c.end}"


def test_readable_decoding():
    c = bpe_codec.Codec(WORD)
    ids = [i for part in c.encode("Hello wörld 日本") for i in part]
    d = bpe_codec.Decoder(c, plain=True)
    assert "".join(d.feed([i]) for i in ids) + d.finish() == "hello wörld 日本 "
    # The first id alone bears only a part of the character.
    halves = [i for part in c.encode("本") for i in part][:1]
    cut = bpe_codec.Decoder(c, plain=True)
    assert cut.feed(halves) + cut.finish() == "\ufffd"


def test_lookahead_of_small_lists():
    length = {t: len(t) for t in ("a", "b", "c", "ab", "bc", "abc")}
    assert bpe_codec.lookaheads([("a", "b")], length)("a") == 1
    # "a" needs b, and "ab" may be undone by b merging first with c: one symbol for b, one for c.
    beyond = bpe_codec.lookaheads([("b", "c"), ("a", "b")], length)
    assert (beyond("a"), beyond("b"), beyond("ab"), beyond("c")) == (2, 1, 1, 0)


def test_documents(spark):
    docs = edge_docs(spark)
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    one, two, c = Tokenizer.from_file(BYTE), Tokenizer.from_file(WORD), bpe_codec.Codec(WORD)
    SPLIT = regex.compile(r"<\|endoftext\|>|" + bpe_codec.PATTERN)
    counted = token_counts.count_tokens(docs, BYTE).collect()
    assert len(counted) == docs.count()
    for r in counted:
        n = len(one.encode(texts[r.doc_id], add_special_tokens=False).ids)
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(texts[r.doc_id].encode()), n, n > 512)
    for r in bpe_codec.encode_documents(docs, WORD).collect():
        ids = two.encode(texts[r.doc_id], add_special_tokens=False).ids
        assert r.ids == ids and r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        readable = "".join(w + " " if w not in c.special else w for w in (m.group() for m in SPLIT.finditer(c.normal(texts[r.doc_id]))))
        assert r.readable_sha256 == hashlib.sha256(readable.encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(two.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert token_counts.count_tokens(no_docs(spark), BYTE).count() == 0
    assert bpe_codec.encode_documents(no_docs(spark), WORD).count() == 0
