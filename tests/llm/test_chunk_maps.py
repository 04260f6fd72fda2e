"""Maps of chunks against the library: chunks of any size, long words, seams."""

import random
import time

import pytest

public = pytest.importorskip("public_tokenizers")
from tokenizers import Tokenizer as Library  # noqa: E402

from domsearch.llm import token_counts  # noqa: E402


@pytest.fixture(scope="module")
def path():
    return public.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def library(path):
    return Library.from_file(path)


@pytest.fixture(scope="module")
def tokenizer(path):
    return token_counts.Tokenizer(path)


def texts():
    draw = random.Random(21)
    words = ["the", "of", "token", "isn't", "we'll", "naïve", "漢字", "12345", "--", "\n\n", "  ", "\t", "'s", "😀", "http://a.b/c", "x" * 40]
    out = [" ".join(draw.choice(words) for _ in range(draw.randint(0, 3000))) for _ in range(30)]
    out += ["".join(draw.choice("abcde '\n.é1") for _ in range(9000)) for _ in range(10)]
    out += ["".join(draw.choice("etaoinshr") for _ in range(20_000)), "ab" * 9000, "a" * 5000, "1" * 5000, " " * 9000, "é" * 5000, "-" * 300 + "x" * 300]
    return out


@pytest.mark.parametrize("chunk", [1, 7, 64, 4096])
def test_counts_at_every_chunk_size(tokenizer, library, monkeypatch, chunk):
    monkeypatch.setattr(token_counts, "CHUNK", chunk)
    monkeypatch.setattr(token_counts, "BLOCK", max(3 * chunk, 50))
    some = texts() if chunk > 7 else [t[:400] for t in texts()]
    assert tokenizer.counts(some).tolist() == [len(library.encode(t, add_special_tokens=False).ids) for t in some]


def test_most_chunks_are_composed(tokenizer, library):
    """With the default sizes a long text is many maps."""
    text = " ".join(texts()[:20])
    (maps,) = tokenizer.maps([(text[: token_counts.BLOCK], 0, min(len(text), token_counts.BLOCK))])
    assert len(maps) > 20 and sum(bool(m.head) for m in maps) > 5
    # composition is associative
    a = tokenizer.automaton
    left = maps[0]
    for m in maps[1:]:
        left = left.then(m, a)
    right = maps[-1]
    for m in maps[-2::-1]:
        right = m.then(right, a)
    want = len(library.encode(text[: token_counts.BLOCK], add_special_tokens=False).ids)
    assert left.total(a) == right.total(a) == token_counts.scanned(maps, a).total(a) == want


@pytest.mark.parametrize("letters", ["a", "ab", "etaoinshrdlu", "abcdefghijklmnopqrstuvwxyz", "0123456789", "-=+"])
def test_a_word_of_a_megabyte(tokenizer, library, letters):
    draw = random.Random(22)
    word = "".join(draw.choice(letters) for _ in range(1_000_000))
    began = time.time()
    n = tokenizer.counts([word])[0]
    assert time.time() - began < 60
    assert n == len(library.encode(word, add_special_tokens=False).ids)
