"""Pieces of several lines are put together from the words that the memo holds."""

import random

import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from motifmill.llm.bpe import Codec


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_lines_and_words_encode_as_the_library_does(name):
    path = public_tokenizers.path(name)
    rng = random.Random(3)
    words = ["alpha", "Beta.", "gamma,", "d\u00e9j\u00e0", "\u00c9t\u00e9.", "x1", "a-b", "", "end!", "\u4e2d\u6587", "q" * 9000, "abcdefghijklmnopqrstuvwxyz" * 3, "<|endoftext|>", "I", "don't"]
    texts = ["".join(rng.choice(words) + rng.choice([" ", " ", "\n", "\n\n", " \n"]) for _ in range(rng.randint(0, 12))) for _ in range(400)]
    texts += ["\nalpha", "alpha\n", "alpha\nBeta.\ngamma,", "alpha.\n", "", " ", "\n"]
    library, own = Tokenizer.from_file(path), Codec(path, memo=5)
    library.no_truncation()
    library.no_padding()
    want = [library.encode(t, add_special_tokens=False).ids for t in texts]
    for at in range(0, len(texts), 20):
        assert own.encode_column(pa.array(texts[at : at + 20])).to_pylist() == want[at : at + 20]


def test_memo_keeps_the_words_of_lines_not_the_lines():
    own = Codec(public_tokenizers.path("byte_bpe_50k.json"))
    own.encode_column(pa.array(["so alpha.\nBeta gamma"]))
    assert (b"Beta",) in own.memo and b"alpha." in own.memo
    assert b"alpha.\nBeta" not in own.memo
