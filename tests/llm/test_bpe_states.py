"""States of the transducer are few whatever the words, and a word is encoded once however it is followed."""

import random
import sys
import unicodedata

import public_tokenizers
import tiktoken

from edgecsr.llm.bpe_transducer import Encoder, Transducer, load_ranks

RANKS = load_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))


def library(pattern=public_tokenizers.PATTERN):
    return tiktoken.Encoding("t", pat_str=pattern, mergeable_ranks=RANKS, special_tokens={})


def test_new_words_need_few_new_states():
    own, whole, rng = Transducer(RANKS), library(r"[\s\S]+"), random.Random(11)
    seen = []
    for _ in range(2):
        for _ in range(4000):
            word = "".join(rng.choices(["er", "on", "th", "in", "é", "ß", "la", "ch", "a", "n", "s", "qu"], k=rng.randint(2, 9)))
            assert own.encode(word.encode()) == whole.encode(word)
        seen.append(len(own.states))
    assert seen[1] < 2000 and seen[1] - seen[0] < 400


def test_a_word_is_encoded_once():
    own, asked = Encoder(RANKS, public_tokenizers.PATTERN), []
    encode = own.transducer.encode
    own.transducer.encode = lambda data: asked.append(data) or encode(data)
    text = "x eroreson eroreson, eroreson.\nQuedora eroreson!! zñadoarí zñadoarí12 zñadoarí's"
    assert own.encode(text) == library().encode_ordinary(text)
    assert sorted(asked) == sorted([" eroreson".encode(), "Quedora".encode(), " zñadoarí".encode()])


def test_letters_of_all_scripts_and_patterns_without_words():
    letters = "".join(filter(str.isalpha, map(chr, range(sys.maxunicode + 1))))
    marks = "".join(c for c in map(chr, range(0x3000)) if not c.isalpha() and unicodedata.category(c) != "Cn")  # libraries differ on the newest letters
    rng = random.Random(3)
    for pattern, words in ((public_tokenizers.PATTERN, True), (r" ?\p{L}{1,3}|\S| |\s+", False), (r" ?[a-z]+|[\s\S]", False)):
        own, whole = Encoder(RANKS, pattern), library(pattern)
        assert own.words is words
        for _ in range(1500):
            text = " ".join("".join(rng.choice(letters if rng.random() < 0.9 else marks) if rng.random() < 0.5 else rng.choice("abcdefxyz") for _ in range(rng.randrange(1, 9))) for _ in range(4))
            assert own.encode(text) == whole.encode_ordinary(text), (pattern, text)
