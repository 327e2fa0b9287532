"""The last byte of a piece makes neither an arc nor a state, and gives the same ids as with them."""

import random

import public_tokenizers
import tiktoken

from edgecsr.llm.bpe_transducer import Transducer, load_ranks


def test_nothing_is_made_for_the_last_byte():
    ranks = load_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    library = tiktoken.Encoding("t", pat_str=r"[\s\S]+", mergeable_ranks=ranks, special_tokens={})
    own, rng = Transducer(ranks), random.Random(5)
    assert own.encode(b"") == [] and own.encode(b"q") == [ranks[b"q"]] and len(own.states) == 1 and not own.start.arcs
    assert own.encode(b"zq") == library.encode("zq") and set(own.start.arcs) == {ord("z")}
    for _ in range(3000):
        text = "".join(rng.choices("abcdeinrst éß", k=rng.randint(1, 14)))
        assert own.encode(text.encode()) == library.encode(text)
        assert own.encode(text.encode()) == own.encode((text + "x").encode()[:-1])
