"""What was made faster gives what the plainer way gives, and workers keep no answers for tasks of other operators."""

import random
import re

from farfield.llm import bpe
from farfield.llm import toxicity as T
from farfield.llm.common import slices


def test_short_pieces_as_long_ones(monkeypatch):
    b, rng = bpe.tokenizer(*bpe.public_tokenizer()), random.Random(3)
    tokens = list(b.bytes_of.values())
    pieces = [b"".join(rng.choice(tokens) for _ in range(rng.randint(1, 6)))[:64] for _ in range(3000)]
    pieces += [bytes(rng.choice(some) for _ in range(rng.randint(1, 40))) for some in (b"abcdefghijklmnopqrstuvwxyz", b"a -=", bytes(range(256))) for _ in range(2000)]
    got = [b._encode_short(p) if p not in b.rank_of else [b.rank_of[p]] for p in pieces]
    monkeypatch.setattr(bpe, "SHORT", -1)
    assert got == [b.encode_piece(p) for p in pieces]


def test_tasks_of_other_operators_drop_the_pieces():
    b = bpe.tokenizer(*bpe.public_tokenizer())
    b.digest("some words to keep")
    list(slices(iter(()), keeps="bpe"))
    assert b.pieces
    list(slices(iter(())))
    assert not b.pieces and not b.pieces.older and not b.fits_known


def test_noisy_places_as_by_separate_branches():
    one, letter, spacer = T._ONE, T._LETTER, T._SPACER
    plain = re.compile(
        rf"(?<![^\W_]){one}(?:{spacer}{{1,3}}{one}){{2,}}(?![^\W_])|{letter}[{re.escape(''.join(T.STANDS_FOR) + T.SPACERS[1:])}]+{letter}|(?P<double>({letter})\2)|(?<!\S){T._SYMBOL}{letter}{{2}}|[0-9@$€£¡§|+]{letter}|{letter}[0-9@$€£§|]"
    )
    rng = random.Random(5)
    texts = ["".join(rng.choice(some) for _ in range(300)) for some in ("ab é._-$1|+ ", "aaabß@ 0\n", "x. y·_~*!¡2") for _ in range(300)]
    both = [[(m.span(), m["double"] is None) for t in texts for m in pattern.finditer(t)] for pattern in (plain, T._NOISE)]
    assert both[0] == both[1]


def test_words_are_runs_of_letters():
    text = "abc1déf_g  h-i\n𝔸ß​q ²x"
    assert T.words_of(text) == set(re.sub(r"[\W\d_]+", " ", text).split())
