"""Words and fragments by replacement and split are those of the patterns they stand for."""

import random

import pytest

from cardest.llm import toxicity as T

TEXTS = ["", " ", "a", "a_b c\u00a0d\x1ce\x85f", "sh1t! $o (c) caf\u00e9 2\u20ac \u0661\u0662 \u00b2x \u4e2d\u6587\u3002\u5b57", "\ud800x y\u0301z", "".join(map(chr, range(0, 3000))), "x".join(map(chr, range(0x2000, 0x2200)))]


@pytest.mark.parametrize("whole, breaks", [(T._WORD, T._BREAK), (T._PLAIN_FRAGMENT, T._PLAIN_BREAK)])
def test_pieces_equal_matches(whole, breaks):
    for text in TEXTS + [c.join(("ab", "1c")) for c in map(chr, range(0x3000))]:
        assert T.pieces(text, whole, breaks) == set(whole.findall(text))


def test_runs_of_short_fragments_equal_the_plain_definition():
    r = T._RUNS
    plain = T.re.compile(rf"(?<!{r}){r}{{1,3}}(?!{r})(?:[^\w{T._SIGN}]{{1,3}}{r}{{1,3}}(?!{r}))+")
    rng = random.Random(1)
    for _ in range(20_000):
        text = "".join(rng.choice("abc1$.,  -") for _ in range(rng.randrange(40)))
        assert T._PLAIN_SHORTS.findall(text) == plain.findall(text)
