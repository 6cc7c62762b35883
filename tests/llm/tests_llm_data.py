"""One messy table of documents."""

import random

_r = random.Random(11)
_words = ["alpha", "beta", "gamma", "delta", "eps", "zeta", "eta", "théta", "iota", "Kappa", "42", "x."]
_long = [_r.choice(_words) for _ in range(60)]


def _edit(words, k):
    out = list(words)
    for _ in range(k):
        out[_r.randrange(len(out))] = "edit" + str(_r.randrange(1000))
    return " ".join(out)


_texts = [None, "", " ", "\n\n", "one", "one two three", "ONE two\tthree", "one  two three", " ".join(_long), " ".join(_long)]
_texts += [_edit(_long, 1) for _ in range(12)] + [_edit(_long, 6) for _ in range(3)]
_texts += ["\n".join(" ".join(_r.choice(_words) for _ in range(8)) for _ in range(5)) for _ in range(4)]
_texts += ["same line of words here today\nsame line of words here today again\nother", "Same line of words here today\n\nunlike"]
_texts += [" ".join(_r.choice(_words) + str(_r.randrange(50)) for _ in range(6000)), "w" * 30_000, "tie", "tie", "日本語 のテキスト ▏ é", "a <|endoftext|> b"]

ROWS = [(3 * k + 1, t, None if k % 7 == 0 else "en", "src0" if k % 3 else None, None if t is None else len(t)) for k, t in enumerate(_texts)]
ROWS += [ROWS[8], (ROWS[4][0], "another text under one id", "en", "src1", 25)]
