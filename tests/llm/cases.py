"""Rows that every operator has to handle: nulls, empty and long texts, ties, repeated rows, clashing columns."""

import random

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, `lines` int, n_dropped string, h1 int, node int, rest string, id int"


def words(seed: int, n: int) -> str:
    rnd = random.Random(seed)
    return " ".join("".join(rnd.choice("abcdeéfg") for _ in range(rnd.randint(1, 7))) for _ in range(n))


def rows() -> list[tuple]:
    base = words(1, 120)
    near = base.split()
    near[60] = "changed"
    texts = [(1, base), (2, " ".join(near)), (3, base), (4, None), (5, ""), (6, " \t\n "), (7, words(2, 30_000)), (8, "one two"), (9, "One TWO"), (10, "same line\n" + words(3, 80) + "\n same LINE\t"), (None, words(4, 90)), (11, base.upper()), (12, words(5, 60) + "\n" + base)]
    texts += [(20 + k, f"same line\n{words(100 + k, 70)}") for k in range(11)]
    texts += [(3, base), (40, "| # %% " * 40), (41, "the " * 300), (42, "\x00 \x1c  nul 日本語 😀 <|endoftext|> " + words(6, 55))]
    return [(i, t, [None, "en", "fr"][k % 3], "s", None, k, "x", 1, 2, "r", 3) for k, (i, t) in enumerate(texts)]


def documents(spark, some=None):
    return spark.createDataFrame(rows() if some is None else some, SCHEMA)
