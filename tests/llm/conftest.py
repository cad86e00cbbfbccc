import random

import pytest


def make_rows():
    """Rows with nulls, empties, odd white space, ties, repeats, near copies,
    shared passages, specials and one long text."""
    rng = random.Random(5)
    vocab = ["".join(rng.choice("abcdeéñöAB") for _ in range(rng.randint(1, 7))) for _ in range(300)]
    text = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    base, passage = text(120), text(30)
    rows = [(0, None), (1, ""), (2, " \t\n\x0b\x0c\r "), (3, "One"), (4, "one"), (5, "a b c d e"), (6, "A  B\tC\nD E"), (None, base), (None, None)]
    rows += [(7, base), (8, base), (8, base), (9, base.upper())]
    for i in range(10, 22):  # near copies of one text
        w = base.split()
        w[(i * 7) % 120] = f"new{i}"
        rows.append((i, " ".join(w)))
    for i in range(22, 30):
        rows.append((i, f"{text(60)} {passage} {text(40)}"))
    rows += [(30, f"{passage} {passage}"), (31, text(5000)), (32, "x" * 3000), (33, "###  *** $$$ %%% &&& ||| <<< >>> " * 12)]
    rows += [(34, "line one two\nline one two\n\nline one two\n other"), (35, "no break space ᵔf😀 ▁mark  ▁ two"), (36, "a  b   c\n\n d \n"), (37, "<|endoftext|> hi <s> </s> <|startoftext|>x")]
    rows += [(38, "1234 " * 30), (39, (text(9) + " ") * 6), (40, "𝄞 ümläut ça où"), (-5, passage), (2**40, base)]
    return rows


@pytest.fixture(scope="session")
def rows():
    return make_rows()


@pytest.fixture(scope="session")
def docs(spark, rows):
    """The rows with extra columns whose names clash with results."""
    full = [(d, t, "en", i, "x") for i, (d, t) in enumerate(rows)]
    return spark.createDataFrame(full, "doc_id long, text string, lang string, n_words int, kept_text string").repartition(5)


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, n_words int, kept_text string")
