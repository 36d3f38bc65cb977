"""Small documents with what the operators must bear: nulls, empties, long texts, ties, repeats, odd columns."""

import random

import pytest

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, words string, gone string, _row string, component_id string, spans string, n_tokens string, m string"


def odd_rows():
    rng = random.Random(3)
    words = ["".join(rng.choice("abcdeé") for _ in range(rng.randint(1, 6))) for _ in range(300)]
    say = lambda n: " ".join(rng.choice(words) for _ in range(n))
    base, passage = say(120).split(" "), say(30)
    texts = [None, "", " \n\t ", "one", "one two", "One two", say(9000), " ".join(base), " ".join(base), " ".join([*base[:60], "changed", *base[61:]]), " ".join(base).upper()]
    texts += [f"{say(20)} {passage} {say(15)}\n{say(8)}\n{passage}" for _ in range(4)]
    texts += [f"{base[0]}  {base[1]}\n\n{base[2]} \r\n x\x0by" for _ in range(2)]
    texts += ["rep rep rep rep rep " * 30, "a\nb\na\n\na b\nb a", "mail a.b@c.d.example, +1 (415) 555-0199 and 4111 1111 1111 1111 at 10.0.0.256 10.0.0.25", "<s> <|endoftext|> ▁x 😀"]
    rows = [(i, t, None if i % 5 == 0 else "en", None if i % 7 == 0 else f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)]
    rows += [(None, "no id " + passage, "en", "s1", 9), (None, None, None, None, None), rows[7], rows[7]]
    return [(*r, *["x"] * 7) for r in rows]


@pytest.fixture(scope="session")
def odd(spark):
    return spark.createDataFrame(odd_rows(), COLUMNS).repartition(3)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], COLUMNS)
