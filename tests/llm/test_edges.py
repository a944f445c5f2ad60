"""Repeated rows, long texts, hot keys and surrogates of random entities."""

import random
import re

from sortbit.llm import line_dedup, near_dedup, pii

from .test_operators import brute_lines


def test_line_dedup_of_repeated_rows_and_ids(spark):
    r = random.Random(2)
    line = lambda: " ".join(r.choice("alpha beta gamma delta".split()) for _ in range(6))
    shared = [line() for _ in range(4)]
    rows = [(1, "\n".join(shared)), (1, "\n".join(shared)), (2, "\n".join([line(), *shared])), (2, "other text under one id\n" + shared[0]), (None, shared[0]), (3, None), (4, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((x.doc_id, x.text) for x in line_dedup.deduplicate_lines(df).collect()), key=str)
    assert [t for d, t in got if d == 1] == ["\n".join(shared)] * 2
    assert all(not (set(shared) & set((t or "").split("\n"))) for d, t in got if d == 2)
    assert (None, shared[0]) in got and (3, None) in got and (4, "") in got and len(got) == 7


def test_line_dedup_of_a_long_text_and_hot_lines(spark):
    n = 30_000
    long = "\n".join(f"line number {i}" if i % 3 else "the same line every time" for i in range(n))
    texts = {0: "the same line every time", 1: long, 2: "x\nthe same line every time"}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {x.doc_id: x.text for x in line_dedup.deduplicate_lines(df, hot_rows=100).collect()}
    assert got[0] == texts[0] and got[2] == "x" and got[1] == "\n".join(x for x in long.split("\n") if not x.startswith("the"))
    small = {i: "\n".join(["a line of some length", "b", "another line of length"][: 1 + i % 3]) for i in range(12)}
    df = spark.createDataFrame(list(small.items()), "doc_id long, text string")
    for hot in (2, 1000):
        assert {x.doc_id: x.text for x in line_dedup.deduplicate_lines(df, hot_rows=hot).collect()} == brute_lines(small, line_dedup.MIN_CHARS)


def test_near_duplicates_of_repeated_ids(spark):
    r = random.Random(3)
    text = lambda: " ".join(f"w{r.randrange(10_000)}" for _ in range(60))
    a, b, c = text(), text(), text()
    df = spark.createDataFrame([(1, a), (5, a), (5, b), (7, b), (8, c), (8, c), (9, None)], "doc_id long, text string")
    got = {(x.doc_id, x.component_id) for x in near_dedup.near_duplicates(df).collect()}
    assert got == {(1, 1), (5, 1), (7, 1), (8, 8), (9, 9)}


def test_surrogates_of_random_entities(spark):
    """No entity survives, equal ones stay equal, different ones different, and signs keep their class."""
    r = random.Random(5)
    some = lambda chars, n: "".join(r.choice(chars) for _ in range(n))
    made = {
        "email": lambda: f"{some('abcdefgh', 5)}.{some('ijklmn', 4)}@{some('opqrst', 6)}.com",
        "phone": lambda: f"+49 {some('123456789', 3)} {some('0123456789', 7)}",
        "ip": lambda: ".".join(str(r.randint(1, 250)) for _ in range(4)),
        "iban": lambda: f"DE{some('123456789', 2)} " + " ".join(some("0123456789", 4) for _ in range(4)) + " " + some("0123456789", 2),
        "hex": lambda: some("0123456789abcdef", 31) + "7",
    }
    entities = [f() for f in made.values() for _ in range(12)]
    rows = [(i, f"first {e} then {e} end") for i, e in enumerate(entities)]
    names = ["Mr. John Smith and Mr. Smith or John Smith", "Mrs. Mary Keller, Mary Keller", "Dr. Emily Brown; Mr. Παπαδόπουλος; господин Петров"]
    rows += [(len(rows) + i, t) for i, t in enumerate(names)]
    got = [x.text for x in sorted(pii.pseudonymise(spark.createDataFrame(rows, "doc_id long, text string"), "k").collect(), key=lambda x: x.doc_id)]
    others = []
    for e, text in zip(entities, got, strict=False):
        one, two = re.fullmatch(r"first (.*) then (.*) end", text).groups()
        assert one == two != e and e not in text
        others.append(one)
        if "@" not in e and e.count(".") != 3:
            shape = lambda x: re.sub("[a-z]", "l", re.sub("[A-Z]", "L", re.sub("[0-9]", "d", x)))
            assert shape(one) == shape(e)
    assert len(set(others)) == len(set(entities)) and not set(others) & set(entities)
    assert all(o.startswith("+49 ") for e, o in zip(entities, others, strict=True) if e.startswith("+")) and all(o.startswith("DE") for e, o in zip(entities, others, strict=True) if e.startswith("DE"))
    full, short, bare = re.fullmatch(r"Mr\. (\S+ \S+) and Mr\. (\S+) or (\S+ \S+)", got[len(entities)]).groups()
    assert full == bare and full.split()[1] == short and "Smith" not in got[len(entities)] and "John" not in got[len(entities)]
    assert re.search(r"Mr\. [Ͱ-Ͽ]+; господин [А-яё]+$", got[-1])
