"""Leaks whose templates repeat, whose names start sentences, and that lie among many repeats."""

import random

import pytest

from adapterlab.llm import decontaminate


def found(spark, docs, items):
    d = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    b = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {(r.doc_id, r.item_id): r for r in decontaminate.find_leaks(d, b).collect()}
    kept = {r.doc_id for r in decontaminate.drop_leaked(d, b).collect()}
    assert kept == set(range(len(docs))) - {d for d, _ in got}
    return got


OPTIONS = "Which bag is heavier: A) 3 apples B) 5 apples C) 7 apples D) 9 apples"
LIST = "Add 3 cups of flour, 5 cups of sugar, 7 cups of milk, 9 cups of oats and 11 cups of water to the bowl."


@pytest.mark.parametrize("item", [OPTIONS, LIST])
def test_repeating_templates_align_token_by_token(spark, item):
    changed = item
    for a, b in (("11", "86"), ("3 ", "41 "), ("5 ", "62 "), ("7 ", "73 "), ("9 ", "84 ")):
        changed = changed.replace(a, b)
    inserted = item.replace("5 ", "just 5 ")
    mixed = item.replace("5 ", "3 ").replace("7 ", "3 ").replace("9 ", "3 ").replace("11 ", "3 ")
    got = found(spark, [item, f"Before it. {changed} After it.", f"Before it. {inserted}", mixed, "Nothing of this kind here, only words."], [item])
    assert {(0, 0), (1, 0)} <= set(got) and (4, 0) not in got and (3, 0) not in got
    assert got[0, 0].changed_slots == 0 and got[0, 0].similarity == 1 and got[1, 0].changed_slots >= 4


NAMED = "Alice has 3 red apples. Alice buys 5 more apples. How many apples does Alice have now?"
SHORT = "What is the capital of France?"
DIGITS = "3 1 4 1 5 9 2"
CODES = "Paris Rome 12 Berlin 7 Oslo"


def test_names_that_start_sentences_and_items_with_few_windows(spark):
    docs = [NAMED.replace("Alice", "Carol"), NAMED.lower(), f'as they asked, "{SHORT}"', f"and so on ({SHORT.lower()}", f"in order: {CODES}, they said", CODES.replace("7", "8"), "What is the colour of France?", NAMED.upper(), f"digits {DIGITS} follow", DIGITS.replace("9", "8")]
    got = found(spark, docs, [NAMED, SHORT, CODES, DIGITS, "Paris 12"])
    assert set(got) == {(0, 0), (1, 0), (2, 1), (3, 1), (4, 2), (5, 2), (7, 0), (8, 3)}
    assert got[0, 0].changed_slots >= 3 and got[4, 2].similarity == 1


def test_edited_copy_among_many_repeats_of_a_part(spark):
    r = random.Random(5)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(5))
    item = [word() for _ in range(30)]
    text = []
    for _ in range(100):
        text += [*item[:18], *(word() for _ in range(40))]
    text += [*item[:15], "inserted", *item[15:]] + [word() for _ in range(20)]
    assert set(found(spark, [" ".join(text), " ".join(text[: 58 * 100])], [" ".join(item)])) == {(0, 0)}


def test_items_with_names_numbers_and_units_against_what_was_planted(spark):
    """Items of words, names, numbers and units; copies with values renamed one to one are leaks, others are not."""
    r = random.Random(11)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(5))
    name = lambda: word().capitalize()
    units = ["kg", "miles", "hours", "litres"]

    def item():
        return [r.choice([("w", word()), ("w", word()), ("w", word()), ("n", name()), ("u", (str(r.randint(2, 99)), r.choice(units)))]) for _ in range(22)]

    def said(tokens):
        return "It " + " ".join(v if k != "u" else " ".join(v) for k, v in tokens) + " so."

    items = [item() for _ in range(12)]
    docs, want = [], set()
    for i, tokens in enumerate(items):
        names, numbers, other = {}, {}, dict(zip(units, units[1:] + units[:1]))
        same = [(k, names.setdefault(v, name()) if k == "n" else (numbers.setdefault(v[0], str(100 + len(numbers))), other[v[1]]) if k == "u" else v) for k, v in tokens]
        cut = [(k, word() if k == "w" and j % 3 == 0 else v) for j, (k, v) in enumerate(tokens)]
        for copy, leaks in ((tokens, True), (same, True), (cut, False)):
            want |= {(len(docs), i)} if leaks else set()
            docs.append(" ".join(word() for _ in range(15)) + ". " + said(copy) + " " + " ".join(word() for _ in range(15)))
    assert set(found(spark, docs, [said(t) for t in items])) == want


def test_codes_are_the_same_in_every_process():
    import subprocess
    import sys

    told = [subprocess.run([sys.executable, "-c", "from adapterlab.llm.decontaminate import Codes; print(Codes()['Berlin,'])"], capture_output=True, text=True, env={"PYTHONHASHSEED": str(k), "PYTHONPATH": ":".join(sys.path)}).stdout for k in (1, 2)]
    assert told[0] == told[1] and int(told[0]) == decontaminate.Codes()["Berlin,"]
