"""The fences on repeated lines and passages reject what the base rule lets pass."""

import random

import pytest

from pagecast.llm import quality_rules

SCHEMA = "doc_id long, text string, lang string, source string"


def words(rng, n):
    return [f"w{rng.randrange(10**9)}" for _ in range(n)]


def judge(spark, rows):
    return {r["doc_id"]: r for r in quality_rules.judged(spark.createDataFrame(rows, SCHEMA), prefix="").collect()}


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(4)
    clean = [(i, "\n".join(" ".join(words(rng, 10)) for _ in range(10)), "en", "clean") for i in range(400)]
    passage, line = words(rng, 9), " ".join(words(rng, 5))
    repeats = (9001, " ".join(passage + words(rng, 41) + passage + words(rng, 41)), "en", "clean")  # 18 of 100 words
    lines = (9002, "\n".join([line, *(" ".join(words(rng, 10)) for _ in range(9)), line, " ".join(words(rng, 10))]), "en", "clean")  # 1 line, 110 words
    # a source in which every fifth document repeats as much sets a wider fence
    usual = [(i, " ".join((p := words(rng, 9 if i % 5 == 0 else 0)) + words(rng, 41) + p + words(rng, 41)), "en", "songs") for i in range(1000, 1400)]
    # every document of a pair fails the base rule: no value for the fences
    junk = [(i, "a b c d e f g h i j " * 9, "xx", "junk") for i in range(2000, 2300)]
    return clean, repeats, lines, usual, junk


def test_repeats_fence(spark, rows):
    clean, repeats, _, usual, junk = rows
    got = judge(spark, [*clean, repeats, *usual, *junk])
    assert not got[9001]["base_failed"] and not got[9001]["kept"] and got[9001]["n_dup_lines"] == 0
    assert all(got[i]["kept"] for i, *_ in clean + usual)
    assert not any(got[i]["kept"] for i, *_ in junk)


def test_dup_lines_fence(spark, rows, monkeypatch):
    clean, _, lines, _, _ = rows
    # the repeats fence out of the way, so that only the lines can speak
    monkeypatch.setattr(quality_rules, "_RATIOS", tuple((*r[:4], 1.0) if r[0] == "repeats" else r for r in quality_rules._RATIOS))
    got = judge(spark, [*clean, lines])
    assert not got[9002]["base_failed"] and got[9002]["n_dup_lines"] == 1 and not got[9002]["kept"]
    assert all(got[i]["kept"] for i, *_ in clean)
