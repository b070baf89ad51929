"""Whole operators against brute force, both sides of every size switch, and
tables that are empty or have columns of the operators' own names."""

import hashlib
import math
import os
import random

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from pagecast.llm import bpe, html_extract, near_dedup, packing, quality_classifier, quality_rules, substring_dedup, token_files, url_filters, vector_search

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
SF = "/root/testdata/sf0.001"
given = pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")


# ------------------------------------------------------------------------- spans
def spans_by_hand(docs, plan):
    """Runs as tuples of words, their first places, and what is left of each text."""
    places, runs_of = {}, {}
    for doc, text in docs.items():
        parts = substring_dedup.sentences(text)
        words = [p.lower().split() for p in parts]
        size = lambda a, b: sum(map(len, words[a : b + 1]))  # noqa: E731, B023
        enough = lambda a, b: (b - a + 1 >= plan.sentences and size(a, b) >= plan.words) or size(a, b) >= plan.alone  # noqa: E731, B023
        found = set()
        for a in range(len(parts)):
            found |= {(a, b) for b in [next((b for b in range(a, len(parts)) if enough(a, b)), None)] if b is not None}
            found |= {(b, a) for b in [next((b for b in range(a, -1, -1) if enough(b, a)), None)] if b is not None}
        runs_of[doc] = {(a, b): tuple(w for part in words[a : b + 1] for w in part) for a, b in found}
        for (a, _), run in runs_of[doc].items():
            places.setdefault(run, []).append((doc, a))
    out = {}
    for doc, text in docs.items():
        gone = set()
        for (a, b), run in runs_of[doc].items():
            if len(places[run]) > 1 and (doc, a) != min(places[run]):
                gone |= set(range(a, b + 1))
        out[doc] = "".join(p for k, p in enumerate(substring_dedup.sentences(text)) if k not in gone)
    return out


def passages_that_repeat(seed=3):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcde") for _ in range(rng.randint(1, 4)))
    say = lambda: " ".join(word() for _ in range(rng.choice([2, 6, 12, 45]))) + rng.choice([". ", "! ", "\n", "? "])
    pool = ["".join(say() for _ in range(rng.randint(1, 5))) for _ in range(12)]
    return {i: "".join(rng.choice(pool) if rng.random() < 0.4 else say() for _ in range(rng.randint(0, 9))) for i in range(60)}


@pytest.mark.parametrize("broadcast", [True, False])
def test_spans_equal_brute_force(spark, monkeypatch, broadcast):
    if not broadcast:
        monkeypatch.setattr(substring_dedup, "BROADCAST_RUNS", -1)
    docs = passages_that_repeat()
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(5)
    got = {r["doc_id"]: r["text"] for r in substring_dedup.remove_repeats(df).collect()}
    want = spans_by_hand(docs, substring_dedup.SpanPlan())
    assert got == want and any(want[i] != docs[i] for i in docs)


# ------------------------------------------------------------------------- rules
@pytest.mark.parametrize("broadcast", [True, False])
def test_fences_equal_exact_quantiles(spark, monkeypatch, broadcast):
    if not broadcast:
        monkeypatch.setattr(quality_rules, "BROADCAST_PAIRS", -1)
    rng = random.Random(5)
    rows = []
    for i in range(900):
        lang, source = rng.choice(["en", "de"]), rng.choice(["a", "b"])
        words = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 9 if source == "a" else 4))) for _ in range(rng.randint(12, 60))]
        if rng.random() < 0.1:
            words += ["##" * rng.randint(1, 30)]
        if rng.random() < 0.1:
            words += words[:7]
        rows.append((i, " ".join(words), lang, source))
    rows += [(5000, "one two " * 30, "fr", "a"), (5001, " ".join(f"x{k}" for k in range(40)), "fr", "a")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = {r["doc_id"]: r["kept"] for r in quality_rules.judged(df, prefix="", min_docs=50).collect()}

    counts = {i: dict(zip(quality_rules.COUNTS, quality_rules.measure(t))) for i, t, *_ in rows}
    ratio = lambda c: {n: c[top] / c[below] if c[below] else None for n, top, below, _, _ in quality_rules._RATIOS}
    failed = {i: c["n_words"] < 10 or 100 * c["n_repeat_words"] > 20 * c["n_words"] for i, c in counts.items()}

    def group(i, lang, source):
        pair = [r for r in rows if (r[2], r[3]) == (lang, source)]
        own = [r for r in rows if r[2] == lang]
        return pair if len(pair) >= 50 else own if len(own) >= 50 else rows

    for i, _, lang, source in rows:
        inside = True
        for name, _, _, low, least in quality_rules._RATIOS:
            rare = name in quality_rules._RARE
            values = sorted(ratio(counts[r[0]])[name] or 0.0 for r in group(i, lang, source) if counts[r[0]]["n_words"] and not (rare and failed[r[0]]))
            q = lambda at: values[max(0, math.ceil(at * len(values)) - 1)]  # noqa: E731, B023
            reach = max(3 * (q(0.75) - q(0.25)), least)
            if rare:
                reach = max(reach, quality_rules._TAIL_REACH * (q(quality_rules._TAIL) - q(0.75)))
            value = ratio(counts[i])[name] or 0.0
            inside = inside and value <= q(0.75) + reach and (not low or value >= q(0.25) - reach)
        assert got[i] == (not failed[i] and inside), i
    assert 0 < sum(not k for k in got.values()) < 300


# -------------------------------------------------------------------------- texts
@given
def test_round_trip_digests_equal_the_library(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    t = Tokenizer.from_file(BYTE)
    t.no_truncation()
    t.no_padding()
    got = {r["doc_id"]: r for r in bpe.round_trip_digests(docs, BYTE).collect()}
    for doc, text in docs.collect():
        ids = t.encode(text or "", add_special_tokens=False).ids
        decoded = t.decode(ids, skip_special_tokens=False)
        r = got[doc]
        assert r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(decoded.encode()).hexdigest()


def sentence(rng):
    common = "the of and to in a is that it was for on are as with his they at be this from have or by one had not but what all were when we there can an your which their said if do".split()
    words = [rng.choice(common) if k % 2 else "".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(3, 8))) for k in range(rng.randint(14, 30))]
    return " ".join(words).capitalize() + "."


def test_generated_pages_give_their_text(spark):
    """Articles among menus, adverts, notices, comments and forms, one very long,
    one repeated."""
    rng = random.Random(11)
    pages, want = [], {}
    for k in range(25):
        paragraphs = [" ".join(sentence(rng) for _ in range(rng.randint(2, 4))) for _ in range(2000 if k == 7 else rng.randint(2, 6))]
        body = "".join(f"<p>{p.replace('said', '<b>said</b>').replace(' and ', ' &#97;nd ')}</p>\n" for p in paragraphs)
        menu = "".join(f'<li><a href="/{i}">{sentence(rng)[:20]}</a></li>' for i in range(6))
        html = (
            f"<html><head><title>{sentence(rng)}</title><script>var x = '{sentence(rng)}';</script><style>p {{ color: red }}</style></head><body>"
            f'<header><h2>{sentence(rng)}</h2></header><nav><ul>{menu}</ul></nav><div class="cookie-notice">{sentence(rng)}</div>'
            f'<article>{body}</article><aside>{sentence(rng)}</aside><div class="comments"><p>{sentence(rng)}</p></div>'
            f"<form><label>{sentence(rng)}</label><input></form><footer>{sentence(rng)}</footer></body></html>"
        )
        pages.append((k, f"http://x.org/{k}", html))
        want[k] = "\n".join(paragraphs)
    pages += [pages[3], (90, None, None), (91, "u", "")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    got = html_extract.extract(df).collect()
    assert len(got) == len(pages)
    for r in got:
        assert r["text"] == want.get(r["page_id"], "") and r["n_chars"] == len(r["text"])


# ------------------------------------------------------------- switches and edges
def near_copies():
    rng = random.Random(9)
    words = [f"w{k}" for k in range(200)]
    rows = []
    for i in range(90):
        if i % 6 == 0:
            base = [rng.choice(words) for _ in range(50)]
        text = list(base)
        for _ in range(rng.randint(0, 4)):
            text[rng.randrange(50)] = rng.choice(words)
        rows.append((i, " ".join(text)))
    return rows


def test_near_duplicates_with_and_without_broadcasts(spark, monkeypatch):
    df = spark.createDataFrame(near_copies(), "doc_id long, text string")
    key = lambda rows: sorted((r["doc_id"], r["component_id"], r["kept"]) for r in rows)
    want = key(near_dedup.near_duplicates(df).collect())
    for name, value in (("BROADCAST_IDS", -1), ("PAIRS_TOGETHER", 2), ("IMAGES", 1), ("BLOCK_BYTES", 500), ("BLOCKS_TOGETHER", 1)):
        monkeypatch.setattr(near_dedup, name, value)
    plain = near_dedup._Links.compare_groups
    monkeypatch.setattr(near_dedup._Links, "compare_groups", lambda self, left, right, keys, many: plain(self, left, right, keys, 0))
    assert key(near_dedup.near_duplicates(df).collect()) == want


def test_packing_with_and_without_broadcast(spark, monkeypatch):
    df = spark.createDataFrame([(i, "word " * (i % 23)) for i in range(300)] + [(None, None)], "doc_id long, text string")
    key = lambda rows: sorted(map(tuple, rows), key=str)
    want = key(packing.pack(df, WORD, limit=32).collect())
    monkeypatch.setattr(packing, "PLACES_BROADCAST", -1)
    monkeypatch.setattr(packing, "RANKED_TOGETHER", 3)
    got = packing.pack(df, WORD, limit=32).collect()
    assert sorted((r["doc_id"] or -1, r["start"], r["length"], r["ids_crc32"]) for r in got) == sorted((w[0] or -1, *w[1:4]) for w in want)
    used = {}
    for r in got:
        used.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert len(used) == len({w[5] for w in want})
    for spots in used.values():
        at = 0
        for offset, length in sorted(spots):
            assert offset == at
            at += length
        assert at <= 32


TEXTS = "doc_id long, text string, lang string, source string"
OPERATORS = {
    "near": lambda df: near_dedup.keep_one(df),
    "spans": lambda df: substring_dedup.remove_repeats(df),
    "rules": lambda df: quality_rules.filtered(df),
    "scores": lambda df: quality_classifier.with_scores(df, quality_classifier.AttentionBag(), score_col="s9"),
    "encode": lambda df: bpe.encode(df, BYTE, ids_col="ids9"),
    "pack": lambda df: packing.pack(df, WORD),
    "files": lambda df: token_files.round_trip(df, BYTE),
    "digests": lambda df: bpe.round_trip_digests(df, BYTE),
}


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_empty_tables_and_own_names(spark, name):
    run = OPERATORS[name]
    assert run(spark.createDataFrame([], TEXTS)).count() == 0
    clashing = "_dup_id kept a b z id bucket digest n bands salt shares _span_doc _span_gone hash first last gone _b_lang _b_source _q_kept _q_n_words score label features part ids start length".split()
    rng = random.Random(2)
    rows = [(i if i else None, " ".join(f"w{rng.randrange(10**6)}" for _ in range(40)) if i % 5 else [None, "", " ", "x. "][i // 5 % 4], "en", None if i % 3 else "s", *("v" for _ in clashing)) for i in range(30)]
    df = spark.createDataFrame(rows, TEXTS + "".join(f", {c} string" for c in clashing))
    out = run(df)
    got = out.collect()
    assert len(got) <= len(rows) and (name in ("near", "rules") or len(got) == len(rows))
    if name in ("near", "spans", "rules"):
        assert out.columns == df.columns


def test_empty_tables_of_the_other_operators(spark):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    assert html_extract.extract(pages).count() == 0
    assert url_filters.judge(pages, url_filters.QUERY_RULES).count() == 0
    vectors = spark.createDataFrame([], "vec_id long, embedding array<float>")
    assert vector_search.search(vectors, F.col("vec_id") % 100 == 0).count() == 0
    docs = spark.createDataFrame([], TEXTS)
    assert quality_classifier.fit(docs, spark.createDataFrame([], "doc_id long, quality int")) is None
