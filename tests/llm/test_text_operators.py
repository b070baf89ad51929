"""Text operators against brute force on small, awkward inputs."""

import io
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from pagecast.llm import bpe, html_extract, near_dedup, packing, quality_classifier, quality_rules, substring_dedup, token_files, url_filters
from pagecast.llm.library_tokens import library_ids
from pagecast.llm.words import shingle_set

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
ODD = [None, "", " ", "\n\n", "one", "Ünïcode ÉTÉ 日本 🙂", "a\x00b\x0bc\xa0d", "x  y\t z\r\n", "<|endoftext|> is <|startoftext|>", "word " * 3000, "don't I'M 3.14 ___ Σ İ"]


def frame(spark, rows, ddl="doc_id long, text string, kept string, score string"):
    return spark.createDataFrame([(*r, "clash", "clash") if ddl.endswith("score string") else r for r in rows], ddl)


# ------------------------------------------------------------------------ tokens
def random_texts(n=1500):
    rng = random.Random(4)
    bits = ["a", "the", "ing", " ", " ", "  ", "\n", "\t", "\xa0", "<|endoftext|>", "é", "日", "🙂", "'s", "1", "23", "!!", ".", ",", "***", "\x1c", "Σ", "I'M", "ab", "\0"]
    return ODD + ["".join(rng.choice(bits) for _ in range(rng.randint(0, 14))) for _ in range(n)]


def test_encoders_equal_the_library():
    import pyarrow as pa

    texts = random_texts()
    own, lib_byte, lib_word = bpe.BacktrackedPieces(bpe.ByteBpe(BYTE)), library_ids(BYTE), library_ids(WORD)
    for kept, path in ((own, BYTE), (lib_byte, BYTE), (lib_word, WORD)):
        t = Tokenizer.from_file(path)
        for text, ids in zip(texts, kept.texts(pa.array(texts))):
            assert np.frombuffer(ids, "<u4").tolist() == t.encode(text or "", add_special_tokens=False).ids, repr(text)


def test_long_runs_stay_linear_and_exact():
    t, own = Tokenizer.from_file(BYTE), bpe.ByteBpe(BYTE)
    rng = random.Random(2)
    for text in ("a" * 30000, "ab" * 20000, "".join(rng.choice("abcdefgh") for _ in range(30000))):
        assert own.encode(text) == t.encode(text, add_special_tokens=False).ids


def test_encode_decode_round_trip(spark):
    df = frame(spark, list(enumerate(ODD)))
    back = bpe.decode(bpe.encode(df, BYTE), BYTE)
    assert all((r["text"] or "") == r["decoded"] for r in back.collect())
    got = {r["doc_id"]: r for r in bpe.round_trip_digests(df, BYTE).collect()}
    assert len(got) == len(ODD) and got[0]["n_tokens"] == got[1]["n_tokens"] == 0
    assert bpe.round_trip_digests(df.where("false"), BYTE).count() == 0


# ----------------------------------------------------------------- near-duplicates
def brute_components(rows, plan):
    sets = [(i, shingle_set(t, plan.shingle_words)) for i, t in rows if i is not None]
    root = {i: i for i, _ in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, (i, x) in enumerate(sets):
        for j, y in sets[:k]:
            both = len(np.intersect1d(x, y))
            if both and 100 * both >= plan.percent * (len(x) + len(y) - both):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: find(i) for i, _ in sets}


def families(seed=5, count=4, members=14):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)]
    rows, i = [], 0
    for _ in range(count):
        base = [rng.choice(words) for _ in range(60)]
        for _ in range(members):
            text = list(base)
            for _ in range(rng.randint(0, 5)):
                text[rng.randrange(60)] = rng.choice(words)
            rows.append((i, " ".join(text)))
            i += 1
    return rows + [(1000, None), (1001, ""), (1002, " \n "), (1003, "one two"), (1004, "One TWO"), (None, rows[0][1]), (5, rows[5][1]), (1006, "word " * 5000)]


@pytest.mark.parametrize("blocks", [False, True])
def test_near_duplicates_equal_brute_force(spark, monkeypatch, blocks):
    if blocks:  # small blocks, used for every comparison within a bucket
        plain = near_dedup._Links.compare_groups
        monkeypatch.setattr(near_dedup, "BLOCK", 5)
        monkeypatch.setattr(near_dedup._Links, "compare_groups", lambda self, left, right, keys, many: plain(self, left, right, keys, 0))
    rows, plan = families(), near_dedup.DedupPlan()
    got = near_dedup.near_duplicates(frame(spark, rows), plan).collect()
    want = brute_components(rows, plan)
    assert len(got) == len(rows)
    assert {r["doc_id"]: r["component_id"] for r in got if r["doc_id"] is not None} == want
    assert all(r["kept"] == (r["doc_id"] is None or r["doc_id"] == want[r["doc_id"]]) for r in got)
    if not blocks:
        kept = near_dedup.keep_one(frame(spark, rows), plan)
        assert kept.columns == ["doc_id", "text", "kept", "score"] and kept.count() == len(set(want.values())) + 1


def test_no_documents(spark):
    none = frame(spark, [(1, "x")]).where("false")
    assert near_dedup.near_duplicates(none).count() == near_dedup.keep_one(none).count() == 0
    assert substring_dedup.remove_repeats(none).count() == packing.pack(none, WORD).count() == 0
    judged = quality_rules.judged(spark.createDataFrame([], "doc_id long, text string, lang string, source string"))
    assert judged.count() == html_extract.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_signature_estimates_similarity():
    plan = near_dedup.DedupPlan()
    x = np.arange(1, 1001, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    a, b = near_dedup.signature(x[:900], plan), near_dedup.signature(x[100:], plan)
    assert abs((a == b).mean() - 0.8) < 0.1


# --------------------------------------------------------------- repeated passages
def test_passages_repeated_across_documents_go(spark):
    rng = random.Random(8)
    say = lambda n: " ".join(rng.choice("abcdefghij") * rng.randint(1, 5) for _ in range(n)) + ". "
    passage = say(9) + say(30) + say(4) + say(12) + say(6)
    one = "".join(say(20) for _ in range(4))
    long = "x" + say(55)
    rows = [(1, one + passage + say(25)), (2, say(14) + passage), (3, passage), (4, say(18) + say(9)), (5, None), (6, ""), (7, long), (8, say(30) + long + say(30)), (None, passage), (1, None)]
    got = {}
    for r in substring_dedup.remove_repeats(frame(spark, rows), counts=("n", "gone")).collect():
        got.setdefault(r["doc_id"], []).append(r)
    texts = {k: [r["text"] for r in v] for k, v in got.items()}
    assert texts[1][0] == rows[0][1] or texts[1][1] == rows[0][1]
    assert texts[2] == [rows[1][1].replace(passage, "")] and texts[3] == [""]
    assert texts[4] == [rows[3][1]] and texts[5] == [None] and texts[6] == [""] and texts[7] == [long]
    assert long not in texts[8][0] and len(texts[8][0]) == len(rows[7][1]) - len(long)
    assert texts[None] == [passage] and got[3][0]["gone"] == 5


def test_sentences_join_to_the_text():
    rng = random.Random(3)
    for _ in range(2000):
        text = "".join(rng.choice(["a", "b ", "the. ", "x!\n", "\n", "  ", "...", "3.14 ", "?", "\r\n"]) for _ in range(rng.randint(0, 30)))
        assert "".join(substring_dedup.sentences(text)) == text


def test_runs_equal_brute_force():
    rng, plan = random.Random(6), substring_dedup.SpanPlan()
    for _ in range(400):
        parts = [" ".join(rng.choice("abc") for _ in range(rng.randint(1, rng.choice([5, 12, 45])))) + ". " for _ in range(rng.randint(0, 12))]
        count, n = [len(p.split()) for p in parts], len(parts)
        enough = lambda a, b: b - a + 1 >= plan.sentences and sum(count[a : b + 1]) >= plan.words or sum(count[a : b + 1]) >= plan.alone
        want = {(a, b) for a in range(n) for b in [next((b for b in range(a, n) if enough(a, b)), None)] if b is not None}
        want |= {(a, b) for b in range(n) for a in [next((a for a in range(b, -1, -1) if enough(a, b)), None)] if a is not None}
        _, a, b = substring_dedup.runs(parts, plan)
        assert set(zip(a.tolist(), b.tolist())) == want


# -------------------------------------------------------------------------- rules
def brute_counts(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    covered = {k for i, w in enumerate(windows) if windows.count(w) > 1 for k in range(i, i + 5)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered)


def test_counts_equal_brute_force():
    texts = [t for t in ODD if len(t or "") < 1000] + ["a b c d e a b c d e f", "x\nx\n\nx \ny", "a a a a a a a", "p | q ## **"]
    assert [quality_rules.measure(t) for t in texts] == [brute_counts(t) for t in texts]


def test_rules_keep_clean_and_reject_odd(spark):
    rng = random.Random(1)
    clean = [(i, " ".join(rng.choice(["alpha", "beta", "gamma", "delta", "of", "the"]) + str(rng.randint(0, 99)) for _ in range(80)), "en" if i % 2 else None, "s") for i in range(600)]
    odd = [(9001, " ".join("word###" for _ in range(40)) + " ".join(f"z{i}###" for i in range(60)), "en", "s"), (9002, None, "en", None), (9003, "a b c d e f g h i j " * 9, "en", "s")]
    df = spark.createDataFrame(clean + odd, "doc_id long, text string, lang string, source string")
    judged = {r["doc_id"]: r for r in quality_rules.judged(df, prefix="").collect()}
    assert all(judged[i]["kept"] for i, *_ in clean)
    assert not any(judged[i]["kept"] for i, *_ in odd) and judged[9002]["base_failed"] and judged[9003]["base_failed"]
    assert quality_rules.filtered(df).columns == df.columns


# --------------------------------------------------------------------- classifier
def test_attention_gradient():
    model = quality_classifier.AttentionBag()
    rng = np.random.default_rng(1)
    x, starts, y = rng.normal(size=(20, quality_classifier.WIDTH)), np.array([0, 3, 4, 11]), np.array([0, 1, 1, 0.0])
    p, kept = model.forward(x, starts)
    grads = model.gradient(p, y, kept)

    def loss():
        q = model.forward(x, starts)[0]
        return -(y * np.log(q) + (1 - y) * np.log(1 - q)).mean()

    for name in model.NAMES:
        flat, g = model.p[name].reshape(-1), grads[name].reshape(-1)
        flat[0] += 1e-6
        up = loss()
        flat[0] -= 2e-6
        down = loss()
        flat[0] += 1e-6
        assert abs((up - down) / 2e-6 - g[0]) < 1e-6


def test_classifier_learns_and_scores_everything(spark):
    rng = random.Random(3)
    rows, labels = [], []
    for i in range(400):
        good = i % 4 != 0
        words = [rng.choice(["sun", "moon", "of", "and", "river"]) + ("" if good else "###") for _ in range(rng.randint(20, 200))]
        rows.append((i, " ".join(words)))
        labels.append((i, int(good)))
    docs, marks = frame(spark, rows + [(9000 + k, t) for k, t in enumerate(ODD)] + [(None, "x")]), spark.createDataFrame(labels + [(None, 1), (1, None)], "doc_id long, quality int")
    model = quality_classifier.fit(docs, marks)
    out = quality_classifier.with_scores(docs.drop("score"), model).select("doc_id", quality_classifier.held_out(F.col("doc_id")).alias("h"), "score").collect()
    assert len(out) == 400 + len(ODD) + 1 and all(0 <= r["score"] <= 1 for r in out)
    held = [r for r in out if r["h"] and r["doc_id"] is not None and r["doc_id"] < 400]
    assert len(held) > 40 and np.mean([(r["score"] >= 0.3) == (r["doc_id"] % 4 != 0) for r in held]) > 0.95
    assert all(r["h"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in out if r["doc_id"] is not None)
    assert quality_classifier.fit(docs, marks.where("false")) is None
    assert {r["score"] for r in quality_classifier.with_scores(docs.drop("score"), None).collect()} == {0.5}


def test_passages_count_every_word():
    texts = ODD + ["a " * 129]
    raw = [(t or "").encode() for t in texts]
    features, bags = quality_classifier.passages(raw)
    assert len(features) == bags.sum() and bags[-1] == 3 and bags[0] == bags[1] == 1 and not np.isnan(features).any()
    for t in raw:
        alone, n = quality_classifier.passages([t])
        at = int(np.cumsum(bags)[raw.index(t)] - n[0])
        assert np.allclose(alone, features[at : at + n[0]], atol=1e-6)


def test_long_texts_are_described_in_parts(monkeypatch):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcXYZ.,#1é") for _ in range(rng.choice([1, 3, 6, 40])))
    texts = [" ".join(word() for _ in range(rng.choice([0, 5, 64, 65, 128, 700, 3000]))) + rng.choice(["", " \n ", "\n" * 900]) for _ in range(40)] + [None, " " * 5000, "x" * 9000]
    want, sizes = quality_classifier.passages([(t or "").encode() for t in texts])
    model = quality_classifier.AttentionBag()
    scores = model.scores(texts)
    monkeypatch.setattr(quality_classifier, "SHARE", 600)
    found = list(quality_classifier.bags(texts))
    assert np.concatenate([n for _, n in found]).tolist() == sizes.tolist()
    assert np.allclose(np.concatenate([f for f, _ in found]), want, atol=1e-6)
    assert np.allclose(model.scores(texts), scores)


def test_scores_equal_a_plain_forward_pass(spark):
    """The operator's score of a document against loops over its passages."""
    docs = frame(spark, [(k, ("fine words of a house. " if k % 2 else "#$% 12 || ") * (1 + k % 90)) for k in range(120)])
    marks = spark.createDataFrame([(k, k % 2) for k in range(120)], "doc_id long, quality int")
    model = quality_classifier.fit(docs, marks)
    p = model.p
    for r in quality_classifier.with_scores(docs.drop("score"), model).collect():
        features, _ = quality_classifier.passages([r["text"].encode()])
        codes, weights = [], []
        for row in features:
            h = np.tanh(np.clip((row - model.mean) / model.scale, -8, 8) @ p["code"] + p["code_bias"])
            codes.append(h)
            weights.append(float((np.tanh(h @ p["show"]) / (1 + np.exp(-(h @ p["let"])))) @ p["weight"]))
        weights = np.exp(np.array(weights) - max(weights))
        z = sum(w * h for w, h in zip(weights / weights.sum(), codes))
        assert abs(r["score"] - 1 / (1 + np.exp(-(z @ p["score"] + p["bias"][0])))) < 1e-9


# ------------------------------------------------------------------------- packing
def test_shortest_pack_comes_first():
    assert sorted(packing.shortest_pack_first({60: 1, 50: 1, 5: 2}, 100)) == [([50, 5, 5], 1), ([60], 1)]
    rng = random.Random(1)
    for _ in range(50):
        histogram = {rng.randint(1, 40): rng.randint(1, 9) for _ in range(rng.randint(1, 12))}
        packs = []
        for length in sorted(histogram, reverse=True):
            for _ in range(histogram[length]):
                least = min(packs, key=sum, default=None)
                if least is None or sum(least) + length > 40:
                    packs.append([length])
                else:
                    least.append(length)
        got = [p for p, n in packing.shortest_pack_first(histogram, 40) for _ in range(n)]
        assert Counter(map(sum, got)) == Counter(map(sum, packs))


def check_packing(rows, ids, limit=4096):
    by_seq, by_doc = {}, {}
    for r in rows:
        by_seq.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        by_doc.setdefault(r["doc_id"], []).append(r)
    for places in by_seq.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at and length > 0
            at += length
        assert at <= limit
    for doc, want in ids.items():
        at = 0
        for r in sorted(by_doc[doc], key=lambda r: r["start"]):
            part = np.array(want[r["start"] : r["start"] + r["length"]], "<u4")
            assert r["start"] == at and r["doc_tokens"] == len(want) and r["ids_crc32"] == zlib.crc32(part.tobytes())
            at += r["length"]
        assert at == len(want)
    return len(by_seq)


def test_packing_places_every_id_once(spark):
    rng, t = random.Random(2), Tokenizer.from_file(WORD)
    texts = ODD + [" ".join(rng.choice(["sun", "moon", "x1", "of"]) for _ in range(rng.randint(0, 1500))) for _ in range(150)] + ["sun " * 9000]
    ids = {i: t.encode(x or "", add_special_tokens=False).ids + [2] for i, x in enumerate(texts)}
    sequences = check_packing(packing.pack(frame(spark, list(enumerate(texts))), WORD).collect(), ids)
    assert sequences * 4096 < 1.1 * sum(map(len, ids.values())) + 4096


def test_shortest_pack_first_uses_every_length():
    rng = random.Random(1)
    for _ in range(60):
        h = {}
        for _ in range(rng.randint(0, 300)):
            n = rng.randint(1, rng.choice([10, 100]))
            h[n] = h.get(n, 0) + rng.randint(1, 9)
        back = {}
        for lengths, count in packing.shortest_pack_first(h, 100):
            assert sum(lengths) <= 100 and lengths == sorted(lengths, reverse=True)
            for n in lengths:
                back[n] = back.get(n, 0) + count
        assert back == h


# ---------------------------------------------------------------------- token files
def test_number_streams_round_trip():
    for values in ([], [0], [255, 256, 65535, 65536, 1 << 24, (1 << 32) - 1], list(range(70000))):
        control, data = token_files.pack_numbers(np.array(values, "<u4"))
        got = token_files.unpack_numbers(np.frombuffer(control, np.uint8), np.frombuffer(data, np.uint8), len(values))
        assert got.tolist() == values


def test_token_files_round_trip(spark, monkeypatch):
    monkeypatch.setattr(token_files, "FILE_IDS", 500)
    monkeypatch.setattr(token_files, "SEGMENT", 64)
    t = Tokenizer.from_file(BYTE)
    rows = [(37 * k % 11 - 5, x) for k, x in enumerate(ODD)] + [(2, x) for x in ODD * 3]
    got = sorted(token_files.round_trip(frame(spark, rows), BYTE).collect(), key=lambda r: r["start"])
    at = 0
    encoded = [(doc, t.encode(text or "", add_special_tokens=False).ids + [0]) for doc, text in rows]
    want = Counter((doc, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())) for doc, ids in encoded)
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in got) == want
    assert [r["doc_id"] for r in got] == sorted(doc for doc, _ in rows)
    for r in got:  # gapless, in order
        assert r["start"] == at
        at += r["n_tokens"]
    assert len(got) == len(rows) and token_files.round_trip(frame(spark, [(None, "a"), (None, None)]), BYTE).count() == 2
    assert token_files.round_trip(frame(spark, rows).where("false"), BYTE).count() == 0


@pytest.mark.parametrize("segment", [1, 4, 7, 1 << 17])
def test_token_file_format(monkeypatch, segment):
    monkeypatch.setattr(token_files, "SEGMENT", segment)
    rng = random.Random(segment)
    docs = [(None if k % 5 == 0 else k, np.array([rng.randrange(1 << rng.choice([7, 15, 23, 31])) for _ in range(rng.choice([0, 1, 3, 9, 40]))], np.uint32)) for k in range(40)]
    for some in (docs, docs[:1], [], [(1, np.empty(0, np.uint32))] * 3):
        file, out = token_files.FileWriter(), io.BytesIO()
        for doc, ids in some:
            file.add(doc, ids)
        file.write(out)
        got = [(d, int(s), r.tolist()) for part in token_files.parse_file(io.BytesIO(out.getvalue())) for d, s, r in zip(*part)]
        starts = np.cumsum([0] + [len(i) for _, i in some])
        assert got == [(d, int(s), i.tolist()) for (d, i), s in zip(some, starts)]
    file, out = token_files.FileWriter(), io.BytesIO()
    file.add(1, np.array([5], np.uint32))
    file.write(out)
    with pytest.raises(ValueError):
        list(token_files.parse_file(io.BytesIO(out.getvalue()[:-1])))


# ---------------------------------------------------------------------------- pages
def test_main_text_of_awkward_pages():
    body = "The house of the river is in the garden, and it was not there for a long time as they would have said to the people of the town."
    page = f"""<html><head><title>t</title><style>p{{}}</style><script>var t="</p>";</script></head><body><header>Site of the day and the rest of it</header>
    <nav><a href=x>one</a> <a href=y>two</a></nav><div class="ad banner">{body}</div><article><h1>Top &amp; more&nbsp;</h1><p>{body}<br>Second  line<p><b>Short.</b><p>{body}</article>
    <div id="comments"><p>{body}</p></div><aside>{body}</aside><form>{body}<input></form><footer>&copy; {body}</footer></body></html>"""
    assert html_extract.main_text(page) == f"Top & more\n{body} Second line\nShort.\n{body}"
    assert [html_extract.main_text(x) for x in (None, "", "<p>", "<!-- x", "<script>x")] == [""] * 5
    plain = f"<div><h2>Head</h2><p>{body}</p><p>Brief.</p><p>{body}</p></div><ul><li><a href=q>more of the same</a></li></ul>"
    assert html_extract.main_text(plain) == f"Head\n{body}\nBrief.\n{body}"


# ----------------------------------------------------------------------------- urls
def test_url_parts():
    cases = {None: ("", ""), "": ("", ""), "no-scheme/x": ("", ""), "HTTP://A.Com": ("a.com", ""), "http://a.com?q=/x": ("a.com", ""), "s://a.com:80/p/q?x#y": ("a.com:80", "/p/q"), "s://h#f/x": ("h", ""), "s://a://b/c": ("a:", "//b/c")}
    for url, want in cases.items():
        assert tuple(x.decode() for x in url_filters.split_url(url)) == want


def test_rules_against_brute_force(spark, monkeypatch):
    rules = [*url_filters.QUERY_RULES, url_filters.Rule("a.b", "", "block"), url_filters.Rule("x.a.b", "/q", "allow")]
    rng = random.Random(3)
    hosts = ["example.com", "www.example.com", "badexample.com", "com", "example.net", "m.example.net", "org", "x.org", "a.b", "x.a.b", "y.x.a.b", "", "COM"]
    urls = [None, "", "x"] + [f"http://{rng.choice(hosts)}{rng.choice(['', '/', '/en/', '/en/7', '/en/75?x', '/de/8', '/de/1', '/es/', '/q', '?/en/'])}" for _ in range(400)]

    def brute(url):
        host, path = (x.decode() for x in url_filters.split_url(url))
        fits = [r for r in rules if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)] if host else []
        best = max(fits, key=lambda r: (len(r.host + r.path), len(r.host)), default=None)
        return (host, path, best and best.host + best.path, best.verdict if best else "allow")

    df = spark.createDataFrame([(i, u, "clash") for i, u in enumerate(urls)], "page_id long, url string, rule string")
    for collide in (False, True):
        if collide:  # all digests equal: the stored strings decide
            monkeypatch.setattr(url_filters.xxhash, "xxh64_intdigest", lambda key: 7)
            import tempfile, os  # noqa: E401

            path = os.path.join(tempfile.mkdtemp(), "r.bin")
            url_filters.DigestArray.write(rules, path)
            got = list(zip(*url_filters._judged(url_filters.DigestArray(path), urls, "allow")))
        else:
            got = [(r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filters.judge(df, rules).orderBy("page_id").collect()]
        assert got == [brute(u) for u in urls]
    with pytest.raises(ValueError):
        url_filters.judge(df, [url_filters.Rule("a", "/", "block"), url_filters.Rule("a", "/", "allow")])
