"""Each operator against brute force on odd rows: nulls, empty and long texts, ties, repeats, clashing columns, empty tables."""

import base64
import hashlib
import re

import numpy as np
import public_tokenizers
import pytest

from shoal.llm import decontaminate, jaccard_join, license_scan, lm_scoring, pieces, quality_rules, substring_dedup, token_counts, url_filter, warc

LOWER = str.maketrans({c: chr(c + 32) for c in range(65, 91)})
LONG = " ".join(f"w{i * i % 977}" for i in range(3000))
PASSAGE = " ".join(f"p{i}" for i in range(60))
ODD = [
    (1, None), (2, ""), (3, " \n\t "), (4, "a b c"), (5, "a b c"), (6, LONG), (7, LONG + " tail end"), (8, f"x y {PASSAGE} z"), (9, f"other words here {PASSAGE} and more of it"),
    (10, "Cc BY, all rights reserved. General Public\nLicense"), (11, "É 日本語 テスト  double   blanks ▁ <s> \x00 end"), (12, "a b c d e " * 30), (13, "thirteen words are in this one and it must stand alone here now"), (13, "same id other text"), (None, LONG),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "n_words clash", 7) for i, t in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, n_words string, component_id int").repartition(3)


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("false")


def key(row):
    return tuple((x is not None, x) if x is not None else (False, 0) for x in row)


def same(df, columns, want):
    got = sorted((tuple(r[c] for c in columns) for r in df.collect()), key=key)
    assert got == sorted(want, key=key)


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def test_warc_round_trip(spark):
    pages = [(1, "http://a.b/c\r\nX: y", "x"), (2, None, None), (3, "http://a.b/é", ""), (4, "u", "x"), (4, "u", "x"), (None, "http://z", "x"), (0, "http://a.b", "x" * 70_000)]
    df = spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, offset int")
    first = {}
    for p, _, h in pages:
        if p is not None:
            first[h or ""] = min(first.get(h or "", 99), p)
    want = []
    for p, _, h in pages:
        body = (h or "").encode()
        refers = None if first[h or ""] == p else first[h or ""]
        want.append((p, len(body), base64.b32encode(hashlib.sha1(body).digest()).decode(), "response" if refers is None else "revisit", refers))
    same(warc.archive_round_trip(df), ("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"), want)
    assert warc.archive_round_trip(df.where("false")).count() == 0


def test_loser_tree():
    runs = [[1, 4, 4], [], [0, 4, 9], [2]]
    assert list(warc.LoserTree([iter(r) for r in runs], lambda x: x)) == [0, 1, 2, 4, 4, 4, 9]


def test_jaccard_classes(docs, none):
    sets = []
    for i, t in ODD:
        w = [x.translate(LOWER) for x in words(t)]
        sets.append((i, {tuple(w[k : k + 4]) for k in range(len(w) - 3)} if len(w) > 3 else {tuple(w)} if w else set()))
    parent = {i: i for i, _ in sets if i is not None}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, s in sets:
        for b, t in sets:
            if a is not None and b is not None and s and t and 100 * len(s & t) >= 85 * len(s | t):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    got = jaccard_join.near_duplicates(docs).where("doc_id IS NOT NULL")
    same(got, ("doc_id", "n_shingles", "component_id"), [(i, len(s), find(i)) for i, s in sets if i is not None])
    assert jaccard_join.near_duplicates(none).count() == 0


def test_decontamination(spark, docs, none):
    items = spark.createDataFrame([("q1", PASSAGE), ("q2", "All rights"), ("q3", None), ("q4", "..."), ("q1", PASSAGE)], "item_id string, text string")
    pattern = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    windows = {}
    for name, t in (("q1", PASSAGE), ("q2", "All rights")):
        w = pattern.findall(t.translate(LOWER))
        for k in range(max(1, len(w) - 9)):
            windows.setdefault(tuple(w[k : k + 10]), set()).add(name)
    want = []
    for i, t in ODD:
        w = pattern.findall((t or "").translate(LOWER))
        hit, found = set(), set()
        for win, names in windows.items():
            for k in range(len(w) - len(win) + 1):
                if tuple(w[k : k + len(win)]) == win:
                    hit.update(range(k, k + len(win)))
                    found |= names
        want.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    same(decontaminate.find_contamination(docs, items), ("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"), want)
    clean = {r["doc_id"]: r["text"] for r in decontaminate.remove_contamination(docs, items).collect()}
    assert "p30" not in clean[8] and clean[8].startswith("x y ") and clean[4] == "a b c"
    assert decontaminate.find_contamination(none, items).count() == 0
    assert decontaminate.find_contamination(docs, items.where("false")).where("contaminated").count() == 0


def test_suffix_array():
    rng = np.random.default_rng(5)
    for n in (1, 2, 7, 200):
        t = rng.integers(0, 3, n)
        assert decontaminate.suffix_array(t).tolist() == sorted(range(n), key=lambda i: t[i:].tolist())


def test_url_trie(spark):
    rules = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("block", "org", "")]
    urls = [None, "", "no scheme", "http://EXAMPLE.com/en/70?x", "http://a.example.com/en/8#f", "https://org", "http://morg/x", "http://x.com/EN/", "://com/en/"]
    df = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.filter_urls(df, rules).collect()}
    assert got[0] == got[1] == got[2] == ("", "", None, "allow")
    assert got[3] == ("example.com", "/en/70", "example.com/en/7", "allow")
    assert got[4][2:] == ("com/en/", "block") and got[5][2:] == ("org", "block") and got[6][2:] == (None, "allow") and got[7][2] is None and got[8][2] == "com/en/"


def test_quality_ledger(docs, none):
    want = []
    for i, t in ODD:
        w = words(t)
        lines = [x for x in (t or "").split("\n") if words(x)]
        places = {}
        for k in range(len(w) - 4):
            places.setdefault(tuple(w[k : k + 5]), []).append(k)
        repeated = {j for p in places.values() if len(p) > 1 for k in p for j in range(k, k + 5)}
        want.append((i, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(repeated), len(w) < 10 or 100 * len(repeated) > 20 * len(w)))
    judged = quality_rules.judge(docs)
    same(judged, ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"), want)
    assert judged.where("kept AND base_failed").count() == 0
    assert quality_rules.judge(none).count() == 0
    kept = quality_rules.keep_good(docs)
    assert kept.columns == docs.columns and kept.count() == judged.where("kept").count()
    alone = {r["rule"]: r["fails_alone"] for r in quality_rules.ablations(quality_rules.measure(docs)).collect()}
    assert alone["few_words"] > 0


def test_pieces_like_the_library(docs, none):
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    lib = sentencepiece.SentencePieceProcessor(model_file=path)
    rng = np.random.default_rng(7)
    texts = [t or "" for _, t in ODD] + ["".join(rng.choice(list("  abcthe▁.,\né日🙂0"), n)) for n in rng.integers(0, 60, 500)] + ["the" * 400]
    tool = pieces.table(path)
    want = lib.encode(texts, add_bos=True, add_eos=True)
    assert tool.encode_batch(texts) == want
    assert [tool.decode(x) for x in want] == [lib.decode(x) for x in want]
    got = {(r["doc_id"], r["n_tokens"]) for r in pieces.encoding_digests(docs, path).collect()}
    assert got == {(i, len(x)) for (i, _), x in zip(ODD, want, strict=False)}
    assert pieces.encoding_digests(none, path).count() == 0


def test_token_counts_like_the_library(docs, none):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    lib = Tokenizer.from_file(path)
    want = [(i, len((t or "").encode()), len(lib.encode(t or "", add_special_tokens=False).ids)) for i, t in ODD]
    same(token_counts.count_tokens(docs, path), ("doc_id", "n_bytes", "n_tokens"), want)
    for t in ("a<|endoftext|>b", "it's İSTANBUL é ½", "O'Neil'S 'LL \x1c z"):
        assert token_counts.counter(path).count(t) == len(lib.encode(t, add_special_tokens=False).ids)
    assert token_counts.count_tokens(none, path).count() == 0


def test_license_scan(docs, none):
    want = []
    for i, t in ODD:
        w = re.findall(license_scan.WORD, (t or "").translate(LOWER))
        at, found = [], set()
        for phrase, label in license_scan.BASE.items():
            p = phrase.split()
            for k in range(len(w) - len(p) + 1):
                if w[k : k + len(p)] == p:
                    at.append(k)
                    found.add(label)
        want.append((i, len(w), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(found))))
    same(license_scan.scan(docs), ("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels"), want)
    assert license_scan.scan(none).count() == 0


def test_cross_entropy_tells_held_out_labels_apart(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    scored = lm_scoring.score_documents(docs, labels.where("doc_id % 2 = 0 AND quality = 1")).join(labels.where("doc_id % 2 = 1"), "doc_id").toPandas().dropna()
    rank, good = scored["score"].rank(), scored["quality"] == 1
    auc = 1 - (rank[good].sum() - good.sum() * (good.sum() + 1) / 2) / (good.sum() * (~good).sum())
    assert auc > 0.65


def test_cross_entropy_odd_rows(spark, docs, none):
    good = spark.createDataFrame([(6,), (6,), (None,), (999,)], "doc_id long")
    rows = lm_scoring.score_documents(docs, good).collect()
    assert len(rows) == len(ODD) and all((r["score"] is None) == (r["n_tokens"] == 0) for r in rows)
    assert lm_scoring.score_documents(none, good).count() == 0


def test_substring_dedup(docs, none):
    owner = {}
    for i, t in ODD:
        w = words(t)
        for k in range(len(w) - 12):
            if i is not None:
                owner[tuple(w[k : k + 13])] = min(owner.get(tuple(w[k : k + 13]), 99), i)
    want = []
    for i, t in ODD:
        w = words(t)
        gone = {j for k in range(len(w) - 12) if i is not None and owner[tuple(w[k : k + 13])] < i for j in range(k, k + 13)}
        kept = " ".join(x for j, x in enumerate(w) if j not in gone)
        want.append((i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    same(substring_dedup.removal_digests(docs), ("doc_id", "n_words", "n_removed", "kept_sha256"), want)
    after = substring_dedup.remove_repeats(docs)
    assert after.columns == docs.columns and after.count() == len(ODD)
    assert substring_dedup.removal_digests(none).count() == 0
