"""The whole pipeline, and each stage on what its predecessor kept, against brute force."""

from __future__ import annotations

import hashlib
import random
import re

import corpus_pipeline
import public_tokenizers
import pytest

LOWER = str.maketrans({c: chr(c + 32) for c in range(65, 91)})
PIECE = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def corpus():
    draw = random.Random(3)
    vocabulary = [f"word{i}" for i in range(400)]
    fresh = lambda n: " ".join(draw.choice(vocabulary) for _ in range(n))
    passage, item = fresh(40), fresh(25)
    base = fresh(200)
    rows = [base, base, f"{base} tail", base.replace("word", "Word"), f"{fresh(60)} {passage} {fresh(30)}", f"{fresh(50)}\n{passage}, {fresh(20)}", f"{fresh(40)} {item.upper()} {fresh(40)}", "few words", "", None, "same five words again here " * 30, fresh(90), fresh(3000), "# $ % & # $ % & # $ % & #" * 3]
    docs = [(i + 1, t, "en", "web", len(t or "")) for i, t in enumerate(rows)] + [(5, fresh(80), "de", "web", 0), (None, fresh(70), None, None, None), (None, base, "en", "web", 1)]
    return docs, [("q1", item), ("q2", None), ("q3", "...")]


def quality(rows):
    out = []
    for r in rows:
        t = r[1] or ""
        w = words(t)
        places = {}
        for k in range(len(w) - 4):
            places.setdefault(tuple(w[k : k + 5]), []).append(k)
        repeated = {j for p in places.values() if len(p) > 1 for k in p for j in range(k, k + 5)}
        lines = [x for x in t.split("\n") if words(x)]
        chars = sum(map(len, w))
        bad = [len(w) < 10, 100 * len(repeated) > 20 * len(w), len(re.findall(r"[#*$%&|<>]", t)) > len(w), chars < len(w) or chars > 40 * len(w), 2 * (len(lines) - len(set(lines))) > len(lines) >= 4]
        if not any(bad):
            out.append(r)
    return out


def shingles(t):
    w = words((t or "").translate(LOWER))
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) > 4 else {tuple(w)} if w else set()


def copies(rows):
    """Of each class of rows with an id the one with the smallest id stays; rows in brute-force classes of sets."""
    sets = [(r, shingles(r[1])) for r in rows]
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, (r, a) in enumerate(sets):
        for j, (s, b) in enumerate(sets[:i]):
            if r[0] is not None and s[0] is not None and a and b and 100 * len(a & b) >= 80 * len(a | b):
                parent[find(i)] = find(j)
    groups = {}
    for i, r in enumerate(rows):
        if r[0] is not None:
            groups.setdefault(find(i), []).append(r)
    kept = [min(g, key=lambda r: r[0]) for g in groups.values()]
    return [r for r in rows if r[0] is None or r in kept]


def substrings(rows):
    owner = {}
    for r in rows:
        w = words(r[1])
        for k in range(len(w) - 12):
            if r[0] is not None:
                owner[tuple(w[k : k + 13])] = min(owner.get(tuple(w[k : k + 13]), r[0]), r[0])
    out = []
    for r in rows:
        w = words(r[1])
        gone = {j for k in range(len(w) - 12) if r[0] is not None and owner[tuple(w[k : k + 13])] < r[0] for j in range(k, k + 13)}
        t = " ".join(x for j, x in enumerate(w) if j not in gone) if gone else r[1]
        out.append((r[0], t, *r[2:4], len(t)))
    return out


def clean(rows, items):
    windows = set()
    for _, t in items:
        w = PIECE.findall((t or "").translate(LOWER))
        windows |= {tuple(w[k : k + 10]) for k in range(max(1, len(w) - 9))} if w else set()
    out = []
    for r in rows:
        found = list(PIECE.finditer(r[1].translate(LOWER)))
        w = [m.group() for m in found]
        hit = {j for x in windows for k in range(len(w) - len(x) + 1) if tuple(w[k : k + len(x)]) == x for j in range(k, k + len(x))}
        t, at = "", 0
        for j in sorted(hit):
            if j - 1 not in hit:
                t += r[1][at : found[j].start()]
            at = found[j].end()
        t += r[1][at:]
        out.append((r[0], t, *r[2:4], len(t)))
    return out


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("pipeline"))
    docs, items = corpus()
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame(items, "item_id string, text string").write.parquet(f"{d}/benchmark.parquet")
    return d


def same(df, want):
    assert sorted(map(repr, (tuple(r) for r in df.collect()))) == sorted(map(repr, want))


def test_stages_and_whole_run(spark, folder):
    import sentencepiece

    docs, items = corpus()
    kind = "doc_id long, text string, lang string, source string, n_chars long"
    now = docs
    for (name, stage), brute in zip(corpus_pipeline.STAGES[:4], (quality, copies, substrings, lambda r: clean(r, items)), strict=True):
        frame = spark.createDataFrame(now, kind)
        found, now = stage(spark, frame, folder), brute(now)
        assert found.columns == frame.columns, name
        same(found, now)
    lib = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    want = []
    for r in now:
        ids = lib.encode(r[1], add_bos=True, add_eos=True)
        packed = b"".join(i.to_bytes(4, "little") for i in ids)
        want.append((r[0], len(ids), hashlib.sha256(packed).hexdigest(), hashlib.sha256(lib.decode(ids).encode()).hexdigest()))
    found = corpus_pipeline.run(spark, folder)
    same(found.select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256"), want)
    assert len(want) >= 6


def test_empty_documents(spark, folder):
    empty = spark.read.parquet(f"{folder}/documents.parquet").where("false")
    for _, stage in corpus_pipeline.STAGES:
        empty_out = stage(spark, empty, folder)
        assert empty_out.count() == 0
