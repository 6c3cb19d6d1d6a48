"""Labels and scores of the licence index (op8) against brute force; templates of any number in a plan of one size."""

from __future__ import annotations

import re

from shoal.llm import license_scan

TEXTS = [
    "Licensed under the Apache License, Version 2.0 (the \"License\")", "apache version 2", "see the Mozilla Public License for all", "public domain work released into the public domain",
    "Permission is hereby granted, free of charge, to any person", "granted free permission", "copyright (c) 1999", "all rights reserved. cc by", "nothing of the kind", None, "", "apache license version 2 " * 50,
    "İ K mozilla public license K", "Redistribution and use in source and binary forms, with or without x", "a creative commons work", "cc by cc by cc all rights reserved",
]


def brute(texts, templates):
    cut = [re.findall(license_scan.WORD, "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")) for t in texts]
    import math

    known = {w for x in [*license_scan.BASE, *(n for n, _ in templates.values())] for w in x.split()}
    idf = {w: math.log((1 + len(cut)) / (1 + sum(w in c for c in cut))) for w in known}
    index = {}
    for name, (notice, _) in templates.items():
        words = notice.split()
        best = sorted(range(len(words)), key=lambda k: (-idf[words[k]], k))[: license_scan.PER_TEMPLATE]
        total = sum(idf[words[k]] for k in best)
        for k in best:
            index.setdefault(words[k], []).append((name, k, idf[words[k]] / total if total else 0.0))
    out = []
    for c in cut:
        rare = sorted((w for w in index if w in c), key=lambda w: (-idf[w], w))[: license_scan.RARE]
        sums = {}
        for p, w in enumerate(c):
            for name, k, weight in index[w] if w in rare else ():
                sums[name, p - k] = sums.get((name, p - k), 0.0) + weight
        line = f" {' '.join(c)} "
        own = {n for (n, _), s in sums.items() if s >= license_scan.ENOUGH and all(f" {k} " in line for k in templates[n][1])}
        at = [(k, label) for phrase, label in license_scan.BASE.items() for k in range(len(c)) if c[k : k + len(phrase.split())] == phrase.split()]
        base = {label for _, label in at}
        score = 1.0 if at else min(1.0, max(sums.values(), default=0.0))
        out.append((len(c), len(at), min((k for k, _ in at), default=None), max((k for k, _ in at), default=None), ",".join(sorted(base)), ",".join(sorted(base | own)), score))
    return out


def check(spark, templates):
    docs = spark.createDataFrame([(i, t, 5) for i, t in enumerate(TEXTS)], "doc_id long, text string, score int")
    found = license_scan.scan(docs, templates=templates)
    got = {r["doc_id"]: tuple(r)[1:] for r in found.collect()}
    for i, want in enumerate(brute(TEXTS, templates)):
        assert got[i][:-1] == want[:-1] and abs(got[i][-1] - want[-1]) < 2e-6, (i, got[i], want)
    return found


def test_labels_and_scores(spark):
    rows = {r["doc_id"]: r["labels"] for r in check(spark, license_scan.TEMPLATES).collect()}
    assert rows[0] == "apache" and rows[4] == "mit" and rows[13] == "bsd" and rows[8] == ""


def test_many_templates_do_not_widen_the_plan(spark):
    many = license_scan.TEMPLATES | {f"t{i}": (f"word{i} licence{i} of the kind number{i}", (f"word{i}",)) for i in range(300)}
    sizes = [len(check(spark, t)._jdf.queryExecution().analyzed().toString().split("lambda")) for t in (license_scan.TEMPLATES, many)]
    assert sizes[0] == sizes[1]
