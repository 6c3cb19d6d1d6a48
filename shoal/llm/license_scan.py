"""Licence notices by a positional index of rare words. DataFrame functions only.

Templates. Each licence has a notice whose words are indexed as postings (word -> template, place, weight):
a constant map that any number of templates may fill; the plan does not grow with them. A word's weight is
its share of the notice's IDF, and only the `PER_TEMPLATE` rarest words of a notice are indexed. How rare
licence words are is counted over all documents. A template also has key phrases that must stand in the file.

Look-up. Of the index's words that a file holds, the `RARE` ones of highest IDF are looked up; each place
says where a template would begin (its position less the place in the notice). Postings are intersected by
that begin: weights that agree on template and begin are added up, and a template whose best begin has a
weight of at least `ENOUGH` is a candidate. Its label is given if all its key phrases stand in the file.
Base phrases are looked up by their rarest word at every place of it and compared word by word.

Words are lower-cased for A-Z only. Spark's lower() treats letters beyond ASCII too; the two of them that
would become ASCII letters are replaced by another letter beforehand, so no word of the index can arise.

Defined results: null and empty texts have no words, no label and score 0; every row is judged alone.
"""

from __future__ import annotations

import json
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: What words are made of; phrases of the base labels.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: The method's own labels: a notice and the key phrases that are mandatory.
TEMPLATES: dict[str, tuple[str, tuple[str, ...]]] = {
    "apache": ("licensed under the apache license version 2 0", ("apache license", "version 2")),
    "mit": ("permission is hereby granted free of charge to any person obtaining a copy of this software", ("permission is hereby granted free of charge",)),
    "bsd": ("redistribution and use in source and binary forms with or without modification are permitted", ("redistribution and use in source and binary forms",)),
    "mpl": ("this source code form is subject to the terms of the mozilla public license", ("mozilla public license",)),
    "cc": ("licensed under a creative commons attribution license", ("creative commons",)),
    "copyright": ("copyright c", ("copyright c",)),
    "public-domain": ("released into the public domain", ("public domain",)),
}
#: Indexed words of a notice; words of a file that are looked up; weight at one begin that makes a candidate.
PER_TEMPLATE, RARE, ENOUGH = 8, 8, 0.25


def _words(text: Column) -> Column:
    plain = F.replace(F.replace(F.coalesce(text, F.lit("")), F.lit("K"), F.lit("ø")), F.lit("İ"), F.lit("ø"))
    return F.regexp_extract_all(F.lower(plain), F.lit(WORD), F.lit(0))


def _constant(value: object, kind: str) -> Column:
    """One constant of any size: a single node of the plan."""
    return F.from_json(F.lit(json.dumps(value)), kind)


def word_idf(docs: DataFrame, templates: dict[str, tuple[str, tuple[str, ...]]], text: str = "text") -> dict[str, float]:
    """IDF of every licence word over all documents."""
    known = sorted({w for t in [*BASE, *(n for n, _ in templates.values())] for w in t.split()})
    # never empty; the outer form keeps Catalyst from adding a filter that would cut the texts once more
    held = docs.select(F.array_append(F.array_intersect(_constant(known, "array<string>"), _words(F.col(text))), F.lit("")).alias("w"))
    counts = {r["word"]: r["n"] for r in held.select(F.explode_outer("w").alias("word")).groupBy("word").agg(F.count("*").alias("n")).collect()}
    return {w: math.log((1 + counts.get("", 0)) / (1 + counts.get(w, 0))) for w in known}


def postings(templates: dict[str, tuple[str, tuple[str, ...]]], idf: dict[str, float]) -> dict[str, list[dict]]:
    """word -> where it stands in which notice, and its weight there."""
    out: dict[str, list[dict]] = {}
    for name, (notice, _) in templates.items():
        words = notice.split()
        places = sorted(range(len(words)), key=lambda k: (-idf[words[k]], k))[:PER_TEMPLATE]
        total = sum(idf[words[k]] for k in places)
        for k in places:
            out.setdefault(words[k], []).append({"name": name, "at": k, "weight": idf[words[k]] / total if total else 0.0})
    return out


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", templates: dict[str, tuple[str, tuple[str, ...]]] = TEMPLATES) -> DataFrame:
    """One row per document: key, n_words, n_base, first_word, last_word, base_labels, labels, score.

    The score is the greatest weight of a template at one begin; 1 where a base phrase stands."""
    idf = word_idf(docs, templates, text)
    index = postings(templates, idf)
    ranked = _constant(sorted(index, key=lambda w: (-idf[w], w)), "array<string>")
    posted = _constant(index, "map<string,array<struct<name:string,at:int,weight:double>>>")
    phrases = []
    for phrase, label in BASE.items():
        words = phrase.split()
        rare = min(words, key=lambda w: (-idf[w], w))
        phrases.append({"label": label, "words": words, "rare": rare, "at": words.index(rare)})
    base = _constant(phrases, "array<struct<label:string,words:array<string>,rare:string,at:int>>")
    keys = _constant([{"name": n, "keys": [f" {k} " for k in ks]} for n, (_, ks) in templates.items()], "array<struct<name:string,keys:array<string>>>")

    w, look, h = F.col("__w"), F.col("__look"), F.col("__h")
    cut = docs.select(F.col(key).alias("__k"), _words(F.col(text)).alias("__w"))
    asked = sorted({p["rare"] for p in phrases})
    found = cut.select("__k", "__w", F.array_intersect(_constant([*dict.fromkeys([*index, *asked])], "array<string>"), w).alias("__found"))
    chosen = found.select("__k", "__w", F.slice(F.array_intersect(ranked, "__found"), 1, RARE).alias("__rare"), F.array_intersect(_constant(asked, "array<string>"), F.col("__found")).alias("__base"))
    looked = chosen.select("*", F.array_union("__rare", "__base").alias("__look"))
    places = F.filter(F.transform(w, lambda x, i: F.when(F.array_contains(look, x), F.struct(x.alias("w"), i.alias("p")))), lambda x: x.isNotNull())
    held = looked.select("__k", "__w", "__rare", F.when(F.size(look) > 0, places).alias("__h"))

    # the begins that each rare word implies, in order, so that equal ones follow each other
    implied = F.flatten(F.transform(F.filter(h, lambda x: F.array_contains("__rare", x["w"])), lambda x: F.transform(F.element_at(posted, x["w"]), lambda q: F.struct(q["name"].alias("name"), (x["p"] - q["at"]).alias("begin"), q["weight"].alias("weight")))))
    none = F.lit("")
    start = F.struct(none.alias("name"), F.lit(0).alias("begin"), F.lit(0.0).alias("sum"), F.lit(0.0).alias("best"), F.array().cast("array<string>").alias("found"))

    def step(a: Column, x: Column) -> Column:
        same = (a["name"] == x["name"]) & (a["begin"] == x["begin"])
        total = F.when(same, a["sum"] + x["weight"]).otherwise(x["weight"])
        found = F.when((total >= ENOUGH) & ~F.array_contains(a["found"], x["name"]), F.array_append(a["found"], x["name"])).otherwise(a["found"])
        return F.struct(x["name"].alias("name"), x["begin"].alias("begin"), total.alias("sum"), F.greatest(a["best"], total).alias("best"), found.alias("found"))

    met = held.select("__k", "__w", "__h", F.when(F.size("__rare") > 0, F.aggregate(F.array_sort(implied), start, step)).alias("__m"))
    stands = F.flatten(
        F.transform(base, lambda b: F.transform(
            F.filter(h, lambda x: (x["w"] == b["rare"]) & (x["p"] >= b["at"]) & (F.slice(w, F.greatest(x["p"] - b["at"], F.lit(0)) + 1, F.size(b["words"])) == b["words"])),
            lambda x: F.struct((x["p"] - b["at"]).alias("s"), b["label"].alias("label")),
        ))
    )
    line = F.concat(F.lit(" "), F.array_join(w, " "), F.lit(" "))
    own = F.transform(F.filter(keys, lambda t: F.array_contains("__m.found", t["name"]) & F.forall(t["keys"], lambda k: F.contains("__line", k))), lambda t: t["name"])
    empty = F.array().cast("array<string>")
    judged = met.select("__k", F.size(w).cast("long").alias("n_words"), "__m", F.when(F.size("__m.found") > 0, line).alias("__line"), F.when(h.isNotNull(), stands).alias("__s"))
    labelled = judged.select("__k", "n_words", "__s", "__m", F.when(F.col("__line").isNotNull(), own).otherwise(empty).alias("__own"))
    joined = lambda parts: F.array_join(F.array_sort(F.array_distinct(parts)), ",")
    based = F.coalesce(F.col("__s.label"), empty)
    n_base = F.coalesce(F.size("__s"), F.lit(0))
    return labelled.select(
        F.col("__k").alias(key), "n_words", F.greatest(n_base, F.lit(0)).cast("long").alias("n_base"), F.array_min("__s.s").cast("long").alias("first_word"), F.array_max("__s.s").cast("long").alias("last_word"),
        joined(based).alias("base_labels"), joined(F.concat(based, "__own")).alias("labels"),
        F.round(F.when(n_base > 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), F.coalesce("__m.best", F.lit(0.0)))), 6).alias("score"),
    )
