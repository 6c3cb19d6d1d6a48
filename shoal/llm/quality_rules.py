"""Quality rules as a ledger of failure bits and measurements. DataFrame functions only.

`measure` evaluates every rule once per document, all inside the row: no shuffle, no Python. The ledger
keeps the measurements and one bit a rule. Policies are versioned masks over those bits, so a new policy
or an ablation ("what would go or stay without this rule") is bit arithmetic on the ledger, not a new
pass over the texts.

Repeated windows are found by fingerprints (64 bits, compared inside one document only): texts whose
windows are all distinct are done after a hash set; only the others sort their windows.

Defined results: null and empty texts have no words, so they fail the rule on few words; every row is
judged alone, so repeats and ties give equal rows; extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: What words are made of, and which characters count as symbols.
WORD = r"[^\x20\x09-\x0D]+"
SYMBOL = r"[#*$%&|<>]"
WINDOW = 5

#: Rules in the order of their bits: a failing document has the bit set.
RULES: dict[str, Column | str] = {
    "few_words": "n_words < 10",
    "repeated_words": "100 * n_repeat_words > 20 * n_words",
    "symbols": "n_symbols > n_words",
    "word_length": "word_chars < n_words OR word_chars > 40 * n_words",
    "repeated_lines": "2 * n_dup_lines > n_lines AND n_lines >= 4",
}
#: Versions of the policy: the rules whose failure rejects a document.
POLICIES: dict[str, tuple[str, ...]] = {
    "base": ("few_words", "repeated_words"),
    "v1": ("few_words", "repeated_words", "symbols", "word_length", "repeated_lines"),
}
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def mask(policy: str) -> int:
    return sum(1 << k for k, rule in enumerate(RULES) if rule in POLICIES[policy])


def measure(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The ledger: the kept columns, the measurements and `bits`."""
    names = [f"__k{i}" for i in range(len(keep))]
    body = F.coalesce(F.col(text), F.lit(""))
    base = docs.select(*(F.col(c).alias(n) for c, n in zip(keep, names, strict=True)), body.alias("__t"))
    cut = base.select(*names, "__t", F.regexp_extract_all("__t", F.lit(WORD), F.lit(0)).alias("__w"), F.filter(F.split("__t", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("__l"))
    w, n = F.col("__w"), F.size("__w")
    window = F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*(F.get(w, i + j) for j in range(WINDOW))))
    hashed = cut.select(
        *names, n.cast("long").alias("n_words"), F.length(F.array_join("__w", "")).cast("long").alias("word_chars"), F.regexp_count("__t", F.lit(SYMBOL)).cast("long").alias("n_symbols"),
        F.size("__l").cast("long").alias("n_lines"), (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long").alias("n_dup_lines"), F.when(n > WINDOW, window).alias("__h"),
    )
    some = F.size(F.array_distinct("__h")) < F.size("__h")
    ranked = hashed.withColumn("__s", F.when(some, F.sort_array(F.transform("__h", lambda x, i: F.struct(x.alias("h"), i.alias("p"))))))
    s = F.col("__s")
    twice = F.transform(s, lambda x, i: F.when(x["h"].eqNullSafe(F.get(s, i - 1)["h"]) | x["h"].eqNullSafe(F.get(s, i + 1)["h"]), x["p"]))
    placed = ranked.withColumn("__p", F.when(s.isNotNull(), F.sort_array(F.array_compact(twice)))).drop("__h", "__s")
    p = F.col("__p")
    covered = F.aggregate(F.transform(p, lambda x, i: F.least(F.lit(WINDOW), F.coalesce(F.get(p, i + 1) - x, F.lit(WINDOW))).cast("long")), F.lit(0).cast("long"), lambda a, b: a + b)
    counted = placed.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0).cast("long")))
    bits = [F.when(F.expr(rule) if isinstance(rule, str) else rule, F.lit(1 << k).cast("long")).otherwise(F.lit(0).cast("long")) for k, rule in enumerate(RULES.values())]
    total = bits[0]
    for b in bits[1:]:
        total = total.bitwiseOR(b)
    # Catalyst must not push a later filter on the bits below this projection: it would put the whole
    # expression tree into the filter and build the arrays anew for each of their elements.
    total = total.bitwiseOR(F.monotonically_increasing_id().bitwiseAND(F.lit(0).cast("long")))
    return counted.select(*(F.col(n).alias(c) for c, n in zip(keep, names, strict=True)), *MEASURES, total.alias("bits"))


def passes(policy: str) -> Column:
    return F.col("bits").bitwiseAND(F.lit(mask(policy)).cast("long")) == 0


def judge(docs: DataFrame, policy: str = "v1", key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: key, the measurements, base_failed, kept, bits."""
    ledger = measure(docs, text, (key,))
    failed = ~passes("base")
    return ledger.select(key, *MEASURES, failed.alias("base_failed"), (~failed & passes(policy)).alias("kept"), "bits")


def keep_good(docs: DataFrame, policy: str = "v1", text: str = "text") -> DataFrame:
    """The documents that pass, with all their columns."""
    names = tuple(f"__c{i}" for i in range(len(docs.columns)))  # columns may be named like measurements
    ledger = measure(docs.toDF(*names), names[docs.columns.index(text)], names)
    return ledger.where(passes(policy) & passes("base")).select(*names).toDF(*docs.columns)


def ablations(ledger: DataFrame, policy: str = "v1") -> DataFrame:
    """For each rule of a policy: documents that fail it, that fail it alone (they would stay without it), and all that go."""
    whole = F.lit(mask(policy)).cast("long")
    used = F.col("bits").bitwiseAND(whole)
    sums = [F.count("*").alias("n"), F.sum((used != 0).cast("long")).alias("gone")]
    for rule in POLICIES[policy]:
        bit = F.lit(1 << list(RULES).index(rule)).cast("long")
        sums += [F.sum((used.bitwiseAND(bit) != 0).cast("long")).alias(f"any_{rule}"), F.sum((used == bit).cast("long")).alias(f"only_{rule}")]
    one = ledger.agg(*sums)
    rows = F.array(*(F.struct(F.lit(policy).alias("policy"), F.lit(r).alias("rule"), F.col("n"), F.col("gone"), F.col(f"any_{r}").alias("fails"), F.col(f"only_{r}").alias("fails_alone")) for r in POLICIES[policy]))
    return one.select(F.inline(rows))
