"""Exact near-duplicate classes of documents by word shingles: a grouped prefix join.

Sets. A document's set holds the 64-bit fingerprints of its distinct shingles. Documents with equal sets
collapse into one, named by its smallest id.

Order. Shingles that occur in one document only can match nothing; a count-min sketch of all shingles
(`shoal.llm.sketch`) finds them, and they come first in the global order; the others follow by the
sketch's rank of their frequency, then by fingerprint, so passages that many documents hold fill no
prefix that rarer shingles can fill. A set can only reach the threshold with a set that shares a shingle of its prefix, so a set
whose prefix holds single shingles only is alone, and most documents end here.

Signatures. Before whole sets travel, candidates must pass a bitmap bound: a bit that only one set's
signature has stands for at least one shingle that the other lacks.

Groups. Sets of equal size and equal (matchable) prefix form one group; groups that share a prefix
shingle, and pass the size and position filters, are candidates. They are expanded to members and
verified on the whole sets.

Hot groups. Wanted are classes, not pairs. So the first round verifies one pair a member (with the
smallest member of its group) and one a group (with the smallest group beside it). Buckets whose members
are in one class by then are done. From the others, a growing random share of leaders is verified
against the members of other classes, and at last all members are; by then few mixed buckets are left.
No candidate is dropped at any size.

Defined results: null or blank texts have an empty set, size 0, and are their own class; texts of fewer
words than a shingle are one shingle; rows that repeat an id get equal rows of that id's smallest class;
a row with a null id keeps a null class.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce
from operator import add

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shoal.core.components import star_labels
from shoal.core.storage import Scratch
from shoal.llm.sketch import repeated_items
from shoal.llm.storage import arrow_stage, tidy
from shoal.llm.words import PLAIN, as_strings, find_words, hash_windows, hash_words, mix, slices

#: 64-bit words of a set's signature: each shingle sets one of 2048 bits.
SIGNATURE = 32
#: Leaders of a mixed bucket in the second round; in the last round all members lead.
LEADERS = (64,)
#: Members of a part of a bucket; one task compares two parts, or one part with the bucket's leaders, at a time.
SPREAD = 2_000
#: Pairs that are compared at once.
PAIRS = 1 << 15


def shingle_sets(column: pa.Array, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Fingerprints of the distinct shingles of each text, rising, and where each text's begin."""
    words = find_words(column, PLAIN, lower=True)
    h = hash_words(words)
    at, value = hash_windows(words, h, width)
    text = words.text[at]
    counts = words.counts
    for n in range(1, width):
        short = np.flatnonzero(counts == n)
        if len(short):
            first = words.first[short]
            total = np.zeros(len(short), np.uint64)
            for j in range(n):
                total = total * np.uint64(0x9E3779B97F4A7C15) + h[first + j]
            value, text = np.append(value, mix(total ^ np.uint64(n))), np.append(text, short)
    order = np.lexsort((value, text))
    value, text = value[order], text[order]
    fresh = np.ones(len(value), bool)
    fresh[1:] = (value[1:] != value[:-1]) | (text[1:] != text[:-1])
    return value[fresh], np.searchsorted(text[fresh], np.arange(len(column) + 1))


def _signature(shingles: np.ndarray) -> np.ndarray:
    bits = np.zeros(SIGNATURE * 64, bool)
    bits[shingles % np.uint64(SIGNATURE * 64)] = True
    return np.packbits(bits, bitorder="little").view(np.int64)


def _lost(a: str, b: str) -> Column:
    """A lower bound of the shingles of set a that set b lacks: bits that only a's signature has."""
    bits = [F.bit_count(F.get(a, F.lit(i)).bitwiseAND(F.bitwise_not(F.get(b, F.lit(i))))) for i in range(SIGNATURE)]
    return reduce(add, bits)


def _items(width: int):
    def items(b: pa.RecordBatch) -> Iterator[np.ndarray]:
        column = as_strings(b.column(0))
        for low, high in slices(column):
            yield shingle_sets(column.slice(low, high - low), width)[0]

    return items


def near_duplicates(docs: DataFrame, width: int = 4, percent: int = 85, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: key, n_shingles, component_id (smallest id of its class)."""
    scratch = Scratch(docs.sparkSession, "jaccard")
    kind = docs.schema[key].dataType.simpleString()
    rows, unique = _sets(docs, width, percent, key, text, F.lit(0).cast("long"), scratch)
    labels = _labels(unique, scratch, percent)
    classes = unique.select(F.col("n").alias("un"), F.col("digest").alias("ud"), "rid").join(labels, F.col("rid") == F.col("id"), "left").select("un", "ud", F.coalesce("label", "rid").alias("label"))
    # sets that cannot match have no digest; they stay out of the join, where all of one size would meet in one task
    some = rows.where("digest IS NOT NULL").select("id", "n", "digest").join(classes, (F.col("digest") == F.col("ud")) & (F.col("n") == F.col("un")), "left").select("id", "n", "label")
    joined = some.unionAll(rows.where("digest IS NULL").select("id", "n", F.lit(None).cast("long").alias("label")))
    return joined.select(F.col("id").cast(kind).alias(key), F.col("n").alias("n_shingles"), F.coalesce("label", "id").cast(kind).alias("component_id"))


def text_mark(text: str) -> Column:
    """Tells rows of one id apart."""
    return F.xxhash64(text)


def other_copies(docs: DataFrame, width: int, percent: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, mark) of the rows that are not their class's kept one, mark being the row's `text_mark`.

    Here a set is its own node, whatever ids its rows have, so two texts of one id are two candidates. Kept is
    the set with the smallest id (then the smallest digest), in its rows of that id."""
    scratch = Scratch(docs.sparkSession, "copies")
    kind = docs.schema[key].dataType.simpleString()
    rows, unique = _sets(docs, width, percent, key, text, text_mark(text), scratch)
    node = F.xxhash64("digest", "n").bitwiseAND(F.lit((1 << 63) - 1))
    labels = _labels(unique.withColumn("rid", node), scratch, percent)
    linked = unique.select("digest", "rid", node.alias("node")).join(labels, F.col("node") == F.col("id")).select("digest", "rid", "label")
    kept = linked.groupBy("label").agg(F.min(F.struct("rid", "digest")).alias("k")).select(F.col("k.digest").alias("digest"))
    gone = linked.join(kept, "digest", "left_anti").select(F.col("digest").alias("gd"))
    sets = unique.select(F.col("n").alias("un"), F.col("digest").alias("ud"), "rid").join(gone, F.col("ud") == F.col("gd"), "left")
    joined = rows.select("id", "n", "digest", "mark").join(sets, (F.col("digest") == F.col("ud")) & (F.col("n") == F.col("un")))
    return joined.where("gd IS NOT NULL OR id <> rid").select(F.col("id").cast(kind).alias(key), "mark").distinct()


def _sets(docs: DataFrame, width: int, percent: int, key: str, text: str, mark: Column, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """The rows with their set's digest, and the distinct sets that can match, each with its smallest id."""
    found = repeated_items(docs, [F.col(text)], _items(width), ranked=True)

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """One row per document; the set itself and its prefix only where it can match and the task has not sent it yet."""
        sent: set[bytes] = set()
        for b in batches:
            column = as_strings(b.column(1))
            named = b.column(0).is_valid().to_pylist()
            for low, high in slices(column):
                value, first = shingle_sets(column.slice(low, high - low), width)
                common = found(value) if len(value) else np.zeros(0, bool)
                rank = found.rank(value) if len(value) else np.zeros(0, np.uint8)
                out: list[list] = [[], [], [], [], [], [], []]
                for i, (s, e) in enumerate(zip(first[:-1].tolist(), first[1:].tolist(), strict=True)):
                    n, body, prefix, digest, single, sign = e - s, None, None, None, 0, None
                    if n and named[low + i]:  # a row without an id is in no class, so it must not stand for its set
                        whole = value[s:e].tobytes()
                        shared = np.flatnonzero(common[s:e])
                        single = n - len(shared)
                        length = n - -(-percent * n // 100) + 1 - single  # matchable shingles in the prefix
                        if length > 0:
                            digest = hashlib.blake2b(whole, digest_size=16).digest()
                            if digest not in sent:
                                if len(sent) < 1_000_000:
                                    sent.add(digest)
                                first_ones = shared[np.argsort(rank[s:e][shared], kind="stable")[:length]]
                                body, prefix, sign = whole, value[s:e][first_ones].view(np.int64), _signature(value[s:e])
                    for column_out, v in zip(out, (n, single, digest, body, prefix, b.column(0)[low + i].as_py(), sign), strict=True):
                        column_out.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(out[5], b.column(0).type), pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.binary()), pa.array(out[3], pa.binary()), pa.array(out[4], pa.list_(pa.int64())), pa.array(out[6], pa.list_(pa.int64())), b.column(2).slice(low, high - low)], ["id", "n", "single", "digest", "body", "prefix", "sign", "mark"])

    rows = scratch.write(arrow_stage(docs, [F.col(key).cast("long"), F.col(text), mark], sets, "id long, n long, single long, digest binary, body binary, prefix array<long>, sign array<long>, mark long"))
    named = rows.where("digest IS NOT NULL AND id IS NOT NULL")
    unique = scratch.write(named.groupBy("n", "digest").agg(F.min("id").alias("rid"), F.first("single", True).alias("single"), F.first("body", True).alias("body"), F.first("prefix", True).alias("prefix"), F.first("sign", True).alias("sign")))
    return rows, unique


def _relabel(label: DataFrame | None, links: DataFrame, scratch: Scratch) -> DataFrame:
    """Labels (id, label) after more links: the links join labels, so only those are contracted anew."""
    if label is None:
        return star_labels(links, scratch)
    a, b = label.select(F.col("id").alias("u"), F.col("label").alias("lu")), label.select(F.col("id").alias("v"), F.col("label").alias("lv"))
    short = links.join(a, "u", "left").join(b, "v", "left").select(F.coalesce("lu", "u").alias("u"), F.coalesce("lv", "v").alias("v"))
    new = star_labels(short, scratch)
    ends = new.select(F.col("id").alias("nid"), F.col("label").alias("nl"))
    old = label.join(ends, F.col("label") == F.col("nid"), "left").select("id", F.coalesce("nl", "label").alias("label"))
    return scratch.write(old.union(new.join(label.select("id"), "id", "left_anti").select("id", "label")))


def _labels(unique: DataFrame, scratch: Scratch, percent: int) -> DataFrame:
    """(id, label): the class of every set that is linked, named by its smallest set."""
    members = unique.select("rid", "n", "single", F.xxhash64("prefix", "n").alias("group"), "prefix")
    groups = members.groupBy("group").agg(F.min("rid").alias("gid"))
    tokens = scratch.write(
        members.join(groups, "group").select("rid", "gid", "n", F.posexplode("prefix").alias("k", "token"), "single")
        .select("token", "rid", "gid", "n", (F.col("single") + F.col("k")).alias("pos"))
    )
    # first round: member and its group's name; group and the smallest group beside it
    own = tokens.where("rid <> gid").select(F.col("gid").alias("u"), F.col("rid").alias("v")).distinct()
    least = tokens.groupBy("token").agg(F.min("gid").alias("least"), F.max("gid").alias("most")).where("least < most").select("token", "least")
    beside = tokens.where("rid = gid").join(least, "token").where("least < gid").groupBy("gid").agg(F.min("least").alias("u")).select("u", F.col("gid").alias("v"))
    label = _relabel(None, scratch.write(_verify(_promising(own.union(beside), unique, percent), unique, percent)), scratch)
    for leaders in (*LEADERS, None):
        placed = tokens.join(label, F.col("rid") == F.col("id"), "left").select("token", "rid", "n", "pos", F.coalesce("label", "rid").alias("label"))
        mixed = placed.groupBy("token").agg(F.count("*").alias("size"), F.min("label").alias("a"), F.max("label").alias("b")).where("a < b").select(F.col("token").alias("bucket"), "size")
        signs = unique.select(F.col("rid").alias("sid"), "sign")
        open_ = scratch.write(placed.join(mixed, F.col("token") == F.col("bucket")).join(signs, F.col("rid") == F.col("sid")).drop("bucket", "sid"))
        if open_.isEmpty():
            break
        pairs = _tiles(open_, leaders).mapInArrow(tidy(_compared(percent)), "u long, v long").distinct()
        more = scratch.write(_verify(pairs, unique, percent))
        if not more.isEmpty():
            label = _relabel(label, more, scratch)
        done = leaders is None or open_.where(F.col("size") > leaders).isEmpty()
        scratch.drop(more, open_)
        if done:
            break
    scratch.drop(tokens)
    return label


def _tiles(rows: DataFrame, leaders: int | None) -> DataFrame:
    """The members of mixed buckets, dealt into tiles (token, a, b) of a bounded size whose left rows are to be compared with its right ones.

    A bucket is cut into parts of about SPREAD members. With `leaders`, a tile holds one part (right) and the bucket's
    leaders (left); without, each two parts of a bucket meet in a tile."""
    parts = F.ceil(F.col("size") / SPREAD).cast("int")
    cut = rows.withColumn("part", F.pmod(F.xxhash64("rid"), parts).cast("int")).withColumn("parts", parts)
    each = F.sequence(F.lit(0), F.col("parts") - 1)
    if leaders is None:
        tiles = cut.withColumn("other", F.explode(each)).withColumn("a", F.least("part", "other")).withColumn("b", F.greatest("part", "other"))
        tiles = tiles.withColumn("left", F.col("part") == F.col("a")).withColumn("right", F.col("part") == F.col("b"))
    else:
        leads = F.pmod(F.xxhash64("rid", F.lit(leaders)), F.greatest(F.lit(1), F.col("size") / leaders).cast("long")) == 0
        tiles = cut.withColumn("left", leads).withColumn("a", F.explode(F.when(F.col("left"), each).otherwise(F.array("part")))).withColumn("b", F.lit(-1))
        tiles = tiles.withColumn("right", F.col("part") == F.col("a"))
    dealt = tiles.select("token", "a", "b", "rid", "n", "pos", "label", "left", "right", "sign").repartition("token", "a", "b")
    return dealt.sortWithinPartitions("token", "a", "b")


def _compared(percent: int):
    """Pairs of a tile's left and right rows, in different classes, that their sizes, positions and signatures allow."""

    def pairs(tile: list[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        rid, n, pos, label, left, right, sign = tile
        ones = np.bitwise_count(sign).sum(axis=1, dtype=np.int64)
        lead, with_ = np.flatnonzero(left), np.flatnonzero(right)
        step = max(1, PAIRS // max(1, len(with_)))
        for low in range(0, len(lead), step):
            p, r = lead[low : low + step, None], with_[None, :]
            need = (n[p] + n[r]) * percent
            may = (label[p] != label[r]) & ((rid[p] < rid[r]) | ~(left[r] & right[p]))  # pairs that meet both ways are taken one way
            may &= (n[r] * 100 >= n[p] * percent) & (n[p] * 100 >= n[r] * percent)
            may &= np.minimum(n[p] - pos[p], n[r] - pos[r]) * (100 + percent) >= need
            i, j = np.nonzero(may)
            x, y = p[i, 0], r[0, j]
            both = np.bitwise_count(sign[x] & sign[y]).sum(axis=1, dtype=np.int64)
            most = np.minimum(n[x] - (ones[x] - both), n[y] - (ones[y] - both))  # bits of one signature only are lost shingles
            ok = most * (100 + percent) >= need[i, j]
            yield np.minimum(rid[x[ok]], rid[y[ok]]), np.maximum(rid[x[ok]], rid[y[ok]])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        at: tuple | None = None
        for batch in _ended(batches):
            if batch is None:
                cuts, keys, columns = [0], [None], []
            else:
                key = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
                fresh = np.ones(batch.num_rows, bool)
                fresh[1:] = reduce(np.logical_or, (k[1:] != k[:-1] for k in key))
                cuts = np.flatnonzero(fresh).tolist()
                keys = [tuple(int(k[c]) for k in key) for c in cuts]
                columns = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3, 9)]
                columns.append(batch.column(9).flatten().to_numpy(zero_copy_only=False).view(np.uint64).reshape(-1, SIGNATURE))
            for low, high, name in zip(cuts, [*cuts[1:], None], keys, strict=True):
                if name != at:
                    if held:
                        for u, v in pairs([np.concatenate(c) for c in zip(*held, strict=True)]):
                            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])
                    held, at = [], name
                if columns:
                    held.append([c[low:high] for c in columns])

    return compare


def _ended(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch | None]:
    """The batches with rows, and None after the last."""
    yield from (b for b in batches if b.num_rows)
    yield None


def _promising(pairs: DataFrame, unique: DataFrame, percent: int) -> DataFrame:
    """Pairs that pass the signature bound."""
    sign = unique.select("rid", "n", "sign")
    a, b = sign.toDF("ru", "l_n", "l_sign"), sign.toDF("rv", "n", "sign")
    both = pairs.join(a, F.col("u") == F.col("ru")).join(b, F.col("v") == F.col("rv"))
    return both.where(_reaches(percent)).select("u", "v")


def _reaches(percent: int) -> Column:
    """Whether sets (n, sign) and (l_n, l_sign) may share enough."""
    need = (F.col("n") + F.col("l_n")) * percent
    return ((F.col("n") - _lost("sign", "l_sign")) * (100 + percent) >= need) & ((F.col("l_n") - _lost("l_sign", "sign")) * (100 + percent) >= need)


def _verify(pairs: DataFrame, unique: DataFrame, percent: int) -> DataFrame:
    """The pairs whose whole sets reach the threshold."""
    body = unique.select(F.col("rid"), F.col("body"))
    both = pairs.join(body.select(F.col("rid").alias("ru"), F.col("body").alias("bu")), F.col("u") == F.col("ru")).select("u", "v", "bu").join(body.select(F.col("rid").alias("rv"), F.col("body").alias("bv")), F.col("v") == F.col("rv"))

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep = []
            for x, y in zip(b.column(2), b.column(3), strict=True):
                p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                if len(p) > len(q):
                    p, q = q, p
                shared = 0
                if 100 * len(p) >= percent * len(q):
                    at = np.minimum(np.searchsorted(q, p), len(q) - 1)
                    shared = int((q[at] == p).sum())
                keep.append(100 * shared >= percent * (len(p) + len(q) - shared))
            mask = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(0).filter(mask), b.column(1).filter(mask)], ["u", "v"])

    return arrow_stage(both, ["u", "v", "bu", "bv"], check, "u long, v long")
