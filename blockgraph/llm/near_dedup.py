"""MinHash near-dedup: universal hash minima with banding, signature verification, exact confirmation, components.

A document's set holds the distinct runs of five words (A-Z lower-cased) or, with fewer words, its whole sequence. Two
documents are linked if 100 * |intersection| >= 75 * |union|; groups are the components of the links.

1. Equal word sequences form one class, kept by its earliest document; only classes go on, so exact copies cost one
   row each.
2. Each class has 192 minima of multiply-add hashes in 48 bands of 4. A pair at 0.75 shares a band but for a chance of
   1.2e-8, a pair at 0.8 but for 2e-11. In each band bucket every class is paired with the bucket's smallest one only.
3. Components of those pairs are clusters: two classes that share any bucket are in one cluster. A cluster of at most
   `block` classes is settled in one task. In a larger one each class first meets the smallest class of each of its
   buckets, at most `block` of them a task; after that only open buckets are left, those whose classes are not yet one
   component, and the blocks of such a bucket meet two by two. So classes that share no bucket are never compared,
   however far clusters are chained. In a task signatures are compared first (a pair at 0.75 fails that test with a
   chance of about 1e-8), then full sets. Pairs already joined are skipped and only links that join something are
   emitted, so a task emits fewer links than it holds documents.
4. Components of the links, by large-star and small-star, name the groups.

Defined results: null or wordless texts have an empty set and are linked with nothing; rows with one doc_id are one
document for grouping (they always share a group, but for wordless ones), each with its own n_shingles; rows with a null
doc_id are left out; repeated rows are answered each; other columns, whatever their names, are ignored; an empty table
gives an empty result. Very long texts are read whole; a text's set, 8 bytes a shingle, is in a task's memory.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import ODD, forget, gram_hashes, materialise, mix, text_key, texts_of, word_bounds, word_hashes
from ._components import components

SHINGLE = 5
BANDS, ROWS = 48, 4
BLOCK = 1024
AGREE = 108
SLOTS = 1 << 26
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def _multipliers() -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20240229)
    n = BANDS * ROWS
    return rng.integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 1 << 63, n, dtype=np.uint64)


def normalised(text: bytes) -> bytes:
    return b" ".join(text.translate(_LOWER).split())


def shingles(text: bytes) -> np.ndarray:
    """Sorted distinct hashes of the shingles of a normalised text."""
    data = np.frombuffer(text, np.uint8)
    starts, ends = word_bounds(data)
    if not len(starts):
        return np.zeros(0, np.uint64)
    return np.unique(gram_hashes(word_hashes(data, starts, ends), min(SHINGLE, len(starts))))


def minima(members: np.ndarray, times: np.ndarray, plus: np.ndarray) -> np.ndarray:
    out = np.full(len(times), np.iinfo(np.uint64).max)
    for at in range(0, len(members), 256):
        np.minimum(out, (members[at : at + 256, None] * times + plus).min(axis=0), out=out)
    return out


def _bands(signature: np.ndarray) -> np.ndarray:
    rows = signature.reshape(BANDS, ROWS)
    key = np.arange(BANDS, dtype=np.uint64)
    for r in range(ROWS):
        key = mix(key * ODD + rows[:, r])
    return key.view(np.int64)


def _profile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    times, plus = _multipliers()
    for batch in batches:
        same, sizes, bands = [], [], []
        known: dict[bytes, int] = {}
        for text in texts_of(batch.column(2)):
            text = normalised(text)
            mark = hashlib.blake2b(text, digest_size=16).digest()
            same.append(mark)
            k = known.setdefault(mark, len(sizes))
            if k < len(sizes):
                sizes.append(sizes[k])
                bands.append(bands[k])
                continue
            members = shingles(text)
            sizes.append(len(members))
            bands.append(_bands(minima(members, times, plus)).tobytes() if len(members) else b"")
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(same, pa.binary()), pa.array(sizes, pa.int64()), pa.array(bands, pa.binary())], ["doc_id", "key", "same", "n_shingles", "bands"])


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        keys = b"".join(batch.column(1).to_pylist())
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(0).to_numpy(), BANDS)), pa.array(np.frombuffer(keys, np.int64))], ["node", "bucket"])


TASKS = "array<struct<place:long,part:int,kind:int,side:int>>"


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    times, plus = _multipliers()
    for whole in batches:
        for at in range(0, whole.num_rows, 512):  # sets are larger than texts: small batches leave
            batch = whole.slice(at, 512)
            sets, signatures = [], []
            for text in texts_of(batch.column(batch.schema.get_field_index("text"))):
                members = shingles(normalised(text))
                sets.append(members.tobytes())
                signatures.append(minima(members, times, plus).astype(np.uint16).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(sets, pa.binary()), pa.array(signatures, pa.binary())], ["node", "joined", "tasks", "members", "signature"])


def joining_links(nodes: list[int], sets: list[np.ndarray], signatures: np.ndarray, side: np.ndarray | None, joined: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that connect what all links of the given documents connect; side: only pairs of different sides count;
    joined: a number for each document, equal where they are known to be connected.

    The smallest document is tried first against all, then each document against those of other groups.
    """
    n = len(nodes)
    group = np.arange(n) if joined is None else np.unique(joined, return_inverse=True)[1]
    sizes = np.array([len(s) for s in sets])
    starts = np.concatenate(([0], np.cumsum(sizes)[:-1]))
    _, codes = np.unique(np.concatenate(sets), return_inverse=True)
    mark = np.zeros(codes.max() + 1, bool)
    links = []
    for x in range(n):
        other = group != group[x]
        other[:x] = False
        if side is not None:
            other &= side != side[x]
        near = np.flatnonzero(other & (100 * np.minimum(sizes, sizes[x]) >= 75 * np.maximum(sizes, sizes[x])))
        if len(near):
            near = near[(signatures[near] == signatures[x]).sum(axis=1) >= AGREE]
        if not len(near):
            continue
        own = codes[starts[x] : starts[x] + sizes[x]]
        mark[own] = True
        if len(near) > n // 4:
            both = np.add.reduceat(mark[codes], starts, dtype=np.int64)[near]
        else:
            both = np.array([mark[codes[starts[y] : starts[y] + sizes[y]]].sum() for y in near.tolist()])
        mark[own] = False
        for y in near[100 * both >= 75 * (sizes[near] + sizes[x] - both)].tolist():
            if group[y] != group[x]:
                links.append((nodes[x], nodes[y]))
                group[group == group[y]] = group[x]
    return links


def _confirm(members: pa.Table) -> pa.Table:
    rows = sorted(zip(*(members.column(c).to_pylist() for c in ("node", "members", "signature", "side", "joined")), strict=True))
    nodes, side = [r[0] for r in rows], np.array([r[3] for r in rows])
    links = joining_links(nodes, [np.frombuffer(r[1], np.uint64) for r in rows], np.array([np.frombuffer(r[2], np.uint16) for r in rows]), None if side[0] < 0 else side, np.array([r[4] for r in rows]))
    return pa.table([pa.array([a for a, _ in links], pa.int64()), pa.array([b for _, b in links], pa.int64())], names=["a", "b"])


def _task(place: str, part: Column, kind: int, side: Column) -> Column:
    """One meeting: what it is about, which part of it, of what kind, and the side that the class is on (-1: no sides)."""
    return F.struct(F.col(place).alias("place"), part.cast("int").alias("part"), F.lit(kind).alias("kind"), side.cast("int").alias("side"))


def _hashed(node: str, parts: Column) -> Column:
    return F.pmod(F.xxhash64(node), parts).cast("int")


def _slot(node: str, key: str) -> Column:
    return F.xxhash64(node, key).bitwiseAND(F.lit(SLOTS - 1)) + 1  # bitmap functions count from 1


def likely(rows: DataFrame, chosen: DataFrame) -> DataFrame:
    """The rows(node, key, ...) that may be among chosen(node, key, ...): all that are and few others. By a bitmap of SLOTS
    bits (8 MB), whatever the corpus, so texts that meet nobody are not shuffled."""
    slot = chosen.select(_slot("node", "key").alias("slot"))
    pieces = slot.groupBy(F.bitmap_bucket_number("slot").alias("piece")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("bits"))
    place = F.bitmap_bit_position(_slot("node", "key"))
    asked = rows.withColumns({"piece": F.bitmap_bucket_number(_slot("node", "key")), "byte": F.floor(place / 8).cast("int") + 1, "bit": F.pmod(place, F.lit(8))})
    mask = F.element_at(F.array(*[F.lit(1 << k) for k in range(8)]), F.col("bit").cast("int") + 1)
    held = F.conv(F.hex(F.substring("bits", F.col("byte"), F.lit(1))), 16, 10).cast("int").bitwiseAND(mask) != 0
    return asked.join(F.broadcast(pieces), "piece").where(held).select(rows.columns)


def _star_tasks(pairs: DataFrame, block: int) -> DataFrame:
    """node, task: the smallest class of each bucket and the others, at most about `block` of them a task."""
    parts = pairs.groupBy(F.col("b").alias("least")).agg(F.ceil(F.count("*") / block).cast("int").alias("parts"))
    others = pairs.join(parts, pairs["b"] == parts["least"]).select(F.col("a").alias("node"), _task("least", _hashed("a", F.col("parts")), 1, F.lit(1)).alias("task"))
    centres = parts.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    return others.unionAll(centres.select(F.col("least").alias("node"), _task("least", F.col("part"), 1, F.lit(0)).alias("task")))


def _bucket_tasks(buckets: DataFrame, joined: DataFrame, block: int) -> DataFrame:
    """node, task: the blocks of each open bucket two by two; a bucket is open if its classes are not yet one component."""
    placed = buckets.join(joined, "node", "left").withColumn("joined", F.coalesce("joined", "node"))
    open_ = placed.groupBy("bucket").agg(F.min("joined").alias("low"), F.max("joined").alias("high"), F.ceil(F.count("*") / block).cast("int").alias("parts")).where("low <> high")
    own = buckets.join(open_.select("bucket", "parts"), "bucket").withColumn("own", _hashed("node", F.col("parts")))
    dealt = own.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    pair = F.least("own", "with") * F.col("parts") + F.greatest("own", "with")  # parts: far below 2^15, a bucket of 2^25 classes
    return dealt.select("node", _task("bucket", pair, 2, F.when(F.col("own") == F.col("with"), -1).otherwise(F.col("own"))).alias("task"))


def _shared_ids(profiles: DataFrame, classes: DataFrame) -> DataFrame:
    """Links between classes that hold rows of one doc_id."""
    worded = profiles.where("n_shingles > 0")
    several = worded.groupBy("doc_id").agg(F.min("same").alias("one"), F.max("same").alias("other")).where("one <> other").select("doc_id", "one")
    pairs = worded.select("doc_id", "same").join(several, "doc_id").where("same <> one").select("one", "same").distinct()
    name = classes.select("same", F.col("doc_id").alias("node"))
    return pairs.join(name.withColumnRenamed("node", "a"), "same").drop("same").join(name.select(F.col("same").alias("one"), F.col("node").alias("b")), "one").select("a", "b").where("a <> b")


def near_duplicates(spark: SparkSession, docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """doc_id, key (a hash of the text), n_shingles and component_id of each row of docs(doc_id, text)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(F.col("text")).alias("key"), F.coalesce("text", F.lit("")).alias("text")).where(F.col("doc_id").isNotNull())
    profiles = materialise(rows.mapInArrow(_profile, "doc_id long, key long, same binary, n_shingles long, bands binary"), "profiles")
    classes = materialise(profiles.groupBy("same").agg(F.min(F.struct("doc_id", "key")).alias("first"), F.first("bands").alias("bands")).select("same", "first.*", "bands"), "classes")

    buckets = classes.where(F.length("bands") > 0).select(F.col("doc_id").alias("node"), "bands").mapInArrow(_unpack, "node long, bucket long")
    least = buckets.groupBy("bucket").agg(F.min("node").alias("least"), F.count("*").alias("n")).where("n > 1").drop("n")
    shared = materialise(buckets.join(least, "bucket").select("node", "bucket", "least"), "shared")  # buckets of one class lead nowhere
    pairs = shared.where("node <> least").select(F.col("node").alias("a"), F.col("least").alias("b")).distinct()
    clusters = materialise(components(pairs, "clusters"), "clustered")
    large = clusters.groupBy("root").agg(F.count("*").alias("n")).where(F.col("n") > block).select("root")

    def links_of(tasks: DataFrame, joined: DataFrame | None, label: str) -> DataFrame:
        """The joining links of all meetings in tasks(node, task)."""
        dealt = tasks.groupBy("node").agg(F.collect_list("task").alias("tasks"))
        known = dealt.withColumn("joined", F.col("node")) if joined is None else dealt.join(joined, "node", "left").withColumn("joined", F.coalesce("joined", "node"))
        chosen = materialise(known.join(classes.select(F.col("doc_id").alias("node"), "key"), "node"), "chosen")
        texts = likely(rows.withColumnRenamed("doc_id", "node"), chosen).join(chosen.hint("merge"), ["node", "key"]).select("node", "joined", "tasks", "text")  # one plan at every size
        sets = texts.mapInArrow(_sets, f"node long, joined long, tasks {TASKS}, members binary, signature binary")
        met = sets.select("node", "joined", "members", "signature", F.inline("tasks"))
        found = materialise(met.groupBy("place", "part", "kind").applyInArrow(_confirm, "a long, b long"), label)
        forget(chosen)
        return found

    small = clusters.join(large, "root", "left_anti").select("node", _task("root", F.lit(0), 0, F.lit(-1)).alias("task"))
    if large.isEmpty():
        links = links_of(small, None, "links")
    else:
        inside = materialise(clusters.join(large, "root", "left_semi").select("node"), "large")
        stars = pairs.join(inside.select(F.col("node").alias("a")), "a", "left_semi")
        first = links_of(small.unionAll(_star_tasks(stars, block)), None, "links")
        joined = materialise(components(first, "joined").withColumnRenamed("root", "joined"), "joined")
        rest = _bucket_tasks(shared.select("node", "bucket").join(inside, "node", "left_semi"), joined, block)
        links = first.unionAll(links_of(rest, joined, "links"))
        forget(inside)
        forget(joined)
    forget(shared)
    forget(clusters)
    groups = components(links.unionAll(_shared_ids(profiles, classes)), "groups").select(F.col("node").alias("doc_id"), "root")
    named = classes.select("same", "doc_id").join(groups, "doc_id", "left").select("same", F.coalesce("root", "doc_id").alias("component_id"))
    alone = F.when(F.col("n_shingles") == 0, F.col("doc_id")).otherwise(F.col("component_id"))  # wordless texts are one class, but no group
    return profiles.select("doc_id", "key", "same", "n_shingles").join(named, "same").select("doc_id", "key", "n_shingles", alone.alias("component_id"))


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))


def one_of_each(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The rows of docs whose document is the smallest of its group, one row for each, unchanged."""
    found = near_duplicates(spark, docs).where(F.col("doc_id") == F.col("component_id"))
    stays = found.groupBy(F.col("doc_id").alias("id")).agg(F.min("key").alias("key"))
    keyed = docs.select(F.struct(*docs.columns).alias("row"), F.col("doc_id").cast("long").alias("id"), text_key(F.col("text")).alias("key"))
    return keyed.join(stays, ["id", "key"]).dropDuplicates(["id"]).select("row.*")
