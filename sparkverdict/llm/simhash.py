"""SimHash near-duplicates by covering locality-sensitive hashing.

Fingerprints of 64 bits that differ in at most `radius` bits are linked. For the radius r the bit positions are mapped to
the non-zero vectors of r + 1 bits; for every non-zero vector v there is one table, whose mask keeps the positions with an
odd inner product with v. Any r differing positions give r linear equations over r + 1 unknown bits, so some v is
orthogonal to all of them: in that table both fingerprints are equal under the mask. Hence no pair within the radius is
missed, and the tables need no luck.

Copies cost nothing: equal fingerprints meet in one aggregation and only distinct fingerprints enter the tables. In a
bucket no pairs are emitted: a search from member to member compares each one with those not reached yet, and the
bucket's connected members leave as a chain, at most one row each. A bucket of more than WIDE members (fingerprints may
agree on half of the bits by the million) is covered again by finer tables, whose buckets are small by construction. The
chains of all tables go through rounds of parent hooking and shortcutting (joins and min-aggregations on tables written
to the shared folder).

Defined cases: null, empty and blank texts have the fingerprint zero and are linked like any other; texts of fewer words
than a shingle have one shingle, their whole word sequence; very long texts are taken whole, their shingles in chunks; a
null doc_id takes part and gets its group's smallest doc_id
(null if its group has none); repeated rows give repeated result rows; a bit set in exactly half of the shingles is 0; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkverdict.llm import near_text
from sparkverdict.llm.common import drop_path, hidden, materialise, ship_package

SHINGLE = 4
SEED = 42
RADIUS = 4
#: Shingle hashes whose bits are counted at once.
CHUNK = 1 << 16
#: Buckets with more members are covered again.
WIDE = 1 << 15
#: Members that are compared with one member at once.
BLOCK = 1 << 20


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """A bit is 1 if it is set in over half of the shingles' hashes."""
    words = (text or "").encode("utf-8", "replace").lower().split()
    if not words:
        return 0
    line = b" ".join(words)
    lengths = np.fromiter(map(len, words), "i8", len(words))
    ends = np.cumsum(lengths + 1) - 1
    k = min(shingle, len(words))
    starts = (ends - lengths)[: len(words) - k + 1].tolist()
    ends = ends[k - 1 :].tolist()
    digest, n = xxhash.xxh64_intdigest, len(starts)
    ones = np.zeros(64, "i8")
    for low in range(0, n, CHUNK):
        h = np.fromiter((digest(line[a:b], SEED) for a, b in zip(starts[low : low + CHUNK], ends[low : low + CHUNK], strict=True)), "u8", min(CHUNK, n - low))
        ones += np.unpackbits(h.view("u1").reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype="i8")
    return int(np.packbits(2 * ones > n, bitorder="little").view("u8")[0])


def masks(radius: int = RADIUS) -> list[int]:
    """The covering masks: position i carries the vector 1 + i mod (2^(radius+1) - 1)."""
    vectors = (1 << (radius + 1)) - 1
    return [sum(1 << i for i in range(64) if ((1 + i % vectors) & v).bit_count() & 1) for v in range(1, vectors + 1)]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from sparkverdict.llm import simhash

    for batch in batches:
        found = [simhash.fingerprint(x.as_py()) for x in batch.column(2)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.asarray(found, "u8").view("i8"))], names=["doc_id", "text_hash", "fp"])


def fingerprints(docs: DataFrame, text: str = "text") -> DataFrame:
    """doc_id, text_hash and fp of every row."""
    ship_package(docs.sparkSession)
    t = F.col(text).cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(t).alias("text_hash"), t.alias("t")).mapInArrow(_fingerprints, "doc_id long, text_hash long, fp long")


def bucket_chains(fps: np.ndarray, ids: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Chains through the groups of one bucket that are connected by links within the radius."""
    if len(fps) == 2:
        return [(int(ids[0]), int(ids[1]))] if int(fps[0] ^ fps[1]).bit_count() <= radius else []
    left = np.arange(len(fps))
    chains = []
    while len(left):
        queue, left, group = [left[0]], left[1:], [left[0]]
        while queue and len(left):
            seed = queue.pop()
            near = np.concatenate([np.bitwise_count(fps[left[low : low + BLOCK]] ^ fps[seed]) <= radius for low in range(0, len(left), BLOCK)])
            reached = left[near]
            left = left[~near]
            queue.extend(reached)
            group.extend(reached)
        chains += [(int(ids[a]), int(ids[b])) for a, b in zip(group, group[1:])]
    return chains


def _links(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by bucket; a bucket that crosses batches is carried on."""
        from sparkverdict.llm.simhash import bucket_chains

        held: list[np.ndarray] = []

        def batch_of(found: list[tuple[int, int]]) -> pa.RecordBatch:
            a = np.asarray(found, "i8").reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(a[:, 0]), pa.array(a[:, 1])], names=["a", "b"])

        def solve(rows: np.ndarray) -> list[tuple[int, int]]:
            return bucket_chains(rows[:, 2].view("u8"), rows[:, 3], radius) if len(rows) > 1 else []

        for batch in batches:
            rows = np.stack([np.asarray(batch.column(i).cast(pa.int64())) for i in range(4)], axis=1)
            if not len(rows):
                continue
            if held and (held[-1][-1, :2] != rows[0, :2]).any():
                yield batch_of(solve(np.ascontiguousarray(np.concatenate(held))))
                held = []
            cuts = np.flatnonzero((rows[1:, :2] != rows[:-1, :2]).any(axis=1)) + 1
            if not len(cuts):
                held.append(rows)
                continue
            first = np.concatenate([*held, rows[: cuts[0]]])
            found = solve(first)
            sizes = np.diff(cuts)
            for at in np.flatnonzero(sizes > 1):
                found += solve(rows[cuts[at] : cuts[at + 1]].copy())
            held = [rows[cuts[-1] :]]
            yield batch_of(found)
        if held:
            yield batch_of(solve(np.concatenate(held)))

    return run


def table_rows(distinct: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(table, key, fp, id): every distinct fingerprint in each covering table."""
    fp = F.col("fp")
    cells = F.array(*[F.struct(F.lit(t).alias("t"), fp.bitwiseAND(F.lit(signed(m))).alias("key")) for t, m in enumerate(masks(radius))])
    return distinct.select("fp", "id", F.explode(cells).alias("c")).select(F.col("c.t").alias("t"), F.col("c.key").alias("key"), "fp", "id")


def finer_masks(radius: int = RADIUS) -> list[tuple[int, int, int]]:
    """(table, finer table, mask) for buckets of many members: the positions that a table's mask leaves free are dealt into
    2 * radius segments, of which at most `radius` hold a difference; so each pair within the radius that meets in the
    bucket agrees in some `radius` segments, and meets again under the mask with those segments added. A bucket of a finer
    table holds at most 2^(half of the free positions) fingerprints, about 2^16 for 64 bits."""
    finer, found = len(masks(radius)), []
    for t, m in enumerate(masks(radius)):
        free = [i for i in range(64) if not m >> i & 1]
        segments = [sum(1 << i for i in free[n :: 2 * radius]) for n in range(2 * radius)]
        for chosen in combinations(segments, radius):
            found.append((t, finer, signed(m | sum(chosen))))
            finer += 1
    return found


def links(distinct: DataFrame, radius: int = RADIUS, wide: int = WIDE) -> DataFrame:
    """Edges (a, b) of ids that join exactly the fingerprints connected by links within the radius, bucket by bucket; a
    bucket of more than `wide` members is covered again by finer tables, so no task gets an unbounded bucket."""
    spark = distinct.sparkSession
    ship_package(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = table_rows(distinct, radius)
    crowded = materialise(rows.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > wide).select("t", "key"), "simhash-wide")
    if crowded.limit(1).count():
        # as many rows as there are finer tables, some thousands for radius 4, whatever the data
        finer = F.broadcast(spark.createDataFrame(finer_masks(radius), "t int, finer int, mask long"))
        split = rows.join(crowded, ["t", "key"], "left_semi").join(finer, "t").select(F.col("finer").alias("t"), F.col("fp").bitwiseAND(F.col("mask")).alias("key"), "fp", "id")
        rows = rows.join(crowded, ["t", "key"], "left_anti").select("t", "key", "fp", "id").union(split)
    dealt = rows.repartition(parts, "t", "key").sortWithinPartitions("t", "key")
    return dealt.mapInArrow(_links(radius), "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root): the smallest node of each connected component, for all nodes of the edges.

    Every round each node's parent becomes the smallest of its grandparent and its neighbours' grandparents, and each
    parent is hooked in the same way. Nodes have few edges each (chains), so joins on nodes are even; joins on parents,
    where one root may have most of the nodes, are plain joins of two written tables, which adaptive execution splits.
    """
    spark = edges.sparkSession
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    both = materialise(both, "cc-edges")
    parents = materialise(both.groupBy(F.col("a").alias("v")).agg(F.min(F.least("a", "b")).alias("f")), "cc-parents")
    while True:
        up = parents.select(F.col("v").alias("w"), F.col("f").alias("g"))
        grand = materialise(parents.join(up, F.col("f") == F.col("w")).select("v", "f", "g"), "cc-grand")
        near = both.join(grand.select(F.col("v").alias("b"), F.col("g").alias("gb")), "b").select("a", "gb")
        low = near.groupBy("a").agg(F.min("gb").alias("gb"))  # smallest grandparent among a node's neighbours
        hooked = grand.join(low, F.col("v") == F.col("a"))
        moves = hooked.select("v", F.least("g", "gb").alias("f")).union(hooked.select(F.col("f").alias("v"), F.least("g", "gb").alias("f")))
        following = materialise(moves.groupBy("v").agg(F.min("f").alias("f")), "cc-parents")
        moved = following.join(parents.withColumnRenamed("f", "was"), "v").filter(F.col("f") != F.col("was")).limit(1).count()
        for old in (parents, grand):
            drop_path(spark, old.inputFiles()[0].rsplit("/", 1)[0]) if old.inputFiles() else None
        parents = following
        if not moved:
            return parents.select(F.col("v").alias("node"), F.col("f").alias("root"))


def members(docs: DataFrame, radius: int = RADIUS, similar: float | None = None) -> DataFrame:
    """doc_id, text_hash, fp, root (the smallest fingerprint of the group) and component_id, one row per document. With
    `similar`, texts of at least that Jaccard similarity (near_text) are linked too, however far their fingerprints."""
    prints = materialise(fingerprints(docs), "simhash")
    distinct = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("id")), "simhash-distinct")
    # a fingerprint is its own node: rows of one doc_id with different texts are not linked by it
    edges = links(distinct.select("fp", F.col("fp").alias("id")), radius)
    if similar is not None:
        t = docs.select(F.col("text").cast("string").alias("t")).withColumn("text_hash", F.xxhash64("t"))
        edges = edges.union(near_text.links(t, prints.select("text_hash", "fp"), similar))
    found = components(edges)
    rooted = materialise(distinct.join(found, F.col("fp") == F.col("node"), "left").select("fp", "id", F.coalesce("root", "fp").alias("root")), "simhash-rooted")
    least = rooted.groupBy("root").agg(F.min("id").alias("component_id"))
    groups = materialise(rooted.join(least, "root").select("fp", "root", "component_id"), "simhash-groups")
    return prints.join(groups, "fp")


def near_duplicates(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id, one row per document."""
    return members(docs, radius).select(
        "doc_id",
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        "component_id",
    )


def one_of_each(docs: DataFrame, radius: int = RADIUS, similar: float | None = None) -> DataFrame:
    """The documents, with all their columns, of which one of each group stays: the one with the smallest doc_id, then the
    smallest hash of the text; a document without doc_id only where the whole group has none. Rows that agree in doc_id
    and text are one document."""
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), F.coalesce("doc_id", F.lit(0)).alias("id"), F.col("text_hash").alias("text"))).alias("m")
    chosen = members(docs, radius, similar).groupBy("root").agg(first).select(F.col("m.none").alias("_none"), F.col("m.id").alias("_id"), F.col("m.text").alias("_text"))
    rows, (doc_id, text) = hidden(docs, "doc_id", "text")
    key = F.col(doc_id).cast("long")
    rows = rows.withColumns({"_none": key.isNull(), "_id": F.coalesce(key, F.lit(0)), "_text": F.xxhash64(F.col(text).cast("string"))})
    kept = rows.join(chosen, ["_none", "_id", "_text"], "left_semi").dropDuplicates(["_none", "_id", "_text"])
    return kept.drop("_none", "_id", "_text").toDF(*docs.columns)
