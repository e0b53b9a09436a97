"""Links between texts of which at least `least` of the word shingles agree (Jaccard over sets of shingles).

Candidates share one of `BANDS` keys, each over `ROWS` minima of seeded permutations of the shingle hashes: at a similarity
of 0.8 a pair misses all of them once in 38,000. Candidates are compared by their whole shingle sets, so no link is
estimated. Keys whose members are the same set of texts are compared once; a task searches from member to member, hence
copies of one text cost one comparison each.

Texts are compared as lower-case words, so those that differ in white space or case are one text. A text of fewer words
than a shingle has one shingle, its whole word sequence; a text without words has none and gets no link.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkverdict.llm.common import materialise, ship_package

SHINGLE = 5
LEAST = 0.8
SEED = 42
BANDS, ROWS = 20, 4
#: Shingle hashes that are permuted at once.
CHUNK = 1 << 13
_RANDOM = np.random.default_rng(SEED)
_A = _RANDOM.integers(0, 1 << 63, BANDS * ROWS, dtype="u8") << np.uint64(1) | np.uint64(1)
_B = _RANDOM.integers(0, 1 << 63, BANDS * ROWS, dtype="u8")


def normal(text: str | None) -> bytes:
    return b" ".join((text or "").encode("utf-8", "replace").lower().split())


def shingles(line: bytes, size: int = SHINGLE) -> np.ndarray:
    """The distinct hashes of the shingles of a normal text, sorted."""
    if not line:
        return np.zeros(0, "u8")
    lengths = np.fromiter(map(len, line.split(b" ")), "i8")
    ends = np.cumsum(lengths + 1) - 1
    k = min(size, len(lengths))
    starts = (ends - lengths)[: len(lengths) - k + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(line[a:b], SEED) for a, b in zip(starts, ends[k - 1 :].tolist(), strict=True)), "u8", len(starts)))


def band_keys(found: np.ndarray) -> np.ndarray:
    least = np.full(BANDS * ROWS, np.iinfo("u8").max, "u8")
    for low in range(0, len(found), CHUNK):
        h = found[low : low + CHUNK]
        mixed = h[None, :] * _A[:, None] + _B[:, None]
        mixed ^= mixed >> np.uint64(32)
        np.minimum(least, mixed.min(axis=1), out=least)
    rows = least.reshape(BANDS, ROWS)
    return np.fromiter((xxhash.xxh64_intdigest(r.tobytes(), i) for i, r in enumerate(rows)), "u8", BANDS)


def _keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from sparkverdict.llm import near_text as n
    from sparkverdict.llm.common import slices

    for batch in slices(batches):
        names, bands = [], []
        for x in batch.column(1):
            line = n.normal(x.as_py())
            names.append(xxhash.xxh64_intdigest(line, n.SEED))
            found = n.shingles(line)
            bands.append(n.band_keys(found).view("i8") if len(found) else [])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.asarray(names, "u8").view("i8")), pa.array(bands, pa.list_(pa.int64()))], names=["text_hash", "k", "bands"])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from sparkverdict.llm import near_text as n
    from sparkverdict.llm.common import slices

    for batch in slices(batches):
        found = [n.shingles(n.normal(x.as_py())).tobytes() for x in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(found, pa.binary())], names=["k", "fp", "shingles"])


def linked(names: list[int], sets: list[np.ndarray], least: float = LEAST) -> list[tuple[int, int]]:
    """Links that join exactly the members connected by pairs of at least this similarity."""
    sizes = np.fromiter(map(len, sets), "i8", len(sets))
    left, out = np.arange(len(sets)), []
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            seed = queue.pop()
            n = sizes[seed]
            fits = (np.minimum(sizes[left], n) >= least * np.maximum(sizes[left], n)) & (sizes[left] > 0)
            some = left[fits]
            if not len(some):
                continue
            every = np.concatenate([sets[i] for i in some])
            at = np.minimum(np.searchsorted(sets[seed], every), n - 1)
            starts = np.concatenate([[0], np.cumsum(sizes[some])[:-1]])
            same = np.add.reduceat((sets[seed][at] == every).astype("i8"), starts)
            reached = some[same >= least * (sizes[some] + n - same)]
            left = left[~np.isin(left, reached)]
            queue.extend(reached)
            out += [(names[seed], names[i]) for i in reached]
    return out


def _links(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by group; a group that crosses batches is carried on."""
        from sparkverdict.llm.near_text import linked

        group, names, sets = None, [], []

        def solved() -> pa.RecordBatch:
            a = np.asarray(linked(names, sets, least), "i8").reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(a[:, 0]), pa.array(a[:, 1])], names=["a", "b"])

        for batch in batches:
            for g, fp, found in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if g != group:
                    if len(names) > 1:
                        yield solved()
                    group, names, sets = g, [], []
                names.append(fp)
                sets.append(np.frombuffer(found, "u8"))
        if len(names) > 1:
            yield solved()

    return run


def links(texts: DataFrame, nodes: DataFrame, least: float = LEAST) -> DataFrame:
    """Edges (a, b) between the nodes of similar texts; `texts` has text_hash and t, `nodes` text_hash and fp (the node)."""
    spark = texts.sparkSession
    ship_package(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    keyed = texts.select("text_hash", "t").mapInArrow(_keys, "text_hash long, k long, bands array<long>")
    keyed = materialise(keyed.groupBy("k").agg(F.min("text_hash").alias("text_hash"), F.first("bands").alias("bands")), "near-keys")
    rows = keyed.select("k", F.explode("bands").alias("key"))
    # equal member sets have equal counts and equal hashes by two seeds
    met = rows.groupBy("key").agg(F.count(F.lit(1)).alias("n"), *[F.bit_xor(F.xxhash64(F.lit(i), "k")).alias(f"s{i}") for i in (1, 2)])
    groups = materialise(met.filter("n > 1").groupBy("n", "s1", "s2").agg(F.min("key").alias("key")).select("key"), "near-groups")
    members = materialise(rows.join(groups, "key").select(F.col("key").alias("g"), "k"), "near-members")
    wanted = keyed.select("k", "text_hash").join(members.select("k").distinct(), "k")
    # copies go before the joins, where they are: a third of all rows may be one text
    wanted = materialise(wanted.join(nodes.groupBy("text_hash").agg(F.min("fp").alias("fp")), "text_hash"), "near-wanted")
    found = texts.groupBy("text_hash").agg(F.first("t").alias("t")).join(wanted, "text_hash")
    sets = materialise(found.select("k", "t", "fp").mapInArrow(_sets, "k long, fp long, shingles binary"), "near-sets")
    together = members.join(sets, "k").select("g", "fp", "shingles").repartition(parts, "g").sortWithinPartitions("g")
    return together.mapInArrow(_links(least), "a long, b long").filter("a <> b").distinct()
