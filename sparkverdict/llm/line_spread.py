"""Line dedup by distinct-site spread: lines that many sites share are boilerplate and leave their documents.

Every line hash gets two HyperLogLog sketches, of the sites that have it and of the texts that hold it; sketches merge by
aggregation straight from the rows of lines, so a line that stands in a third of all documents costs one pair of sketches
a task and no table of distinct (line, site) pairs is made. The sketches settle every line whose estimate is off the
threshold by more than `sigmas` of their standard errors; the lines near it, and only those, get exact distinct counts.
Removed lines go back to documents by joins on the line hash and on the document. Only DataFrame functions are used.

Boilerplate is a line on `min_sites` sites and in as many different texts. A document that was copied to many sites is
one text, so its own lines stay, on all copies alike (near-dedup is the operator for copies). Every document that holds a
boilerplate line loses it, however much of the document that is.

Defined cases: lines are split at newlines and compared after trimming ASCII white space; blank lines are never
boilerplate; a null text stays null and has no lines; a document that is all boilerplate keeps its row with an empty
text; a null site adds nothing to the spread; repeated rows add no further site or text; rows that tie in doc_id are told
apart by their texts; a document without doc_id counts and is cut like any other; very long texts are taken whole, in
time linear in their lines; an empty table gives an empty result; all input columns are kept, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkverdict.llm.common import SPACE_CHARS, hidden, materialise


@dataclass(frozen=True)
class SpreadRules:
    #: Distinct sites, and distinct texts, from which a line is boilerplate.
    min_sites: int = 10
    #: Estimates within so many standard errors of the threshold are counted exactly.
    sigmas: float = 6.0
    #: log2 of the sketch's size.
    lg_k: int = 12

    @property
    def band(self) -> tuple[float, float]:
        """Estimates between these two say too little."""
        off = self.sigmas * 1.04 / 2 ** (self.lg_k / 2)
        return self.min_sites * (1 - off), self.min_sites * (1 + off)


def _line_key(line: Column) -> Column:
    return F.xxhash64(F.btrim(line, F.lit(SPACE_CHARS)))


def _blank(line: Column) -> Column:
    return F.length(F.btrim(line, F.lit(SPACE_CHARS))) == 0


def line_rows(docs: DataFrame, site: str = "source") -> DataFrame:
    """One narrow row per line that is not blank: doc_id, t (hash of the text), pos, h (hash of the line), s (of the site)."""
    text = docs.select("doc_id", F.xxhash64("text").alias("t"), F.when(F.col(site).isNotNull(), F.xxhash64(F.col(site))).alias("s"), F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    return text.filter(~_blank(F.col("line"))).select("doc_id", "t", "pos", _line_key(F.col("line")).alias("h"), "s")


def sketched(lines: DataFrame, rules: SpreadRules = SpreadRules()) -> DataFrame:
    """h with the estimates of its sites and of its texts."""
    sketch = lambda c: F.hll_sketch_estimate(F.hll_sketch_agg(c, F.lit(rules.lg_k)))
    return lines.filter(F.col("s").isNotNull()).groupBy("h").agg(sketch("s").alias("sites"), sketch("t").alias("texts"))


def boilerplate(lines: DataFrame, rules: SpreadRules = SpreadRules()) -> DataFrame:
    """Hashes of lines on at least min_sites distinct sites and in as many distinct texts."""
    low, high = rules.band
    least = F.least("sites", "texts")
    rated = materialise(sketched(lines, rules).filter(least >= low), "line-spread")
    sure = rated.filter(least > high).select("h")
    near = rated.filter(least <= high).select("h")
    exact = lines.filter(F.col("s").isNotNull()).join(near, "h", "left_semi").groupBy("h").agg(F.countDistinct("s").alias("sites"), F.countDistinct("t").alias("texts"))
    return sure.union(exact.filter(F.least("sites", "texts") >= rules.min_sites).select("h"))


def _cut(docs: DataFrame, rules: SpreadRules) -> DataFrame:
    """A table whose other columns have working names, with doc_id, site and text: the text that stays, and _removed_lines."""
    lines = materialise(line_rows(docs, "site"), "line-rows")
    bad = materialise(boilerplate(lines, rules), "line-bad")
    # what one document loses is bounded by its own lines; a null doc_id is spread by the hash of the text
    hits = lines.join(bad, "h").groupBy("doc_id", "t").agg(F.collect_set("pos").alias("_gone")).withColumnsRenamed({"doc_id": "_hit_id", "t": "_hit_text"})
    same = F.col("doc_id").eqNullSafe(F.col("_hit_id")) & (F.xxhash64("text") == F.col("_hit_text"))
    joined = docs.join(hits, same, "left").drop("_hit_id", "_hit_text")
    split = joined.withColumn("_lines", F.when(F.col("_gone").isNotNull(), F.split("text", "\n")))
    kept = F.array_except(F.sequence(F.lit(0), F.size("_lines") - 1), "_gone")  # by a hash set, in order
    cut = F.array_join(F.transform(kept, lambda i: F.get(F.col("_lines"), i)), "\n")
    return (
        split.withColumn("text", F.when(F.col("_gone").isNotNull(), cut).otherwise(F.col("text")))
        .withColumn("_removed_lines", F.coalesce(F.size("_gone"), F.lit(0)).cast("long"))
        .withColumn("_removed_lines", F.greatest("_removed_lines", F.lit(0)))
        .drop("_gone", "_lines")
    )


def remove_boilerplate(docs: DataFrame, site: str = "source", rules: SpreadRules = SpreadRules(), length: str | None = None) -> DataFrame:
    """The documents with boilerplate lines taken out of `text`; the column `length`, if any, follows where lines went."""
    rows, found = hidden(docs, "doc_id", "text", site, *([length] if length else []))
    order = rows.columns
    cut = _cut(rows.withColumnsRenamed({found[0]: "doc_id", found[1]: "text"}).withColumn("site", F.col(found[2])), rules)
    cut = cut.withColumnsRenamed({"doc_id": found[0], "text": found[1]})
    if length:
        kind = rows.schema[found[3]].dataType
        cut = cut.withColumn(found[3], F.when(F.col("_removed_lines") > 0, F.length(found[1]).cast(kind)).otherwise(F.col(found[3])))
    return cut.select(*order).toDF(*docs.columns)


def deduplicated_lines(docs: DataFrame, site: str = "source", rules: SpreadRules = SpreadRules()) -> DataFrame:
    """doc_id, n_lines, n_removed and the text that stays, for every document."""
    n = F.coalesce(F.size(F.split("text", "\n")), F.lit(0)).cast("long")
    narrow = docs.select("doc_id", F.col(site).alias("site"), F.col("text").cast("string").alias("text"), F.when(F.col("text").isNull(), F.lit(0).cast("long")).otherwise(n).alias("_n_lines"))
    done = _cut(narrow, rules)
    return done.select("doc_id", F.col("_n_lines").alias("n_lines"), F.col("_removed_lines").alias("n_removed"), "text")
