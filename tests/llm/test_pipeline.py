"""The pipeline's stages against plain versions of their decisions, on the small tables."""

from __future__ import annotations

from collections import Counter

import corpus_pipeline
from sparkverdict.llm import bpe
from sparkverdict.llm.common import table
from sparkverdict.llm.queries import queries, vocabulary


def test_stages(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").cache()
    columns = docs.columns
    kept = corpus_pipeline.quality(spark, docs, sf_dir).cache()
    scores = {r.doc_id: r.predicted for r in queries()["op9_pu_quality"](spark, sf_dir).collect()}
    assert kept.columns == columns and {r.doc_id for r in kept.collect()} == {i for i, p in scores.items() if p}
    cut = corpus_pipeline.line_dedup(spark, kept, sf_dir).cache()
    assert cut.columns == columns and cut.count() == kept.count()
    one = corpus_pipeline.near_dedup(spark, cut, sf_dir).cache()
    from sparkverdict.llm.simhash import near_duplicates

    groups = {r.component_id for r in near_duplicates(cut).collect()}
    assert one.columns == columns and sorted(r.doc_id for r in one.collect()) == sorted(groups)
    mixed = corpus_pipeline.mixing(spark, one, sf_dir).cache()
    from sparkverdict.llm.fair_queue import mix

    want = Counter({r.doc_id: r.taken // r.size for r in mix(one).collect() if r.taken})
    assert mixed.columns == columns and Counter(r.doc_id for r in mixed.collect()) == want
    last = corpus_pipeline.tokens(spark, mixed, sf_dir).collect()
    coder = bpe.encoder(vocabulary())
    texts = {r.doc_id: r.text for r in mixed.collect()}
    assert len(last) == sum(want.values()) and all(len(coder.encode(texts[r.doc_id])[0]) == 4 * r.n_tokens for r in last)


def test_empty_tables(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf_dir)
        assert docs.count() == 0


def test_clashing_columns_nulls_and_repeats(spark, sf_dir):
    """Stages keep columns named like their working ones, and every text of which no copy stays elsewhere."""
    other = ("_id", "_bad", "_copies", "_text", "_none", "site", "_removed_lines")
    long = "\n".join(f"line {i} says what only this text says {i * i}" for i in range(12))
    rows = [(1, long), (1, long), (1, "another text of the same id with many other words in it"), (2, long + " end"), (None, "no id here but words that stand nowhere else"), (None, "second text without any id and with its own words"), (None, None), (7, "")]
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in other)
    docs = spark.createDataFrame([(i, t, "en", f"s{n % 2}", len(t or ""), *other) for n, (i, t) in enumerate(rows)], schema)
    cut = corpus_pipeline.line_dedup(spark, docs, sf_dir)
    assert cut.columns == docs.columns and sorted(map(str, cut.collect())) == sorted(map(str, docs.collect()))
    one = corpus_pipeline.near_dedup(spark, docs, sf_dir)
    got = {(r.doc_id, r.text) for r in one.collect()}
    assert one.columns == docs.columns and one.count() == len(got) == 5 and {r.site for r in one.collect()} == {"site"}
    assert got == {rows[0], rows[2], rows[4], rows[5], rows[7]}
    assert corpus_pipeline.mixing(spark, one, sf_dir).columns == docs.columns


def test_removed_lines_change_the_length(spark):
    from sparkverdict.llm import line_spread

    footer = "all rights to this text are kept by its site"
    docs = spark.createDataFrame([(i, "\n".join([f"own {i} " + " ".join(f"w{i}x{j}" for j in range(30)), footer]), f"s{i}", 0) for i in range(12)], "doc_id long, text string, source string, n_chars int")
    got = line_spread.remove_boilerplate(docs, length="n_chars").collect()
    assert all(footer not in r.text and r.n_chars == len(r.text) for r in got) and len(got) == 12


def test_near_dedup_finds_every_similar_text(spark):
    """Texts of Jaccard 0.8 or more are one group, by brute force, also where their fingerprints are far apart."""
    import random

    from sparkverdict.llm import near_text, simhash

    rng = random.Random(5)
    rows, i = [], 0
    for base in range(40):
        words = [f"w{rng.randrange(3000)}" for _ in range(rng.choice((60, 150, 400)))]
        for copy in range(4):
            edited = list(words)
            for _ in range(copy * len(words) // 60):
                edited[rng.randrange(len(edited))] = f"x{rng.randrange(3000)}"
            rows.append((i, " ".join(edited)))
            i += 1
    sets = [set(near_text.shingles(near_text.normal(t)).tolist()) for _, t in rows]
    prints = [simhash.fingerprint(t) for _, t in rows]
    root, far = list(range(len(rows))), 0

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            apart = (prints[a] ^ prints[b]).bit_count()
            alike = len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])
            far += alike and apart > simhash.RADIUS
            if alike or apart <= simhash.RADIUS:
                x, y = sorted((top(a), top(b)))
                root[y] = x
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id for r in dict(corpus_pipeline.STAGES)["SimHash near-dedup"](spark, docs, "").collect()}
    assert far > 20 and got == {top(x) for x in range(len(rows))}


def test_every_page_loses_boilerplate(spark):
    """However much of a page is boilerplate, it goes; copies are treated like any page that holds the line."""
    footer = "all rights to this text are kept by its site"
    rows = [(i, f"own {i}\n{footer}", f"s{i}", 0) for i in range(12)] + [(20, f"same\n{footer}", "s0", 7), (21, f"same\n{footer}", "s1", 7), (22, f"twice\n{footer}", "s1", 7), (22, f"twice\n{footer}", "s1", 7), (23, footer, "s1", 7), (None, f"none\n\n{footer}", None, 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, n_chars int")
    got = sorted(((r.doc_id, r.text, r.n_chars) for r in corpus_pipeline.line_dedup(spark, docs, "").collect()), key=str)
    want = [(i, f"own {i}", len(f"own {i}")) for i in range(12)] + [(20, "same", 4), (21, "same", 4), (22, "twice", 5), (22, "twice", 5), (23, "", 0), (None, "none\n", 5)]
    assert got == sorted(want, key=str)
