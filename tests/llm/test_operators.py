"""Brute-force versions and edge cases of the operators. One fixture has nulls, blanks, copies, ties and odd columns."""

from __future__ import annotations

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from sparkverdict.llm import bpe, fair_queue, hash_tree, host_quality, line_spread, m_tree, pu_quality, simhash, site_tree, token_frames
from sparkverdict.llm.queries import vocabulary

WORD = re.compile(r"[^\x20\x09-\x0D]+")
BASE = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega"


def fixture_rows() -> list[tuple]:
    rows: list[tuple] = [
        (0, None, "s0"), (1, "", "s0"), (2, " \t\n\x0b\x0c\r ", None), (3, "one", "s1"), (4, BASE, "s1"), (5, BASE, "s2"),
        (6, BASE.replace("omega", "OMEGA"), "s2"), (7, BASE + " again", None), (8, "a b c d e f g h " * 12, "s3"),
        (9, "x\n" * 3 + "Same line here\nSame line here\n", "s3"), (10, "Ünïcode 😀 naïve <b>#$%</b> don't I'LL 12 ½ <|endoftext|> x", "s4"),
        (11, "w" * 3000, "s4"), (12, "long " * 4000 + "tail", "s5"), (13, "\x1c\x1d a b 　", "s5"),
    ]
    rows += [(20 + i, f"Shared boilerplate line\n{BASE} number {i} of many\nmore own words {i}", f"site{i}") for i in range(12)]
    rows += [(40 + i, BASE, "s0") for i in range(5)]
    return rows + [rows[4]]


@pytest.fixture(scope="module")
def docs(spark):
    schema = "doc_id long, text string, source string, lang string, n_words int, `rank` int, `shard` string, `score` double"
    return spark.createDataFrame([(*r, "xx", 1, 2, "z", 0.5) for r in fixture_rows()], schema).repartition(3)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.filter("doc_id < 0")


def test_host_rules(docs, empty):
    got = Counter(tuple(r)[:7] for r in host_quality.apply_host_rules(docs).collect())
    want: Counter = Counter()
    for doc_id, text, _ in fixture_rows():
        text = text or ""
        w = WORD.findall(text)
        lines = [x for x in text.split("\n") if WORD.search(x)]
        grams = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        covered = {i + k for i in range(len(w) - 7) if grams[tuple(w[i : i + 8])] > 1 for k in range(8)}
        want[(doc_id, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered), len(w) < 20 or 100 * len(covered) > 30 * len(w))] += 1
    assert got == want
    assert host_quality.apply_host_rules(empty).collect() == []


def test_bad_host_takes_its_clean_documents_along(spark):
    rows = [(i, "short", "bad") for i in range(60)] + [(100, BASE, "bad")] + [(200 + i, BASE, f"h{i % 6}") for i in range(60)] + [(300, BASE, None)]
    got = {r.doc_id: r for r in host_quality.apply_host_rules(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert not got[100].kept and not got[100].base_failed and got[200].kept and got[300].kept


def test_shrinkage_spares_a_small_host(spark):
    rows = [(i, BASE, f"h{i % 20}") for i in range(400)] + [(900, "short", "tiny"), (901, BASE, "tiny"), (902, "short", "tiny")]
    tree = host_quality.host_verdicts(host_quality.rule_rows(spark.createDataFrame(rows, "doc_id long, text string, source string")))
    tiny = tree.filter("host = 'tiny'").first()
    assert tiny.bad / tiny.n > 0.5 > 0 and tiny.rate < tiny.bad / tiny.n


def test_frames_round_trip(spark, docs, empty, tmp_path):
    t = Tokenizer.from_file(vocabulary())
    manifest = token_frames.write_frames(docs, vocabulary(), f"file://{tmp_path}/frames")
    got = sorted(map(tuple, token_frames.read_frames(manifest).collect()), key=lambda r: r[1])
    want, start = [], 0
    for doc_id, text, _ in sorted(fixture_rows(), key=lambda r: r[0]):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 1]
        want.append((doc_id, start, len(ids), zlib.crc32(np.asarray(ids, "<u4").tobytes())))
        start += len(ids)
    assert got == want
    one = token_frames.documents(spark, manifest, [4, 10])
    assert one[10] == [[*t.encode(dict((r[0], r[1]) for r in fixture_rows())[10], add_special_tokens=False).ids, 1]] and len(one[4]) == 2
    assert token_frames.token_frames(empty, vocabulary()).collect() == []


def test_damaged_frame_is_noticed(tmp_path):
    path = tmp_path / "x"
    with path.open("wb") as f:
        w = token_frames.FrameWriter(f, 2)
        w.add(1, np.arange(500))
        w.add(None, np.arange(3))
        w.close()
    store, name = token_frames.file_system(f"file://{path}")
    with store.open_input_file(name) as f:
        r = token_frames.FrameReader(f)
        assert r.doc_ids == [1, None] and r.document(1).tolist() == [0, 1, 2]
    raw = bytearray(path.read_bytes())
    raw[60] ^= 1
    path.write_bytes(raw)
    with store.open_input_file(name) as f, pytest.raises(Exception):
        token_frames.FrameReader(f).document(0)


def slow_fingerprint(text):
    w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + 4]).encode(), 42) for i in range(max(1, len(w) - 3))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_against_all_pairs(docs, empty):
    rows = fixture_rows()
    prints = [slow_fingerprint(r[1]) for r in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= 4:
                root[find(i)] = find(j)
    least = defaultdict(lambda: 1 << 62)
    for i, r in enumerate(rows):
        least[find(i)] = min(least[find(i)], r[0])
    want = Counter((r[0], f"{prints[i]:016x}", least[find(i)]) for i, r in enumerate(rows))
    assert Counter(tuple(r) for r in simhash.near_duplicates(docs).collect()) == want
    assert simhash.near_duplicates(empty).collect() == []


def test_covering_masks_miss_no_pair():
    rng = np.random.default_rng(3)
    ms = simhash.masks(4)
    assert len(ms) == 31
    for _ in range(3000):
        d = sum(1 << int(b) for b in rng.choice(64, rng.integers(1, 5), replace=False))
        assert any(d & m == 0 for m in ms)


def test_links_and_components_of_random_fingerprints(spark):
    rng = np.random.default_rng(8)
    centres = rng.integers(0, 1 << 63, 40, dtype="u8")
    prints = np.unique(np.concatenate([centres, *[c ^ np.bitwise_or.reduce(np.uint64(1) << rng.integers(0, 64, (60, 2), dtype="u8"), axis=1) for c in centres]]))
    ids = rng.permutation(len(prints))
    distinct = spark.createDataFrame([(simhash.signed(int(p)), int(i)) for p, i in zip(prints, ids)], "fp long, id long")
    got = {r.node: r.root for r in simhash.components(simhash.links(distinct)).collect()}
    root = {int(i): int(i) for i in ids}

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for n, p in enumerate(prints):
        for j in np.flatnonzero(np.bitwise_count(prints[:n] ^ p) <= 4):
            a, b = find(int(ids[n])), find(int(ids[j]))
            root[max(a, b)] = min(a, b)
    assert {int(i): find(int(i)) for i in ids} == {int(i): got.get(int(i), int(i)) for i in ids}


def test_crowded_buckets_are_covered_again(spark):
    """With buckets of three members at most, the finer tables lose no link; each finer bucket is small by its mask."""
    assert max(64 - (m & (1 << 64) - 1).bit_count() for _, _, m in simhash.finer_masks()) <= 18
    rng = np.random.default_rng(11)
    centre = np.uint64(rng.integers(0, 1 << 63))
    prints = np.unique(np.asarray([centre ^ np.bitwise_or.reduce(np.uint64(1) << rng.integers(0, 64, rng.integers(1, 12), dtype="u8")) for _ in range(700)]))
    distinct = spark.createDataFrame([(simhash.signed(int(p)), i) for i, p in enumerate(prints)], "fp long, id long").cache()
    groups = [{r.node: r.root for r in simhash.components(simhash.links(distinct, wide=wide)).collect()} for wide in (simhash.WIDE, 3)]
    root = list(range(len(prints)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for n, p in enumerate(prints):
        for j in np.flatnonzero(np.bitwise_count(prints[:n] ^ p) <= 4):
            a, b = sorted((find(n), find(int(j))))
            root[b] = a
    want = {i: find(i) for i in range(len(prints))}
    assert all({i: g.get(i, i) for i in want} == want for g in groups) and len(set(want.values())) > 1


def test_null_ids_take_part(spark):
    rows = [(None, BASE), (7, BASE), (None, "quite another text with some words of its own here")]
    got = {(r.doc_id, r.component_id) for r in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {(None, 7), (7, 7), (None, None)}


def test_line_spread(docs, empty):
    got = {r.doc_id: r for r in line_spread.deduplicated_lines(docs).collect()}
    assert got[20].n_removed == 1 and got[20].text == f"{BASE} number 0 of many\nmore own words 0"
    assert got[0].text is None and got[0].n_lines == 0 and got[4].text == BASE and got[9].n_removed == 0
    assert line_spread.deduplicated_lines(docs).count() == len(fixture_rows())
    assert line_spread.deduplicated_lines(empty).collect() == []


def test_copies_keep_their_lines_and_threshold_is_exact(spark):
    rows = [(i, f"{BASE}\nsecond line of the copy", f"s{i}") for i in range(30)]
    rows += [(100 + i, f"nine sites only\n{BASE} {i} own text", f"s{i % 9}") for i in range(40)]
    rows += [(200 + i, f"ten sites\n{BASE} {i} own words", f"s{i % 10}") for i in range(40)]
    got = {r.doc_id: r for r in line_spread.deduplicated_lines(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert all(got[i].n_removed == 0 for i in [*range(30), *range(100, 140)]) and all(got[i].n_removed == 1 for i in range(200, 240))


def test_the_sketch_settles_lines_off_the_threshold(spark):
    """Only lines near the threshold are counted exactly: with the sketch's estimates alone the others are the same."""
    rows = [(100 * n + i, f"line of {n} sites\nown text {n} {i}", f"s{i}") for n in (2, 9, 10, 11, 12, 40, 300) for i in range(n)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    rules = line_spread.SpreadRules()
    lines = line_spread.line_rows(docs)
    low, high = rules.band
    assert 9 < low < 10 < high < 11
    rated = {round(r.sites): (r.sites, r.texts) for r in line_spread.sketched(lines, rules).collect()}
    assert set(rated) >= {1, 2, 9, 10, 11, 12, 40} and any(abs(n - 300) < 20 for n in rated)
    bad = {r.h for r in line_spread.boilerplate(lines, rules).collect()}
    assert len(bad) == 5
    # a coarse sketch sends more lines to the exact count, with the same result
    coarse = line_spread.SpreadRules(lg_k=4)
    assert coarse.band[0] < 0 and {r.h for r in line_spread.boilerplate(lines, coarse).collect()} == bad


def test_line_spread_of_a_very_long_text(spark):
    rows = [(i, "\n".join(["shared by all", *[f"own {i} {j}" for j in range(20_000 if i == 0 else 3)], "shared by all"]), f"s{i}") for i in range(10)]
    got = {r.doc_id: r for r in line_spread.deduplicated_lines(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert all(r.n_removed == 2 and r.text == rows[i][1].removeprefix("shared by all\n").removesuffix("\nshared by all") for i, r in got.items())


def hash_long(x: int, seed: int) -> int:
    return xxhash.xxh64_intdigest((x & (1 << 64) - 1).to_bytes(8, "little"), seed)


def test_hash_tree(docs, empty):
    rows = hash_tree.shard(docs).collect()
    assert len(rows) == len(fixture_rows()) and {r.law for r in rows} == {"key"}
    by = defaultdict(list)
    for r in rows:
        by[r.shard].append(r.slot)
        assert r.grown_shard in (r.shard, 40)
    assert all(sorted(s) == list(range(len(s))) for s in by.values())
    texts = {r[0]: (r[1] or "").encode() for r in fixture_rows()}
    assert all(r.size == len(texts[r.doc_id]) + 16 and r.text_crc32 == zlib.crc32(texts[r.doc_id]) for r in rows)
    tree = hash_tree.Tree.regular(2, 4, 5)
    for r in rows:  # the descent by hand
        def draw(level, children):
            out = []
            for i, (name, w) in enumerate(children):
                h = hash_long(r.doc_id, 42)
                for part in (level, name):
                    h = xxhash.xxh64_intdigest(part.encode(), h)
                out.append((-np.log(((h >> 11) + 0.5) / float(1 << 53)) / w, i))
            return min(out)[1]

        i = draw("region", [(str(i), 20.0) for i in range(2)])
        j = draw(f"rack/{i}", [(str(j), 5.0) for j in range(4)])
        rack = tree.regions[i][j]
        assert r.shard == rack[draw(f"shard/{i}/{j}", [(str(s), w) for s, w in rack])][0]
    assert hash_tree.shard(empty).collect() == []


def test_hash_tree_weights_and_growth(spark):
    df = spark.range(20000).withColumnRenamed("id", "doc_id")
    tree = hash_tree.Tree(((((0, 1.0), (1, 3.0)),), (((2, 2.0),), ((3, 2.0),))))
    bigger = tree
    for _ in range(2):
        grown = bigger.grown(2.0)
        both = hash_tree.assign(hash_tree.assign(df, bigger, "doc_id", "a"), grown, "doc_id", "b")
        new = max(s for region in grown.regions for rack in region for s, _ in rack)
        assert both.filter((F.col("a") != F.col("b")) & (F.col("b") != new)).count() == 0
        bigger = grown
    share = {r.s: r["count"] / 20000 for r in hash_tree.assign(df, tree, "doc_id", "s").groupBy("s").count().collect()}
    assert all(abs(share[s] - w / 8) < 0.02 for s, w in ((0, 1), (1, 3), (2, 2), (3, 2)))
    heavier = hash_tree.Tree(((((0, 1.0), (1, 6.0)),), tree.regions[1]))
    moved = hash_tree.assign(hash_tree.assign(df, tree, "doc_id", "a"), heavier, "doc_id", "b").filter("a != b and a in (2, 3) and b in (2, 3)")
    assert moved.count() == 0  # nothing moves between subtrees whose weights stay


def test_fair_queue(docs, empty):
    first = sorted(map(tuple, fair_queue.mix(docs).collect()), key=repr)
    assert first == sorted(map(tuple, fair_queue.mix(docs.repartition(2)).collect()), key=repr)
    sizes = Counter()
    for _, text, source in fixture_rows():
        sizes[source] += len(WORD.findall(text or ""))
    order = sorted((s for s in sizes if s is not None)) + [None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    open_, left, target = set(sizes), 1.5 * sum(sizes.values()), {}
    while True:
        level = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if level * weight[s] >= 2 * sizes[s]}
        if not full:
            break
        for s in full:
            target[s] = 2.0 * sizes[s]
            left -= target[s]
        open_ -= full
    target |= {s: level * weight[s] for s in open_}
    source = {r[0]: r[2] for r in fixture_rows()}
    taken = Counter()
    for doc_id, size, source_size, goal, took in first:
        assert source_size == sizes[source[doc_id]] and goal == pytest.approx(target[source[doc_id]]) and took in (0, size, 2 * size)
        taken[source[doc_id]] += took
    longest = max(r[1] for r in first)
    assert all(abs(taken[s] - target[s]) <= longest for s in sizes) and sum(taken.values()) <= 1.5 * sum(sizes.values())
    assert fair_queue.mix(empty).collect() == []


def test_bpe_equals_the_library(docs, empty):
    t = Tokenizer.from_file(vocabulary())
    got = Counter(tuple(r) for r in bpe.digests(docs, vocabulary()).collect())
    want: Counter = Counter()
    for doc_id, text, _ in fixture_rows():
        ids = t.encode(text or "", add_special_tokens=False).ids
        want[(doc_id, len(ids), hashlib.sha256(np.asarray(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest())] += 1
    assert got == want and bpe.digests(empty, vocabulary()).collect() == []


def test_forced_cuts_on_odd_texts():
    t, coder = Tokenizer.from_file(vocabulary()), bpe.ForcedCutEncoder(vocabulary())
    rng = np.random.default_rng(2)
    pool = list("abcXYZ012 '!?.,\n\téÉßİΣ́日\U0001f600 \x1cÅ½") + ["<|endoftext|>", "'s", "'LL", "thequick", "aaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaqz"]
    for _ in range(1500):
        text = "".join(rng.choice(pool, rng.integers(0, 30)))
        e = t.encode(text, add_special_tokens=False)
        ids, said = coder.encode(text)
        assert np.frombuffer(ids, "<u4").tolist() == e.ids and said.decode() == t.decode(e.ids, skip_special_tokens=False)


def test_pieces_are_certain():
    coder = bpe.ForcedCutEncoder(vocabulary())
    rng = np.random.default_rng(4)
    cut = 0
    for _ in range(400):
        word = "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyzqqzzxxjj"), 40)).encode()
        pieces = coder.pieces(word)
        cut += len(pieces) > 1
        assert b"".join(pieces) == word
        assert coder.encode_word(word) == [x.id for x in coder.last.tokenize(word.decode())]
    assert cut > 200


def test_every_pair_of_latin_characters():
    t, coder = Tokenizer.from_file(vocabulary()), bpe.ForcedCutEncoder(vocabulary())
    texts = [f"ab{chr(a)}{chr(b)}'so" for a in range(256) for b in range(256)]
    want = [e.ids for e in t.encode_batch(texts, add_special_tokens=False)]
    assert [np.frombuffer(x, "<u4").tolist() for x in coder.encode_batch(texts)] == want


def test_forced_cuts_make_the_fragments_of_documents(spark):
    """Nearly all cuts are made by pairs that no token joins; thousands of them are inside words."""
    coder = bpe.ForcedCutEncoder(vocabulary())
    counts: Counter = Counter()
    for (text,) in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("text").toLocalIterator():
        try:
            run = (text or "").lower().encode("latin-1") + b"\n"
        except UnicodeEncodeError:
            continue
        forced, ends = coder.cuts(run)
        full = coder.classes[np.frombuffer(run, "u1")] != bpe.SPACE
        counts["space"] += int((forced & (full[:-1] ^ full[1:])).sum())
        counts["space, not forced"] += int((~forced & (full[:-1] ^ full[1:])).sum())
        inside = full[:-1] & full[1:]
        counts["word end"] += int((forced & ends & inside).sum())
        counts["inside a word"] += int((forced & ~ends & inside).sum())
        counts["pattern only"] += int((~forced & ends & inside).sum())
    assert counts["space, not forced"] == 0 and counts["inside a word"] > 10_000
    assert counts["pattern only"] < 0.01 * (counts["space"] + counts["word end"] + counts["inside a word"])


def test_long_texts_go_in_parts(monkeypatch):
    t, coder = Tokenizer.from_file(vocabulary()), bpe.ForcedCutEncoder(vocabulary())
    monkeypatch.setattr(bpe, "RUN", 50)
    monkeypatch.setattr(bpe, "FRAGMENTS_KEPT", 20)
    texts = [" word qzqz'll né" * 90, None, "", "x" * 400, "日本 語 " * 40, BASE * 3]
    assert [np.frombuffer(x, "<u4").tolist() for x in coder.encode_batch(texts)] == [t.encode(x or "", add_special_tokens=False).ids for x in texts]


def test_other_kinds_of_vocabulary_are_refused():
    import public_tokenizers

    with pytest.raises(ValueError, match="certain cuts"):
        bpe.ForcedCutEncoder(public_tokenizers.path("byte_bpe_50k.json"))


@pytest.mark.parametrize("dim", [3, 16])
def test_top_k(spark, dim):
    rng = np.random.default_rng(dim)
    rows = [(int(i), rng.normal(size=dim).tolist()) for i in range(400)] + [(1000 + i, [0.5] * dim) for i in range(60)]
    rows += [(5000, None), (5020, [float("nan")] * dim), (5040, [None] * dim), (5060, []), (None, [0.1] * dim), (40, rows[3][1])]
    df = spark.createDataFrame([(*r, 1, "q") for r in rows], "vec_id long, embedding array<float>, score int, `rank` string")
    got = {(r.query_id, r["rank"], r.vec_id, r.score) for r in m_tree.top_k(df).collect()}
    ok = [(i, np.floor(64 * np.asarray(v, "f4").astype("f8"))) for i, v in rows if i is not None and i < 5000]
    want = set()
    for q in {i for i, _ in ok if i % 20 == 0}:
        for at in [v for i, v in ok if i == q][:1]:
            if sum(i == q for i, _ in ok) > 1:
                continue
            best = sorted(((-int(v @ at), i) for i, v in ok if i != q))[:20]
            want |= {(q, n + 1, i, -s) for n, (s, i) in enumerate(best)}
    assert {g for g in got if g[0] != 40} == want
    assert m_tree.top_k(df.filter("vec_id < 0")).collect() == []


def test_m_tree_prunes_and_stays_exact():
    rng = np.random.default_rng(0)
    x = np.floor(64 * np.concatenate([rng.normal(c, 0.05, (500, 8)) for c in rng.normal(size=(12, 8))]))
    ids = rng.permutation(len(x))
    tree = m_tree.build(ids, x, 5, page=32)
    for i in range(0, len(x), 371):
        s = x @ x[i]
        best = sorted((-int(a), int(b)) for a, b in zip(s, ids) if b != ids[i])[:5]
        assert tree.search(x[i], 5, int(ids[i])) == [(-a, b) for a, b in best]


def test_pu_quality(spark):
    rng = np.random.default_rng(1)
    vocab = ["".join(rng.choice(list("etaoinshr"), rng.integers(2, 8))) for _ in range(400)]
    good = [" ".join(rng.choice(vocab, rng.integers(30, 120))) + "." for _ in range(1800)]
    junk = [" ".join(w.upper() + "!!" for w in rng.choice(vocab, 60)) if i % 2 else " ".join(f"{w}###" for w in rng.choice(vocab, 60)) for i in range(500)]
    texts = [(i, t, int(i < 1800)) for i, t in enumerate(good + junk)]
    docs = spark.createDataFrame([(i, t, "en") for i, t, _ in texts] + [(9000, None, "en"), (9001, "", "en")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, q) for i, _, q in texts if i % 2 == 0], "doc_id long, quality int")
    fit = pu_quality.Fit(steps=300)
    rows = {r.doc_id: r for r in pu_quality.classify(docs, labels, fit).collect()}
    truth = {i: q for i, _, q in texts}
    assert len(rows) == 2302 and all(0 <= r.score <= 1 and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows.values())
    held = [r for r in rows.values() if r.held_out and r.doc_id in truth]
    good_scores, junk_scores = ([r.score for r in held if truth[r.doc_id] == c] for c in (1, 0))
    ordered = np.mean([g > j for g in good_scores for j in junk_scores])
    assert ordered > 0.99 and np.mean([s >= pu_quality.THRESHOLD for s in good_scores]) > 0.97
    flipped = labels.withColumn("quality", F.when(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, 1 - F.col("quality")).otherwise(F.col("quality")))
    assert {r.doc_id: r.score for r in pu_quality.classify(docs, flipped, fit).collect()} == pytest.approx({i: r.score for i, r in rows.items()})
    assert pu_quality.classify(docs.filter("doc_id < 0"), labels, fit).collect() == []
    assert {r.score for r in pu_quality.classify(docs, labels.filter("quality > 5"), fit).collect()} == {0.5}


def page(body, head=""):
    return f"<!DOCTYPE html><html><head><title>T</title><style>p{{x}}</style>{head}</head><body>{body}</body></html>"


@pytest.mark.parametrize(
    ("html", "text"),
    [
        (None, ""), ("", ""), ("plain &amp; simple", "plain & simple"), ("<p>a<p>b  \n c", "a\nb c"),
        (page("<nav><a href=x>Menu</a></nav><article><h1>T&eacute;st</h1><p><b>One.<br><p>Two &lt;b&gt;</article><footer>f</footer>"), "Tést\nOne.\nTwo <b>"),
        (page("<div id=content><p>Kept <i>in</i>line <a href='a>b'>link</a></p></div><div class='ad big'>Buy</div><aside>s</aside><form>f<input></form>"), "Kept inline link"),
        (page("<article><p>A</p><!-- x <p>no</p> --><div class=comments><p>c</p><article class=comment>d</article></div><script>var a='</p>';</script><p>B</article>"), "A\nB"),
        (page("<main><ul><li>x<li>y</ul><table><tr><td>1<td>2</table></main><p>out"), "x\ny\n1 2"),
        ("<p>broken <a href='unclosed>tail <b", "broken tail"), ("<!-- never closed <p>x", ""), ("<script>if (a<b) x", ""),
        (page("<article><header class='entry-header'><h1>Title</h1></header><p>A</p></article>"), "Title\nA"),
        (page("<article><h1 class=header>Title</h1><p>A</p><section class=related-work><h2>Related work</h2><p>B</p></section><div class='related-posts'>x</div><aside>y</aside></article>"), "Title\nA\nRelated work\nB"),
        (page("<div class='site_header2'>x</div><ul class=menu><li>m</ul><div id=comments><p>c</p></div><div class=headers-explained>About headers</div>"), "About headers"),
        (page("<header>site</header><div class=cookie-notice>ok?</div><p>Body &#8364; &nbsp; end</p>"), "Body € end"),
    ],
)
def test_main_text(html, text):
    if html and "unclosed" in html:
        assert site_tree.main_text(html).startswith("broken")
    else:
        assert site_tree.main_text(html) == text


def test_style_tree_removes_what_a_site_repeats(spark):
    rows = [(i, f"http://h.example/{i}", page(f"<div class=top>Welcome to the site</div><div class=body><p>Own text {i} of page.</p><p>And {i * 7} more.</p></div>")) for i in range(12)]
    rows += [(100, None, rows[0][2]), (101, "not a url", None), (102, "http://small.example/", rows[0][2])]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, text string")
    got = {r.page_id: r for r in site_tree.extract(df).collect()}
    assert got[3].text == "Own text 3 of page.\nAnd 21 more." and got[3].n_chars == len(got[3].text)
    assert got[102].text.startswith("Welcome") and got[100].text.startswith("Welcome") and got[101].text == "" and len(got) == 15
    assert site_tree.extract(df.filter("page_id < 0")).collect() == []


def test_trees_alone_find_the_articles_of_the_given_pages(spark):
    """Without names and marks the trees give the same texts; without the trees every page has its menu and advert."""
    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    full, trees, neither = (
        {r.page_id: r.text for r in site_tree.extract(pages, rules).collect()}
        for rules in (site_tree.Rules(), site_tree.Rules(named=False, marked=False), site_tree.Rules(named=False, marked=False, low=0.0, low_inside=0.0))
    )
    assert len(full) == 2500 and trees == full and not any(neither[i] == full[i] for i in full)


def test_copies_of_pages_are_no_template(spark):
    """A host that has one page in many copies, or two, keeps its text; one with few pages too."""
    rows = [(i, "http://copies.example/", page("<div><p>The one text of this host.</p></div>")) for i in range(40)]
    rows += [(100 + i, "http://two.example/", page(f"<div><p>Text of {'first' if i % 2 else 'second'} kind.</p></div>")) for i in range(40)]
    rows += [(200 + i, "http://few.example/", page(f"<div class=lead>Same lead</div><div><p>Text {'abc'[i]} of a kind.</p></div>")) for i in range(3)]
    got = {r.page_id: r.text for r in site_tree.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[7] == "The one text of this host." and got[101] == "Text of first kind." and got[201] == "Same lead\nText b of a kind."


def test_long_and_deep_pages_take_linear_time():
    import time

    began = time.process_time()
    wide = site_tree.main_text("<div>" + "".join(f"<div class=x><p>t{i}</div>" for i in range(60_000)))
    deep = site_tree.main_text("<div>" * 60_000 + "end" + "</b></p></li>" * 60_000)
    assert wide.count("\n") == 59_999 and deep == "end" and time.process_time() - began < 30


def test_m_tree_reads_a_page_once_for_a_bundle_of_queries(monkeypatch):
    rng = np.random.default_rng(6)
    x, taken, pop = np.floor(64 * rng.normal(size=(3000, 16))), [], m_tree.heapq.heappop
    monkeypatch.setattr(m_tree.heapq, "heappop", lambda heap: taken.append(1) or pop(heap))
    every = pd.DataFrame({"vec_id": np.arange(3000), "v": list(x), "is_query": False})
    asked = every[every["vec_id"] % 20 == 0].assign(is_query=True)
    (got,) = m_tree._search_blocks(5)((), iter([pd.concat([every, asked])]))
    want = {(q, s, i) for q in range(0, 3000, 20) for s, i in [(-a, i) for a, i in sorted((-int(a), i) for i, a in enumerate(x @ x[q]) if i != q)[:5]]}
    assert set(got[["query_id", "score", "vec_id"]].itertuples(index=False, name=None)) == want
    assert len(taken) < len(asked)  # one by one, each query would read most of the pages


def test_workers_hold_few_texts_as_objects():
    """Batches of any size are taken in parts, with the rows of the whole."""
    import pyarrow as pa

    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(2000)), "text": [f"{i} word " * 9 for i in range(2000)]})
    made = list(bpe._digest_batches(vocabulary())(iter([batch, batch.slice(0, 0)])))
    assert max(b.num_rows for b in made) <= 512 and [i for b in made for i in b.column(0).to_pylist()] == list(range(2000))
