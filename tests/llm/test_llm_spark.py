"""The corpus operators on small tables with nulls, ties, repeated rows, long texts, clashing columns and no rows."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from congraph.llm import best_fit, bitpack, exact_dedup, html_extract, kd_shards, line_dedup, merkle, ngram_join, sentencepiece_viterbi, toxicity
from congraph.llm.common import Stages
from congraph.llm.components import components
from tests_llm_data import ROWS

NAMES = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame(ROWS, NAMES)
    # Names that the operators use inside.
    return df.withColumn("n", F.lit(1)).withColumn("class", F.lit("x")).withColumn("size", F.lit(None).cast("int")).withColumn("keep_id", F.lit(0)).withColumn("score", F.lit(0.5)).withColumn("_kept_id", F.lit(3)).withColumn("bucket", F.lit(2)).cache()


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def spark_of(df):
    return df.sparkSession


def texts():
    return [(r[0], r[1] or "") for r in ROWS]


def test_exact_classes(docs, none):
    norm = lambda t: re.sub("[\x20\x09-\x0d]+", " ", t)
    groups = collections.defaultdict(list)
    for i, t in texts():
        groups[norm(t)].append(i)
    got = sorted(tuple(r) for r in exact_dedup.exact_classes(docs).collect())
    assert got == sorted((i, min(groups[norm(t)]), len(groups[norm(t)]), i == min(groups[norm(t)]), hashlib.sha256(norm(t).encode()).hexdigest()) for i, t in texts())
    assert exact_dedup.exact_classes(none).count() == 0
    kept = exact_dedup.drop_copies(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {min(g) for g in groups.values()}
    spilled = exact_dedup.exact_classes(docs, task_budget=1000, trie_budget=1000)
    assert sorted(tuple(r) for r in spilled.collect()) == got


def brute_components(rows):
    sets = []
    for i, t in rows:
        w = re.findall("[^\x20\x09-\x0d]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t))
        sets.append((i, {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()))
    parent = {i: i for i, _ in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, (i, x) in enumerate(sets):
        for j, y in sets[:a]:
            if x and y and 100 * len(x & y) >= 80 * len(x | y):
                p, q = find(i), find(j)
                parent[max(p, q)] = min(p, q)
    return sets, find


def test_near_components(docs, none):
    sets, find = brute_components(texts())
    got = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in ngram_join.near_components(docs).collect())
    assert got == collections.Counter((i, len(s), find(i)) for i, s in sets)
    assert len({c for _, _, c in got}) < len({i for i, _ in sets})
    assert ngram_join.near_components(none).count() == 0
    parts = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in ngram_join.near_components(docs, long_list=2).collect())
    assert parts == got
    kept = ngram_join.drop_near_copies(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {find(i) for i, _ in sets}


def random_family(seed):
    """Edited copies of a few texts that meet in shared passages, with likenesses around the threshold."""
    r = random.Random(seed)
    passage = [f"p{k}" for k in range(30)]
    bases = [[f"b{b}w{r.randrange(400)}" for _ in range(60)] + passage for b in range(4)]
    out = []
    for k in range(120):
        words = list(r.choice(bases))
        for _ in range(r.choice((0, 1, 1, 2, 2, 3))):
            words[r.randrange(len(words))] = f"e{r.randrange(5)}"
        out.append((k * 3, " ".join(words[r.choice((0, 0, 6)) :])))
    return out


@pytest.mark.parametrize("long_list", [5, 20_000])
def test_components_of_families_around_the_threshold(spark, long_list):
    rows = random_family(long_list)
    sets, find = brute_components(rows)
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.near_components(table, long_list=long_list).collect()}
    assert got == {i: (len(s), find(i)) for i, s in sets} and 4 < len({c for _, c in got.values()}) < 100


def test_one_row_of_each_group_stays(spark):
    """Repeated ids: rows with one id and text are one row's copies; one id with two texts is two documents."""
    long = " ".join(f"w{k}" for k in range(60))
    rows = [(1, "x y"), (1, "x y"), (1, "another text of the same id"), (2, "x  y"), (3, long), (3, long), (3, long + " z"), (4, long + " z"), (5, ""), (5, "")]
    table = spark.createDataFrame(rows, "doc_id long, text string").coalesce(2)
    kept = lambda df: sorted(map(tuple, df.collect()))
    assert kept(exact_dedup.drop_copies(table)) == sorted([(1, "x y"), (1, "another text of the same id"), (3, long), (3, long + " z"), (5, "")])
    near = kept(ngram_join.drop_near_copies(table))
    assert len(near) == 5 and [r for r in near if r[0] != 3] == sorted([(1, "x y"), (1, "another text of the same id"), (5, ""), (5, "")])
    assert [r[0] for r in near].count(3) == 1


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101)], "a long, b long")
    assert dict(map(tuple, components(edges, Stages(spark)).collect())) == {**{k: 0 for k in range(1, 41)}, 101: 100}


def test_packed_ids(docs, none, spark):
    tokenizers = pytest.importorskip("tokenizers")
    files = pytest.importorskip("public_tokenizers")
    lib = tokenizers.Tokenizer.from_file(files.path("byte_bpe_50k.json"))
    folder, manifest = bitpack.write_packed(docs)
    got = bitpack.read_packed(spark, folder, manifest).orderBy("start").collect()
    assert [r.doc_id for r in got] == sorted(i for i, _ in texts())
    by_id, at = collections.defaultdict(list), 0
    for i, t in texts():
        ids = np.array(lib.encode(t, add_special_tokens=False).ids + [2], "<u4")
        by_id[i].append((len(ids), zlib.crc32(ids.tobytes())))
    for r in got:
        assert r.start == at and (r.n_tokens, r.ids_crc32) in by_id[r.doc_id]
        at += r.n_tokens
    first = manifest.where("n_ids > 3").first()
    assert len(bitpack.packed_ids(folder, first.path, 1, 3)) == 2
    folder, manifest = bitpack.write_packed(none)
    assert bitpack.read_packed(spark, folder, manifest).count() == 0


def test_best_fit(docs, none):
    tokenizers = pytest.importorskip("tokenizers")
    files = pytest.importorskip("public_tokenizers")
    lib = tokenizers.Tokenizer.from_file(files.path("word_bpe_49k.json"))
    got = best_fit.pack_documents(docs).collect()
    expected = collections.Counter()
    for i, t in texts():
        ids = np.array(lib.encode(t, add_special_tokens=False).ids + [0], "<u4")
        for k, a in enumerate(range(0, len(ids), 2048)):
            expected[i, k, a, len(ids[a : a + 2048]), zlib.crc32(ids[a : a + 2048].tobytes())] += 1
    assert collections.Counter(tuple(r)[:5] for r in got) == expected
    bins = collections.defaultdict(list)
    for r in got:
        bins[r.sequence_id].append((r.offset, r.length))
    for pieces in bins.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 2048
    assert best_fit.pack_documents(none).count() == 0


def test_packed_sequences(docs):
    pytest.importorskip("public_tokenizers")
    once = docs.dropDuplicates(["doc_id"])
    placed = best_fit.pack_documents(once)
    sizes = {r.sequence_id: r.n for r in placed.groupBy("sequence_id").agg(F.sum("length").alias("n")).collect()}
    assert {r.sequence_id: len(r.ids) for r in best_fit.packed_sequences(once, placed).collect()} == sizes


def test_shards(docs, none):
    got = kd_shards.shard_documents(docs, leaves=4).collect()
    assert collections.Counter((r.doc_id, r.size, r.text_crc32) for r in got) == collections.Counter((i, len(t.encode()) + 1, zlib.crc32(t.encode())) for i, t in texts())
    slots = collections.defaultdict(list)
    for r in got:
        slots[r.shard].append(r.slot)
    assert set(slots) <= set(range(4)) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert kd_shards.shard_documents(none).count() == 0
    total = sum(r.size for r in got)
    assert {r.law for r in got} == {"bytes"}
    # Cuts lie at weighted medians: a cut puts a half apart by one row's size at most, and three cuts lie above a shard at eight leaves.
    even = [(3 * k, "w" * (5 + k * 7 % 90)) for k in range(400)]
    sizes = collections.Counter()
    for r in kd_shards.shard_documents(spark_of(docs).createDataFrame(even, "doc_id long, text string"), leaves=8).collect():
        sizes[r.shard] += r.size
    whole = sum(sizes.values())
    assert len(sizes) == 8 and max(sizes.values()) - min(sizes.values()) <= 0.1 * whole / 8
    assert len({r.shard for r in kd_shards.shard_documents(docs, leaves=None, target_bytes=total // 3).collect()}) >= 3


def test_fingerprints(docs, none):
    got = {}
    for r in merkle.fingerprints(docs).collect():
        got.setdefault(r.doc_id, []).append(r)
    rows = sorted(texts(), key=lambda x: (x[0], x[1].encode()))
    prints = {}
    for k, (i, t) in enumerate(rows):
        after = rows[(k + 1) % len(rows)][1]
        half = len(t) // 2
        edited = t[: len(t) - half] + after[:half]
        r = next(x for x in got[i] if x.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest() and x.n_chars == len(t))
        assert prints.setdefault(t, r.fingerprint) == r.fingerprint and 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
        assert r.near_edited == pytest.approx(merkle.likeness(r.fingerprint, r.edited_fingerprint))
    assert len(set(prints.values())) == len(prints)
    assert merkle.fingerprints(none).count() == 0
    assert merkle.fingerprints(docs.limit(1)).count() == 1


def test_lines(docs, none):
    rows = sorted({(i, t) for i, t in texts()})
    seen, gone = [], collections.Counter()
    for i, t in rows:
        for k, line in enumerate(t.split("\n")):
            words = {w for w in re.split("[\x20\x09-\x0d]+", line.lower()) if w}
            if not words:
                continue
            if any(100 * len(words & s) >= 80 * len(words | s) for s in seen):
                gone[i] += 1
            seen.append(words)
    got = {r.doc_id: r for r in line_dedup.dedup_lines(docs).collect()}
    once = [i for i, n in collections.Counter(i for i, _ in texts()).items() if n == 1]
    assert {i: got[i].n_removed for i in once} == {i: gone[i] for i in once} and sum(gone.values()) > 3
    assert all(len(got[i].text.split("\n")) >= 1 and got[i].n_lines == len(t.split("\n")) for i, t in texts())
    assert line_dedup.dedup_lines(none).count() == 0


def test_pieces(docs, none):
    pytest.importorskip("public_tokenizers")
    got = sentencepiece_viterbi.encode_digests(docs).collect()
    assert len(got) == len(ROWS) and all(r.round_trip for r in got)
    back = sentencepiece_viterbi.decode(sentencepiece_viterbi.encode(docs))
    assert collections.Counter(map(tuple, back.collect())) == collections.Counter(texts())
    assert sentencepiece_viterbi.encode_digests(none).count() == 0


def test_pages(spark):
    pages = spark.createDataFrame([(1, "u", "<p>Some text of the page, long enough.</p>", 1), (2, None, None, 1), (2, "v", "", 1), (3, "w", "<article><p>" + "x" * 100_000 + "</p></article>", 1)], "page_id long, url string, html string, n_chars int")
    got = sorted((r.page_id, len(r.text), r.n_chars) for r in html_extract.extract_pages(pages).collect())
    assert got == [(1, 35, 35), (2, 0, 0), (2, 0, 0), (3, 100_000, 100_000)]
    assert html_extract.extract_pages(pages.limit(0)).count() == 0


def test_toxicity(docs, none, spark):
    clean = ["the weather is mild and the sea is calm today", "we read a book about birds in the garden"]
    bad = ["you are such an idiot and everyone here knows it", "what an idiot that man is they all said"]
    rows = [(1000 + k, (bad if k % 2 else clean)[k // 2 % 2] + f" number {k}") for k in range(300)] + [(5000, "Y0u are an 1d10t my friend"), (5001, None), (5002, "a calm sea")]
    table = spark.createDataFrame(rows, "doc_id long, text string").withColumn("label", F.lit("z")).withColumn("score", F.lit(1))
    labels = spark.createDataFrame([(1000 + k, 1, k % 2) for k in range(300)] + [(None, 1, 1), (1001, 1, None)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.score_toxicity(table, labels).collect()}
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in got.values())
    assert all(got[1000 + k].predicted == k % 2 for k in range(300)) and got[5000].predicted == 1 and got[5002].predicted == 0
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in got.items())
    assert {r.doc_id for r in toxicity.drop_toxic(table, labels).collect()} == {i for i, r in got.items() if not r.predicted}
    assert toxicity.score_toxicity(docs, labels.limit(0)).where("score <> 0").count() == 0
    assert toxicity.score_toxicity(none, labels).count() == 0


def test_pipeline_stages_on_each_others_rows(spark, tmp_path):
    """Toxic rows, copies, near copies and repeated ids, with columns of names that the stages use; then no rows at all."""
    import corpus_pipeline

    mild = ["the weather is mild and the sea is calm today", "we read a book about birds in the garden"]
    rude = ["you are such an idiot and everyone here knows it", "what an idiot that man is they all said"]
    marked = [(10_000 + k, (rude if k % 4 == 1 else mild)[k // 2 % 2 if k % 4 != 1 else k // 4 % 2] + f" number {k} " + " ".join(f"u{k}x{j}" for j in range(9))) for k in range(240)]
    rows = [(r[0], r[1]) for r in ROWS if r[1] != "another text under one id"] + marked + [(20_000, "Y0u are an 1d10t my friend"), (20_000, "a calm sea and a mild wind")]
    table = spark.createDataFrame(rows, "doc_id long, text string").withColumn("class", F.lit("x")).withColumn("score", F.lit(0.1)).withColumn("n", F.lit(3)).withColumn("_text0", F.lit(1))
    table.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(10_000 + k, 1, int(k % 4 == 1)) for k in range(240)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    norm = lambda t: re.sub("[\x20\x09-\x0d]+", " ", t)
    first = {}
    for i, t in sorted((i, t or "") for i, t in rows):
        if "idiot" not in t and "1d10t" not in t:
            first.setdefault(norm(t), (i, t))
    stay = sorted(set(first.values()))
    _, find = brute_components(stay)
    expected = {i for i, _ in stay if find(i) == i}
    assert {r.doc_id for r in out} == expected and 20_000 in expected and not any(10_000 + k in expected for k in range(1, 240, 4))
    assert collections.Counter(r.doc_id for r in out if r.piece == 0) == collections.Counter(expected)
    empty = tmp_path / "empty"
    table.limit(0).write.parquet(f"{empty}/documents.parquet")
    spark.read.parquet(f"{tmp_path}/labels.parquet").limit(0).write.parquet(f"{empty}/labels.parquet")
    assert corpus_pipeline.run(spark, str(empty)).count() == 0


def test_null_ids_lose_no_row(spark):
    long = " ".join(f"w{k}" for k in range(60))
    rows = [(None, "only here"), (None, "copied  once"), (5, "copied once"), (3, "copied once"), (None, long), (None, long + " x"), (8, "near " + long), (None, ""), (9, "other text of this table here"), (None, None)]
    alone = [(None, "n" + long.replace("w", "v")), (None, "m" + long.replace("w", "v"))]
    table = spark.createDataFrame(rows + alone, "doc_id long, text string").coalesce(1)
    got = collections.Counter((r.doc_id, r.keep_id, r.group_size, r.kept) for r in exact_dedup.exact_classes(table).collect())
    assert got == collections.Counter([(None, None, 1, None), (None, 3, 3, None), (5, 3, 3, False), (3, 3, 3, True), (8, 8, 1, True), (9, 9, 1, True)] + [(None, None, 2, None)] * 2 + [(None, None, 1, None)] * 4)
    assert sum(exact_dedup.exact_classes(table, task_budget=1, trie_budget=1).groupBy().count().first()) == len(rows) + 2
    kept = collections.Counter(tuple(r) for r in exact_dedup.drop_copies(table).collect())
    # Null and empty are one text, and of one text one row stays.
    assert kept[None, ""] + kept[None, None] == 1
    assert kept - collections.Counter([(None, ""), (None, None)]) == collections.Counter([r for r in rows if r[1] not in ("copied  once", "", None) and r[0] != 5] + alone)
    near = collections.Counter((r.doc_id, r.component_id) for r in ngram_join.near_components(table).collect())
    assert near[None, 8] == 2 and near[None, 3] == 1 and sum(near.values()) == len(rows) + 2
    kept = collections.Counter(tuple(r) for r in ngram_join.drop_near_copies(table).collect())
    # The two of `alone` are near each other: one stays.
    assert kept[alone[0]] + kept[alone[1]] == 1
    assert kept - collections.Counter(alone) == collections.Counter([(None, "only here"), (3, "copied once"), (8, "near " + long), (None, ""), (9, "other text of this table here"), (None, None)])


def test_near_pairs_are_the_whole_join(docs, none):
    sets, _ = brute_components(texts())
    near = lambda x, y: x and y and 100 * len(x & y) >= 80 * len(x | y)
    expected = collections.Counter((i, len(x), sum(bool(near(x, y)) for _, y in sets) - bool(x)) for i, x in sets)
    pairs, members = ngram_join.near_pairs(docs)
    assert collections.Counter((r.doc_id, r.n_shingles, r.n_links) for r in members.collect()) == expected
    classes = {frozenset(x) for _, x in sets}
    found = pairs.collect()
    assert len(found) == len(set(found)) == sum(bool(near(x, y)) for x in classes for y in classes if x != y) // 2
    parts = {r.component_id for r in ngram_join.near_components(docs).where("n_shingles > 0").collect()}
    assert len(found) > len({x for x in classes if x}) - len(parts)
    pairs, members = ngram_join.near_pairs(none)
    assert pairs.count() == members.count() == 0


def test_short_lines_match_at_a_lower_percent(spark):
    table = spark.createDataFrame([(1, "red old"), (2, "red old box"), (3, "unlike")], "doc_id long, text string")
    removed = lambda percent: {r.doc_id: r.n_removed for r in line_dedup.dedup_lines(table, percent).collect()}
    assert removed(60) == {1: 0, 2: 1, 3: 0} and removed(80) == {1: 0, 2: 0, 3: 0}
