"""Operators 1, 6 and the pipeline against plain versions over small tables."""

import random
import zlib
from collections import defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from binflow.llm import common, packing, quality, queries, simhash, substring

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(common.tokenizer_path())


def check_packing(rows, texts, library, capacity):
    """Rows (id, piece, start, length, crc, sequence, offset) hold every text's ids and the end id, in gapless sequences."""
    pieces, sequences = defaultdict(list), defaultdict(list)
    for i, piece, start, length, crc, sequence, offset in rows:
        pieces[i].append((piece, start, length, crc))
        sequences[sequence].append((offset, length))
    assert set(pieces) == set(texts)
    for i, text in texts.items():
        ids = np.array([*library.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        n = -(-len(ids) // capacity)
        cuts = [0, *(len(ids) - capacity * (n - 1 - k) for k in range(n))]
        assert sorted(pieces[i]) == [(k, a, b - a, zlib.crc32(ids[a:b].tobytes())) for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))]
    for places in sequences.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= capacity
    assert len(sequences) <= 1.01 * sum(r[3] for r in rows) / capacity + 1


def own_fingerprint(text):
    """Votes of each bit, counted one by one."""
    words = [w for w in "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").replace("\t", " ").replace("\n", " ").replace("\x0b", " ").replace("\x0c", " ").replace("\r", " ").split(" ") if w]
    if not words:
        return 0
    width = min(3, len(words))
    hashes = [xxhash.xxh64(" ".join(words[i : i + width]).encode(), seed=42).intdigest() for i in range(len(words) - width + 1)]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def groups_of(prints):
    """id -> smallest id reachable over prints at two bits or fewer."""
    ids = sorted(prints)
    label = {i: i for i in ids}
    changed = True
    while changed:
        changed = False
        for a in ids:
            for b in ids:
                if (prints[a] ^ prints[b]).bit_count() <= 2 and label[b] < label[a]:
                    label[a], changed = label[b], True
    return label


def test_packing_against_the_library(spark, library):
    draw = random.Random(20)
    texts = {i: " ".join(draw.choices(["alpha", "Beta", "gamma 7", "\n", "é"], k=draw.choice([0, 1, 5, 40, 200]))) for i in range(200)} | {200: None, 201: "", 202: "long word " * 3000}
    df = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string").repartition(5)
    check_packing([tuple(r) for r in packing.pack(df, capacity=64).collect()], texts, library, 64)
    check_packing([tuple(r) for r in packing.pack(df).collect()], texts, library, 2048)


def test_fingerprints_against_all_pairs(spark):
    draw = random.Random(21)
    words = [f"w{i}" for i in range(400)]
    texts = {}
    for i in range(0, 120, 3):
        base = draw.choices(words, k=draw.choice([1, 2, 3, 30, 300]))
        near = base.copy()
        near[draw.randrange(len(near))] = "changed"
        texts |= {i: " ".join(base), i + 1: "\n".join(base).upper(), i + 2: " ".join(near)}
    texts |= {200: None, 201: "", 202: " \t"}
    got = {r.doc_id: (r.fp & (1 << 64) - 1, r.component_id) for r in simhash.near_duplicates(spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")).collect()}
    prints = {i: own_fingerprint(t) for i, t in texts.items()}
    label = groups_of(prints)
    assert got == {i: (prints[i], label[i]) for i in texts}
    assert sum(label[i] != i for i in label) > 40


def test_pipeline_against_plain_stages(spark, library):
    """Each stage's decisions on all that its predecessor kept, and the packed rows of the whole."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    text = {r.doc_id: r.text for r in docs.collect()}
    scores = {r.doc_id: r.predicted for r in quality.score(docs, quality.train(docs, labels)).collect()}
    stages = [docs]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        stages.append(common.materialise(stage(spark, stages[-1], SMALL), "stage"))
        assert stages[-1].columns == docs.columns
    kept = [{r.doc_id: r.text for r in s.collect()} for s in stages]
    assert kept[1] == {i: t for i, t in text.items() if scores[i]}
    label = groups_of({i: own_fingerprint(t) for i, t in kept[1].items()})
    assert kept[2] == {i: t for i, t in kept[1].items() if label[i] == i}

    runs = lambda t, n: {tuple(w[k : k + n]) for w in [(t or "").lower().split()] for k in range(len(w) - n + 1)}
    assert set(kept[3]) == set(kept[2])
    seen, shingles, cut = set(), set(), 0
    for i in sorted(kept[3]):
        assert not runs(kept[3][i], 50) & seen  # what an earlier document holds is gone
        if not runs(kept[2][i], 5) & shingles:
            assert kept[3][i] == kept[2][i]  # and nothing else
        seen |= runs(kept[2][i], 50)
        shingles |= runs(kept[2][i], 5)
        cut += kept[3][i] != kept[2][i]
    assert cut > 0
    check_packing([tuple(r) for r in corpus_pipeline.run(spark, SMALL).collect()], kept[3], library, packing.CAPACITY)


def test_queries_of_contracts_on_odd_tables(spark, tmp_path):
    """Null, empty and repeated rows, clashing names, and an empty table through the registered digests."""
    rows = [(1, None, "x", 1), (2, "", "x", None), (3, "a b c " * 60, None, 2), (3, "a b c " * 60, None, 2), (4, "Released under the MIT License.", "y", 0)]
    odd = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, key int").withColumn("source", F.lit("s")).withColumn("n_chars", F.length("text")).withColumn("length", F.lit(1))
    for name, df in (("odd", odd), ("none", odd.limit(0))):
        df.write.parquet(f"file://{tmp_path}/{name}/documents.parquet")
        spark.createDataFrame([(1, 1, 0), (3, 0, 0)], "doc_id bigint, quality int, toxic int").write.parquet(f"file://{tmp_path}/{name}/labels.parquet")
        for q in ("op2_bpe_round_trip", "op4_sharding", "op6_simhash_near_dedup", "op8_quality_classifier", "op9_token_counts", "op10_license_scan"):
            assert queries.queries()[q](spark, f"file://{tmp_path}/{name}").count() == df.count(), q
        assert queries.queries()["op7_substring_dedup"](spark, f"file://{tmp_path}/{name}").count() == 0
        assert (queries.queries()["pipeline"](spark, f"file://{tmp_path}/{name}").count() == 0) == (name == "none")


def test_text_ids_are_ordered(spark):
    draw = random.Random(22)
    words = lambda n: " ".join("".join(draw.choices("abcdefgh", k=6)) for _ in range(n))
    shared = words(60)
    df = spark.createDataFrame([(f"d{i}", f"{words(40)} {shared} {words(40)}") for i in range(3)] + [(None, shared)], "doc_id string, text string")
    found = substring.repeated_passages(df).collect()
    assert sorted(map(tuple, found)) == [("d1", 40, 100, "d0"), ("d2", 40, 100, "d0")]
    assert substring.remove_repeated(df).where("doc_id = 'd0' or doc_id is null").exceptAll(df).count() == 0
