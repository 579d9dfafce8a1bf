"""The pipeline against plain Python over a small table."""

import hashlib
import re

import numpy as np
import public_tokenizers
import tiktoken
import xxhash
from pyspark.sql import Row

import corpus_pipeline
from obljoin.llm import bpe, mixing

LOWER = str.maketrans({c: c.lower() for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"})


def fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text.translate(LOWER))
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + 3]).encode(), 42) for i in range(max(1, len(words) - 2))] if words else []
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_stages_and_run(spark, tmp_path):
    source = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    extra = [Row(doc_id=9001, text=None, lang="en", source="src1", n_chars=0), Row(doc_id=9002, text="12 34 !!", lang="en", source="src1", n_chars=8), Row(doc_id=None, text="The of and in the thing on the", lang=None, source=None, n_chars=None)]
    docs = source.unionByName(spark.createDataFrame(extra, source.schema)).unionByName(source.limit(3))
    docs.coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    held = {None: docs}
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, str(tmp_path))
        docs.write.parquet(str(tmp_path / name))
        held[name] = docs = spark.read.parquet(str(tmp_path / name))
    rows = {k: [r.asDict() for r in d.collect()] for k, d in held.items()}
    for name in ("language_id", "exact_dedup", "simhash", "mixing"):
        assert held[name].columns == source.columns
    judged = {str(r) for r in rows["language_id"]}
    gone = [r for r in rows[None] if str(r) not in judged]
    assert {r["doc_id"] for r in gone} >= {9001, 9002} and len(gone) <= 4
    best = {}
    for r in rows["language_id"]:
        key = r["text"].translate(LOWER)
        best[key] = max(best.get(key, -1), -1 if r["doc_id"] is None else r["doc_id"])
    assert sorted(-1 if r["doc_id"] is None else r["doc_id"] for r in rows["exact_dedup"]) == sorted(best.values())
    left = sorted(rows["exact_dedup"], key=lambda r: (r["doc_id"] is None, r["doc_id"]))
    prints, parent = [fingerprint(r["text"]) for r in left], list(range(len(left)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(left)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= 2 and find(i) != find(j):
                parent[max(find(i), find(j))] = min(find(i), find(j))
    assert sorted(str(left[i]["doc_id"]) for i in range(len(left)) if find(i) == i) == sorted(str(r["doc_id"]) for r in rows["simhash"])
    words = lambda r: len(re.findall(r"[^\x20\x09-\x0D]+", r["text"]))
    domain = lambda r: f"domain{int(m[1]) % 4 if (m := re.search(r'([0-9]+)$', r['source'] or '')) else 0}"
    supply, leaves = {}, {}
    for r in rows["simhash"]:
        leaf = (domain(r), r["lang"] or "", r["source"] or "")
        supply[leaf] = supply.get(leaf, 0) + words(r)
        leaves.setdefault(leaf, []).append(r)
    given = mixing.budgets(supply, mixing.document_tree()[1], int(sum(supply.values()) * 0.8), 1)
    want = []
    for leaf, group in leaves.items():
        if given[leaf] >= supply[leaf]:
            want += group
            continue
        used = 0
        for r in sorted(group, key=lambda r: hashlib.md5(f"8:0:{'-' + hashlib.md5(r['text'].encode()).hexdigest() if r['doc_id'] is None else r['doc_id']}".encode()).hexdigest()[:15]):
            used += words(r)
            if 2 * used - words(r) <= 2 * given[leaf]:
                want.append(r)
    assert sorted(map(str, want)) == sorted(map(str, rows["mixing"]))
    ranks = bpe.load_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    reference = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    expect = set()
    for r in rows["mixing"]:
        ids = reference.encode_ordinary(r["text"])
        expect.add((r["doc_id"], len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(r["text"].encode()).hexdigest()))
    assert {tuple(r.values()) for r in rows["byte_bpe"]} == expect
    assert {tuple(r) for r in corpus_pipeline.run(spark, str(tmp_path)).collect()} == expect


def test_columns_of_any_name_pass_through(spark, tmp_path):
    """Names that the operators use inside come out of the filtering stages as they went in."""
    extra = {"_id": 1, "_key": "k", "_content": 2, "_stay": 3, "copies": 4, "mix_0": "m", "row": "r", "class": "c"}
    rows = [Row(doc_id=i, text=t, lang="en", source="src1", n_chars=len(t), **extra) for i, t in enumerate(["The of and in the thing", "The of and in the thing", "Reouha the of heble", "Of the other things in this"] * 3)]
    docs = spark.createDataFrame(rows)
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns == list(rows[0].asDict())
        got = docs.collect()
        assert got and all(r.asDict() in [x.asDict() for x in rows] for r in got)


def test_empty_table(spark, tmp_path):
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).collect() == []
