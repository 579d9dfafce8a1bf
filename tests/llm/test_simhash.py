import random
import re

import xxhash
from pyspark.sql import Row

from obljoin.llm.simhash import as_hex, links, simhash_groups


def brute_fingerprint(text, width=3):
    lowered = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", lowered)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(fps):
    nodes = sorted(fps)
    parent = {x: x for x in nodes}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, x in enumerate(nodes):
        for y in nodes[:i]:
            if (x ^ y).bit_count() <= 2:
                parent[find(x)] = find(y)
    return {x: find(x) for x in nodes}


def check(spark, texts):
    docs = spark.createDataFrame([Row(doc_id=i, text=t, fp="clash", row=1) for i, t in texts], "doc_id long, text string, fp string, row int")
    rows = simhash_groups(docs).select("doc_id", as_hex("fp").alias("f"), "component_id", "keep").collect()
    fps = {i: brute_fingerprint(t) for i, t in texts}
    roots = brute_components(set(fps.values()))
    first = {}
    for i, f in fps.items():
        first[roots[f]] = min(first.get(roots[f], i), i)
    assert {r.doc_id: (r.f, r.component_id) for r in rows} == {i: (f"{f:016x}", first[roots[f]]) for i, f in fps.items()}
    assert sum(r.keep for r in rows) == len(first)


def test_matches_brute_force(spark):
    rng = random.Random(3)
    words = ["".join(rng.choice("abcdeé") for _ in range(rng.randint(1, 6))) for _ in range(200)]
    base = [" ".join(rng.choice(words) for _ in range(300)) for _ in range(6)]
    texts = [None, "", " \n", "one", "Two words", "Two\x0bwords", "É É", "x" * 50_000]
    for t in base:
        texts.append(t)
        for _ in range(25):
            w = t.split(" ")
            w[rng.randrange(len(w))] = rng.choice(words)
            texts.append("  ".join(w))
    texts += [base[0]] * 5
    check(spark, list(enumerate(texts, 10)))


def test_empty_table(spark):
    assert simhash_groups(spark.createDataFrame([], "doc_id long, text string")).collect() == []


def test_crowded_cells_lose_no_link(spark):
    rng = random.Random(5)
    fps = set()
    for _ in range(4):
        centre = rng.getrandbits(64)
        fps |= {centre ^ sum(1 << b for b in rng.sample(range(64), rng.randint(0, 3))) for _ in range(60)}
    signed = {f - (1 << 64) if f >> 63 else f: f for f in fps}
    found = links(spark.createDataFrame([(s,) for s in signed], "fp long"), cell_most=4).collect()
    assert all((signed[r.a] ^ signed[r.b]).bit_count() <= 2 for r in found)
    parent = {f: f for f in fps}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for r in found:
        parent[find(signed[r.a])] = find(signed[r.b])
    want = brute_components(fps)
    groups = lambda of: sorted(sorted(x for x in fps if of(x) == g) for g in {of(x) for x in fps})
    assert groups(find) == groups(want.get)
