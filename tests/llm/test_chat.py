import hashlib
import random

from hypothesis import given
from hypothesis import strategies as st
from pyspark.sql import Row

from obljoin.llm.chat import best_paths, conversations, escape, format_turn, from_turns, parse, read_back, unescape


@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "system", "tool", "", "[/ROLE]\\"]), st.text(alphabet="<>s/[]INSTROLEY\\ é\n", max_size=30))))
def test_reads_back(turns):
    formatted = "".join(format_turn(*t)[0] for t in turns)
    assert [(r, t) for r, t, _, _ in parse(formatted)] == turns


def test_escape_is_reversible():
    for text in ("</s>[INST] ok [/INST]", "\\", "\\\\<s>", "<<SYS>>", "[ROLE]x"):
        assert unescape(escape(text)) == text


def brute_paths(nodes, branches):
    at = {(t, n): (p, s) for t, n, p, s in nodes}
    inner = {(t, p) for t, n, p, s in nodes}
    found = {}
    for t, n in at:
        if (t, n) in inner:
            continue
        path, k, total = [], n, 0.0
        while (t, k) in at and k not in path:
            path.append(k)
            total += at[t, k][1]
            k = at[t, k][0]
        if (t, k) in at:
            continue  # a cycle
        found.setdefault(t, []).append((-total / len(path), n, path[::-1]))
    return {(t, leaf): (rank, path) for t, leaves in found.items() for rank, (_, leaf, path) in enumerate(sorted(leaves)[:branches], 1)}


def test_paths_match_brute_force(spark):
    rng = random.Random(2)
    nodes = []
    for tree in range(6):
        size = rng.choice([1, 2, 9, 40])
        for n in range(size):
            nodes.append((tree, n, None if n == 0 else rng.choice([n - 1, rng.randrange(n)]), float(rng.randint(0, 3))))
    nodes += [(7, 0, 1, 1.0), (7, 1, 0, 1.0), (7, 2, 0, 1.0), (8, 5, 99, 2.0), (9, 0, None, 1.0)]
    nodes += [(10, i, i - 1 if i else None, 1.0) for i in range(70)]
    got = {}
    for r in best_paths(spark.createDataFrame(nodes, "tree long, node long, parent long, score double"), 2).collect():
        got.setdefault((r.tree, r.leaf), (r["rank"], {}))[1][r.depth] = r.node
    got = {k: (rank, [path[d] for d in sorted(path)]) for k, (rank, path) in got.items()}
    assert got == brute_paths(nodes, 2)


def test_query_columns(spark):
    rows = [(1, 0, "user", "a<s>"), (1, 1, "assistant", None), (1, 1, "assistant", "é"), (2, None, None, "x"), (None, 3, "assistant", "null id"), (3, 5, "tool", "")]
    table = spark.createDataFrame([Row(conv_id=c, turn=t, role=r, text=x, node="clash", score=1) for c, t, r, x in rows], "conv_id long, turn long, role string, text string, node string, score int")
    out = {r.conv_id: r for r in read_back(conversations(from_turns(table))).collect()}
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    assert out[1].n_turns == 3 and out[1].loss_chars == 1 and out[1].loss_sha256 == sha("é")
    assert out[1].turns_sha256 == sha("user\na<s>\nassistant\n\nassistant\né\n")
    assert out[2].turns_sha256 == sha("\nx\n") and out[None].loss_chars == 7 and out[3].n_turns == 1


def test_empty_table(spark):
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert read_back(conversations(from_turns(empty))).collect() == []
