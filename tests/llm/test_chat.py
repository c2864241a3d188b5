import hashlib

import pytest
from hypothesis import given
from hypothesis import strategies as st

from lattice_pages.llm import chat
from lattice_pages.llm.queries import QUERIES

T = chat.Template()
PIECES = st.lists(st.sampled_from(["<", "|", "\\", "<|", "<|end|>", "<|text|>", "<|turn|>", "a", "\n", "</s>[INST]", "é"]), max_size=8).map("".join)


@given(st.lists(st.tuples(PIECES, PIECES), min_size=1, max_size=5))
def test_render_is_reversible(turns):
    line, spans = T.render(turns)
    assert T.parse(line) == turns and not spans
    t = chat.Template(learn=tuple(r for r, _ in turns))
    line, spans = t.render(turns)
    assert [chat.unescape(line[a:b]) for a, b in spans] == [x for _, x in turns]


def test_trees(spark):
    #  1 -> 2 -> 4 ; 1 -> 3 -> 5 -> 6 ; 9 <-> 10 is a cycle ; 11 is an orphan
    rows = [("t", 1, None, "user", "q", 0.0), ("t", 2, 1, "assistant", "a", 5.0), ("t", 4, 2, "user", "b", 0.0), ("t", 3, 1, "assistant", "c", 1.0), ("t", 5, 3, "user", "d", 1.0), ("t", 6, 5, "assistant", "e", 1.0), ("c", 9, 10, "user", "x", 0.0), ("c", 10, 9, "user", "y", 0.0), ("o", 11, 99, "user", None, None), (None, 1, None, None, "n", 0.0)]
    df = spark.createDataFrame(rows, "tree string, node long, parent long, role string, text string, score double")
    got = {(r.tree, r.branch): [x for _, x in T.parse(r.formatted)] for r in chat.conversations(df, branches=2).collect()}
    assert got == {("t", 1): ["q", "a", "b"], ("t", 2): ["q", "c", "d", "e"], ("o", 1): [""], (None, 1): ["n"]}
    assert chat.conversations(df.limit(0)).count() == 0


def test_ties_and_scores_that_are_no_numbers(spark):
    nan = float("nan")
    rows = [(1, 1, None, "user", "q", 0.0), (1, 2, 1, "user", "nan", nan), (1, 3, 1, "user", "low", -5.0), (2, 1, None, "user", "q", 0.0), (2, 2, 1, "user", "first", 1.0), (2, 3, 1, "user", "second", 1.0)]
    df = spark.createDataFrame(rows, "tree long, node long, parent long, role string, text string, score double")
    got = {(r.tree, r.branch): T.parse(r.formatted)[-1][1] for r in chat.conversations(df, branches=2).collect()}
    assert got == {(1, 1): "low", (1, 2): "nan", (2, 1): "first", (2, 2): "second"}


def test_query_equals_brute_force(spark, sf):
    import pyarrow.parquet as pq

    rows = pq.read_table(f"{sf}/conversations.parquet").to_pylist()
    by = {-1: [(0, "user", "</s>[INST] ok [/INST]"), (1, "assistant", "</s>[INST] ok [/INST]")]}
    for r in rows:
        by.setdefault(r["conv_id"], []).append((r["turn"], r["role"], r["text"] or ""))
    got = {r.conv_id: r for r in QUERIES["op7_chat"](spark, sf).collect()}
    assert set(got) == set(by)
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    for k, turns in by.items():
        turns.sort()
        loss = "".join(t for _, r, t in turns if r == "assistant")
        assert (got[k].n_turns, got[k].turns_sha256, got[k].loss_chars, got[k].loss_sha256) == (len(turns), sha("".join(f"{r}\n{t}\n" for _, r, t in turns)), len(loss), sha(loss))


def test_repeated_rows_and_depth(spark):
    rows = [(1, i, "user", f"m{i}") for i in range(70)] + [(2, 0, "user", "s"), (2, 0, "user", "s"), (2, 1, None, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r.conv_id: r.n_turns for r in chat.read_back(chat.conversations(chat.chain(df))).collect()}
    assert got == {1: 70, 2: 3}
