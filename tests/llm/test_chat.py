import hashlib

import pytest
from hypothesis import given
from hypothesis import strategies as st

from ranksort.llm import chat

hostile = st.lists(st.one_of(st.sampled_from([*chat.CONTROLS, "\\", "<", "[", "s>", "/INST]", "é\n"]), st.text(max_size=3)), max_size=8).map("".join)


@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "system", "", "tool", "[END]"]), hostile), max_size=6))
def test_template_is_reversible(turns):
    formatted, mask = chat.render(turns)
    assert chat.parse(formatted) == turns
    assert [chat.unescape(formatted[a:b]) for a, b in mask] == [t for r, t in turns if r == "assistant"]
    assert all(c not in chat.escape(t) for _, t in turns for c in chat.CONTROLS)


def tree(spark, rows):
    return spark.createDataFrame(rows, "tree long, node long, parent long, role string, text string, score double")


def brute(rows):
    """Paths as (tree, leaf) -> (mean score, texts)."""
    by = {(r[0], r[1]): r for r in rows}
    inner = {(r[0], r[2]) for r in rows if (r[0], r[2]) in by}
    out = {}
    for key in by.keys() - inner:
        path, at, seen = [], key, set()
        while at in by and at not in seen:
            seen.add(at)
            path.append(by[at])
            at = (at[0], by[at][2])
        if at not in seen:
            out[key] = (sum(r[5] or 0 for r in path) / len(path), [r[4] or "" for r in path[::-1]])
    return out


def random_trees(t_count=6, seed=3):
    import random

    rng, rows = random.Random(seed), []
    for t in range(t_count):
        for n in range(40):
            rows.append((t, n, rng.randrange(n) if n and rng.random() < 0.95 else None, rng.choice(["user", "assistant"]), f"t{t}n{n}", float(rng.randrange(4))))
    rows += [(7, 1, 2, "user", "a", 0.0), (7, 2, 1, "user", "b", 0.0), (7, 3, 2, "user", "below a cycle", 0.0), (8, 1, 99, None, None, None)]
    return rows + [(9, n, n - 1 if n else None, "user", f"c{n}", None) for n in range(70)]


@pytest.mark.parametrize("whole_tree,max_broadcast", [(10_000, 10), (30, 1_000), (0, 0)])
def test_paths_and_ranks_against_brute_force(spark, whole_tree, max_broadcast):
    rows = random_trees()
    expected, options = brute(rows), dict(score="score", whole_tree=whole_tree, max_broadcast=max_broadcast)
    found = {(r.tree, r.leaf): (r.score, [t.text for t in r.turns]) for r in chat.conversations(tree(spark, rows), **options).collect()}
    assert found.keys() == expected.keys()
    assert all(found[k][1] == expected[k][1] and abs(found[k][0] - expected[k][0]) < 1e-12 for k in found)
    best = chat.conversations(tree(spark, rows), top=2, salts=3, **options).collect()
    for t in {k[0] for k in expected}:
        order = sorted((k for k in expected if k[0] == t), key=lambda k: (-round(expected[k][0], 9), k[1]))[:2]
        assert [(r.tree, r.leaf) for r in sorted((r for r in best if r.tree == t), key=lambda r: r.branch_rank)] == order
    repeated = rows + rows[::3] + [(0, 0, None, "z", "later in order", 0.0)]
    again = {(r.tree, r.leaf): [t.text for t in r.turns] for r in chat.conversations(tree(spark, repeated), **options).collect()}
    assert again == {k: x[1] for k, x in found.items()}


def test_one_shuffle_moves_texts(spark, sf):
    plan = chat._by_tree(*(spark.createDataFrame([], s) for s in ("tree long, node long, role string, text string", "tree long, leaf long, branch_rank int, score double, node long, above long")), True)
    assert plan._jdf.queryExecution().executedPlan().toString().count("Exchange") == 1
    turns = spark.read.parquet(f"{sf}/conversations.parquet")
    links = chat.as_reply_trees(turns).select("tree", "node", "parent")._jdf.queryExecution().optimizedPlan().toString()
    body = chat.as_reply_trees(turns).select("tree", "node", "role", "text")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in body and "Window [lag(node" in links


def test_linear_conversations_read_back(spark):
    rows = [(1, 0, "user", None), (1, 1, "assistant", "</s>[INST] ok"), (1, 1, "assistant", "</s>[INST] ok"), (2, 5, "assistant", "x" * 50_000), (None, 0, None, "y")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    done = {r.tree: r for r in chat.read_back(chat.format_conversations(chat.conversations(chat.as_reply_trees(turns), top=1, keep_repeats=True))).collect()}
    said = "".join(f"{r}\n{t or ''}\n" for _, _, r, t in rows[:3])
    assert done[1].n_turns == 3 and done[1].turns_sha256 == hashlib.sha256(said.encode()).hexdigest()
    assert done[1].loss_chars == 2 * len("</s>[INST] ok") and done[2].loss_chars == 50_000
    assert done[1].formatted_chars == len(done[1].formatted)


def test_defined_cases(spark):
    assert chat.conversations(tree(spark, [])).count() == 0
    twice = chat.conversations(tree(spark, [(1, 1, None, "user", "a", 0.0), (1, 1, None, "user", "b", 1.0), (None, 1, None, "user", "c", 0.0), (1, None, 1, "user", "d", 0.0)])).collect()
    assert [(r.tree, r.leaf, [t.text for t in r.turns]) for r in twice] == [(1, 1, ["a"])]
    extra = tree(spark, [(1, 1, None, "user", "a", 0.0)]).selectExpr("*", "1 as leaf", "2 as turns", "3 as up", "4 as places", "5 as at")
    assert chat.conversations(extra).collect()[0].turns[0].text == "a"
    odd = chat.conversations(extra).selectExpr("*", "1 as made", "2 as formatted", "3 as n_turns", "4 as read", "5 as _read")
    done = chat.read_back(chat.format_conversations(odd))
    assert len(set(done.columns)) == len(done.columns) and done.first().n_turns == 1 and done.first().made == 1


def test_branching_trees_over_the_whole_table(spark, sf):
    """All conversations with replies to random earlier turns and scores: the best branch of each, against brute force."""
    import random

    rng, rows, last, nodes = random.Random(12), [], None, []
    for r in sorted(spark.read.parquet(f"{sf}/conversations.parquet").collect(), key=lambda r: (r.conv_id, r.turn)):
        nodes = [] if r.conv_id != last else nodes
        parent = rng.choice(nodes) if nodes else None
        rows.append((r.conv_id, r.turn, parent, r.role, r.text, float(rng.randrange(5))))
        nodes.append(r.turn)
        last = r.conv_id
    expected = {}
    for (t, leaf), (score, texts) in brute(rows).items():
        if t not in expected or (-score, leaf) < expected[t][:2]:
            expected[t] = (-score, leaf, texts)
    done = chat.read_back(chat.format_conversations(chat.conversations(tree(spark, rows), score="score", top=1))).collect()
    assert {r.tree: (r.leaf, [x.text for x in r.turns]) for r in done} == {t: x[1:] for t, x in expected.items()}
    for r in done:
        said = "".join(f"{x.role}\n{x.text}\n" for x in r.turns)
        assert r.turns_sha256 == hashlib.sha256(said.encode()).hexdigest()
