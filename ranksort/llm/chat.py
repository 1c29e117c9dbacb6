"""Reply trees: root-to-leaf paths by iterative self-joins, branches ranked by score, one conversation a path.

Ancestors are found by doubling: the jump table of round k holds each message's 2^k-th ancestor, and
the sum and number of the scores on the way to it; it is the self-join of the table before, so a chain
of d messages takes log2 d rounds.  The last table has every path's score, one row a message; only
the branches that are chosen are then expanded into (leaf, ancestor) pairs.  Rounds see ids alone.
Texts move once, by tree; those of trees with over ``whole_tree`` messages once by message and once
more by path, so no task gets such a tree alone.

Template: each turn opens with a mark and closes with one (``MARKS``).  Inside texts a control
string gets a backslash after its first character, and one that has k backslashes there gets k + 1;
unescaping takes one away.  No text can then hold a mark, and the map is one-to-one.

Defined results: a null text or role is empty; a message whose parent is null or not in its tree is
a root; messages that hang below a cycle have no root and are left out; equal scores rank by leaf
id; rows that repeat an id within a tree are one message, with the smallest parent, the highest score
and the smallest (role, text) of them, or with ``keep_repeats`` one after the other; rows without a
tree or an id are left out; extra columns are ignored; no rows give no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import materialize, release, unused

# The opening and closing mark of each role; any other role is written out in its mark.
MARKS = {"user": ("[INST]", "[/INST]"), "assistant": ("[ASST]", "</s>"), "system": ("[SYS]", "[/SYS]")}
OTHER = ("[ROLE]", "[/ROLE]")
BEGIN, OTHER_END = "<s>", "[END]"
CONTROLS = [BEGIN, OTHER_END, *OTHER, *(m for pair in MARKS.values() for m in pair)]

_PLAIN = re.compile("|".join(rf"{re.escape(c[0])}\\*{re.escape(c[1:])}" for c in CONTROLS))
_ESCAPED = re.compile("|".join(rf"{re.escape(c[0])}\\+{re.escape(c[1:])}" for c in CONTROLS))
_ANY_MARK = re.compile("|".join(re.escape(c) for c in sorted(CONTROLS, key=len, reverse=True)))


def escape(text: str) -> str:
    return _PLAIN.sub(lambda m: f"{m[0][0]}\\{m[0][1:]}", text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(lambda m: m[0][0] + m[0][2:], text)


def render(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The conversation's string and the loss mask: spans of the assistant's texts, in code points."""
    parts, at, mask = [BEGIN], len(BEGIN), []
    for role, text in turns:
        body = escape(text)
        start, end = MARKS.get(role) or (f"{OTHER[0]}{escape(role)}{OTHER[1]}", OTHER_END)
        at += len(start)
        if role == "assistant":
            mask.append((at, at + len(body)))
        at += len(body) + len(end)
        parts += (start, body, end)
    return "".join(parts), mask


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns of a string that ``render`` made."""
    marks, turns, i = list(_ANY_MARK.finditer(formatted)), [], 1
    opened = {start: role for role, (start, _) in MARKS.items()}
    while i < len(marks):
        first = marks[i]
        if first[0] == OTHER[0]:
            role, i = unescape(formatted[first.end() : marks[i + 1].start()]), i + 1
        else:
            role = opened[first[0]]
        turns.append((role, unescape(formatted[marks[i].end() : marks[i + 1].start()])))
        i += 2
    return turns


def _jumps(links: DataFrame) -> tuple[list[DataFrame], DataFrame, int]:
    """Jump tables (tree, node, up, total, steps) of 1, 2, 4, ... steps, ``up`` null beyond the root, the last one, and how many messages there are.

    total and steps: the sum and the number of the scores from the message up to where the jump ends.
    """
    present = links.select("tree", F.col("node").alias("parent"), F.lit(True).alias("known"))
    first = links.join(present, ["tree", "parent"], "left").select("tree", "node", F.when(F.col("known"), F.col("parent")).alias("up"), F.col("points").alias("total"), F.lit(1).cast("long").alias("steps"))
    largest, n = links.groupBy("tree").count().agg(F.max("count"), F.sum("count")).first()
    largest, n = largest or 0, n or 0
    jump, tables, step = materialize(first, "chat-jump", n), [], 1
    while jump.where("up is not null").limit(1).count() and step < 2 * largest:
        tables.append(jump)
        onward = jump.select("tree", F.col("node").alias("up"), F.col("up").alias("top"), F.col("total").alias("more"), F.col("steps").alias("further"))
        doubled = jump.where("up is not null").join(onward, ["tree", "up"]).select("tree", "node", F.col("top").alias("up"), (F.col("total") + F.col("more")).alias("total"), (F.col("steps") + F.col("further")).alias("steps"))
        jump = materialize(jump.where("up is null").unionByName(doubled), "chat-jump", n)
        step *= 2
    return tables, jump, n


def _best(scored: DataFrame, top: int, salts: int) -> DataFrame:
    """The ``top`` leaves of each tree: first within salted parts, then among the parts' best."""
    order = [F.desc("score"), F.asc("leaf")]
    part = Window.partitionBy("tree", F.pmod(F.xxhash64("leaf"), F.lit(salts))).orderBy(*order)
    best = scored.withColumn("branch_rank", F.row_number().over(part)).where(F.col("branch_rank") <= top)
    return best.withColumn("branch_rank", F.row_number().over(Window.partitionBy("tree").orderBy(*order))).where(F.col("branch_rank") <= top)


def paths(links: DataFrame, *, top: int | None = None, salts: int = 64) -> DataFrame:
    """(tree, leaf, branch_rank, score, node, above): the chosen leaves with each message on the way up, ``above`` = steps from the leaf.

    links: (tree, node, parent, points), one row a message.  A path's score is the mean of its messages'.
    The rank is 1 for all without ``top``.
    """
    tables, ends, n = _jumps(links)
    whole = ends.where("up is null")  # the others lead into a cycle
    inner = tables[0].where("up is not null").select("tree", F.col("up").alias("node")).distinct() if tables else None
    leaves = whole.join(inner, ["tree", "node"], "left_anti") if tables else whole
    scored = leaves.select("tree", F.col("node").alias("leaf"), (F.col("total") / F.col("steps")).alias("score"))
    chosen = scored.withColumn("branch_rank", F.lit(1)) if top is None else _best(scored, top, salts)
    columns = ["tree", "leaf", "branch_rank", "score"]
    found = materialize(chosen.select(*columns, F.col("leaf").alias("node"), F.lit(0).cast("long").alias("above")), "chat-paths", n)
    for k, jump in enumerate(tables):
        up = jump.where("up is not null").select("tree", "node", "up")
        further = found.join(up, ["tree", "node"]).select(*columns, F.col("up").alias("node"), (F.col("above") + (1 << k)).alias("above"))
        before, found = found, materialize(found.unionByName(further), "chat-paths", n)
        release(before, jump)
    release(ends)
    return found


def conversations(
    messages: DataFrame, *, tree: str = "tree", node: str = "node", parent: str = "parent", role: str = "role", text: str = "text",
    score: str | None = None, top: int | None = None, salts: int = 64, keep_repeats: bool = False, whole_tree: int = 10_000, max_broadcast: int = 1_000_000,
) -> DataFrame:
    """One row a path: tree, leaf, branch_rank (within the best ``top``; 1 for all without ``top``), score, turns.

    A path's score is the mean of its messages' scores (null or no column: 0).  The list of large trees is
    broadcast while it has at most ``max_broadcast`` rows (counted).
    """
    named = messages.where(F.col(tree).isNotNull() & F.col(node).isNotNull())
    points = F.coalesce(F.col(score).cast("double"), F.lit(0.0)) if score else F.lit(0.0)
    rows = named.select(F.col(tree).alias("tree"), F.col(node).alias("node"), F.col(parent).alias("parent"), points.alias("points"))
    links = materialize(rows.groupBy("tree", "node").agg(F.min("parent").alias("parent"), F.max("points").alias("points"), F.count("*").alias("rows")), "chat-links")
    way = paths(links, top=top, salts=salts)
    body = named.select(F.col(tree).alias("tree"), F.col(node).alias("node"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    large = links.groupBy("tree").agg(F.sum("rows").alias("rows")).where(F.col("rows") > whole_tree).select("tree")
    n_large = large.limit(max_broadcast + 1).count()
    if not n_large:
        release(links)
        return _by_tree(body, way, keep_repeats)
    apart = F.broadcast(large) if n_large <= max_broadcast else large
    small = _by_tree(body.join(apart, "tree", "left_anti"), way.join(apart, "tree", "left_anti"), keep_repeats)
    return small.unionByName(_by_message(body.join(apart, "tree", "left_semi"), way.join(apart, "tree", "left_semi"), keep_repeats))


_PATH = ["tree", "leaf", "branch_rank", "score"]


def _turns(met: DataFrame) -> DataFrame:
    turn = F.struct((-F.col("above")).alias("place"), "role", "text")
    return met.groupBy(*_PATH).agg(F.sort_array(F.collect_list(turn)).alias("turns"))


def _by_tree(body: DataFrame, way: DataFrame, keep_repeats: bool) -> DataFrame:
    """Texts and places go to their tree together: one shuffle, whose partitions serve the window and the aggregate."""
    place = F.struct("leaf", "branch_rank", "score", "above")
    places = way.select("tree", "node", place.alias("at"), F.lit(None).cast("string").alias("role"), F.lit(None).cast("string").alias("text"))
    both = body.select("tree", "node", F.lit(None).cast(places.schema["at"].dataType).alias("at"), "role", "text").unionByName(places).repartition("tree")
    same = Window.partitionBy("tree", "node")
    met = both.withColumn("places", F.collect_list("at").over(same))
    if not keep_repeats:
        met = met.withColumn("turn", F.row_number().over(same.orderBy(F.col("text").isNull(), "role", "text"))).where("turn = 1")
    met = met.where("text is not null").select("tree", "role", "text", F.explode("places").alias("at"))
    return _turns(met.select("tree", "at.*", "role", "text"))


def _by_message(body: DataFrame, way: DataFrame, keep_repeats: bool) -> DataFrame:
    """Texts meet their places message by message, then path by path."""
    said = body if keep_repeats else body.groupBy("tree", "node").agg(F.min(F.struct("role", "text")).alias("said")).select("tree", "node", "said.role", "said.text")
    return _turns(way.join(said, ["tree", "node"]))


def _render(turns: Iterator[pa.Array]) -> Iterator[pa.Array]:
    kind = pa.struct([("formatted", pa.string()), ("loss", pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))])
    for batch in turns:
        out = []
        for talk in batch:
            formatted, mask = render([(t["role"], t["text"]) for t in talk.as_py() or []])
            out.append({"formatted": formatted, "loss": [{"start": a, "end": b} for a, b in mask]})
        yield pa.array(out, kind)


def _digest(formatted: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
    kind = pa.struct([("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])
    for texts, masks in formatted:
        out = []
        for text, mask in zip(texts.to_pylist(), masks.to_pylist()):
            turns = parse(text)
            loss = "".join(unescape(text[m["start"] : m["end"]]) for m in mask)
            digest = hashlib.sha256("".join(f"{role}\n{said}\n" for role, said in turns).encode()).hexdigest()
            out.append({"n_turns": len(turns), "turns_sha256": digest, "loss_chars": len(loss), "loss_sha256": hashlib.sha256(loss.encode()).hexdigest(), "formatted_chars": len(text)})
        yield pa.array(out, kind)


def format_conversations(chosen: DataFrame) -> DataFrame:
    """Adds ``formatted`` and ``loss`` (spans of the assistant's texts in it) to rows that have ``turns``; columns of these names are replaced."""
    made = unused(chosen.columns, "made")
    done = chosen.withColumn(made, F.arrow_udf(_render, "struct<formatted:string,loss:array<struct<start:int,end:int>>>")("turns"))
    return done.select(*(c for c in chosen.columns if c not in ("formatted", "loss")), f"{made}.formatted", f"{made}.loss")


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the formatted strings say, parsed from them alone; columns of the digests' names are replaced."""
    digests = "n_turns:long,turns_sha256:string,loss_chars:long,loss_sha256:string,formatted_chars:long"
    read, names = unused(formatted.columns, "read"), [d.partition(":")[0] for d in digests.split(",")]
    done = formatted.withColumn(read, F.arrow_udf(_digest, f"struct<{digests}>")("formatted", "loss"))
    return done.select(*(c for c in formatted.columns if c not in names), f"{read}.*")


def as_reply_trees(turns: DataFrame, *, conversation: str = "conv_id", order: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Linear conversations as reply trees: each row answers the one before it (ties by role, then the text's SHA-256).

    A row's id is a hash of its place, role and text, so that it is known where the text is; rows that
    repeat share it, which ``keep_repeats`` is for.  Texts take no part in the ordering.
    """
    rows = turns.select(F.col(conversation).alias("tree"), F.col(order).alias("place"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    rows = rows.withColumns({"node": F.xxhash64("place", "role", "text"), "digest": F.unhex(F.sha2("text", 256))})
    before = Window.partitionBy("tree").orderBy(F.col("place").asc_nulls_first(), "role", "digest", "node")
    answered = F.lag("node").over(before)
    fresh = F.when(answered != F.col("node"), answered)  # a repeat answers nothing; the first of its kind has the parent
    return rows.withColumn("parent", fresh).select("tree", "node", "parent", "role", "text")
