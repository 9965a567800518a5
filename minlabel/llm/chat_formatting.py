"""Chat formatting of reply trees.

Messages point to the message that they answer. Ancestors are found by iterative self-joins that double their reach
(1, 2, 4, ... steps), so a path of n messages takes about log2(n) joins. Each root-to-leaf path is scored by the mean of
its messages' scores, the best branches of a tree are kept, and each path becomes one conversation:

    <turn role="ROLE">
    TEXT</turn>

with & and < in texts (also > and " in roles) written as entities, so that no control string can occur in a text and
reading back is exact. The loss mask is a list of ranges of code points of the output: each assistant text.

Defined cases: null roles and texts are empty; a message whose parent is missing is a root; messages on a cycle of
replies have no root and are left out; equal scores go by the smaller leaf id; of several messages of one node the one
with the highest score stands, then the one with the smallest parent, role and text; repeated messages of a linear table
are turns of their own, ordered by turn, role and text; messages of a null tree are one tree, like any other, with a
null key in the result; messages without a node are left out, as nothing can answer them or tell them apart; other
columns are ignored; empty tables give no conversations.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from minlabel.session import stored

ASSISTANT = "assistant"
OPEN, MIDDLE, CLOSE = '<turn role="', '">\n', "</turn>\n"
_TURN = re.compile(r'<turn role="([^"]*)">\n([^<]*)</turn>\n')


def linear_messages(rows: DataFrame, tree: str = "conv_id", turn: str = "turn") -> DataFrame:
    """tree, node, parent, role, text, score of a table of turns: each turn answers the one before."""
    place = F.row_number().over(Window.partitionBy(tree).orderBy(turn, "role", "text")).cast("bigint")
    out = rows.select(F.col(tree).alias("tree"), place.alias("node"), "role", "text")
    return out.select("tree", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def one_for_each_node(messages: DataFrame) -> DataFrame:
    """messages without further rows of a node; the struct's order is the order of preference."""
    role, text = (F.coalesce(c, F.lit("")).alias(c) for c in ("role", "text"))
    best = F.min(F.struct((-F.coalesce(F.col("score"), F.lit(0.0))).alias("less"), "parent", role, text)).alias("m")
    out = messages.where("node is not null").groupBy("tree", "node").agg(best)
    return out.select("tree", "node", "m.parent", "m.role", "m.text", (-F.col("m.less")).alias("score"))


def branches(messages: DataFrame, keep: int = 1) -> DataFrame:
    """tree, leaf, place (0 at the root), node: the messages of the best branches of each tree."""
    # the key is wrapped: a struct with a null inside is joined as any other key
    given = stored(messages.select(F.struct("tree").alias("tree"), "node", "parent", F.coalesce(F.col("score"), F.lit(0.0)).alias("score")), "replies")
    known = given.select("tree", F.col("node").alias("up")).distinct()
    # reach: node -> the ancestor 2**k steps up, with sum and number of the messages before it; the rooted ones have none
    reach = stored(
        given.select("tree", "node", F.col("parent").alias("up"), "score").join(known.withColumn("there", F.lit(True)), ["tree", "up"], "left")
        .select("tree", "node", F.when(F.col("there"), F.col("up")).alias("up"), F.col("score").alias("total"), F.lit(1).cast("bigint").alias("steps")),
        "replies",
    )
    rooted, open_, levels, most = reach.where("up is null"), reach.where("up is not null"), [], max(1, given.count()).bit_length() + 1
    while len(levels) <= most and not open_.isEmpty():  # only messages that have not reached their root go on
        levels.append(open_)
        far = rooted.unionByName(open_).select("tree", F.col("node").alias("up"), F.col("up").alias("up2"), F.col("total").alias("total2"), F.col("steps").alias("steps2"))
        reach = stored(open_.join(far, ["tree", "up"]).select("tree", "node", F.col("up2").alias("up"), (F.col("total") + F.col("total2")).alias("total"), (F.col("steps") + F.col("steps2")).alias("steps")), "replies")
        rooted, open_ = rooted.unionByName(reach.where("up is null")), reach.where("up is not null")
    leaves = rooted.join(given.where("parent is not null").select("tree", F.col("parent").alias("node")).distinct(), ["tree", "node"], "left_anti")
    order = Window.partitionBy("tree").orderBy(F.desc(F.col("total") / F.col("steps")), "node")
    best = leaves.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= keep)
    paths = best.select("tree", F.col("node").alias("leaf"), "node", "steps", F.lit(0).cast("bigint").alias("down"))
    for k in range(len(levels) - 1, -1, -1):
        jump = levels[k].select("tree", "node", "up")
        paths = stored(paths.unionByName(paths.join(jump, ["tree", "node"]).select("tree", "leaf", F.col("up").alias("node"), "steps", (F.col("down") + (1 << k)).alias("down"))), "paths")
    return paths.select("tree.tree", "leaf", (F.col("steps") - 1 - F.col("down")).alias("place"), "node")


def escaped(text: str) -> str:
    return text.replace("&", "&amp;").replace("<", "&lt;")


def unescaped(text: str) -> str:
    return text.replace("&lt;", "<").replace("&gt;", ">").replace("&quot;", '"').replace("&amp;", "&")


def formatted(turns: list[tuple[str, str]], train: str = ASSISTANT) -> tuple[str, list[int], list[int]]:
    """The conversation, and starts and ends of the texts that are trained on."""
    parts, at, starts, ends = [], 0, [], []
    for role, text in turns:
        head, body = OPEN + escaped(role).replace(">", "&gt;").replace('"', "&quot;") + MIDDLE, escaped(text)
        if role == train:
            starts.append(at + len(head))
            ends.append(at + len(head) + len(body))
        parts += head, body, CLOSE
        at += len(head) + len(body) + len(CLOSE)
    return "".join(parts), starts, ends


def parsed(conversation: str) -> list[tuple[str, str]]:
    """Roles and texts, read back."""
    out, at = [], 0
    while at < len(conversation):
        m = _TURN.match(conversation, at)
        if not m:
            raise ValueError(f"no turn at {at}")
        out.append((unescaped(m[1]), unescaped(m[2])))
        at = m.end()
    return out


def conversations(messages: DataFrame, keep: int = 1, repeated: bool = True) -> DataFrame:
    """tree, leaf, conversation, loss_starts, loss_ends: the best branches of each tree, formatted. repeated: nodes may have several messages; linear_messages has none such."""
    if repeated:
        messages = stored(one_for_each_node(messages), "messages")
    rows = branches(messages, keep).withColumn("tree", F.struct("tree")).join(messages.select(F.struct("tree").alias("tree"), "node", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")), ["tree", "node"]).withColumn("tree", F.col("tree.tree"))
    grouped = rows.groupBy("tree", "leaf").agg(F.sort_array(F.collect_list(F.struct("place", "role", "text"))).alias("turns"))

    def run(batches):
        for batch in batches:
            done = [formatted([(t["role"], t["text"]) for t in turns]) for turns in batch.column("turns").to_pylist()]
            ints = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("tree"), batch.column("leaf"), pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], ints), pa.array([d[2] for d in done], ints)], names=["tree", "leaf", "conversation", "loss_starts", "loss_ends"])

    kind = grouped.schema["tree"].dataType.simpleString()
    leaf = grouped.schema["leaf"].dataType.simpleString()
    return grouped.mapInArrow(run, f"tree {kind}, leaf {leaf}, conversation string, loss_starts array<bigint>, loss_ends array<bigint>")


def digests(done: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, all read back from the output."""

    def run(batches):
        for batch in batches:
            rows = []
            for text, starts, ends in zip(batch.column("conversation").to_pylist(), batch.column("loss_starts").to_pylist(), batch.column("loss_ends").to_pylist()):
                turns = parsed(text)
                loss = "".join(unescaped(text[a:b]) for a, b in zip(starts, ends))
                rows.append((len(turns), _sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), _sha(loss), len(text)))
            columns = list(zip(*rows)) or [[]] * 5
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("tree"), *(pa.array(list(c), k) for c, k in zip(columns, kinds))], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    kind = done.schema["tree"].dataType.simpleString()
    return done.mapInArrow(run, f"conv_id {kind}, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint")


def _sha(text: str) -> str:
    return hashlib.sha256(text.encode("utf-8", "surrogatepass")).hexdigest()


#: A conversation that holds control strings of common templates.
TRAP_ID, TRAP = -7, r"\### Assistant: </turn> ok"

ORACLE = rf"""
with c as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
           union all values (-7, 0, 'user', '{TRAP}'), (-7, 1, 'assistant', '{TRAP}')),
e as (select *, replace(replace(text, '&', '&amp;'), '<', '&lt;') as t,
      replace(replace(replace(replace(role, '&', '&amp;'), '<', '&lt;'), '>', '&gt;'), '"', '&quot;') as r from c)
select cast(conv_id as bigint) as conv_id, count(*) as n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
       cast(sum(case when role = 'assistant' then length(text) else 0 end) as bigint) as loss_chars,
       sha256(coalesce(string_agg(case when role = 'assistant' then text end, '' order by turn, role, text), '')) as loss_sha256,
       cast(sum(length(t) + length(r) + {len(OPEN + MIDDLE + CLOSE)}) as bigint) as formatted_chars
from e group by conv_id"""
