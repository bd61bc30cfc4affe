"""Chat formatting on a prefix tree of conversations.

Conversations that begin with the same turns share the nodes of those turns.  A node's id is a chained digest of the turns up
to it, so equal prefixes meet without any join; its path, the ids at which the way from the root branches, sorts the nodes depth
first (then by depth).  Each node is emitted once in that order, as token ids with the position of its first token (tokens of its ancestors), its own
interval in the packed sequence, the intervals of its ancestors (what its tokens may attend to, beside the causal part of
its own interval), and the interval under the loss mask.

A popular first turn makes a large tree, never a large task: the nodes are dealt by ranges of their paths, and ranges cut
through trees.

Template of a turn: ``<|im_start|>`` role line feed text ``<|im_end|>`` line feed.  Inside texts, ``<``, then k backslashes, then
``|`` gets one backslash more, so ``<|`` never stands in a text; roles also escape line feeds.  Both are undone on reading.

Defined cases: null roles and texts are empty; turns of a conversation are ordered by (turn, role, text), null turns first;
conversations with a null id form one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sharetree.llm.storage import materialize

# Fixed values of the template.
START, END = "<|im_start|>", "<|im_end|>"
LOSS_ROLE = "assistant"
NODES = "part int, in_part long, node binary, parent binary, depth int, n_tokens long, loss_from long, loss_to long, tokens array<int>"
SPANS = "node binary, position long, ancestors array<struct<start:long,stop:long>>"
DIGESTS = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def escape(text: str) -> str:
    return re.sub(r"<(\\*)\|", r"<\1\\|", text)


def unescape(text: str) -> str:
    return re.sub(r"<\\(\\*)\|", r"<\1|", text)


def escape_role(role: str) -> str:
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(role: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


def format_turn(role: str, text: str) -> tuple[str, str, str]:
    """What stands before the text, the escaped text, and what follows."""
    return f"{START}{escape_role(role)}\n", escape(text), f"{END}\n"


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns of a formatted conversation."""
    turns, at = [], 0
    while at < len(formatted):
        if not formatted.startswith(START, at):
            raise ValueError("a turn doesn't begin with its mark")
        line = formatted.index("\n", at)
        end = formatted.index(END + "\n", line)
        turns.append((unescape_role(formatted[at + len(START) : line]), unescape(formatted[line + 1 : end])))
        at = end + len(END) + 1
    return turns


def _chained(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["conv_id", "turn_no", "node", "parent", "role", "text"]
    kinds = [pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.string(), pa.string()]
    for batch in batches:
        rows: list[tuple] = []
        for conv_id, turns in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            node = b""
            for i, turn in enumerate(turns):
                role, text = turn["role"].encode(), turn["text"].encode()
                parent, node = node, hashlib.blake2b(node + len(role).to_bytes(8, "little") + role + text, digest_size=16).digest()
                rows.append((conv_id, i, node, parent, turn["role"], turn["text"]))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)


def turns_of(conversations: DataFrame) -> DataFrame:
    """A row for each turn of each conversation, with its node of the tree."""
    turn = F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    grouped = conversations.groupBy(F.col("conv_id").cast("long").alias("conv_id")).agg(F.sort_array(F.collect_list(turn)).alias("turns"))
    return grouped.mapInArrow(_chained, "conv_id long, turn_no int, node binary, parent binary, role string, text string")


def _emit(tokenizer: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sharetree.llm.token_store import encoder

        encode, part, at = encoder(tokenizer), TaskContext.get().partitionId(), 0
        kinds = [pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32())]
        names = [c.split()[0] for c in NODES.split(", ")]
        for batch in batches:
            rows = []
            nodes, parents, depths, roles, texts = (c.to_pylist() for c in batch.columns)
            pieces = [format_turn(r, t) for r, t in zip(roles, texts)]
            heads, bodies, tails = (encode([p[i] for p in pieces]) for i in range(3))
            for node, parent, depth, role, head, body, tail in zip(nodes, parents, depths, roles, heads, bodies, tails):
                ids, a = [*head.tolist(), *body.tolist(), *tail.tolist()], len(head)
                b = a + len(body) if role == LOSS_ROLE else a
                rows.append((part, at, node, parent, depth, len(ids), a, b, ids))
                at += len(ids)
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    return run


def _branches(turns: DataFrame) -> DataFrame:
    """The turns with ``path``: the nodes of the conversation, up to the turn, that have siblings (or are roots)."""
    later = turns.where("turn_no > 0")
    forks = later.groupBy("parent").agg(F.min("node").alias("a"), F.max("node").alias("b")).where("a <> b").select(F.col("parent").alias("fork"))
    marked = later.join(forks, F.col("parent") == F.col("fork"), "left").withColumn("entry", F.when(F.col("fork").isNotNull(), F.col("node"))).drop("fork")
    marked = marked.unionByName(turns.where("turn_no = 0").withColumn("entry", F.col("node")))
    way = Window.partitionBy("conv_id").orderBy("turn_no").rowsBetween(Window.unboundedPreceding, 0)
    return marked.withColumn("path", F.collect_list("entry").over(way)).drop("entry")


def prefix_tree(turns: DataFrame, tokenizer: str) -> DataFrame:
    """The nodes in depth-first order, written and read back: ``start`` is a node's place in the packed sequence."""
    nodes = _branches(turns).groupBy("node").agg(F.first("parent").alias("parent"), F.first("path").alias("path"), (F.first("turn_no") + 1).alias("depth"), F.first("role").alias("role"), F.first("text").alias("text"))
    ordered = nodes.repartitionByRange("path", "depth").sortWithinPartitions("path", "depth").select("node", "parent", "depth", "role", "text")
    stored = materialize(ordered.mapInArrow(_emit(tokenizer), NODES), "chat-nodes")
    totals = stored.groupBy("part").agg(F.sum("n_tokens").alias("tokens"))  # a row a part
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("part", F.coalesce(F.sum("tokens").over(before), F.lit(0)).alias("base"))
    return stored.join(bases, "part").withColumn("start", F.col("base") + F.col("in_part")).drop("base")


def _attend(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Along each part, depth first, the stack of ancestors; rows with ``carried`` set only fill it at the part's start."""
    span = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))
    part, stack = None, []  # (end of the node, tokens up to it, merged intervals up to it)
    for batch in batches:
        out: list[tuple] = []
        for p, carried, depth, node, start, n in zip(*(c.to_pylist() for c in batch.columns)):
            if p != part:
                part, stack = p, []
            del stack[depth - 1 :]
            stop, position, spans = stack[-1] if stack else (None, 0, ())
            if not carried:
                out.append((node, position, [{"start": a, "stop": b} for a, b in spans]))
            # what follows its parent directly lengthens the parent's interval
            spans = (*spans[:-1], (spans[-1][0], start + n)) if spans and stop == start else (*spans, (start, start + n))
            stack.append((start + n, position + n, spans))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate((pa.binary(), pa.int64(), span))], names=["node", "position", "ancestors"])


def attention(tree: DataFrame, turns: DataFrame) -> DataFrame:
    """position (of the node's first token) and the merged intervals of the ancestors, nearest last, of every node."""
    # what a part's first node has above it lies in earlier parts, and is what a conversation that has the node begins with
    rows = tree.select("part", F.lit(False).alias("carried"), "depth", "node", "start", "n_tokens")
    heads = tree.where("in_part = 0 and depth > 1").select("part", "node")
    of = turns.join(heads, "node").groupBy("part").agg(F.min(F.struct("conv_id", "turn_no")).alias("at"))
    of = of.select("part", F.col("at.conv_id").alias("in_conv"), F.col("at.turn_no").alias("until"))
    above = turns.join(of, F.col("conv_id").eqNullSafe(F.col("in_conv")) & (F.col("turn_no") < F.col("until"))).select("part", "node").distinct()
    rows = rows.unionByName(tree.drop("part").join(above, "node").select("part", F.lit(True).alias("carried"), "depth", "node", "start", "n_tokens"))
    order = ["part", F.col("carried").desc(), F.when(F.col("carried"), F.col("depth").cast("long")).otherwise(F.col("start"))]
    walked = rows.repartition("part").sortWithinPartitions(*order).select("part", "carried", "depth", "node", "start", "n_tokens")
    return tree.join(walked.mapInArrow(_attend, SPANS), "node").drop("part", "in_part")


def _digest(tokenizer: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sharetree.llm.token_store import encoder

        names = [c.split()[0] for c in DIGESTS.split(", ")]
        kinds = [pa.string() if "sha" in c else pa.int64() for c in names]
        t = encoder(tokenizer).tokenizer
        text = lambda ids: t.decode(ids, skip_special_tokens=False)
        for batch in batches:
            rows = []
            for conv_id, nodes in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                formatted, loss = [], []
                for node in nodes:
                    ids, a, b = node["tokens"], node["loss_from"], node["loss_to"]
                    c = max(a, b)
                    formatted += [text(ids[:a]), text(ids[a:c]), text(ids[c:])]
                    loss.append(unescape(text(ids[a:b])))
                whole, under = "".join(formatted), "".join(loss)
                turns = parse(whole)
                said = hashlib.sha256("".join(f"{r}\n{x}\n" for r, x in turns).encode()).hexdigest()
                rows.append((conv_id, len(turns), said, len(under), hashlib.sha256(under.encode()).hexdigest(), len(whole)))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    return run


def read_conversations(turns: DataFrame, tree: DataFrame, tokenizer: str) -> DataFrame:
    """Each conversation, decoded from the tree's tokens and digested."""
    parts = turns.select("conv_id", "turn_no", "node").join(tree.select("node", "tokens", "loss_from", "loss_to"), "node")
    grouped = parts.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn_no", "tokens", "loss_from", "loss_to"))).alias("nodes"))
    return grouped.mapInArrow(_digest(tokenizer), DIGESTS)


def chat_digests(conversations: DataFrame, tokenizer: str) -> DataFrame:
    turns = materialize(turns_of(conversations), "chat-turns")
    tree = attention(materialize(prefix_tree(turns, tokenizer), "chat-packed"), turns)
    return read_conversations(turns, materialize(tree, "chat-tree"), tokenizer)
