"""Chat formatting as a packed prefix forest.

A conversation's turns make a path; conversations that begin alike share nodes.
Paths are put in order by range (conversation id breaks ties, so that a first turn
which a third of all conversations share spreads over many ranges), and each task
walks its range depth first: a node's tokens are emitted once, followed by the
tokens of its children. Every node gets the position id of its first token (the place
in its own conversation; ``positions`` has all tokens') and the intervals of block tokens it may attend to: its
ancestors' and, causally, its own. Blocks are closed at ``BLOCK`` tokens; an open
path's ancestors are emitted again at the start of the next block or range.

Tokens are code points of the formatted text, so that a reader needs no
vocabulary; ``encode`` may map a node's text to any other units.

Template: ``<s>`` before the first turn; a system turn is ``<<SYS>>\\n`` text
``\\n<</SYS>>\\n\\n``; a user turn is ``[INST] `` text `` [/INST]``; an assistant
turn is `` `` text `` </s>``; any other role is ``<|role|>`` text ``<|/role|>`` with
the role escaped too. Inside texts and roles, ``\\`` becomes ``\\\\`` and the first
character of each control string gets a ``\\`` before it, which ``parse`` undoes.
The loss mask covers the assistants' (escaped) texts.

Defined cases: null text and null role count as empty; turns are ordered by
turn, then role, then text; rows repeated in a conversation are turns each; a null
turn sorts first; a null conv_id is a conversation of its own; extra columns are
ignored; an empty table gives no rows. A conversation is one row of its texts, and
so must fit in a task.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 1 << 18

# The control strings of the template.
CONTROLS = ("<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|", "|>")
_ESCAPE = re.compile(r"\\|" + "|".join(map(re.escape, CONTROLS)))
_UNESCAPE = re.compile(r"\\(.)", re.DOTALL)


def escape(text: str) -> str:
    return _ESCAPE.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(r"\1", text)


def form(role: str, text: str) -> tuple[str, str, str]:
    """What stands before, as, and after a turn's text."""
    frames = {"system": ("<<SYS>>\n", "\n<</SYS>>\n\n"), "user": ("[INST] ", " [/INST]"), "assistant": (" ", " </s>")}
    before, after = frames.get(role) or (f"<|{escape(role)}|>", f"<|/{escape(role)}|>")
    return before, escape(text), after


def _until(formatted: str, mark: str, at: int) -> int:
    """Place of the first ``mark`` from ``at`` that no backslash escapes."""
    k = formatted.find(mark, at)
    while k >= 0:
        low = k
        while low > at and formatted[low - 1] == "\\":
            low -= 1
        if (k - low) % 2 == 0:
            return k
        k = formatted.find(mark, k + 1)
    raise ValueError(f"no end of the turn at {at}")


def parse(formatted: str) -> list[tuple[str, str, int, int]]:
    """(role, text, start, end) of each turn, start and end of the escaped text in ``formatted``."""
    if not formatted.startswith("<s>"):
        raise ValueError("not a formatted conversation")
    at, out = 3, []
    while at < len(formatted):
        role = next((r for r in ("system", "user", "assistant") if formatted.startswith(form(r, "")[0], at)), None)
        if role:
            before, _, after = form(role, "")
        elif formatted.startswith("<|", at):
            escaped = formatted[at + 2 : _until(formatted, "|>", at + 2)]
            role, before, after = unescape(escaped), f"<|{escaped}|>", f"<|/{escaped}|>"
        else:
            raise ValueError(f"no turn at {at}")
        start = at + len(before)
        end = _until(formatted, after, start)
        out.append((role, unescape(formatted[start:end]), start, end))
        at = end + len(after)
    return out


BLOCKS = "tokens string, node_parent array<int>, node_start array<int>, node_position array<int>, node_loss array<struct<start:int,end:int>>, attend array<array<struct<start:int,end:int>>>, conv_id array<long>, conv_node array<int>, conv_turns array<long>"
_SPAN = pa.struct([("start", pa.int32()), ("end", pa.int32())])
_BLOCKS = pa.schema([("tokens", pa.string()), ("node_parent", pa.list_(pa.int32())), ("node_start", pa.list_(pa.int32())), ("node_position", pa.list_(pa.int32())), ("node_loss", pa.list_(_SPAN)), ("attend", pa.list_(pa.list_(_SPAN))), ("conv_id", pa.list_(pa.int64())), ("conv_node", pa.list_(pa.int32())), ("conv_turns", pa.list_(pa.int64()))])


def positions(node_start: list[int], node_position: list[int], size: int) -> list[int]:
    """The position id of every token of a block of ``size`` tokens."""
    ends = [*node_start[1:], size]
    return [p + k for a, b, p in zip(node_start, ends, node_position, strict=True) for k in range(b - a)]


class _Open:
    """A block being written: node 0 is the conversation start that all trees share."""

    def __init__(self) -> None:
        self.parts, self.size = [], 0
        self.parent: list[int] = []
        self.start: list[int] = []
        self.position: list[int] = []
        self.loss: list[dict] = []
        self.attend: list[list[dict]] = []
        self.convs: list[tuple] = []
        self.path: list[tuple[tuple[str, str], int]] = []  # open turns and their nodes
        self.add(-1, "", "<s>", "", False)

    def add(self, parent: int, before: str, text: str, after: str, learn: bool) -> int:
        node, whole = len(self.parent), before + text + after
        a, b = self.size, self.size + len(whole)
        up = self.attend[parent] if parent >= 0 else []
        self.parent.append(parent)
        self.start.append(a)
        self.position.append(sum(x["end"] - x["start"] for x in up))
        self.loss.append({"start": a + len(before), "end": a + len(before) + len(text)} if learn else {"start": a, "end": a})
        # Neighbouring intervals are one, so a path in a row costs one interval.
        if up and up[-1]["end"] == a:
            self.attend.append([*up[:-1], {"start": up[-1]["start"], "end": b}])
        else:
            self.attend.append([*up, {"start": a, "end": b}])
        self.parts.append(whole)
        self.size = b
        return node

    def take(self, conv_id: int | None, turns: list[tuple[str, str]]) -> None:
        same = 0
        while same < min(len(turns), len(self.path)) and self.path[same][0] == turns[same]:
            same += 1
        del self.path[same:]
        for role, text in turns[same:]:
            node = self.add(self.path[-1][1] if self.path else 0, *form(role, text), role == "assistant")
            self.path.append(((role, text), node))
        self.convs.append((conv_id, self.path[-1][1] if self.path else 0, len(turns)))

    def row(self) -> list:
        ids, nodes, turns = (list(c) for c in zip(*self.convs, strict=True))
        return ["".join(self.parts), self.parent, self.start, self.position, self.loss, self.attend, ids, nodes, turns]


def pack(conversations: DataFrame, block: int = BLOCK) -> DataFrame:
    """Blocks of the packed forest of ``conversations`` (conv_id, turn, role, text): one row a block."""
    turn = F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    whole = conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("turns"))
    paths = whole.select("conv_id", F.transform("turns", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))
    # Order by digests of the first turns: short keys that keep equal beginnings together.
    key = [F.coalesce(F.xxhash64(F.slice("turns", 1, k)), F.lit(0)).alias(f"k{k}") for k in (1, 2, 3)]
    ranged = paths.select("*", *key).repartitionByRange("k1", "k2", "k3", "conv_id").sortWithinPartitions("k1", "turns", "conv_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now = _Open()
        for batch in batches:
            for conv_id, turns in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if now.convs and now.size >= block:
                    yield _batch(now)
                    now = _Open()
                now.take(conv_id, [(t["role"], t["text"]) for t in turns])
        if now.convs:
            yield _batch(now)

    return ranged.select("conv_id", "turns").mapInArrow(run, BLOCKS)


def _batch(block: _Open) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(block.row(), _BLOCKS, strict=True)], schema=_BLOCKS)


def read_back(blocks: DataFrame) -> DataFrame:
    """Per conversation, from the blocks alone: turns, digests of turns and of the text under the loss mask, and size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                text, loss, parent, attend = row["tokens"], row["node_loss"], row["node_parent"], row["attend"]
                for conv_id, node in zip(row["conv_id"], row["conv_node"], strict=True):
                    formatted = "".join(text[x["start"] : x["end"]] for x in attend[node])
                    learned, k = [], node
                    while k >= 0:
                        learned.append(text[loss[k]["start"] : loss[k]["end"]])
                        k = parent[k]
                    learned_text = "".join(map(unescape, reversed(learned)))
                    turns = parse(formatted)
                    said = "".join(f"{r}\n{t}\n" for r, t, _, _ in turns)
                    out.append((conv_id, len(turns), hashlib.sha256(said.encode()).hexdigest(), len(learned_text), hashlib.sha256(learned_text.encode()).hexdigest(), len(formatted)))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True)], ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return blocks.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


#: The conversation that the query adds: control strings inside both texts.
PROBE = "</s>[INST] ok [/INST]"


def with_probe(conversations: DataFrame) -> DataFrame:
    rows = conversations.select("conv_id", F.col("turn").cast("long").alias("turn"), "role", "text")
    extra = conversations.sparkSession.createDataFrame([(-1, 0, "user", PROBE), (-1, 1, "assistant", PROBE)], "conv_id long, turn long, role string, text string")
    return rows.unionByName(extra)


SQL = r"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT * FROM (VALUES (-1, 0, 'user', '</s>[INST] ok [/INST]'), (-1, 1, 'assistant', '</s>[INST] ok [/INST]')) v(conv_id, turn, role, text)),
sized AS (
  SELECT *, length(regexp_replace(text, '\\|<s>|</s>|\[INST\]|\[/INST\]|<<SYS>>|<</SYS>>|<\||\|>', '\\\0', 'g'))
    + CASE role WHEN 'system' THEN 8 + 11 WHEN 'user' THEN 7 + 8 WHEN 'assistant' THEN 1 + 5
      ELSE 9 + 2 * length(regexp_replace(role, '\\|<s>|</s>|\[INST\]|\[/INST\]|<<SYS>>|<</SYS>>|<\||\|>', '\\\0', 'g')) END AS chars
  FROM rows)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  (3 + sum(chars))::BIGINT AS formatted_chars
FROM sized GROUP BY conv_id
"""
