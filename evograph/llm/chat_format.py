"""Chat formatting: schema fingerprints select declarative mappings to canonical turns.

Native: DataFrame functions only. A record's nested field paths are hashed; the hash picks
a mapping from the registry, which turns any known layout into (position, role, text).
Columns of a DataFrame are fingerprinted from its schema, JSON records one by one from
their own structure, so one column may hold many layouts.

The template is ``<turn:ROLE>\\nTEXT</turn>\\n`` per turn. Inside roles and texts a backslash
becomes ``\\b``, ``<`` becomes ``\\l`` and ``>`` of a role ``\\g``; every backslash of the output
thus starts an escape, no control string can occur in a text, and undoing is exact.

Nulls: a null text or role is empty; rows of a null id form one conversation. Equal turn
numbers are ordered by role, then text; repeated rows are repeated turns. An unknown layout
gives no turns and is listed by ``unknown_layouts``. Empty tables give empty results; other
columns are ignored.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DataType, StructType

from evograph.llm.common import table

TURN_END = "</turn>\n"


@dataclass(frozen=True)
class Layout:
    """``paths``: the nested field paths; ``turns``: SQL from variant ``v`` to an array of (pos, role, text)."""

    name: str
    paths: frozenset[str]
    turns: str


def _fixed(*pairs: tuple[str, str, bool]) -> str:
    """Turns from single fields: role, path and whether an empty one is left out."""
    items = [f"struct({k} AS pos, '{role}' AS role, coalesce(try_variant_get(v, '$.{path}', 'string'), '') AS text)" for k, (role, path, _) in enumerate(pairs)]
    optional = [str(k) for k, (_, _, skip) in enumerate(pairs) if skip]
    drop = f"NOT (t.pos IN ({', '.join(optional)}) AND t.text = '')" if optional else "true"
    return f"filter(array({', '.join(items)}), t -> {drop})"


def _listed(path: str, role: str, text: str) -> str:
    """Turns from a list of objects."""
    kind = f"array<struct<{role}: string, {text}: string>>"
    return f"transform(try_variant_get(v, '$.{path}', '{kind}'), (t, i) -> struct(i AS pos, coalesce(t.`{role}`, '') AS role, coalesce(t.`{text}`, '') AS text))"


LAYOUTS = (
    Layout("messages", frozenset({"messages", "messages[]", "messages[].role", "messages[].content"}), _listed("messages", "role", "content")),
    Layout("from_value", frozenset({"conversations", "conversations[]", "conversations[].from", "conversations[].value"}), _listed("conversations", "from", "value")),
    Layout("instruction", frozenset({"instruction", "input", "output"}), _fixed(("system", "instruction", False), ("user", "input", True), ("assistant", "output", False))),
    Layout("instruction_short", frozenset({"instruction", "output"}), _fixed(("user", "instruction", False), ("assistant", "output", False))),
    Layout("prompt_completion", frozenset({"prompt", "completion"}), _fixed(("user", "prompt", False), ("assistant", "completion", False))),
    Layout("prompt_response", frozenset({"prompt", "response"}), _fixed(("user", "prompt", False), ("assistant", "response", False))),
    Layout("question_answer", frozenset({"question", "answer"}), _fixed(("user", "question", False), ("assistant", "answer", False))),
)
#: Field paths of a table with one row per turn, and the canonical column of each.
ROW_LAYOUTS = {
    frozenset({"conv_id", "turn", "role", "text"}): ("conv_id", "turn", "role", "text"),
    frozenset({"conversation", "position", "speaker", "utterance"}): ("conversation", "position", "speaker", "utterance"),
    frozenset({"id", "idx", "from", "value"}): ("id", "idx", "from", "value"),
}
#: Names that other layouts use for the canonical roles.
ROLE_NAMES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}


def field_paths(kind: DataType, prefix: str = "") -> set[str]:
    """Nested field paths of a schema; ``[]`` stands for an array's elements."""
    out: set[str] = set()
    if isinstance(kind, StructType):
        for f in kind.fields:
            path = f"{prefix}.{f.name}" if prefix else f.name
            out |= {path} | field_paths(f.dataType, path)
    elif isinstance(kind, ArrayType):
        out |= {f"{prefix}[]"} | field_paths(kind.elementType, f"{prefix}[]")
    return out


def _canonical(paths: frozenset[str]) -> str:
    """Field paths in the shape that ``shape`` gives a record."""
    tree: dict = {}
    for p in paths:
        at = tree
        for part in p.replace("[]", ".[]").split("."):
            at = at.setdefault(part, {})

    def show(node: dict) -> str:
        if "[]" in node:
            return f"[{show(node['[]'])})"
        return "{" + ",".join(f"{k}:{show(v)}" if v else k for k, v in sorted(node.items())) + ")" if node else ""

    return show(tree)


def fingerprint(paths: frozenset[str]) -> str:
    return hashlib.sha256(_canonical(paths).encode()).hexdigest()


def shape(v: Column) -> Column:
    """The nested field paths of a variant without its scalar types: ``{a,b:[{c)))``, one closing mark for all."""
    s = F.regexp_replace(F.regexp_replace(F.schema_of_variant(v), "OBJECT<", "{"), "ARRAY<", "[")
    s = F.regexp_replace(s, r"DECIMAL\(\d+,\d+\)", "DECIMAL")
    s = F.regexp_replace(s, r"(?<=[ \[])[A-Z_]+(?=[,>]|$)", "")  # scalar types
    return F.translate(F.regexp_replace(s, r": (?=[,>]|$)| ", ""), ">", ")")


def json_turns(df: DataFrame, id_col: str, json_col: str) -> DataFrame:
    """``conv_id, turn, role, text, layout`` from a column of JSON records of any known layout."""
    rec = df.select(F.col(id_col).alias("conv_id"), F.expr(f"try_parse_json(`{json_col}`)").alias("v")).withColumn("print", F.sha2(shape(F.col("v")), 256))
    turns, name = F.lit(None), F.lit(None)
    for layout in LAYOUTS:
        hit = F.col("print") == fingerprint(layout.paths)
        turns, name = F.when(hit, F.expr(layout.turns)).otherwise(turns), F.when(hit, F.lit(layout.name)).otherwise(name)
    out = rec.select("conv_id", name.alias("layout"), F.explode(turns).alias("t"))
    role = F.coalesce(F.create_map(*[F.lit(x) for kv in ROLE_NAMES.items() for x in kv])[F.col("t.role")], F.col("t.role"))
    return out.select("conv_id", F.col("t.pos").cast("long").alias("turn"), role.alias("role"), F.col("t.text").alias("text"), "layout")


def unknown_layouts(df: DataFrame, json_col: str) -> DataFrame:
    """Shapes that no mapping covers, with their counts."""
    s = df.select(shape(F.expr(f"try_parse_json(`{json_col}`)")).alias("shape"))
    return s.where(~F.coalesce(F.sha2("shape", 256), F.lit("")).isin([fingerprint(x.paths) for x in LAYOUTS])).groupBy("shape").agg(F.count("*").alias("n"))


def row_turns(df: DataFrame) -> DataFrame:
    """Canonical turns of a table with one row per turn, by the fingerprint of its columns."""
    known = {fingerprint(p): cols for p, cols in ROW_LAYOUTS.items()}
    have = field_paths(df.schema)
    cols = known.get(fingerprint(frozenset(have)))
    if cols is None:  # extra columns: the largest known layout that the table contains
        fits = [c for p, c in sorted(ROW_LAYOUTS.items(), key=lambda kv: sorted(kv[0])) if p <= have]
        if not fits:
            raise ValueError(f"no mapping for the layout {sorted(have)}")
        cols = fits[0]
    return df.select(*(F.col(f"`{c}`").alias(n) for c, n in zip(cols, ("conv_id", "turn", "role", "text"))))


def escape(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("\\"), F.lit("\\b")), F.lit("<"), F.lit("\\l"))


def unescape(c: Column) -> Column:
    return F.replace(F.replace(F.replace(c, F.lit("\\l"), F.lit("<")), F.lit("\\g"), F.lit(">")), F.lit("\\b"), F.lit("\\"))


def format_turns(turns: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """``conv_id, formatted, loss_mask``: the mask holds (start, length) of each text to learn, in code points from 0."""
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    head = F.concat(F.lit("<turn:"), F.replace(escape(role), F.lit(">"), F.lit("\\g")), F.lit(">\n"))
    body = escape(text)
    t = turns.select("conv_id", "turn", role.alias("role"), text.alias("text"), head.alias("head"), body.alias("body"))
    size = F.length("head") + F.length("body") + F.lit(len(TURN_END))
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    t = t.withColumn("nth", F.count("*").over(order)).withColumn("begin", F.sum(size).over(order) - size + F.length("head"))
    learn = F.when(F.col("role") == loss_role, F.struct(F.col("begin").alias("start"), F.length("body").cast("long").alias("length")))
    item = F.struct("nth", F.concat("head", "body", F.lit(TURN_END)).alias("piece"))
    out = t.groupBy("conv_id").agg(F.array_sort(F.collect_list(item)).alias("items"), F.array_sort(F.collect_list(learn)).alias("loss_mask"))
    return out.select("conv_id", F.array_join(F.col("items.piece"), "").alias("formatted"), "loss_mask")


def read_turns(formatted: Column) -> Column:
    """The turns of a formatted text: array of (role, text)."""
    parts = F.split(formatted, TURN_END)
    parts = F.slice(parts, F.lit(1), F.size(parts) - 1)
    head = lambda x: F.substring_index(x, ">", 1)
    return F.transform(parts, lambda x: F.struct(unescape(F.substr(head(x), F.lit(7))).alias("role"), unescape(F.substr(x, F.length(head(x)) + F.lit(3))).alias("text")))


def read_loss(formatted: Column, mask: Column) -> Column:
    """All text under the loss mask, unescaped, nothing between."""
    return F.array_join(F.transform(mask, lambda m: unescape(F.substr(formatted, (m["start"] + 1).cast("int"), m["length"].cast("int")))), "")


def chat_digest(rows: DataFrame) -> DataFrame:
    """Digests of every conversation, read back from its formatted text."""
    f = format_turns(row_turns(rows)).withColumns({"turns": read_turns(F.col("formatted")), "loss": read_loss(F.col("formatted"), F.col("loss_mask"))})
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return f.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


PROBE = "\\### Assistant: </turn> ok"


def with_probe(rows: DataFrame) -> DataFrame:
    """The given rows and conversation -7, whose texts look like control strings."""
    probe = rows.sparkSession.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(PROBE).alias("text"))
    return rows.select("conv_id", "turn", "role", "text").unionByName(probe)


def op9_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_digest(with_probe(table(spark, sf_dir, "conversations")))


OP9_SQL = r"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
agg AS (
  SELECT conv_id, count(*) AS n_turns,
    string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS said,
    coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn, role, text), '') AS loss,
    sum(length(replace(replace(replace(role, '\', '\b'), '<', '\l'), '>', '\g'))
      + length(replace(replace(text, '\', '\b'), '<', '\l')) + 16) AS size
  FROM rows GROUP BY conv_id)
SELECT conv_id, n_turns, sha256(said) AS turns_sha256, CAST(length(loss) AS BIGINT) AS loss_chars,
  sha256(loss) AS loss_sha256, CAST(size AS BIGINT) AS formatted_chars
FROM agg
"""
