"""Chat formatting of typed content parts, in DataFrame functions only.

A turn's content is an array of parts (type, text, ref, units). The visitor walks the parts in order:
text parts are escaped and stay, while image, audio and document parts become placeholders
`<|type:n|>`, numbered through the conversation. Each attachment is recorded with its reference, its
number, its turn and the tokens that it will take: `base + per_unit * units` of its type. A
conversation becomes one string; turns are marked by control strings. All of them begin with `<|`,
and in texts and roles a backslash is doubled and `<|` becomes `<\\|`, so no text holds a control
string, and unescaping is exact: after escaping, a single backslash between `<` and `|` can only be
the mark.

The loss mask covers the text of the trained roles. It is kept for each turn as start and length in
code points, and for the conversation as spans.

One conversation is one row, as its digest needs; its turns are pre-aggregated before the shuffle.

Defined results: null texts and roles count as empty; turns of a conversation are ordered by turn
(nulls first), then role, then the text of their parts, and repeated rows stay as turns; conv_id and turn
are of any types that sort (`op3` reads them as whole numbers, and a text that is none raises); a null conv_id is a conversation;
an unknown part type is kept as a placeholder with no tokens; no rows, no conversations.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

ROLE, CONTENT, END = "<|turn|>", "<|content|>", "<|end|>"
#: Tokens of a placeholder: type -> (base, for each unit: tiles, seconds, pages).
EXPANSION = {"image": (2, 576), "audio": (2, 25), "document": (2, 600)}
TRAINED = ("assistant",)
PARTS = "array<struct<type:string,text:string,ref:string,units:bigint>>"


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def text_part(text: Column) -> Column:
    return F.array(F.struct(F.lit("text").alias("type"), text.alias("text"), F.lit(None).cast("string").alias("ref"), F.lit(None).cast("bigint").alias("units"))).cast(PARTS)


def _tokens(part: Column) -> Column:
    out = F.lit(0).cast("bigint")
    for kind, (base, each) in EXPANSION.items():
        out = F.when(part["type"] == kind, F.lit(base) + F.lit(each) * F.greatest(F.coalesce(part["units"], F.lit(1)), F.lit(0))).otherwise(out)
    return out


def _is_text(part: Column) -> Column:
    return F.coalesce(part["type"], F.lit("text")) == "text"


def format_chat(turns: DataFrame, trained: tuple[str, ...] = TRAINED) -> DataFrame:
    """turns (conv_id, turn, role, parts) -> conv_id, formatted, turns, loss_spans, attachments, expanded_tokens.

    turns: for each turn role, n_chars (of the formatted turn), loss_start and loss_chars in it, trained.
    loss_spans: start and length in `formatted`, in code points, from 0.
    attachments: number, turn_index, type, ref, tokens.
    """
    parts = F.coalesce(F.col("parts").cast(PARTS), F.array().cast(PARTS))
    text = F.array_join(F.transform(parts, lambda p: F.coalesce(p["text"], F.lit(""))), "")
    rest = F.to_json(F.struct(parts.alias("parts")))  # of turns alike in their texts
    rows = turns.select("conv_id", F.struct("turn", F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), text.alias("text"), rest.alias("rest"), parts.alias("parts")).alias("t"))
    whole = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("ts"))
    # number of attachments before each turn, by one pass over the counts
    held = F.transform("ts", lambda t: F.size(F.filter(t["parts"], lambda p: ~_is_text(p))))
    whole = whole.withColumn("held", held)
    start = F.struct(F.lit(0).alias("n"), F.array().cast("array<int>").alias("out"))
    before = F.when(
        F.exists("held", lambda n: n > 0),
        F.aggregate("held", start, lambda acc, n: F.struct((acc["n"] + n).alias("n"), F.concat(acc["out"], F.array(acc["n"])).alias("out")), lambda acc: acc["out"]),
    ).otherwise(F.transform("held", lambda n: F.lit(0)))
    whole = whole.withColumn("before", before)

    def visit(t: Column, i: Column) -> Column:
        base = F.element_at("before", (i + 1).cast("int"))
        pieces = F.transform(
            t["parts"],
            lambda p, k: F.when(_is_text(p), escape(F.coalesce(p["text"], F.lit("")))).otherwise(
                F.concat(F.lit("<|"), F.replace(escape(p["type"]), F.lit("|"), F.lit("/")), F.lit(":"), (base + F.size(F.filter(F.slice(t["parts"], 1, k), lambda q: ~_is_text(q)))).cast("string"), F.lit("|>"))
            ),
        )
        return F.struct(t["role"].alias("role"), F.concat(F.lit(ROLE), escape(t["role"]), F.lit(CONTENT)).alias("head"), F.array_join(pieces, "").alias("body"))

    whole = whole.withColumn("vs", F.transform("ts", visit))
    formatted = F.array_join(F.transform("vs", lambda v: F.concat(v["head"], v["body"], F.lit(END))), "")
    kept = F.transform(
        "vs",
        lambda v: F.struct(
            v["role"].alias("role"),
            (F.length(v["head"]) + F.length(v["body"]) + len(END)).alias("n_chars"),
            F.length(v["head"]).alias("loss_start"),
            F.when(v["role"].isin(*trained), F.length(v["body"])).otherwise(0).alias("loss_chars"),
            v["role"].isin(*trained).alias("trained"),
        ),
    )
    attachments = F.flatten(
        F.transform(
            "ts",
            lambda t, i: F.transform(
                F.filter(t["parts"], lambda p: ~_is_text(p)),
                lambda p, k: F.struct((F.element_at("before", (i + 1).cast("int")) + k).alias("number"), i.alias("turn_index"), p["type"].alias("type"), p["ref"].alias("ref"), _tokens(p).alias("tokens")),
            ),
        )
    )
    out = whole.select("conv_id", formatted.alias("formatted"), kept.alias("turns"), attachments.alias("attachments"))
    return out.withColumn("expanded_tokens", F.aggregate("attachments", F.lit(0).cast("bigint"), lambda a, x: a + x["tokens"]))


def loss_spans(formatted: DataFrame) -> DataFrame:
    """conv_id, start, length of each masked span in `formatted` (code points, from 0): a row a span."""
    turn = F.posexplode("turns").alias("k", "t")
    flat = formatted.select("conv_id", F.monotonically_increasing_id().alias("row"), "turns").select("conv_id", "row", turn)
    from pyspark.sql import Window

    upto = Window.partitionBy("row").orderBy("k").rowsBetween(Window.unboundedPreceding, -1)
    start = F.coalesce(F.sum("t.n_chars").over(upto), F.lit(0)) + F.col("t.loss_start")
    return flat.withColumn("start", start).filter("t.trained").select("conv_id", "start", F.col("t.loss_chars").alias("length"))


def read_chat(formatted: DataFrame) -> DataFrame:
    """The formatted string read back: conv_id, formatted, read (role, text of each turn), loss_text.

    The turns come from the control strings alone; the loss text from the mask, cut out of each turn.
    """
    pieces = F.slice(F.split("formatted", r"<\|end\|>"), 1, F.greatest(F.size("turns"), F.lit(0)))
    whole = formatted.withColumn("pieces", pieces)
    read = F.transform(
        "pieces",
        lambda x: F.struct(
            unescape(F.substring_index(F.substring(x, F.lit(len(ROLE) + 1), F.length(x)), CONTENT, 1)).alias("role"),
            unescape(F.substring_index(x, CONTENT, -1)).alias("text"),
        ),
    )
    masked = F.zip_with("pieces", "turns", lambda x, t: F.when(t["trained"], unescape(F.substring(x, t["loss_start"] + 1, t["loss_chars"]))).otherwise(F.lit("")))
    return whole.withColumn("read", read).withColumn("loss_text", F.array_join(masked, "")).drop("pieces")


def op3_chat_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("bigint").alias("conv_id"), F.col("turn").cast("bigint").alias("turn"), "role", "text")
    planted = spark.sql("SELECT bigint(-7) AS conv_id, bigint(turn) AS turn, role, '</s>[INST] ok [/INST]' AS text FROM VALUES (0, 'user'), (1, 'assistant') AS v(turn, role)")
    rows = given.unionByName(planted).withColumn("parts", text_part(F.coalesce("text", F.lit(""))))
    back = read_chat(format_chat(rows))
    whole = F.array_join(F.transform("read", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id",
        F.size("read").cast("bigint").alias("n_turns"),
        F.sha2(F.encode(whole, "utf-8"), 256).alias("turns_sha256"),
        F.length("loss_text").cast("bigint").alias("loss_chars"),
        F.sha2(F.encode("loss_text", "utf-8"), 256).alias("loss_sha256"),
        F.length("formatted").cast("bigint").alias("formatted_chars"),
    )


ORACLE_SQL = r"""
WITH given AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
sized AS (
  SELECT *, length(replace(replace(text, '\', '\\'), '<|', '<\|')) + length(replace(replace(role, '\', '\\'), '<|', '<\|'))
            + length('<|turn|>') + length('<|content|>') + length('<|end|>') AS n
  FROM given)
SELECT CAST(conv_id AS BIGINT) AS conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
       CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
       sha256(string_agg(CASE WHEN role = 'assistant' THEN text ELSE '' END, '' ORDER BY turn NULLS FIRST, role, text)) AS loss_sha256,
       CAST(sum(n) AS BIGINT) AS formatted_chars
FROM sized GROUP BY conv_id
"""
