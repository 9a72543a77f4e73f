"""Chat formatting with multi-party perspective rotation.

For every participant of a conversation (every distinct role but ``system``) the dialogue is rendered once with that
speaker as the assistant and all others as named users.  ``rotate`` has one row per conversation, perspective and turn:
in turn order the ``rendered`` pieces of a perspective are the whole training text, and the loss mask is a span of each
piece.  ``dialogues`` assembles the pieces, with all mask spans.  Participants are found by a distinct over (conversation,
role), which combines before its shuffle; turns meet them in a plain join, so a conversation that holds a third of all
rows is split by Spark and never gathered in one task.

Names are injective: letters, digits, ``.``, ``-`` and ``_`` stand for themselves, every other byte of the UTF-8 role is
``%`` and two hexadecimal digits, so different speakers never get one name.

Defined cases: a null role is a speaker of its own without a name (null speaker and perspective, and no ``name=``); an
empty role has an empty name; a null text is empty; rows with a null conv_id are left out;
null turns sort first; repeated rows are rendered each; a conversation without participants gives no rows; template
markers inside texts are broken up so that they cannot end a turn.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def name_of(role: Column) -> Column:
    return F.replace(F.replace(F.url_encode(role), F.lit("+"), F.lit("%20")), F.lit("*"), F.lit("%2A"))


def rotate(turns: DataFrame) -> DataFrame:
    """conv_id, perspective, turn, speaker, chat_role, rendered, mask_start, mask_end (characters; null if not trained
    on) for rows (conv_id, turn, role, text)."""
    turns = turns.where("conv_id is not null").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").alias("speaker"), F.coalesce("text", F.lit("")).alias("text"))
    seats = turns.where("not (speaker <=> 'system')").select("conv_id", F.col("speaker").alias("perspective")).distinct()
    seat = F.col("perspective").eqNullSafe(F.col("speaker"))
    chat_role = F.when(F.col("speaker") == "system", "system").when(seat, "assistant").otherwise("user")
    name = F.when((F.col("chat_role") == "user") & F.col("speaker").isNotNull(), F.concat(F.lit(" name="), name_of(F.col("speaker")))).otherwise("")
    safe = F.replace(F.col("text"), F.lit("<|im_"), F.lit("<| im_"))
    head = F.concat(F.lit(OPEN), "chat_role", name, F.lit("\n"))
    out = turns.join(seats, "conv_id").withColumn("chat_role", chat_role).withColumns({"head": head, "body": safe})
    trained = F.col("chat_role") == "assistant"
    start = F.length("head").cast("long")
    return out.select(
        "conv_id", "perspective", "turn", "speaker", "chat_role", F.concat("head", "body", F.lit(CLOSE + "\n")).alias("rendered"),
        F.when(trained, start).alias("mask_start"), F.when(trained, start + F.length("body") + len(CLOSE)).alias("mask_end"),
    )


def dialogues(turns: DataFrame, span: int = 512) -> DataFrame:
    """conv_id, perspective, part, text, masks: the assembled training texts and the character spans that are trained on.

    A part holds the turns whose numbers fall into one range of ``span`` (part = turn div span; null turns are part -1),
    so a very long conversation is several rows and no row gathers it whole; in order, the parts are the whole dialogue.
    Pieces of equal turns follow in the order of their text.
    """
    part = F.coalesce(F.floor(F.col("turn") / span), F.lit(-1)).cast("long")
    pieces = F.array_sort(F.collect_list(F.struct("turn", "rendered", "mask_start", "mask_end")))
    rows = rotate(turns).withColumn("part", part).groupBy("conv_id", "perspective", "part").agg(pieces.alias("p"))
    empty = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,stop:bigint>>").alias("spans"))

    def add(acc: Column, x: Column) -> Column:
        one = F.struct((acc["at"] + x["mask_start"]).alias("start"), (acc["at"] + x["mask_end"]).alias("stop"))
        spans = F.when(x["mask_start"].isNull(), acc["spans"]).otherwise(F.array_append(acc["spans"], one))
        return F.struct((acc["at"] + F.length(x["rendered"])).alias("at"), spans.alias("spans"))

    return rows.select("conv_id", "perspective", "part", F.array_join(F.transform("p", lambda x: x["rendered"]), "").alias("text"), F.aggregate("p", empty, add)["spans"].alias("masks"))
