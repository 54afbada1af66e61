"""Chat formatting by prefix-target expansion, in DataFrame functions only.

Every assistant turn becomes an example of its own: all turns up to it, of which its text alone is trainable. A
conversation whose last turn isn't an assistant's gives one more example, of all turns and nothing trainable, so that
formatting loses no turn. A turn is written <|im_start|>role NEWLINE text<|im_end|> NEWLINE; inside roles and texts every
"<" before bars gets one bar more, so no control string can occur in them, and taking one bar away gives them back.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Fixed values of the template.
START, END, AFTER_ROLE, AFTER_TURN = "<|im_start|>", "<|im_end|>", "\n", "\n"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"<(\|+)", r"<|$1")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"<\|(\|+)", r"<$1")


def escape_role(role: Column) -> Column:
    return escape(F.replace(F.replace(role, F.lit("%"), F.lit("%25")), F.lit("\n"), F.lit("%0A")))


def unescape_role(role: Column) -> Column:
    return F.replace(F.replace(unescape(role), F.lit("%0A"), F.lit("\n")), F.lit("%25"), F.lit("%"))


def expand(conversations: DataFrame) -> DataFrame:
    """(conv_id, example, target_turn, text, loss_start, loss_end), an example a row.

    example counts from 0 in each conversation; loss_start and loss_end are code points into text, null without a
    trainable part. Turns go by turn, then role, then text, nulls first; rows that repeat are turns of their own. A null
    role or text is empty; rows with a null conv_id are one conversation. Other columns are ignored.
    """
    rows = conversations.select("conv_id", F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    turns = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))

    def written(t: Column) -> Column:
        role, text = escape_role(t["role"]), escape(t["text"])
        return F.struct(
            t["turn"].alias("turn"), (t["role"] == "assistant").alias("target"), F.length(text).alias("own"),
            F.concat(F.lit(START), role, F.lit(AFTER_ROLE), text, F.lit(END + AFTER_TURN)).alias("segment"),
        )

    out = turns.select("conv_id", F.transform("turns", written).alias("turns"))
    places = F.filter(F.sequence(F.lit(0), F.size("turns") - 1), lambda i: F.col("turns")[i]["target"] | (i == F.size("turns") - 1))
    out = out.select("conv_id", "turns", F.posexplode(places).alias("example", "place"))
    last = F.col("turns")[F.col("place")]
    text = F.array_join(F.transform(F.slice("turns", F.lit(1), F.col("place") + 1), lambda t: t["segment"]), "")
    out = out.select("conv_id", "example", F.when(last["target"], last["turn"]).alias("target_turn"), last["own"].alias("own"), last["target"].alias("target"), text.alias("text"))
    end = F.when(F.col("target"), F.length("text") - len(END + AFTER_TURN))
    return out.select("conv_id", "example", "target_turn", "text", (end - F.col("own")).alias("loss_start"), end.alias("loss_end"))


def read_back(examples: DataFrame) -> DataFrame:
    """(conv_id, n_turns, turns_text, loss_text, formatted_chars) from formatted examples alone.

    turns_text has role NEWLINE text NEWLINE for each turn of the conversation's last example, which has all of them;
    loss_text is all trainable text, in the order of the examples.
    """
    parts = F.filter(F.split("text", r"<\|im_end\|>\n", -1), lambda x: x != "")
    turns = F.transform(
        F.transform(parts, lambda x: F.substr(x, F.lit(len(START) + 1))),
        lambda x: F.concat(unescape_role(F.substring_index(x, "\n", 1)), F.lit("\n"), unescape(F.substr(x, F.instr(x, "\n") + 1)), F.lit("\n")),
    )
    loss = F.coalesce(unescape(F.substr("text", F.col("loss_start") + 1, F.col("loss_end") - F.col("loss_start"))), F.lit(""))
    each = examples.select("conv_id", "example", F.length("text").cast("long").alias("chars"), loss.alias("loss"), "text")
    last = F.max("example").alias("last")
    by = each.groupBy("conv_id").agg(
        F.sum("chars").alias("formatted_chars"), last, F.max_by("text", "example").alias("text"),
        F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("example", "loss"))), lambda x: x["loss"]), "").alias("loss_text"),
    )
    return by.select("conv_id", F.size(parts).cast("long").alias("n_turns"), F.array_join(turns, "").alias("turns_text"), "loss_text", "formatted_chars")
