r"""Chat formatting by prefix-target expansion.

Every assistant turn becomes an example of its own: all earlier turns as context, only that reply under the loss mask.
Turns after the last reply form one closing example without a target, so that no turn is lost.

Template of a turn: `<|im_start|>` role newline text `<|im_end|>` newline. Inside roles and texts a backslash is doubled
and `<|` becomes `<\|`, so no control string can arise from content; in roles a newline becomes `\n` as well. Both are
undone exactly by replacing `<\|`, then doubled backslashes.

Turns of a conversation are ordered by turn, then role, then text (nulls first); null role and null text are empty.
Rows with a null conv_id form one conversation whose conv_id is null. Repeated rows are repeated turns.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

START, END = "<|im_start|>", "<|im_end|>"


def escaped(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescaped(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def escaped_role(role: Column) -> Column:
    return F.replace(escaped(role), F.lit("\n"), F.lit("\\n"))


def unescaped_role(role: Column) -> Column:
    """Undoes escaped_role: pieces between doubled backslashes hold single ones only as `\\n` or `<\\|`."""
    pieces = F.transform(F.split(role, r"\\\\"), lambda p: F.replace(F.replace(p, F.lit("\\n"), F.lit("\n")), F.lit("<\\|"), F.lit("<|")))
    return F.array_join(pieces, "\\")


def examples(conversations: DataFrame) -> DataFrame:
    """conversations (conv_id, turn, role, text) -> one row per example.

    conv_id, example (from 0), is_last, text (the formatted example), loss_start and loss_chars (the code points of
    `text` that are trainable; loss_chars is null in a closing example, which has no target).

    One conversation is gathered at a time: that is the size of its own last example, which has to exist anyway.
    """
    turn = F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    whole = (conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("turns"))
             .withColumn("n", F.size("turns"))
             .withColumn("targets", F.filter(F.sequence(F.lit(1), F.col("n")), lambda i: F.get("turns", i - 1)["role"] == "assistant"))
             .withColumn("ends", F.when(F.coalesce(F.array_max("targets"), F.lit(0)) < F.col("n"), F.concat("targets", F.array("n"))).otherwise(F.col("targets")))
             .withColumn("parts", F.transform("turns", lambda t: F.concat(F.lit(START), escaped_role(t["role"]), F.lit("\n"), escaped(t["text"]), F.lit(END + "\n")))))
    exploded = whole.select("conv_id", "parts", F.size("targets").alias("n_targets"), F.size("ends").alias("n_examples"),
                            F.transform("turns", lambda t: F.length(escaped(t["text"]))).alias("lengths"), F.posexplode("ends").alias("example", "end"))
    text = F.array_join(F.slice("parts", 1, F.col("end")), "")
    is_target = F.col("example") < F.col("n_targets")
    loss = F.when(is_target, F.get("lengths", F.col("end") - 1))
    return (exploded.select("conv_id", F.col("example").cast("long").alias("example"), (F.col("example") == F.col("n_examples") - 1).alias("is_last"),
                            text.alias("text"), loss.cast("long").alias("loss_chars"))
            .withColumn("loss_start", F.when(F.col("loss_chars").isNotNull(), F.length("text") - len(END) - 1 - F.col("loss_chars")).cast("long")))


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of the conversations, parsed again out of examples().

    conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars (code points of all its examples).
    Every field of an example is read before the examples of a conversation meet, so no text is shuffled but targets.
    """
    # a turn's text cannot hold a control string, so the start mark cuts exactly at turns
    pieces = F.filter(F.split("text", r"<\|im_start\|>"), lambda p: p != "")
    body = lambda p: F.substring(p, F.locate("\n", p) + 1, F.length(p) - F.locate("\n", p) - len(END) - 1)
    plain = F.transform(pieces, lambda p: F.concat(unescaped_role(F.substring_index(p, "\n", 1)), F.lit("\n"), unescaped(body(p)), F.lit("\n")))
    target = F.col("text").substr(F.col("loss_start") + 1, F.col("loss_chars"))
    read = formatted.select(
        "conv_id", "example", F.length("text").alias("chars"),
        F.when(F.col("is_last"), F.size(pieces)).alias("n_turns"),
        F.when(F.col("is_last"), F.sha2(F.array_join(plain, ""), 256)).alias("turns"),
        F.when(F.col("loss_chars").isNotNull(), unescaped(target)).alias("target"))
    learned = F.array_join(F.transform(F.sort_array(F.collect_list(F.when(F.col("target").isNotNull(), F.struct("example", "target")))), lambda x: x["target"]), "")
    return (read.groupBy("conv_id")
            .agg(F.max("n_turns").cast("long").alias("n_turns"), F.max("turns").alias("turns_sha256"), learned.alias("loss"),
                 F.sum("chars").cast("long").alias("formatted_chars"))
            .select("conv_id", "n_turns", "turns_sha256", F.length("loss").cast("long").alias("loss_chars"),
                    F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars"))
