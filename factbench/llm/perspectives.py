"""Chat formatting by multi-party perspective rotation, in DataFrame functions alone.

Every participant of a dialogue is the assistant once; the others become named users, and system turns belong to
nobody. Only dialogues whose texts are longer than a stated size come in parts, so that no group grows with the
table; parts keep all turns, in order. Texts and names are escaped, so that no turn can forge a control mark.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.llm.common import running_sum

TAIL = "<|end|>\n"
#: What a name may not hold, and what stands for it; the percent sign first. Fixed values.
NAME_MARKS = (("%", "%25"), ("<", "%3C"), ("|", "%7C"), (">", "%3E"), ("\n", "%0A"), ("\r", "%0D"))
#: Characters that a turn counts for besides its text.
FRAME = 16


def escaped_text(c: Column) -> Column:
    """Openings of control marks get a second bar: replacing ``<||`` by ``<|`` gives the text back."""
    return F.replace(c, F.lit("<|"), F.lit("<||"))


def escaped_name(c: Column) -> Column:
    for mark, code in NAME_MARKS:
        c = F.replace(c, F.lit(mark), F.lit(code))
    return c


def rotate(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", speaker: str = "role", text: str = "text", system: str = "system", part_chars: int = 1 << 20, spread: int = 64) -> DataFrame:
    """(conv, perspective, part, n_turns, n_own, rendered, masks): one row per participant and part of a dialogue.

    Turns are ordered by turn number (null first), then speaker, then text; repeated rows are turns of their own.
    ``masks`` lists the [start, end) character spans of ``rendered`` to train on: the text and end mark of each
    turn of the participant. A dialogue is one part up to ``part_chars`` characters of text (sixteen more a turn);
    longer ones are cut between turns there, and masks count from the start of a part; a longer turn stays whole.
    Turns of the speaker ``system`` are shown to everyone as such, are never trained on, and give no perspective; a
    dialogue of nothing else gives no row. A null speaker is a participant called ``unknown``; null texts are empty;
    rows with a null dialogue id form one dialogue. Names and texts are escaped. Further columns are left out; an
    empty table gives an empty table. Rows grow with participants times parts, as the format asks for.
    """
    who, said = F.coalesce(F.col(speaker), F.lit("unknown")), F.coalesce(F.col(text), F.lit(""))
    rows = turns.select(
        F.col(conv).alias("_conv"), F.col(turn).alias("_turn"), who.alias("_who"), said.alias("_text"),
        (F.length(said) + FRAME).cast("long").alias("_chars"), F.floor(F.coalesce(F.col(turn), F.lit(-1)) / spread).alias("_bucket"),
    )
    seen = running_sum(rows, ["_conv"], "_bucket", [F.col("_turn").asc_nulls_first(), F.col("_who"), F.col("_text")], "_chars", "_at")
    parts = (
        seen.groupBy("_conv", F.floor(F.col("_at") / part_chars).cast("int").alias("part"))
        .agg(F.array_sort(F.collect_list(F.struct("_at", "_who", "_text"))).alias("_turns"))
        .withColumnRenamed("_conv", conv)
    )
    cast = rows.filter(F.col("_who") != system).select("_conv", F.col("_who").alias("perspective")).distinct()
    both = parts.join(cast, parts[conv].eqNullSafe(cast["_conv"]))
    mine = lambda t: t["_who"] == F.col("perspective")
    head = lambda t: F.when(mine(t), F.lit("<|assistant|>\n")).when(t["_who"] == system, F.lit("<|system|>\n")).otherwise(F.concat(F.lit("<|user name="), escaped_name(t["_who"]), F.lit("|>\n")))
    pieces = F.transform("_turns", lambda t: F.struct(F.concat(head(t), escaped_text(t["_text"]), F.lit(TAIL)).alias("s"), F.length(head(t)).alias("h"), mine(t).alias("own")))
    empty = F.expr("cast(array() as array<struct<start:int,end:int>>)")
    walked = F.aggregate(
        "_pieces",
        F.struct(F.lit(0).alias("at"), empty.alias("spans")),
        lambda done, p: F.struct(
            (done["at"] + F.length(p["s"])).alias("at"),
            F.when(p["own"], F.concat(done["spans"], F.array(F.struct((done["at"] + p["h"]).alias("start"), (done["at"] + F.length(p["s"]) - 1).alias("end"))))).otherwise(done["spans"]).alias("spans"),
        ),
    )
    return both.withColumn("_pieces", pieces).select(
        conv, "perspective", "part", F.size("_turns").alias("n_turns"),
        F.size(F.filter("_pieces", lambda p: p["own"])).alias("n_own"),
        F.array_join(F.transform("_pieces", lambda p: p["s"]), "").alias("rendered"), walked["spans"].alias("masks"),
    )
