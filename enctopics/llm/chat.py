"""Conversations as one training text each, with a loss mask, by array expressions alone.

Template: a block `<|im_start|>role`, newline, texts, `<|im_end|>`, newline. Adjacent turns of one role share a
block, parted by `<|im_sep|>`, so the turns can still be read back one by one. Inside roles and texts `&` becomes
`&amp;` and `<|` becomes `&lt;|`, so that no marker can occur there; a role's newline becomes `&nl;`.

Nulls: a null text or role is empty, null turn numbers come first, null ids form one conversation. Ties in the
turn number are ordered by role, then text; repeated rows are repeated turns. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import narrow, no_null

START, SEP, END = "<|im_start|>", "<|im_sep|>", "<|im_end|>\n"


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("&"), F.lit("&amp;")), F.lit("<|"), F.lit("&lt;|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("&lt;|"), F.lit("<|")), F.lit("&amp;"), F.lit("&"))


def _merged(turns: Column) -> Column:
    """Blocks of adjacent turns with one role, from sorted turns."""
    block = "array<struct<role:string,texts:array<string>>>"

    def add(blocks: Column, t: Column) -> Column:
        last = F.try_element_at(blocks, F.lit(-1))
        grown = F.struct(last["role"].alias("role"), F.concat(last["texts"], F.array(t["text"])).alias("texts"))
        fresh = F.struct(t["role"].alias("role"), F.array(t["text"]).alias("texts"))
        same = F.coalesce(last["role"] == t["role"], F.lit(False))
        return F.when(same, F.concat(F.slice(blocks, F.lit(1), F.greatest(F.size(blocks) - 1, F.lit(0))), F.array(grown))).otherwise(F.concat(blocks, F.array(fresh))).cast(block)

    return F.aggregate(turns, F.array().cast(block), add)


def format_chats(turns: DataFrame, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", loss_role: str = "assistant") -> DataFrame:
    """conv_id, formatted, loss_spans: character ranges [start, end) of the texts that count for the loss."""
    rows = narrow(turns, conv_id=id_col, turn=turn_col, role=role_col, text=text_col)
    role = F.replace(escape(no_null(F.col("role"))), F.lit("\n"), F.lit("&nl;"))
    turn = F.struct("turn", role.alias("role"), escape(no_null(F.col("text"))).alias("text"))
    blocks = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("turns")).select("conv_id", _merged(F.col("turns")).alias("blocks"))

    def pieces(b: Column) -> Column:
        head = F.concat(F.lit(START), b["role"], F.lit("\n"))
        last = F.size(b["texts"]) - 1
        return F.transform(
            b["texts"],
            lambda t, i: F.struct(
                F.when(i == 0, head).otherwise(F.lit(SEP)).alias("head"), t.alias("text"), F.when(i == last, F.lit(END)).otherwise(F.lit("")).alias("tail"), (b["role"] == loss_role).alias("loss")
            ),
        )

    walk = "struct<at:bigint,spans:array<struct<start:bigint,end:bigint>>>"

    def step(acc: Column, p: Column) -> Column:
        start = acc["at"] + F.length(p["head"])
        end = start + F.length(p["text"])
        more = F.array(F.struct(start.alias("start"), end.alias("end")))
        return F.struct((end + F.length(p["tail"])).alias("at"), F.when(p["loss"], F.concat(acc["spans"], more)).otherwise(acc["spans"]).alias("spans")).cast(walk)

    none = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast("array<struct<start:bigint,end:bigint>>").alias("spans")).cast(walk)
    return blocks.select("conv_id", F.flatten(F.transform("blocks", pieces)).alias("pieces")).select(
        "conv_id",
        F.array_join(F.transform("pieces", lambda p: F.concat(p["head"], p["text"], p["tail"])), "").alias("formatted"),
        F.aggregate("pieces", none, step)["spans"].alias("loss_spans"),
    )


def read_turns(formatted: Column) -> Column:
    """The turns (role, text) that a formatted text holds."""
    blocks = F.filter(F.split(formatted, r"<\|im_end\|>\n"), lambda b: b != "")

    def turns(b: Column) -> Column:
        cut_at = F.locate("\n", b)
        role = unescape(F.replace(F.substr(b, F.lit(len(START) + 1), cut_at - len(START) - 1), F.lit("&nl;"), F.lit("\n")))
        return F.transform(F.split(F.substr(b, cut_at + 1), r"<\|im_sep\|>"), lambda t: F.struct(role.alias("role"), unescape(t).alias("text")))

    return F.flatten(F.transform(blocks, turns))


def read_loss(formatted: Column, spans: Column) -> Column:
    """The texts under the mask, unescaped, put together."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substr(formatted, (s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int")))), "")


def digest(chats: DataFrame) -> DataFrame:
    """One row a conversation with what is read back from the formatted text."""
    read = chats.select("conv_id", read_turns(F.col("formatted")).alias("turns"), read_loss(F.col("formatted"), F.col("loss_spans")).alias("loss"), F.length("formatted").cast("long").alias("formatted_chars"))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return read.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss"), 256).alias("loss_sha256"),
        "formatted_chars",
    )
