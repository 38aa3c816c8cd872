"""Documents to paragraphs with their positions, and back."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Bits of a packed position, which orders paragraphs by shard, document and place and stays positive: 2,048 shards, 17 billion
# document numbers, 262,144 lines a document.
SHARD_BITS, DOC_BITS, PARA_BITS = 11, 34, 18


def packed_position(shard: Column, doc: Column, para_no: Column) -> Column:
    """The three numbers in one long. One that does not fit raises an error: packed all the same, it would be another paragraph's position."""
    parts = [(shard, SHARD_BITS), (doc, DOC_BITS), (para_no, PARA_BITS)]
    fits = F.lit(True)
    for part, bits in parts:
        fits = fits & (F.shiftright(part.cast("long"), bits) == 0)
    packed = F.shiftleft(shard.cast("long"), DOC_BITS + PARA_BITS).bitwiseOR(F.shiftleft(doc.cast("long"), PARA_BITS)).bitwiseOR(para_no.cast("long"))
    told = F.concat(F.lit("no packed position for shard, document, line "), F.concat_ws(", ", *(part.cast("string") for part, _ in parts)))
    return F.when(fits, packed).when(fits.isNotNull(), F.raise_error(told).cast("long"))


def shard_of(pos: Column) -> Column:
    return F.shiftright(pos, DOC_BITS + PARA_BITS).cast("int")


def doc_of(pos: Column) -> Column:
    return F.shiftright(pos, PARA_BITS).bitwiseAND((1 << DOC_BITS) - 1)


def para_of(pos: Column) -> Column:
    return pos.bitwiseAND((1 << PARA_BITS) - 1).cast("int")


def explode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shard: Column | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, shard_id, para_no, pos, para, *keep): one row for each non-blank line. Numbers count all lines."""
    shard = F.lit(0) if shard is None else shard
    lines = docs.select(F.col(id_col), shard.cast("int").alias("shard_id"), *keep, F.posexplode(F.split(text_col, "\n")).alias("para_no", "para"))
    lines = lines.where(F.trim("para") != "")
    return lines.select(id_col, "shard_id", "para_no", packed_position(F.col("shard_id"), F.col(id_col), F.col("para_no")).alias("pos"), "para", *keep)


def explode_blocks(pages: DataFrame, blocks: Column, id_col: str = "page_id", shard: Column | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """The same from an array of blocks."""
    return explode(pages.withColumn("__text", F.array_join(blocks, "\n")), id_col, "__text", shard, keep)


def from_turns(turns: DataFrame) -> DataFrame:
    """Conversations as documents: (conv_id, para_no, role, para), a turn being a paragraph."""
    return turns.where(F.trim("text") != "").select("conv_id", F.col("turn").cast("int").alias("para_no"), "role", F.col("text").alias("para"))


def assemble(paras: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, text, para_nos): the paragraphs of each document in order."""
    rows = paras.groupBy(id_col).agg(F.array_sort(F.collect_list(F.struct("para_no", "para"))).alias("p"))
    return rows.select(id_col, F.array_join(F.transform("p", lambda x: x["para"]), "\n").alias("text"), F.transform("p", lambda x: x["para_no"]).alias("para_nos"))


def pick_lines(text: Column, para_nos: Column) -> Column:
    """The lines of a text with the given numbers, in order: the wide side of a document is filtered in place."""
    # The lines are bound by the outer lambda, so the text is split once and not for each number.
    picked = F.transform(F.array(F.split(text, "\n")), lambda lines: F.array_join(F.transform(para_nos, lambda i: F.get(lines, i)), "\n"))
    return picked[0]
