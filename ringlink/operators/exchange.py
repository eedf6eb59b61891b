"""The hand-over of pieces: what each holder gets of each owner, and an audit of it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.operators.encoding import bit_columns, ones, places, tokenise
from ringlink.spec import LinkageSpec


def word_columns(spec: LinkageSpec) -> list[str]:
    return [f"w{k}" for k in range(spec.words)]


def split_segments(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """party, rid, bkv, x_own, piece, w0.., seg_ones: each filter in P pieces of equal width."""
    bits = bit_columns(spec)
    cut = F.array(*(F.struct(F.lit(i + 1).alias("piece"), *(F.col(bits[i * spec.words + k]).alias(f"w{k}") for k in range(spec.words))) for i in range(spec.parties)))
    rows = encoded.select("party", "rid", "bkv", "x_own", F.explode(cut).alias("p")).select("party", "rid", "bkv", "x_own", "p.*")
    return rows.withColumn("seg_ones", ones(word_columns(spec)))


def piece_places(spec: LinkageSpec) -> Column:
    """The places inside one piece that its words hold."""
    return places(spec, word_columns(spec))


def slot() -> Column:
    """The place of an owner in a holder's merge order: its own record first, then the others ascending."""
    h, o = F.col("holder"), F.col("owner")
    return F.when(h == o, 1).when(o < h, o + 1).otherwise(o).cast("int")


def exchange_segments(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, owner, slot, rid, bkv, w0.., seg_ones, x_own: holder j gets piece j of every owner, its own included.

    Record ids and block keys travel as keyed tokens; x_own, the bits of the whole filter, is known to its owner
    alone and null elsewhere. No clear attribute and no entity is in the view.
    """
    rows = split_segments(encoded, spec).withColumnsRenamed({"party": "owner", "piece": "holder"})
    own = F.when(F.col("holder") == F.col("owner"), F.col("x_own")).alias("x_own")
    return rows.select("holder", "owner", slot().alias("slot"), tokenise(F.col("rid"), "rid", spec.secret).alias("rid"), tokenise(F.col("bkv"), "bkv", spec.secret).alias("bkv"), *word_columns(spec), "seg_ones", own)


def record_tokens(encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """party, rid, token: what each owner keeps to read results by."""
    return encoded.select("party", "rid", tokenise(F.col("rid"), "rid", spec.secret).alias("token"))


def exposure_audit(view: DataFrame, spec: LinkageSpec) -> DataFrame:
    """holder, owner, rows, max_bits, width: no holder has more of another's record than one piece."""
    return view.groupBy("holder", "owner").agg(F.count("*").alias("rows"), F.max("seg_ones").alias("max_bits"), F.lit(spec.width).alias("width"))
