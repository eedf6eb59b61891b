"""Secure summation: masked running sums from party to party, read by the one who holds the masks.

Masks are digests under a key that an initiator alone has, 60 bits, and sums are taken modulo 2^60, so what a party
receives is spread evenly whatever the sum. Keys are never part of the spec that parties share.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ringlink.spec import LinkageSpec

MODULUS = 1 << 60


def mask(key: Column | str, kind: str, cand: Column) -> Column:
    """The initiator's mask of one candidate's sum of `kind`."""
    own = F.lit(key) if isinstance(key, str) else key
    return F.conv(F.substring(F.md5(F.concat(own, F.lit(f"|{kind}|"), cand)), 1, 15), 16, 10).cast("long")


def modular(value: Column, modulus: int = MODULUS) -> Column:
    return F.pmod(value, F.lit(modulus))


def ring_sum(values: DataFrame, parties: int, start: int = 1, masks: int = 0) -> tuple[DataFrame, DataFrame]:
    """(transcript, total) of values (party, value): one ring, plain integers, one given mask.

    transcript: hop, sender, receiver, message; total: what the initiator reads when the ring closes.
    """
    hop = (F.pmod(F.col("party") - start, F.lit(parties)) + 1).cast("int")
    run = W.orderBy("hop").rowsBetween(W.unboundedPreceding, 0)  # P rows
    rows = values.select(hop.alias("hop"), F.col("party").alias("sender"), "value")
    sent = rows.select("hop", "sender", (F.pmod("sender", F.lit(parties)) + 1).cast("int").alias("receiver"), (F.sum("value").over(run) + masks).alias("message"))
    return sent, sent.where(F.col("hop") == parties).select((F.col("message") - masks).alias("total"))


def candidate(spec: LinkageSpec) -> Column:
    return F.concat_ws(",", *(f"r{j}" for j in range(1, spec.parties + 1)))


def first_party(cand: Column, spec: LinkageSpec, initiator: str) -> Column:
    """The party that starts a candidate's ring: `one` (party 1), `rotate` (dealt by digest), `external` (party 0)."""
    if initiator == "rotate":
        return (F.conv(F.substring(F.md5(F.concat(F.lit("first|"), cand)), 1, 8), 16, 10).cast("long") % spec.parties + 1).cast("int")
    return F.lit({"one": 1, "external": 0}[initiator])


def _key(key: str, first: Column) -> Column:
    """Each initiator has a key of its own."""
    return F.concat(F.lit(f"{key}|"), first.cast("string"))


def ring_transcript(partials: DataFrame, spec: LinkageSpec, key: str, initiator: str = "one", modulus: int = MODULUS) -> DataFrame:
    """cand, first, hop, sender, receiver, masked_c, masked_x: every message of every candidate's ring.

    With an external party each holder sends it its own masked counts instead of a running sum (hop 1, receiver 0);
    the masks of a candidate are agreed among holders and cancel out in the sum.
    """
    rows = partials.select(candidate(spec).alias("cand"), "holder", "c", "x")
    if initiator == "external":
        share = lambda kind: _share(key, kind, spec)
        sent = rows.select("cand", F.lit(0).alias("first"), F.lit(1).alias("hop"), F.col("holder").alias("sender"), F.lit(0).alias("receiver"), modular(F.col("c") + share("c"), modulus).alias("masked_c"), modular(F.col("x") + share("x"), modulus).alias("masked_x"))
        return sent
    rows = rows.withColumn("first", first_party(F.col("cand"), spec, initiator))
    rows = rows.withColumn("hop", (F.pmod(F.col("holder") - F.col("first"), F.lit(spec.parties)) + 1).cast("int"))
    run = W.partitionBy("cand").orderBy("hop").rowsBetween(W.unboundedPreceding, 0)
    own = _key(key, F.col("first"))
    message = lambda kind: modular(F.sum(kind).over(run) + mask(own, kind, F.col("cand")), modulus).alias(f"masked_{kind}")
    return rows.select("cand", "first", "hop", F.col("holder").alias("sender"), (F.col("holder") % spec.parties + 1).cast("int").alias("receiver"), message("c"), message("x"))


def joint_transcript(joint: DataFrame, spec: LinkageSpec, key: str, initiator: str = "one", modulus: int = MODULUS) -> DataFrame:
    """`ring_transcript` of joint counts (c1..cP, x1..xP in one row): running sums are sums of columns, so no candidate is sorted."""
    p = spec.parties
    rows = joint.withColumn("cand", candidate(spec)).withColumn("first", first_party(F.col("cand"), spec, initiator))
    hops = range(1, p + 1)
    if initiator == "external":
        values = F.array(*(F.struct(F.lit(1).alias("hop"), F.lit(h).alias("holder"), F.col(f"c{h}").alias("c"), F.col(f"x{h}").alias("x")) for h in hops))
        sent = rows.select("cand", "first", F.explode(values).alias("m")).select("cand", "first", "m.*")
        masked = [modular(F.col(k) + _share(key, k, spec), modulus).alias(f"masked_{k}") for k in "cx"]
        return sent.select("cand", "first", "hop", F.col("holder").alias("sender"), F.lit(0).alias("receiver"), *masked)
    own = _key(key, F.col("first"))
    rows = rows.select("cand", "first", *(F.array(*(f"{k}{h}" for h in hops)).alias(k) for k in "cx"), *(mask(own, k, F.col("cand")).alias(f"mask_{k}") for k in "cx"))
    at = lambda k, n: F.element_at(k, F.pmod(F.col("first") + F.lit(n - 2), F.lit(p)) + 1)  # noqa: E731  # the n-th sender's value
    run = lambda k, n: sum((at(k, i) for i in range(2, n + 1)), at(k, 1))
    message = lambda k, n: modular(run(k, n) + F.col(f"mask_{k}"), modulus).alias(f"masked_{k}")
    sender = lambda n: (F.pmod(F.col("first") + F.lit(n - 2), F.lit(p)) + 1).cast("int")
    values = F.array(*(F.struct(F.lit(n).alias("hop"), sender(n).alias("sender"), (sender(n) % p + 1).cast("int").alias("receiver"), message("c", n), message("x", n)) for n in hops))
    return rows.select("cand", "first", F.explode(values).alias("m")).select("cand", "first", "m.*")


def _share(key: str, kind: str, spec: LinkageSpec) -> Column:
    """Holder i's part of masks that add to 0 modulo 2^60: its pair mask with the next party less that with the one before."""
    pair = lambda i: mask(F.concat(F.lit(f"{key}|"), i.cast("string")), kind, F.col("cand"))
    return modular(pair(F.col("holder")) - pair(F.pmod(F.col("holder") - 2, F.lit(spec.parties)) + 1))


def ring_totals(partials: DataFrame, spec: LinkageSpec, key: str, initiator: str = "one", modulus: int = MODULUS) -> DataFrame:
    """r1..rP, first, masked_c, masked_x, holders: the message that closes each candidate's ring.

    The last hop's running sum is the sum over holders, so one aggregation gives it without building the transcript.
    Candidates that some holder dropped have no closed ring and leave here.
    """
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    summed = partials.groupBy(*ids).agg(F.sum("c").alias("c"), F.sum("x").alias("x"), F.count("*").alias("holders")).where(F.col("holders") == spec.parties)
    return _closed(summed.drop("holders"), spec, key, initiator, modulus)


def joint_totals(joint: DataFrame, spec: LinkageSpec, key: str, initiator: str = "one", modulus: int = MODULUS, carry: bool = False) -> DataFrame:
    """`ring_totals` of joint counts, with their name1..nameP or, with `carry`, all columns: every candidate's ring closes inside its row."""
    total = lambda k: sum((F.col(f"{k}{h}") for h in range(2, spec.parties + 1)), F.col(f"{k}1"))
    return _closed(joint.withColumns({k: total(k) for k in "cx"}), spec, key, initiator, modulus, joint.columns if carry else None)


def _closed(summed: DataFrame, spec: LinkageSpec, key: str, initiator: str, modulus: int, others: list[str] | None = None) -> DataFrame:
    ids = [f"r{j}" for j in range(1, spec.parties + 1)]
    names = [c for c in (others or summed.columns) if c not in ids and (others or c.startswith("name"))]
    summed = summed.withColumn("cand", candidate(spec)).withColumn("first", first_party(F.col("cand"), spec, initiator))
    if initiator == "external":  # the holders' masks cancel out
        closed = {f"masked_{k}": modular(F.col(k), modulus) for k in "cx"}
    else:
        closed = {f"masked_{k}": modular(F.col(k) + mask(_key(key, F.col("first")), k, F.col("cand")), modulus) for k in "cx"}
    return summed.withColumns(closed).select(*ids, *names, "cand", "first", "masked_c", "masked_x")


def unmask(totals: DataFrame, key: str, initiator: str = "one", modulus: int = MODULUS) -> DataFrame:
    """totals with c and x, as the initiator of each ring reads them."""
    if initiator == "external":
        return totals.withColumns({k: F.col(f"masked_{k}") for k in "cx"})
    return totals.withColumns({k: modular(F.col(f"masked_{k}") - mask(_key(key, F.col("first")), k, F.col("cand")), modulus) for k in "cx"})
