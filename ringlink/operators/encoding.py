"""q-grams and the bit arrays made of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.operators.blocking import block_key
from ringlink.plans.physical import settle
from ringlink.spec import LinkageSpec

#: Distinct (attribute, gram) rows up to which the dictionary of grams is broadcast.
DICTIONARY_ROWS = 200_000


def clean(value: Column) -> Column:
    """The form that is cut in grams; null counts as empty."""
    return F.lower(F.trim(F.coalesce(value, F.lit(""))))


def qgrams(value: Column, q: int = 2, pad: str = "", distinct: bool = True) -> Column:
    """q-grams; with `pad` that sign stands q-1 times at both ends. Null and values shorter than q have none."""
    if pad:
        value = F.when(F.length(value) > 0, F.concat(F.lit(pad * (q - 1)), value, F.lit(pad * (q - 1)))).otherwise(value)
    n = F.length(value) - (q - 1)
    cut = F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: value.substr(i, F.lit(q)))
    return F.when(n > 0, F.array_distinct(cut) if distinct else cut).otherwise(F.array().cast("array<string>"))


def _number(hexed: Column) -> Column:
    return F.conv(hexed, 16, 10).cast("long")


def hash_positions(gram: Column, bits: int, hashes: int, secret: str = "", scheme: str = "independent") -> Column:
    """Bit places 0..bits-1 of a gram, one per hash, in hash order.

    independent: a keyed digest per hash. double: two halves a, b of one digest, a + i*b.
    """
    each = F.sequence(F.lit(0), F.lit(hashes - 1))
    if scheme == "independent":
        return F.transform(each, lambda i: _number(F.substring(F.md5(F.concat(F.lit(f"{secret}|"), i.cast("string"), F.lit("|"), gram)), 1, 8)) % bits)
    digest = F.md5(F.concat(F.lit(secret), gram))
    return F.transform(each, lambda i: (_number(F.substring(digest, 1, 8)) + i * _number(F.substring(digest, 9, 8))) % bits)


def bloom_positions(value: Column, bits: int, hashes: int, q: int = 2, secret: str = "", scheme: str = "independent") -> Column:
    """Sorted bit places of one string."""
    return F.array_sort(F.array_distinct(F.flatten(F.transform(qgrams(clean(value), q), lambda g: hash_positions(g, bits, hashes, secret, scheme)))))


def record_grams(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """party, rid, attr, gram: each attribute's distinct grams, a row each."""
    per = F.array(*(F.struct(F.lit(i).alias("attr"), qgrams(clean(F.col(c)), spec.q, spec.pad).alias("grams")) for i, c in enumerate(spec.qids)))
    return register.select("party", "rid", F.explode(per).alias("a")).select("party", "rid", F.col("a.attr").alias("attr"), F.explode("a.grams").alias("gram"))


def sample_places(spec: LinkageSpec) -> list[list[int]]:
    """For each attribute the (source place, record place) draws of the sampled encoding.

    Record places are dealt to attributes by weight in runs of their shares, shuffled by a keyed digest; each draws a
    source place of the attribute's filter by another digest.
    """
    import hashlib

    number = lambda text: int(hashlib.md5(text.encode()).hexdigest()[:8], 16)
    order = sorted(range(spec.bits), key=lambda j: (hashlib.md5(f"{spec.secret}|order|{j}".encode()).hexdigest(), j))
    out, at = [], 0
    for share in spec.bits_by_qid:
        out.append([[number(f"{spec.secret}|draw|{j}") % spec.bits, j] for j in order[at : at + share]])
        at += share
    return out


def dictionary(grams: DataFrame, spec: LinkageSpec) -> DataFrame:
    """attr, gram, b0..: the record bits that each distinct gram sets, so a gram is hashed once, not once a record."""
    hashes = F.element_at(F.array(*map(F.lit, spec.hashes_by_qid)), F.col("attr") + 1)
    places = F.slice(hash_positions(F.col("gram"), spec.bits, max(spec.hashes_by_qid), spec.secret, spec.scheme), F.lit(1), hashes)
    rows = grams.select("attr", "gram", F.explode(places).alias("place"))
    if spec.encoding == "sampled":
        drawn = [(a, s, j) for a, draws in enumerate(sample_places(spec)) for s, j in draws]
        table = grams.sparkSession.createDataFrame(drawn, "attr int, place long, to long")  # one row a record bit
        rows = rows.join(F.broadcast(table), ["attr", "place"]).select("attr", "gram", F.col("to").alias("place"))
    off = F.col("place") % spec.width
    column = F.floor(F.col("place") / spec.width) * spec.words + F.floor(off / 63)
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (off % 63).cast("int"))
    rows = rows.select("attr", "gram", column.alias("col"), bit.alias("bit"))
    return rows.groupBy("attr", "gram").agg(*(F.expr(f"bit_or(if(col = {k}, bit, 0L)) AS b{k}") for k in range(spec.parties * spec.words)))


def bit_columns(spec: LinkageSpec) -> list[str]:
    return [f"b{k}" for k in range(spec.parties * spec.words)]


def ones(columns: list[str]) -> Column:
    return F.expr("int(" + " + ".join(f"bit_count({c})" for c in columns) + ")")


def _filters(register: DataFrame, spec: LinkageSpec, keys: list[str]) -> DataFrame:
    grams = record_grams(register, spec)
    words = dictionary(grams.select("attr", "gram").distinct(), spec)
    words = settle(words)
    if words.count() <= DICTIONARY_ROWS:  # bounded by the alphabet; beyond it the join shuffles
        words = F.broadcast(words)
    return grams.join(words, ["attr", "gram"]).groupBy(*keys).agg(*(F.bit_or(b).alias(b) for b in bit_columns(spec)))


def encode_register(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """party, rid, bkv, b0.., x_own of a register: piece i is columns i*words .. (i+1)*words-1, 63 bits each.

    One shuffle by record: rows are dealt by (party, rid) before the grams are made, the aggregation and the join
    back find them there. Records without a gram have no bit.
    """
    dealt = register.select("party", "rid", block_key(spec.block_keys, spec.block_fn).alias("bkv"), *spec.qids).repartition("party", "rid")
    bits = bit_columns(spec)
    rows = dealt.select("party", "rid", "bkv").join(_filters(dealt, spec, ["party", "rid"]).hint("shuffle_hash"), ["party", "rid"], "left")
    rows = rows.select("party", "rid", "bkv", *(F.expr(f"coalesce({b}, 0L) AS {b}") for b in bits))
    return rows.withColumn("x_own", ones(bits))


def encode_attributes(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """party, rid, attr, b0.., ones: one filter per attribute, the first stage of composite encodings."""
    rows = _filters(register.repartition("party", "rid"), spec, ["party", "rid", "attr"])
    names = F.element_at(F.array(*map(F.lit, spec.qids)), F.col("attr") + 1)
    return rows.select("party", "rid", names.alias("attr"), *bit_columns(spec), ones(bit_columns(spec)).alias("ones"))


def places(spec: LinkageSpec, columns: list[str] | None = None, first: int = 0) -> Column:
    """The sorted bit places that columns (all pieces, or one piece from place `first`) hold."""
    cols = columns or bit_columns(spec)
    out = []
    for k, c in enumerate(cols):
        base = first + (k // spec.words) * spec.width + (k % spec.words) * 63
        size = min(63, spec.width - (k % spec.words) * 63)
        out.append(F.expr(f"transform(filter(sequence(0, {size - 1}), i -> getbit({c}, i) = 1), i -> i + {base})"))
    return F.concat(*out)


def listed(array: Column) -> Column:
    return F.concat_ws(" ", array.cast("array<string>"))


def attribute_weights(register: DataFrame, spec: LinkageSpec) -> DataFrame:
    """attr, m, u, w: agreement among pairs of records of one entity, chance agreement, and log2(m/u).

    Pairs are those of neighbouring parties. The chance that two records agree is the sum of squared value shares.
    """
    values = register.select("party", "entity", F.explode(F.array(*(F.struct(F.lit(c).alias("attr"), F.col(c).alias("value")) for c in spec.qids))).alias("a")).select("party", "entity", "a.attr", "a.value")
    other = values.select((F.col("party") - 1).alias("party"), "entity", "attr", F.col("value").alias("other"))
    same = values.join(other, ["party", "entity", "attr"]).groupBy("attr").agg(F.count("*").alias("pairs"), F.count_if(F.col("value") == F.col("other")).alias("agree"))
    shares = values.groupBy("attr", "value").agg(F.count("*").alias("n")).groupBy("attr").agg(F.sum(F.col("n") * F.col("n")).alias("squares"), F.sum("n").alias("all"))
    m, u = F.col("agree") / F.col("pairs"), F.col("squares") / (F.col("all") * F.col("all"))
    return same.join(shares, "attr").select("attr", F.round(m, 6).alias("m"), F.round(u, 6).alias("u"), F.round(F.log2(m / u), 6).alias("w"))


def bloom_theory(register: DataFrame, encoded: DataFrame, spec: LinkageSpec) -> DataFrame:
    """q_avg, k_opt, f_opt, f_k, fill_exp, fill_obs: mean grams a record and what follows from it."""
    grams = record_grams(register, spec).select("party", "rid", "gram").distinct()
    n = register.agg(F.count("*").alias("n"))
    mean = grams.agg(F.count("*").alias("g")).crossJoin(n).select((F.col("g") / F.col("n")).alias("q"))  # one row each
    seen = encoded.agg((F.sum("x_own") / (F.count("*") * spec.bits)).alias("fill"))
    ln2, load = F.log(F.lit(2.0)), F.exp(-spec.hashes * F.col("q") / spec.bits)
    r = lambda c, name: F.round(c, 6).alias(name)
    return mean.crossJoin(seen).select(r(F.col("q"), "q_avg"), r(spec.bits / F.col("q") * ln2, "k_opt"), r(F.pow(F.pow(F.lit(2.0), -ln2), spec.bits / F.col("q")), "f_opt"), r(F.pow(1 - load, F.lit(spec.hashes)), "f_k"), r(1 - load, "fill_exp"), r(F.col("fill"), "fill_obs"))


def choose_k(register: DataFrame, spec: LinkageSpec) -> int:
    """The whole number of hashes next to the optimum for the mean number of grams a record has."""
    row = record_grams(register, spec).select("party", "rid", "gram").distinct().agg(F.count("*").alias("g"), F.countDistinct("party", "rid").alias("n")).first()
    return max(1, round(spec.bits / (row["g"] / row["n"]) * 0.6931471805599453)) if row["n"] else spec.hashes


def perturb(encoded: DataFrame, spec: LinkageSpec, rate: tuple[int, int], seed: str = "") -> DataFrame:
    """encoded with noise: a bit flips where its keyed digest falls under the rate (numerator, denominator).

    Flips are made as a mask per word and combined by exclusive or; x_own follows.
    """
    num, den = rate
    flips = []
    for k, b in enumerate(bit_columns(spec)):
        size = min(63, spec.width - (k % spec.words) * 63)
        base = (k // spec.words) * spec.width + (k % spec.words) * 63
        flips.append(F.expr(f"bigint(aggregate(sequence(0, {size - 1}), 0L, (m, i) -> m | if(bigint(conv(substring(md5(concat('{seed}|', rid, '|', i + {base})), 1, 8), 16, 10)) % {den} < {num}, shiftleft(1L, i), 0L)))").alias(f"f{b}"))
    noisy = encoded.select("*", *flips)
    out = noisy.select("party", "rid", "bkv", *(F.col(b).bitwiseXOR(F.col(f"f{b}")).alias(b) for b in bit_columns(spec)), ones([f"f{b}" for b in bit_columns(spec)]).alias("flipped"))
    return out.withColumn("x_own", ones(bit_columns(spec)))


def tokenise(value: Column, kind: str, secret: str) -> Column:
    """A keyed token of 128 bits: equal values have equal tokens, for who knows the secret alone."""
    return F.substring(F.sha2(F.concat(F.lit(f"{kind}|{secret}|"), value), 256), 1, 32)


def encrypt_rid(value: Column, key: str) -> Column:
    """A record id under AES (key of 16, 24 or 32 signs): each owner can undo its own."""
    return F.base64(F.aes_encrypt(value, F.lit(key), F.lit("ECB"), F.lit("PKCS")))


def decrypt_rid(value: Column, key: str) -> Column:
    return F.aes_decrypt(F.unbase64(value), F.lit(key), F.lit("ECB"), F.lit("PKCS")).cast("string")
