"""Corrupted copies of shared records, driven by keyed digests, so reruns agree.

The edits are SQL text: the plan of a fold over edits is built in one go, not expression by expression.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Forms that scanning confuses, and spellings of one sound. Each pair works both ways.
OCR = [("o", "0"), ("l", "1"), ("s", "5"), ("b", "8"), ("g", "9"), ("z", "2"), ("m", "rn"), ("w", "vv"), ("d", "cl"), ("h", "li"), ("u", "v"), ("n", "ri"), ("e", "c"), ("i", "j")]
SOUNDS = [("ph", "f"), ("ck", "k"), ("c", "k"), ("z", "s"), ("ie", "y"), ("th", "t"), ("gh", "g"), ("sch", "sh"), ("ei", "ai"), ("v", "w"), ("nn", "n"), ("tt", "t"), ("en", "an"), ("er", "ar")]
QIDS = ("given", "surname", "suburb", "postcode")


def digest(*parts: str) -> str:
    """32 bits of the keyed digest of SQL values."""
    return f"bigint(conv(substring(md5(concat_ws('|', {', '.join(f'string({p})' for p in parts)})), 1, 8), 16, 10))"


def edit_insert(c: str, pos: str, sign: str) -> str:
    return f"concat(substring({c}, 1, {pos} - 1), {sign}, substring({c}, {pos}))"


def edit_delete(c: str, pos: str) -> str:
    return f"concat(substring({c}, 1, {pos} - 1), substring({c}, {pos} + 1))"


def edit_substitute(c: str, pos: str, sign: str) -> str:
    return f"concat(substring({c}, 1, {pos} - 1), {sign}, substring({c}, {pos} + 1))"


def edit_transpose(c: str, pos: str) -> str:
    """Swaps the sign at pos with the next; at the last place nothing changes."""
    return f"concat(substring({c}, 1, {pos} - 1), substring({c}, {pos} + 1, 1), substring({c}, {pos}, 1), substring({c}, {pos} + 2))"


def rewrite(c: str, table: list[tuple[str, str]], draw: str) -> str:
    """One rule of the table, drawn among those (either way) whose left side stands in c, at its first place."""
    rules = ", ".join(f"named_struct('f', '{a}', 't', '{b}')" for pair in table for a, b in (pair, pair[::-1]))
    fit = f"filter(array({rules}), r -> contains({c}, r.f))"
    # the rules that fit are bound once, the drawn one once more, each as the single element of an array
    drawn = f"transform(array({fit}), fit -> if(size(fit) = 0, null, fit[int({draw} % greatest(size(fit), 1))]))"
    put = f"concat(substring({c}, 1, locate(r.f, {c}) - 1), r.t, substring({c}, locate(r.f, {c}) + length(r.f)))"
    return f"transform({drawn}, r -> if(r is null, {c}, {put}))[0]"


def ocr_confuse(c: str, draw: str = "0") -> str:
    return rewrite(c, OCR, draw)


def phonetic_rewrite(c: str, draw: str = "0") -> str:
    return rewrite(c, SOUNDS, draw)


def _changed(c: str, digits: str) -> str:
    """c after the edit that the draws d.o (kind), d.p (place), d.s (sign) and d.r (rule) name; null stays null."""
    pos = f"int(1 + d.p % greatest(length({c}), 1))"
    sign = f"char(if({digits}, 48 + d.s % 10, 97 + d.s % 26))"
    return f"""CASE WHEN d.o % 6 = 0 THEN {edit_insert(c, pos, sign)} WHEN d.o % 6 = 1 THEN {edit_delete(c, pos)}
 WHEN d.o % 6 = 2 THEN {edit_substitute(c, pos, sign)} WHEN d.o % 6 = 3 THEN {edit_transpose(c, pos)} WHEN {digits} THEN {c}
 WHEN d.o % 6 = 4 THEN {ocr_confuse(c, 'd.r')} ELSE {phonetic_rewrite(c, 'd.r')} END"""


def corrupt_register(register: DataFrame, parties: int, rate: int, seed: str = "", most: int = 3) -> DataFrame:
    """register with `corrupted`: `rate` percent of the shared entities change at some parties, never at all of them.

    One to `most` edits per record, each on a drawn attribute: insert, delete, substitute, transpose, a look-alike
    form or a spelling of the same sound. Postcodes stay digits. Null values stay null.
    """
    key = f"'{seed}'"
    some = f"(shiftright(1 + {digest(key, chr(39) + 'm' + chr(39), 'entity')} % {2**parties - 2}, party - 1) & 1) = 1"
    hit = f"pmod(entity, {parties + 1}) = 0 AND {digest(key, chr(39) + 'c' + chr(39), 'entity')} % 100 < {rate} AND {some}"
    draws = ", ".join("named_struct(" + ", ".join(f"'{k}', {digest(key, chr(39) + k + chr(39), 'entity', 'party', str(i))}" for k in "aopsr") + ")" for i in range(1, most + 1))
    edits = f"slice(array({draws}), 1, int(if(corrupted, 1 + {digest(key, chr(39) + 'n' + chr(39), 'entity', 'party')} % {most}, 0)))"
    step = f"transform(record, (c, i) -> if(i = d.a % {len(QIDS)}, {_changed('c', f'i = {len(QIDS) - 1}')}, c))"
    rows = register.withColumn("corrupted", F.expr(f"coalesce({hit}, false)"))
    done = rows.withColumn("_record", F.expr(f"aggregate({edits}, array({', '.join(QIDS)}), (record, d) -> {step})"))
    return done.withColumns({q: F.col("_record")[i] for i, q in enumerate(QIDS)}).drop("_record")


def corruption_audit(clean: DataFrame, dirty: DataFrame, parties: int) -> DataFrame:
    """share of the shared entities with a changed record, fewest clean copies of one, and clean records that differ (none)."""
    shared = dirty.where(F.pmod("entity", F.lit(parties + 1)) == 0)
    per = shared.groupBy("entity").agg(F.max(F.col("corrupted").cast("int")).alias("dirty"), F.count_if(~F.col("corrupted")).alias("clean"))
    a = per.agg(F.round(F.sum("dirty") / F.count("*"), 6).alias("share"), F.min("clean").alias("min_clean"))
    both = clean.select("party", "rid", F.struct(*QIDS).alias("was")).join(dirty.select("party", "rid", "corrupted", F.struct(*QIDS).alias("now")), ["party", "rid"])
    b = both.agg(F.count_if(~F.col("corrupted") & ~F.col("was").eqNullSafe(F.col("now"))).alias("wrong"))
    return a.crossJoin(b)  # one row each
