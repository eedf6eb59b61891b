"""Functions for SQL users, and Python forms of native ones to compare with."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import IntegerType, LongType, StringType, StructField, StructType

#: SQL functions over arrays of bit places.
SQL_FUNCTIONS = {
    "bf_grams": "(v STRING, q INT) RETURNS ARRAY<STRING> RETURN if(length(v) >= q, array_distinct(transform(sequence(1, length(v) - q + 1), i -> substring(v, i, q))), array())",
    "bf_encode": "(v STRING, l INT, k INT) RETURNS ARRAY<INT> RETURN array_sort(array_distinct(flatten(transform(bf_grams(lower(trim(v)), 2), g -> transform(sequence(0, k - 1), i -> int(bigint(conv(substring(md5(concat('|', i, '|', g)), 1, 8), 16, 10)) % l))))))",
    "bf_segment": "(b ARRAY<INT>, piece INT, width INT) RETURNS ARRAY<INT> RETURN filter(b, p -> p div width = piece - 1)",
    "bf_dice": "(a ARRAY<INT>, b ARRAY<INT>) RETURNS DOUBLE RETURN try_divide(2 * size(array_intersect(a, b)), size(a) + size(b))",
}


def register_functions(spark: SparkSession) -> None:
    """bf_grams, bf_encode, bf_segment and bf_dice as temporary SQL functions: plain expressions, inlined in plans."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")


@pandas_udf(IntegerType())
def popcount_and(a: pd.Series, b: pd.Series) -> pd.Series:
    """Common bits of two words: a check on the native expression, not a replacement."""
    import numpy as np

    return pd.Series(np.bitwise_count(a.to_numpy() & b.to_numpy()).astype("int32"))


@pandas_udf(LongType())
def bf_union(words: pd.Series) -> int:
    """The OR of a group's words, as bit_or gives it."""
    import numpy as np

    return int(np.bitwise_or.reduce(words.to_numpy())) if len(words) else 0


@udtf(returnType=StructType([StructField("cand", StringType()), StructField("c", IntegerType())]))
class BlockCandidates:
    """Record sets of one block, built inside one call: an executor for blocks the guard has bounded.

    members: JSON of {party: [[rid, [word, ...]], ...]}; prefixes without a common bit leave early.
    """

    def eval(self, members: str, parties: int):
        import json

        held = json.loads(members)
        front = [([rid], words) for rid, words in held.get("1", [])]
        for j in range(2, parties + 1):
            front = [([*ids, rid], both) for ids, a in front for rid, b in held.get(str(j), []) if any(both := [x & y for x, y in zip(a, b, strict=True)])]
        for ids, words in front:
            yield ",".join(ids), sum(w.bit_count() for w in words)


def encode_in_pandas(register, spec):
    """party, rid, x_own by an Arrow batch encoder: the throughput reference for the native encoder."""
    qids, bits, k, q, secret = spec.qids, spec.bits, spec.hashes, spec.q, spec.secret

    def run(frames):
        import hashlib

        known: dict = {}
        for df in frames:
            ones = []
            for row in df[list(qids)].fillna("").itertuples(index=False):
                held: set = set()
                for v in row:
                    v = v.strip(" ").lower()
                    for i in range(len(v) - q + 1):
                        g = v[i : i + q]
                        if g not in known:
                            known[g] = {int(hashlib.md5(f"{secret}|{h}|{g}".encode()).hexdigest()[:8], 16) % bits for h in range(k)}
                        held |= known[g]
                ones.append(len(held))
            yield pd.DataFrame({"party": df["party"], "rid": df["rid"], "x_own": ones})

    return register.select("party", "rid", *qids).mapInPandas(run, "party int, rid string, x_own int")


def edit_similarity(a: str, b: str):
    """1 - levenshtein / longer length, on clear text."""
    return F.round(1 - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b)), 6)
