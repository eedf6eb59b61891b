"""Personal data: base patterns, then bootstrapped contextual extraction. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.llm.common import settle, shield

KINDS = ("email", "ip", "card", "phone", "context")
#: Runs are taken whole at once (possessive) and only where a search can start, so a long run costs linear time.
PATTERN = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
GUARD = {"email": "@", "ip": ".", "card": r"[0-9](?:[\x20-]?[0-9]){13}", "phone": r"\+[0-9]"}
_SPAN = "array<struct<start:int,kind:int,end:int,value:string>>"


def _luhn(digits: Column) -> Column:
    spots = F.sequence(F.lit(1), F.greatest(F.length(digits), F.lit(1)))

    def add(a: Column, i: Column) -> Column:
        d = F.substring(F.reverse(digits), i, F.lit(1)).cast("int")
        twice = F.when(d > 4, d * 2 - 9).otherwise(d * 2)
        return a + F.when(i % 2 == 0, twice).otherwise(d)

    return F.aggregate(spots, F.lit(0), add) % 10 == 0


def _holds(kind: str, value: Column) -> Column:
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(value, r"\."), lambda p: (F.length(F.regexp_replace(p, "^0+", "")) <= 3) & (F.coalesce(F.regexp_replace(p, "^0+(?=.)", "").try_cast("int"), F.lit(999)) <= 255))
    if kind == "card":
        return F.when(F.length(digits).between(14, 19), _luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(digits).between(10, 15)
    return F.lit(True)


#: Matches that are placed in one fold; longer runs of matches are folded in parts, so the time stays near linear.
_FOLD = 256


def _located(text: Column, kind: str) -> Column:
    """Spans of one kind: what stands between the matches gives their places."""
    found, between = F.regexp_extract_all(text, F.lit(PATTERN[kind]), F.lit(0)), F.split(text, PATTERN[kind], -1)
    step = F.zip_with(found, F.slice(between, F.lit(1), F.size(found)), lambda m, b: F.struct(m.alias("m"), F.length(b).alias("b")))
    # arrays of one element bind what is used more than once
    parts = F.transform(F.array(step), lambda s: F.transform(F.sequence(F.lit(0), F.floor(F.size(s) / _FOLD).cast("int")), lambda c: F.slice(s, c * _FOLD + 1, F.lit(_FOLD))))[0]
    begun = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<at:int,part:array<struct<m:string,b:int>>>>").alias("out"))

    def open_(a: Column, part: Column) -> Column:
        wide = F.aggregate(part, F.lit(0), lambda n, s: n + s["b"] + F.length(s["m"]))
        return F.struct((a["at"] + wide).alias("at"), F.concat(a["out"], F.array(F.struct(a["at"].alias("at"), part.alias("part")))).alias("out"))

    def add(a: Column, s: Column) -> Column:
        at = a["at"] + s["b"]
        end = at + F.length(s["m"])
        one = F.array(F.struct(at.alias("start"), F.lit(KINDS.index(kind)).alias("kind"), end.alias("end"), s["m"].alias("value")))
        return F.struct(end.alias("at"), F.concat(a["out"], one).alias("out"))

    placed = F.aggregate(parts, begun, open_, lambda a: a["out"])
    spans = F.flatten(F.transform(placed, lambda p: F.aggregate(p["part"], F.struct(p["at"].alias("at"), F.array().cast(_SPAN).alias("out")), add, lambda a: a["out"])))
    guard = F.contains(text, F.lit(GUARD[kind])) if kind in ("email", "ip") else text.rlike(GUARD[kind])
    return F.when(guard, F.filter(spans, lambda s: _holds(kind, s["value"]))).otherwise(F.array().cast(_SPAN))


#: Forms that have a check of their own; what fails it is no identifier, whatever stands before it.
_CHECKED = {"card": "^[0-9]{14,19}$", "ip": r"^[0-9]+(?:\.[0-9]+){3}$"}
#: An unknown identifier: a word of seven characters or more with two digits.
_ITEM = r"(?<![A-Za-z0-9@._+/-])(?=[A-Za-z@._+/-]*+[0-9][A-Za-z@._+/-]*+[0-9])[A-Za-z0-9@._+/-]{7,}+(?![A-Za-z0-9@._+/-])"
PATTERN["context"], GUARD["context"] = _ITEM, "[0-9]"
_W, _S = r"[\p{L}\p{N}_]", r"[^\p{L}\p{N}_]"
#: Contexts of an item: one to three words before it, one or two after it, with the signs between, as far as the window
#: shows them whole. A word or gap that is cut by the window is no context: the window is part of what a pattern is.
_CONTEXTS = {f"l{k}": rf"(?<!{_W})(?:{_W}++{_S}++){{{k}}}$" for k in (1, 2, 3)} | {f"r{k}": rf"^(?:{_S}++{_W}++){{{k}}}" for k in (1, 2)}
_WINDOW = 160


#: Signs of a piece of text: what looks around a place in a long text touches a few pieces, not the text.
_PIECE = 1024


def _pieces(text: Column) -> Column:
    """The text in pieces of _PIECE code points; cut in two steps, since a cut reads all that stands before it."""
    cut = lambda t, n: F.transform(F.sequence(F.lit(0), F.floor(F.greatest(F.length(t) - 1, F.lit(0)) / n).cast("int")), lambda i: F.substring(t, i * n + 1, F.lit(n)))
    return F.flatten(F.transform(cut(text, _PIECE * 64), lambda t: cut(t, _PIECE)))


def _at(pieces: Column, i: Column) -> Column:
    return F.coalesce(F.get(pieces, i), F.lit(""))


def _around(pieces: Column, m: Column) -> tuple[Column, Column]:
    """What stands before and after a span, _WINDOW signs at most."""
    i, j = F.floor(m["start"] / _PIECE).cast("int"), F.floor(m["end"] / _PIECE).cast("int")
    before = F.concat(_at(pieces, i - 1), F.substring(_at(pieces, i), F.lit(1), m["start"] - i * _PIECE))
    after = F.substring(F.concat(F.substring(_at(pieces, j), m["end"] - j * _PIECE + 1, F.lit(_PIECE)), _at(pieces, j + 1)), 1, _WINDOW)
    return F.lower(F.right(before, F.lit(_WINDOW))), F.lower(after)


def _contexts(before: Column, after: Column) -> Column:
    """The contexts of what stands between, each marked with its side and length."""
    found = ((k, F.regexp_replace(F.regexp_extract(before if k[0] == "l" else after, p, 0), r"\s+", " ")) for k, p in _CONTEXTS.items())
    return F.array_compact(F.array(*(F.when(c != "", F.concat(F.lit(k + ":"), c)) for k, c in found)))


def _items(text: Column, base: Column) -> Column:
    """Base spans, and the identifier-like words that overlap none: start, kind, end, value. Piece by piece, so that a
    long text does not compare all words with all spans."""
    starts = F.sequence(F.lit(0), F.floor(F.length(text) / _PIECE).cast("int"))

    def free(words: Column) -> Column:
        def of(i: Column) -> Column:
            here = F.filter(words, lambda m: F.floor(m["start"] / _PIECE) == i)
            near = F.transform(F.array(here), lambda h: F.filter(base, lambda b: (F.size(h) > 0) & (b["start"] < F.array_max(F.transform(h, lambda m: m["end"]))) & (b["end"] > i * _PIECE)))
            return F.transform(near, lambda n: F.filter(here, lambda m: ~F.exists(n, lambda b: (b["start"] < m["end"]) & (m["start"] < b["end"]))))[0]

        return F.flatten(F.transform(starts, of))

    return F.concat(base, F.when(F.size(base) == 0, _located(text, "context")).otherwise(F.transform(F.array(_located(text, "context")), free)[0]))


def patterns(items: DataFrame, counts: DataFrame, rounds: int = 3, least: float = 0.6, support: int = 5) -> DataFrame:
    """(context, score) of the trusted lexical patterns of items (context, item, class, seed) and word counts (word, n).

    Base entities are the seeds (1), what fails its check is none (0), all else is unknown (null). Patterns and
    instance classes (alphabet and length) score each other over the rounds: a class by its seeds among its checked
    items, drawn to the share of seeds among all checked items, then by its best pattern; a pattern by the belief in
    its items over the count of its rarest word, which no context exceeds: words that mostly stand elsewhere lend no
    trust. A pattern needs `support` different items.
    """
    kinds = settle(items.groupBy("context", "class", "seed").agg(F.count("*").alias("n")))
    per_class = settle(items.where("first").groupBy("class").agg(F.count_if(F.col("seed") == 1).alias("good"), F.count("seed").alias("known")))
    whole = per_class.agg((F.coalesce(F.sum("good"), F.lit(0)) / (F.coalesce(F.sum("known"), F.lit(0)) + 1)).alias("share")).first()["share"]
    belief = per_class.select("class", ((F.col("good") + 2 * F.lit(whole)) / (F.col("known") + 2)).alias("belief"))
    enough = items.groupBy("context").agg(F.countDistinct("item").alias("different")).where(F.col("different") >= support).select("context")
    parts = enough.select("context", F.explode(F.filter(F.split(F.substring("context", 4, 1 << 20), _S + "+"), lambda w: w != "")).alias("word"))
    rarest = settle(parts.join(counts, "word").groupBy("context").agg(F.min("n").alias("of")))
    kinds = settle(kinds.join(rarest, "context"))
    score = None
    for _ in range(rounds):
        one = F.coalesce(F.col("seed").cast("double"), "belief")
        score = kinds.join(belief, "class").groupBy("context").agg((F.sum(one * F.col("n")) / F.greatest(F.max("of"), F.sum("n"))).alias("score"))
        score = settle(score.where(F.col("score") >= least))
        belief = kinds.where("seed is null").join(score, "context").groupBy("class").agg(F.max("score").alias("belief")).union(belief).groupBy("class").agg(F.max("belief").alias("belief"))
        belief = settle(belief)
    return score


def find(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text and any other columns) with `base` and `spans` (start, kind, end, value; code points, end
    exclusive), sorted. Other columns must not be named base, spans or with a leading underscore; see `shield`.

    Null text is empty. The base kinds are found row by row. Base spans and identifier-like words with the contexts
    around form the pattern graph, over all documents; every unknown word in a trusted context is of kind `context`.
    Repeated rows are found each; rows with one id and text share their context spans.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    hash_ = F.xxhash64(text)
    base = F.array_sort(F.concat(*(_located(text, k) for k in KINDS[:4])))
    rows = docs.where(text.rlike("[0-9]")).select(F.col("doc_id").alias("_d"), hash_.alias("_h"), text.alias("text"), base.alias("base"), _pieces(text).alias("pieces"))
    rows = rows.select("_d", "_h", "pieces", _items(F.col("text"), F.col("base")).alias("items"))
    around = F.transform("items", lambda m: F.struct(m.alias("m"), *(c.alias(n) for c, n in zip(_around(F.col("pieces"), m), ("before", "after"), strict=True))))
    rows = rows.select("_d", "_h", F.explode(around).alias("a")).select("_d", "_h", "a.m", "a.before", "a.after")
    value = F.col("m.value")
    kind = F.when(value.rlike("^[0-9]+$"), "d").when(value.rlike("^(?:[0-9a-f]+|[0-9A-F]+)$"), "h").when(value.rlike("^[A-Za-z0-9]+$"), "a").otherwise("s")
    seed = F.when(F.col("m.kind") < 4, 1).when(value.rlike("|".join(_CHECKED.values())), 0)
    items = rows.select("_d", "_h", "m", F.concat(kind, F.length(value)).alias("class"), seed.alias("seed"), F.posexplode(_contexts(F.col("before"), F.col("after"))).alias("i", "context"))
    items = settle(items)
    counts = docs.select(F.explode(F.split(F.lower(text), _S + "+")).alias("word")).groupBy("word").agg(F.count("*").alias("n"))
    trusted = patterns(items.select("context", F.col("m.value").alias("item"), "class", "seed", (F.col("i") == 0).alias("first")), counts)
    more = items.where("seed is null").join(trusted.select("context"), "context", "left_semi").groupBy("_d", "_h").agg(F.collect_set("m").alias("more"))
    out = docs.withColumn("base", base).withColumn("_hash", hash_)
    out = out.join(more, F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("_hash") == F.col("_h")), "left")
    return out.withColumn("spans", F.array_sort(F.concat("base", F.coalesce("more", F.array().cast(_SPAN))))).drop("more", "_hash", "_d", "_h")


def _listed(spans: str) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def digest(docs: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans of every row of docs; null text is empty, an empty table gives no rows."""
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long")
    found = find(docs.select("doc_id", "text"))
    return found.select("doc_id", *(count(k).alias(f"n_{KINDS[k]}") for k in range(4)), F.sha2(_listed("base"), 256).alias("base_sha256"), _listed("spans").alias("spans"))


def redact(docs: DataFrame) -> DataFrame:
    """docs whose text has each span replaced by its kind in brackets; columns as they were, whatever their names.

    Spans that overlap are one stretch with the names of all their kinds. A null text stays null.
    """
    rows, back = shield(docs, "doc_id", "text")
    found = find(rows)
    names = F.array(*(F.lit(f"[{k.upper()}]") for k in KINDS))
    text = F.coalesce(F.col("text"), F.lit(""))

    def piece(t: Column, i: Column) -> Column:
        first = i * _PIECE
        here = F.filter("spans", lambda s: (s["start"] < first + _PIECE) & (s["end"] > first))

        def add(a: Column, s: Column) -> Column:
            keep = F.substring(t, a["at"] + 1, F.greatest(s["start"] - first - a["at"], F.lit(0)))
            name = F.when(s["start"] >= first, F.element_at(names, s["kind"] + 1)).otherwise("")  # named where it starts
            return F.struct(F.greatest(a["at"], s["end"] - first).alias("at"), F.concat(a["out"], keep, name).alias("out"))

        return F.aggregate(here, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), add, lambda a: F.concat(a["out"], F.substring(t, a["at"] + 1, F.lit(_PIECE))))

    done = F.array_join(F.transform(_pieces(text), piece), "")
    return found.withColumn("text", F.when(F.size("spans") > 0, done).otherwise(F.col("text"))).select(*back)
