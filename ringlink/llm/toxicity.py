"""Toxicity: noisy-channel deobfuscation of whole texts, then a score learned from labels."""

from __future__ import annotations

import itertools
import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: What a written sign may stand for.
LEET = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t"}
ALPHABET = "^abcdefghijklmnopqrstuvwxyz"
_WORD = re.compile(r"[^\W_]+")
_ODD = re.compile(r"[a-z]*[0-9@$!|+][a-z0-9@$!|+]*[a-z][a-z0-9@$!|+]*|[a-z]+[0-9@$!|+][a-z0-9@$!|+]*|\w*(\w)\1\1\w*")
_SPACED = re.compile(r"(?<!\w)[a-z0-9@$!|+](?:[ .\-_*][a-z0-9@$!|+]){3,}+(?!\w)")


def counted(texts) -> np.ndarray:
    """Character trigram counts of the texts over ^a-z, ^ standing for all that is no letter."""
    code = np.zeros(256, np.int64)
    code[97:123] = np.arange(1, 27)
    code[65:91] = np.arange(1, 27)
    out = np.zeros(27**3, np.int64)
    for t in texts:
        c = code[np.frombuffer(("  " + t + " ").encode("utf-8", "replace"), np.uint8)]
        out += np.bincount(c[:-2] * 729 + c[1:-1] * 27 + c[2:], minlength=27**3)
    return out


def decode(token: str, cost: np.ndarray, gaps: bool = False) -> str:
    """Viterbi over the lattice of a token: a sign gives one of its letters or, repeated, nothing.

    With `gaps` blanks in the token are places where a word may end, at the model's cost of a boundary. Time is linear
    in the token: a column holds a state for each pair of letters at most, and points back to the one before it.
    """
    column = {(0, 0): (0.0, None)}  # state -> cost, (state before, letter) chain
    before = ""
    for ch in token:
        if gaps and ch == " ":
            new = dict(column)
            for (a, b), (w, back) in column.items():
                if b and ((b, 0) not in new or w + cost[a, b, 0] < new[b, 0][0]):
                    new[b, 0] = (w + cost[a, b, 0], (back, " "))
            column = new
            continue
        letters = LEET.get(ch, ch if "a" <= ch <= "z" else "")
        if not letters:
            before = ch
            continue
        new = {}
        for (a, b), (w, back) in column.items():
            options = [(ord(x) - 96, x, 0.0 if x == ch else 0.7) for x in letters]
            if ch == before:
                options.append((None, "", 0.5))
            for k, x, noise in options:
                key, v = ((a, b), w + noise) if k is None else ((b, k), w + noise + cost[a, b, k])
                if key not in new or v < new[key][0]:
                    new[key] = (v, (back, x) if x else back)
        column, before = new, ch
    _, back = min(((w + cost[a, b, 0], back) for (a, b), (w, back) in column.items()), key=lambda x: x[0])
    out = []
    while back is not None:
        back, x = back
        out.append(x)
    return "".join(reversed(out))


def _shapes() -> bytes:
    """Byte -> x where a spaced-out word may have it, s where it may part two of them, else o."""
    return bytes(120 if chr(c) in "abcdefghijklmnopqrstuvwxyz0123456789@$!|+" else 115 if chr(c) in " .-_*" else 111 for c in range(256))


_SHAPE = _shapes()


class Restored(dict):
    """Token between white space -> its words and what its obfuscated stretches decode to."""

    def __init__(self, cost: np.ndarray, most: int = 200_000) -> None:
        self.cost, self.most = cost, most

    def __missing__(self, token: str) -> tuple:
        if len(self) >= self.most:
            self.clear()
        out = self[token] = (*_WORD.findall(token), *(decode(m.group(), self.cost) for m in _ODD.finditer(token)))
        return out

    def spaced(self, raw: str) -> list[str]:
        """The words of a run of single signs, boundaries as the model places them."""
        return decode(re.sub(r"[ .\-_*]", " ", raw), self.cost, gaps=True).split()

    def words(self, text: str | None) -> set:
        """The distinct words of a whole text, with what each obfuscated stretch decodes to besides."""
        low = (text or "").lower()
        out = set(itertools.chain.from_iterable(map(self.__getitem__, set(low.split()))))
        if b"sxsxsx" in low.encode("utf-8", "replace").translate(_SHAPE):  # no spaced-out word without it
            for m in _SPACED.finditer(low):
                out.update(self.spaced(m.group()))
        return out


def held_out():
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) == 1, F.lit(False))


def features(word: str) -> tuple:
    """A word and its beginnings of four to six letters."""
    return (word, *(word[:k] + "~" for k in (4, 5, 6) if len(word) > k)) if len(word) > 2 else ()


def evidence(words: set, strong: dict, marked: frozenset, rates: tuple[float, float], heads: set | None = None) -> float:
    """Log odds of a text: that of its strong words, or of how dense its words with marked beginnings are, whichever is higher."""
    heads = {f[:3] for f in (*strong, *marked)} if heads is None else heads
    near = [w for w in words if w[:3] in heads]
    hit = {f for w in near for f in features(w) if f in strong}
    k = sum(1 for w in near if any(f in marked for f in features(w)))
    bad, good = rates
    dense = k * math.log(bad / good) - len(words) * (bad - good) if k else 0.0
    return BIAS + max(sum(strong[f] for f in hit), dense)


BIAS = -4.0


def score(docs: DataFrame, labels: DataFrame, sample: int = 20_000, least: int = 3, share: float = 0.03) -> DataFrame:
    """doc_id, held_out, score, predicted of docs (doc_id, text), one row each.

    The channel's language model counts all documents. The lexicon is learned from at most `sample` labelled
    training rows, chosen by hash: features in at least `least` and a `share` of the toxic texts. Those that clean
    texts hardly have count by presence; those eight times as frequent among toxic texts' words count by density,
    since a long clean text may hold one by chance. Null and empty texts get the score of no evidence; without labels
    every score is that.
    """
    d = docs.select("doc_id", "text", held_out().alias("held_out"))

    def counting(batches):
        total = np.zeros(27**3, np.int64)
        for b in batches:
            total += counted(t or "" for t in b.column("text").to_pylist())
        at = np.nonzero(total)[0]
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at], pa.int64())], names=["gram", "n"])

    grams = d.select("text").mapInArrow(counting, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))
    n3 = np.zeros(27**3)
    for r in grams.collect():  # 27^3 rows at most
        n3[r["gram"]] = r["n"]
    n3 = n3.reshape(27, 27, 27)
    n1 = n3.sum((0, 1)) + 1
    p = (n3 + 5 * n1 / n1.sum()) / (n3.sum(2, keepdims=True) + 5)
    cost = -np.log(p)
    chosen = labels.where(F.col("toxic").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id")).limit(sample)
    train = d.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "toxic")  # sample rows at most

    def learning(batches):
        """Per feature and class: texts that have it, distinct words that carry it; "" counts texts and words."""
        restored = Restored(cost)
        texts, carriers = (Counter(), Counter()), (Counter(), Counter())
        for b in batches:
            for t, x in zip(b.column("text").to_pylist(), b.column("toxic").to_pylist(), strict=True):
                words, y = restored.words(t), int(x > 0)
                found = Counter(f for w in words for f in features(w))
                texts[y].update(found.keys())
                carriers[y].update(found)
                texts[y][""] += 1
                carriers[y][""] += len(words)
        keys = list(set(texts[0]) | set(texts[1]))
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), *(pa.array([c[y][k] for k in keys], pa.int64()) for c in (texts, carriers) for y in (1, 0))], names=["f", "bad", "good", "bad_words", "good_words"])

    known = train.mapInArrow(learning, "f string, bad long, good long, bad_words long, good_words long").groupBy("f").agg(*(F.sum(c).alias(c) for c in ("bad", "good", "bad_words", "good_words"))).where((F.col("f") == "") | (F.col("bad") >= least))
    rows = {r["f"]: tuple(r)[1:] for r in known.collect()}  # words of the sample's toxic texts at most
    bad, good, bad_words, good_words = rows.pop("", (0, 0, 0, 0))
    strong, marked = {}, set()
    for f, (a, b, aw, bw) in rows.items():
        if a < share * bad:
            continue
        weight = math.log((a + 0.1) / (bad + 1)) - math.log((b + 0.1) / (good + 1))
        if weight > 5:
            strong[f] = weight
        elif (aw / bad_words) / ((bw + 1) / (good_words + 1)) >= 8:
            marked.add(f)
    marked = frozenset(marked)

    def density(batches):
        """Distinct words and those with a marked beginning, of toxic texts that have one and of clean texts."""
        restored = Restored(cost)
        out = [0, 0, 0, 0]
        for b in batches:
            for t, x in zip(b.column("text").to_pylist(), b.column("toxic").to_pylist(), strict=True):
                words = restored.words(t)
                k = sum(1 for w in words if any(f in marked for f in features(w)))
                if x <= 0 or k and not any(f in strong for w in words for f in features(w)):
                    out[2 * (x <= 0)] += k
                    out[2 * (x <= 0) + 1] += len(words)
        yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in out], names=["a", "b", "c", "d"])

    a, b, c, e = train.mapInArrow(density, "a long, b long, c long, d long").agg(*(F.coalesce(F.sum(x), F.lit(0)) for x in "abcd")).first() if marked else (0, 0, 0, 0)
    clean = (c + 0.5) / (e + 1)
    rates = (max((a + 0.5) / (b + 1), clean), clean)

    heads = {f[:3] for f in (*strong, *marked)}

    def scoring(batches):
        restored = Restored(cost)
        for b in batches:
            odds = (evidence(restored.words(t), strong, marked, rates, heads) for t in b.column("text").to_pylist())
            out = [1 / (1 + math.exp(-max(-30.0, min(30.0, x)))) for x in odds]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(out, pa.float64()), pa.array([int(x >= 0.7) for x in out], pa.int32())], names=["doc_id", "held_out", "score", "predicted"])

    return d.mapInArrow(scoring, "doc_id long, held_out boolean, score double, predicted int")
