"""Best-fit packing in rounds: partitions pack, nearly full bins leave, underfull bins merge as items."""

from __future__ import annotations

import bisect
import functools
import itertools
import re
import struct
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringlink.llm.common import KEPT, lean, settle

LIMIT = 4096
_PIECE = "struct<doc_id:bigint,piece:int,start:bigint,length:bigint,ids_crc32:bigint>"
BIN = f"total long, done boolean, pieces array<{_PIECE}>"
_ARROW = pa.list_(pa.struct([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())]))
_ODD = "\x1c\x1d\x1e\x1f"  # white space to Python, not to the tokenizer
_TAIL = re.compile(r"([^\W\d_]+)([.,!?;:#$%&*|]*)")
#: How the tokenizer writes a byte: as its own sign where that is printable, else as one of those from 256 on.
_PRINTED = [*range(33, 127), *range(161, 173), *range(174, 256)]
_BYTES = {b: chr(b) for b in _PRINTED} | {b: chr(256 + k) for k, b in enumerate(sorted({*range(256)} - {*_PRINTED}))}


class Ids(dict):
    """White-space separated chunk -> its ids as little-endian bytes; chunks are independent for this tokenizer."""

    def __init__(self, path: str, most: int = 600_000) -> None:
        from tokenizers import Tokenizer

        self.tokenizer, self.most, self.parts = Tokenizer.from_file(path), most, {}
        self.model = self.tokenizer.model

    def __missing__(self, chunk: str) -> bytes:
        if len(self) >= self.most:
            self.clear()
        tail = _TAIL.fullmatch(chunk)  # the tokenizer parts a word from the signs after it
        out = self[chunk] = self.part(tail[1]) + self.part(tail[2]) if tail and tail[1].lower().isalpha() else self.encode(chunk)
        return out

    def part(self, word: str) -> bytes:
        word = word.lower() if word.isascii() else word  # as the tokenizer does
        if word not in self.parts:
            if len(self.parts) >= self.most:
                self.parts.clear()
            self.parts[word] = self.letters(word) if word.isalpha() and max(word) < "\u0100" else self.encode(word)
        return self.parts[word]

    def letters(self, word: str) -> bytes:
        """A word of Latin-1 letters: it has one form, one lower case and no place to part it, so the model takes it as it is."""
        found = [t.id for t in self.model.tokenize(word.lower().encode().decode("latin-1").translate(_BYTES))]
        return struct.pack(f"<{len(found)}I", *found)

    def encode(self, text: str) -> bytes:
        return b"".join(i.to_bytes(4, "little") for i in self.tokenizer.encode(text, add_special_tokens=False).ids)

    def of(self, text: str) -> bytes:
        if any(c in text for c in _ODD):
            return self.encode(text)
        return b"".join(map(self.__getitem__, text.split()))


@functools.lru_cache
def _ids(path: str) -> Ids:
    """One cache a Python worker: a function of this module goes to workers by name, so all their tasks share it."""
    return Ids(path)


KEPT.append(_ids.cache_clear)

def _best_fit(items: list, limit: int) -> list[list]:
    """Best-fit decreasing. items: (total, key, pieces); gives [total, pieces] bins."""
    free: list[tuple[int, int]] = []  # (room, bin), sorted
    bins: list[list] = []
    for total, _, pieces in sorted(items, key=lambda x: (-x[0], x[1])):
        at = bisect.bisect_left(free, (total, -1))
        if at < len(free):
            room, k = free.pop(at)
            bins[k][0] += total
            bins[k][1].extend(pieces)
            room -= total
        else:
            k, room = len(bins), limit - total
            bins.append([total, list(pieces)])
        if room > 0:
            bisect.insort(free, (room, k))
    return bins


def _batch(bins, limit: int, slack: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([b[0] for b in bins], pa.int64()), pa.array([b[0] >= limit - slack for b in bins], pa.bool_()), pa.array([b[1] for b in bins], _ARROW)], names=["total", "done", "pieces"])


def _rows(batch: pa.RecordBatch, step: int = 256):
    """doc_id and text of each row; only `step` texts at a time stand in memory as strings too."""
    for at in range(0, batch.num_rows, step):
        some = batch.slice(at, step)
        yield from zip(some.column("doc_id").to_pylist(), some.column("text").to_pylist(), strict=True)


def _first(path: str, limit: int, end_id: int, slack: int, hold: int = 50_000):
    def packed(batches):
        ids = _ids(path)
        end, items, keys = end_id.to_bytes(4, "little"), [], itertools.count()
        for batch in batches:
            for doc, text in _rows(batch):
                raw = ids.of(text or "") + end
                for k, at in enumerate(range(0, len(raw), 4 * limit)):
                    part = raw[at : at + 4 * limit]
                    items.append((len(part) // 4, next(keys), [{"doc_id": doc, "piece": k, "start": at // 4, "length": len(part) // 4, "ids_crc32": zlib.crc32(part)}]))
            if len(items) >= hold:
                yield _batch(_best_fit(items, limit), limit, slack)
                items = []
        yield _batch(_best_fit(items, limit), limit, slack)

    return packed


def _again(limit: int, slack: int, hold: int = 50_000):
    def packed(batches):
        items = []
        for batch in batches:
            for total, pieces in zip(batch.column("total").to_pylist(), batch.column("pieces").to_pylist(), strict=True):
                items.append((total, (pieces[0]["doc_id"] or 0, pieces[0]["piece"]), pieces))
            if len(items) >= hold:
                yield _batch(_best_fit(items, limit), limit, slack)
                items = []
        yield _batch(_best_fit(items, limit), limit, slack)

    return packed


def pack(docs: DataFrame, tokenizer_path: str, limit: int = LIMIT, end_id: int = 1) -> DataFrame:
    """(sequence_id, total, pieces) of docs (doc_id, text).

    Null text is empty, so a document of one end id. Longer documents are cut into pieces of `limit` ids. Each
    partition packs its own pieces best-fit; bins within the slack of full leave, the others are items of the
    next round on an eighth of the partitions, down to one task once 50,000 bins or fewer are left. Each round
    is settled in the shared folder; a round holds 50,000 items in memory at most. Repeated rows are packed each.
    """
    all_ = settle(docs.select("doc_id", "text").mapInArrow(lean(_first(tokenizer_path, limit, end_id, limit // 64), drop=False), BIN))
    parts = [all_.where("done")]
    under = all_.where("not done")
    left = under.count()
    slack = limit // 64
    while left:
        tasks = max(1, left // 20_000)
        slack = min(limit, slack * 4) if tasks > 1 else limit
        key = F.xxhash64(F.col("pieces")[0]["doc_id"], F.col("pieces")[0]["piece"])
        bins = settle(under.repartition(tasks, key).mapInArrow(lean(_again(limit, slack), drop=False), BIN))
        parts.append(bins.where("done"))
        under, was = bins.where("not done"), left
        left = under.count()
        if left >= was:
            parts.append(under)
            break
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select(F.monotonically_increasing_id().alias("sequence_id"), "total", "pieces")


def digest(docs: DataFrame) -> DataFrame:
    import public_tokenizers

    bins = pack(docs, public_tokenizers.path("word_bpe_49k.json"))
    placed = bins.select("sequence_id", F.posexplode("pieces").alias("at", "p"), "pieces")
    offset = F.aggregate(F.slice("pieces", F.lit(1), F.col("at")), F.lit(0).cast("long"), lambda a, p: a + p["length"])
    return placed.select("p.doc_id", "p.piece", "p.start", "p.length", "p.ids_crc32", "sequence_id", offset.alias("offset"))
