"""Record sets of a block whose similarity reaches a threshold, found pairs first.

A chain of joins over blocks multiplies every prefix by the whole block. Here each record of the first party meets the
block's others once; only those that can be in a set with it are put together, by what the pairs have in common at most.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.plans.physical import small

#: Records of the first party, and of each further one, that meet in one tile of a block.
FIRST, OTHERS = 1024, 16384
#: Blocks up to which their sizes are broadcast.
BLOCKS = 200_000
#: Tasks to one shuffle partition, so that large tiles do not end last.
TASKS = 3
#: Prefixes times records compared at once, and sets in one batch.
CELLS, ROWS = 1 << 18, 1 << 15

KINDS = ("dice", "overlap", "cosine")


def _tiled(rows: DataFrame, p: int) -> DataFrame:
    """rows of the blocks that all parties have, with `tile`: each set of a block meets in exactly one of its tiles.

    A party's records are dealt by digest; a record is copied to every tile that its own part is in.
    """
    sizes = rows.groupBy("bkv").agg(*(F.count_if(F.col("party") == j).alias(f"g{j}") for j in range(1, p + 1)))
    sizes = sizes.where(reduce(lambda a, b: a & b, (F.col(f"g{j}") > 0 for j in range(1, p + 1))))
    parts = [F.ceil(F.col(f"g{j}") / F.lit(FIRST if j == 1 else OTHERS)).cast("long").alias(f"g{j}") for j in range(1, p + 1)]
    met = rows.where(F.col("party").between(1, p)).join(small(sizes.select("bkv", *parts), BLOCKS), "bkv")

    def by_party(of) -> Column:
        return reduce(lambda c, j: c.when(F.col("party") == j, of(j)), range(2, p + 1), F.when(F.col("party") == 1, of(1)))

    before = by_party(lambda j: reduce(lambda a, b: a * b, (F.col(f"g{m}") for m in range(1, j)), F.lit(1).cast("long")))
    every = reduce(lambda a, b: a * b, (F.col(f"g{j}") for j in range(1, p + 1)))
    dealt = met.select(*rows.columns, before.alias("_low"), by_party(lambda j: F.col(f"g{j}")).alias("_own"), every.alias("_all"))
    dealt = dealt.withColumn("_part", F.pmod(F.xxhash64("rid"), F.col("_own"))).withColumn("_e", F.explode(F.expr("sequence(0L, _all div _own - 1)")))
    return dealt.select(*rows.columns, F.expr("_e % _low + _part * _low + (_e div _low) * _low * _own").alias("tile"))


def sets_reaching(rows: DataFrame, p: int, words: list[str], threshold: tuple[int, int], kind: str = "dice", pieces: int = 1, labels: tuple[str, ...] = ("rid",), prune: tuple[int, int] | None = None) -> DataFrame:
    """<label>1..<label>p, c1..c<pieces>, x1..xp of the sets, one record of each party in one block, that reach `threshold`.

    rows: party, bkv, rid, words, x_own. ch is what the set has in common in the h-th of equal pieces of the words. prune:
    only the sets that every piece's holder keeps by the filter `prefix` of `compare.partial_counts` (needs p pieces).
    The number of partitions is given, as candidates say more than bytes.
    """
    n = TASKS * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    held = _tiled(rows.select("party", "bkv", *dict.fromkeys(("rid", *labels)), *words, F.col("x_own").cast("int").alias("x_own")), p)
    ready = held.repartition(n, "bkv", "tile").sortWithinPartitions("bkv", "tile")
    schema = ", ".join([f"{name}{j} string" for name in labels for j in range(1, p + 1)] + [f"c{h} long" for h in range(1, pieces + 1)] + [f"x{j} long" for j in range(1, p + 1)])

    def run(batches):
        return _partition(batches, p, words, threshold, kind, pieces, labels, prune)

    return ready.mapInArrow(run, schema)


def _partition(batches, p, words, threshold, kind, pieces, labels, prune):
    """The sets of a partition's tiles; batches come sorted by block and tile, a tile at a time is in memory."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    held, last = [], None
    for batch in batches:
        if not batch.num_rows:
            continue
        block, tile = batch.column("bkv"), batch.column("tile")
        new = pc.or_(pc.not_equal(block[1:], block[:-1]), pc.not_equal(tile[1:], tile[:-1])).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(new) + 1).tolist(), batch.num_rows]
        for at, end in zip(cuts, cuts[1:], strict=False):
            key = (block[at].as_py(), tile[at].as_py())
            if key != last and held:
                yield from _tile(pa.Table.from_batches(held), p, words, threshold, kind, pieces, labels, prune)
                held = []
            held.append(batch.slice(at, end - at))
            last = key
    if held:
        yield from _tile(pa.Table.from_batches(held), p, words, threshold, kind, pieces, labels, prune)


def _bits(words):
    """Bits set in each column of a matrix of words."""
    import numpy as np

    out = np.zeros(words.shape[1], np.int32)
    for row in words:
        out += np.bitwise_count(row)
    return out


def _measure(kind, threshold, p):
    """(reach, joined, total): sets with c common bits reach the threshold if reach(c) >= total(sizes joined one by one)."""
    import numpy as np

    num, den = threshold
    if kind == "dice":
        return (lambda c: den * p * c), np.add, (lambda s: num * s)
    if kind == "overlap":
        return (lambda c: den * c), np.minimum, (lambda s: num * s)
    if kind == "cosine":  # the p-th powers; what rounding may lose is left for the exact test of whole sets
        return (lambda c: (den * np.asarray(c, np.float64)) ** p), np.multiply, (lambda s: (1 - 1e-9) * float(num) ** p * s)
    raise ValueError(f"unknown similarity {kind}")


def _tile(table, p, words, threshold, kind, pieces, labels, prune):
    import numpy as np
    import pyarrow as pa

    table = table.combine_chunks()
    party, size = table["party"].to_numpy(), table["x_own"].to_numpy()
    # no similarity where a divisor is 0; larger filters last, so that memory is read in order
    held = [np.flatnonzero((party == j) & ((size > 0) | (kind == "dice"))) for j in range(1, p + 1)]
    if not all(map(len, held)):
        return
    columns = [table[w].to_numpy().view(np.uint64) for w in words]
    filters = [np.stack([c[at] for c in columns]) for at in held]
    sizes = [size[at] for at in held]
    names = {label: table[label].combine_chunks() for label in labels}

    def batch(found):
        at = [np.concatenate(rows) for rows in zip(*found, strict=True)]
        parts = [f[:, rows] for f, rows in zip(filters, at, strict=True)]
        if prune is not None:
            keep = _kept(parts, p, prune)
            at, parts = [rows[keep] for rows in at], [f[:, keep] for f in parts]
        both, w = reduce(np.bitwise_and, parts), len(words) // pieces
        named = [names[label].take(pa.array(held[j][at[j]])) for label in labels for j in range(p)]
        named = [n.combine_chunks() if isinstance(n, pa.ChunkedArray) else n for n in named]
        common = [pa.array(_bits(both[h * w : (h + 1) * w]).astype(np.int64)) for h in range(pieces)]
        own = [pa.array(sizes[j][at[j]].astype(np.int64)) for j in range(p)]
        heads = [f"{label}{j}" for label in labels for j in range(1, p + 1)] + [f"c{h}" for h in range(1, pieces + 1)] + [f"x{j}" for j in range(1, p + 1)]
        return pa.RecordBatch.from_arrays([*named, *common, *own], heads)

    ready, rows = [], 0
    for found in _search(filters, sizes, *_measure(kind, threshold, p)):
        ready.append(found)
        rows += len(found[0])
        if rows >= ROWS:
            yield batch(ready)
            ready, rows = [], 0
    if ready:
        yield batch(ready)


def _search(filters, sizes, reach, joined, total):
    """Index arrays, one a party, of the sets that reach the threshold.

    What a set has in common is no more than any of its pairs has, and each record still to come is no smaller than the
    smallest that can still come; both only leave out what cannot reach the threshold.
    """
    import numpy as np

    p = len(filters)
    typed = [s.astype(np.float64) if joined is np.multiply else s for s in sizes]
    smallest = [s.min() for s in typed]

    def longer(j, at, words, common, held, met, least):
        """Sets of prefixes of parties 0..j-1, given by indexes, merged words, common bits and joined sizes."""
        if j == p:
            yield at
            return
        rows, pair = met[j]
        theirs, rest = typed[j][rows], least[j + 1 :]
        step = max(1, CELLS // len(rows))
        for start in range(0, len(common), step):
            cut = slice(start, start + step)
            grown = joined(held[cut, None], theirs[None, :])
            bound = reduce(joined, rest, grown)
            a, b = np.nonzero(np.minimum(reach(common[cut])[:, None], reach(pair)[None, :]) >= total(bound))
            if not len(a):
                continue
            both = words[:, cut][:, a] & filters[j][:, rows[b]]
            count = _bits(both)
            keep = np.flatnonzero(reach(count) >= total(bound[a, b]))
            if len(keep):
                a, b = a[keep], b[keep]
                whole = [i[cut][a] for i in at] + [rows[b]]
                yield from longer(j + 1, whole, both[:, keep] if j + 1 < p else None, count[keep], grown[a, b], met, least)

    for first in range(len(sizes[0])):
        own, x = filters[0][:, first : first + 1], typed[0][first]
        met, least = [None] * p, [x, *smallest[1:]]
        pairs = [None] + [_bits(own & filters[j]) for j in range(1, p)]
        for _ in range(2):  # again with the smallest of those left
            for j in range(1, p):
                rows, pair = (None, pairs[j]) if met[j] is None else met[j]
                theirs = typed[j] if rows is None else typed[j][rows]
                others = reduce(joined, (least[m] for m in range(p) if m != j))
                keep = np.flatnonzero(reach(pair) >= total(joined(theirs, others)))
                if not len(keep):
                    break
                met[j] = (keep if rows is None else rows[keep], pair[keep])
                least[j] = theirs[keep].min()
            else:
                continue
            break
        else:
            rows, pair = met[1]
            at = [np.full(len(rows), first), rows]
            yield from longer(2, at, own & filters[1][:, rows] if p > 2 else None, pair, joined(typed[1][rows], x), met, least)


def _kept(parts, p, prune):
    """Which sets every holder keeps: its own piece first, then those of the others ascending, tested after every merge."""
    import numpy as np

    (num, den), w = prune, len(parts[0]) // p
    keep = np.ones(parts[0].shape[1], bool)
    for h in range(p):
        piece = [f[h * w : (h + 1) * w] for f in parts]
        merged, bits = piece[h], _bits(piece[h])
        for n, j in enumerate((j for j in range(p) if j != h), 2):
            merged, bits = merged & piece[j], bits + _bits(piece[j])
            keep &= den * n * _bits(merged) >= num * bits
    return keep
