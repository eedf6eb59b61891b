"""SimHash near-duplicates by covering locality-sensitive hashing."""

from __future__ import annotations

import functools
import itertools
import math
import zlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ringlink.llm.common import Forest, components, lean, settle, shield

#: The ASCII letters are lower-cased, all else stays.
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def shingle_hashes(text: str | None, shingle: int) -> np.ndarray:
    """XXH64 (seed 42) of each shingle, of all words where they are no more than one shingle has; no word: none."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()  # bytes split at \x20 \x09-\x0D
    n, h = len(words), xxhash.xxh64_intdigest
    if n <= shingle:
        return np.array([h(b" ".join(words), 42)] if words else [], np.uint64)
    if shingle == 3:
        parts = map(b"%b %b %b".__mod__, zip(words, words[1:], words[2:]))
    else:
        parts = map(b" ".join, zip(*(words[i:] for i in range(shingle))))
    return np.fromiter((h(p, 42) for p in parts), np.uint64, n - shingle + 1)


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """64 bits: a bit is set if over half of the shingles' hashes have it. Null or no word: 0."""
    return majority(shingle_hashes(text, shingle))


def majority(hashes: np.ndarray) -> int:
    total, rows = np.zeros(64, np.int64), len(hashes)
    for at in range(0, rows, 1 << 16):
        bits = np.unpackbits(hashes[at : at + (1 << 16)].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        total += bits.sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * total > rows).tobytes(), "big")


def masks(bits: list[int], radius: int) -> list[int]:
    """Covering masks over the given bit places: any `radius` places or fewer are left out by some mask together.

    Each place gets a non-zero code of radius+1 bits; mask v holds the places whose code has odd inner product
    with v. The codes of `radius` places span at most `radius` dimensions, so some v is orthogonal to them all.
    """
    codes = 2 ** (radius + 1) - 1
    return [sum(1 << b for j, b in enumerate(bits) if (((j % codes) + 1) & v).bit_count() & 1) for v in range(1, codes + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _printed(shingle: int):
    def run(batches):
        for batch in batches:
            prints = [_signed(fingerprint(t, shingle)) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), pa.array(prints, pa.int64())], names=["doc_id", "fp"])

    return run


def _covered(radius: int, bits: int):
    """Rows (mask, fp, rep), each once for every mask that covers the places its mask left free."""
    finer: dict[int, np.ndarray] = {}

    def run(batches):
        for batch in batches:
            mask, fp, rep = (batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("mask", "fp", "rep"))
            for m in np.unique(mask):
                if m not in finer:
                    held = int(m) & (1 << 64) - 1
                    subs = sorted({held | x for x in masks([b for b in range(bits) if not held >> b & 1], radius)})
                    finer[m] = np.array([_signed(x) for x in subs], np.int64)
                here, subs = mask == m, finer[m]
                f, r = np.tile(fp[here], len(subs)), np.tile(rep[here], len(subs))
                k = np.repeat(subs, here.sum())
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (k, f & k, f, r)], names=["mask", "key", "fp", "rep"])

    return run


def _near(radius: int, forest: bool, block: int = 1024):
    """Each bucket's links: all of them, or with `forest` only a star for each of its connected groups."""

    def run(batches):
        for batch in batches:
            a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for members in batch.column("members").to_pylist():
                fp = np.array([m["fp"] for m in members], np.int64).view(np.uint64)
                rep = np.array([m["rep"] for m in members], np.int64)
                if forest:
                    near = np.bitwise_count(fp[:, None] ^ fp[None, :]) <= radius
                    root, was = rep, None
                    while was is None or (root != was).any():
                        was, root = root, np.where(near, root[None, :], np.iinfo(np.int64).max).min(1)
                    keep = root != rep
                    a.append(root[keep]), b.append(rep[keep])
                    continue
                for at in range(0, len(fp), block):
                    i, j = np.nonzero(np.bitwise_count(fp[at : at + block, None] ^ fp[None, :]) <= radius)
                    keep = i + at < j
                    a.append(rep[i[keep] + at]), b.append(rep[j[keep]])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], names=["a", "b"])

    return run


def links(prints: DataFrame, radius: int = 3, small: int = 256, bits: int = 64, forest: bool = False) -> DataFrame:
    """(a, b) of the distinct fingerprints (fp, rep) that differ in `radius` bits or fewer, all of them.

    A bucket of over `small` fingerprints is covered again on the places that its mask left free, about half as
    many each time; with 2^radius free places or fewer it holds few enough to be compared at once. With `forest`
    a bucket gives links enough to connect what its links connect, not every pair of a crowded group.
    """
    spark = prints.sparkSession
    found = spark.createDataFrame([], "a long, b long")
    level = prints.select(F.lit(0).cast("long").alias("mask"), "fp", "rep")
    split = (F.col("n") > small) & (F.bit_count("mask") < bits - 2**radius)
    first = True
    while True:
        rows = level.mapInArrow(_covered(radius, bits), "mask long, key long, fp long, rep long")
        if not first:
            rows = rows.dropDuplicates(["mask", "fp"])  # two coarse masks may lead to one finer mask
        first = False
        sizes = rows.groupBy("mask", "key").agg(F.count("*").alias("n")).where("n > 1")
        full = settle(rows.join(sizes, ["mask", "key"]))
        few = full.where(~split).groupBy("mask", "key").agg(F.collect_list(F.struct("fp", "rep")).alias("members"))
        found = found.union(few.select("members").mapInArrow(_near(radius, forest), "a long, b long"))
        level = full.where(split).select("mask", "fp", "rep")
        if level.isEmpty():
            return found.distinct()


def near_duplicates(docs: DataFrame, shingle: int = 3, radius: int = 3) -> DataFrame:
    """(doc_id, fp, component_id): component_id is the smallest doc_id that links reach, its own included.

    Null and empty texts have fingerprint zero and link like any other; rows with equal fingerprints are one
    class, never expanded into pairs. Repeated rows stay.
    """
    prints = settle(docs.select("doc_id", "text").mapInArrow(_printed(shingle), "doc_id long, fp long"))
    classes = settle(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")))
    groups = components(links(classes, radius, forest=True))
    named = classes.join(groups, F.col("rep") == F.col("node"), "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


def digest(docs: DataFrame) -> DataFrame:
    return near_duplicates(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def _set(text: str | None, shingle: int) -> np.ndarray:
    return np.unique(shingle_hashes(text, shingle).view(np.int64))


def _packed(text: str | None) -> bytes:
    """A text for the way to another task: less than its shingles' hashes, which nothing compresses."""
    return zlib.compress((text or "").encode("utf-8", "surrogatepass"), 4)


def _unpacked(shingle: int):
    """A function from packed texts to their sets, which remembers the last ones."""
    return functools.lru_cache(512)(lambda packed: _set(zlib.decompress(packed).decode("utf-8", "surrogatepass"), shingle))


def _key(held: np.ndarray) -> int:
    return _signed(xxhash.xxh64_intdigest(held.tobytes(), 42))


def _common(docs: DataFrame, shingle: int, part: int = 16, often: int = 4, most: int = 100_000) -> np.ndarray:
    """Shingles that many texts have, from one text in `part`. They only order the prefixes: which ones are known changes the time, not the result."""

    def each(batches):
        for batch in batches:
            held = [_set(t, shingle) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(0, np.int64), *held]))], names=["s"])

    some = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(part)) == 0).select("text").mapInArrow(lean(each), "s long")
    counts = some.groupBy("s").agg(F.count("*").alias("n")).where(F.col("n") >= often)
    return np.array(sorted(r["s"] for r in counts.orderBy(F.desc("n"), "s").limit(most).collect()), np.int64)


def _prefixed(shingle: int, least: float, common: np.ndarray):
    """Each text's set: its key, its size, and so many of its shingles, the common ones last, that two sets of
    Jaccard `least` or more share one of them at least."""

    def run(batches):
        for batch in batches:
            keys, prints, sizes, prefixes, odd = [], [], [], [], []
            for t in batch.column("text").to_pylist():
                hashes = shingle_hashes(t, shingle)
                held = np.unique(hashes.view(np.int64))
                prints.append(_signed(majority(hashes)))
                late = common[np.minimum(np.searchsorted(common, held), len(common) - 1)] == held if len(common) else np.zeros(len(held), bool)
                keys.append(_key(held)), sizes.append(len(held)), odd.append(_odd(held))
                prefixes.append(np.concatenate([held[~late], held[late]])[: len(held) - math.ceil(least * len(held) - 1e-9) + 1])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), batch.column("h"), pa.array(keys, pa.int64()), pa.array(prints, pa.int64()), pa.array(sizes, pa.int64()), pa.array(prefixes, pa.list_(pa.int64())), pa.array(odd, pa.binary())], names=["doc_id", "h", "key", "fp", "n", "prefix", "odd"])

    return run


def _buckets(batches):
    """The sets that share a shingle, from rows sorted by shingle and key: one row a shingle that two sets have or more."""
    rest = [np.zeros(0, np.int64) for _ in range(3)]
    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            rest = [np.concatenate([r, batch.column(c).to_numpy(zero_copy_only=False)]) for r, c in zip(rest, ("s", "key", "n"), strict=True)]
        new = np.ones(len(rest[0]), bool)
        new[1:] = (rest[0][1:] != rest[0][:-1]) | (rest[1][1:] != rest[1][:-1])  # exact copies are one set
        s, *rest_ = rest = [r[new] for r in rest]
        starts = np.nonzero(np.concatenate([[True], s[1:] != s[:-1]]))[0] if len(s) else np.zeros(0, np.int64)
        ends = np.append(starts[1:], len(s))
        if batch is not None:  # the last shingle may go on in the next batch
            cut = int(starts[-1]) if len(starts) else 0
            starts, ends = starts[:-1], ends[:-1]
        else:
            cut = len(s)
        many = [(int(a), int(b)) for a, b in zip(starts[ends - starts > 1], ends[ends - starts > 1], strict=True)]
        lists = [pa.array([r[a:b] for a, b in many], pa.list_(pa.int64())) for r in rest_]
        yield pa.RecordBatch.from_arrays([pa.array([int(s[a]) for a, _ in many], pa.int64()), *lists], names=["s", "keys", "sizes"])
        rest = [r[cut:] for r in rest]


def _needed(x: np.ndarray, y: np.ndarray, least: float) -> np.ndarray:
    """How many shingles two prefixes must share if sets of sizes x, y reach `least`: all they share, but for those behind the prefix that ends first."""
    behind = np.ceil(least * np.maximum(x, y) - 1e-9) - 1
    return np.maximum(1, np.ceil(least / (1 + least) * (x + y) - 1e-6) - behind).astype(np.int64)


def _pairs(key, n, i, j, least: float) -> pa.RecordBatch:
    a, b, need = key[i], key[j], _needed(n[i], n[j], least)
    return pa.RecordBatch.from_arrays([pa.array(x) for x in (np.minimum(a, b), np.maximum(a, b), need)], names=["a", "b", "need"])


def _same_size(starts: np.ndarray, lengths: np.ndarray, cells: int = 500_000):
    """The buckets that have one length, as rows of places, so many at a time that their pairs stay under `cells`."""
    for k in np.unique(lengths[lengths > 1]):
        here, step = starts[lengths == k], max(1, cells // (int(k) * int(k)))
        for at in range(0, len(here), step):
            yield here[at : at + step, None] + np.arange(k)


def _by_length(batch: pa.RecordBatch, column: str, *others: str):
    """The list column's rows of places, by `_same_size`, and its flat values: of its struct's fields, or of it and the other lists."""
    lists = batch.column(column)
    flat = lists.flatten()
    flat = [flat.field(f) for f in others] if pa.types.is_struct(flat.type) else [flat, *(batch.column(c).flatten() for c in others)]
    lengths = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    return [f.to_numpy(zero_copy_only=False) for f in flat], _same_size(np.cumsum(lengths) - lengths, lengths)


def _first_pairs(least: float):
    """Pairs enough to connect each bucket if they hold: neighbours by size, and all with the smallest key."""

    def run(batches):
        for batch in batches:
            (key, n), rows = _by_length(batch, "keys", "sizes")
            for at in rows:  # places by key, then by size
                at = np.take_along_axis(at, np.argsort(n[at], axis=1, kind="stable"), 1)
                low, place = np.argmin(key[at], axis=1)[:, None], np.arange(at.shape[1])[None, :]
                far = np.abs(place - low) > 1  # the smallest key's neighbours are pairs already
                first = np.take_along_axis(at, low, 1)
                i = np.concatenate([at[:, :-1].ravel(), np.where(place < low, at, first)[far]])
                j = np.concatenate([at[:, 1:].ravel(), np.where(place < low, first, at)[far]])
                ok = n[i] >= least * n[j] - 1e-9
                yield _pairs(key, n, i[ok], j[ok], least)

    return run


def _other_pairs(least: float, block: int = 512):
    """All pairs of a bucket that nothing connects yet and whose sizes allow `least`."""

    def run(batches):
        for batch in batches:
            (key, n, label), rows = _by_length(batch, "members", "key", "n", "label")
            for at in rows:
                at = np.take_along_axis(at, np.argsort(n[at], axis=1, kind="stable"), 1)
                k = at.shape[1]
                if k <= block:
                    x, y = np.triu_indices(k, 1)
                    i, j = at[:, x].ravel(), at[:, y].ravel()
                    ok = (label[i] != label[j]) & (n[i] >= least * n[j] - 1e-9)
                    yield _pairs(key, n, i[ok], j[ok], least)
                    continue
                for one in at:
                    size, of = n[one], label[one]
                    for begin in range(0, k, block):
                        i = np.arange(begin, min(begin + block, k))[:, None]
                        j = np.arange(begin, np.searchsorted(size, size[i[-1, 0]] / least + 1e-9, "right"))[None, :]
                        x, y = np.nonzero((i < j) & (of[i] != of[j]) & (size[i] >= least * size[j] - 1e-9))
                        yield _pairs(key, n, one[x + begin], one[y + begin], least)

    return run


def _parity(flat: np.ndarray, starts: np.ndarray, bits: int = 1024) -> np.ndarray:
    """Each set's parities of shingles by their lowest bits: two sets differ in as many shingles at least as these words differ in bits."""
    rows = np.repeat(np.arange(len(starts) - 1), np.diff(starts))
    odd = np.bincount(rows * bits + (flat & (bits - 1)), minlength=(len(starts) - 1) * bits) & 1
    return np.packbits(odd.astype(np.uint8).reshape(-1, bits), axis=1).view(np.uint64)


def _odd(held: np.ndarray) -> bytes:
    """A set's parities in 1,024 bits, or in twice as many as it has shingles, rounded up to a power of two."""
    return _parity(held, np.array([0, len(held)]), max(1024, 2 << (len(held) - 1).bit_length())).tobytes()


def _half(prints: np.ndarray) -> np.ndarray:
    """Parities in half as many bits."""
    return prints[:, : prints.shape[1] // 2] ^ prints[:, prints.shape[1] // 2 :]


def _room(n, m, least: float):
    """In how many shingles sets of sizes n, m may differ if they reach `least`."""
    return n + m - 2 * np.ceil(least / (1 + least) * (n + m) - 1e-6)


def _may_hold(least: float):
    """The pairs whose parities (x, y, of sets of n and m shingles) do not rule out `least`."""

    def run(batches):
        for batch in batches:
            keep = []
            for x, y, n, m in zip(*(batch.column(c).to_pylist() for c in ("x", "y", "n", "m")), strict=True):
                x, y = np.frombuffer(x, np.uint64)[None, :], np.frombuffer(y, np.uint64)[None, :]
                while x.shape != y.shape:
                    x, y = (_half(x), y) if x.shape[1] > y.shape[1] else (x, _half(y))
                keep.append(bool(np.bitwise_count(x ^ y).sum(dtype=np.int64) <= _room(n, m, least)))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def _widths(odd: list[bytes]) -> dict[int, tuple[int, np.ndarray]]:
    """Parities of sets, sorted by size, by width in bytes: the first place of that width or more, and those from there on in that width."""
    size = np.array([len(o) for o in odd])
    out: dict[int, tuple[int, np.ndarray]] = {}
    for width in sorted({*size.tolist()}, reverse=True):
        own = np.frombuffer(b"".join(o for o in odd if len(o) == width), np.uint64).reshape(-1, width // 8)
        wider = out[min(out)][1] if out else np.zeros((0, width // 8), np.uint64)
        while wider.shape[1] > own.shape[1]:
            wider = _half(wider)
        out[width] = (len(odd) - len(own) - len(wider), np.concatenate([own, wider]))
    return out


def _unruled(n: np.ndarray, label: np.ndarray, odd: list[bytes], near: np.ndarray, least: float, most: int, block: int = 64):
    """Places (i, j) of the pairs, of sets sorted by size, across labels (and across parts, where there are two) whose
    parities allow `least`, None if they are more than `most`; and whether each set is in such a pair."""
    widths, two, out, total, met = _widths(odd), near.min() != near.max(), [], 0, np.zeros(len(n), bool)
    for at in range(0, len(n), block):
        i = np.arange(at, min(at + block, len(n)))
        j = np.arange(at, np.searchsorted(n, n[i[-1]] / least + 1e-9, "right"))
        ok = (i[:, None] < j) & (label[i][:, None] != label[j]) & (n[i][:, None] >= least * n[j] - 1e-9)
        if two:
            ok &= near[i][:, None] != near[j]
        x, y = np.nonzero(ok)
        begin, prints = widths[len(odd[at])]
        for some in range(0, len(x), 1 << 16):
            p, q = i[x[some : some + (1 << 16)]], j[y[some : some + (1 << 16)]]
            keep = np.bitwise_count(prints[p - begin] ^ prints[q - begin]).sum(axis=1, dtype=np.int64) <= _room(n[p], n[q], least)
            met[p[keep]] = met[q[keep]] = True
            total += int(keep.sum())
            out = [*out, (p[keep], q[keep])] if total <= most else []
    return [np.concatenate([np.zeros(0, np.int64), *(o[k] for o in out)]) for k in (0, 1)] if total <= most else None, met


def _bound(n: np.ndarray, label: np.ndarray, held: list[np.ndarray], near: np.ndarray, least: float, block: int = 64):
    """Places (i, j) of sets, sorted by size, whose links connect what all links of Jaccard `least` or more among them connect.

    `near` says whether a set is of the first or the second part; where there are two, only links between them count.
    """
    forest, prints = Forest(), []
    for at in range(0, len(n), 256):
        some = held[at : at + 256]
        prints.append(_parity(np.concatenate(some), np.concatenate([[0], np.cumsum([len(h) for h in some])])))
    prints, two = np.concatenate(prints), near.min() != near.max()
    for at in range(0, len(n), block):
        i = np.arange(at, min(at + block, len(n)))
        end = np.searchsorted(n, n[i[-1]] / least + 1e-9, "right")
        root = np.array([forest.find(x) for x in label[at:end].tolist()], np.int64)
        if (root == root[0]).all():
            continue
        j = np.arange(at, end)
        ok = (i[:, None] < j) & (root[: len(i), None] != root) & (n[i][:, None] >= least * n[j] - 1e-9)
        if two:
            ok &= near[i][:, None] != near[j]
        x, y = np.nonzero(ok)
        for begin in range(0, len(x), 1 << 16):
            p, q = i[x[begin : begin + (1 << 16)]], j[y[begin : begin + (1 << 16)]]
            differ = np.bitwise_count(prints[p] ^ prints[q]).sum(axis=1, dtype=np.int64)
            keep = differ <= _room(n[p], n[q], least)
            for u, v in zip(p[keep].tolist(), q[keep].tolist()):
                if forest.find(label[u]) == forest.find(label[v]):
                    continue
                both = len(np.intersect1d(held[u], held[v], assume_unique=True))
                if both >= least * (len(held[u]) + len(held[v]) - both) - 1e-9:
                    forest.link(label[u], label[v])
                    yield u, v


def _by_tile(batches):
    """The rows of each tile, by size, from rows sorted by tile; None after each batch."""
    tile, rows = None, []
    for batch in itertools.chain(batches, [None]):
        for r in batch.to_pylist() if batch is not None else [None]:
            if r is None or (r["s"], r["one"], r["two"]) != tile:
                if len(rows) > 1:
                    yield tile, sorted(rows, key=lambda r: r["n"])
                tile, rows = r and (r["s"], r["one"], r["two"]), []
            rows.append(r)
        yield None


def _columns(rows: list[dict]):
    return (np.array([r[c] for r in rows], np.int64) for c in ("n", "label", "part", "key"))


def _sketched(least: float, share: float):
    """What a tile's parities leave to compare: its pairs (a, b), or the sets in them (b null) if they are more than `share` times its members."""

    def run(batches):
        found = []
        for each in _by_tile(batches):
            if each is not None:
                tile, rows = each
                n, label, part, key = _columns(rows)
                pairs, met = _unruled(n, label, [r["odd"] for r in rows], part, least, int(share * len(rows)))
                if pairs is None:
                    found += [(k, None, *tile) for k in key[met].tolist()]
                else:
                    a, b = key[pairs[0]], key[pairs[1]]
                    found += [(*p, *tile) for p in zip(np.minimum(a, b).tolist(), np.maximum(a, b).tolist(), strict=True)]
                continue
            yield pa.RecordBatch.from_arrays([pa.array([f[k] for f in found], pa.int64()) for k in range(5)], names=["a", "b", "s", "one", "two"])
            found = []

    return run


def _crowded(shingle: int, least: float):
    """Links within each tile, from rows sorted by tile: (a, b) of sets, no more than a tile has members."""

    def run(batches):
        found, opened = [], _unpacked(shingle)
        for each in _by_tile(batches):
            if each is not None:
                rows = each[1]
                n, label, part, key = _columns(rows)
                found += [(int(key[u]), int(key[v])) for u, v in _bound(n, label, [opened(r["held"]) for r in rows], part, least)]
                continue
            pairs = [(min(p), max(p)) for p in found]
            yield pa.RecordBatch.from_arrays([pa.array([p[k] for p in pairs], pa.int64()) for k in (0, 1)], names=["a", "b"])
            found = []

    return run


def _tiles(crowds: DataFrame, least: float, room: int) -> DataFrame:
    """The members (s, key, n, label) of each bucket dealt into parts of about `room` shingles by size (a set counts 200 more),
    and each two parts whose sizes allow `least`, or a part by itself, as a tile: (s, one, two, part, key, n, label)."""
    sizes, one = crowds.groupBy("s", "n").agg(F.count("*").alias("c")), F.col("n") + 200
    before = F.coalesce(F.sum(one * F.col("c")).over(Window.partitionBy("s").orderBy("n").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sizes = sizes.select("s", "n", F.floor(before / room).alias("from"), F.floor((before + one * (F.col("c") - 1)) / room).alias("to"))
    dealt = crowds.join(sizes, ["s", "n"]).withColumn("part", F.col("from") + F.pmod(F.xxhash64("key"), F.col("to") - F.col("from") + 1))
    dealt = settle(dealt.select("s", "part", "key", "n", "label"))
    parts = dealt.groupBy("s", "part").agg(F.min("n").alias("low"), F.max("n").alias("high"))
    one, two = (parts.select("s", *(F.col(c).alias(f"{c}{k}") for c in ("part", "low", "high"))) for k in (1, 2))
    tiles = one.join(two, "s").where((F.col("part1") <= F.col("part2")) & (F.col("high1") >= least * F.col("low2") - 1e-9))
    tiles = tiles.select("s", F.col("part1").alias("one"), F.col("part2").alias("two"), F.explode(F.array_distinct(F.array("part1", "part2"))).alias("part"))
    return dealt.join(tiles, ["s", "part"]).select("s", "one", "two", "part", "key", "n", "label")


def _alike(shingle: int, least: float):
    def run(batches):
        opened = _unpacked(shingle)
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist(), strict=True):
                x, y = opened(x), opened(y)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(both >= least * (len(x) + len(y) - both) - 1e-9)
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def near_copies(docs: DataFrame, shingle: int = 5, least: float = 0.8, few: int = 32, room: int = 1_000_000, share: float = 1.0) -> DataFrame:
    """(doc_id, h, component_id), h a hash of the text: component_id is the smallest doc_id that links reach (null last); texts link when the Jaccard
    similarity of their sets of word shingles is `least` or more, all such links, none else.

    SimHash fingerprints of the shingles that are equal or differ in three bits or fewer are met by covering masks;
    their texts are candidates, whose sets are then compared. At .8 a fingerprint differs in about ten of its 64 bits
    with a wide spread, which no number of masks covers, so those whose fingerprints are further apart are found by a
    shared shingle of their prefixes. Links that hold among a few pairs of each bucket join the
    big groups first; after that only pairs across groups are left to compare. A bucket of over `few` sets makes no pair
    rows: its sets are brought together, in tiles of twice `room` shingles, by their parities. The pairs that these leave
    are compared like others; if they are more than `share` times a tile's members, the texts of the sets in them are
    brought together and give links enough to connect what their links connect. Texts without a word are one class.
    """
    held = docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h"))
    sets = settle(held.mapInArrow(lean(_prefixed(shingle, least, _common(held, shingle))), "doc_id long, h long, key long, fp long, n long, prefix array<long>, odd binary"))
    rows = sets.select("key", "n", F.explode("prefix").alias("s")).select("s", "key", "n")
    lists = "s long, keys array<long>, sizes array<long>"
    full = settle(rows.repartition("s").sortWithinPartitions("s", "key").mapInArrow(lean(_buckets), lists))

    def whole(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            yield pa.RecordBatch.from_arrays([pa.array([_key(_set(t, shingle)) for t in texts], pa.int64()), pa.array([_packed(t) for t in texts], pa.binary())], names=["key", "held"])

    def sided(pairs: DataFrame, rows: DataFrame, **names: tuple[str, str]) -> DataFrame:
        """The pairs with columns of both their sets, each under a name a side."""
        for k, side in enumerate("ab"):
            pairs = pairs.join(rows.select(F.col("key").alias(side), *(F.col(c).alias(n[k]) for c, n in names.items())), side)
        return pairs

    def holding(counted: DataFrame, done: DataFrame | None = None, crowds: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
        """The pairs that share enough of their prefixes, and those of them that hold; with `crowds` also links within these tiles."""
        tried = counted.groupBy("a", "b", "need").agg(F.count("*").alias("c")).where("c >= need").select("a", "b").distinct()
        tried = settle(tried.join(done, ["a", "b"], "left_anti") if done is not None else tried)
        nodes = tried.select(F.explode(F.array("a", "b")).alias("key"))
        nodes = settle((nodes.union(crowds.select("key")) if crowds is not None else nodes).distinct())
        odds = settle(sets.join(nodes, "key", "left_semi").select("key", "h", "n", "odd").dropDuplicates(["key"]))  # one text a set
        close = settle(sided(tried, odds, odd=("x", "y"), n=("n", "m")).mapInArrow(lean(_may_hold(least)), "a long, b long"))
        nodes = close.select(F.explode(F.array("a", "b")).alias("key"))
        if crowds is not None:  # parities first: whole sets only of the pairs they leave, and of tiles where these are many
            rows = crowds.join(odds.select("key", "odd"), "key").repartition("s", "one", "two").sortWithinPartitions("s", "one", "two")
            left = settle(rows.mapInArrow(lean(_sketched(least, share)), "a long, b long, s long, one long, two long"))
            close = settle(close.union(left.where("b is not null").select("a", "b").join(done, ["a", "b"], "left_anti")).distinct())
            crowds = settle(crowds.join(left.where("b is null").select("s", "one", "two", F.col("a").alias("key")), ["s", "one", "two", "key"], "left_semi"))
            nodes = close.select(F.explode(F.array("a", "b")).alias("key")).union(crowds.select("key"))
        nodes = settle(nodes.distinct())
        some = settle(odds.join(nodes, "key", "left_semi").select("h").distinct())
        if nodes.count() <= 300_000:  # drops texts before their sets are made; more are left to shuffled joins
            nodes, some = F.broadcast(nodes), F.broadcast(some)
        texts = held.join(some, "h", "left_semi").select("text")
        sets_ = settle(texts.mapInArrow(lean(whole), "key long, held binary").join(nodes, "key", "left_semi").dropDuplicates(["key"]))
        found = settle(sided(close, sets_, held=("x", "y")).mapInArrow(lean(_alike(shingle, least)), "a long, b long"))
        if crowds is not None and not crowds.isEmpty():
            tiles = crowds.join(sets_, "key").repartition("s", "one", "two").sortWithinPartitions("s", "one", "two")
            found = found.union(settle(tiles.mapInArrow(lean(_crowded(shingle, least)), "a long, b long")))
        return tried, found

    prints = sets.select("key", "fp").distinct()
    reps = settle(prints.groupBy("fp").agg(F.min("key").alias("rep")))
    near = links(reps, forest=True).select("a", "b").union(prints.join(reps, "fp").where("key <> rep").select("rep", "key"))
    near = near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.lit(1).cast("long").alias("need")).distinct()
    tried, found = holding(near.union(full.mapInArrow(lean(_first_pairs(least)), "a long, b long, need long")))
    groups = components(found)
    members = full.select("s", F.size("keys").alias("size"), F.explode(F.arrays_zip("keys", "sizes")).alias("m")).select("s", "size", F.col("m.keys").alias("key"), F.col("m.sizes").alias("n"))
    members = members.join(groups, F.col("key") == F.col("node"), "left").withColumn("label", F.coalesce("component", "key"))
    members = settle(members.select("s", "key", "n", "label", "size"))
    open_ = members.where(F.col("size") <= few).groupBy("s").agg(F.collect_list(F.struct("key", "n", "label")).alias("members"), F.min("label").alias("low"), F.max("label").alias("high")).where("low <> high")
    others = open_.select("members").mapInArrow(lean(_other_pairs(least)), "a long, b long, need long")
    # a pair that has crowded buckets too is compared there, so what it lacks of `need` here loses no link
    big = members.where(F.col("size") > few)
    big = big.join(big.groupBy("s").agg(F.min("label").alias("low"), F.max("label").alias("high")).where("low <> high").select("s"), "s", "left_semi")
    crowds = settle(_tiles(settle(big.select("s", "key", "n", "label")), least, room))
    groups = components(found.union(holding(others, tried, crowds)[1]))
    keys = sets.groupBy("key").agg(F.min("doc_id").alias("low"))  # a class may have much of the rows: keys are joined once each
    keys = keys.join(groups, F.col("key") == F.col("node"), "left").select("key", "low", F.coalesce("component", "key").alias("class"))
    first = keys.groupBy("class").agg(F.min("low").alias("component_id"))
    keys = keys.join(first, "class").select(F.col("key").alias("k"), "component_id")
    return sets.select("doc_id", "h", "key").join(keys, F.col("key") == F.col("k")).select("doc_id", "h", "component_id")


def first_of_copies(docs: DataFrame) -> DataFrame:
    """The rows of docs that stay: of each group of near copies the one with the smallest doc_id, columns as they were.

    Rows with one id and one text are told apart only if there are such: then one of them stays. A group whose ids are
    all null keeps one row. Empty texts are a group like any other.
    """
    rows, back = shield(docs, "doc_id", "text")
    named = settle(near_copies(rows))
    gone = named.where(~F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("_d"), F.col("h").alias("_h")).distinct()
    stay = named.where(F.col("doc_id").eqNullSafe(F.col("component_id")))
    n = stay.agg(F.count("*").alias("n"), F.countDistinct(F.struct("component_id")).alias("d")).first()
    h = F.xxhash64(F.coalesce("text", F.lit("")))
    gone = settle(gone)
    gone = F.broadcast(gone) if gone.count() <= 200_000 else gone
    left = rows.withColumn("_hash", h).join(gone, F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("_hash") == F.col("_h")), "left_anti")
    if n["n"] != n["d"]:  # rows of one id in one group, or a group of null ids
        left = left.dropDuplicates(["doc_id"] if stay.where("doc_id is null").isEmpty() else ["doc_id", "_hash"])
    return left.select(*back)
