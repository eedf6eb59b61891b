import collections
import functools
import math
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from ringlink.llm import embeddings, licenses, mixing, registry, rules, simhash, toxicity, warc


def _docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_covering_simhash_against_all_pairs(spark):
    rng = random.Random(7)
    seeds = [rng.getrandbits(64) for _ in range(5)]
    fps = {s ^ sum(1 << b for b in rng.sample(range(64), rng.randint(0, 4))) for s in seeds for _ in range(60)}
    fps = sorted(fps)
    prints = spark.createDataFrame([(simhash._signed(f), i) for i, f in enumerate(fps)], "fp long, rep long")
    want = {(i, j) for i in range(len(fps)) for j in range(i + 1, len(fps)) if (fps[i] ^ fps[j]).bit_count() <= 3}
    for small in (256, 8):  # the second covers crowded buckets again
        assert {tuple(sorted(r)) for r in simhash.links(prints, small=small).collect()} == want


def test_simhash_edges(spark):
    out = {r["doc_id"]: r for r in simhash.digest(_docs(spark, [(1, None), (2, ""), (3, "a B"), (4, "a b"), (4, "a b")])).collect()}
    assert out[1]["fingerprint"] == "0" * 16 and out[2]["component_id"] == 1 and out[3]["fingerprint"] == out[4]["fingerprint"]


def test_pipeline_near_copies_against_brute_force(spark):
    import corpus_pipeline

    rng = random.Random(5)
    vocab = [f"w{i}" for i in range(300)]
    texts = ["", "one two"]
    for g in range(12):
        words = [rng.choice(vocab) for _ in range(rng.choice((12, 60, 200)))]
        for c in range(9):
            copy = list(words)
            for _ in range(rng.randint(0, max(1, len(words) // 40))):
                copy[rng.randrange(len(copy))] = rng.choice(vocab)
            texts.append(" ".join(copy[: len(copy) - rng.randint(0, len(copy) // 12)]) + (" all rights are reserved by us" if g < 6 else ""))
    texts += [texts[5].upper(), None]
    sets = [frozenset(simhash._set(t, 5).tolist()) for t in texts]
    like = lambda x, y: x == y or len(x & y) >= 0.8 * len(x | y) - 1e-9
    root = list(range(len(texts)))
    for _ in texts:
        for i in range(len(texts)):
            root[i] = min(root[j] for j in range(len(texts)) if like(sets[i], sets[j]))
    while any(root[r] != r for r in root):
        root = [root[r] for r in root]
    assert len(set(root)) < len(set(sets))  # near copies, not equal sets alone
    rows = _docs(spark, list(enumerate(texts))).repartition(3)
    assert {r["doc_id"]: r["component_id"] for r in simhash.near_copies(rows).collect()} == dict(enumerate(root))
    kept = {r["doc_id"] for r in corpus_pipeline.simhash_dedup(spark, rows, "").collect()}
    assert kept == set(root)
    crowded = simhash.near_copies(rows, few=1, room=1500)  # every bucket in tiles, a few sets in each
    assert {r["doc_id"]: r["component_id"] for r in crowded.collect()} == dict(enumerate(root))


def test_epsilon_grid_join_against_all_pairs(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(12, 16))
    v = np.concatenate([base + rng.normal(size=base.shape) * s for s in (0, 0.1, 0.3, 0.4)])
    rows = [(i, [float(x) for x in a], int(i % 12 % 3)) for i, a in enumerate(v)] + [(100, None, 1), (101, [0.0] * 16, 1), (102, [float(x) for x in v[0]], None)]
    out = {r["vec_id"]: r for r in embeddings.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")).collect()}
    u = v / np.linalg.norm(v, axis=1, keepdims=True)
    for i in range(len(v)):
        assert out[i]["n_links"] == sum(1 for j in range(len(v)) if j != i and j % 12 % 3 == i % 12 % 3 and u[i] @ u[j] >= 0.93)
    assert all(out[i]["n_links"] == 0 and out[i]["kept"] for i in (100, 101, 102))


def test_rules_by_hand(spark):
    assert rules.measure("a b c a b c\nx\nx") == (8, 8, 0, 1, 6, 3)
    assert rules.measure(None) == (0, 0, 0, 0, 0, 0)
    assert [r["kept"] for r in rules.digest(_docs(spark, [(1, None)])).collect()] == [False]


def test_licenses(spark):
    rows = [(1, "x CC-BY y\nLicensed under CC BY-NC 4.0."), (2, None), (3, "ccc by"), (4, "the Apache License, Version 2.0 licensed under")]
    out = {r["doc_id"]: r for r in licenses.digest(_docs(spark, rows)).collect()}
    assert (out[1]["n_base"], out[1]["first_word"], out[1]["last_word"], out[1]["labels"]) == (2, 1, 6, "cc-by,cc-by-nc-4.0")
    assert out[2]["n_words"] == 0 and out[3]["n_base"] == 0 and "apache-2.0" in out[4]["labels"]


def _sources(spark, n=400):
    rng = random.Random(11)
    names = [None, "a", "b", "é", "z"]
    return [(i, " ".join(["w"] * rng.choice((0, 1, 5, 40, 200))), names[0 if i % 3 else rng.randrange(5)]) for i in range(n)]


def _waterfill(sizes, share=1.5, most=2.0):
    order = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [s for s in sizes if s is None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    out, left = {}, share * sum(sizes.values())
    while open_ := [s for s in order if s not in out]:
        unit = left / sum(weight[s] for s in open_)
        full = [s for s in open_ if unit * weight[s] > most * sizes[s]]
        for s in full or open_:
            out[s] = most * sizes[s] if full else unit * weight[s]
            left -= out[s]
    return out


def test_mixing_meets_targets(spark):
    rows = _sources(spark)
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    out = mixing.digest(docs).collect()
    source = {i: s for i, _, s in rows}
    sizes: dict = {}
    for i, t, s in rows:
        sizes[s] = sizes.get(s, 0) + len(t.split())
    want, taken = _waterfill(sizes), {}
    for r in out:
        s = source[r["doc_id"]]
        assert r["source_size"] == sizes[s] and abs(r["target"] - want[s]) < 1e-6 * max(1, want[s]) and r["taken"] <= 2 * r["size"]
        taken[s] = taken.get(s, 0) + r["taken"]
    assert len(out) == len(rows) and all(abs(taken[s] - want[s]) <= 200 for s in want)
    again = mixing.digest(docs).collect()
    assert sorted(map(tuple, out)) == sorted(map(tuple, again))


def test_mixing_rates_are_tilts_of_the_size(spark):
    """Newton's duals meet each source's constraint: the sum of tilted rates times sizes is the target."""
    cells = spark.createDataFrame([("a", 10, 30), ("a", 100, 5), ("b", 7, 4), (None, 3, 9)], "source string, size long, n long")
    aims = spark.createDataFrame([("a", 800, 500.0), ("b", 28, 56.0), (None, 27, 40.0)], "source string, size long, target double")
    dual = {r["source"]: r["dual"] for r in mixing.balance(cells, aims).collect()}
    assert dual["b"] == float("inf")
    for s, parts, target in (("a", ((10, 30), (100, 5)), 500.0), (None, ((3, 9),), 40.0)):
        mean = sum(x * n for x, n in parts) / sum(n for _, n in parts)
        got = sum(x * n * 2 / (1 + np.exp(-dual[s] * x / mean)) for x, n in parts)
        assert abs(got - target) < 1e-4 * target


def test_decoding():
    cost = -np.log((toxicity.counted(["the idiot is an idiot and a loser"] * 20).reshape(27, 27, 27) + 0.1) / 100)
    assert toxicity.decode("1d10t", cost) == "idiot" and toxicity.decode("looooser", cost) == "loser"
    assert re.fullmatch("[a-z]*", toxicity.decode("@$!", cost))
    assert toxicity.decode("l" + "o" * 60 + "ser", cost) == "loser"  # of any length
    assert toxicity.Restored(cost).spaced("a l o s e r a n d a n i d i o t") == "a loser and an idiot".split()


def test_toxicity_counts_rare_beginnings_by_density():
    rates, marked = (0.03, 0.0005), frozenset(["achli~"])
    odds = lambda words: toxicity.evidence(set(words), {"moron": 8.0}, marked, rates)
    short = [f"wort{i}" for i in range(60)]
    long = [f"wort{i}" for i in range(900)]
    assert odds([*short, "achlicher", "achliches", "achlichkeit"]) > 1 > 0 > odds([*long, "achlicher"])
    assert odds([*long, "moron"]) > 1 and odds([]) == odds(short) == toxicity.BIAS


def test_pii_bootstrapping_trusts_no_form_that_fails_its_check(spark):
    from ringlink.llm import pii

    good, bad = "4111111111111111", "4111111111111112"
    rows = [(i, f"card {good if i < 3 else bad} seen") for i in range(12)] + [(20 + i, f"login user{i + 10}@mail.org now") for i in range(6)] + [(40, "login ab12cd34ef now")]
    out = {r["doc_id"]: r for r in pii.digest(_docs(spark, [*rows, (50, None)])).collect()}
    assert out[0]["n_card"] == 1 and out[5]["spans"] == "" and out[20]["n_email"] == 1
    assert out[40]["spans"] == "context:6:16" and out[50]["spans"] == ""


def test_pii_reaches_recurring_contexts_and_every_occurrence(spark):
    from ringlink.llm import pii

    hex_ = ["ab3d" * 8 + f"{i * 7919 + 11:08x}" for i in range(8)]
    rows = [(i, f'some words token = "{x}" more\nand token = "{x}" again') for i, x in enumerate(hex_)]
    rows += [(20 + i, f"call +1 (017) 555-{1000 + i} please or card 4111 1111 1111 1111") for i in range(8)] + [(40, "call ab12cd34ef or xab12cd34ef, token of none"), (41, "id please x777x777x")]
    rows += [(50 + i, f"the word stands before the word and the item{i}{i}x") for i in range(6)]
    docs = _docs(spark, rows)
    out = {r["doc_id"]: r["spans"] for r in pii.digest(docs).collect()}
    for i, x in enumerate(hex_):
        assert out[i] == ",".join(f"context:{m.start()}:{m.end()}" for m in re.finditer(x, rows[i][1]))
    assert out[40] == "context:5:15" and all(out[50 + i] == "" for i in range(6))
    text = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    assert not any(x in text[i] for i, x in enumerate(hex_)) and text[40] == "call [CONTEXT] or xab12cd34ef, token of none"


def test_quality_backs_off_to_lower_orders(spark):
    from ringlink.llm import quality_lm

    text = "the cat sat on the mat \u4e2d and the dog ran to the cat " * 3
    grams, n = quality_lm._distinct([text, "\U0001f600 too"])
    counts = spark.createDataFrame([("en", int(a), int(b)) for a, b in zip(grams.view(np.int64), n, strict=True)], "lang string, gram long, n long")
    answers: dict = {}
    for r in quality_lm.model(counts).collect():
        answers.setdefault(r["k"], []).append((r["gram"] % 2**64, np.nan if r["p"] is None else r["p"], np.nan if r["back"] is None else r["back"]))
    answers = {k: (np.array([x[0] for x in v], np.uint64), *(np.array([x[i] for x in v]) for i in (1, 2))) for k, v in ((k, sorted(v)) for k, v in answers.items())}
    units = np.unique(grams & np.uint64(0xFFFF))
    for before in ("the", " ca", "zzt", "zzz"):  # seen and unseen contexts alike
        ctx = functools.reduce(lambda g, c: g << 16 | ord(c), before, 0)
        p = quality_lm.resolve(np.array([ctx << 16 | int(u) for u in units], np.uint64), answers)
        lacking = quality_lm.resolve(np.array([ctx << 16 | 0xFFFD], np.uint64), answers)  # one for all it lacks
        assert p.min() > 0 and abs(p.sum() + lacking[0] - 1) < 1e-6


def _kneser_ney(texts):
    """The probability of a unit after three, from definitions, as a function of a gram of four."""
    levels = [collections.Counter(g for t in texts for g in zip(*(("   " + t + " ")[i:] for i in range(4)), strict=False))]
    for _ in range(3):
        levels.append(collections.Counter(g[1:] for g in levels[-1]))
    flat = 1 / (len(levels[-1]) + 1)

    def discount(level, n):
        t = collections.Counter(level.values())
        y, i = (t[1] / (t[1] + 2 * t[2]) if t[1] else 0.0), min(n, 3)
        return max(0.05, min(i - 0.05, i - (i + 1) * y * t[i + 1] / t[i] if t[i] else i * 0.5))

    cuts = {id(level): {n: discount(level, n) for n in set(level.values())} for level in levels}

    def p(gram):
        if not gram:
            return flat
        level = levels[4 - len(gram)]
        after = [n for g, n in level.items() if g[:-1] == gram[:-1]]
        if not after:
            return p(gram[1:])
        d = cuts[id(level)]
        n = level.get(gram, 0)
        return ((n - d[n]) / sum(after) if n else 0.0) + sum(d[m] for m in after) / sum(after) * p(gram[1:])

    return p


def test_quality_against_brute_force(spark):
    from ringlink.llm import quality_lm

    rng = random.Random(3)
    words = ["the", "cat", "sat", "\u4e2d\u6587", "mat", "Dog", "", "n\u00e9", "12"]
    rows = [(i, " ".join(rng.choices(words, k=rng.randint(1, 30))), "en" if i % 3 else None) for i in range(60)] + [(90, None, "en"), (91, "", "xx"), (None, "the cat", "en")]
    docs, good = spark.createDataFrame(rows, "doc_id long, text string, lang string"), range(0, 60, 2)
    out = quality_lm.score(docs, spark.createDataFrame([(i, 1) for i in good], "doc_id long, quality int"), quantile=0.5, block=300).collect()
    total = sum(len(r[1] or "") for r in rows)
    place = {tuple(r)[:1]: r["b"] for r in docs.select("doc_id", F.pmod(F.xxhash64("doc_id", "text"), F.lit(2 + total // 600 * 2)).alias("b")).collect()}
    assert len(out) == len(rows) and len(set(place.values())) > 4
    models = {(h, lang): _kneser_ney([t for i, t, x in rows if i in good and x == lang and place[(i,)] % 2 != h]) for h in (0, 1) for lang in ("en", None)}
    want = {}
    for i, t, lang in rows:
        if lang == "xx":
            want[i] = None
            continue
        grams = list(zip(*(("   " + (t or "") + " ")[k:] for k in range(4)), strict=False))
        want[i] = math.exp(-sum(math.log(models[place[(i,)] % 2, lang](g)) for g in grams) / len(grams))
    for r in out:
        assert r["perplexity"] is None and r["kept"] if want[r["doc_id"]] is None else math.isclose(r["perplexity"], want[r["doc_id"]], rel_tol=1e-4)
        assert r["kept"] == (r["perplexity"] is None or r["perplexity"] <= r["threshold"])
    assert {r["kept"] for r in out} == {True, False}


def _warc_rows(rows):
    import base64
    import hashlib

    groups: dict = {}
    for i, _, h in rows:
        groups.setdefault(h or "", []).append(i)
    out = []
    for h, ids in groups.items():
        first, done = min(ids, key=lambda x: (x is None, x or 0)), False
        for i in ids:
            response = i == first and not done
            done |= response
            b = h.encode()
            out.append((i, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "response" if response else "revisit", None if response else first))
    return sorted(out, key=str)


def test_warc_round_trip(spark, tmp_path):
    rows = [(1, "u", "a"), (1, "u", "a"), (2, "u", "a"), (3, None, None), (None, "x", ""), (4, "v", "é\r\n\r\nx"), (5, "u\r\nW: x", "é\r\n\r\nx"), (1, "z", "a"), (None, "q", "only"), (None, "q", "only"), (9, "l", "x" * 700_000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit(1)).withColumn("own", F.lit(2))
    assert sorted((tuple(r) for r in warc.digest(pages).collect()), key=str) == _warc_rows(rows)
    warc.write(pages, f"{tmp_path}/w", least=5)
    got = warc.assemble(warc.read(spark, f"{tmp_path}/w")).collect()
    assert len(got) == len(rows) and all(r["request"] is not None and r["metadata"] is not None for r in got)
    assert sorted(bytes(r["response"]["payload"]).decode() for r in got if r["response"]["kind"] == "response") == sorted(h or "" for _, _, h in rows if h != "é\r\n\r\nx") + ["é\r\n\r\nx"]
    assert warc.digest(pages.where("page_id = 77")).isEmpty()


def test_embedding_components_against_brute_force(spark):
    rng = np.random.default_rng(5)
    base = rng.normal(size=(30, 12))
    v = np.concatenate([base, base + rng.normal(size=base.shape) * 0.2, base * 3, base])
    rows = [(1000 - i, [float(x) for x in a], i % 30 % 2) for i, a in enumerate(v)] + [(2000, [1.0, 0.5], 1), (2001, [2.0, 1.0], 1), (2002, [1.0, 0.5], 0), (2003, [1.0, float("nan")], 1), (2004, [None, 1.0], 1), (2005, [], 1)]
    out = {r["vec_id"]: r for r in embeddings.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").repartition(4), block=16).collect()}
    ids, link = [r[0] for r in rows], {}
    for i, a, x in rows:
        for j, b, y in rows:
            ok = i != j and x == y and len(a) == len(b) > 0 and all(q is not None and np.isfinite(q) for q in (*a, *b))
            if ok and np.dot(a, b) / np.linalg.norm(a) / np.linalg.norm(b) >= 0.93:
                link.setdefault(i, set()).add(j)
    root = {i: i for i in ids}
    for _ in ids:
        root = {i: min([root[i], *(root[j] for j in link.get(i, ()))]) for i in ids}
    for i in ids:
        assert (out[i]["n_links"], out[i]["component_id"]) == (len(link.get(i, ())), root[i])


def test_grid_join_skips_distant_intervals():
    rng = np.random.default_rng(1)
    centres = np.eye(8)[:, :] * 1.0
    a = np.concatenate([c + rng.normal(size=(200, 8)) * 0.02 for c in centres])
    a /= np.linalg.norm(a, axis=1, keepdims=True)
    skipped: list = []
    pairs = sum(len(i) for i, _ in embeddings.meet(a, a, a, a, 0.93, float(np.sqrt(0.14)), 64, True, skipped=skipped))
    assert pairs == 8 * 200 * 199 // 2 and sum(skipped) > 0.8 * len(a) ** 2 / 2


def test_pii_base_against_brute_force(spark):
    import hashlib

    from ringlink.llm import pii

    patterns = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]

    def luhn(d):
        return sum(sum(divmod(int(c) * 2, 10)) if i % 2 else int(c) for i, c in enumerate(reversed(d))) % 10 == 0

    def base(t):
        out = []
        for k, (name, p) in enumerate(patterns):
            for m in re.finditer(p, t):
                d = re.sub("[^0-9]", "", m.group())
                if {"email": True, "ip": name == "ip" and all(int(x) <= 255 for x in m.group().split(".")), "card": 14 <= len(d) <= 19 and luhn(d), "phone": 10 <= len(d) <= 15}[name]:
                    out.append((m.start(), k, m.end(), name))
        return sorted(out)

    rng, bits = random.Random(3), ["a@b.c", "x.y@z", "@", ".", "1.2.3.4", "300.1.1.1", "4111111111111111", "4111 1111-1111 1111", "+1 (017) 555-0123", "+", " ", "é", "-", "12", "\n", "007.0.0.1"]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 40))) for _ in range(300)] + ["a@b" + ".c" * 2000, "1.2.3.4 " * 3000, None, ""]
    for r in pii.digest(_docs(spark, list(enumerate(texts)))).collect():
        found = base(texts[r["doc_id"]] or "")
        assert r["base_sha256"] == hashlib.sha256(",".join(f"{n}:{s}:{e}" for s, _, e, n in found).encode()).hexdigest()
        assert r["n_email"] == sum(n == "email" for *_, n in found)


def test_licenses_wrapped_and_apart(spark):
    rows = [(1, "Redistribution and use in source and binary forms, with or\nwithout modification, are permitted"), (2, "Released under the MIT License."), (3, "GNU General Public License version 2"), (4, "under a tree the mit people met a license " + "x " * 50 + "license")]
    out = {r["doc_id"]: r["labels"] for r in licenses.digest(_docs(spark, rows)).collect()}
    assert out[1] == "bsd" and out[2] == "mit" and out[3] == "gpl"


def test_ledger_policies_and_ablation(spark, tmp_path):
    texts = ["w " * 60, "a b c " * 40, "# # # " * 30, "x", None, "same line\n" * 30]
    book = rules.ledger(_docs(spark, list(enumerate(texts))))
    book.write.parquet(f"{tmp_path}/book")
    book = spark.read.parquet(f"{tmp_path}/book")  # policies are applied to the stored bits, texts are not read again
    for policy in rules.POLICIES:
        kept = {r["doc_id"] for r in book.where(rules.verdict(policy)).collect()}
        assert kept == {r["doc_id"] for r in rules.keep(_docs(spark, list(enumerate(texts))), policy).collect()}
    bits = {r["doc_id"]: r["failures"] for r in book.collect()}
    for r in rules.ablation(book).collect():
        bit = 1 << [n for n, _ in rules.rules()].index(r["rule"])
        assert r["failed"] == sum(bool(b & bit) for b in bits.values()) and r["only"] == sum(b & rules.POLICIES["v1"] == bit for b in bits.values())


NASTY = "doc_id long, text string, lang string, source string, n_chars long, size long, u long, spans string, base string, key string, _h long, page_id long"


def _nasty(spark):
    long_ = " ".join(f"word{i % 997} user{i}@mail.org" for i in range(2_000))
    texts = [None, "", " \n\t ", "one", "one", long_, "the same text is here twice " * 12, "the same text is here twice " * 12, "é" * 5000, "# | % &" * 40]
    rows = [(i, t, None if i == 2 else "en", "s" if i % 2 else None, 0, 1, 2, "x", "y", "z", 3, 4) for i, t in enumerate(texts)]
    return spark.createDataFrame([*rows, rows[6], (None, "null id", *rows[0][2:])], NASTY)


@pytest.mark.parametrize("name", ["op1_best_fit_packing", "op4_license_containment", "op6_entropy_mixing", "op7_covering_simhash", "op8_bootstrapped_pii", "op10_rule_ledger", "op2_channel_toxicity", "op9_kneser_ney_quality"])
def test_hard_rows_and_empty_tables(spark, tmp_path, name):
    docs = _nasty(spark)
    labels = spark.createDataFrame([(0, 1, 0), (5, 1, 0), (6, 0, 1)], "doc_id long, quality int, toxic int")
    for i, (d, lab) in enumerate(((docs, labels), (docs.limit(0), labels.limit(0)), (docs, labels.limit(0)))):
        if i == 2 and name not in ("op2_channel_toxicity", "op9_kneser_ney_quality"):
            continue
        d.write.parquet(f"{tmp_path}/{i}/documents.parquet")
        lab.write.parquet(f"{tmp_path}/{i}/labels.parquet")
        n = registry.queries()[name](spark, f"{tmp_path}/{i}").count()
        assert n >= d.count() if name.startswith("op1_") else n == d.count()


def test_pipeline_stages_keep_columns_and_hard_rows(spark):
    import corpus_pipeline

    docs = _nasty(spark)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        for d in (docs, docs.limit(0)):
            out = stage(spark, d, "")
            assert out.columns == docs.columns, name
            ids = [r["doc_id"] for r in out.select("doc_id").collect()]
            assert len(ids) == len(set(ids)) or name not in ("simhash near-dedup",)


def test_pipeline_copies_are_met_by_fingerprints(spark, monkeypatch):
    import pyarrow as pa

    import corpus_pipeline

    def nothing(least):  # no prefix gives a pair
        return lambda batches: (pa.RecordBatch.from_arrays([pa.array([], pa.int64())] * 3, names=["a", "b", "need"]) for _ in batches)

    monkeypatch.setattr(simhash, "_first_pairs", nothing)
    monkeypatch.setattr(simhash, "_other_pairs", nothing)
    words = [f"w{i}" for i in range(400)]
    near = " ".join([*words, "end"])
    prints = [simhash.fingerprint(t, 5) for t in (" ".join(words), near)]
    assert (prints[0] ^ prints[1]).bit_count() <= 3
    rows = _docs(spark, [(1, " ".join(words)), (2, near), (3, " ".join(reversed(words)))])
    assert {r["doc_id"] for r in corpus_pipeline.simhash_dedup(spark, rows, "").collect()} == {1, 3}


def test_pipeline_crowded_buckets_make_no_pair_rows(spark, monkeypatch):
    import pyarrow as pa

    def nothing(least):
        return lambda batches: (pa.RecordBatch.from_arrays([pa.array([], pa.int64())] * 3, names=["a", "b", "need"]) for _ in batches)

    monkeypatch.setattr(simhash, "_first_pairs", nothing)
    monkeypatch.setattr(simhash, "_other_pairs", nothing)
    monkeypatch.setattr(simhash, "links", lambda prints, forest: spark.createDataFrame([], "a long, b long"))
    words, texts = [f"w{i}" for i in range(200)], []
    for c in range(60):
        texts.append(" ".join([*words[: 3 * c], f"new{c}", *words[3 * c + 1 :]]))
    texts.append(" ".join([*words[:120], *(f"far{i}" for i in range(80))]))  # shares a passage, is no copy
    out = {r["doc_id"]: r["component_id"] for r in simhash.near_copies(_docs(spark, list(enumerate(texts)))).collect()}
    assert out == {i: 0 for i in range(60)} | {60: 60}


def test_pipeline_parities_settle_crowded_buckets_without_whole_sets(spark, monkeypatch):
    import pyarrow as pa

    def nothing(*names):
        return lambda *args: lambda batches: (pa.RecordBatch.from_arrays([pa.array([], pa.int64())] * len(names), names=names) for _ in batches)

    for name in ("_first_pairs", "_other_pairs"):
        monkeypatch.setattr(simhash, name, nothing("a", "b", "need"))
    monkeypatch.setattr(simhash, "_crowded", nothing("a", "b"))  # no tile's sets are needed
    monkeypatch.setattr(simhash, "links", lambda prints, forest: spark.createDataFrame([], "a long, b long"))
    passage, texts = [f"w{i}" for i in range(60)], []
    for c in range(40):  # pairs of near copies; all share one passage
        own = [f"own{c}x{i}" for i in range(12)]
        texts += [" ".join([*passage, *own]), " ".join([*passage, *own[:-1], "other"])]
    docs = _docs(spark, list(enumerate(texts)))
    assert {r["doc_id"]: r["component_id"] for r in simhash.near_copies(docs).collect()} == {i: i - i % 2 for i in range(80)}


def test_parities_rule_out_no_link():
    import numpy as np

    rng = np.random.default_rng(5)
    base, sets = rng.integers(-(2**63), 2**63 - 1, 5000), []
    for _ in range(90):
        held = base[: rng.integers(1, 5000)].copy()
        lost = rng.permutation(len(held))[: int(len(held) * rng.uniform(0, 0.2))]
        held[lost] = rng.integers(-(2**63), 2**63 - 1, len(lost))
        sets.append(np.unique(held))
    sets.sort(key=len)
    n, odd, label = np.array([len(s) for s in sets]), [simhash._odd(s) for s in sets], np.arange(90) // 2
    for part in (np.zeros(90, np.int64), np.arange(90) % 2):
        want = set()
        for i in range(90):
            for j in range(i + 1, 90):
                both = len(np.intersect1d(sets[i], sets[j]))
                if label[i] != label[j] and both >= 0.8 * (n[i] + n[j] - both) and (not part.any() or part[i] != part[j]):
                    want.add((i, j))
        pairs, met = simhash._unruled(n, label, odd, part, 0.8, 10**6, block=16)
        got = set(zip(*(p.tolist() for p in pairs)))
        assert want and want <= got and len(got) < 2 * len(want) + 20
        assert met.nonzero()[0].tolist() == sorted({x for p in got for x in p})
        none, same = simhash._unruled(n, label, odd, part, 0.8, 0, block=16)
        assert none is None and (same == met).all()


def test_links_of_a_tile_connect_what_all_its_links_connect():
    import numpy as np

    rng = np.random.default_rng(3)
    for trial in range(20):
        bases = [rng.integers(-(2**62), 2**62, rng.integers(1, 3000 if trial < 4 else 60)) for _ in range(5)]
        sets = []
        for _ in range(120):
            base = bases[rng.integers(len(bases))]
            sets.append(np.unique(np.concatenate([base[rng.random(len(base)) < rng.uniform(0.8, 1)], rng.integers(-(2**62), 2**62, rng.integers(0, 4))])))
        sets = sorted((s for s in sets if len(s)), key=len)
        part = rng.integers(0, 2, len(sets)) if trial % 2 else np.zeros(len(sets), np.int64)
        want, got, label = simhash.Forest(), simhash.Forest(), rng.permutation(len(sets)) // 2
        for i in range(len(sets)):
            for j in range(i):
                both = len(np.intersect1d(sets[i], sets[j]))
                if both >= 0.8 * (len(sets[i]) + len(sets[j]) - both) - 1e-9 and (part[i] != part[j] or not part.any()):
                    want.link(int(label[i]), int(label[j]))
        found = list(simhash._bound(np.array([len(s) for s in sets]), label, sets, part, 0.8, block=16))
        for i, j in found:
            both = len(np.intersect1d(sets[i], sets[j]))
            assert both >= 0.8 * (len(sets[i]) + len(sets[j]) - both) - 1e-9
            assert got.link(int(label[i]), int(label[j]))
        assert [want.find(int(x)) for x in label] == [got.find(int(x)) for x in label] and found


def test_worker_caches_are_emptied(monkeypatch):
    from ringlink.llm import common

    emptied = []
    monkeypatch.setattr(common, "KEPT", [lambda: emptied.append(1)])
    assert list(common.lean(iter)([1, 2])) == [1, 2] and emptied == [1]
    assert list(common.lean(iter, drop=False)([3])) == [3] and emptied == [1]
