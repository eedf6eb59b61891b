import random
import zlib
from collections import defaultdict

import public_tokenizers
from tokenizers import Tokenizer

from ringlink.llm import packing

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_ids_by_chunk_are_those_of_the_whole_text():
    rng, whole, ids = random.Random(5), Tokenizer.from_file(PATH), packing.Ids(PATH)
    bits = ["Word", "élan", "ÉTÉ", "don't", "it's", "x1y", "9", "...", "!!", "'s", "<|endoftext|>", "é", "́", "ΣΑΣ", "İ", "日本", "_", "a_b", "#$%", ",", "|", "ß", "\x1c", "🙂", "'", "½"]
    for _ in range(3000):
        text = "".join(rng.choice(bits) + rng.choice(["", "", " ", "\n", "  "]) for _ in range(rng.randint(0, 12)))
        want = b"".join(i.to_bytes(4, "little") for i in whole.encode(text, add_special_tokens=False).ids)
        assert ids.of(text) == want, repr(text)


def test_words_of_latin_letters_skip_the_whole_tokenizer():
    rng, whole, ids = random.Random(6), Tokenizer.from_file(PATH), packing.Ids(PATH)
    letters = [c for c in map(chr, range(256)) if c.isalpha()]
    words = [*letters, *("".join(rng.choice(letters[: rng.choice([52, 999])]) for _ in range(rng.randint(1, 30))) for _ in range(5000))]
    ids.part("")  # what follows a word without signs
    encode, ids.encode = ids.encode, None  # such a word never gets there
    for word in words:
        assert ids.of(word) == encode(word), word
    ids.encode = encode
    assert ids.of("Ωmega ﬁ ŉ") == b"".join(i.to_bytes(4, "little") for i in whole.encode("Ωmega ﬁ ŉ", add_special_tokens=False).ids)


def test_packing_places_every_id_once(spark):
    rng = random.Random(2)
    texts = [None, "", "a b c", "long " * 9000, *("word " * rng.randint(1, 3000) for _ in range(60))]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    rows = packing.digest(docs).collect()
    whole, pieces, bins = Tokenizer.from_file(PATH), defaultdict(list), defaultdict(list)
    for r in rows:
        pieces[r["doc_id"]].append(r)
        bins[r["sequence_id"]].append(r)
    for i, t in enumerate(texts):
        ids, at = [*whole.encode(t or "", add_special_tokens=False).ids, 1], 0
        for k, r in enumerate(sorted(pieces[i], key=lambda r: r["piece"])):
            part = ids[at : at + 4096]
            assert (r["piece"], r["start"], r["length"]) == (k, at, len(part))
            assert r["ids_crc32"] == zlib.crc32(b"".join(x.to_bytes(4, "little") for x in part))
            at += len(part)
        assert at == len(ids)
    for b in bins.values():
        at = 0
        for r in sorted(b, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 4096
    assert len(bins) <= -(-sum(r["length"] for r in rows) // 4096) + 1


def test_rows_of_a_batch_come_in_steps():
    import pyarrow as pa

    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(700)), "text": [None if i % 7 == 0 else f"t{i}" for i in range(700)]})
    assert list(packing._rows(batch)) == list(zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist())) == list(packing._rows(batch, 1))
    assert list(packing._rows(batch.slice(0, 0))) == []
