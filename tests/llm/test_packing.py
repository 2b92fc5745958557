import random
import zlib

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from zplane.llm.packing import Schedule, WordEncoder, pack

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_encoder_equals_the_library():
    rng, e, t = random.Random(1), WordEncoder(PATH, most=2000), Tokenizer.from_file(PATH)
    alphabet = "ab İéß'sst.,!<|>\n\t ́ᾳΣ九1２_-😀"
    texts = ["", " ", ".,", "a.b", "x..y", "Ünï"] + ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 25))) + rng.choice(["", "<|endoftext|>", " don't"]) for _ in range(4000)]
    for lo in range(0, len(texts), 500):
        flat, at = e(texts[lo : lo + 500])
        got = [flat[a:b].tolist() for a, b in zip(at[:-1], at[1:])]
        assert got == [x.ids for x in t.encode_batch(texts[lo : lo + 500], add_special_tokens=False)]


def test_schedule_fills_every_place_once_and_keeps_deficits_small():
    rng = random.Random(2)
    for totals in ([5000], [100_000, 3, 700], [1, 1, 1], [12_345, 99_999, 5000, 0, 256], [4096 * 3]):
        s = Schedule(totals)
        owner = np.full(s.n, -1)
        begins = np.concatenate([np.arange(s.full + 1) * s.length, s.tail_ends])
        for i, t in enumerate(totals):
            at = 0
            while at < t:
                sizes = []
                while at + sum(sizes) < t and len(sizes) < 20:
                    sizes.append(min(rng.randint(1, 900), t - at - sum(sizes)))
                doc, start, size, seq, off = s.pieces(i, at, sizes)
                assert (np.bincount(doc, weights=size) == sizes).all()
                for p, m in zip(begins[seq] + off, size):
                    assert (owner[p : p + m] == -1).all()
                    owner[p : p + m] = i
                at += sum(sizes)
        assert (owner >= 0).all()
        for w in range(1, s.full + 1):  # at every window end each source is within a block (and rounding) of its target
            got = np.bincount(owner[: w * s.length], minlength=len(totals))
            assert (np.abs(got - np.array(totals) * (w * s.length / s.n)) <= 2 * s.block + 1).all()
        tail = np.diff([s.full * s.length, *s.tail_ends])
        assert all(x & (x - 1) == 0 for x in tail.tolist())


def _check(rows, texts):
    t = Tokenizer.from_file(PATH)
    by: dict = {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
    for i, text in texts.items():
        ids = t.encode(text or "", add_special_tokens=False).ids + [2]
        at = 0
        for r in sorted(by[i], key=lambda r: r.start):
            part = np.array(ids[r.start : r.start + r.length], "<u4").tobytes()
            assert r.start == at and r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(part) and list(r.ids) == ids[r.start : r.start + r.length]
            at += r.length
        assert at == len(ids)
    seqs: dict = {}
    for r in rows:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in seqs.values():
        at = 0
        for off, n in sorted(parts):
            assert off == at
            at += n
        assert at == 4096 or at & (at - 1) == 0
    return len(seqs)


def test_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = pack(docs, PATH).collect()
    _check(rows, {r.doc_id: r.text for r in docs.collect()})


def test_edges(spark):
    rows = [(1, None, "a"), (2, "", None), (3, "x " * 9000, "a"), (4, "hello <|endoftext|> world", "b"), (5, "z", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").selectExpr("*", "'q' as ids", "1 as start")
    _check(pack(docs, PATH).collect(), {r[0]: r[1] for r in rows})
    twice = pack(docs.union(docs), PATH, rates={"a": 3, "b": 1}).collect()
    assert sum(r.length for r in twice) == 2 * sum(r.length for r in pack(docs, PATH).collect())
    assert pack(docs.limit(0), PATH).count() == 0


def test_words_with_one_polynomial_hash_are_kept_apart():
    e, t = WordEncoder(PATH), Tokenizer.from_file(PATH)
    for a, b in ("t", "h"), ("e", "q"):
        word = a
        while len(word) < 1024:
            word += word.translate(str.maketrans(a + b, b + a))
        other = word.translate(str.maketrans(a + b, b + a))
        for text in (word, other, f"x {word}, {other}"):
            assert e([text])[0].tolist() == t.encode(text, add_special_tokens=False).ids
