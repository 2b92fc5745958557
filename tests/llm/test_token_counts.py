import random

import public_tokenizers
import pyarrow.parquet as pq
import sentencepiece

from zplane.llm.token_counts import count_tokens
from zplane.llm.token_fst import compile_model

PATH = public_tokenizers.path("piece_bpe_32k.model")


def _lib(texts):
    sp = sentencepiece.SentencePieceProcessor(model_file=PATH)
    return [len(x) for x in sp.encode(texts, num_threads=1)]


def test_equals_the_library_on_odd_texts_at_any_chunk_size():
    t, rng = compile_model(PATH), random.Random(1)
    alphabet = " ▁ab  thet\n①é日\t'.<s></s>0123ninger  ▁the▁ the ing\x00😀"
    texts = ["", " ", "  a b  ", "▁▁", " " * 15, " " * 31, " " * 100 + "x", "<s> x </s>", "a" * 3000]
    for _ in range(3000):
        s = "".join(rng.choice(alphabet) for _ in range(rng.randint(0, 40)))
        texts.append(s.replace("a", " " * rng.randint(1, 40)) if rng.random() < 0.3 else s)
    assert [t.count(s, chunk_chars=rng.choice([1, 2, 3, 7, 1000])) for s in texts] == _lib(texts)


def test_chunk_maps_compose_associatively():
    t = compile_model(PATH)
    maps = [t.chunk(x) for x in (" the qu", "ick", "er  fo", "x jumps", " ", "over")]
    left = maps[0]
    for m in maps[1:]:
        left = t.compose(left, m)
    right = maps[-1]
    for m in reversed(maps[:-1]):
        right = t.compose(m, right)
    assert left == right


def test_bounded_memory_gives_the_same_counts():
    from zplane.llm.token_fst import Transducer

    big = compile_model(PATH)
    small = Transducer(list(big.score.items()) + [("▁" * n, -1e9) for n in (*range(2, 15), 16)], max_states=300, max_units=50)
    texts = pq.read_table("/root/testdata/sf0.001/documents.parquet").column("text").to_pylist()[:30]
    assert [small.count(x) for x in texts] == [big.count(x) for x in texts]


def test_whole_table_and_edges(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r.doc_id: r for r in count_tokens(docs, PATH).collect()}
    texts = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    assert [rows[i].n_tokens for i, _ in texts] == _lib([t for _, t in texts])
    assert all(rows[i].n_bytes == len(t.encode()) and rows[i].over_limit == (rows[i].n_tokens > 4096) for i, t in texts)
    odd = spark.createDataFrame([(1, None, 5), (None, "x", 5), (1, None, 5)], "doc_id long, text string, n_tokens int")
    assert sorted((r.doc_id or 0, r.n_bytes, r.n_tokens) for r in count_tokens(odd, PATH).collect()) == [(0, 1, 1), (1, 0, 0), (1, 0, 0)]
    assert count_tokens(odd.limit(0), PATH).count() == 0


def test_words_with_one_polynomial_hash_are_kept_apart():
    from zplane.llm.token_fst import UnitCounts

    counts = UnitCounts(compile_model(PATH))
    for a, b in ("t", "h"), ("a", "1"), ("e", "q"):
        word = a
        while len(word) < 1024:
            word += word.translate(str.maketrans(a + b, b + a))
        other = word.translate(str.maketrans(a + b, b + a))
        texts = [word, other, f"x {word} y", f"x {other} y"]
        assert [int(counts([t])[0]) for t in texts] == _lib(texts) == counts(texts).tolist()
