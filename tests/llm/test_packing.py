import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from veilmatch.llm.packing import PieceIds, pack, pieces, plan, token_bytes

PATH = public_tokenizers.path("word_bpe_49k.json")
ODD = [
    None, "", " ", "\n", "Don't we'LL they're O'Brien's 3.14 x²", "ÀÉÎ straße ŁÓDŹ İstanbul ΣΑΣ Σ", "é äbc ́x", "日本語 текст Ωmega", "a\tb c d\x0be\r\nf",
    "<|endoftext|> x<|startoftext|>y", "!!!??? -- ... ***", "K Å ﬀ ǆ", "word," * 3000, "​zero ﻿bom", "1234567890 ½ Ⅷ", "a\x1cb\x1f c\x85d\xa0e\u2003f\u3000g\u180eh", "~!x \x00y \x7fz", "🙂🙂 emoji👩‍👩‍👧",
]


def test_ids_equal_the_library(spark, sf):
    whole = Tokenizer.from_file(PATH)
    words = PieceIds(PATH, most=500)
    texts = ODD + [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    for t in texts:
        want = whole.encode(t or "", add_special_tokens=False).ids + [0]
        assert np.frombuffer(token_bytes(t, words), "<u4").tolist() == want, repr(t)[:80]


def test_pieces_and_places_are_whole(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()] + [(5000 + i, t) for i, t in enumerate(ODD)] + [(5000, None), (None, "null id")]
    docs = spark.createDataFrame([(i, t, 3, "y") for i, t in rows], "doc_id long, text string, length int, piece string").repartition(5)
    got = pack(pieces(docs, PATH)).collect()
    whole = Tokenizer.from_file(PATH)
    want = defaultdict(int)
    for i, t in rows:
        ids = np.array(whole.encode(t or "", add_special_tokens=False).ids + [0], "<u4")
        for k in range(0, len(ids), 2048):
            want[i, k // 2048, k, len(ids[k : k + 2048]), zlib.crc32(ids[k : k + 2048].tobytes())] += 1
    have = defaultdict(int)
    sequences = defaultdict(list)
    for r in got:
        have[r.doc_id, r.piece, r.start, r.length, r.ids_crc32] += 1
        sequences[r.sequence_id].append((r.offset, r.length))
    assert have == want
    for spans in sequences.values():
        end = 0
        for offset, length in sorted(spans):
            assert offset == end
            end += length
        assert end <= 2048
    total = sum(r.length for r in got)
    assert len(sequences) <= 1.02 * -(-total // 2048) + 1


def test_empty_table(spark):
    assert pack(pieces(spark.createDataFrame([], "doc_id long, text string"), PATH)).count() == 0


def test_plan_uses_every_piece_once_and_few_sequences():
    rng = np.random.default_rng(3)
    for most, n in ((64, 500), (64, 5), (2048, 4000), (2048, 1)):
        counts = np.bincount(rng.integers(1, most + 1, n), minlength=most + 1)
        lines = plan(counts, most)
        used = np.zeros(most + 1, int)
        for lengths, times in lines:
            assert sum(lengths) <= most and times > 0
            for x in lengths:
                used[x] += times
        assert (used == counts).all()
        least = -(-int((counts * np.arange(most + 1)).sum()) // most)
        assert sum(t for _, t in lines) <= least * 1.05 + 2


def test_exact_combinations_fill_gaps():
    counts = np.zeros(21, int)
    counts[[12, 8]] = 1  # single
    counts[[11, 5, 4]] = 1  # pair
    counts[[14, 3, 2, 1]] = 1  # triple
    assert sum(t for _, t in plan(counts, 20)) == 3
