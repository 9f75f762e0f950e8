import random
import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from rarespan.llm.packing import UnitEncoder, pack

PATH = public_tokenizers.path("byte_bpe_50k.json")


def plain():
    t = Tokenizer.from_file(PATH)
    return t


def texts(n, seed):
    rnd = random.Random(seed)
    alphabet = " \n\t\r  ab'sZ1.$é中 　\x1c\x85"
    out = ["".join(rnd.choice(alphabet) for _ in range(rnd.choice([0, 1, 2, 3, 5, 40, 300, 5000]))) for _ in range(n)]
    return out + ["<|endoftext|> a", "don't we'll  x", "x" * 5000 + " " + "中" * 300]


def test_units_equal_the_whole_tokenizer():
    import pyarrow as pa

    from rarespan.llm import textkit as T

    rows = texts(800, 3)
    with open(PATH, encoding="utf-8") as f:
        encode = UnitEncoder(f.read(), bits=9)  # so small that it is cleared on the way
    raw, offsets = T.text_buffers(pa.array(rows))
    got = []
    for lo, hi in T.blocks(offsets, 20_000):
        at = offsets[lo : hi + 1]
        ids, counts = encode(raw[at[0] : at[-1]], at - at[0])
        got += [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])]
    assert got == [e.ids for e in plain().encode_batch(rows, add_special_tokens=False)]


def test_pieces_tile_texts_and_sequences(spark):
    rows = [(i, t, 0) for i, t in enumerate(texts(400, 4))]
    rows += [(1000, None, 1), (1001, "", 1), (7, rows[7][1], 2)]
    df = spark.createDataFrame(rows, "doc_id long, text string, length long").repartition(5)
    got = pack(df, PATH, window=256, open_windows=4, keep_ids=True).collect()
    whole = plain()
    want = {i: whole.encode(t or "", add_special_tokens=False).ids + [1] for i, t, _ in rows if i != 7}
    docs, sequences = defaultdict(list), defaultdict(list)
    for r in got:
        assert zlib.crc32(bytes(r.ids)) == r.ids_crc32 and len(r.ids) == 4 * r.length
        docs[r.doc_id].append(r)
        sequences[r.sequence_id].append(r)
    for i, ids in want.items():
        pieces = sorted(docs[i], key=lambda r: r.start)
        assert [x for p in pieces for x in np.frombuffer(p.ids, "<u4").tolist()] == ids
        assert all(p.doc_tokens == len(ids) for p in pieces)
    assert sum(p.length for p in docs[7]) == 2 * docs[7][0].doc_tokens
    padding = 0
    for pieces in sequences.values():
        pieces.sort(key=lambda r: r.offset)
        size = 0
        for p in pieces:
            assert p.offset == size
            size += p.length
        assert size <= 256
        padding += 0 if size & (size - 1) == 0 else 256 - size
    assert padding == 0
    assert pack(df.limit(0), PATH).collect() == []
