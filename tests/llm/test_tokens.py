import zlib

import numpy as np
from divknn.llm import binary_output, packing
from divknn.llm.common import shared_dir, table
from divknn.llm.tokens import vocabulary_path
from tokenizers import Tokenizer

from .helpers import AWKWARD, docs

TRICKY = [(40, "It's  a <|endoftext|> TEST of　spaces é ́x ΣΑΣ 12345 don't've\n\n'll"), (41, "ﬁ Å̧ ​ zero"), (42, "word " * 9000), (43, "ÀÖ×÷ßÿ IT'S we'll's a\x85b\xa0c\x1cd\x1f ª²µ <|startoftext|> <| x|> ###De%%% 1234 ÇA.\"'re'T")]


def ids_of(rows, end):
    t = Tokenizer.from_file(vocabulary_path())
    return [(k, t.encode(x or "", add_special_tokens=False).ids + [end]) for k, x in rows]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_arrow_round_trip(spark, sf):
    for df in (table(spark, sf, "documents"), docs(spark, AWKWARD + TRICKY)):
        rows = sorted(((r[0], r[1]) for r in df.select("doc_id", "text").collect()), key=lambda r: (r[0] is not None, r[0] or 0))
        want, at = [], 0
        for k, ids in ids_of(rows, 2):
            want.append((k, at, len(ids), crc(ids)))
            at += len(ids)
        folder = shared_dir(spark)
        manifest = binary_output.write_shards(df.repartition(3), folder, vocabulary_path())
        got = sorted(map(tuple, binary_output.read_documents(manifest, folder).collect()), key=lambda r: r[1])
        assert got == want
        first = manifest.orderBy("shard").first()
        ids, mask = binary_output.Sequences(folder, first["ids"]).row(0)
        whole = [x for _, i in ids_of(rows, 2) for x in i][: binary_output.LENGTH]
        n = min(len(whole), first["n_ids"])
        assert ids[: min(n, 2048)].tolist() == whole[: min(n, 2048)] and mask.sum() == min(first["n_ids"], 2048)


def test_arrow_empty(spark):
    folder = shared_dir(spark)
    assert binary_output.read_documents(binary_output.write_shards(docs(spark, []), folder, vocabulary_path()), folder).count() == 0


def check_packing(rows, want_pieces, capacity):
    assert sorted(map(str, ((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows))) == sorted(map(str, want_pieces))
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for own in by.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_packing(spark, sf):
    for df in (table(spark, sf, "documents"), docs(spark, AWKWARD + TRICKY)):
        want, total = [], 0
        for k, ids in ids_of([(r[0], r[1]) for r in df.select("doc_id", "text").collect()], 1):
            total += len(ids)
            want += [(k, i, s, len(ids[s : s + 4096]), crc(ids[s : s + 4096])) for i, s in enumerate(range(0, len(ids), 4096))]
        n = check_packing(packing.pack(df, vocabulary_path()).collect(), want, 4096)
        assert n <= -(-total // 4096) + 1
    assert packing.pack(docs(spark, []), vocabulary_path()).count() == 0


def test_plan_places_each_piece_once():
    rng = np.random.default_rng(1)
    for capacity, most, n in ((10, 10, 50), (100, 100, 3000), (100, 40, 500), (100, 60, 1), (3, 3, 7)):
        lengths = rng.integers(1, most + 1, n)
        hist = {int(k): int(v) for k, v in zip(*np.unique(lengths, return_counts=True), strict=True)}
        runs, made = packing.plan_bins(hist, capacity)
        used = {}
        for length, a, b, first, offset in runs:
            for j in range(b - a):
                used.setdefault(first + j, []).append((offset, length))
        assert sum(map(len, used.values())) == n and len(used) == made
        for own in used.values():
            own.sort()
            assert [o for o, _ in own] == list(np.cumsum([0] + [x for _, x in own])[:-1]) and sum(x for _, x in own) <= capacity
        for length in hist:
            spans = sorted((a, b) for x, a, b, _, _ in runs if x == length)
            assert [a for a, _ in spans] == [0] + [b for _, b in spans][:-1] and spans[-1][1] == hist[length]
        assert made <= np.ceil(lengths.sum() / capacity) * 1.35 + 1
