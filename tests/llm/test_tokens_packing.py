import io
import random
import struct
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from tokenizers import Tokenizer

from tierbit.llm import packing, tokenio
from tierbit.llm.tokens import Encoder

ODD = ["", "  ", "\n\n a \t b  ", "it's WE'LL don't '' 's", "a\x0bb\x1cc\x85d e", "²³¹ ½ Ⅷ ٣", "ñandú ÀÉ ß × ÷ ÿ", "é x̃", "<|endoftext|> <|startoftext|>", "a <|endoftext|> b", "A <|EndOfText|> b<|startoftext|>", "日本語 🙂🙂", "x" * 5000, "a1b22c333", "$$$ *** && %%%", "12 345,678.9", "word " * 3000]
SCHEMA = "doc_id long, text string, start string"


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_encoder_equals_the_library(name):
    lib = Tokenizer.from_file(P.path(name))  # as it comes
    rng, enc = random.Random(1), Encoder(P.path(name), cached=50)
    pool = "abcXYZ  \n\t'sdrelmtvé ñÑ0123456789.,!?-#$%&*()<|>²٣ "
    texts = ODD + ["".join(rng.choices(pool, k=rng.randint(0, 80))) for _ in range(400)]
    for t, got in zip(texts, enc.encode(texts)):
        assert np.frombuffer(got, "<u4").tolist() == lib.encode(t, add_special_tokens=False).ids, t


def test_frames_round_trip_and_point_reads():
    sink = io.BytesIO()
    writer = tokenio.FrameWriter(sink, frame_bytes=100)
    docs = [(None, b"")] + [(i, struct.pack(f"<{i % 30}I", *range(i % 30))) for i in range(200)]
    for d in docs:
        writer.add(*d)
    writer.close()
    reader = tokenio.FrameReader(io.BytesIO(sink.getvalue()))
    assert list(reader.documents()) == docs
    one = tokenio.FrameReader(io.BytesIO(sink.getvalue()))
    assert list(one.documents({77})) == [docs[78]] and one.frames_read == 1 < len(one.entries) - 1
    import zstandard

    whole = zstandard.ZstdDecompressor().stream_reader(io.BytesIO(sink.getvalue()), read_across_frames=True).read()
    assert whole == b"".join(d[1] for d in docs)  # any reader can skip the tables
    broken = bytearray(sink.getvalue())
    broken[reader.entries[0][0] + 14] ^= 1
    with pytest.raises(Exception):
        list(tokenio.FrameReader(io.BytesIO(bytes(broken))).documents())


def test_files_of_a_table(spark):
    rows = [(i, t, "x") for i, t in enumerate(ODD)] + [(None, None, None), (4, "again", "y"), (4, ODD[4], "z"), (4, ODD[4], "z")]
    path = P.path("word_bpe_49k.json")
    manifest = tokenio.write_tokens(spark.createDataFrame(rows, SCHEMA).repartition(5), path, 2, frame_bytes=200)
    got = tokenio.read_tokens(spark, manifest).collect()
    assert len(got) == len(rows)
    got.sort(key=lambda r: r["start"])
    at = 0
    for r in got:
        assert r["start"] == at and r["n_tokens"] == len(r["ids"]) // 4 and r["ids"][-4:] == struct.pack("<I", 2)
        at += r["n_tokens"]
    keys = [-1 if r["doc_id"] is None else r["doc_id"] for r in got]
    assert keys == sorted(keys)
    enc = Encoder(path)
    assert sorted(bytes(r["ids"]) for r in got) == sorted(enc.whole(t or "") + struct.pack("<I", 2) for _, t, _ in rows)
    assert {d for d, *_ in tokenio.read_some(spark, manifest, [7])} == {7}
    empty = tokenio.write_tokens(spark.createDataFrame([], SCHEMA), path, 2)
    assert tokenio.read_tokens(spark, empty).count() == 0


def test_fill_is_the_best_sum():
    rng = random.Random(3)
    for _ in range(150):
        counts = {rng.randint(1, 40): rng.randint(1, 4) for _ in range(rng.randint(1, 6))}
        space = rng.randint(1, 90)
        sums = {0}
        for x, n in counts.items():
            sums = {s + x * k for s in sums for k in range(n + 1)}
        used = packing.fill(space, counts)
        assert sum(x * n for x, n in used.items()) == max(s for s in sums if s <= space)
        assert all(n <= counts[x] for x, n in used.items())


def test_plan_places_everything_within_the_window():
    rng = random.Random(5)
    counts = {rng.randint(1, 256): rng.randint(1, 2000) for _ in range(120)} | {256: 77}
    plan = packing.plan_windows(counts, 256)
    placed: dict[int, int] = {}
    for times, used in plan:
        assert sum(x * n for x, n in used.items()) <= 256
        for x, n in used.items():
            placed[x] = placed.get(x, 0) + n * times
    assert placed == counts
    windows, tokens = sum(t for t, _ in plan), sum(x * n for x, n in counts.items())
    halves = sum(n for x, n in counts.items() if x > 128)  # no two of them share a window
    assert windows <= 1.02 * max(tokens / 256, halves) + 2


def test_pack_covers_every_token_once(spark):
    rng = random.Random(6)
    rows = [(i, " ".join(rng.choices(["alpha", "beta", "gamma", "é"], k=rng.choice([0, 3, 9, 9, 9, 300]))), "x") for i in range(150)] + [(None, None, None), (3, "twice", "a"), (3, "twice", "a")]
    path = P.path("byte_bpe_50k.json")
    out = packing.pack(spark.createDataFrame(rows, SCHEMA), path, 1, window=64, share=20, with_ids=True)
    got, enc = out.collect(), Encoder(path)
    want = sorted(enc.whole(t or "") + struct.pack("<I", 1) for _, t, _ in rows)
    by: dict = {}
    for r in got:
        assert r["length"] == len(r["ids"]) // 4 and r["ids_crc32"] == zlib.crc32(r["ids"])
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for s in by.values():
        at = 0
        for offset, n in sorted(s):
            assert offset == at
            at += n
        assert at <= 64
    assert all(len(s) == 1 for s in by.values() if s[0][1] == 64)
    planned = sorted(i for i, s in by.items() if s[0][1] < 64)
    assert planned == list(range(len(planned)))
    pieces: dict = {}
    for r in got:
        pieces.setdefault((r["doc_id"], r["doc_tokens"], r["start"]), []).append(bytes(r["ids"]))
    for i, t, _ in rows:  # every document's pieces join up to the library's ids
        ids = enc.whole(t or "") + struct.pack("<I", 1)
        for at in range(0, len(ids) // 4, 64):
            pieces[i, len(ids) // 4, at].remove(ids[4 * at : 4 * (at + 64)])
    assert not any(pieces.values())
    assert sum(r["length"] for r in got) == sum(map(len, want)) // 4
    tokens = sum(map(len, want)) // 4
    assert len(by) <= 1.05 * tokens / 64 + 2
    seqs = packing.sequences(out, 64).collect()
    assert all(len(r["ids"]) == 256 for r in seqs) and sum(r["n_tokens"] for r in seqs) == tokens
    assert packing.pack(spark.createDataFrame([], SCHEMA), path, 1).count() == 0


@pytest.mark.parametrize("file_bytes", [400, 1 << 20])
def test_files_roll_and_a_repeated_row_is_dealt_out(spark, file_bytes):
    rows = [(5, "the same words again", "x")] * 900 + [(i, f"number {i}", None) for i in range(300)]
    manifest = tokenio.write_tokens(spark.createDataFrame(rows, SCHEMA).repartition(3), P.path("word_bpe_49k.json"), 2, frame_bytes=100, file_bytes=file_bytes)
    files = manifest.orderBy("file_no").collect()
    assert (len(files) > 20) == (file_bytes == 400)
    at = 0
    for i, f in enumerate(files):
        assert f["file_no"] == i and f["start"] == at
        at += f["n_tokens"]
    got = tokenio.read_tokens(spark, manifest).orderBy("start").collect()
    assert [r["doc_id"] for r in got] == sorted(r[0] for r in rows) and sum(r["n_tokens"] for r in got) == at


def test_reading_many_frames_is_linear():
    import time

    sink = io.BytesIO()
    writer = tokenio.FrameWriter(sink, frame_bytes=8)
    for i in range(60_000):
        writer.add(i, b"\x01\x00\x00\x00" * 2)
    writer.close()
    start = time.process_time()
    assert sum(1 for _ in tokenio.FrameReader(io.BytesIO(sink.getvalue())).documents()) == 60_000
    assert time.process_time() - start < 10


def test_registered_queries_rebuild_every_document(spark):
    """op6 and op7 as registered, against an unmodified library."""
    import __spark_entry__ as E

    sf = "/root/testdata/sf0.001"
    texts = {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for op, name, end in (("op6_tokens", "word_bpe_49k.json", 2), ("op7_packing", "byte_bpe_50k.json", 1)):
        lib = Tokenizer.from_file(P.path(name))
        want = {i: np.array([*lib.encode(t, add_special_tokens=False).ids, end], "<u4").tobytes() for i, t in texts.items()}
        got = E.queries()[op](spark, sf).collect()
        if op == "op6_tokens":
            at = 0
            for r in sorted(got, key=lambda r: r["doc_id"]):
                assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(want[r["doc_id"]]) // 4, zlib.crc32(want[r["doc_id"]]))
                at += r["n_tokens"]
            assert len(got) == len(texts)
        else:
            upto = dict.fromkeys(texts, 0)
            for r in sorted(got, key=lambda r: (r["doc_id"], r["start"])):
                own = want[r["doc_id"]]
                assert r["start"] == upto[r["doc_id"]] and r["doc_tokens"] == len(own) // 4 and r["length"] <= 2048
                assert r["ids_crc32"] == zlib.crc32(own[4 * r["start"] : 4 * (r["start"] + r["length"])])
                upto[r["doc_id"]] += r["length"]
            assert all(n == len(want[i]) // 4 for i, n in upto.items())
            windows: dict = {}
            for r in got:
                windows.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
            for w in windows.values():
                ends = [0, *(o + n for o, n in sorted(w))]
                assert [o for o, _ in sorted(w)] == ends[:-1] and ends[-1] <= 2048
