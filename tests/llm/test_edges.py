"""The edge cases that every operator and every stage defines: nulls in any column, empty, blank and very long texts, ties, repeated
rows and ids, empty tables, and columns that clash with results and working names."""

import corpus_pipeline
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from mixwright.llm import kneser_ney, mpeg_audio, packing, pfair, quality_rules, reply_trees, sharding, simhash, suffix_dedup, token_store

VOCAB = public_tokenizers.path("word_bpe_49k.json")
CLASHES = ["_p_slot", "_w_quota", "_m_chunk", "_x_spans", "_x_n_bytes", "_x_place", "_s_drop", "slot", "block", "media", "measures", "cluster", "fp", "key", "component", "bucket", "path", "n_tokens", "score", "shard"]
LONG = "some words of a very long text that goes on and on. " * 60_000


def words(c="text"):
    return F.size(F.array_remove(F.split(F.coalesce(F.col(c), F.lit("")), r"[\x20\x09-\x0D]+"), ""))


def shares(df):
    return pfair.mix(df, block_bytes=300, chunk_rows=4)


OPERATORS = {
    "op1": lambda df: sharding.shard(df, shards=3, range_rows=5),
    "op2": lambda df: kneser_ney.score(df, kneser_ney.fit(df, shard_bytes=1 << 20)),
    "op3": lambda df: quality_rules.measure(df),
    "op4": lambda df: simhash.near_groups(df),
    "op5": lambda df: token_store.read_digests(token_store.write_tokens(df, VOCAB, file_bytes=4000)),
    "op6": lambda df: mpeg_audio.describe(mpeg_audio.with_media(df)),
    "op8": shares,
    "op9": lambda df: packing.pack(df, words(), F.xxhash64("text"), capacity=50, pool_rows=8).select("doc_id").distinct(),
    "op10": lambda df: suffix_dedup.digests(df),
    "near_texts": lambda df: simhash.near_texts(df),
}
STAGES = dict(corpus_pipeline.STAGES)


@pytest.fixture(scope="module")
def odd(spark):
    """Null and repeated ids, null, empty, blank and equal texts, null sources, and a column for every working name."""
    rows = [(None, "a text without an id"), (None, None), (None, "a text without an id"), (1, None), (1, None), (2, ""), (3, " \n\t"), (4, "one"), (4, "another text of the same id"), (5, "word " * 300), (6, "word " * 300), (7, "é ü 漢字 😀"), (8, "x" * 500), (-9, "a negative id"), (1 << 62, "a large id")]
    rows = [(d, t, None if i % 3 else "en", None if i % 4 == 0 else f"s{i % 2}", None if i % 5 else 7) for i, (d, t) in enumerate(rows)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(4)
    return df.select("*", *[F.lit(k).alias(c) for k, c in enumerate(CLASHES)])


@pytest.mark.parametrize("name", OPERATORS)
def test_operator_keeps_every_odd_row(odd, name):
    want = sorted((r.doc_id for r in odd.collect()), key=str)
    got = OPERATORS[name](odd).collect()
    ids = sorted((r["doc_id"] if "doc_id" in r else r["id"] for r in got), key=str)
    assert ids == (sorted(set(want), key=str) if name == "op9" else want)


@pytest.mark.parametrize("name", OPERATORS)
def test_operator_takes_an_empty_table(odd, name):
    assert OPERATORS[name](odd.filter("doc_id = 99")).count() == 0


@pytest.mark.parametrize("name", STAGES)
def test_stage_takes_odd_rows_and_empty_tables(spark, odd, name):
    got = STAGES[name](spark, odd, "")
    rows = got.collect()
    assert {r.doc_id for r in rows} <= {r.doc_id for r in odd.collect()}
    if name != "best_fit_packing":
        assert got.columns == odd.columns
        for c, k in zip(CLASHES, range(len(CLASHES))):
            assert all(r[c] == k for r in rows)
    none = STAGES[name](spark, odd.filter("doc_id = 99"), "")
    assert none.count() == 0 and none.columns == got.columns


@pytest.mark.parametrize("name", ["op1", "op2", "op4", "op5", "op6", "op8", "op9", "op10", "near_texts"])
def test_operator_takes_a_very_long_text(spark, name):
    df = spark.createDataFrame([(1, LONG, "a"), (2, "short", "b")], "doc_id long, text string, source string")
    if name == "op9":
        got = packing.pack(df, words(), F.xxhash64("text")).groupBy("doc_id").agg(F.sum("n_tokens").alias("n")).collect()
        assert {r.doc_id: r.n for r in got} == {1: 720_000, 2: 1}
    else:
        assert OPERATORS[name](df).count() == 2


def test_quality_rules_take_a_long_text(spark):
    df = spark.createDataFrame([(1, LONG[:200_000]), (2, "short")], "doc_id long, text string")
    assert quality_rules.measure(df).select("measures.n_words").count() == 2


@pytest.mark.parametrize("name", ["op4", "op5", "op9", "op10", "near_texts"])
def test_ids_that_are_no_integers_are_refused(odd, name):
    with pytest.raises(TypeError, match="integers"):
        OPERATORS[name](odd.withColumn("doc_id", F.col("doc_id").cast("string"))).collect()


@pytest.mark.parametrize("name", ["op1", "op2", "op6", "op8"])
def test_string_ids_are_kept(odd, name):
    assert OPERATORS[name](odd.withColumn("doc_id", F.concat(F.lit("k"), "doc_id"))).count() == odd.count()


def test_id_columns_named_like_results_are_refused(odd):
    plain = odd.select("doc_id", "text")
    with pytest.raises(ValueError, match="may not be named"):
        sharding.shard(plain.withColumnRenamed("doc_id", "size"), id_col="size")
    with pytest.raises(ValueError, match="may not be named"):
        simhash.near_groups(plain.withColumnRenamed("doc_id", "fp"), id_col="fp")


def test_pipeline_of_an_empty_table(spark, tmp_path):
    spark.read.parquet("/root/testdata/sf0.001/documents.parquet").filter("doc_id < 0").write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_reply_trees_take_nulls_and_repeats(spark):
    chat = spark.createDataFrame([(None, None, None, None), (None, 1, "user", ""), (3, 1, "user", "x"), (3, 1, "user", "x"), (4, 2, None, "y" * 100_000)], "conv_id long, turn long, role string, text string")
    nodes = reply_trees.chains(chat)
    got = {r.tree: r.n_turns for r in reply_trees.format_paths(nodes, reply_trees.branch_paths(nodes)).collect()}
    assert got == {None: 2, 3: 2, 4: 1}


FOREIGN = {
    "short frames": (bytes([0xFF, 0xFB, 0x14, 0xC0]) + bytes(92)) * 5,  # 32 kbit/s at 48 kHz, mono: 96 bytes, no room for a payload
    "noise": bytes(range(256)) * 40,
    "only sync": b"\xff" * 3000,
    "bad tag": b"ID3\x03\0\0\0\0\x00\x1f" + b"TXXX" + (21).to_bytes(4, "big") + b"\0\0" + b"\0content bytes\0" + b"no num" + (bytes([0xFF, 0xFB, 0x14, 0xC0]) + bytes(92)) * 2,
}


@pytest.mark.parametrize("name", FOREIGN)
def test_foreign_streams_do_not_crash(spark, name):
    df = spark.createDataFrame([(1, bytearray(FOREIGN[name]))], "doc_id long, media binary")
    got = mpeg_audio.describe(df).first()
    assert got.n_bytes == 0 and got.media_bytes == len(FOREIGN[name]) and got.payload_bytes == 0
    assert mpeg_audio.streams(df).first().n_frames == {"short frames": 5, "bad tag": 2}.get(name, 0)


def walk(data):
    """Frames of a carried stream, one by one: an independent reading of the format."""
    at = 10 + (data[6] << 21 | data[7] << 14 | data[8] << 7 | data[9]) if data[:3] == b"ID3" else 0
    frames = []
    while at + 4 <= len(data):
        kbps, rate = (0, 32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320)[data[at + 2] >> 4], (44100, 48000, 32000)[data[at + 2] >> 2 & 3]
        assert data[at] == 0xFF and data[at + 1] & 0xFE == 0xFA
        frames.append(at)
        at += 144_000 * kbps // rate + (data[at + 2] >> 1 & 1)
    return frames


@pytest.mark.parametrize("size", [0, 1, 192, 193, 192 * 120 + 5])
def test_feature_equals_an_independent_walk(size):
    import zlib

    import numpy as np

    media = mpeg_audio.carry(b"q" * size)
    info, *frames = walk(media)
    seek = zlib.crc32(np.array(frames[::50], "<i8").tobytes())
    n = len(frames)
    assert mpeg_audio.parse(media).features() == f"layer=3;rate=48000;frames={n};samples={n * 1152};micros={n * 1152 * 1000 // 48};kbps=80;vbr_frames={n};vbr_bytes={(n + 1) * 240};crc={n}-0;resyncs=0;skipped=0;seek={seek:08x}"


def crc_of_bits(bits):
    crc = 0xFFFF
    for b in bits:
        crc = (crc << 1 ^ (0x8005 if (crc >> 15 ^ b) & 1 else 0)) & 0xFFFF
    return crc


def bits_of(data):
    return [x >> (7 - k) & 1 for x in data for k in range(8)]


@pytest.mark.parametrize("layer,head,covered", [(1, bytes([0xFF, 0xFE, 0x44, 0xC0]), 32 * 4), (1, bytes([0xFF, 0xFE, 0x84, 0x50]), 4 * (2 * 8 + 24)), (2, bytes([0xFF, 0xFC, 0x84, 0xC0]), 11 * 4 + 12 * 3 + 4 * 2 + 2 * 11)])
def test_checksums_of_layers_one_and_two(layer, head, covered):
    h = mpeg_audio.header(head)
    assert h.layer == layer and h.protected
    body = bytearray(h.length - 6)
    for k in range(11 if layer == 2 else 0):  # the first eleven bands of layer II have an allocation, 4 bits each
        body[k // 2] |= (1 if k % 2 else 16)
    body[covered // 8 + 2 :] = b"\x55" * len(body[covered // 8 + 2 :])
    crc = crc_of_bits([*bits_of(head[2:]), *bits_of(body)[:covered]])
    frame = head + crc.to_bytes(2, "big") + bytes(body)
    good = mpeg_audio.parse(frame * 4)
    assert (good.frames, good.crc_checked, good.crc_bad) == (4, 4, 0)
    hurt = bytearray(frame * 4)
    hurt[h.length + 6] ^= 1
    assert mpeg_audio.parse(bytes(hurt)).crc_bad == 1


def test_free_format_and_seek_tables():
    free = (bytes([0xFF, 0xFB, 0x04, 0xC0]) + b"\1" * 296) * 6
    s = mpeg_audio.parse(b"junk\xff" + free)
    assert (s.frames, s.samples, s.skipped, s.kbps) == (6, 6 * 1152, 5, {100}) and s.seek(2) == [5, 605, 1205]
    frame = bytearray(bytes([0xFF, 0xFB, 0x64, 0xC0]) + bytes(236))
    vbri = b"VBRI" + bytes(6) + (960).to_bytes(4, "big") + (3).to_bytes(4, "big") + (3).to_bytes(2, "big") + (2).to_bytes(2, "big") + (2).to_bytes(2, "big") + (1).to_bytes(2, "big") + b"".join(x.to_bytes(2, "big") for x in (120, 120, 120))
    frame[36 : 36 + len(vbri)] = vbri
    s = mpeg_audio.parse(bytes(frame) + (bytes([0xFF, 0xFB, 0x64, 0xC0]) + bytes(236)) * 3)
    assert s.frames == 3 and s.vbr == {"kind": "VBRI", "bytes": 960, "frames": 3, "step": 1, "toc": [0, 240, 480, 720]}
