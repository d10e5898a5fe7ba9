"""Each operator against brute force on a rough table and an empty one."""

import collections
import hashlib
import math
import zlib
from fractions import Fraction

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F

from mixwright.llm import hash_arrays, kneser_ney, mpeg_audio, packing, pfair, quality_rules, reply_trees, sharding, simhash, suffix_dedup, token_store
from mixwright.llm.suffix_array import sorted_suffixes, suffix_array

VOCAB = public_tokenizers.path("word_bpe_49k.json")


def rows(df):
    return sorted(df.select("doc_id", "text").collect())


def test_sharding(rough, empty):
    got = sharding.shard(rough, shards=7, range_rows=10, oversample=4).collect()
    src = dict(rows(rough))
    assert sorted(r.doc_id for r in got) == sorted(src)
    for r in got:
        b = (src[r.doc_id] or "").encode()
        assert (r.size, r.text_crc32, r.law, r.grown_shard) == (len(b) + 16, zlib.crc32(b), "bytes", None)
    total, top = sum(r.size for r in got), max(r.size for r in got)
    for s in range(7):
        mine = [r for r in got if r.shard == s]
        assert sorted(r.slot for r in mine) == list(range(len(mine)))
        assert abs(sum(r.size for r in mine) - total / 7) <= top
    assert sharding.shard(empty).count() == 0


def test_quality_rules(rough, empty):
    for r in quality_rules.measure(rough).select("doc_id", "text", "measures").collect():
        t = r.text or ""
        w = t.encode().split()
        grams = [tuple(w[i : i + 8]) for i in range(len(w) - 7)]
        times = collections.Counter(grams)
        cover = {i + k for i, g in enumerate(grams) if times[g] > 1 for k in range(8)}
        lines = [x for x in t.split("\n") if x.encode().split()]
        m = r.measures
        assert (m.n_words, m.word_chars, m.n_repeat_words) == (len(w), sum(len(x.decode()) for x in w), len(cover))
        assert (m.n_symbols, m.n_dup_lines) == (sum(x in "#*$%&|<>" for x in t), len(lines) - len(set(lines)))
    kept = quality_rules.keep_good(rough)
    assert kept.columns == rough.columns
    judged = quality_rules.measure(rough).select("doc_id", quality_rules.passes(F.col("measures")).alias("good"), F.size(quality_rules.broken_rules(F.col("measures"))).alias("broken")).collect()
    assert {r.doc_id for r in kept.collect()} == {r.doc_id for r in judged if r.good}
    assert all(r.good == (r.broken == 0) for r in judged)
    assert quality_rules.keep_good(empty).count() == 0


@pytest.mark.parametrize("radius,bucket", [(2, 64), (2, 1), (3, 1), (1, 1)])
def test_simhash(rough, radius, bucket):
    got = {r[0]: (r[1] & (1 << 64) - 1, r[2]) for r in simhash.near_groups(rough, radius=radius, bucket_rows=bucket).collect()}
    prints = {}
    for d, t in rows(rough):
        w = (t or "").encode().lower().split()
        s = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [b" ".join(w)] if w else []
        hs = [xxhash.xxh64_intdigest(x, seed=42) for x in s]
        prints[d] = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))
    root = {d: d for d in prints}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in prints:
        for b in prints:
            if a < b and bin(prints[a] ^ prints[b]).count("1") <= radius:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    assert got == {d: (prints[d], find(d)) for d in prints}


def test_simhash_masks_cover_every_pair():
    rng = np.random.default_rng(1)
    for radius in (1, 2, 3):
        tables = [m & (1 << 64) - 1 for m in simhash.masks(radius)]
        for _ in range(300):
            bits = rng.choice(64, radius, replace=False)
            x = sum(1 << int(b) for b in bits)
            assert any(x & m == 0 for m in tables)


def test_simhash_keep_one(rough, empty):
    kept = simhash.keep_one(rough)
    comp = {r[0]: r[2] for r in simhash.near_groups(rough).collect()}
    assert {r.doc_id for r in kept.collect()} == set(comp.values()) and kept.columns == rough.columns
    assert simhash.keep_one(empty).count() == 0


def test_token_store(spark, rough, empty):
    from tokenizers import Tokenizer

    index = token_store.write_tokens(rough, VOCAB, file_bytes=2000)
    assert index.count() > 5
    t, start, flat = Tokenizer.from_file(VOCAB), 0, []
    got = sorted(token_store.read_digests(index).collect())
    for r, (d, text) in zip(got, rows(rough), strict=True):
        ids = t.encode(text or "", add_special_tokens=False).ids + [1]
        assert tuple(r) == (d, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
        flat += ids
    for i in (0, 7, len(flat) // 2, len(flat) - 1):
        assert token_store.token_at(index, i) == flat[i]
    assert token_store.read_digests(token_store.write_tokens(empty, VOCAB)).count() == 0
    whole = token_store.write_tokens(rough, VOCAB).first()
    one = token_store.TokenFile(whole.path)
    opened = one.taken
    assert [one[i] for i in range(0, len(flat), 97)] == flat[::97] and one.taken - opened <= 3 * 73 * len(flat[::97])


def test_token_store_splits_a_repeated_id(spark):
    docs = spark.range(60).select(F.lit(None).cast("long").alias("doc_id"), F.concat(F.lit("text number "), F.col("id").cast("string")).alias("text"))
    index = token_store.write_tokens(docs, VOCAB, file_bytes=200)
    got = sorted(token_store.read_digests(index).collect(), key=lambda r: r.start)
    assert index.count() > 3 and len(got) == 60 and got[0].start == 0 and all(a.start + a.n_tokens == b.start for a, b in zip(got, got[1:]))
    with pytest.raises(TypeError, match="integers"):
        token_store.write_tokens(docs.withColumn("doc_id", F.lit("x")), VOCAB)


@pytest.mark.parametrize("text", ["a<|endoftext|>b ć ́x don't I'LL 123a c\x1cd \x85e", "x\x00y 　z ÀÉ ﬁ é İ", "", " \n", "<|ENDOFTEXT|> <|endof text|>", "Straße. ÉTÉ, a., .b ... ß"])
def test_word_encoder_equals_whole_texts(text):
    from tokenizers import Tokenizer

    got = np.frombuffer(next(token_store.WordEncoder.shared(VOCAB, 1).encode([text.encode()])), "<u2").tolist()
    assert got == Tokenizer.from_file(VOCAB).encode(text, add_special_tokens=False).ids + [1]


def test_words_with_marks_and_words_met_before_spare_the_whole_way(monkeypatch):
    import random
    import string

    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(VOCAB)
    coder = token_store.WordEncoder(VOCAB, 1)
    draw = random.Random(3)
    ends = ["".join(draw.choices(string.punctuation, k=draw.randint(1, 5))) for _ in range(3000)]
    texts = [f"{w}{e}" for e, w in zip(ends, ["the", "Word", "Été", "s", "don't", "ßa", "x1", "unbelievably"] * 375, strict=True)]
    for text, got in zip(texts, coder.encode([t.encode() for t in texts]), strict=True):
        assert np.frombuffer(got, "<u2").tolist() == whole.encode(text, add_special_tokens=False).ids + [1], text
    monkeypatch.setattr(coder, "_whole", lambda w: pytest.fail(f"{w} took the whole way"))
    monkeypatch.setattr(token_store, "CACHE_WORDS", 2)
    coder.marks.setdefault(b"$$$", coder._bytes(whole.encode("$$$", add_special_tokens=False).ids))
    once = list(coder.encode([b"planet$$$ river"] * 300))
    assert len(set(once)) == 1 and coder.before
    monkeypatch.setattr(coder, "tokenize", lambda t: pytest.fail(f"{t} was forgotten"))
    assert next(coder.encode([b"river planet$$$"]))


def test_digests_unpack_a_file_at_once(monkeypatch, spark):
    docs = spark.range(50).select(F.col("id").alias("doc_id"), F.concat(F.lit("text number "), F.col("id").cast("string")).alias("text"))
    path = token_store.write_tokens(docs, VOCAB).first().path
    read, cut = [], token_store.Codes.slice
    monkeypatch.setattr(token_store.Codes, "slice", lambda self, a, b: read.append((a, b)) or cut(self, a, b))
    assert token_store.file_digests(path, 7).num_rows == 50 and len(read) == 1


def test_codes():
    values = np.array([0, 255, 256, 70000, 5, 49000, 1 << 23] * 300)
    codes = token_store.Codes(token_store.pack_codes(values))
    assert [codes[i] for i in range(len(values))] == values.tolist()
    for a, b in ((0, 2100), (5, 700), (513, 514), (512, 1024), (7, 7)):
        assert codes.slice(a, b).tolist() == values[a:b].tolist()
    assert len(token_store.Codes(token_store.pack_codes(values[:0]))) == 0


def test_mpeg_audio(rough, empty):
    src = dict(rows(rough))
    for r in mpeg_audio.describe(mpeg_audio.with_media(rough)).collect():
        b = (src[r.doc_id] or "").encode()
        padded = b + b" " * (-len(b) % 192 if b else 192)
        media = mpeg_audio.carry(b)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(b), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-16:]))
        assert (r.media_bytes, r.media_sha256) == (len(media), hashlib.sha256(media).hexdigest()) and f"frames={len(padded) // 192};" in r.feature
    assert mpeg_audio.with_media(rough).columns.count("media") == 1
    assert mpeg_audio.describe(mpeg_audio.with_media(empty)).count() == 0


def test_mpeg_stream():
    whole = mpeg_audio.carry(b"hello " * 400)
    s = mpeg_audio.parse(whole)
    assert (s.samples, s.rate, s.crc_bad, s.vbr["frames"]) == (s.frames * 1152, 48000, 0, s.frames)
    at = int(s.all_offsets()[5])
    hurt = mpeg_audio.parse(whole[:at] + b"\xff\xfbjunk\xff\xe0" + whole[at:])
    assert (hurt.frames, hurt.resyncs, hurt.skipped) == (s.frames, 1, 8)
    bad = bytearray(whole)
    bad[at + 8] ^= 1
    assert mpeg_audio.parse(bytes(bad)).crc_bad == 1
    late = mpeg_audio.parse(b"noise" + whole[at:] + b"TAG" + b"song".ljust(30, b"\0") + bytes(95))
    assert (late.frames, late.tags["TIT1"], late.resyncs) == (s.frames - 5, "song", 1)
    assert mpeg_audio.parse(None).frames == mpeg_audio.parse(b"").frames == mpeg_audio.parse(b"\xff\xfb").frames == 0
    h = mpeg_audio.header(bytes([0xFF, 0xFB, 0x90, 0x00]))
    assert (h.version, h.layer, h.kbps, h.rate, h.length, h.samples) == (1.0, 3, 128, 44100, 417, 1152)


def test_reply_trees(spark):
    nodes = spark.createDataFrame(
        [("t", 1, None, "user", "q", 1.0), ("t", 2, 1, "assistant", "bad", 0.1), ("t", 3, 1, "assistant", "good </s> [INST] <\\/s>", 0.9), ("t", 4, 3, None, None, 0.5), ("t", 5, 9, "user", "orphan", 0.0), (None, 1, None, "user", "x", None), ("c", 1, 2, "user", "round", 1.0), ("c", 2, 1, "user", "round", 1.0)],
        "tree string, node long, parent long, role string, text string, score double",
    )
    paths = reply_trees.branch_paths(nodes, per_tree=3)
    got = {}
    for r in sorted(paths.collect(), key=lambda r: (r.tree or "", r.rank, r.depth)):
        got.setdefault((r.tree, r.rank), []).append(r.node)
    assert got == {("t", 1): [1, 3, 4], ("t", 2): [1, 2], ("t", 3): [5], (None, 1): [1]}
    out = reply_trees.format_paths(nodes, paths).select("tree", "rank", "formatted", reply_trees.read_back(F.col("formatted")).alias("turns"), reply_trees.read_loss(F.col("formatted"), F.col("loss")).alias("learnt")).collect()
    best = next(r for r in out if r.tree == "t" and r["rank"] == 1)
    assert [tuple(x) for x in best.turns] == [("user", "q"), ("assistant", "good </s> [INST] <\\/s>"), ("", "")] and best.learnt == ["good </s> [INST] <\\/s>"]


def test_reply_chains_keep_ties(spark):
    chat = spark.createDataFrame([(1, 0, "user", "a"), (1, 0, "user", "a"), (1, 1, "assistant", "b"), (2, None, None, None)], "conv_id long, turn long, role string, text string")
    nodes = reply_trees.chains(chat)
    got = {r.tree: r.n_turns for r in reply_trees.format_paths(nodes, reply_trees.branch_paths(nodes)).collect()}
    assert got == {1: 3, 2: 1}
    none = reply_trees.chains(chat.filter("conv_id > 9"))
    assert reply_trees.format_paths(none, reply_trees.branch_paths(none)).count() == 0


@pytest.mark.parametrize("weights", [{"a": 1, "b": 1, "c": 2}, {"a": 5, "b": 3, "c": 1, "d": 7}, {"a": 63, "b": 1}, {"a": 999_999, "b": 1}, {None: 1, "x": Fraction(2, 7), "y": 3}])
def test_pfair_deviation_is_below_one_block(weights):
    total = sum(weights.values())
    blocks = {k: int(4000 * w / total) + 2 for k, w in weights.items()}
    plan, given, phase, origin, start = pfair.schedule(blocks, weights), collections.Counter(), 0, 0, {}
    assert [p[2] for p in plan] == list(range(sum(blocks.values())))
    for name, j, slot, release, due, p in plan:
        if p != phase:
            phase, origin, start = p, slot, dict(given)
        assert given[name] == j and release <= slot < due
        given[name] += 1
        live = [k for k in weights if start.get(k, 0) < blocks[k]]
        share = {k: Fraction(weights[k]) / sum(Fraction(weights[x]) for x in live) for k in live}
        assert all(abs(given[k] - start.get(k, 0) - share[k] * (slot + 1 - origin)) < 1 for k in live)
    assert given == blocks


def test_pfair_slots_of_tiny_weights_and_many_sources():
    plan = pfair.schedule({"a": 20_000, "b": 3}, {"a": 10_000 - 1, "b": 1})
    assert [p[2] // 10_000 for p in plan if p[0] == "b"] == [0, 1, 2]
    many = pfair.schedule({str(i): 1 for i in range(5000)}, {str(i): i + 1 for i in range(5000)})
    assert sorted(p[2] for p in many) == list(range(5000))


def brute_mix(docs, sized, block, weights):
    """Blocks and slots by walking the rows of each source in their order."""
    blocks, where = {}, {}
    for source, mine in docs.items():
        upto = 0
        for d in mine:
            where[d] = (source, upto // block)
            upto += sized[d]
        blocks[source] = upto // block + 1
    slots = {p[:2]: p[2:] for p in pfair.schedule(blocks, weights)}
    return {d: (j, *slots[s, j]) for d, (s, j) in where.items()}


def test_pfair_mix(spark, rough, empty):
    sized = {d: len((t or "").encode()) for d, t in rows(rough)}
    out = pfair.mix(rough, block_bytes=500, ceiling=0.4, chunk_rows=1000)
    got = out.collect()
    assert sorted(r.doc_id for r in got) == sorted(sized) and out.columns.count("slot") == 1
    mass, order = collections.Counter(), collections.defaultdict(list)
    keyed = dict(rough.select("doc_id", F.xxhash64(F.col("doc_id").cast("string"), F.lit("mix"))).collect())
    for r in sorted(got, key=lambda r: keyed[r.doc_id]):
        mass[r.source] += sized[r.doc_id]
        order[r.source].append(r.doc_id)
    want = brute_mix(order, sized, 500, pfair.capped_weights({k: max(1, v) for k, v in mass.items()}, 0.4))
    assert {r.doc_id: (r.block, r.slot, r.release, r.deadline, 0 if r.selected else 1) for r in got} == {d: (*w[:4], min(w[4], 1)) for d, w in want.items()}
    chunked = pfair.mix(rough, block_bytes=500, ceiling=0.4, chunk_rows=3).collect()
    taken = collections.Counter()
    for r in chunked:
        taken[r.source, r.block] += sized[r.doc_id]
    assert sorted(r.doc_id for r in chunked) == sorted(sized) and all(r.release <= r.slot < r.deadline for r in chunked)
    assert max(taken.values()) < 500 + max(sized.values())
    assert pfair.mix(empty).count() == 0 and pfair.mix(empty).columns[-5:] == out.columns[-5:]
    assert pfair.capped_weights({"a": 60, "b": 20, "c": 20}, 0.4) == {"a": Fraction(2, 5), "b": Fraction(3, 10), "c": Fraction(3, 10)}
    given = pfair.mix(rough.filter("source is not null"), weights={"hot": 1, "s1": 1e-6, "s2": 3}, block_bytes=200)
    assert given.count() == rough.filter("source is not null").count()
    alike = spark.createDataFrame([(None, "x", "t")] * 50, "doc_id string, source string, text string")
    assert pfair.mix(alike, chunk_rows=7).count() == 50


def test_packing(rough, empty):
    n = F.size(F.array_remove(F.split(F.coalesce("text", F.lit("")), r"[\x20\x09-\x0D]+"), ""))
    got = packing.pack(rough, n, F.xxhash64(F.lower("text")), capacity=100, per_source=2, pool_rows=20).collect()
    want = {d: len((t or "").encode().split()) for d, t in rows(rough)}
    have, bins = collections.Counter(), collections.defaultdict(list)
    for r in got:
        have[r.doc_id] += r.n_tokens
        bins[r.pool, r.bin].append(r)
    assert set(have) == set(want) and all(have[d] == want[d] for d in want)
    for mine in bins.values():
        assert sum(r.n_tokens for r in mine) == mine[0].bin_tokens <= 100 and len(mine) == mine[0].bin_pieces
        assert max(collections.Counter(r.source for r in mine if r.source is not None).values(), default=0) <= 2
        assert max(collections.Counter(r.cluster for r in mine if r.cluster is not None).values(), default=0) <= 1
        assert len({r.doc_id for r in mine}) == len(mine)
        spans = sorted((r.bin_offset, r.n_tokens) for r in mine)
        assert all(a + k == b for (a, k), (b, _) in zip(spans, spans[1:]))
    assert packing.pack(empty, n, F.lit(1)).count() == 0


def test_pools_hand_their_open_bins_on(spark):
    docs = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat(F.lit("s"), F.col("id") % 40).alias("source"), (F.pmod(F.xxhash64("id"), F.lit(60)) + 1).alias("n"))
    bins = lambda **o: packing.pack(docs, F.col("n"), F.col("doc_id"), capacity=200, per_source=20, **o).select("pool", "bin").distinct().count()
    whole, pooled, alone = bins(pool_rows=4000), bins(pool_rows=100), bins(pool_rows=100, slack=1.0)
    assert whole <= pooled < alone and pooled <= 1.01 * whole + 1


def test_packed_bins_hold_the_ids(rough):
    index = token_store.write_tokens(rough, VOCAB, file_bytes=3000)
    sizes = token_store.documents(index).select("doc_id", F.col("n_tokens").alias("n"))
    placed = packing.pack(sizes.join(rough.select("doc_id", "source"), "doc_id"), F.col("n"), F.col("doc_id"), capacity=300, pool_rows=30)
    files = packing.write_bins(placed, index).collect()
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(VOCAB)
    ids = {d: t.encode(text or "", add_special_tokens=False).ids + [1] for d, text in rows(rough)}
    held = {}
    for f in files:
        raw = np.fromfile(f.path.removeprefix("file://"), "<u1")
        n = int(raw[:8].view("<u8")[0])
        cuts, body = raw[8 : 16 + 8 * n].view("<u8"), raw[16 + 8 * n :].view("<u4")
        assert (n, len(body)) == (f.n_bins, f.n_tokens)
        held |= {(f.pool, b): body[int(cuts[b]) : int(cuts[b + 1])].tolist() for b in range(n)}
    for r in placed.collect():
        assert held[r.pool, r.bin][r.bin_offset : r.bin_offset + r.n_tokens] == ids[r.doc_id][r.piece_start : r.piece_start + r.n_tokens]
    assert sum(map(len, held.values())) == sum(map(len, ids.values()))


def test_best_fit_takes_the_tightest_compatible_bin():
    rng = np.random.default_rng(0)
    for _ in range(60):
        pieces = sorted([(int(rng.integers(1, 30)), int(rng.integers(-1, 3)), 1 << int(rng.integers(0, 5)) if rng.random() < 0.7 else 0) for _ in range(60)], reverse=True)
        pieces.sort(key=lambda p: (-p[0], p[1], p[2]))
        state, want = [], []
        for n, s, c in pieces:
            fits = [(left, i) for i, (left, src, clu) in enumerate(state) if left >= n and not clu & c and (s < 0 or src.count(s) < 2)]
            i = min(fits)[1] if fits else len(state)
            if not fits:
                state.append((40, [], 0))
            left, src, clu = state[i]
            want.append((i, 40 - left))
            state[i] = (left - n, src + [s], clu | c)
        assert packing.best_fit(pieces, 40, 2) == want


def brute_repeats(docs, length):
    seen, out = set(), {}
    for d, t in docs:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            w = b[i : i + length]
            if w in seen:
                gone[i : i + length] = b"\1" * length
            seen.add(w)
        spans = sum(1 for i in range(len(b)) if gone[i] and (i == 0 or not gone[i - 1]))
        out[d] = (len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest())
    return out


@pytest.mark.parametrize("options", [{}, {"shard_bytes": 3000, "sort_bytes": 2000, "hot_sample": 20, "memory": 500}])
def test_suffix_dedup(rough, options):
    got = {r[0]: tuple(r[1:]) for r in suffix_dedup.digests(rough, **options).collect()}
    assert got == brute_repeats(rows(rough), 100)


def test_suffix_clean(rough, empty):
    out = suffix_dedup.clean(rough)
    assert out.columns == rough.columns and out.count() == rough.count()
    assert all(r.n_chars == len(r.text) for r in out.collect())
    assert suffix_dedup.clean(empty).count() == 0


def test_suffix_array(tmp_path):
    rng = np.random.default_rng(0)
    cases = [(bytes(rng.integers(0, int(rng.integers(1, 4)), int(rng.integers(0, 80)), dtype=np.uint8)), int(rng.integers(1, 40))) for _ in range(150)]
    parts = [bytes(rng.integers(97, 100, int(rng.integers(1, 30)), dtype=np.uint8)) for _ in range(6)]
    cases += [(b"".join(parts[int(i)] for i in rng.integers(0, 6, 60)), 100) for _ in range(5)]
    for b, depth in cases:
        for memory in (1 << 20, 100):
            sa, lcp = suffix_array(np.frombuffer(b, np.uint8), depth, memory, f"file://{tmp_path}/q")
            assert sorted(sa.tolist()) == list(range(len(b) + 1))
            keys = [b[i : i + depth] for i in sa]
            assert keys == sorted(keys)
            for i in range(1, len(sa)):
                x, y = keys[i - 1], keys[i]
                want = next((k for k, (u, v) in enumerate(zip(x, y)) if u != v), min(len(x), len(y)))
                assert min(int(lcp[i]), depth) == want
    assert not list((tmp_path / "q").iterdir())


def test_default_sorts_go_to_disk(tmp_path):
    import inspect

    size = inspect.signature(suffix_dedup.repeat_marks).parameters["sort_bytes"].default
    words = [bytes(w) for w in np.random.default_rng(2).integers(97, 123, (3000, 6), dtype=np.uint8)]
    text = b" ".join(words[i] for i in np.random.default_rng(1).integers(0, 3000, size // 7))[:size]
    spills, last, seen = [], None, 0
    for sa, lcp in sorted_suffixes(np.frombuffer(text, np.uint8), 100, folder=f"file://{tmp_path}/q", spilt=spills.append):
        seen += len(sa)
        for a, b, n in zip(sa[:-1:999], sa[1::999], lcp[1::999]):
            x, y = text[a : a + 100], text[b : b + 100]
            assert x <= y and min(int(n), 100) == next((k for k, (u, v) in enumerate(zip(x, y)) if u != v), min(len(x), len(y)))
    assert seen == len(text) + 1 and sum(spills) > 3 and not list((tmp_path / "q").iterdir())


def test_pipeline(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = {r.doc_id: r for r in docs.collect()}
        docs = stage(spark, docs, sf)
        after = docs.collect()
        assert {r.doc_id for r in after} <= set(before)
        if i < 4:
            assert docs.columns == columns
        if name == "suffix_array_dedup":
            whole = brute_repeats(sorted((d, r.text) for d, r in before.items()), 100)
            assert all(len(r.text.encode()) <= whole[r.doc_id][0] - whole[r.doc_id][1] for r in after)
        if name == "best_fit_packing":
            assert {r.doc_id for r in after} == set(before)
        docs = corpus_pipeline.shared.stored(docs, "test")


def test_pipeline_near_dedup_links_all_at_the_threshold(spark, rough, empty):
    import corpus_pipeline
    from tests.test_near import brute_classes, planted

    docs = planted(spark).unionByName(rough.select((F.col("doc_id") + 1000).alias("doc_id"), "text"))
    assert {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, "").collect()} == set(brute_classes(rows(docs))[0].values())
    assert corpus_pipeline.drop_near_copies(spark, empty, "").count() == 0


def test_pipeline_mixing_keeps_every_document(spark, rough, empty):
    import corpus_pipeline

    uneven = spark.range(300).select(F.col("id").alias("doc_id"), F.lit("some words here").alias("text"), F.when(F.col("id") < 3, "small").otherwise("large").alias("source"))
    for docs in (uneven, rough, empty):
        got = corpus_pipeline.mix_sources(spark, docs, "")
        assert got.columns == docs.columns and sorted(r.doc_id for r in got.select("doc_id").collect()) == sorted(r.doc_id for r in docs.select("doc_id").collect())


@pytest.mark.parametrize("order,options", [(2, {}), (2, {"shard_bytes": 2000, "hot_share": 0.3}), (3, {"shard_bytes": 2000, "hot_share": 0.3}), (3, {"shard_bytes": 2000, "hot_share": 0.001}), (4, {"shard_bytes": 4000, "hot_share": 0.05})])
def test_kneser_ney(rough, empty, order, options):
    train = rough.filter("doc_id % 3 > 0")
    model = kneser_ney.fit(train, order=order, **options)
    toks = {d: (t or "").encode().lower().split() + [b"</s>"] for d, t in rows(rough)}
    c, top = collections.Counter(), collections.Counter()
    for d in (d for d, _ in rows(train)):
        c.update(toks[d])
        pad = [b"<s>"] * (order - 1) + toks[d]
        top.update(zip(*(pad[k:] for k in range(order))))
    counts = [top]
    for _ in range(order - 1):
        counts.append(collections.Counter(g[1:] for g in counts[-1]))
    levels = []
    for grams in counts:
        disc = kneser_ney.discounts(*(sum(1 for x in grams.values() if x == k) for k in (1, 2, 3, 4)))
        total, freed = collections.Counter(), collections.Counter()
        for g, k in grams.items():
            total[g[:-1]] += k
            freed[g[:-1]] += disc[min(k, 3) - 1]
        levels.append((grams, disc, total, freed))

    def p(gram):
        if not gram:
            return 1 / (len(c) + 1)
        grams, disc, total, freed = levels[order - len(gram)]
        if not total[gram[:-1]]:
            return p(gram[1:])
        k = grams.get(gram, 0)
        return (k - disc[min(k, 3) - 1] if k else 0) / total[gram[:-1]] + freed[gram[:-1]] / total[gram[:-1]] * p(gram[1:])

    n, v = sum(c.values()), len(c)
    assert (model.tokens, model.vocabulary, model.pair_types) == (n, v, len(counts[-2]))
    assert math.isclose(sum(p((b"<s>",) * (order - 1) + (w,)) for w in [*c, b"never seen"]), 1)
    for r in kneser_ney.score(rough, model).collect():
        pad = [b"<s>"] * (order - 1) + toks[r.doc_id]
        assert (r.n_tokens, r.n_known) == (len(toks[r.doc_id]), sum(c[x] > 0 for x in toks[r.doc_id]))
        assert math.isclose(r.score, sum(math.log10(p(g)) for g in zip(*(pad[k:] for k in range(order)))), rel_tol=1e-9)
        assert math.isclose(r.base_score, sum(math.log10((c[x] + 1) / (n + v + 1)) for x in toks[r.doc_id]), rel_tol=1e-9)
    bare = kneser_ney.fit(empty, order=order)
    assert bare.tokens == 0 and kneser_ney.score(empty, bare).count() == 0
    assert kneser_ney.score(rough, bare).filter("isnan(score)").count() == 0


def test_hash_arrays(tmp_path):
    rng = np.random.default_rng(3)
    for n in (0, 1, 17, 5000):
        keys = np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1))
        numbers = [rng.integers(0, 300, len(keys)).astype(np.uint64), np.where(rng.random(len(keys)) < 0.1, np.uint64(1 << 40), np.uint64(3))]
        hash_arrays.write(f"file://{tmp_path}/f{n}", {"a": hash_arrays.pack(keys, numbers), "none": hash_arrays.pack(keys[:0], [])})
        files = hash_arrays.Files(f"file://{tmp_path}")
        hit, got = files.array(f"f{n}", "a").find(np.concatenate([keys, keys ^ np.uint64(1 << 62)]))
        assert hit[: len(keys)].all() and not hit[len(keys) :].any()
        assert all((g == x).all() for g, x in zip(got, numbers))
        assert not files.array(f"f{n}", "none").find(keys)[0].any() and files.array("missing", "a") is None


def test_pipeline_packs_bins_along_the_schedule(spark, tmp_path):
    """The same rows in another order are packed otherwise: pools are stretches of the schedule, and bins follow it."""
    import corpus_pipeline

    docs = spark.range(9000).select(F.col("id").alias("doc_id"), F.concat_ws(" ", F.array_repeat(F.concat(F.lit("w"), "id"), 40)).alias("text"), F.lit("en").alias("lang"), F.concat(F.lit("s"), F.col("id") % 90).alias("source"), F.lit(1).cast("long").alias("n_chars"))
    found = {}
    for name, key in (("up", F.col("doc_id")), ("down", -F.col("doc_id"))):
        docs.repartitionByRange(3, key).sortWithinPartitions(key).write.parquet(str(tmp_path / name))
        found[name] = corpus_pipeline.pack_bins(spark, spark.read.parquet(str(tmp_path / name)), "").collect()
        assert {r.doc_id for r in found[name]} == set(range(9000))
        assert all(r.place == (r.doc_id if name == "up" else 8999 - r.doc_id) for r in found[name])
        assert all(r.pool == r.place * 3 // 9000 for r in found[name] if r.pool < 1 << 40)
        first = {}
        for r in sorted(found[name], key=lambda r: r.place):
            first.setdefault((r.pool, r.bin), r.place)
        for pool in {p for p, _ in first}:
            at = [first[k] for k in sorted(k for k in first if k[0] == pool)]
            assert at == sorted(at)
    assert {(r.doc_id, r.pool, r.bin) for r in found["up"]} != {(r.doc_id, r.pool, r.bin) for r in found["down"]}
    small = docs.limit(50)  # not read as it is from files
    assert sorted(r.place for r in corpus_pipeline.pack_bins(spark, small, "").collect()) == list(range(50))


def test_merged_blocks_equal_grouped_rows():
    rng = np.random.default_rng(1)
    parts, words = [], np.unique(rng.integers(0, 1 << 40, 300, dtype=np.uint64))
    for _ in range(3):
        own = np.sort(rng.choice(words, 90, replace=False))
        parts.append((own, [rng.integers(0, 90, 500).astype("u2") for _ in range(3)], rng.integers(1, 5, 500).astype("u8")))
    want = collections.Counter()
    for own, codes, n in parts:
        for *row, k in zip(*(own[c].tolist() for c in codes), n.tolist()):
            want[tuple(row)] += k
    columns, sums = kneser_ney._merged(words, iter(parts), 3)
    got = dict(zip(zip(*(words[c].tolist() for c in columns)), sums.tolist()))
    assert got == want and sums.dtype == np.uint64
