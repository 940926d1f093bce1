"""Tokenizing, packing, token files and progressive JPEG: exact round trips."""

import zlib

import numpy as np
import pyarrow as pa
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from sparse_neighbors.llm import packing, progressive_jpeg, shared, textscan, token_files, tokens
from sparse_neighbors.llm.tokens import CachedEncoder

TEXTS = ["", None, "Hello  world\n\n  it's  don't ", " lead", "tail ", "a\u00a0b \u2003c\x1cd \x1c e", "naïve Ünï ½ 12 345 <|endoftext|> x", "\n \n x\n y \t z", "word " * 3000, "日本語 テキスト", "e\u0301 \u0301x", "  ", "'s 's' s'"]
DOCS = "doc_id long, text string, ids string"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "clash") for i, t in enumerate(TEXTS)] + [(None, "no id", None), (3, "again", None), (3, "again", None)]
    return spark.createDataFrame(rows, DOCS)


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_cached_ids_are_the_tokenizers_ids(name):
    path = public_tokenizers.path(name)
    plain = Tokenizer.from_file(path)
    texts = [t or "" for t in TEXTS]
    for got, text in zip(CachedEncoder(path).encode(texts), texts, strict=True):
        assert np.frombuffer(got, "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids, text


def test_special_tokens_and_odd_characters():
    """Random strings, with the strings of special tokens matched as the library does by default or taken as text."""
    rng = np.random.default_rng(5)
    parts = [*"abzAZ09 .,;'\n\t\r<|>-_\x1c\x1f\x85", "\u00e9", "\u00df", "\u0130", "\u03a3", "\u03c2", "\u00bd", "\u00b2", "\u0301", "\u200b", "\u65e5", "\u3000", "\u017f", "\u2167", "\u0663", " 's", " 'll", "<|endoftext|>", "<|EndOfText|>", "  ", " \n"]
    texts = ["".join(rng.choice(parts, int(n))) for n in rng.integers(0, 25, 4000)]
    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        path = public_tokenizers.path(name)
        for as_text in (False, True):
            plain = Tokenizer.from_file(path)
            plain.encode_special_tokens = as_text
            for got, text in zip(CachedEncoder(path, as_text).encode(texts), texts, strict=True):
                assert np.frombuffer(got, "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids, text


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_a_word_with_a_comma_or_dot_needs_no_pattern(name):
    path = public_tokenizers.path(name)
    own, plain = CachedEncoder(path), Tokenizer.from_file(path)
    texts = ["x Known words, known WORDS. na\u00efve, it's. 12, a-b, ,, .. don't, \u00aa, x", ". a , b. \u0130, \u4e2d."]
    for got, text in zip(own.encode(texts), texts, strict=True):
        assert np.frombuffer(got, "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids
    tried = []
    pieces = own._pieces
    own._pieces = lambda text: tried.append(text) or pieces(text)
    own.encode(["x fresh, words. NEWLY, made."])
    assert not [t for t in tried if "," in t or "." in t]


def test_encoders_go_when_a_worker_turns_to_other_operators():
    path = public_tokenizers.path("word_bpe_49k.json")
    kept = tokens.encoder(path)
    assert tokens.encoder(path) is kept
    list(textscan.hashed_words(pa.array(["some text"])))
    assert tokens.encoder(path) is not kept


def test_ids_are_counted_from_whole_buffers():
    rows = [np.array(x, "<u2").tobytes() for x in ([1, 2], [], [2], [9, 9, 9], [4])]
    column = pa.array(rows, pa.binary())
    for part, want in ((column, {1: 1, 2: 2, 4: 1, 9: 3}), (column.slice(1, 3), {2: 1, 9: 3}), (column.slice(0, 0), {}), (column.cast(pa.large_binary()).slice(4), {4: 1})):
        arrays = list(token_files._all_ids(part, "<u2"))
        assert len(arrays) <= 1
        got = next(token_files._id_counts(16)([pa.RecordBatch.from_arrays([part], ["ids"])]))
        assert dict(zip(got["id"].to_pylist(), got["n"].to_pylist(), strict=True)) == want


def test_caches_change_generations(monkeypatch):
    from sparse_neighbors.llm import tokens

    monkeypatch.setattr(tokens, "LIMIT", 50)
    path = public_tokenizers.path("byte_bpe_50k.json")
    own, plain = CachedEncoder(path), Tokenizer.from_file(path)
    rng = np.random.default_rng(7)
    for _ in range(30):
        texts = [" ".join(f"w{n}" for n in rng.integers(0, 300, 40)) for _ in range(5)]
        for got, text in zip(own.encode(texts), texts, strict=True):
            assert np.frombuffer(got, "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids
        assert len(own.words) <= 50 + 200 and len(own.words.old) <= 50 + 200


def test_packing_places_every_piece_once(spark, docs):
    path = public_tokenizers.path("byte_bpe_50k.json")
    plain = Tokenizer.from_file(path)
    got = packing.pack_documents(docs, path, 0, 64).toPandas()
    want = []
    for r in docs.collect():
        ids = np.array([*plain.encode(r.text or "", add_special_tokens=False).ids, 0], "<u4")
        first = len(ids) % 64 or min(len(ids), 64)
        cuts = [0, *range(first, len(ids) + 1, 64)]
        want += [(-1 if r.doc_id is None else r.doc_id, p, a, b - a, zlib.crc32(ids[a:b].tobytes())) for p, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))]
    rows = got.fillna({"doc_id": -1})[["doc_id", "piece", "start", "length", "ids_crc32"]].astype(int).itertuples(index=False)
    assert sorted(map(tuple, rows)) == sorted(want)
    check_sequences(got, 64)
    assert packing.pack_documents(docs.where("false"), path).count() == 0


def check_sequences(got, capacity):
    for _, own in got.groupby("sequence_id"):
        own = own.sort_values("offset")
        ends = (own.offset + own.length).tolist()
        assert own.offset.tolist() == [0, *ends[:-1]] and ends[-1] <= capacity


@pytest.mark.parametrize("seed", range(4))
def test_plans_fill_sequences(seed):
    rng = np.random.default_rng(seed)
    lengths = rng.integers(1, 101, 3000) if seed else np.full(999, 7)
    counts = dict(zip(*np.unique(lengths, return_counts=True), strict=True))
    plan = packing.Plan(100, counts)
    keys, shift, offset = plan.arrays()
    place = {}
    for length, n in counts.items():
        rank = np.arange(n)
        at = np.searchsorted(keys, (int(length) << 44) + rank, "right") - 1
        for s, o in zip(shift[at] + rank, offset[at], strict=True):
            place.setdefault(int(s), []).append((int(o), int(length)))
    for own in place.values():
        own.sort()
        assert [o for o, _ in own] == [0, *np.cumsum([n for _, n in own])[:-1].tolist()] and sum(n for _, n in own) <= 100
    least = max(-(-int(lengths.sum()) // 100), int((lengths > 50).sum()))
    assert len(place) == plan.sequences <= (least * 1.03 if seed else -(-999 // 14))


def test_token_files_round_trip(spark, docs):
    path = public_tokenizers.path("word_bpe_49k.json")
    plain = Tokenizer.from_file(path)
    got = token_files.round_trip(docs, path, 2).toPandas()
    want, start = [], 0
    order = sorted(docs.collect(), key=lambda r: -1 if r.doc_id is None else r.doc_id)
    for r in order:
        ids = np.array([*plain.encode(r.text or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((-1 if r.doc_id is None else r.doc_id, start, len(ids), zlib.crc32(ids.tobytes())))
        start += len(ids)
    got = got.fillna({"doc_id": -1}).astype(int).sort_values("start")
    free = lambda rows: sorted((d, n, crc) for d, _, n, crc in rows)  # noqa: E731  rows of one id come in any order
    assert free(got.itertuples(index=False)) == free(want) and got.doc_id.is_monotonic_increasing
    assert got.start.tolist() == (got.n_tokens.cumsum() - got.n_tokens).tolist()
    assert token_files.round_trip(docs.where("false"), path, 2).count() == 0
    with pytest.raises(Exception, match="beyond the vocabulary"):
        token_files.write_token_files(docs, path, 2, token_files.new_path(spark, "small"), vocabulary=100).count()


def test_huffman_codes_are_optimal_limited_and_decodable():
    rng = np.random.default_rng(1)
    counts = np.concatenate([np.zeros(5, np.int64), (1.6 ** np.arange(25)).astype(np.int64)])
    for longest in (5, 8, 25):
        lengths = token_files.code_lengths(counts, longest)
        own = lengths[5:].astype(float)
        assert own.max() <= longest and abs((2.0**-own).sum() - 1) < 1e-12 and not lengths[:5].any()
    total = (token_files.code_lengths(counts, 25)[5:] * counts[5:]).sum()
    heap = sorted(counts[5:].tolist())
    best = 0
    while len(heap) > 1:
        a, b, *heap = heap
        best += a + b
        heap = sorted([*heap, a + b])
    assert total == best
    ids = rng.choice(np.arange(5, 30), 5000)
    lengths = token_files.code_lengths(counts, 12)
    words, at = token_files.pack_bits(token_files.canonical_codes(lengths)[ids], lengths[ids])
    back = token_files.unpack_blocks(words, at[:: token_files.BLOCK], len(ids), token_files.decoding_table(lengths))
    assert (back == ids).all()
    assert token_files.code_lengths(np.array([0, 3, 0])).tolist() == [0, 1, 0]


def test_payloads_come_back_from_images(spark, docs):
    got = progressive_jpeg.store_texts(docs).toPandas()
    import hashlib

    for r in docs.collect():
        data = (r.text or "").encode()
        payload = progressive_jpeg.padded(data)
        assert len(payload) % 576 == 0 and payload
        own = got[(got.payload_sha256 == hashlib.sha256(payload).hexdigest()) & (got.n_bytes == len(data))]
        assert len(own) and (own.tail_crc32 == zlib.crc32(payload[-32:])).all() and own.media_sha256.nunique() == own.feature.nunique() == 1
    assert len(got) == docs.count()


def scalar_scan(coefficients, start, end, high, low, bits):
    """Codes one AC scan of a list of blocks the plain way: runs, sixteen zeros, one end-of-band per block."""
    out = []
    for block in coefficients:
        band = [int(np.sign(c)) * (abs(int(c)) >> low) for c in block[start : end + 1]]
        run, fixes = 0, []
        last = max((i for i, c in enumerate(band) if (abs(c) == 1 if high else c)), default=-1)
        for i, c in enumerate(band):
            if high and abs(c) > 1:
                fixes.append(abs(c) & 1)
                continue
            if c == 0:
                if i > last:
                    continue
                run += 1
                if run == 16 and any((abs(x) == 1 if high else x) for x in band[i + 1 :]):
                    out += [bits(0xF0), *((f, 1) for f in fixes)]
                    run, fixes = 0, []
                continue
            if high:
                out += [bits(run << 4 | 1), (int(c > 0), 1), *((f, 1) for f in fixes)]
            else:
                size = abs(c).bit_length()
                out += [bits(run << 4 | size), (c if c > 0 else c + (1 << size) - 1, size)]
            run, fixes = 0, []
        if last < len(band) - 1:
            out += [bits(0x00), *((f, 1) for f in fixes)]
    return out


def test_decoder_reads_runs_bands_and_refinements():
    """Sparse coefficients with spectral bands and two refinement passes, coded by a scalar coder."""
    rng = np.random.default_rng(6)
    blocks = np.zeros((12, 64), np.int64)
    spots = rng.random(blocks.shape) < 0.15
    blocks[spots] = rng.integers(-15, 16, spots.sum())
    blocks[3] = 0
    blocks[4, 1:] = 0
    blocks[5, 60] = 7
    symbols = [r << 4 | s for r in range(16) for s in range(5)]
    table = ([0] * 7 + [len(symbols)] + [0] * 8, symbols)
    codes = progressive_jpeg.huffman_codes(*table)
    bits = codes.__getitem__

    def string(pairs):
        return progressive_jpeg.join_codes(np.array([c for c, _ in pairs], np.uint64), np.array([n for _, n in pairs], np.int64), np.zeros(len(pairs), np.int64), 1)[0]

    seg = progressive_jpeg.segment
    file = b"\xff\xd8" + seg(0xDB, bytes([0]) + bytes([3] * 64)) + seg(0xC2, bytes([8, 0, 24, 0, 32, 1, 1, 0x11, 0]))
    file += progressive_jpeg._dht(0x00, table) + progressive_jpeg._dht(0x10, table)
    dc, last = [], 0
    for b in blocks:
        value = int(b[0]) >> 1
        diff, last = value - last, value
        size = abs(diff).bit_length()
        dc += [bits(size), (diff if diff > 0 else diff + (1 << size) - 1, size)] if size else [bits(0)]
    scan = lambda start, end, ah, al: seg(0xDA, bytes([1, 1, 0x00, start, end, ah << 4 | al]))
    file += scan(0, 0, 0, 1) + string(dc) + scan(0, 0, 1, 0) + string([(int(b[0]) & 1, 1) for b in blocks])
    for start, end in ((1, 5), (6, 63)):
        file += scan(start, end, 0, 2) + string(scalar_scan(blocks, start, end, 0, 2, bits))
    for high, low in ((2, 1), (1, 0)):
        file += scan(1, 63, high, low) + string(scalar_scan(blocks, 1, 63, high, low, bits))
    image = progressive_jpeg.decode_batch([file + b"\xff\xd9"])[0]
    assert (image.components[0].coefficients.reshape(-1, 64) == blocks).all()
    rgb = progressive_jpeg.to_rgb(image, progressive_jpeg._basis())
    assert rgb.shape == (24, 32, 3)
    x, u = np.meshgrid(np.arange(8), np.arange(8), indexing="ij")
    one = np.cos((2 * x + 1) * u * np.pi / 16) * np.where(u == 0, np.sqrt(0.125), 0.5)
    square = np.zeros(64)
    square[progressive_jpeg.ZIGZAG] = blocks[0] * 3
    want = np.clip(np.rint(one @ square.reshape(8, 8) @ one.T + 128), 0, 255)
    assert np.abs(rgb[:8, :8, 0].astype(int) - want).max() <= 1


def test_media_column(spark, monkeypatch):
    files = progressive_jpeg.encode_payloads([progressive_jpeg.padded(b"some bytes" * 100), progressive_jpeg.padded(b"more")])
    baseline = bytearray(files[0])
    baseline[files[0].index(b"\xff\xc2") + 1] = 0xC0
    bad = [b"no image", b"\xff\xd8", files[0][: len(files[0]) // 2], files[0][:40], bytes(baseline), b""]
    rows = [(1, files[0], 7), (2, None, 7), (3, files[1], None), *((10 + i, f, 7) for i, f in enumerate(bad))]
    media = spark.createDataFrame([(i, None if f is None else bytearray(f), h) for i, f, h in rows], "id long, media binary, height int")
    got = {r.id: r for r in progressive_jpeg.decode_column(media).collect()}
    assert len(got) == len(rows) and progressive_jpeg.decode_column(media).columns == ["id", "media", "height", "width", "rgb"]
    assert all(len(got[i].rgb) == got[i].height * got[i].width * 3 for i in (1, 3))
    assert got[2].rgb is None and all(got[10 + i].rgb is None and got[10 + i].height is None for i in (0, 1, 3, 4, 5))
    assert progressive_jpeg.decode_column(media.where("false")).count() == 0
    monkeypatch.setattr(progressive_jpeg, "TENSORS", 10)
    one = [t for _, t in progressive_jpeg.tensors([files[0], None, files[1], b"x"])]
    assert one[1] is None and one[3] is None and one[0].tobytes() == bytes(got[1].rgb) and one[2].tobytes() == bytes(got[3].rgb)
    assert progressive_jpeg.store_texts(spark.createDataFrame([], DOCS)).count() == 0


def test_packing_sends_few_texts_at_once_after_heap_is_released(spark, monkeypatch):
    """Executors return unused heap before workers tokenize, which get short batches; the session's limit is back afterwards."""
    own, seen = spark.conf.get(shared.BATCH_ROWS), []
    monkeypatch.setattr(packing, "release_heap", lambda s, f=packing.release_heap: (seen.append("released"), f(s)))
    monkeypatch.setattr(packing, "materialize", lambda df, name, f=packing.materialize: (seen.append((name, df.sparkSession.conf.get(shared.BATCH_ROWS))), f(df, name))[1])
    docs = spark.createDataFrame([(i, "some words " * i) for i in range(5)], "doc_id long, text string")
    packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), 0, 64).collect()
    assert seen[:2] == ["released", ("pieces", str(packing.BATCH))] and spark.conf.get(shared.BATCH_ROWS) == own


def test_a_worker_that_tokenizes_drops_the_tables_of_hashes():
    list(textscan.hashed_words(pa.array(["some text"])))
    assert textscan._tables.cache_info().currsize == 1
    tokens.encoder(public_tokenizers.path("byte_bpe_50k.json"))
    assert textscan._tables.cache_info().currsize == 0
