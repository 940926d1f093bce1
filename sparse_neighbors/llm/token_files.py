"""Token ids in files of canonical length-limited Huffman codes.

Code lengths come from the counts of all ids (a package-merge over at most the vocabulary), so one code serves all
files. A file holds segments; a segment has its documents' ids and token counts, the bits of all their tokens and a bit
offset every BLOCK tokens. Blocks decode independently: all blocks of a segment advance together, one table look-up a
token. Files follow doc_id (null first) and are named by the manifest that the writing job returns, so a task that runs
again leaves at most a file that no manifest names.

Results for odd input: a null or empty text has the end id only; a null doc_id sorts first and stays null; rows that
repeat a doc_id follow each other in any order; an empty table gives no files and an empty result; other columns are ignored.
"""

from __future__ import annotations

import json
import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyarrow import fs as arrow_fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import discard, materialize, new_path, prepare_workers
from .tokens import encoded

LONGEST = 18  # bits of a code; the decoding table has 2 ** LONGEST entries
BLOCK = 512  # tokens between bit-offset checkpoints
SEGMENT = 1 << 20  # tokens after which a segment is closed
MAGIC = b"HUFTOKEN"


def code_lengths(counts: np.ndarray, longest: int = LONGEST) -> np.ndarray:
    """Optimal code lengths of at most `longest` bits for the symbols with a count (package-merge)."""
    used = np.flatnonzero(counts)
    out = np.zeros(len(counts), np.uint8)
    n = len(used)
    if n <= 1:
        out[used] = 1
        return out
    if n > 1 << longest:
        raise ValueError(f"{n} symbols don't fit codes of {longest} bits")
    order = used[np.argsort(counts[used], kind="stable")]
    leaves = counts[order].astype(np.float64)
    packages = np.zeros(0)
    is_leaf = []
    for _ in range(longest):
        merged = np.concatenate([leaves, packages])
        rank = np.argsort(merged, kind="stable")
        is_leaf.append(rank < n)
        merged = merged[rank]
        packages = merged[: len(merged) // 2 * 2].reshape(-1, 2).sum(1)
    take = 2 * n - 2
    lengths = np.zeros(n, np.uint8)
    for flags in reversed(is_leaf):
        chosen = int(flags[:take].sum())
        lengths[:chosen] += 1
        take = 2 * (take - chosen)
    out[order] = lengths
    return out


def canonical_codes(lengths: np.ndarray) -> np.ndarray:
    """Codes in order of (length, symbol)."""
    codes = np.zeros(len(lengths), np.uint64)
    order = np.lexsort((np.arange(len(lengths)), lengths))
    order = order[lengths[order] > 0]
    if len(order):
        own = lengths[order].astype(np.int64)
        width = 1 << (int(own.max()) - own)
        codes[order] = (np.concatenate([[0], np.cumsum(width)[:-1]]) >> (int(own.max()) - own)).astype(np.uint64)
    return codes


def decoding_table(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """(symbol, length) for every possible next `bits` bits."""
    order = np.lexsort((np.arange(len(lengths)), lengths))
    order = order[lengths[order] > 0]
    bits = int(lengths.max()) if len(order) else 1
    symbols, sizes = np.zeros(1 << bits, np.uint32), np.ones(1 << bits, np.uint8)
    spread = np.repeat(order, 1 << (bits - lengths[order].astype(np.int64)))
    symbols[: len(spread)], sizes[: len(spread)] = spread, lengths[spread]
    return symbols, sizes, bits


def pack_bits(codes: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit words with the first bit on top, bit offset of every code)."""
    lengths = lengths.astype(np.int64)
    ends = np.cumsum(lengths)
    at = ends - lengths
    total = int(ends[-1]) if len(ends) else 0
    words = np.zeros(total // 64 + 2, np.uint64)
    if len(at):
        word, over = at >> 6, (at & 63) + lengths - 64
        shift = np.abs(over).astype(np.uint64)
        top = np.where(over > 0, codes >> shift, codes << shift)
        first = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
        words[word[first]] = np.bitwise_or.reduceat(top, first)
        split = np.flatnonzero(over > 0)
        words[word[split] + 1] |= codes[split] << (np.uint64(64) - shift[split])
    return words, at


def unpack_blocks(words: np.ndarray, starts: np.ndarray, n: int, table: tuple[np.ndarray, np.ndarray, int]) -> np.ndarray:
    """The n symbols whose blocks begin at the given bit offsets."""
    symbols, sizes, bits = table
    out = np.zeros((BLOCK, len(starts)), np.uint32)
    at = starts.astype(np.int64).copy()
    top = np.uint64(64 - bits)
    last = len(words) - 2
    for step in range(min(BLOCK, n)):
        word, bit = np.minimum(at >> 6, last), (at & 63).astype(np.uint64)
        window = (words[word] << bit) | ((words[word + 1] >> np.uint64(1)) >> (np.uint64(63) - bit))
        code = (window >> top).astype(np.int64)
        out[step] = symbols[code]
        at += sizes[code]
    return out.T.ravel()[:n] if len(starts) else np.zeros(0, np.uint32)


def _open(folder: str):
    system, path = arrow_fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (arrow_fs.LocalFileSystem(), folder)
    return system, path


def _unit(vocabulary: int) -> str:
    """The type that holds every id of the vocabulary between tasks."""
    return "<u2" if vocabulary <= 1 << 16 else "<u4"


def _token_rows(path: str, end_id: int, vocabulary: int):
    def run(batches):
        end, unit, row = np.array([end_id], "<u4").tobytes(), _unit(vocabulary), TaskContext.get().partitionId() << 40
        for batch in batches:
            out = []
            for _, tokens in encoded(batch.column("text"), path):
                ids = np.frombuffer(tokens + end, "<u4")
                if int(ids.max()) >= vocabulary:
                    raise ValueError(f"id {int(ids.max())} is beyond the vocabulary of {vocabulary}")
                out.append(ids.astype(unit).tobytes())
            rows = pa.array(np.arange(row, row + len(out)))
            row += len(out)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), rows, pa.array(out, pa.binary())], ["doc_id", "row", "ids"])

    return run


def _all_ids(column: pa.Array, unit: str):
    """The ids of all rows as few arrays as their buffers allow."""
    for chunk in getattr(column, "chunks", [column]):
        _, offsets, data = chunk.buffers()
        if len(chunk) and data is not None:
            at = np.frombuffer(offsets, np.int64 if pa.types.is_large_binary(chunk.type) else np.int32)
            yield np.frombuffer(data, np.uint8)[at[chunk.offset] : at[chunk.offset + len(chunk)]].view(unit)


def _id_counts(vocabulary: int):
    def run(batches):
        counts = np.zeros(vocabulary, np.int64)
        for batch in batches:
            for own in _all_ids(batch.column("ids"), _unit(vocabulary)):
                counts += np.bincount(own, minlength=vocabulary)
        at = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(counts[at])], ["id", "n"])

    return run


def segment_bytes(doc_ids: list, tokens: list[np.ndarray], lengths: np.ndarray, codes: np.ndarray) -> bytes:
    ids = np.concatenate(tokens).astype(np.int64)
    words, at = pack_bits(codes[ids], lengths[ids])
    parts = [
        np.array([d is not None for d in doc_ids], np.uint8).tobytes(),
        np.array([d or 0 for d in doc_ids], "<i8").tobytes(),
        np.array([len(t) for t in tokens], "<i8").tobytes(),
        at[::BLOCK].astype("<i8").tobytes(),
        words.astype("<u8").tobytes(),
    ]
    return struct.pack("<4q", len(doc_ids), len(ids), len(at[::BLOCK]), len(words)) + b"".join(parts)


def _writer(folder: str, lengths: np.ndarray):
    codes, unit = canonical_codes(lengths), _unit(len(lengths))

    def run(batches):
        part, docs, total = TaskContext.get().partitionId(), 0, 0
        system, path = _open(folder)
        system.create_dir(path, recursive=True)
        name = f"part-{part:06d}-{uuid.uuid4().hex}.huf"
        with system.open_output_stream(f"{path}/{name}") as out:
            head = json.dumps({"block": BLOCK, "symbols": len(lengths)}).encode()
            out.write(MAGIC + struct.pack("<q", len(head)) + head + lengths.tobytes())
            held, size = ([], []), 0

            def close():
                nonlocal held, size
                if held[0]:
                    out.write(segment_bytes(*held, lengths, codes))
                held, size = ([], []), 0

            for batch in batches:
                for doc_id, data in zip(batch.column("doc_id").to_pylist(), batch.column("ids").to_pylist(), strict=True):
                    own = np.frombuffer(data, unit)
                    held[0].append(doc_id)
                    held[1].append(own)
                    size, docs, total = size + len(own), docs + 1, total + len(own)
                    if size >= SEGMENT:
                        close()
            close()
        yield pa.RecordBatch.from_pydict({"part": [part], "name": [name], "docs": [docs], "tokens": [total]})

    return run


def read_segments(stream):
    """(doc ids with None for null, token counts, tokens) of every segment of an open file."""
    if stream.read(len(MAGIC)) != MAGIC:
        raise ValueError("not a token file")
    head = json.loads(stream.read(struct.unpack("<q", stream.read(8))[0]))
    table = decoding_table(np.frombuffer(stream.read(head["symbols"]), np.uint8))
    while len(size := stream.read(32)) == 32:
        docs, n, blocks, words = struct.unpack("<4q", size)
        known = np.frombuffer(stream.read(docs), np.uint8).astype(bool)
        ids = np.frombuffer(stream.read(8 * docs), "<i8")
        counts = np.frombuffer(stream.read(8 * docs), "<i8")
        starts = np.frombuffer(stream.read(8 * blocks), "<i8")
        bits = np.frombuffer(stream.read(8 * words), "<u8").astype(np.uint64)
        yield pa.array(ids, mask=~known), counts, unpack_blocks(bits, starts, n, table)


def _reader(folder: str):
    def run(batches):
        for batch in batches:
            system, path = _open(folder)
            for name, start in zip(batch.column("name").to_pylist(), batch.column("start").to_pylist(), strict=True):
                with system.open_input_stream(f"{path}/{name}") as stream:
                    for ids, counts, tokens in read_segments(stream):
                        ends = np.cumsum(counts)
                        data, cuts = tokens.astype("<u4"), [0, *ends.tolist()]
                        crcs = [zlib.crc32(data[a:b].tobytes()) for a, b in zip(cuts, cuts[1:], strict=False)]
                        yield pa.RecordBatch.from_arrays([ids, pa.array(start + ends - counts), pa.array(counts), pa.array(crcs, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])
                        start += int(ends[-1])

    return run


def write_token_files(docs: DataFrame, tokenizer: str, end_id: int, folder: str, vocabulary: int = 65_536) -> DataFrame:
    """Write docs (doc_id, text) as token files below folder; returns their manifest (part, name, docs, tokens).

    Every id must be below `vocabulary`; one that isn't is an error.
    """
    spark = docs.sparkSession
    prepare_workers(spark)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    tokens = materialize(texts.mapInArrow(_token_rows(tokenizer, end_id, vocabulary), "doc_id long, row long, ids binary"), "tokens")
    counts = tokens.mapInArrow(_id_counts(vocabulary), "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).toArrow()
    totals = np.zeros(vocabulary, np.int64)  # bounded by the vocabulary
    totals[np.asarray(counts["id"], dtype=np.int64)] = np.asarray(counts["n"], dtype=np.int64)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    order = [F.col("doc_id").asc_nulls_first(), F.col("row")]  # the written row number lets rows of one id, or of none, spread over files
    ordered = tokens.repartitionByRange(parts, *order).sortWithinPartitions(*order).select("doc_id", "ids")
    manifest = materialize(ordered.mapInArrow(_writer(folder, code_lengths(totals)), "part long, name string, docs long, tokens long"), "manifest")
    discard(tokens)
    return manifest.where("docs > 0")


def read_token_files(manifest: DataFrame, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, decoded from the files."""
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row a file
    placed = manifest.select("part", "name", F.coalesce(F.sum("tokens").over(before), F.lit(0)).alias("start"))
    parts = max(1, manifest.count())
    return placed.repartitionByRange(parts, "part").mapInArrow(_reader(folder), "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, tokenizer: str, end_id: int) -> DataFrame:
    folder = new_path(docs.sparkSession, "token-files")
    return read_token_files(write_token_files(docs, tokenizer, end_id, folder), folder)
