"""N-gram Jaccard join by parity sketches.

A document is the set of its distinct k-word shingles. Each shingle flips one bit of a sketch, so common
shingles cancel and the Hamming distance of two sketches never exceeds the symmetric difference. Sizes
fall into bands such that documents that can reach the threshold lie in the same or adjacent bands. In a
band the largest possible symmetric difference D is known; the sketch is cut into D + 1 + e pieces, and
two linked documents agree in at least 1 + e of them. A piece (as a 64-bit code linear in its bits, so
that it is the XOR of the codes of the shingles that fall into it) is the key of an equi-join. Sets that must agree in
c pieces still share one if each leaves out its c - 1 most frequent keys, so passages that many unlinked texts share hardly
bring them together. Candidates pass a whole-sketch Hamming test and an exact intersection of their shingle sets. Sets that a
small sketch can't tell apart have a wide one besides, with at least a bit for each shingle.

Groups of copies are never expanded into pairs. Equal sets become one class; each key tests its members against
one of them, a different one for each key, and only members that the verified links don't connect are paired
afterwards, so that no key holds two components with an untested pair. Components come from star contractions.

Results for odd input: a null or empty text, or one without words, has no shingles and links with nothing; a
null doc_id is returned with its own size and a null component; rows that repeat a doc_id are one node that
has the links of all its rows; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .components import connected_components
from .shared import collect_garbage, discard, giving_back, materialize, prepare_workers, short_batches
from .textscan import hashed_words, mix64, shingle_hashes

WORDS = 8  # 64-bit words of the sketch that every document has; larger sets have a wide one as well, of a bit or more a shingle
FILTER_BITS = 1 << 26  # of the filter of documents that are needed; a full filter only lets more rows through
SLICE = 1 << 18  # keys of a task in hand at once
BATCH = 2000  # rows of texts, keys or blocks that travel at once
FEW = 100_000  # ids up to which they are sent to every task, so that only their texts go to Python
LOW = 40  # bits of a key that travel; two keys that agree in them and in their part only make more candidates


@dataclass(frozen=True)
class Bands:
    """Size bands for a Jaccard threshold of num / den."""

    num: int
    den: int

    def edges(self, most: int) -> np.ndarray:
        return np.array(_edges(self.num, self.den, 1 << max(4, int(most).bit_length())))

    def difference(self, size_sum):
        """Largest symmetric difference of two linked sets whose sizes add up to size_sum."""
        return size_sum * (self.den - self.num) // (self.den + self.num)

    def band(self, n: int) -> int:
        return int(np.searchsorted(self.edges(n), n, "right")) - 1

    def high(self, band: int) -> int:
        """Largest size in a band."""
        most = 16
        while len(lows := self.edges(most)) < band + 2:
            most *= 4
        return int(lows[band + 1] - 1)

    def pieces(self, high: int) -> tuple[int, int]:
        """(pieces, pieces agreeing beyond the first) for linked sets of at most `high` elements."""
        d = self.difference(2 * high)
        if d == 0:  # only equal sets link, and these are one class already
            return 0, 0
        spare = 2 + (d + 1) // (8 if self.den - self.num > 1 else 24)
        return d + 1 + spare, spare


@lru_cache(1 << 16)
def spare_keys(n: int, bands: Bands) -> tuple[int, int, int]:
    """(lowest bit of the own band's keys, keys of the own band and of the next that a set of n shingles can leave out).

    A partner has n * den / num shingles at most, so all but the largest difference of these two sizes agree; one of them is needed.
    """
    own, out = bands.band(n), []
    for band in (own, own + 1):
        high = bands.high(band)
        k, _ = bands.pieces(high)
        out.append(max(0, k - bands.difference(n + min(high, n * bands.den // bands.num)) - 1))
    return own & 1, *out


@lru_cache(8)
def _edges(num: int, den: int, most: int) -> tuple[int, ...]:
    lows = [1]
    while lows[-1] <= most:
        lows.append(max(lows[-1] + 1, (lows[-1] - 1) * den // num + 1))
    return tuple(lows)


def piece_keys(shingles: np.ndarray, bands: Bands) -> np.ndarray:
    """Keys of one document from its sorted distinct shingle hashes: its own band's and the next band's pieces, empty ones too.

    The lowest bit tells the two bands apart.
    """
    own = bands.band(len(shingles))
    out = []
    high_part, bit = shingles >> np.uint64(32), shingles & np.uint64(255)
    for band in (own, own + 1):
        k, _ = bands.pieces(bands.high(band))
        if k == 0:
            continue
        piece = (high_part * np.uint64(k)) >> np.uint64(32)
        code = mix64((piece << np.uint64(8)) + bit + np.uint64(band << 40))
        at = np.flatnonzero(np.r_[True, piece[1:] != piece[:-1]])
        full = np.zeros(k, np.uint64)
        full[piece[at].astype(np.int64)] = np.bitwise_xor.reduceat(code, at)
        names = mix64(full + mix64(np.arange(k, dtype=np.uint64) + np.uint64((band << 24) + 1)))
        out.append(names & ~np.uint64(1) | np.uint64(band & 1))
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def sketch(shingles: np.ndarray, words: int = WORDS) -> np.ndarray:
    """Parity of the shingles that fall on each bit of a sketch of `words` 64-bit words, a power of two.

    A sketch of half the size is the XOR of both halves.
    """
    spot = (mix64(shingles + np.uint64(0x5DEECE66D)) & np.uint64(64 * words - 1)).astype(np.int64)
    odd = (np.bincount(spot, minlength=64 * words) & 1).astype(np.uint8)
    return np.packbits(odd, bitorder="little").view(np.int64)


def wide_words(n: int) -> int:
    """Size of the wide sketch of n shingles; two sets that can link differ by a factor of two at most."""
    return 1 << int(-(-n // 64) - 1).bit_length() if n > 64 * WORDS else 0


def wide_distance(a: Column, b: Column) -> Column:
    """Hamming distance of two wide sketches, the larger one folded to the size of the smaller."""
    n = F.least(F.size(a), F.size(b))
    folded = lambda x, i: F.when(F.size(x) > n, F.get(x, i).bitwiseXOR(F.get(x, i + n))).otherwise(F.get(x, i))
    return F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(0), lambda total, i: total + F.bit_count(folded(a, i).bitwiseXOR(folded(b, i))))


def _per_text(batch: pa.RecordBatch, k: int):
    """(row, sorted distinct shingle hashes) of every text."""
    for i, j, borders, words in hashed_words(batch.column("text")):
        owner, hashes = shingle_hashes(borders, words, k)
        order = np.argsort(owner, kind="stable") if len(owner) and (np.diff(owner) < 0).any() else slice(None)
        owner, hashes = owner[order], hashes[order]
        cut = np.searchsorted(owner, np.arange(j - i + 1))
        for t in range(j - i):
            yield i + t, np.unique(hashes[cut[t] : cut[t + 1]])


PRINT_SCHEMA = "doc_id long, n long, print_a long, print_b long, sketch array<long>, wide array<long>, keys array<long>, side int, spare int, spare_next int"


def _ragged(rows: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, rows)], dtype=np.int64)
    flat = np.concatenate([np.zeros(0, np.int64), *(r.view(np.int64) for r in rows)])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat))


def _prints(k: int, bands: Bands):
    none = np.zeros(0, np.uint64)

    def run(batches):
        seen: set[tuple[int, int, int]] = set()  # equal sets of a task give their keys once
        for batch in batches:
            ids, rows = batch.column("doc_id"), []
            known = np.asarray(ids.is_valid())
            for row, s in _per_text(batch, k):
                if not len(s):
                    rows.append((row, 0, 0, 0, sketch(s), none, none, (0, 0, 0)))
                    continue
                a, b = int(np.add.reduce(mix64(s)).view(np.int64)), int(np.bitwise_xor.reduce(mix64(s ^ np.uint64(0xA5A5A5A5A5A5A5A5))).view(np.int64))
                first = bool(known[row]) and (len(s), a, b) not in seen
                if first:
                    seen.add((len(s), a, b))
                words, keys, spare = wide_words(len(s)), piece_keys(s, bands) if first else none, spare_keys(len(s), bands)
                if len(np.unique(keys & np.uint64((1 << LOW) - 1))) < len(keys):  # pieces that may have one key don't count twice
                    spare = (spare[0], 0, 0)
                rows.append((row, len(s), a, b, sketch(s), sketch(s, words) if words else none, keys, spare))
                if len(rows) >= 2000:
                    yield _batch(ids, rows)
                    rows = []
            if rows:
                yield _batch(ids, rows)

    def _batch(ids, rows):
        at, n, a, b, sk, wide, keys, spare = zip(*rows, strict=True)
        return pa.RecordBatch.from_arrays(
            [ids.take(pa.array(at, pa.int64())).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), _ragged(list(sk)), _ragged(list(wide)), _ragged(list(keys)), *(pa.array(x, pa.int32()) for x in zip(*spare, strict=True))],
            ["doc_id", "n", "print_a", "print_b", "sketch", "wide", "keys", "side", "spare", "spare_next"],
        )

    return run


def _sets(k: int, bits: np.ndarray | None):
    """Shingle sets of the documents that the filter lets through, of all without one."""

    def run(batches):
        for batch in batches:
            ids = batch.column("doc_id").cast(pa.int64())
            wanted = np.asarray(ids.is_valid())
            if bits is not None:
                spots = _filter_spots(np.asarray(ids.fill_null(0), dtype=np.int64))
                wanted = wanted & np.logical_and.reduce([(bits[s >> 3] >> (s & 7)) & 1 for s in spots]).astype(bool)
            batch = batch.select(["doc_id", "text"]).filter(pa.array(wanted))
            held, size = [], 0
            for row, s in _per_text(batch, k):
                held.append((row, s))
                size += len(s)
                if size > 500_000:
                    yield _set_batch(batch, held)
                    held, size = [], 0
            if held:
                yield _set_batch(batch, held)

    def _set_batch(batch, held):
        ids = batch.column("doc_id").take(pa.array([r for r, _ in held], pa.int64())).cast(pa.int64())
        return pa.RecordBatch.from_arrays([ids, _ragged([s for _, s in held])], ["doc_id", "shingles"])

    return run


def _key_blocks(parts: int):
    """(part, low, names): the keys of a batch by part, LOW bits each, and for each key the short name of its set.

    The high bits of a key choose its part, so both together are the key that the rest of the join uses.
    """

    def run(batches):
        for batch in (piece for whole in batches for piece in _slices(whole)):
            keys = batch.column("keys")
            sizes = np.asarray(keys.value_lengths().fill_null(0), dtype=np.int64)
            flat = np.asarray(keys.flatten(), dtype=np.int64).view(np.uint64)
            name = np.repeat(np.asarray(batch.column("print_a"), dtype=np.int64).astype("<u4"), sizes)
            part = ((flat >> np.uint64(LOW)) % np.uint64(parts)).astype(np.uint16)
            order = np.argsort(part, kind="stable")
            cuts = np.searchsorted(part[order], np.arange(parts + 1))
            low, name = flat[order].astype("<u8").view(np.uint8).reshape(-1, 8)[:, : LOW // 8], name[order]
            used = np.flatnonzero(np.diff(cuts))
            spans = [(cuts[p], cuts[p + 1]) for p in used]
            yield pa.RecordBatch.from_arrays([pa.array(used), pa.array([low[a:b].tobytes() for a, b in spans], pa.binary()), pa.array([name[a:b].tobytes() for a, b in spans], pa.binary())], ["part", "low", "names"])

    return run


def _slices(batch: pa.RecordBatch):
    """Rows of a batch in slices of about SLICE keys, so that a long batch costs no more memory."""
    ends = np.cumsum(np.asarray(batch.column("keys").value_lengths().fill_null(0), dtype=np.int64))
    at = 0
    while at < len(ends):
        stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + SLICE, "right")))
        yield batch.slice(at, stop - at)
        at = stop


def _shared_keys(batches):
    """(key, name, sets) of the keys that sets of different names have, each once, and how many names have them; rows come sorted by part, and a task has all of a part."""
    keys, names, now = [], [], None
    for batch in batches:
        for part, low, name in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            if part != now:
                yield from _shared_in(keys, names)
                keys, names, now = [], [], part
            wide = np.zeros((len(name) // 4, 8), np.uint8)
            wide[:, : LOW // 8] = np.frombuffer(low, np.uint8).reshape(-1, LOW // 8)
            keys.append(wide.view("<u8").ravel().astype(np.int64) | (part << LOW))
            names.append(np.frombuffer(name, "<u4"))
    yield from _shared_in(keys, names)


def _shared_in(keys: list[np.ndarray], names: list[np.ndarray]):
    if not keys:
        return
    key, name = np.concatenate(keys), np.concatenate(names)
    order = np.argsort(key)
    key, name = key[order], name[order]
    again = np.r_[False, key[1:] == key[:-1]]
    kept = again | np.r_[again[1:], False]
    if not kept.any():  # no set shares a key of this part
        return
    key, name = key[kept], name[kept]
    order = np.lexsort((name, key))
    key, name = key[order], name[order]
    first = np.r_[True, (key[1:] != key[:-1]) | (name[1:] != name[:-1])]
    key, name = key[first], name[first].astype(np.int64)
    again = np.r_[False, key[1:] == key[:-1]]
    first = np.flatnonzero(~again)
    sets = np.repeat(size := np.diff(np.r_[first, len(key)]), size)
    kept = np.flatnonzero(sets > 1)
    for at in range(0, len(kept), 100_000):
        own = kept[at : at + 100_000]
        yield pa.RecordBatch.from_arrays([pa.array(key[own]), pa.array(name[own]), pa.array(sets[own])], ["key", "name", "sets"])


def _filter_spots(ids: np.ndarray, hashes: int = 3) -> list[np.ndarray]:
    base = ids.view(np.uint64)
    return [(mix64(base + np.uint64(7919 * (i + 1))) & np.uint64(FILTER_BITS - 1)).astype(np.int64) for i in range(hashes)]


def _id_filter(ids: DataFrame, hashes: int = 3) -> np.ndarray:
    """A Bloom filter of fixed size over a column of ids: what reaches the driver is bounded by FILTER_BITS."""

    def run(batches):
        bits = np.zeros(FILTER_BITS // 8, np.uint8)
        for batch in batches:
            for s in _filter_spots(np.asarray(batch.column(0), dtype=np.int64), hashes):
                np.bitwise_or.at(bits, s >> 3, (1 << (s & 7)).astype(np.uint8))
        words = bits.view(np.int64)
        at = np.flatnonzero(words)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(words[at])], ["at", "word"])

    merged = ids.mapInArrow(run, "at long, word long").groupBy("at").agg(F.bit_or("word").alias("word")).toArrow()
    out = np.zeros(FILTER_BITS // 64, np.int64)
    out[np.asarray(merged["at"], dtype=np.int64)] = np.asarray(merged["word"], dtype=np.int64)
    return out.view(np.uint8)


def _verified(pairs: DataFrame, sets: DataFrame, bands: Bands) -> DataFrame:
    """Pairs (u, v) whose shingle sets reach the threshold."""
    left = sets.select(F.col("doc_id").alias("u"), F.col("shingles").alias("su"))
    right = sets.select(F.col("doc_id").alias("v"), F.col("shingles").alias("sv"))
    both = F.size(F.array_intersect("su", "sv"))
    joined = pairs.join(left, "u").join(right, "v").withColumn("both", both)
    return joined.where(F.col("both") * bands.den >= (F.size("su") + F.size("sv") - F.col("both")) * bands.num).select("u", "v")


def jaccard_components(docs: DataFrame, k: int = 5, num: int = 4, den: int = 5) -> DataFrame:
    """docs (doc_id, text) -> (doc_id, n_shingles, component_id), linking sets with Jaccard >= num / den."""
    with short_batches(docs.sparkSession, BATCH):
        return _components(docs, k, num, den)


def _components(docs: DataFrame, k: int, num: int, den: int) -> DataFrame:
    spark = docs.sparkSession
    prepare_workers(spark)
    bands = Bands(num, den)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    prints = materialize(texts.mapInArrow(giving_back(_prints(k, bands)), PRINT_SCHEMA), "prints")
    known = prints.where("doc_id is not null")
    filled = known.where("n > 0")
    classes = materialize(filled.groupBy("n", "print_a", "print_b").agg(F.min("doc_id").alias("rep"), F.first("side").alias("side"), F.min("spare").alias("spare"), F.min("spare_next").alias("spare_next")), "classes")
    # keys travel once, as blocks of bytes, with a short name of their set in place of its id; only what sets of different names share comes back
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    blocks = filled.select("print_a", "keys").mapInArrow(giving_back(_key_blocks(min(16 * tasks, 1 << 16))), "part long, low binary, names binary")
    shared = materialize(blocks.repartition(tasks, "part").sortWithinPartitions("part").mapInArrow(giving_back(_shared_keys), "key long, name long, sets long"), "keys")
    collect_garbage(spark)
    named = classes.select(F.col("print_a").bitwiseAND(F.lit(0xFFFFFFFF)).alias("name"), F.col("rep").alias("doc_id"), "side", "spare", "spare_next")
    named = named.withColumn("same", F.count("*").over(Window.partitionBy("name")))
    # different sets of one name would hide each other, so their name is a key of its own, and they leave out no key
    clash = named.where("same > 1").select("doc_id", (-F.col("name") - 1).alias("key"), F.lit(True).alias("own"))
    own = F.col("key").bitwiseAND(1) == F.col("side")
    most_frequent = Window.partitionBy("name", own).orderBy(F.desc("sets"), "key")
    rare = shared.join(named, "name").withColumn("nth", F.row_number().over(most_frequent)).withColumn("own", own)
    rare = rare.where((F.col("same") > 1) | (F.col("nth") > F.when(F.col("own"), F.col("spare")).otherwise(F.col("spare_next"))))
    rows = materialize(rare.select("doc_id", "key", "own").unionByName(clash).distinct(), "keys")
    discard(shared)
    # the member nearest to the key in XOR distance is the hub: another one for each key
    spot = F.col("doc_id").bitwiseXOR(F.col("key"))
    span = rows.groupBy("key").agg(F.min(spot).alias("low"), F.max(spot).alias("high"), F.max("own").alias("some")).where("low <> high and some")  # two sets that both are of the band before meet there
    hubs = span.select("key", F.col("low").bitwiseXOR(F.col("key")).alias("hub"))
    buckets = materialize(rows.join(hubs, "key"), "buckets")
    discard(rows)
    met = filled.join(buckets.select("doc_id").distinct(), "doc_id", "left_semi")
    marks = materialize(met.select("doc_id", "n", "sketch", "wide").dropDuplicates(["doc_id", "n", "sketch"]), "sketches")
    whole, prints = prints, materialize(prints.select("doc_id", "n", "print_a", "print_b"), "sizes")
    discard(whole)
    known = prints.where("doc_id is not null")
    filled = known.where("n > 0")

    def possible(nu, nv, ku, kv):
        """What sizes and sketches don't rule out: Hamming distance is at most the symmetric difference."""
        apart = sum(F.bit_count(F.col(ku)[i].bitwiseXOR(F.col(kv)[i])) for i in range(WORDS))
        most = F.floor((F.col(nu) + F.col(nv)) * (den - num) / (den + num))
        return (F.least(nu, nv) * den >= F.greatest(nu, nv) * num) & (apart <= most)

    left = [F.col("n").alias("nu"), F.col("sketch").alias("ku")]
    right = [F.col("n").alias("nv"), F.col("sketch").alias("kv")]

    def stars(members: DataFrame) -> DataFrame:
        """Links between hubs and members (key, doc_id, hub)."""
        pairs = members.where("doc_id <> hub").select(F.least("hub", "doc_id").alias("u"), F.greatest("hub", "doc_id").alias("v")).distinct()
        pairs = pairs.join(marks.select(F.col("doc_id").alias("u"), *left), "u").join(marks.select(F.col("doc_id").alias("v"), *right), "v")
        return materialize(sifted(pairs.where(possible("nu", "nv", "ku", "kv")).select("u", "v").distinct()), "pairs")

    def sifted(pairs: DataFrame) -> DataFrame:
        """Pairs (u, v) that wide sketches don't rule out, where both have one; rows that repeat a doc_id are tried each."""
        wide = marks.where(F.size("wide") > 0)
        wu, wv = (wide.select(F.col("doc_id").alias(x), F.col("n").alias(f"n{x}"), F.col("wide").alias(f"w{x}")) for x in "uv")
        both = pairs.join(wu, "u", "left").join(wv, "v", "left")
        most = F.floor((F.col("nu") + F.col("nv")) * (den - num) / (den + num))
        open_ = F.col("wu").isNull() | F.col("wv").isNull()
        if 2 * num < den:  # sizes may differ by more than the fold allows for
            return pairs
        fits = F.greatest(F.size("wu"), F.size("wv")) > 2 * F.least(F.size("wu"), F.size("wv"))
        return both.where(open_ | fits | (wide_distance(F.col("wu"), F.col("wv")) <= most)).select("u", "v").distinct()

    def verified(pairs: DataFrame) -> DataFrame:
        wanted = materialize(pairs.select(F.explode(F.array("u", "v")).alias("doc_id")).distinct(), "wanted")
        few = wanted.count() <= FEW
        held = texts.join(F.broadcast(wanted), "doc_id", "left_semi") if few else texts
        sets = materialize(held.mapInArrow(giving_back(_sets(k, None if few else _id_filter(wanted))), "doc_id long, shingles array<long>"), "sets")
        found = materialize(_verified(pairs, sets, bands), "links")
        discard(sets, wanted)
        return found

    def unconnected(members: DataFrame, labels: DataFrame) -> DataFrame:
        """Members (key, doc_id, own, component, base) of the keys that still hold several components, base being one of them."""
        member = members.join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left").select("key", "doc_id", "own", F.coalesce("component", "doc_id").alias("component"))
        split = member.groupBy("key").agg(F.min("component").alias("base"), F.max("component").alias("top")).where("base <> top").select("key", "base")
        return materialize(member.join(split, "key"), "open")

    # rows that repeat a doc_id with other texts tie their classes together
    tied = filled.join(classes, ["n", "print_a", "print_b"]).select("doc_id", "rep")
    ties = tied.groupBy("doc_id").agg(F.min("rep").alias("u"), F.max("rep").alias("v")).where("u <> v")
    ties = tied.join(ties.select("doc_id", "u"), "doc_id").select("u", F.col("rep").alias("v"))
    # one candidate of each document is verified before the others, which matter only if they connect components
    first = stars(buckets)
    links = materialize(verified(first.groupBy("v").agg(F.min("u").alias("u")).select("u", "v")).unionByName(ties).distinct(), "links")
    labels = connected_components(links)
    of_u = labels.select(F.col("node").alias("u"), F.col("component").alias("cu"))
    of_v = labels.select(F.col("node").alias("v"), F.col("component").alias("cv"))
    apart = first.join(of_u, "u", "left").join(of_v, "v", "left").where(F.coalesce("cu", "u") != F.coalesce("cv", "v")).select("u", "v")
    links = materialize(links.unionByName(verified(materialize(apart, "pairs"))).distinct(), "links")
    labels = connected_components(links)
    # members of different components are paired, where the sketches don't rule them out
    open_ = unconnected(buckets, labels)
    marked = open_.join(marks, "doc_id")
    stray = marked.where("component <> base").select("key", F.col("doc_id").alias("u"), F.col("component").alias("cu"), F.col("own").alias("ou"), *left)
    other = marked.select("key", F.col("doc_id").alias("v"), F.col("component").alias("cv"), F.col("own").alias("ov"), *right)
    rest = stray.join(other, (stray["key"] == other["key"]) & (F.col("cu") != F.col("cv")) & (F.col("ou") | F.col("ov")) & possible("nu", "nv", "ku", "kv"))
    rest = rest.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct().join(first, ["u", "v"], "left_anti")
    rest = materialize(sifted(rest), "pairs")
    if rest.limit(1).count():
        links = materialize(links.unionByName(verified(rest)).distinct(), "links")
        labels = connected_components(links)
    discard(buckets, marks, first, open_, rest)
    of_class = classes.join(labels.withColumnRenamed("node", "rep"), "rep", "left").select("n", "print_a", "print_b", F.coalesce("component", "rep").alias("component"))
    own = prints.select("doc_id", "n", "print_a", "print_b").join(of_class, ["n", "print_a", "print_b"], "left")
    return own.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component_id"))


def keep_one_of_each_group(docs: DataFrame, k: int = 5, num: int = 4, den: int = 5) -> DataFrame:
    """The rows of docs that have the smallest doc_id of their component; a null doc_id is kept.

    A doc_id is one document, whatever its rows: all texts of a kept one come out, each once (of rows that repeat doc_id and
    text, the first in the order of the other columns), and all texts of one that is dropped go.
    """
    groups = jaccard_components(docs, k, num, den)
    kept = groups.where("doc_id = component_id").select("doc_id").distinct()
    named = docs.where("doc_id is not null").join(kept, "doc_id", "left_semi")
    others = [f.name for f in docs.schema.fields if f.name not in ("doc_id", "text") and not {"map", "variant"} & set(re.findall(r"\w+", f.dataType.simpleString()))]
    repeats = Window.partitionBy("doc_id", "text").orderBy(*others, F.lit(0))
    named = named.withColumn("_nth", F.row_number().over(repeats)).where("_nth = 1").drop("_nth")
    return named.unionByName(docs.where("doc_id is null"))
