"""SimHash near-duplicates by multi-index hashing, and near copies by similarity for the corpus pipeline.

A fingerprint is cut in two segments with a table each. Two fingerprints within two bits differ by at most one bit in the first
segment or agree in the second; so each asks the first table for a small Hamming ball around its value and the second for its value,
and every match is checked by its complete distance. Table values that many fingerprints share are split by the other segment,
so that no bucket grows without bound and no match is left out.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Cut, RowSets, connected_components, located, write_row_sets

SEED = 42
#: Bits of a segment, and fingerprints of one segment value above which it is split by the other segment.
HALF, CROWD = 32, 1024


def _hashes(words: list[bytes], n: int) -> np.ndarray:
    import xxhash

    digest = xxhash.xxh64_intdigest
    if not words:
        return np.empty(0, "<u8")
    joined = b" ".join(words)
    if len(words) <= n:
        return np.array([digest(joined, SEED)], "<u8")
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    spans = zip(starts[: len(words) - n + 1].tolist(), ends[n - 1 :].tolist())
    return np.fromiter((digest(joined[a:b], SEED) for a, b in spans), "<u8", len(words) - n + 1)


def _majority(h: np.ndarray) -> int:
    """Bit k is 1 if set in over half of ``h``; counted in slices of bounded size."""
    count = np.zeros(64, np.int64)
    for k in range(0, len(h), 1 << 16):
        part = np.ascontiguousarray(h[k : k + (1 << 16)])
        count += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * count > len(h), bitorder="little").view("<u8")[0])


def text_words(text: str | None) -> list[bytes]:
    """Words of a text with A-Z lower-cased; bytes.split() cuts at exactly U+0020 and U+0009 to U+000D."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def fingerprint(text: str | None, n: int = 3) -> int:
    """64-bit SimHash of the n-word shingles, repeats counted; no words: 0."""
    h = _hashes(text_words(text), n)
    return _majority(h) if len(h) else 0


def fingerprints(docs: DataFrame, n: int = 3) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed long. One row per row of ``docs``, nulls kept."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(t.as_py(), n) for t in b.column(1)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(fp, pa.int64())], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, fp long")


def hex_fingerprint(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def _table(part: Column, seg: int, fp: Column) -> Column:
    return F.struct(F.lit(seg).alias("seg"), part.alias("value"), fp.alias("fp"))


def segments(fp: Column) -> tuple[Column, Column]:
    """The fingerprint's halves as non-negative longs."""
    return F.shiftrightunsigned(fp, HALF), fp.bitwiseAND(F.lit((1 << HALF) - 1))


def refined(rows: DataFrame, crowded: DataFrame) -> DataFrame:
    """Add ``part`` and ``rest``: rows of a crowded table value are keyed by each third of the other segment too.

    Two fingerprints within two bits that meet there differ in the other segment by at most two bits, so they share one of its thirds.
    """
    top, low = segments(F.col("fp"))
    other = F.when(F.col("seg") == 0, low).otherwise(top)
    third = lambda k, a, n: F.struct(F.lit(k).alias("part"), F.shiftright(other, a).bitwiseAND(F.lit((1 << n) - 1)).alias("rest"))
    whole = F.array(F.struct(F.lit(-1).alias("part"), F.lit(0).cast("long").alias("rest")))
    keys = F.when(F.col("many").isNull(), whole).otherwise(F.array(third(0, 0, 11), third(1, 11, 11), third(2, 22, 10)))
    return rows.join(crowded, ["seg", "value"], "left").select("seg", "value", "fp", F.explode(keys).alias("k")).select("seg", "value", "k.part", "k.rest", "fp")


def links(cut: Cut, distinct_fps: DataFrame) -> DataFrame:
    """Edges (a, b) between all fingerprints that differ in one or two bits.

    Each segment has a table of its values. Two differing bits are at most one in the first segment or none in the second, so a
    fingerprint asks the first table for the ball of radius one around its value and the second for its value alone; of two
    neighbours in a ball, the one whose bit is 0 asks. What a table holds is checked by the complete distance. Values with more than
    ``CROWD`` fingerprints are split by the other segment, whatever their number.
    """
    fp = F.col("fp")
    top, low = segments(fp)
    table = cut(distinct_fps.select("fp", F.explode(F.array(_table(top, 0, fp), _table(low, 1, fp))).alias("t")).select("t.seg", "t.value", "fp"))
    crowded = cut(table.groupBy("seg", "value").count().where(F.col("count") > CROWD).select("seg", "value", F.lit(True).alias("many")))
    one = lambda i: F.call_function("shiftleft", F.lit(1).cast("long"), i)
    free = F.filter(F.sequence(F.lit(0), F.lit(HALF - 1)), lambda i: top.bitwiseAND(one(i)) == 0)
    around = F.concat(F.array(top), F.transform(free, lambda i: top.bitwiseOR(one(i))))
    asked = distinct_fps.select("fp", F.explode(F.concat(F.transform(around, lambda v: F.struct(F.lit(0).alias("seg"), v.alias("value"))), F.array(F.struct(F.lit(1).alias("seg"), low.alias("value"))))).alias("q"))
    held = refined(table, crowded).withColumnRenamed("fp", "b")
    sought = refined(asked.select("q.seg", "q.value", "fp"), crowded).withColumnRenamed("fp", "a")
    a, b = F.col("a"), F.col("b")
    # Holders of one value meet once; a neighbour in the ball stands in another value of the first table.
    same_value = F.when(F.col("seg") == 0, segments(a)[0] == segments(b)[0]).otherwise(F.lit(True))
    met = sought.join(held, ["seg", "value", "part", "rest"]).where((F.bit_count(a.bitwiseXOR(b)) <= 2) & (~same_value | (a < b)) & (a != b))
    return met.select("a", "b").distinct()


def near_duplicates(docs: DataFrame, n: int = 3) -> DataFrame:
    """(doc_id, fp, component_id): fingerprints link at 2 or fewer differing bits.

    ``component_id`` is the smallest doc_id reachable. Rows with a null doc_id keep their row; they get
    null only where no row of the component has an identifier. Repeated doc_ids give a row each.
    """
    cut = Cut(docs.sparkSession)
    fps = cut(fingerprints(docs, n))
    distinct = cut(fps.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = connected_components(cut, links(cut, distinct))
    rooted = cut(distinct.join(roots, distinct.fp == roots.v, "left").select("fp", "least", F.coalesce("root", "fp").alias("root")))
    least = cut(rooted.groupBy("root").agg(F.min("least").alias("component_id")))
    named = cut(rooted.join(least, "root").select("fp", "component_id"))
    return fps.join(named, "fp").select("doc_id", "fp", "component_id")


# --- near copies by similarity ------------------------------------------------------------------------------

#: Words of the shingles whose similarity counts.
SHINGLE_WORDS = 5
#: Segments of a long fingerprint (16 bits each) and 64-bit words beside them by which the holders of a segment value are compared. About 15 % of
#: the bits of a pair with Jaccard 0.8 differ, so it shares no segment with probability 0.0002, whatever the number of documents and
#: wherever the two differ (up to 0.02 for sets of four or five shingles, whose majorities are coarser).
SEGMENTS, CHECK_WORDS = 112, 2
#: Words of 64 bits in the parity map that bounds a pair's difference from below before its shingles are compared.
PARITY_WORDS = 16
#: Words of the parity map as folded for the first look at a band's holders.
FOLDED_WORDS = 4
#: Holders of a band above which all of them stay after that first look, and that are later compared as one piece.
BLOCK = 2048


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def _grams(word_hashes: np.ndarray, n: int) -> np.ndarray:
    """Distinct hashes of the n-word shingles (of the whole sequence if shorter)."""
    n = min(n, len(word_hashes))
    g = np.zeros(len(word_hashes) - n + 1, np.uint64)
    for k in range(n):
        g = _mix(g + word_hashes[k : len(word_hashes) - n + 1 + k])
    return np.unique(g)


_SALT = np.random.default_rng(SEED).integers(0, 1 << 63, SEGMENTS // 4 + CHECK_WORDS, np.uint64)


def _long_fingerprint(h: np.ndarray) -> np.ndarray:
    """The SimHash of a set of hashes: bit k is 1 if set in over half of the members; counted in slices of bounded size."""
    count = np.zeros(64 * len(_SALT), np.int64)
    for k in range(0, len(h), 255):
        drawn = _mix(h[k : k + 255, None] ^ _SALT)
        count += np.unpackbits(drawn.view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.uint8)
    return np.packbits(2 * count > len(h), bitorder="little").view("<i8")


def reach(similarity: float) -> int:
    """Bits of the check words in which sets of that similarity differ at most, by four standard deviations and a quarter for small sets."""
    share = math.acos(2 * similarity / (1 + similarity)) / math.pi
    return int(64 * CHECK_WORDS * share * 1.25 + 4 * math.sqrt(64 * CHECK_WORDS * share))


def _parity(h: np.ndarray) -> np.ndarray:
    """Bit k is 1 if an odd number of ``h`` fall on it: two maps differ in no more bits than the sets have unshared members."""
    count = np.bincount((h >> np.uint64(20)).astype(np.int64) % (64 * PARITY_WORDS), minlength=64 * PARITY_WORDS)
    return np.packbits((count & 1).astype(bool), bitorder="little").view("<i8")


def _word_hashes(words: list[bytes]) -> np.ndarray:
    import xxhash

    return np.fromiter((xxhash.xxh64_intdigest(w, SEED) for w in words), np.uint64, len(words)) if words else np.zeros(1, np.uint64)


def near_copy_prints(rows: DataFrame) -> DataFrame:
    """(file, row, same, size, parity, bands) of (file, row, text).

    ``same`` is a hash (128 bits) of the word sequence; then the number of hashed shingles, their parity map and their long
    fingerprint. A word sequence that a batch has met before leaves the last three null.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for whole_batch in batches:
            for b in (whole_batch.slice(k, 512) for k in range(0, whole_batch.num_rows, 512)):
                same, size, parity, bands, met = [], [], [], [], set()
                for t in b.column(2):
                    words = text_words(t.as_py())
                    same.append(xxhash.xxh3_128_digest(b" ".join(words), SEED))
                    if same[-1] in met:
                        for column in (size, parity, bands):
                            column.append(None)
                        continue
                    met.add(same[-1])
                    g = _grams(_word_hashes(words), SHINGLE_WORDS)
                    size.append(len(g))
                    parity.append(_parity(g))
                    bands.append(_long_fingerprint(g))
                longs = pa.list_(pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), b.column(1), pa.array(same, pa.binary()), pa.array(size, pa.int64()), pa.array(parity, longs), pa.array(bands, longs)],
                    ["file", "row", "same", "size", "parity", "bands"],
                )

    return rows.select("file", "row", "text").mapInArrow(
        run, "file long, row long, same binary, size long, parity array<long>, bands array<long>"
    )


def shingle_sets(cut: Cut, rows: DataFrame, prints: DataFrame, asked: DataFrame) -> DataFrame:
    """(same, grams) of the asked word sequences (same): their texts are found by file and row, so no text travels."""
    first = prints.where("size is not null").select("same", "file", "row").join(asked, "same", "left_semi").groupBy("same").agg(F.min(F.struct("file", "row")).alias("at"))
    folder = cut.path(f"asked-{cut.n:04d}")
    write_row_sets(first.select("at.file", "at.row"), folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        wanted = RowSets(folder)
        for b in batches:
            hit = wanted.mask(b.column(0).to_numpy(), b.column(1).to_numpy())
            for t in b.column(2).filter(pa.array(hit)):
                words = text_words(t.as_py())
                g = _grams(_word_hashes(words), SHINGLE_WORDS).view(np.int64)
                same = xxhash.xxh3_128_digest(b" ".join(words), SEED)
                yield pa.RecordBatch.from_arrays([pa.array([same], pa.binary()), pa.array([g], pa.list_(pa.int64()))], ["same", "grams"])

    return cut(rows.select("file", "row", "text").mapInArrow(run, "same binary, grams array<long>"))


def unshared(m: np.ndarray | Column, similarity: float) -> np.ndarray | Column:
    """Members that two sets of ``m`` members together have apart at most, if they have that Jaccard similarity."""
    return m * ((1 - similarity) / (1 + similarity)) + 1e-6


def may_reach(a: str, b: str, similarity: float) -> Column:
    """False only for pairs (structs with size and parity) whose sets cannot have that Jaccard similarity."""
    differ = sum((F.bit_count(F.get(f"{a}.parity", F.lit(k)).bitwiseXOR(F.get(f"{b}.parity", F.lit(k)))) for k in range(PARITY_WORDS)), F.lit(0))
    return F.greatest(differ, F.abs(F.col(f"{a}.size") - F.col(f"{b}.size"))) <= unshared(F.col(f"{a}.size") + F.col(f"{b}.size"), similarity)


def similar(cut: Cut, pairs: DataFrame, rows: DataFrame, prints: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) whose shingle sets have that Jaccard similarity, counted exactly; sets are made for these pairs only."""
    pairs = cut(pairs)
    held = shingle_sets(cut, rows, prints, pairs.select(F.explode(F.array("a", "b")).alias("same")).distinct())
    left, right = held.toDF("a", "x"), held.toDF("b", "y")
    shared = F.size(F.array_intersect("x", "y"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", shared.alias("n"), (F.size("x") + F.size("y")).alias("m"))
    out = cut(both.where(F.col("n") / (F.col("m") - F.col("n")) >= similarity).select("a", "b"))
    cut.drop(held)
    return out


def whole_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows in order of their first column (a number), in tables that hold all rows of each of its values."""
    held, n = [], 0
    for b in batches:
        if not b.num_rows:
            continue
        held.append(b)
        n += b.num_rows
        if n < 1 << 16 or b.column(0)[0].as_py() == b.column(0)[b.num_rows - 1].as_py():
            continue
        t = pa.Table.from_batches(held)
        key = t.column(0).to_numpy()
        whole = int(np.searchsorted(key, key[-1]))
        yield t.slice(0, whole)
        held, n = t.slice(whole).to_batches(), len(key) - whole
    if held:
        yield pa.Table.from_batches(held)


def near_in_group(key: np.ndarray, crowd: np.ndarray, near: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Rows that are near another row of their key and, for each, the smallest row near it, or itself; rows are in order of ``key``.

    ``near`` says of rows i and j which are near. Rows of a ``crowd`` all stay, with the first of their key.
    """
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    sizes = np.diff(np.r_[starts, len(key)])
    first, size = np.repeat(starts, sizes), np.repeat(sizes, sizes)
    lead, stays = np.where(crowd, first, np.arange(len(key))), crowd.copy()
    at, lag = np.flatnonzero(~stays), 1
    while len(at := at[at + lag < (first + size)[at]]):
        met = at[near(at, at + lag)]
        stays[met] = stays[met + lag] = True
        np.minimum.at(lead, met + lag, met)
        lag += 1
    rows = np.flatnonzero(stays)
    return rows, lead[rows]


def close_holders(prints: DataFrame, similarity: float, bounds: bool = False, nodes: DataFrame | None = None) -> DataFrame:
    """(key, a, n): holders n of a segment value (key) that are near another holder of it by the check words.

    ``a`` is the smallest holder near n, or n itself. Of values with more than ``BLOCK`` holders all stay, with the smallest of all.
    With ``bounds``, holders whose sizes or folded parity maps show that their sets cannot have the similarity are not near.
    Each text sends a row for every segment, so these rows carry the check words and a short name only; the few that are near
    another by the check words then get the rest from ``nodes`` (same, size, parity; made from ``prints`` if not given) and meet again.
    """
    parts, limit = SEGMENTS // 4, reach(similarity)
    word = lambda k: F.get("bands", F.floor(k / 4).cast("int"))
    value = lambda k: F.call_function("shiftright", word(k), (k % 4) * 16).bitwiseAND(F.lit(0xFFFF).cast("long"))
    checks = [f"c{k}" for k in range(CHECK_WORDS)]
    # A name that two nodes share adds holders and loses none.
    name = F.xxhash64("same").alias("name")
    held = prints.where("size is not null").groupBy("same").agg(F.first("bands").alias("bands"))
    if nodes is None:
        nodes = prints.where("size is not null").groupBy("same").agg(F.first("size").alias("size"), F.first("parity").alias("parity"))
    each = F.explode(F.transform(F.sequence(F.lit(0), F.lit(SEGMENTS - 1)), lambda k: k.cast("long") * 65536 + value(k)))
    keys = held.select(each.alias("key"), name, *[F.get("bands", F.lit(parts + k)).alias(c) for k, c in enumerate(checks)])

    def stacked(t: pa.Table, columns: list[str]) -> np.ndarray:
        return np.stack([t.column(c).to_numpy().view(np.uint64) for c in columns], axis=1)

    def first_look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches):
            key, check = t.column("key").to_numpy(), stacked(t, checks)
            starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
            sizes = np.diff(np.r_[starts, len(key)])
            crowd = np.repeat(sizes > BLOCK, sizes)
            rows, _ = near_in_group(key, crowd, lambda i, j: np.bitwise_count(check[i] ^ check[j]).sum(1) <= limit)
            left = t.append_column("crowd", pa.array(crowd))
            for k in range(0, len(rows), 1 << 14):
                yield from left.take(pa.array(rows[k : k + (1 << 14)])).combine_chunks().to_batches()

    few = keys.repartition("key").sortWithinPartitions("key").mapInArrow(first_look, f"key long, name long, {', '.join(f'{c} long' for c in checks)}, crowd boolean")
    fold = lambda k: reduce(Column.bitwiseXOR, [F.get("parity", F.lit(i)) for i in range(k, PARITY_WORDS, FOLDED_WORDS)])
    folds = [f"f{k}" for k in range(FOLDED_WORDS * bounds)]
    wide = nodes.select(name, "same", *[F.col("size").cast("long").alias("size"), *[fold(k).alias(c) for k, c in enumerate(folds)]][: len(folds) + bounds])
    # Nothing of a crowd is compared, so its rows stay light.
    light = [F.when(~F.col("crowd"), F.col(c)).otherwise(F.lit(0).cast("long")).alias(c) for c in [*checks, *["size"][:bounds], *folds]]
    full = few.join(wide, "name").select("key", "same", "crowd", *light)

    def second_look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches):
            check, folded = stacked(t, checks), stacked(t, folds) if bounds else None
            size = t.column("size").to_numpy() if bounds else None

            def near(i: np.ndarray, j: np.ndarray) -> np.ndarray:
                met = np.bitwise_count(check[i] ^ check[j]).sum(1) <= limit
                if bounds:
                    i, j = i[met], j[met]
                    apart = np.maximum(np.bitwise_count(folded[i] ^ folded[j]).sum(1), np.abs(size[i] - size[j]))
                    met[met] = apart <= unshared(size[i] + size[j], similarity)
                return met

            rows, lead = near_in_group(t.column("key").to_numpy(), t.column("crowd").to_numpy(), near)
            same = t.column("same").combine_chunks()
            for k in range(0, len(rows), 1 << 14):
                r, a = (pa.array(x[k : k + (1 << 14)]) for x in (rows, lead))
                yield from pa.table({"key": t.column("key").take(r), "a": same.take(a), "n": same.take(r)}).combine_chunks().to_batches()

    return full.repartition("key").sortWithinPartitions("key", "same").mapInArrow(second_look, "key long, a binary, n binary")


def near_copies(rows: DataFrame, similarity: float, cut: Cut) -> DataFrame:
    """(file, row, component) of (file, row, text): groups of rows with equal words or similar five-word shingles.

    Rows with equal word sequences collapse to one node. Nodes that share a segment of their SimHash and are near by its check words are
    candidates, and a match counts if the Jaccard similarity of the two shingle sets is high enough.
    Every holder of a segment value (a band) first meets the smallest holder near it. The components of these links stand for what is
    already joined; then all pairs of a band's holders from different components meet, so that only pairs that
    could not change a component are left out. Crowded bands are cut in pieces.
    ``component`` names the group (a node's hash).
    """
    prints = cut(near_copy_prints(rows))
    nodes = cut(prints.where("size is not null").groupBy("same").agg(F.first("size").alias("size"), F.first("parity").alias("parity")))
    shared = cut(close_holders(prints, similarity, True, nodes))
    pairs = cut(shared.where("a <> n").select("a", F.col("n").alias("b")).distinct())
    edges = similar(cut, plausible(pairs, nodes, similarity), rows, prints, similarity)
    joined = cut(nodes.join(connected_components(cut, edges).withColumnRenamed("v", "same"), "same", "left").withColumn("root", F.coalesce("root", "same")))
    rest = similar(cut, holder_pairs(cut, shared.select("key", F.col("n").alias("same")), joined, similarity), rows, prints, similarity)
    roots = connected_components(cut, edges.unionByName(rest))
    grouped = cut(nodes.select("same").join(roots, nodes.same == roots.v, "left").select("same", F.coalesce("root", "same").alias("component")))
    out = cut(prints.select("file", "row", "same").join(grouped, "same").select("file", "row", "component"))
    for done in (prints, nodes, shared, pairs, joined, grouped):
        cut.drop(done)
    return out


def plausible(pairs: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) that ``may_reach`` leaves, by the sizes and parity maps of ``nodes``."""
    side = lambda name: nodes.select(F.col("same").alias(name), F.struct("size", "parity").alias(f"of_{name}"))
    return pairs.join(side("a"), "a").join(side("b"), "b").where(may_reach("of_a", "of_b", similarity)).select("a", "b")


def holder_pairs(cut: Cut, shared: DataFrame, joined: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) of holders of one band (key, same) in different components that ``may_reach`` leaves.

    The holders of a band's largest component ask nothing, they are only asked by those of its other components. Askers and holders are
    dealt over parts of some sqrt(n * BLOCK) of the band's n holders, and each part of the askers meets each part of the holders in a
    piece. Up to ``BLOCK`` holders are one piece with a row for each; of more, a holder stands in sqrt(n / BLOCK) pieces as asker and as
    holder at most, and in one where the others are few.
    """
    rows = cut(shared.join(joined.select("same", "root"), "same"))
    each = rows.groupBy("key", "root").agg(F.count(F.lit(1)).alias("n"))
    bands = each.groupBy("key").agg(F.sum("n").alias("n"), F.max(F.struct("n", "root")).alias("most")).where("n > most.n")
    parts = F.ceil(F.sqrt(F.col("n") / BLOCK)).cast("int")
    dealt = bands.select("key", F.col("most.root").alias("large"), parts.alias("parts"), F.ceil((F.col("n") - F.col("most.n")) * parts / F.col("n")).cast("int").alias("askers"))
    mixed = cut(rows.join(dealt, "key").join(joined.select("same", F.col("size").cast("long").alias("size"), F.col("parity").cast("array<long>").alias("parity")), "same"))
    few, place = F.col("root") != F.col("large"), F.xxhash64("same")
    asker, holder = F.pmod(F.shiftright(place, 32), F.col("askers")), F.pmod(place, F.col("parts"))
    piece = lambda i, j: F.col("key") * (1 << 32) + i * F.col("parts") + j
    row = lambda i, j, asks, held: F.struct(piece(i, j).alias("piece"), asks.alias("asks"), held.alias("held"))
    asking = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: row(asker, j, F.lit(True), j == holder))
    holding = F.transform(F.filter(F.sequence(F.lit(0), F.col("askers") - 1), lambda i: ~few | (i != asker)), lambda i: row(i, holder, F.lit(False), F.lit(True)))
    pieces = mixed.select("same", "root", "size", "parity", few.alias("few"), F.explode(F.when(few, F.concat(asking, holding)).otherwise(holding)).alias("at"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches):
            at = t.column("piece").to_numpy()
            ends = np.r_[np.flatnonzero(at[1:] != at[:-1]) + 1, len(at)]
            asks, held, few = (t.column(c).to_numpy() for c in ("asks", "held", "few"))
            same, size = t.column("same").combine_chunks(), t.column("size").to_numpy()
            root = t.column("root").combine_chunks().dictionary_encode().indices.to_numpy()
            parity = t.column("parity").combine_chunks().flatten().to_numpy().view(np.uint64).reshape(-1, PARITY_WORDS)
            for start, end in zip(np.r_[0, ends[:-1]].tolist(), ends.tolist()):
                a, b = (start + np.flatnonzero(x[start:end]) for x in (asks, held))
                step = max(1, (1 << 16) // max(1, len(b)))
                for k in range(0, len(a), step):
                    i = a[k : k + step, None]
                    # Two askers meet both ways; one of them counts.
                    x, y = np.nonzero((root[i] != root[b]) & (~few[b] | (i < b)) & (np.abs(size[i] - size[b]) <= unshared(size[i] + size[b], similarity)))
                    x, y, differ = i[x, 0], b[y], 0
                    for words in (slice(0, FOLDED_WORDS), slice(FOLDED_WORDS, None)):
                        differ = differ + np.bitwise_count(parity[x, words] ^ parity[y, words]).sum(1, dtype=np.int64)
                        left = differ <= unshared(size[x] + size[y], similarity)
                        x, y, differ = x[left], y[left], differ[left]
                    if len(x):
                        yield pa.RecordBatch.from_arrays([same.take(pa.array(x)), same.take(pa.array(y))], ["a", "b"])

    kind = joined.schema["same"].dataType.simpleString()
    found = pieces.select("at.*", "same", "root", "size", "parity", "few").repartition("piece").sortWithinPartitions("piece", "same").mapInArrow(run, f"a {kind}, b {kind}")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def keep_one_of_each(docs: DataFrame, similarity: float = 0.8) -> DataFrame:
    """One row of each group of near copies, with all columns of ``docs``: the one with the smallest doc_id.

    Null identifiers come last; of rows with one identifier the first of the smallest file number stays. The rows that go
    are named by file and place, and the second reading of the table leaves them out: no text is shuffled. A null or empty text
    is a text without words; such rows are copies of each other. An empty table gives an empty result.
    """
    cut, names = Cut(docs.sparkSession), docs.columns
    table = located(docs, cut, F.struct(*[F.col(f"`{c}`") for c in names]).alias("doc"))
    rows = table.select("file", "row", F.col("doc.doc_id").cast("long").alias("number"), F.col("doc.text").cast("string").alias("text"))
    groups = near_copies(rows, similarity, cut)
    order = F.struct(F.col("number").isNull().alias("last"), "number", "file", "row")
    numbered = cut(groups.join(rows.select("file", "row", "number"), ["file", "row"]).select("component", order.alias("o")))
    first = numbered.groupBy("component").agg(F.min("o").alias("first"))
    gone = numbered.join(first, "component").where("o <> first").select("o.file", "o.row")
    folder = cut.path("gone")
    write_row_sets(gone, folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left_out = RowSets(folder)
        for b in batches:
            k = b.num_columns - 2
            stays = ~left_out.mask(b.column(k).to_numpy(), b.column(k + 1).to_numpy())
            yield pa.RecordBatch.from_arrays(b.filter(pa.array(stays)).columns[:k], names)

    return table.select(*[F.col("doc").getField(c).alias(f"_{k}") for k, c in enumerate(names)], "file", "row").mapInArrow(run, docs.schema)
