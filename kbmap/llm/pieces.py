"""SentencePiece encoding as a relational lattice, and decoding.

Where no piece spans two neighbouring characters, every way through a text passes between them, so a text falls into
words there (a piece never holds a space after another character; the space before a word belongs to it) that are encoded
apart. Every different word goes through the lattice once: its substrings of
bounded length are exploded and joined to the piece table, the matches (edges) are grouped by word, and a fold
over the edges in order of their ends keeps the best way to each position. A file's texts fall into stretches of
rows with a bounded number of different words; the pieces of each stretch's words are written as one file
in the scratch folder, and the texts look them up there, so no text is shuffled and nothing that grows with the corpus is
broadcast or collected. Words that sampled rows hold most often are encoded first and broadcast (at most ``HEAD_WORDS``); they
needn't travel with every stretch. What the sample holds changes no result. A word that
neither table has is an error, never encoded in another way.

Scores add up as those of a unigram model, as the sentencepiece library does when it is given the same pieces as a
unigram model; of equal ways the one whose last piece is longest wins. Characters without a piece become
byte pieces. Null and empty texts have no pieces. Decoding gives the text back; a literal U+2581 comes
back as a space. Repeated rows give a row each; an empty table gives an empty result. Only a run above ``LONG_WORD`` code points
whose neighbours are all spanned by pieces is folded by the worker that meets it, in time linear in its length.
"""

from __future__ import annotations

import bisect
import functools
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Cut, folder_of, located, named_whole

#: Different words after which a stretch of rows ends, and code points of texts cut at once: bound what a worker holds.
STRETCH_WORDS = 600_000
#: Most words in the broadcast table, the files they are sampled from, and the share (one in so many) of these files' rows.
HEAD_WORDS, HEAD_FILES, HEAD_SHARE = 200_000, 32, 16
#: Partitions of words per shuffle partition of the session.
EXPANSION = 8
#: Words that a task groups in memory before it falls back to sorting.
GROUPED_WORDS = 20_000
#: Words above so many code points are folded by the worker that meets them.
LONG_WORD = 1000
MAX_VOCABULARY = 1_000_000
#: Characters, words or ids that an array step takes at once, and the greatest table of pairs of characters.
SLICE, DENSE = 1 << 18, 1 << 24
_SPACE = "▁"


@dataclass
class Pieces:
    """A piece table: text (space for the space mark) -> (id, score), the first byte piece's id, and all pieces as bytes by id."""

    table: dict[str, tuple[int, float]]
    byte_base: int
    unknown_score: float
    as_bytes: list[bytes]
    width: int

    @classmethod
    def load(cls, path: str) -> Pieces:
        from sentencepiece import SentencePieceProcessor

        m = SentencePieceProcessor(model_file=path)
        n, table, back, base = m.get_piece_size(), {}, [], None
        if n > MAX_VOCABULARY:
            raise ValueError("the piece table is too large to broadcast")
        for i in range(n):
            piece = m.id_to_piece(i)
            if m.is_byte(i):
                base = i if base is None else base
                back.append(bytes([i - base]))
            elif m.is_control(i) or m.is_unknown(i) or m.is_unused(i):
                back.append(b"")
            else:
                text = piece.replace(_SPACE, " ")
                table[text] = (i, m.get_score(i))
                back.append(text.encode())
        if base is None:
            raise ValueError("the model has no byte pieces")
        return cls(table, base, min(s for _, s in table.values()) - 10.0, back, 2 if n <= 65536 else 4)

    @functools.cached_property
    def longest(self) -> int:
        return max(map(len, self.table))

    def competitive(self) -> dict[str, tuple[int, float]]:
        """The pieces that a best way can hold: single characters and those whose score no smaller pieces surpass."""
        out = {}
        for piece, (i, score) in self.table.items():
            best = [0.0]
            for b in range(1, len(piece) + 1):
                ways = [(a, self.table.get(piece[a:b])) for a in range(b) if b - a < len(piece)]
                best.append(max((best[a] + (hit[1] if hit else self.unknown_score) for a, hit in ways if hit or b - a == 1), default=score))
            if len(piece) == 1 or best[-1] <= score:
                out[piece] = (i, score)
        return out

    def hard(self) -> str:
        return "".join(c for c in "\n\t\r" if not any(c in p for p in self.table))

    def splitter(self) -> re.Pattern:
        """Matches one word after the other; characters that no piece holds stand alone where they are line or tab characters."""
        hard = self.hard()
        alone = f"|[{re.escape(hard)}]" if hard else ""
        return re.compile(rf" +[^ {re.escape(hard)}]*|[^ {re.escape(hard)}]+{alone}")

    def pack(self, ids: list[int]) -> bytes:
        """Ids as bytes; a negative one stands for a character without a piece."""
        flat = []
        for i in ids:
            if i >= 0:
                flat.append(i)
            else:
                flat += [self.byte_base + b for b in chr(-1 - i).encode("utf-8", "surrogatepass")]
        return np.asarray(flat, f"<u{self.width}").tobytes()

    def fold(self, word: str) -> list[int]:
        """The best way through one word, for long words and as the reference of the relational fold."""
        best, most = [(0.0, 0, 0)], self.longest
        for j in range(1, len(word) + 1):
            ways = []
            for i in range(max(0, j - most), j):
                hit = self.table.get(word[i:j])
                if hit is not None:
                    ways.append((best[i][0] + hit[1], -i, hit[0]))
                elif i == j - 1:
                    ways.append((best[i][0] + self.unknown_score, -i, -1 - ord(word[i])))
            best.append(max(ways))
        ids, at = [], len(word)
        while at:
            ids.append(best[at][2])
            at = -best[at][1]
        return ids[::-1]

    def decoder(self):
        """A function from an array of ids to the bytes they stand for, gathered in slices of bounded size."""
        sizes = np.array([len(b) for b in self.as_bytes], np.int64)
        starts, blob = sizes.cumsum() - sizes, np.frombuffer(b"".join(self.as_bytes), np.uint8)

        def back(ids: np.ndarray) -> bytes:
            out = []
            for k in range(0, len(ids), SLICE):
                part = ids[k : k + SLICE]
                n = sizes[part]
                ends = n.cumsum()
                out.append(blob[np.repeat(starts[part] - ends + n, n) + np.arange(ends[-1])].tobytes())
            return b"".join(out)

        return back

    def decode(self, ids) -> str:
        back = self.as_bytes
        text = b"".join([back[i] for i in ids]).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text


def split_words(text: str | None, splitter: re.Pattern) -> list[str]:
    return splitter.findall(" " + text.replace(_SPACE, " ")) if text else []


class Segments:
    """Cuts texts, each with a space before it, wherever no piece spans two neighbouring characters."""

    def __init__(self, pieces: Pieces):
        pairs = {p[k : k + 2] for p in pieces.table for k in range(len(p) - 1)}
        ends = [sorted({ord(p[side]) for p in pairs}) for side in (0, 1)]
        step = len(ends[1]) + 1
        self.left, self.right = np.zeros(0x110000, np.int64), np.zeros(0x110000, np.int64)
        self.left[ends[0]], self.right[ends[1]] = np.arange(1, len(ends[0]) + 1) * step, np.arange(1, step)
        self.codes = np.array(sorted(self.left[ord(a)] + self.right[ord(b)] for a, b in pairs), np.int64)
        self.dense = None
        if (n := (len(ends[0]) + 1) * step) <= DENSE:
            self.dense = np.zeros(n, bool)
            self.dense[self.codes] = True

    def spanned(self, points: np.ndarray) -> np.ndarray:
        """For neighbours in an array of code points, whether a piece spans them."""
        code = self.left[points[:-1]] + self.right[points[1:]]
        return np.isin(code, self.codes) if self.dense is None else self.dense[code]

    def __call__(self, texts: list[str]) -> tuple[pa.Array, np.ndarray, bytes, np.ndarray]:
        """For non-empty texts: all words; the number of words before each text and of all; the bytes of all texts; the place of each text there."""
        whole = "".join([f" {t}" for t in texts]).replace(_SPACE, " ")
        borders = np.cumsum([0, *(len(t) + 1 for t in texts)])
        starts, places, size = [], [], 0
        for a in range(0, len(whole), SLICE):
            part = whole[max(a - 1, 0) : a + SLICE]
            points = np.frombuffer(part.encode("utf-32-le"), "<u4")
            first = ~self.spanned(points)
            if a:
                points = points[1:]
            else:
                first = np.concatenate([[True], first])
            first[borders[np.searchsorted(borders, a) : np.searchsorted(borders, min(a + SLICE, len(whole)))] - a] = True
            at = np.flatnonzero(first)
            starts.append(at + a)
            if part.isascii():
                places.append(at + size)
                size += len(points)
            else:
                wide = (1 + (points >= 0x80) + (points >= 0x800) + (points >= 0x10000)).cumsum()
                places.append(np.concatenate([[0], wide])[at] + size)
                size += int(wide[-1])
        offsets = np.concatenate([*places, [size]]).astype(np.int64)
        data = whole.encode()
        words = pa.Array.from_buffers(pa.large_string(), len(offsets) - 1, [None, pa.py_buffer(offsets), pa.py_buffer(data)])
        before = np.searchsorted(np.concatenate([*starts, [len(whole)]]), borders)
        return words, before, data, offsets[before]


def runs_of_rows(batch: pa.RecordBatch, limit: int) -> Iterator[tuple[int, int, int, list[str]]]:
    """(file, first row, number of rows, their texts) of a batch (file, row, ..., text): neighbouring rows of one file with at most
    ``limit`` code points, or one row."""
    files, rows, column = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(batch.num_columns - 1)
    sizes = pc.fill_null(pc.utf8_length(column), 0).to_pylist()
    a = held = 0
    for k in range(len(files) + 1):
        if k == len(files) or k > a and (files[k] != files[a] or rows[k] != rows[k - 1] + 1 or held + sizes[k] > limit):
            if k > a:
                yield files[a], rows[a], k - a, [t or "" for t in column.slice(a, k - a).to_pylist()]
            a, held = k, 0
        if k < len(files):
            held += sizes[k]


#: Bytes of a piece number in the fold, and the bit that marks a character without a piece.
NUMBER, CHARACTER = 3, 1 << 23


def lattice(words: DataFrame, pieces: Pieces) -> DataFrame:
    """(word, ids) from (word), which must be distinct and partitioned by word: no further shuffle.

    ``ids`` holds ``NUMBER`` bytes (greatest first) for each piece; numbers with the bit ``CHARACTER`` stand for a character that has none.
    Each position keeps its best score and the pieces on the way there; of equal scores the first edge, whose piece is longest, stays.
    """
    spark = words.sparkSession
    subs, hits = zip(*pieces.competitive().items())
    columns = {"sub": pa.array(subs), "id": pa.array([i.to_bytes(NUMBER, "big") for i, _ in hits]), "score": pa.array([s for _, s in hits], pa.float64())}
    # Arrow data need no Python workers; rows would start a second set of them on every executor.
    table = spark.createDataFrame(pa.table(columns))
    ends = words.select("word", F.explode(F.sequence(F.lit(1), F.length("word"))).alias("j"))
    spans = ends.select("word", "j", F.explode(F.sequence(F.greatest(F.col("j") - pieces.longest, F.lit(0)), F.col("j") - 1)).alias("i"))
    subs = spans.withColumn("sub", F.substring("word", F.col("i") + 1, F.col("j") - F.col("i")))
    edges = subs.join(F.broadcast(table), "sub", "left").where("id is not null or j - i = 1")  # at most MAX_VOCABULARY rows
    character = F.unhex(F.lpad(F.hex(F.ascii("sub") + F.lit(CHARACTER)), 2 * NUMBER, "0"))
    edge = F.struct("j", "i", F.coalesce("score", F.lit(pieces.unknown_score)).alias("s"), F.coalesce("id", character).alias("p"))
    grouped = edges.groupBy("word").agg(F.sort_array(F.collect_list(edge)).alias("e"))
    start = F.expr("named_struct('a', array(named_struct('s', 0D, 'p', X'')), 'c', named_struct('s', double('-infinity'), 'p', X''))")

    def step(t, e):
        """``t.a`` has the positions before the one whose edges come now, ``t.c`` that one's best way so far."""
        n, before = F.size(t.a), F.get(t.a, e.i)
        way = lambda x: F.struct((x.s + e.s).alias("s"), F.concat(x.p, e.p).alias("p"))
        better = F.when(before.s + e.s > t.c.s, F.struct(t.a.alias("a"), way(before).alias("c"))).otherwise(t)
        moved = F.struct(F.concat(t.a, F.array(t.c)).alias("a"), F.when(e.i == n, way(t.c)).otherwise(way(before)).alias("c"))
        return F.when(e.j <= n, better).otherwise(moved)

    return grouped.select("word", F.aggregate("e", start, step, lambda t: t.c.p).alias("ids"))


def pack_folded(folded: pa.Array, pieces: Pieces) -> pa.Array:
    """The lattice's ids as unsigned numbers of the model's width; characters without a piece as their byte pieces."""
    raw = folded.cast(pa.large_binary())
    ends = np.frombuffer(raw.buffers()[1], np.int64)[raw.offset : raw.offset + len(raw) + 1]
    data = np.frombuffer(raw.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]].reshape(-1, NUMBER).astype(np.int32)
    flat = data[:, 0] << 16 | data[:, 1] << 8 | data[:, 2]
    cuts = (ends - ends[0]) // NUMBER
    if len(flat) and flat.max() >= CHARACTER:
        signed = np.where(flat >= CHARACTER, CHARACTER - 1 - flat, flat)
        return pa.array([pieces.pack(signed[a:b].tolist()) for a, b in zip(cuts, cuts[1:])], pa.binary())
    at = (cuts * pieces.width).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(raw), [None, pa.py_buffer(at.tobytes()), pa.py_buffer(flat.astype(f"<u{pieces.width}").tobytes())])


def frequent_words(source: DataFrame, shared, size: int) -> DataFrame:
    """(word): the words that sampled rows hold most often, at most ``size``; a bounded number of files is sampled."""
    named = source.sparkSession._jvm.org.apache.hadoop.fs.Path
    files = sorted(named(f).toString() for f in source.inputFiles())
    chosen = files[:: max(1, -(-len(files) // HEAD_FILES))]
    rows = source.where(F.col("path").isin(chosen) & (F.col("row") % HEAD_SHARE == 0)).select("text")
    limit = STRETCH_WORDS

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut = Segments(shared.value)
        for b in batches:
            numbers = pa.array(range(len(b)), pa.int64())
            for _, _, _, texts in runs_of_rows(pa.RecordBatch.from_arrays([pa.array([0] * len(b)), numbers, b.column(0)], ["file", "row", "text"]), limit):
                found = cut([t for t in texts if t])[0].value_counts()
                found = found.filter(pc.less_equal(pc.utf8_length(found.field(0)), LONG_WORD))
                yield pa.RecordBatch.from_arrays([found.field(0).cast(pa.string()), found.field(1)], ["word", "n"])

    counted = rows.mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n")).where("n > 1")
    return counted.orderBy(F.desc("n"), "word").limit(size).select("word")


def _stretch_words(shared, head, limit: int):
    """For mapInArrow over (file, row, text): the words of each stretch that the broadcast table lacks, with the stretch.

    A stretch ends with the run of rows that takes it above ``limit`` words, so it has at most twice as many, or those of one text.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut, known = Segments(shared.value), set(head.value)
        words, at, first, last = set(), None, 0, 0

        def out():
            # A stretch with nothing of its own still has a table: its absence would be an error.
            found = sorted(w for w in words.difference(known) if len(w) <= LONG_WORD) or [" "]
            for k in range(0, len(found), 50_000):
                part = found[k : k + 50_000]
                n = len(part)
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array([at] * n, pa.int64()), pa.array([first << 32 | last - first] * n, pa.int64())], ["word", "file", "span"])

        for b in batches:
            for file, row, n, texts in runs_of_rows(b, limit):
                if at is not None and (file != at or row != last + 1 or len(words) > limit):
                    yield from out()
                    words, at = set(), None
                if at is None:
                    at, first = file, row
                last = row + n - 1
                words.update(cut([t for t in texts if t])[0].unique().to_pylist())
        if at is not None:
            yield from out()

    return run


def _write_dictionaries(rows: DataFrame, folder: str, shared) -> int:
    """A file per stretch with its words and packed ids, under its file's number and named after its rows; returns how many.

    A file gets its name when it is whole, and every attempt writes the same, so retries and copies of a task do no harm.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import uuid

        from pyarrow import fs

        schema = pa.schema([("word", pa.string()), ("ids", pa.binary())])
        at = sink = writer = system = name = None
        done = 0

        def close():
            writer.close()
            sink.close()
            named_whole(system, name, f"{name.rpartition('/')[0]}/{at[1] >> 32}-{(at[1] >> 32) + (at[1] & 0xFFFFFFFF)}.arrow")

        for b in batches:
            files, spans = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero((np.diff(files) != 0) | (np.diff(spans) != 0)) + 1).tolist(), len(files)]
            for x, y in zip(cuts, cuts[1:]):
                if x == y:
                    continue
                if (int(files[x]), int(spans[x])) != at:
                    if at is not None:
                        close()
                    at, done = (int(files[x]), int(spans[x])), done + 1
                    system, name = fs.FileSystem.from_uri(f"{folder_of(folder, at[0])}/{uuid.uuid4().hex}.part")
                    system.create_dir(name.rpartition("/")[0], recursive=True)
                    sink = system.open_output_stream(name)
                    writer = pa.ipc.new_stream(sink, schema, options=pa.ipc.IpcWriteOptions(compression="zstd"))
                part = b.slice(x, y - x)
                writer.write_batch(pa.RecordBatch.from_arrays([part.column(2).cast(pa.string()), pack_folded(part.column(3), shared.value)], schema=schema))
        if at is not None:
            close()
        yield pa.RecordBatch.from_arrays([pa.array([done], pa.int64())], ["n"])

    dealt = rows.repartition("file", "span").sortWithinPartitions("file", "span").select("file", "span", "word", "ids")
    return dealt.mapInArrow(run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0))).collect()[0][0]


class Stretches:
    """Tables of the stretches of one file after the other, read as rows ask for them."""

    def __init__(self, folder: str, head: dict[str, bytes]):
        self.folder, self.head, self.file, self.last, self.words = folder, head, None, -1, {}

    def turn_to(self, file: int, row: int) -> None:
        if file == self.file and self.first <= row <= self.last:
            return
        from pyarrow import fs

        if file != self.file:
            self.system, self.at = fs.FileSystem.from_uri(folder_of(self.folder, file))
            names = [i.base_name for i in self.system.get_file_info(fs.FileSelector(self.at)) if i.base_name.endswith(".arrow")]
            self.spans = sorted((*map(int, n[: -len(".arrow")].split("-")), n) for n in names)
        k = bisect.bisect(self.spans, (row, float("inf"))) - 1
        if k < 0 or not self.spans[k][0] <= row <= self.spans[k][1]:
            raise LookupError(f"no table of words for row {row} of file {file}")
        self.file, (self.first, self.last, name) = file, self.spans[k]
        self.words = dict(self.head)
        with self.system.open_input_file(f"{self.at}/{name}") as f:
            for batch in pa.ipc.open_stream(f):
                self.words.update(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))


def _apply(shared, head, folder: str, limit: int):
    """For mapInArrow over (file, row, doc_id, text): ids, their number and checksum, and whether decoding gives the text back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, tables = shared.value, Stretches(folder, head.value)
        cut, back, kind = Segments(p), p.decoder(), f"<u{p.width}"

        def missing(w: str) -> bytes:
            if len(w) <= LONG_WORD:
                raise LookupError("a word is missing from its stretch's table")
            return p.pack(p.fold(w))

        def encoded(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
            """The ids of all words, and the number of ids before each word and of all."""
            coded = words.dictionary_encode()
            different = coded.dictionary.to_pylist()
            found = list(map(tables.words.get, different))
            for k in [k for k, x in enumerate(found) if x is None]:
                found[k] = missing(different[k])
            flat = np.frombuffer(b"".join(found), kind)
            sizes = np.fromiter(map(len, found), np.int64, len(found)) // p.width
            starts, each = sizes.cumsum() - sizes, coded.indices.to_numpy()
            parts, before = [np.empty(0, kind)], [np.zeros(1, np.int64)]
            for k in range(0, len(each), SLICE):
                part = each[k : k + SLICE]
                n = sizes[part]
                ends = n.cumsum()
                parts.append(flat[np.repeat(starts[part] - ends + n, n) + np.arange(ends[-1])])
                before.append(ends + before[-1][-1])
            return np.concatenate(parts), np.concatenate(before)

        def rows_of(doc_ids: pa.Array, texts: list[str]) -> pa.RecordBatch:
            words, first, data, places = cut([t for t in texts if t])
            ids, before = encoded(words)
            full = np.array([bool(t) for t in texts])
            upto = np.concatenate([[0], full.cumsum()])
            ends, sides = before[first][upto], places[upto]
            wide = ids.astype("<u4")
            crc = [zlib.crc32(wide[a:b]) for a, b in zip(ends, ends[1:])]
            trips = [back(ids[a:b]) == data[x:y] for a, b, x, y in zip(ends, ends[1:], sides, sides[1:])]
            lists = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(wide.view(np.int32)))
            columns = [doc_ids, lists, pa.array(np.diff(ends)), pa.array(crc, pa.int64()), pa.array(trips, pa.bool_())]
            return pa.RecordBatch.from_arrays(columns, ["doc_id", "ids", "n_pieces", "ids_crc32", "round_trip"])

        for b in batches:
            k = 0
            for file, row, n, texts in runs_of_rows(b, limit):
                at = 0
                while at < n:
                    tables.turn_to(file, row + at)
                    upto = min(n, tables.last - row + 1)
                    yield rows_of(b.column(2).slice(k + at, upto - at), texts[at:upto])
                    at = upto
                k += n

    return run


def _table_of(rows, pieces: Pieces) -> dict[str, bytes]:
    """Words with their packed ids."""
    return dict(zip([r.word for r in rows], pack_folded(pa.array([bytes(r.ids) for r in rows], pa.binary()), pieces).to_pylist()))


def encode(docs: DataFrame, model: str) -> DataFrame:
    """(doc_id, ids, n_pieces, ids_crc32, round_trip): one row per row of ``docs``.

    ``round_trip`` says that decoding the ids gives the text back, but for literal U+2581.
    """
    spark: SparkSession = docs.sparkSession
    cut, pieces, limit = Cut(spark), Pieces.load(model), STRETCH_WORDS
    shared = spark.sparkContext.broadcast(pieces)  # bounded by MAX_VOCABULARY
    source = located(docs, cut, F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    # A word becomes some sixty substrings, so it takes more and smaller partitions to group them in memory.
    n = EXPANSION * int(spark.conf.get("spark.sql.shuffle.partitions"))
    threshold = "spark.sql.objectHashAggregate.sortBased.fallbackThreshold"
    before = spark.conf.get(threshold)
    spark.conf.set(threshold, str(GROUPED_WORDS))
    try:
        frequent = cut(frequent_words(source, shared, HEAD_WORDS))
        head = spark.sparkContext.broadcast(_table_of(lattice(frequent.repartition(n, "word"), pieces).collect(), pieces))  # HEAD_WORDS at most
        pairs = source.select("file", "row", "text").mapInArrow(_stretch_words(shared, head, limit), "word string, file long, span long").where("word is not null")
        dealt = pairs.repartition(n, "word")
        # The condition keeps all columns of this branch, so that both read one exchange.
        words = dealt.groupBy("word").agg(F.max("file").alias("f"), F.max("span").alias("s")).where("f is not null and s is not null").select("word")
        encoded = lattice(words, pieces)
        rows = dealt.join(encoded.hint("shuffle_hash"), "word").select("file", "span", "word", "ids")
        folder = cut.path("words")
        _write_dictionaries(rows, folder, shared)
    finally:
        spark.conf.set(threshold, before)
    placed = source.select("file", "row", "doc_id", "text")
    return placed.mapInArrow(_apply(shared, head, folder, limit), "doc_id long, ids array<int>, n_pieces long, ids_crc32 long, round_trip boolean")


def decode(encoded: DataFrame, model: str) -> DataFrame:
    """(doc_id, text) from (doc_id, ids); null ids give null."""
    pieces = Pieces.load(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [None if i is None else pieces.decode(i) for i in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select(F.col("doc_id").cast("long"), F.col("ids").cast("array<int>")).mapInArrow(run, "doc_id long, text string")
