"""SentencePiece encoding and decoding of texts of any length.

Unigram models: the best segmentation is a path of largest total score over the lattice of pieces. A text is split
into chunks at any character. What a chunk must know of the rest is how far a piece reaches over its borders, at most
`longest - 1` characters, so a chunk is a matrix of best scores from every entry offset to every exit offset. These
matrices multiply in the (max, +) semiring; the product is associative, so chunks are worked out in parallel and
combined by a scan; then each chunk traces its own best path between its two offsets. Ties go to the shorter last
piece, as in one sequential pass.

BPE models merge by rank; their result is no path of largest score, so the scan cannot give the library's ids (see
README). No piece of such a model runs on into a following word mark, though, so a text is cut at word marks: chunks
are words, whose borders need no state, and each word is encoded once in a worker by the library.

Null texts count as empty and have no pieces; repeated rows are kept; other columns are passed by; an empty table
gives an empty result.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import exchange_size, materialize, ranges

MARK = "▁"
_WORKER: dict[str, "WordPieces"] = {}
LOW = -1e18


# ---- max-plus scan for unigram models ---------------------------------------------------------------------------


class Lattice:
    """Pieces with scores; a character without a piece is an unknown of score `unknown`."""

    def __init__(self, scores: dict[str, float], unknown: float) -> None:
        self.scores, self.unknown = scores, unknown
        self.longest = max([1, *map(len, scores)])

    def arcs(self, text: str, i: int) -> Iterator[tuple[int, float]]:
        """(length, score) of the pieces that begin at i."""
        single = self.scores.get(text[i])
        yield 1, self.unknown if single is None else single
        for n in range(2, min(self.longest, len(text) - i) + 1):
            s = self.scores.get(text[i : i + n])
            if s is not None:
                yield n, s

    def forward(self, text: str, begin: int, end: int, entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Best scores and lengths of last pieces at positions begin .. end + longest - 1, one row for each entry offset.

        Row k starts at begin + k; pieces begin before `end` and may reach over it. text holds what they need.
        """
        width = end - begin + self.longest
        best, last = np.full((len(entries), width), LOW), np.zeros((len(entries), width), np.int32)
        best[np.arange(len(entries)), entries] = 0
        for i in range(end - begin):
            here = best[:, i]
            if (here <= LOW).all():
                continue
            for n, s in self.arcs(text, begin + i):
                value = here + s
                better = (here > LOW) & ((value > best[:, i + n]) | ((value == best[:, i + n]) & (n < last[:, i + n])))
                best[better, i + n] = value[better]
                last[better, i + n] = n
        return best, last

    def transfer(self, text: str, begin: int, end: int) -> np.ndarray:
        """(longest, longest): best score from entry offset a (piece border at begin + a) to exit offset b (at end + b)."""
        w = self.longest
        entries = np.arange(min(w, end - begin))
        best, _ = self.forward(text, begin, end, entries)
        out = np.full((w, w), LOW)
        out[: len(entries)] = best[:, end - begin : end - begin + w]
        # a piece may pass over the whole chunk
        for a in range(end - begin, w):
            out[a, a - (end - begin)] = 0
        return out

    def trace(self, text: str, begin: int, end: int, entry: int, exit_: int) -> list[int]:
        """Lengths of the pieces that begin in the chunk, on its best path from entry to exit offset."""
        if entry >= end - begin:
            return []
        best, last = self.forward(text, begin, end, np.array([entry]))
        at, out = end - begin + exit_, []
        while at > entry:
            out.append(int(last[0, at]))
            at -= out[-1]
        return out[::-1]


def max_plus(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a[:, :, None] + b[None]).max(axis=1), LOW)


def offsets(matrices: list[np.ndarray], entry: int = 0, exit_: int = 0) -> list[int]:
    """Border offsets entry = o_0, o_1, ..., o_m = exit of the best path through consecutive chunks."""
    w = len(matrices[0])
    state = np.full(w, LOW)
    state[entry] = 0
    states = [state]
    for m in matrices:
        state = np.maximum((state[:, None] + m).max(axis=0), LOW)
        states.append(state)
    out = [exit_]
    for m, s in zip(reversed(matrices), reversed(states[:-1])):
        out.append(int(np.argmax(s + m[:, out[-1]])))
    return out[::-1]


def product(matrices: list[np.ndarray]) -> np.ndarray:
    """The (max, +) product of consecutive matrices, combined in pairs."""
    while len(matrices) > 1:
        pairs = [max_plus(a, b) for a, b in zip(matrices[::2], matrices[1::2])]
        matrices = pairs + ([matrices[-1]] if len(matrices) % 2 else [])
    return matrices[0]


def segment(lattice: Lattice, text: str, chunk: int | None = None) -> list[str]:
    """Pieces of the best segmentation; with `chunk`, by the scan over chunks of that many characters."""
    if not text:
        return []
    size = chunk or len(text)
    cuts = [*range(0, len(text), size), len(text)]
    spans = list(zip(cuts, cuts[1:]))
    borders = offsets([lattice.transfer(text, b, e) for b, e in spans]) if len(spans) > 1 else [0, 0]
    lengths = [n for (b, e), i, j in zip(spans, borders, borders[1:]) for n in lattice.trace(text, b, e, i, j)]
    ends = np.cumsum(lengths).tolist()
    return [text[a:b] for a, b in zip([0, *ends], ends)]


def segment_giants(docs: DataFrame, lattice: Lattice, chunk: int = 20_000, fan: int = 64) -> DataFrame:
    """doc_id, pieces array<string>: texts cut into chunks that tasks work out apart, for unigram models.

    Up: each chunk's transfer matrix, then products of `fan` consecutive ones, level by level, until a text has one group
    left. Down: a group's entry and exit offsets give those of its members. Last, each chunk traces its own path. A
    group holds at most `fan` small matrices, however long a text is. Rows are told apart by numbers of their own, so
    null and repeated ids do not matter; null texts have no pieces.
    """
    lat = docs.sparkSession.sparkContext.broadcast(lattice)
    w, size = lattice.longest, exchange_size(docs.sparkSession)
    rows = materialize(docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("row", F.monotonically_increasing_id()), "numbered")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Chunks, each with the characters that its last pieces may reach."""
        for b in batches:
            for row, text in zip(b.column("row").to_pylist(), b.column("text").to_pylist()):
                for at in range(0, len(text), chunk * 50):
                    starts = list(range(at, min(len(text), at + chunk * 50), chunk))
                    cols = [[row] * len(starts), [s // chunk for s in starts], [text[s : s + chunk + w] for s in starts], [min(chunk, len(text) - s) for s in starts]]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.string(), pa.int32()))], names=["row", "no", "part", "len"])

    chunks = materialize(rows.mapInArrow(cut, "row long, no long, part string, len int").repartition(size, "row", "no"), "chunks")

    def matrices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            m = [lat.value.transfer(p, 0, k).tobytes() for p, k in zip(b.column("part").to_pylist(), b.column("len").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("row"), b.column("no"), pa.array(m, pa.binary())], names=["row", "no", "m"])

    def read(pdf) -> list[np.ndarray]:
        return [np.frombuffer(m).reshape(w, w) for m in pdf.sort_values("no")["m"]]

    def combined(key, pdf):
        import pandas as pd

        return pd.DataFrame({"row": [key[0]], "no": [key[1]], "m": [product(read(pdf)).tobytes()]})

    def inside(key, pdf):
        import pandas as pd

        pdf = pdf.sort_values("no")
        o = offsets(read(pdf), int(pdf["entry"].iloc[0]), int(pdf["exit"].iloc[0]))
        return pd.DataFrame({"row": pdf["row"], "no": pdf["no"], "entry": o[:-1], "exit": o[1:]})

    group = F.floor(F.col("no") / fan).alias("up")
    levels = [materialize(chunks.mapInArrow(matrices, "row long, no long, m binary"), "matrices")]
    most = levels[0].agg(F.max("no")).first()[0] or 0
    while most >= fan:
        levels.append(materialize(levels[-1].groupBy("row", group).applyInPandas(combined, "row long, no long, m binary"), "products"))
        most //= fan
    # each text is one group on the top level; it begins and ends without a piece reaching over
    found = levels[0].select("row").distinct().select("row", F.lit(0).cast("long").alias("up"), F.lit(0).alias("entry"), F.lit(0).alias("exit"))
    for level in reversed(levels):
        both = level.withColumn("up", group).join(found, ["row", "up"])
        found = materialize(both.groupBy("row", "up").applyInPandas(inside, "row long, no long, entry int, exit int"), "offsets").withColumnRenamed("no", "up")

    def traces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for p, k, i, j in zip(*(b.column(c).to_pylist() for c in ("part", "len", "entry", "exit"))):
                at, pieces = i, []
                for n_ in lat.value.trace(p, 0, k, i, j):
                    pieces.append(p[at : at + n_])
                    at += n_
                out.append(pieces)
            yield pa.RecordBatch.from_arrays([b.column("row"), b.column("no"), pa.array(out, pa.list_(pa.string()))], names=["row", "no", "pieces"])

    traced = chunks.join(found.withColumnRenamed("up", "no"), ["row", "no"]).select("row", "no", "part", "len", "entry", "exit").mapInArrow(traces, "row long, no long, pieces array<string>")
    joined = traced.groupBy("row").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("no", "pieces"))), lambda x: x["pieces"])).alias("pieces"))
    return rows.select("row", "doc_id").join(joined, "row", "left").select("doc_id", F.coalesce("pieces", F.array().cast("array<string>")).alias("pieces"))


# ---- word-wise encoding for BPE models --------------------------------------------------------------------------


class WordPieces:
    """The library's ids of whole texts, each word encoded once."""

    def __init__(self, path: str, max_words: int = 1_000_000) -> None:
        from sentencepiece import SentencePieceProcessor

        self.library = SentencePieceProcessor(model_file=path)
        pieces = [self.library.id_to_piece(i) for i in range(self.library.get_piece_size())]
        #: No piece holds a word mark after another character, so words can be encoded alone.
        self.words_alone = not any(MARK in p.lstrip(MARK) for p in pieces)
        self.doubtful = re.compile(f"  |^ | $|[{MARK}\\x00-\\x1f\\x7f-\\x9f]|[^\\x20-\\u024f]")
        self.max_words = max_words
        self.codes: dict[str, int] = {}
        self.pool: list[np.ndarray] = []
        self.flat, self.starts, self.lengths = np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def encode_many(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """ids of all texts in one array, number of ids of each."""
        if len(self.codes) > self.max_words:
            self.codes, self.flat, self.starts, self.lengths = {}, self.flat[:0], self.starts[:0], self.lengths[:0]
        rows: list[np.ndarray | None] = []
        fresh: list[str] = []
        codes = self.codes
        for t in texts:
            if not self.words_alone or self._must_see_whole(t):
                rows.append(None)
                continue
            row = []
            for word in t.split(" ") if t else ():
                c = codes.get(word)
                if c is None:
                    c = codes[word] = len(codes)
                    fresh.append(word)
                row.append(c)
            rows.append(np.array(row, np.int64))
        if fresh:
            new = self.library.encode(fresh, num_threads=1)
            sizes = np.fromiter(map(len, new), np.int64, len(new))
            self.starts = np.concatenate([self.starts, len(self.flat) + np.cumsum(sizes) - sizes])
            self.lengths = np.concatenate([self.lengths, sizes])
            self.flat = np.concatenate([self.flat, np.fromiter((i for ids in new for i in ids), np.int32, int(sizes.sum()))])
        out, sizes = [], np.zeros(len(texts), np.int64)
        for k, (t, row) in enumerate(zip(texts, rows)):
            if row is None:
                ids = np.array(self.library.encode(t, num_threads=1), np.int32)
            else:
                ids = self.flat[ranges(self.starts[row], self.lengths[row])]
            out.append(ids)
            sizes[k] = len(ids)
        return (np.concatenate(out) if out else np.zeros(0, np.int32)), sizes

    def _must_see_whole(self, text: str) -> bool:
        """Blanks that the library would join or drop, and characters that its normal form may change."""
        return self.doubtful.search(text.replace("\n", "")) is not None or "\n " in text or " \n" in text


def worker_pieces(path: str) -> WordPieces:
    if path not in _WORKER:
        _WORKER[path] = WordPieces(path)
    return _WORKER[path]


def encode(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, ids array<int> for every row of docs(doc_id, text), equal to the library's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = worker_pieces(path)
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                ids, sizes = enc.encode_many([t or "" for t in b.column("text").to_pylist()])
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(ids))
                yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), lists], names=["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """encoded(doc_id, ids) -> doc_id, text, as the library decodes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        library = worker_pieces(path).library
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                texts = library.decode([i or [] for i in b.column("ids").to_pylist()], num_threads=1) if b.num_rows else []
                yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def encode_and_check(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_pieces, ids_crc32 (unsigned, of little-endian unsigned 32-bit ids), decoded_crc32 (of the decoded text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        library = worker_pieces(path).library
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                ids = b.column("ids")
                cuts = ids.offsets.to_numpy()
                flat = np.asarray(ids.values.to_numpy(), "<u4")
                parts = [flat[i:j] for i, j in zip(cuts, cuts[1:])]
                texts = library.decode([p.tolist() for p in parts], num_threads=1)
                cols = [np.diff(cuts), [zlib.crc32(p) for p in parts], [zlib.crc32(t.encode()) for t in texts]]
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, pa.int64()) for c in cols)], names=["doc_id", "n_pieces", "ids_crc32", "decoded_crc32"])

    return encode(docs, path).mapInArrow(run, "doc_id long, n_pieces long, ids_crc32 long, decoded_crc32 long")
