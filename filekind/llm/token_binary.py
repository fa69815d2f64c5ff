"""Token ids in Simple-8b words, in segments that any reader can decode on its own.

Documents are range-partitioned by id and sorted, tokenised, and written as segments of consecutive documents. A segment is one byte
string: header, document ids, document lengths, an index of word offsets with one entry per block of BLOCK ids, the positions of escapes, and the 64-bit words.
The top four bits of a word select how many ids it packs and in how many bits; blocks start at a word of their own, so blocks are packed and read as arrays.
An id of 60 bits or more is written as an escape word followed by the id itself.

Each segment is a file of the shared folder, in whatever store pyarrow opens by its URI. A file is written under a name of its own and moved into place; a task that
runs again writes the same bytes again, and readers go by the list of files, which Spark commits, so lost executors leave nothing that counts.

Defined cases: a null or empty text holds the end id alone; null ids come first; rows that repeat an id keep
their own entries, ordered by the hash of the text; an empty table gives no segments; further columns are left alone.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import clean_text, shared_dir, shuffle_width, stash, table

MAGIC, VERSION = b"FKS8", 1
BLOCK = 128
END_ID = 2
#: Ids per segment after which a new one begins, and bytes of text that are tokenised at a time.
SEGMENT_IDS, TEXT_BYTES = 1 << 20, 1 << 23
#: Distinct words whose ids a worker process keeps, and words of letters that go to the library in one text.
MOST_WORDS, TOGETHER = 400_000, 64
#: Bits of an id under each selector; selector 0 is the escape, 1 is not used.
BITS = np.array([64, 0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60], np.uint64)
COUNTS = np.array([1, 0] + [60 // int(b) for b in BITS[2:]], np.int64)
#: The class of each id of up to 16 bits: the narrowest of BITS[2:] that holds it.
CLASSES = np.searchsorted(BITS[2:14], np.array([i.bit_length() for i in range(1 << 16)]), "left").astype(np.uint8)
HEADER = "<4sHHIQIII"  # magic, version, block, documents, ids, blocks, words, escapes


def pack(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(words, word offset of each block, word positions of escapes) of unsigned 64-bit ids."""
    n = len(ids)
    blocks = -(-n // BLOCK)
    grid = np.zeros((blocks, BLOCK), np.uint64)
    grid.reshape(-1)[:n] = ids
    # Class 14: none of BITS[2:] holds the id, an escape.
    if n and int(ids.max()) < 1 << 16:
        width = CLASSES[grid]
    else:
        width = np.zeros((blocks, BLOCK), np.uint8)
        for b in BITS[2:]:
            width += (grid >> b > 0).astype(np.uint8)
    selector = np.zeros((blocks, BLOCK), np.uint8)
    widest, reach = width.copy(), 1
    for s in range(15, 1, -1):  # from one id in a word to sixty
        while reach < COUNTS[s]:
            np.maximum(widest[:, : BLOCK - reach], width[:, reach:], out=widest[:, : BLOCK - reach])
            reach += 1
        fits = widest <= s - 2
        if not fits.any():
            break  # more ids in fewer bits fit nowhere either
        np.copyto(selector, s, where=fits)
    start = np.zeros(blocks * BLOCK, bool)
    flat, at = selector.reshape(-1), np.arange(blocks) * BLOCK
    end = np.minimum(at + BLOCK, n)
    while len(at):
        start[at] = True
        at = at + COUNTS[flat[at]]
        more = at < end
        at, end = at[more], end[more]
    at = np.flatnonzero(start)
    kinds = flat[at].astype(np.int64)
    place = np.cumsum(1 + (kinds == 0)) - 1 - (kinds == 0)
    words = np.zeros(len(at) + int((kinds == 0).sum()), np.uint64)
    padded = np.concatenate([grid.reshape(-1), np.zeros(60, np.uint64)])
    for s in np.unique(kinds):
        mine = kinds == s
        if s == 0:
            words[place[mine] + 1] = padded[at[mine]]
            continue
        c, b = int(COUNTS[s]), BITS[s]
        first = at[mine]
        room = BLOCK - first % BLOCK
        value = np.full(len(first), np.uint64(s) << np.uint64(60), np.uint64)
        for j in range(c):
            value |= np.where(j < room, padded[first + j], np.uint64(0)) << np.uint64(j * int(b))
        words[place[mine]] = value
    offsets = place[np.searchsorted(at, np.arange(blocks) * BLOCK)]
    return words, offsets.astype("<u4"), place[kinds == 0].astype("<u4")


def unpack(words: np.ndarray, offsets: np.ndarray, escapes: np.ndarray, n: int) -> np.ndarray:
    """The ids again."""
    kinds = (words >> np.uint64(60)).astype(np.int64)
    counts = COUNTS[kinds]
    if len(escapes):
        kinds[escapes], counts[escapes] = 0, 1
        kinds[escapes + 1], counts[escapes + 1] = 1, 0
    before = np.cumsum(counts) - counts
    block = np.repeat(np.arange(len(offsets)), np.diff(np.append(offsets.astype(np.int64), len(words))))
    inside = before - before[offsets.astype(np.int64)][block]
    out = np.zeros(len(offsets) * BLOCK, np.uint64)
    for s in np.unique(kinds):
        mine = np.flatnonzero(kinds == s)
        to = block[mine] * BLOCK + inside[mine]
        if s == 0:
            out[to] = words[mine + 1]
        elif s > 1:
            b = int(BITS[s])
            mask = np.uint64((1 << b) - 1)
            for j in range(int(COUNTS[s])):
                ok = inside[mine] + j < BLOCK
                out[to[ok] + j] = words[mine[ok]] >> np.uint64(j * b) & mask
    return out[:n]


def segment_bytes(doc_ids: list[int | None], lengths: np.ndarray, ids: np.ndarray) -> bytes:
    words, offsets, escapes = pack(ids.astype(np.uint64))
    known = np.array([d is not None for d in doc_ids], np.uint8)
    return b"".join((
        struct.pack(HEADER, MAGIC, VERSION, BLOCK, len(doc_ids), len(ids), len(offsets), len(words), len(escapes)),
        np.array([d or 0 for d in doc_ids], "<i8").tobytes(), known.tobytes(), lengths.astype("<u4").tobytes(),
        offsets.tobytes(), escapes.tobytes(), words.astype("<u8").tobytes(),
    ))


def read_segment(data: bytes) -> tuple[list[int | None], np.ndarray, np.ndarray]:
    """(document ids, lengths, ids) of a segment."""
    magic, version, block, docs, n, blocks, words, escapes = struct.unpack_from(HEADER, data)
    if (magic, version, block) != (MAGIC, VERSION, BLOCK):
        raise ValueError("not a segment of this format")
    at = struct.calcsize(HEADER)

    def take(kind: str, count: int) -> np.ndarray:
        nonlocal at
        got = np.frombuffer(data, kind, count, at)
        at += got.nbytes
        return got

    doc_ids, known, lengths = take("<i8", docs), take("u1", docs), take("<u4", docs)
    offsets, odd, packed = take("<u4", blocks), take("<u4", escapes), take("<u8", words)
    return [int(d) if k else None for d, k in zip(doc_ids, known, strict=True)], lengths, unpack(packed.astype(np.uint64), offsets, odd.astype(np.int64), n)


class Words:
    """Ids of texts, encoding each distinct white-space-separated piece once.

    The tokenizer of the contract treats white space as a gap that no token, letter composition or special token crosses, so the ids of a
    text are those of its pieces one after another. Every piece goes to the library as it is; ids of pieces seen before are kept. Pieces of nothing but letters
    go many in one text, as a call costs more than a word: each is one pre-token, so its ids end at the only one of them that closes a word. All others go by themselves.
    """

    #: A letter, signs that are one pre-token after it, and the end of the piece: parting them by a space changes no id and leaves fewer distinct pieces.
    SIGNS = "([a-zA-Z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff])([.,;:!?*%$#&]+)(\\s|$)"
    #: Where letters must keep their case: special tokens are told by it, and a small letter may be composed with a mark that a capital is not.
    CASED = "<\\||[\u0300-\u036f]"

    #: Letters that stay one letter each, whatever stands beside them.
    LETTERS = "^[a-zA-Z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+$"

    def __init__(self, path: str):
        import os

        os.environ["RAYON_NUM_THREADS"] = "1"  # tasks already use every core
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        #: Whether an id closes a word; a vocabulary that marks no ends gets every piece by itself.
        vocabulary, mark = self.tokenizer.get_vocab(), getattr(self.tokenizer.model, "end_of_word_suffix", None)
        self.closes = np.zeros(max(vocabulary.values()) + 1, bool)
        self.closes[[i for token, i in vocabulary.items() if mark and token.endswith(mark)]] = True
        self.words, self.values, self.start, self.size = pa.array([], pa.string()), np.zeros(0, np.uint32), np.zeros(0, np.int64), np.zeros(0, np.int64)

    @classmethod
    def of(cls, path: str) -> Words:
        """The one of this worker process: its tasks share the loaded vocabulary and the ids of the first MOST_WORDS distinct words."""
        if path not in _WORDS:
            _WORDS[path] = cls(path)
        return _WORDS[path]

    def distinct(self, words: pa.Array, letters: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """(ids of the words one after another, the number of ids of each), each word encoded by the library; so many at the head are of letters alone."""
        texts = words.to_pylist()
        joined = [" ".join(texts[i : min(i + TOGETHER, letters)]) for i in range(0, letters, TOGETHER)]
        found = [e.ids for e in self.tokenizer.encode_batch_fast(joined + texts[letters:], add_special_tokens=False)]
        size = np.fromiter(map(len, found), np.int64, len(found))
        ids = np.fromiter(chain.from_iterable(found), np.uint32, int(size.sum()))
        if not letters:
            return ids, size
        ends = np.flatnonzero(self.closes[ids[: size[: len(joined)].sum()]])
        if len(ends) != letters:
            return self.distinct(words)
        return ids, np.concatenate([np.diff(ends, prepend=-1), size[len(joined) :]])

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts in order, the number of ids of each)."""
        texts = pc.if_else(pc.match_substring_regex(texts, self.CASED), texts, pc.ascii_lower(texts))
        pieces = pc.ascii_split_whitespace(pc.replace_substring_regex(texts, self.SIGNS, r"\1 \2\3"))
        coded = pieces.flatten().dictionary_encode()
        at = pc.index_in(coded.dictionary, value_set=self.words)
        new = np.flatnonzero(at.is_null().to_numpy(zero_copy_only=False))
        simple = pc.match_substring_regex(coded.dictionary.take(pa.array(new)), self.LETTERS).to_numpy(zero_copy_only=False) & self.closes.any()
        new = np.concatenate([new[simple], new[~simple]])
        fresh = coded.dictionary.take(pa.array(new))
        more, lengths = self.distinct(fresh, int(simple.sum()))
        values = np.concatenate([self.values, more])
        begin = len(self.values) + np.cumsum(lengths) - lengths
        at = at.fill_null(0).to_numpy(zero_copy_only=False)
        start, size = (x[at] if len(x) else np.zeros(len(at), np.int64) for x in (self.start, self.size))
        start[new], size[new] = begin, lengths
        if len(self.words) + len(fresh) <= MOST_WORDS:
            self.words, self.values = pa.concat_arrays([self.words, fresh]), values
            self.start, self.size = np.concatenate([self.start, begin]), np.concatenate([self.size, lengths])
        which = coded.indices.to_numpy(zero_copy_only=False)
        lengths = size[which]
        ends = np.cumsum(lengths)
        total = int(ends[-1]) if len(ends) else 0
        source = np.repeat(start[which] - (ends - lengths), lengths) + np.arange(total)
        bounds = np.concatenate([[0], ends])[pieces.offsets.to_numpy() - pieces.offsets[0].as_py()]
        return values[source], np.diff(bounds)


#: The Words of this worker process by path of the vocabulary.
_WORDS: dict[str, Words] = {}


def with_end(ids: np.ndarray, lengths: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    out = np.empty(len(ids) + len(lengths), np.uint32)
    stops = np.cumsum(lengths + 1) - 1
    out[stops] = end_id
    rest = np.ones(len(out), bool)
    rest[stops] = False
    out[rest] = ids
    return out, lengths + 1


def put_file(folder: str, name: str, data: bytes) -> None:
    """Write a file of the shared folder (a URI or path) under a name of its own and move it into place, so that no reader sees a part of it."""
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(folder)
    with store.open_output_stream(under_way := f"{path}/_{name}-{uuid.uuid4().hex}") as f:
        f.write(data)
    store.move(under_way, f"{path}/{name}")


def get_file(folder: str, name: str) -> bytes:
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(folder)
    with store.open_input_file(f"{path}/{name}") as f:
        return f.read()


def write_segments(df: DataFrame, vocabulary: str, folder: str, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Tokenise, pack, and write a file for each segment into the folder; the (written) list of files: part, seq, file, bytes, n_docs, n_tokens."""
    from pyarrow import fs

    store, place = fs.FileSystem.from_uri(folder)
    store.create_dir(place, recursive=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seq, words = TaskContext.get().partitionId(), 0, Words.of(vocabulary)
        docs, sizes, held, total = [], [], [], 0

        def flush() -> pa.RecordBatch:
            nonlocal seq, docs, sizes, held, total
            data = segment_bytes(docs, np.concatenate(sizes), np.concatenate(held))
            put_file(folder, name := f"{part:06d}-{seq:06d}.s8b", data)
            row = pa.RecordBatch.from_pylist([{"part": part, "seq": seq, "file": name, "bytes": len(data), "n_docs": len(docs), "n_tokens": total}], LISTED)
            seq, docs, sizes, held, total = seq + 1, [], [], [], 0
            return row

        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            bytes_before = np.concatenate([[0], np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False))])
            at = 0
            while at < len(ids):
                to = max(at + 1, int(np.searchsorted(bytes_before, bytes_before[at] + TEXT_BYTES, "right")) - 1)
                coded, lengths = with_end(*words.encode(texts.slice(at, to - at)), end_id)
                docs += ids[at:to]
                sizes.append(lengths)
                held.append(coded)
                total, at = total + len(coded), to
                if total >= SEGMENT_IDS:
                    yield flush()
        if docs:
            yield flush()

    spark = df.sparkSession
    ordered = df.select(F.col(id_col).cast("long").alias("doc_id"), clean_text(text_col).alias("text")).repartitionByRange(shuffle_width(spark), "doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text"))
    return stash(ordered.mapInArrow(run, "part int, seq int, file string, bytes long, n_docs long, n_tokens long"))


LISTED = pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("file", pa.string()), ("bytes", pa.int64()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())])


def read_documents(segments: DataFrame, folder: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the files of the folder that `segments` lists."""
    parts = segments.groupBy("part").agg(F.sum("n_tokens").alias("ids"))  # as many rows as range partitions
    base = parts.select("part", F.coalesce(F.sum("ids").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = F.coalesce(F.sum("n_tokens").over(Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = segments.select("part", "file", inside.alias("inside")).join(F.broadcast(base), "part").select("file", (F.col("base") + F.col("inside")).alias("start"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                docs, lengths, ids = read_segment(get_file(folder, name))
                ends = np.cumsum(lengths.astype(np.int64))
                data = memoryview(ids.astype("<u4").tobytes())
                crcs = [zlib.crc32(data[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), lengths.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(docs, pa.int64()), pa.array(start + ends - lengths, pa.int64()), pa.array(lengths, pa.int64()), pa.array(crcs, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"],
                )

    # Only names and offsets move; each task reads its files where they are.
    return starts.repartition(shuffle_width(segments.sparkSession), "file").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op8_simple8b_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    folder = f"{shared_dir(spark)}/segments-{uuid.uuid4().hex}"
    return read_documents(write_segments(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), folder), folder)
