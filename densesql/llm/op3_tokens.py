"""Token ids as canonical length-limited Huffman files.

Texts are encoded once and their ids staged in two bytes each.  Global id counts (one
vector per task, summed by id) give code lengths by package merging under a length
limit; codes are canonical, so the file format carries only the lengths.  Ids are
written in ascending doc_id order as segments: whole documents, each segment coded on
its own, with the bit offset of every 256th id, so that any stretch can be decoded by
table look-up without what stands before it.

File format: a folder ``segments`` of Parquet rows (part, seq, ahead, doc_ids,
n_tokens, n_ids, checkpoints, payload) and a folder ``code`` with one row (max_bits, lengths).
``part`` ascends with doc_id and ``seq`` within a part, where ``ahead`` ids precede.

Defined results: a null or empty text is its end id alone; null doc_ids stand first;
rows with equal doc_id follow by number of ids and place in the input; repeated rows give one
result row each; an empty table gives empty files; other columns are ignored.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm.common import arrow_schema, documents, small_batches, trimmed
from densesql.plans.staging import Staging, shuffles_released

TOKENIZER, END_ID = "word_bpe_49k.json", 2
#: Longest code; ids between checkpoints; ids a segment aims at.
MAX_BITS, STRIDE, SEGMENT_IDS = 18, 256, 1 << 19
#: Cores whose ids a worker remembers; beyond that the older half is forgotten.
REMEMBERED = 600_000
#: Marks that are split off behind a letter (none that special tokens contain), and words encoded together.
MARKS, JOINED = ".,;:!?*#$%&", 64
#: Bytes of text encoded together, and distinct pieces that Python holds at once.
GATHERED_BYTES, DISTINCT = 14 << 20, 1 << 15

ENCODED = "doc_id long, n_tokens long, ids binary"
SEGMENTS = "part int, seq int, ahead long, doc_ids array<long>, n_tokens array<long>, n_ids long, checkpoints array<long>, payload binary"
READ = "doc_id long, start long, n_tokens long, ids_crc32 long"

_ENCODERS: dict[str, "WordEncoder"] = {}


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordEncoder:
    """Encodes texts piece by piece, remembering what it has encoded.

    The tokenizer's own pre-tokenisation never joins what a space, line feed or tab
    separates, nor a letter and a mark that follows it; and it lower-cases first.  So a
    text's ids are the ids of its pieces in turn, and a piece's those of its lower-cased
    core and its marks.  New cores of letters only are encoded many at a time: each is
    one word to the tokenizer, whose last id alone ends a word.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab()
        if self.tokenizer.get_vocab_size() > 1 << 16:
            raise ValueError("ids need more than 16 bits")
        self.ends_word = np.zeros(1 << 16, dtype=bool)
        self.ends_word[[i for w, i in vocabulary.items() if w.endswith("</w>")]] = True
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def _parts(self, piece: str) -> tuple[str, str]:
        """A piece's core and marks; marks are split off only behind a letter."""
        core = piece.rstrip(MARKS)
        if not core or not core[-1].isalpha():
            return piece if "<" in piece or not piece.isascii() else piece.lower(), ""
        return core if "<" in core or not core.isascii() else core.lower(), piece[len(core) :]

    def _one_by_one(self, parts: list[str]) -> None:
        for w, e in zip(parts, self.tokenizer.encode_batch_fast(parts, add_special_tokens=False), strict=True):
            self.young[w] = np.array(e.ids, dtype="<u2").tobytes()

    def _learn(self, parts: set[str]) -> None:
        """Remember the ids of parts."""
        words = [w for w in parts if w.isalpha()]
        rest = [w for w in parts if not w.isalpha()]
        for k in range(0, len(words), JOINED):
            chunk = words[k : k + JOINED]
            ids = np.array(self.tokenizer.encode_batch_fast([" ".join(chunk)], add_special_tokens=False)[0].ids, dtype="<u2")
            ends = 2 * (np.flatnonzero(self.ends_word[ids]) + 1)
            if len(ends) == len(chunk):
                raw, start = ids.tobytes(), 0
                for w, end in zip(chunk, ends.tolist(), strict=True):
                    self.young[w] = raw[start:end]
                    start = end
            else:
                rest += chunk
        self._one_by_one(rest)

    def encode(self, texts: pa.Array) -> pa.Array:
        """Ids of each text as little-endian 16-bit integers in a binary array.

        Splitting, finding the distinct pieces and putting the ids together run inside Arrow;
        Python sees each distinct piece of a batch once.
        """
        texts = pc.fill_null(texts, "")
        for blank in "\n\t":
            texts = pc.replace_substring(texts, blank, " ")
        n_texts, lists = len(texts), pc.split_pattern(texts, " ")
        coded, ends = lists.flatten().dictionary_encode(), np.array(lists.offsets)
        del texts, lists  # the largest arrays, done with before the ids are put together
        words = coded.dictionary
        cuts = (self._ids_of(words.slice(k, DISTINCT).to_pylist()) for k in range(0, max(1, len(words)), DISTINCT))
        found = pa.concat_arrays([pa.array(ids, pa.large_binary()) for ids in cuts]).take(coded.indices)
        offsets = np.frombuffer(found.buffers()[1], dtype=np.int64)[found.offset :][: len(found) + 1]
        at = (offsets[ends - ends[0]] - offsets[0]).astype(np.int64)
        data = found.buffers()[2].slice(int(offsets[0])) if found.buffers()[2] else pa.py_buffer(b"")
        return pa.Array.from_buffers(pa.large_binary(), n_texts, [None, pa.py_buffer(at), data])

    def _ids_of(self, pieces: list[str]) -> list[bytes]:
        split = list(map(self._parts, pieces))
        young, old = self.young, self.old
        new = {core for core, _ in split}
        new.update(marks for _, marks in split)
        new.difference_update(young)
        young.update((part, old[part]) for part in new if part in old)
        self._learn(new.difference(old))
        ids = [young[core] + young[marks] if marks else young[core] for core, marks in split]
        if len(young) > REMEMBERED // 2:
            self.young, self.old = {}, young
        return ids


def encoder(path: str) -> WordEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = WordEncoder(path)
    return _ENCODERS[path]


def gathered(batches: Iterator[pa.RecordBatch], least_bytes: int = GATHERED_BYTES) -> Iterator[pa.RecordBatch]:
    """Batches put together until they hold so many bytes: the more text, the fewer distinct pieces a word."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        held.append(batch)
        if sum(b.nbytes for b in held) >= least_bytes:
            yield pa.concat_batches(held)
            held = []
    if held:
        yield pa.concat_batches(held)


def encode_documents(docs: DataFrame, tokenizer: str) -> DataFrame:
    """(doc_id, n_tokens, ids): the ids of the whole text; n_tokens counts the end id too, which is not stored."""
    schema = arrow_schema(docs.sparkSession, ENCODED)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = encoder(tokenizer)
        for batch in gathered(batches):
            ids = words.encode(batch.column(1))
            sizes = pc.add(pc.divide(pc.binary_length(ids), 2), 1)
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), sizes.cast(pa.int64()), ids.cast(pa.binary())], schema=schema)
            pa.default_memory_pool().release_unused()

    small_batches(docs.sparkSession)
    return docs.select("doc_id", "text").mapInArrow(trimmed(run), ENCODED)


# --- the code ---------------------------------------------------------------------------


def limited_lengths(counts: np.ndarray, max_bits: int = MAX_BITS) -> np.ndarray:
    """Optimal code lengths of at most ``max_bits`` for the ids with a count (package merging)."""
    ids = np.flatnonzero(counts)
    lengths = np.zeros(len(counts), dtype=np.uint8)
    if len(ids) < 2:
        lengths[ids] = 1
        return lengths
    if len(ids) > 1 << max_bits:
        raise ValueError("too many ids for the length limit")
    order = ids[np.argsort(counts[ids], kind="stable")]
    leaves = counts[order].astype(np.int64)
    level, is_leaf = leaves, [np.ones(len(leaves), dtype=bool)]
    for _ in range(max_bits - 1):
        even = len(level) // 2 * 2
        packages = level[0:even:2] + level[1:even:2]
        weights = np.concatenate([leaves, packages])
        at = np.argsort(weights, kind="stable")
        level = weights[at]
        is_leaf.append(at < len(leaves))
    take = 2 * len(leaves) - 2
    for flags in reversed(is_leaf):
        chosen = int(flags[:take].sum())
        lengths[order[:chosen]] += 1
        take = 2 * (take - chosen)
    return lengths


def canonical_codes(lengths: np.ndarray) -> np.ndarray:
    """Codes that ascend by length and then id."""
    codes = np.zeros(len(lengths), dtype=np.uint64)
    code, width = 0, 0
    for i in np.lexsort((np.arange(len(lengths)), lengths)):
        if lengths[i]:
            code <<= int(lengths[i]) - width
            width = int(lengths[i])
            codes[i] = code
            code += 1
    return codes


def pack(ids: np.ndarray, lengths: np.ndarray, codes: np.ndarray) -> tuple[bytes, np.ndarray]:
    """The ids' bits as big-endian 32-bit words, and the bit offset of every STRIDE-th id."""
    if not len(ids):
        return b"", np.zeros(0, dtype=np.int64)
    bits = lengths[ids].astype(np.int64)
    ends = np.cumsum(bits)
    at = ends - bits
    word, shift = at >> 5, (64 - (at & 31) - bits).astype(np.uint64)
    value = codes[ids] << shift
    first = np.flatnonzero(np.diff(word, prepend=-1))
    out = np.zeros(int(ends[-1] >> 5) + 3, dtype=np.uint64)
    out[word[first]] += np.add.reduceat(value >> np.uint64(32), first)
    out[word[first] + 1] += np.add.reduceat(value & np.uint64(0xFFFFFFFF), first)
    return out.astype(">u4").tobytes(), at[::STRIDE]


class Decoder:
    """Table-driven decoding: one look-up of ``max_bits`` bits gives an id and its length.

    All stretches between checkpoints advance together, one id a step.
    """

    def __init__(self, lengths: np.ndarray, max_bits: int = MAX_BITS):
        self.bits = max_bits
        used = np.flatnonzero(lengths)
        order = used[np.lexsort((used, lengths[used]))]
        spans = np.left_shift(1, max_bits - lengths[order].astype(np.int64))
        self.symbol = np.zeros(1 << max_bits, dtype=np.int32)
        self.length = np.ones(1 << max_bits, dtype=np.int64)
        self.symbol[: spans.sum()] = np.repeat(order, spans)
        self.length[: spans.sum()] = np.repeat(lengths[order].astype(np.int64), spans)

    def unpack(self, payload: bytes, checkpoints: np.ndarray, n_ids: int) -> np.ndarray:
        if not n_ids:
            return np.zeros(0, dtype=np.int32)
        words = np.frombuffer(payload, dtype=">u4").astype(np.uint64)
        pairs = (words << np.uint64(32)) | np.append(words[1:], np.uint64(0))
        at = np.asarray(checkpoints, dtype=np.int64).copy()
        out = np.empty((min(STRIDE, n_ids), len(at)), dtype=np.int32)
        last, mask = len(pairs) - 1, np.uint64((1 << self.bits) - 1)
        for row in out:
            window = (pairs[np.minimum(at >> 5, last)] >> (64 - self.bits - (at & 31)).astype(np.uint64)) & mask
            row[:] = self.symbol[window]
            at += self.length[window]
        return out.T.reshape(-1)[:n_ids]


def count_ids(encoded: DataFrame, end_id: int = END_ID, n_ids: int = 1 << 16, max_tasks: int = 2048) -> np.ndarray:
    """How often each id occurs in all documents; what reaches the driver is one row an id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(n_ids, dtype=np.int64)
        for batch in batches:
            data = batch.column(0)
            at = np.frombuffer(data.buffers()[1], dtype=np.int32)[data.offset :][: len(data) + 1]
            if len(data) and at[-1] > at[0]:
                total += np.bincount(np.frombuffer(data.buffers()[2], dtype="<u2")[at[0] // 2 : at[-1] // 2], minlength=n_ids)
            total[end_id] += len(data)
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(total[used])], names=["id", "n"])

    found = encoded.select("ids").coalesce(max_tasks).mapInArrow(trimmed(run), "id int, n long").groupBy("id").agg(F.sum("n").alias("n")).toPandas()
    counts = np.zeros(n_ids, dtype=np.int64)
    counts[found["id"].to_numpy(dtype=np.int64)] = found["n"].to_numpy(dtype=np.int64)
    return counts


# --- files ------------------------------------------------------------------------------


def write_token_files(encoded: DataFrame, path: str, end_id: int = END_ID, max_bits: int = MAX_BITS) -> None:
    """Write a staged table of encoded documents in ascending doc_id order; see the format above."""
    spark = encoded.sparkSession
    lengths = limited_lengths(count_ids(encoded, end_id), max_bits)
    codes = canonical_codes(lengths)
    schema = arrow_schema(spark, SEGMENTS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seq = TaskContext.get().partitionId(), 0
        end = np.array([end_id], dtype="<u2")
        doc_ids: list[int | None] = []
        sizes: list[int] = []
        ids: list[np.ndarray] = []
        held = ahead = 0

        def close() -> pa.RecordBatch:
            flat = np.concatenate(ids).astype(np.int64)
            payload, checkpoints = pack(flat, lengths, codes)
            row = ([part], [seq], [ahead], [doc_ids], [sizes], [len(flat)], [checkpoints], [payload])
            return pa.RecordBatch.from_arrays([pa.array(v, type=f.type) for v, f in zip(row, schema, strict=True)], schema=schema)

        for batch in batches:
            for doc_id, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                doc_ids.append(doc_id)
                ids += [np.frombuffer(raw.as_buffer(), dtype="<u2"), end]
                sizes.append(len(ids[-2]) + 1)
                held += sizes[-1]
                if held >= SEGMENT_IDS:
                    yield close()
                    doc_ids, sizes, ids, held, seq, ahead = [], [], [], 0, seq + 1, ahead + held
        if ids:
            yield close()

    keys = [F.col("doc_id").asc_nulls_first(), "n_tokens", "row_id"]
    ordered = encoded.repartitionByRange(*keys).sortWithinPartitions(*keys).select("doc_id", "ids")
    with shuffles_released(spark):
        ordered.mapInArrow(trimmed(run), SEGMENTS).write.mode("overwrite").parquet(f"{path}/segments")
    code = spark.createDataFrame([(max_bits, bytearray(lengths.tobytes()))], "max_bits int, lengths binary")
    code.coalesce(1).write.mode("overwrite").parquet(f"{path}/code")


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """Decode every segment: (doc_id, start, n_tokens, ids_crc32), one row a document."""
    code = spark.read.parquet(f"{path}/code").first()
    lengths, max_bits = np.frombuffer(bytes(code["lengths"]), dtype=np.uint8), code["max_bits"]
    segments = spark.read.parquet(f"{path}/segments")
    sizes = segments.groupBy("part").agg(F.sum("n_ids").alias("n")).collect()  # one row a written part
    totals = sorted((r["part"], r["n"]) for r in sizes)
    before = dict(zip([p for p, _ in totals], np.cumsum([0] + [n for _, n in totals])[:-1].tolist(), strict=True))
    schema = arrow_schema(spark, READ)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decoder = Decoder(lengths, max_bits)
        for batch in batches:
            for row in (batch.slice(k, 1).to_pylist()[0] for k in range(batch.num_rows)):
                ids = decoder.unpack(row["payload"], np.array(row["checkpoints"], dtype=np.int64), row["n_ids"]).astype("<u4")
                sizes = np.array(row["n_tokens"], dtype=np.int64)
                ends = np.cumsum(sizes)
                start = before[row["part"]] + row["ahead"] + ends - sizes
                crcs = [zlib.crc32(ids[a:b].tobytes()) for a, b in zip(ends - sizes, ends, strict=True)]
                cols = (row["doc_ids"], start, sizes, crcs)
                yield pa.RecordBatch.from_arrays([pa.array(v, type=f.type) for v, f in zip(cols, schema, strict=True)], schema=schema)

    return segments.mapInArrow(trimmed(run), READ)


def token_files(docs: DataFrame, tokenizer: str | None = None, end_id: int = END_ID) -> DataFrame:
    """Encode, write, read back: (doc_id, start, n_tokens, ids_crc32)."""
    staging = Staging(docs.sparkSession, "tokens")
    encoded = staging.table(encode_documents(docs, tokenizer or tokenizer_path()), "encoded", row_id="row_id")
    write_token_files(encoded, staging.path("files"), end_id)
    staging.drop("encoded")
    return read_token_files(docs.sparkSession, staging.path("files"))


def op3_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files(documents(spark, sf_dir))
