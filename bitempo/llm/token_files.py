"""Token-id output in Arrow stream files of equal-length sequences.

A file holds record batches of ``ids`` (fixed-size list of uint16 or uint32), ``mask`` (fixed-size list of bool, one bit each: a real id
or padding), ``ends`` (fixed-size list of bool: last id of a document) and ``doc_ids`` (ids of the documents that end in the sequence, in
order). Batches are uncompressed and all but a file's last hold the same number of sequences, which the schema names. The writer reports where
each batch begins, so a reader finds sequence n by one division, one seek and one slice: a reader of a mapped file gets its ids, and the
eight to a byte packed bits of its mask, as views of the file's pages.

Cases: null and empty texts hold the end id alone; documents of one id are ordered by a hash of their texts, then by the texts, so that reruns agree
and a hot id is dealt over files; repeated rows are written once for each row; null doc_ids come first; an empty table gives no file and
no rows; other columns are ignored. Each attempt of a task writes a file with a name of its own, and only files that a
successful task reports are read, so lost executors and repeated tasks leave no double rows.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_of_ids, cut, default_vocabulary, fresh_folder, word_tokenizer

SEQUENCE = 2048
BATCH_SEQUENCES = 256
NO_ID = -(1 << 63)  # stands for a null doc_id inside a file


def _schema(length: int, wide: bool, batch: int):
    import pyarrow as pa

    if length % 8:
        raise ValueError("a sequence's length must be a multiple of 8, so that its mask begins at a byte")
    return pa.schema(
        [
            ("ids", pa.list_(pa.uint32() if wide else pa.uint16(), length)),
            ("mask", pa.list_(pa.bool_(), length)),
            ("ends", pa.list_(pa.bool_(), length)),
            ("doc_ids", pa.list_(pa.int64())),
        ],
        {"sequences_a_batch": str(batch)},
    )


def open_uri(uri: str):
    """Filesystem and path behind a URI; plain paths are local."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


class SequenceWriter:
    """Cuts a stream of documents' ids into sequences of one length and writes them as an Arrow stream file."""

    def __init__(self, uri: str, length: int = SEQUENCE, wide: bool = False, batch: int = BATCH_SEQUENCES):
        import pyarrow as pa

        self.length, self.batch, self.kind = length, batch, np.uint32 if wide else np.uint16
        files, path = open_uri(uri)
        files.create_dir(path.rpartition("/")[0], recursive=True)
        self.schema = _schema(length, wide, batch)
        self.sink = files.open_output_stream(path)
        self.writer = pa.ipc.new_stream(self.sink, self.schema)
        self.offsets: list[int] = []  # where each batch begins
        self.sequences = 0
        self._clear()

    def _clear(self) -> None:
        self.ids = np.zeros(self.batch * self.length, self.kind)
        self.ends = np.zeros(self.batch * self.length, bool)
        self.filled = 0
        self.done: list[tuple[int, int]] = []  # (sequence in this batch, doc_id)

    def add(self, doc_id: int, ids: np.ndarray) -> None:
        at, room = 0, self.batch * self.length
        while at < len(ids):
            n = min(room - self.filled, len(ids) - at)
            self.ids[self.filled : self.filled + n] = ids[at : at + n]
            self.filled += n
            at += n
            if at == len(ids):
                self.ends[self.filled - 1] = True
                self.done.append(((self.filled - 1) // self.length, doc_id))
            if self.filled == room:
                self.flush()

    def flush(self) -> None:
        import pyarrow as pa

        if not self.filled:
            return
        n = -(-self.filled // self.length)
        size = n * self.length
        mask = np.arange(size) < self.filled
        held: list[list[int]] = [[] for _ in range(n)]
        for sequence, doc_id in self.done:
            held[sequence].append(doc_id)
        pack = lambda flat: pa.FixedSizeListArray.from_arrays(pa.array(flat), self.length)
        columns = [pack(self.ids[:size]), pack(mask), pack(self.ends[:size]), pa.array(held, pa.list_(pa.int64()))]
        self.offsets.append(self.sink.tell() or self.schema.serialize().size)  # the schema is written with the first batch
        self.sequences += n
        self.writer.write_batch(pa.RecordBatch.from_arrays(columns, schema=self.schema))
        self._clear()

    def close(self) -> None:
        self.flush()
        self.writer.close()
        self.sink.close()


def read_batches(uri: str):
    """Record batches of a file; a local file is mapped, so that their buffers are the file's pages."""
    import pyarrow as pa

    files, path = open_uri(uri)
    source = pa.memory_map(path) if files.type_name == "local" else files.open_input_stream(path)
    with source, pa.ipc.open_stream(source) as reader:
        yield from reader


class SequenceReader:
    """Random access to the sequences of one file; ``offsets`` as the writer reported them, else they are found by one walk over the batches' heads."""

    def __init__(self, uri: str, offsets: list[int] | None = None):
        import pyarrow as pa

        files, path = open_uri(uri)
        self.source = pa.memory_map(path) if files.type_name == "local" else files.open_input_file(path)
        self.schema = pa.ipc.open_stream(self.source).schema
        self.length = self.schema.field("ids").type.list_size
        self.a_batch = int(self.schema.metadata[b"sequences_a_batch"])
        self.offsets = list(offsets) if offsets is not None else self._walk()
        self.held: tuple[int, object] | None = None

    def _walk(self) -> list[int]:
        import pyarrow as pa

        self.source.seek(0)
        pa.ipc.read_message(self.source)  # the schema
        out = []
        while True:
            at = self.source.tell()
            try:
                pa.ipc.read_message(self.source)
            except EOFError:
                return out
            out.append(at)

    def _batch(self, index: int):
        import pyarrow as pa

        number, place = divmod(index, self.a_batch)
        if index < 0 or number >= len(self.offsets):
            raise IndexError(index)
        if self.held is None or self.held[0] != number:
            self.source.seek(self.offsets[number])
            self.held = number, pa.ipc.read_record_batch(pa.ipc.read_message(self.source), self.schema)
        if place >= self.held[1].num_rows:
            raise IndexError(index)
        return self.held[1], place

    def ids(self, index: int) -> np.ndarray:
        """Ids of a sequence, padding included, as a view."""
        batch, place = self._batch(index)
        return batch.column("ids").flatten().to_numpy(zero_copy_only=True)[place * self.length : (place + 1) * self.length]

    def mask_bits(self, index: int) -> np.ndarray:
        """The mask's bits, eight to a byte and the least bit first, as a view."""
        batch, place = self._batch(index)
        bits = np.frombuffer(batch.column("mask").flatten().buffers()[1], np.uint8)
        return bits[place * self.length // 8 : (place + 1) * self.length // 8]

    def mask(self, index: int) -> np.ndarray:
        return np.unpackbits(self.mask_bits(index), bitorder="little").astype(bool)


def sequence_at(uri: str, index: int, offsets: list[int] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Ids, as a view, and mask of sequence ``index`` of a file."""
    reader = SequenceReader(uri, offsets)
    return reader.ids(index), reader.mask(index)


def documents_of(uri: str) -> Iterator[tuple[int | None, np.ndarray]]:
    """The documents of a file in order: (doc_id, ids with the end id)."""
    parts: list[np.ndarray] = []
    for batch in read_batches(uri):
        ids = batch.column("ids").flatten().to_numpy()
        ends = np.flatnonzero(batch.column("ends").flatten().to_numpy(zero_copy_only=False))
        used = int(batch.column("mask").flatten().true_count)
        at = 0
        for end, doc_id in zip(ends, batch.column("doc_ids").flatten().to_pylist(), strict=True):
            piece = ids[at : end + 1]
            yield (None if doc_id == NO_ID else doc_id), np.concatenate([*parts, piece]) if parts else piece
            parts, at = [], end + 1
        if at < used:
            parts.append(ids[at:used].copy())


def write_token_files(docs: DataFrame, folder: str, vocabulary: str | None = None, end_id: int = 1, length: int = SEQUENCE) -> DataFrame:
    """Encode ``docs(doc_id, text)`` and write one file for each range of doc_ids.

    Returns (place int, file string, sequences long, offsets array<long>): files in ascending order of the doc_ids they hold. Texts are dealt by
    range before they are encoded, so that encoding happens once.
    """
    vocabulary = vocabulary or default_vocabulary()

    def write(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        tokens, writer = word_tokenizer(vocabulary), None
        end = np.array([end_id], tokens.kind)
        place = TaskContext.get().partitionId()
        name = f"{folder}/part-{place:06d}-{uuid.uuid4().hex}.arrows"
        for batch in batches:
            for at in range(0, len(batch), 64):
                part = batch.iloc[at : at + 64]
                ids = part["doc_id"].astype("object").tolist()
                for doc_id, encoded in zip(ids, tokens.encode(part["text"].tolist())):
                    if writer is None:
                        writer = SequenceWriter(name, length, tokens.library.get_vocab_size() > 1 << 16)
                    writer.add(NO_ID if pd.isna(doc_id) else int(doc_id), np.concatenate([encoded, end]))
        if writer is not None:
            writer.close()
            yield pd.DataFrame({"place": [place], "file": [name], "sequences": [writer.sequences], "offsets": [writer.offsets]})

    hashed = F.xxhash64("text")
    dealt = docs.select("doc_id", "text").repartitionByRange("doc_id", hashed).sortWithinPartitions("doc_id", hashed, "text")
    return dealt.select("doc_id", "text").mapInPandas(write, "place int, file string, sequences long, offsets array<long>")


def read_token_files(files: DataFrame) -> DataFrame:
    """(place, file, doc_id, local_start, n_tokens, ids_crc32) for each document, all taken from the files."""

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for place, name in zip(batch["place"], batch["file"]):
                rows, start = [], 0
                for doc_id, ids in documents_of(name):
                    rows.append((place, name, doc_id, start, len(ids), crc_of_ids(ids)))
                    start += len(ids)
                    if len(rows) == 20_000:
                        yield _frame(rows)
                        rows = []
                yield _frame(rows)

    return files.mapInPandas(read, "place int, file string, doc_id long, local_start long, n_tokens long, ids_crc32 long")


def _frame(rows: list[tuple]) -> pd.DataFrame:
    out = pd.DataFrame(rows, columns=["place", "file", "doc_id", "local_start", "n_tokens", "ids_crc32"])
    return out.astype({"doc_id": "Int64"})


def token_index(docs: DataFrame, folder: str | None = None, vocabulary: str | None = None, end_id: int = 1, length: int = SEQUENCE) -> DataFrame:
    """Write the files, read them back and place every document: doc_id, start, n_tokens, ids_crc32, file, local_start.

    ``start`` counts the ids of all documents before it. It is the sum of the files before (one row for each file, joined
    by place) and the document's place in its own file.
    """
    from pyspark.sql import Window

    spark = docs.sparkSession
    folder = folder or fresh_folder(spark, "token-files")
    files = cut(write_token_files(docs, folder, vocabulary, end_id, length))
    found = cut(read_token_files(files.repartition(max(1, files.count()), "place")))
    totals = found.groupBy("place").agg(F.sum("n_tokens").alias("held"))
    before = Window.orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("place", F.coalesce(F.sum("held").over(before), F.lit(0)).alias("base"))
    return found.join(bases, "place").select("doc_id", (F.col("base") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32", "file", "local_start")
