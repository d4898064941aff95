"""Helpers that the training-data operators share: tables, lineage cuts, shared folders, tokenizer access."""

from __future__ import annotations

import os
import re
import tempfile
import unicodedata
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


#: One Spark task has one core; the tokenizers library must not start threads of its own.
os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share; a temporary one is made only by a session of one machine that names none (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    context = spark.sparkContext
    known = context.getCheckpointDir()
    if known:
        return known.rstrip("/")
    if not context.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    context.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="bitempo-"))
    return context.getCheckpointDir().rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` once into the shared folder and read it from there; survives lost executors."""
    spark = df.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(shared_folder(spark))
    return df.checkpoint(eager=True)


def fresh_folder(spark: SparkSession, purpose: str) -> str:
    return f"{shared_folder(spark)}/bitempo-{purpose}-{uuid.uuid4().hex}"


def stash(df: DataFrame, purpose: str) -> DataFrame:
    """Like :func:`cut`, but as Parquet: columns stay prunable and the file size is known to the planner."""
    spark = df.sparkSession
    folder = fresh_folder(spark, purpose)
    schema = df.schema
    df.write.parquet(folder)
    return spark.read.schema(schema).parquet(folder)


def fold_of(column: str | Column, parts: int) -> Column:
    """crc32 of the id's decimal text, modulo ``parts``; a null id falls in fold 0."""
    column = F.col(column) if isinstance(column, str) else column
    return F.coalesce(F.crc32(column.cast("string").cast("binary")) % parts, F.lit(0).cast("long"))


def crc_of_ids(ids) -> int:
    """Unsigned crc32 of ids laid out as little-endian unsigned 32-bit integers."""
    return zlib.crc32(np.ascontiguousarray(ids, dtype="<u4").tobytes())


#: Letters outside this set, or a dotted capital I, are lower-cased by the library alone.
_LATIN = re.compile("[^\x00-\u012f\u0131-\u024f]")
#: A full stop or comma after another mark belongs to one run of marks and must not be split off.
_RUN_OF_MARKS = re.compile("[^ \t\r\nA-Za-z0-9\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f][.,]")


class WordTokenizer:
    """Whole-text ids of a lower-casing, word-splitting tokenizer, put together from its ids of single words.

    The vocabulary splits at white space before anything else, so a text's ids are those of its space- or
    newline-separated words in turn. Words are encoded by the library once and remembered as packed ids in two generations of
    at most ``remember`` words each, which bounds the memory of a worker. Texts in Latin letters are lower-cased and
    have their full stops and commas set apart first, which the library would do as well, so that fewer words differ;
    other texts, and those that may hold special tokens, keep their words as they are.
    """

    def __init__(self, path: str, remember: int = 150_000):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.kind = np.dtype("<u2" if self.library.get_vocab_size() <= 1 << 16 else "<u4")
        self.remember = remember
        self.young: dict[str, bytes] = {"": b""}
        self.old: dict[str, bytes] = {}
        # the printable stand-in of each byte in byte-level vocabularies
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = iter(range(256, 512))
        self.stand_in = [chr(b) if b in plain else chr(next(rest)) for b in range(256)]

    def _learn(self, words: set[str]) -> None:
        slow, pack, one, stand_in = [], self.kind, self.model.tokenize, self.stand_in
        for word in words:
            known = self.old.get(word)
            if known is not None:
                self.young[word] = known
            elif len(word) < 64 and word.isascii() and word.isalpha() and word.islower():
                self.young[word] = np.array([t.id for t in one(word)], pack).tobytes()
            elif len(word) < 64 and word.isalpha() and word.islower() and not _LATIN.search(word) and unicodedata.is_normalized("NFC", word):
                self.young[word] = np.array([t.id for t in one("".join([stand_in[b] for b in word.encode()]))], pack).tobytes()
            else:
                slow.append(word)
        for at in range(0, len(slow), 10_000):
            part = slow[at : at + 10_000]
            for word, encoded in zip(part, self.library.encode_batch_fast(part, add_special_tokens=False)):
                self.young[word] = np.array(encoded.ids, pack).tobytes()

    @staticmethod
    def words(text: str | None) -> list[str]:
        if not text:
            return []
        if "<|" not in text and not _LATIN.search(text):
            text = text.lower()
            if not _RUN_OF_MARKS.search(text):
                text = text.replace(".", " .").replace(",", " ,")
        return text.replace("\n", " ").split(" ")

    def encode(self, texts: list[str | None]) -> Iterator[np.ndarray]:
        """One array of ids for each text; null texts have none."""
        for text in texts:
            words = self.words(text)
            if len(self.young) > self.remember:
                self.old, self.young = self.young, {"": b""}
            fresh = set(words).difference(self.young)
            if fresh:
                self._learn(fresh)
            yield np.frombuffer(b"".join(map(self.young.__getitem__, words)), self.kind)


_TOKENIZERS: dict[str, WordTokenizer] = {}


def word_tokenizer(path: str) -> WordTokenizer:
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = WordTokenizer(path)
    return _TOKENIZERS[path]


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")
