"""Token identifiers of whole documents in sorted-string-table shards.

Documents are dealt out by identifier range and sorted, each task encodes its
documents and writes them to shard files keyed by identifier, and a manifest
with one row per shard gives file order and token counts.  Reading streams the
files block by block; a document's position in the whole token stream is its
place in the shard plus the tokens of all shards before.

Encoding is by the tokenizers library.  In byte-level BPE a lone space or line
break between two visible characters always starts a new pre-token, so a text
whose white space is all of that kind is the concatenation of its words' ids;
those are encoded once each and kept in a bounded dictionary.  Any other text goes to the library whole.

Defined results: a null text counts as empty and has the end id alone; equal
identifiers are ordered by their texts' hash, then text; null identifiers come first; an empty table
gives no shards and no rows; other columns are ignored.
"""

from __future__ import annotations

import os
import struct
import zlib
from array import array
from collections.abc import Callable
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entlink.llm import sstable
from entlink.llm.sharedfiles import publishing, reading
from entlink.storage import materialize, scratch_path

END_ID = 0
SHARD_BYTES = 64 << 20
CACHE_WORDS = 600_000
TEXTS_AT_ONCE = 1024
MET = (1 << 23) - 1


MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"  # no apostrophe: it may begin a contraction


class BytePairEncoder:
    """Ids of whole texts as little-endian unsigned 32-bit bytes.

    Known words are kept in two generations: the younger fills up, then takes the older one's place, and a word
    met again in the older moves to the younger.  So words that recur stay, and memory has a bound.
    """

    def __init__(self, source: str | bytes):
        """``source`` is the path of a vocabulary file or what it holds."""
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_buffer(source) if isinstance(source, bytes) else Tokenizer.from_file(source)
        newline = self.tokenizer.encode("\n", add_special_tokens=False).ids
        self.newline = array("I", newline).tobytes()
        # The short cut needs byte-level pre-tokens and one id for a line break.
        self.narrow = self.tokenizer.get_vocab_size() <= 1 << 16
        self.by_word = "ByteLevel(add_prefix_space=False" in repr(self.tokenizer.pre_tokenizer) and len(newline) == 1
        self.merge = self.tokenizer.model.tokenize
        # The alphabet in which byte-level models spell bytes: visible Latin-1 characters are themselves.
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        others = [b for b in range(256) if b not in plain]
        self.spelled = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(others)}
        self.blank = self.spelled[32]
        self.young: dict[str, bytes] = {}  # ids of words after a blank or, with it in front, a line break
        self.old: dict[str, bytes] = {}
        self.marks: dict[str, bytes] = {}

    def _whole(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids).tobytes()

    def _word(self, word: str, lead: str) -> bytes:
        """Ids of a word: letters with marks behind them are two pre-tokens for the library's merge model."""
        base = word.rstrip(MARKS)
        if not base.isalpha():
            return self._whole(lead + word)
        spelled = base if base.isascii() else "".join(map(self.spelled.__getitem__, base.encode()))
        if lead:
            spelled = self.blank + spelled
        raw = array("I", [t.id for t in self.merge(spelled)]).tobytes()
        if len(base) == len(word):
            return raw
        tail = word[len(base) :]
        if tail not in self.marks:
            if len(self.marks) > 10_000:
                self.marks.clear()
            self.marks[tail] = array("I", [t.id for t in self.merge(tail)]).tobytes()
        return raw + self.marks[tail]

    def _met(self, word: str) -> bytes:
        found = self.old.get(word)
        if found is None:
            found = self.newline + self._word(word[1:], "") if word[0] == "\n" else self._word(word, " ")
        self.young[word] = found
        return found

    def _text(self, text: str) -> bytes:
        # Equal only if all white space is single blanks and line breaks, each between visible characters.
        if not self.by_word or " ".join(text.split()) != text.replace("\n", " "):
            return self._whole(text)
        words = text.replace("\n", " \n").split(" ")
        ids = list(map(self.young.get, words))
        ids[0] = self._word(words[0], "")
        if None in ids:
            met = self._met
            ids = [met(w) if v is None else v for w, v in zip(words, ids)]
        return b"".join(ids)

    def encode(self, texts: list[str]) -> list[bytes]:
        out = []
        for t in texts:
            out.append(self._text(t))
            if len(self.young) > CACHE_WORDS // 2:
                self.old, self.young = self.young, {}
        return out


@lru_cache(maxsize=1)
def bpe_encoder(source: str | bytes) -> BytePairEncoder:
    """The encoder of a vocabulary, once for each Python worker."""
    return BytePairEncoder(source)


def key_of(doc_id: int | None) -> bytes:
    """Nine bytes that order as identifiers do, null first."""
    return b"\x00" if doc_id is None else b"\x01" + struct.pack(">Q", doc_id + (1 << 63))


def id_of(key: bytes) -> int | None:
    return None if key == b"\x00" else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def write_tokens(
    docs: DataFrame,
    encoder: Callable[[], BytePairEncoder],
    path: str | None = None,
    id_col: str = "doc_id",
    text_col: str = "text",
    shard_bytes: int = SHARD_BYTES,
) -> DataFrame:
    """Write all documents; returns the manifest ``(part, seq, uri, docs, tokens)``."""
    spark = docs.sparkSession
    path = path or scratch_path(spark, "tokens")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def run(batches):
        part, enc = TaskContext.get().partitionId(), None
        stream = table = None
        seq = n_docs = n_tokens = size = 0

        def done():
            table.close()
            stream.__exit__(None, None, None)
            return pa.RecordBatch.from_arrays(
                [pa.array([part]), pa.array([seq]), pa.array([f"{path}/{part:06d}-{seq:06d}.sst"]), pa.array([n_docs]), pa.array([n_tokens])],
                ["part", "seq", "uri", "docs", "tokens"],
            )

        for b in batches:
            enc = enc or encoder()
            ids = b.column(0).to_pylist()
            for at in range(0, b.num_rows, TEXTS_AT_ONCE):
                texts = [t or "" for t in b.column(1).slice(at, TEXTS_AT_ONCE).to_pylist()]
                for doc_id, raw in zip(ids[at : at + TEXTS_AT_ONCE], enc.encode(texts)):
                    if table is None:
                        stream = publishing(f"{path}/{part:06d}-{seq:06d}.sst")
                        table = sstable.Writer(stream.__enter__(), {"dtype": "<u2" if enc.narrow else "<u4"})
                    value = raw + struct.pack("<I", END_ID)
                    n_docs, n_tokens, size = n_docs + 1, n_tokens + len(value) // 4, size + len(value)
                    table.add(key_of(doc_id), np.frombuffer(value, "<u4").astype("<u2").tobytes() if enc.narrow else value)
                    if size >= shard_bytes:
                        yield done()
                        table, seq, n_docs, n_tokens, size = None, seq + 1, 0, 0, 0
        if table is not None:
            yield done()

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), F.xxhash64(text_col).alias("hash"))
    # By identifier and hash, so that rows of one identifier, or of none, spread over ranges too.
    ranged = slim.repartitionByRange(parts, "id", "hash").sortWithinPartitions("id", "hash", "text").select("id", "text")
    return materialize(ranged.mapInArrow(run, "part long, seq long, uri string, docs long, tokens long"), "token-manifest")


def stored_ids(table: sstable.Reader, value: bytes) -> bytes:
    """Ids of one value as little-endian unsigned 32-bit bytes."""
    return np.frombuffer(value, table.meta["dtype"]).astype("<u4").tobytes()


def read_tokens(manifest: DataFrame, with_ids: bool = True) -> DataFrame:
    """``(id, start, n_tokens, ids_crc32, ids)`` of every document, from the files."""
    until = lambda w: F.coalesce(F.sum("tokens").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    # Sums within each range, and one row for each range in the only window over all.
    ranges = manifest.groupBy("part").agg(F.sum("tokens").alias("tokens")).select("part", until(Window.orderBy("part")).alias("before"))
    shards = manifest.withColumn("within", until(Window.partitionBy("part").orderBy("seq"))).join(ranges, "part")
    shards = shards.select("uri", (F.col("before") + F.col("within")).alias("start"))
    parts = int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches):
        for b in batches:
            for uri, start in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                with reading(uri) as f:
                    rows, held, table = [], 0, sstable.Reader(f)
                    for key, value in table:
                        ids = stored_ids(table, value)
                        n = len(ids) // 4
                        rows.append((id_of(key), start, n, zlib.crc32(ids), ids if with_ids else None))
                        start, held = start + n, held + len(ids)
                        if held > 8 << 20:
                            yield pack(rows)
                            rows, held = [], 0
                    if rows:
                        yield pack(rows)

    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
    names = ["id", "start", "n_tokens", "ids_crc32", "ids"]

    def pack(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    return shards.repartition(parts).mapInArrow(run, "id long, start long, n_tokens long, ids_crc32 long, ids binary")


def lookup(uri: str, doc_id: int | None) -> list[list[int]]:
    """Ids of a document in one shard file, by Bloom filter and binary search."""
    with reading(uri) as f:
        table = sstable.Reader(f)
        return [np.frombuffer(v, table.meta["dtype"]).tolist() for v in table.get(key_of(doc_id))]
