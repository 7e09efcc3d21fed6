"""Token ids in Parquet list columns: ordered, dictionary or delta encoded, readable in part.

Files hold one row per document: ``doc_id``, ``part``, ``start_in_part``,
``n_tokens`` and the list ``ids``.  Parts are ranges of doc_id, rows are in
ascending order within a part, row groups and pages are of a set size, and the
writer keeps page indexes, so a reader that asks for some documents or only
for the counts reads a small share of the bytes.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Callable, Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import MEMORY, WORD_BYTES, new_path, text_slices
from .words import WordTable, find_words

END_ID = 1
#: Punctuation that the vocabulary's split keeps apart from letters; quotes and the marks of special tokens are not among it.
_EDGE = ".,!?;:()[]{}*+-/=#%&@_~^$"
TABLE = "doc_id long, part int, start_in_part long, n_tokens long, ids array<int>"
_loaded: dict[str, "WordEncoder"] = {}


def vocabulary(name: str) -> str:
    """Path of a public vocabulary file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def split_words(text: str) -> list[str]:
    """Pieces between ASCII white space; empty ones stand for runs of it."""
    for c in "\t\n\v\f\r":
        if c in text:
            text = text.replace(c, " ")
    return text.split(" ")


class WordEncoder:
    """Ids of texts, encoded word by word with a memory.

    The vocabulary drops white space and no rule of it looks across white
    space, so the ids of a text are those of its words in order.  Where ids
    mark word ends, unknown words of letters only are encoded many to a call
    and cut apart at the marks, of which punctuation around them has its own.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocab = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.marked = bool(self.ends.any())
        self.table = WordTable(self._words, MEMORY)

    @staticmethod
    def at(path: str) -> "WordEncoder":
        if path not in _loaded:
            _loaded[path] = WordEncoder(path)
        return _loaded[path]

    def _each(self, words: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]

    def _words(self, words: list[str]) -> list[bytes]:
        """Ids of letter runs and the punctuation around them together, of anything else one by one."""
        out, runs, pieces, rest = {}, [], [], []
        for w in words:
            core = w.strip(_EDGE) if self.marked else ""
            if core.isalpha():
                runs.append(w)
                pieces.append(1 + (core[0] != w[0]) + (core[-1] != w[-1]))
            else:
                rest.append(w)
        for lo in range(0, len(runs), 1024):
            some = runs[lo : lo + 1024]
            ids = np.array(self.tokenizer.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids, "<u4")
            stop, last = 4 * (np.flatnonzero(self.ends[ids]) + 1), np.cumsum(pieces[lo : lo + 1024])
            if len(stop) == last[-1] and stop[-1] == 4 * len(ids):
                body, stop = ids.tobytes(), stop[last - 1].tolist()
                out.update(zip(some, [body[s:e] for s, e in zip([0, *stop], stop)]))
            else:  # a letter that lower-cases to more than letters
                out.update(zip(some, self._each(some)))
        out.update(zip(rest, self._each(rest)))
        return [out[w] for w in words]

    def __call__(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of a column of texts end to end, and the number of ids of each text; nulls are empty."""
        words = find_words(column)
        ids, n = self.table(words)
        ends = np.concatenate([[0], np.cumsum(n)])
        return ids, ends[words.first + words.count] - ends[words.first]


def write_token_table(
    docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text", encoder: Callable[[], Callable] | None = None,
    vocab: str | None = None, end_id: int | None = END_ID, parts: int | None = None, row_group_bytes: int = 8 << 20, page_bytes: int = 256 << 10, delta: bool = False,
) -> DataFrame:
    """Encode every whole text, write the table in ascending id order and return it as read back.

    Null texts are empty; null ids come first; rows that share an id follow
    each other in the order of their text's hash.  ``delta`` asks for delta
    packed ids instead of dictionary pages.
    """
    spark = docs.sparkSession
    vocab = vocab or vocabulary("word_bpe_49k.json")
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    rows = rows.repartitionByRange(parts, "doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, start = TaskContext.get().partitionId(), 0
        encode_texts = encoder() if encoder else WordEncoder.at(vocab)
        for batch in batches:
            for b in text_slices(batch, "text", WORD_BYTES):
                ids, n = encode_texts(b.column(1))
                if end_id is not None:
                    ids, n = np.insert(ids, np.cumsum(n), end_id), n + 1
                ends = np.cumsum(n)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(ids.view(np.int32)))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.full(len(n), part, np.int32)), pa.array(start + ends - n), pa.array(n), lists], ["doc_id", "part", "start_in_part", "n_tokens", "ids"])
                start += int(ends[-1])

    options = {"parquet.block.size": row_group_bytes, "parquet.page.size": page_bytes, "parquet.enable.dictionary": "false" if delta else "true", "parquet.writer.version": "v2" if delta else "v1", "compression": "zstd"}
    rows.mapInArrow(encode, TABLE).write.options(**{k: str(v) for k, v in options.items()}).parquet(path)
    return read_token_table(spark, path)


def read_token_table(spark: SparkSession, path: str, doc_ids: list[int] | None = None, ids: bool = True) -> DataFrame:
    """The table, or of it only some documents (pruned by row-group and page statistics) or only the counts."""
    df = spark.read.schema(TABLE).parquet(path)
    df = df if doc_ids is None else df.where(F.col("doc_id").isin(doc_ids))
    return df if ids else df.drop("ids")


def part_starts(table: DataFrame) -> DataFrame:
    """Ids before each part: one row per written part, so its size follows the number of tasks, not of documents."""
    sums = sorted((r.part, r.n) for r in table.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect())
    before = accumulate((n for _, n in sums), initial=0)
    return table.sparkSession.createDataFrame([(p, b) for (p, _), b in zip(sums, before)], "part int, before long")


def checksums(table: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every row of a token table."""

    def crc(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(4)
            offs = lists.offsets.to_numpy()
            body = lists.values.to_numpy().astype("<i4").tobytes()
            sums = [zlib.crc32(body[4 * s : 4 * e]) for s, e in zip(offs[:-1].tolist(), offs[1:].tolist())]
            yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(sums, pa.int64())], ["doc_id", "part", "start_in_part", "n_tokens", "ids_crc32"])

    rows = table.mapInArrow(crc, "doc_id long, part int, start_in_part long, n_tokens long, ids_crc32 long")
    return rows.join(F.broadcast(part_starts(table)), "part").select("doc_id", (F.col("before") + F.col("start_in_part")).alias("start"), "n_tokens", "ids_crc32")


def digest(docs: DataFrame) -> DataFrame:
    """The query's columns, from files written to the shared folder and read back."""
    return checksums(write_token_table(docs, new_path(docs.sparkSession, "tokens")))
