"""Token counts through a digest cache.

A text's content digest (of its normalised form) and the tokenizer's version digest (of its file and of how
texts are prepared for it) key a table of stored counts. Texts whose key is in the table are never
encoded; of the others each distinct one is encoded once, and the new counts are appended to the table
before the result joins all rows to it.

Normalised form: for tokenizers that drop white space, runs of space, tab, CR and LF become one space
and the ends are trimmed, which leaves their count as it is; for the others the text itself.

Scale: what is shuffled is digests, 16 bytes a row, and of the texts only those that occur more than once. A
bitmap of digest prefixes (its size follows the count of digests and is bounded) marks the digests that are stored or
repeated. A text outside it is a miss that occurs once: it is encoded where it is scanned. A text inside it is looked up
among the misses by its whole digest and, if it is one, grouped by digest so that it is encoded once. A full bitmap
moves more texts and changes no result.

Encoding splits a text at those same characters where the tokenizer drops white space (no token spans
them) and remembers the counts of pieces, in a memory bounded by characters; otherwise whole texts go to
the library. Very long texts are split into runs of about a million characters at white space first, so a worker holds
pieces of one run. Special strings inside texts are treated as the library's default does.

Nulls: a null text counts as an empty one (0 bytes, 0 tokens); a null key keeps its row. Repeated rows and equal texts
(ties) are encoded once and each row gets the count. Empty tables give empty results. Columns of the input other than key
and text are not read, so none can clash. The cache is append-only Parquet; keys stored twice by concurrent runs are
read as one.
"""

from __future__ import annotations

import hashlib
import os
import re
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import arrow_rows, broadcast_if_small, materialize, text_or_empty, work_dir

CACHE_SCHEMA = "content binary, tokenizer string, n_tokens bigint"
GAPS = "[ \\t\\n\\r]+"
GAP = re.compile(GAPS)
RUN = 1_000_000  # characters of a text split at once
BITMAP_BITS = 1 << 28  # most bits of the bitmap: 4 million words of 64


@dataclass(frozen=True)
class TokenizerSpec:
    """A tokenizer file; drops_white_space: no token holds white space and none spans it."""

    path: str
    drops_white_space: bool = False

    def version(self) -> str:
        with open(self.path, "rb") as f:
            digest = hashlib.sha256(f.read())
        digest.update(f"gaps={self.drops_white_space};1".encode())
        return digest.hexdigest()[:32]

    def load(self):
        """A function from a list of texts to the list of their token counts."""
        if self.path.endswith(".json"):
            os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core, and each thread would keep memory of its own
            from tokenizers import Tokenizer

            t = Tokenizer.from_file(self.path)
            t.no_truncation()
            t.no_padding()
            return lambda texts: [len(e) for e in t.encode_batch_fast(texts, add_special_tokens=False)]
        if self.path.endswith(".model"):
            from sentencepiece import SentencePieceProcessor

            p = SentencePieceProcessor(model_file=self.path)
            return lambda texts: [len(x) for x in p.encode(texts, num_threads=1)]
        raise ValueError(f"no library for {self.path}")


class PieceCounts(dict):
    """Token counts of pieces between white space, in two generations of bounded size; long pieces are not remembered.

    When the young one holds `most` pieces or `chars` characters it becomes the old one, and what is met again moves on.
    """

    def __init__(self, encode, chars: int = 4_000_000, most: int = 250_000, longest: int = 64):
        super().__init__()
        self.encode, self.chars, self.most, self.longest, self.held, self.old = encode, chars, most, longest, 0, {}

    def __missing__(self, piece: str) -> int:
        n = self[piece] = self.old[piece]
        self.held += len(piece)
        return n

    def count(self, text: str) -> int:
        return sum(self._run(run) for run in runs_of(text))

    def _run(self, text: str) -> int:
        pieces = text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")
        old = self.old
        fresh = [x for x in dict.fromkeys(pieces) if x not in self and x not in old]
        long: dict[str, int] = {}
        for i in range(0, len(fresh), 1024):
            for x, n in zip(part := fresh[i : i + 1024], self.encode(part), strict=True):
                if len(x) > self.longest:
                    long[x] = n
                else:
                    self[x] = n
                    self.held += len(x)
        total = sum(long[x] if x in long else self[x] for x in pieces) if long else sum(map(self.__getitem__, pieces))
        if self.held > self.chars or len(self) > self.most:
            self.old = dict(self)
            self.clear()
            self.held = 0
        return total


def runs_of(text: str, size: int = RUN) -> Iterator[str]:
    """The text cut at white space into runs of `size` characters or, where no white space comes, more."""
    at = 0
    while len(text) - at > size:
        gap = GAP.search(text, at + size)
        if gap is None:
            break
        yield text[at : gap.start()]
        at = gap.end()
    yield text[at:] if at else text


def _encoded(batches: Iterator[pa.RecordBatch], spec: TokenizerSpec) -> Iterator[pa.RecordBatch]:
    encode = spec.load()
    pieces = PieceCounts(encode) if spec.drops_white_space else None
    for batch in batches:
        counts: list[int] = []
        for body in batch.column("body"):  # one text at a time is a Python string
            text = body.as_py()
            counts.append(pieces.count(text) if pieces is not None else encode([text])[0])
        yield pa.RecordBatch.from_arrays([batch.column("content"), pa.array(counts, pa.int64())], names=["content", "n_tokens"])


def content_of(text: Column, spec: TokenizerSpec) -> Column:
    """The normalised form."""
    return F.trim(F.regexp_replace(text, GAPS, " ")) if spec.drops_white_space else text


def open_cache(spark, path: str) -> DataFrame:
    """The cache at path, made empty where there is none."""
    spark.createDataFrame([], CACHE_SCHEMA).write.mode("ignore").parquet(path)
    return spark.read.schema(CACHE_SCHEMA).parquet(path)


def _prefix(bits: int) -> Column:
    """The first bits of a digest as a number below `bits`, a power of two."""
    return F.conv(F.hex(F.substring("content", 1, 4)), 16, 10).cast("long").bitwiseAND(F.lit(bits - 1))


def _bitmap(digests: DataFrame, bits: int) -> DataFrame:
    """(word, marks): the prefixes of the digests, 64 to a word; at most bits / 64 rows."""
    at = digests.select(_prefix(bits).alias("at"))
    return at.groupBy(F.shiftright("at", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(at & 63 as int))")).alias("marks"))


def fill_cache(texts: DataFrame, digests: DataFrame, spec: TokenizerSpec, cache: str, *, broadcast_rows: int = 500_000) -> int:
    """Encode the texts that the cache at path `cache` lacks, each distinct one once; how many those were.

    texts: content, body; digests: the content of each row of texts, materialized.
    """
    spark, version = texts.sparkSession, spec.version()
    known = open_cache(spark, cache).filter(F.col("tokenizer") == version).select("content").distinct()
    counts = digests.groupBy("content").agg(F.count("*").alias("n"))
    stated = materialize(counts.join(known.withColumn("stored", F.lit(True)), "content", "left").withColumn("once", F.col("stored").isNull() & (F.col("n") == 1)), "token-digests")
    misses, marked = stated.agg(F.count_if(F.col("stored").isNull()), F.count_if(~F.col("once"))).first()
    if not misses:
        return 0
    lacking, _ = broadcast_if_small(stated.filter("stored IS NULL AND NOT once").select("content"), broadcast_rows)  # 16 bytes a row
    bits = min(BITMAP_BITS, 1 << max(10, (16 * marked).bit_length()))
    bitmap = materialize(_bitmap(stated.filter("NOT once"), bits), "token-bitmap")
    at = F.expr("cast(at & 63 as int)")
    met = texts.withColumn("at", _prefix(bits)).withColumn("word", F.shiftright("at", 6)).join(F.broadcast(bitmap), "word", "left")  # at most BITMAP_BITS / 64 rows
    met = met.withColumn("inside", F.coalesce(F.getbit("marks", at) == 1, F.lit(False)))
    with arrow_rows(spark, 64):
        singles = met.filter("NOT inside").select("content", "body").mapInArrow(lambda it: _encoded(it, spec), "content binary, n_tokens bigint")
        _append(singles, version, cache)
        again = met.filter("inside").select("content", "body")
        # equal digests that the bitmap caught by chance occur once and join their own digest below
        chance = stated.filter("once").select("content").withColumn("at", _prefix(bits)).withColumn("word", F.shiftright("at", 6)).join(F.broadcast(bitmap), "word").filter(F.getbit("marks", at) == 1).select("content")
        wanted, _ = broadcast_if_small(materialize(lacking.unionByName(chance), "token-lacking"), broadcast_rows)
        once = again.join(wanted, "content", "left_semi").groupBy("content").agg(F.first("body").alias("body"))
        _append(once.mapInArrow(lambda it: _encoded(it, spec), "content binary, n_tokens bigint"), version, cache)
    return misses


def _append(counted: DataFrame, version: str, cache: str) -> None:
    counted.select("content", F.lit(version).alias("tokenizer"), "n_tokens").write.mode("append").parquet(cache)


def count_tokens(docs: DataFrame, spec: TokenizerSpec, cache: str, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_bytes, n_tokens) of every row; the cache at path `cache` gains what it lacked."""
    spark = docs.sparkSession
    body = text_or_empty(text)
    texts = docs.select(F.col(key), F.octet_length(body).cast("long").alias("n_bytes"), content_of(body, spec).alias("body")).withColumn("content", F.unhex(F.md5("body")))
    keyed = materialize(texts.select(key, "n_bytes", "content"), "token-rows")
    fill_cache(texts.select("content", "body"), keyed.select("content"), spec, cache)
    stored = spark.read.schema(CACHE_SCHEMA).parquet(cache).filter(F.col("tokenizer") == spec.version()).groupBy("content").agg(F.max("n_tokens").alias("n_tokens"))
    # written first, so that the rows of one text can be split where they meet its count
    return keyed.join(materialize(stored, "token-stored"), "content").select(key, "n_bytes", "n_tokens")


def op8_query(spark, sf_dir: str) -> DataFrame:
    """Token counts of every document by the word-end BPE, with a cache of this run's own."""
    import public_tokenizers

    spec = TokenizerSpec(public_tokenizers.path("word_bpe_49k.json"), drops_white_space=True)
    cache = f"{work_dir(spark).rstrip('/')}/token-counts-{uuid.uuid4().hex}"
    counts = count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), spec, cache)
    return counts.withColumn("over_limit", F.col("n_tokens") > 2048)
