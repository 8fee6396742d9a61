"""Token counts behind a digest cache.

A stored count is found by the digest of the normalised content and the digest of the tokenizer file. Only content
without a stored count is encoded, once for each distinct digest, and its count is appended to the cache. Repeated texts
cost one encoding however often they occur; a second run over the same texts encodes nothing.

Content is normalised by the model's own normaliser. Where that changes nothing but blanks to marks (seen on probes of
every kind of character it could change), content is its own normal form and its digest is taken by SQL functions.

Texts don't move unless they must: a bit set of the digests that occur twice or are stored (eight bits a digest, up to
``MOST_SIEVE_BITS``) tells the scan which texts are surely new and single; these are encoded where they are read. Only
the others are brought together by digest, joined with the cache and encoded once.

Null text counts as empty (0 tokens). An empty table gives no rows and leaves the cache as it is. Two runs may append
the same digest at the same time; the reader takes the least stored count per digest, and equal keys hold equal counts.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privq.llm.common import Batches, table, text_or_empty, tidy
from privq.sources.scratch import Scratch, fresh_path, materialize

CACHE_SCHEMA = T.StructType([T.StructField("content_sha", T.BinaryType()), T.StructField("tokenizer_sha", T.StringType()), T.StructField("n_tokens", T.LongType())])
CACHE_ENTRIES = 500_000
#: Longest bit set, as a power of two.
MOST_SIEVE_BITS = 26
_MARK = "▁"


def file_digest(path: str) -> str:
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


class PieceCounter:
    """Counts pieces of whole texts as the library gives them, remembering the counts of words.

    A blank becomes a mark that only ever begins a piece of such a vocabulary (checked here, over all pieces), so no
    merge crosses the place before a lone mark and the words of a text are counted one by one. Texts with several
    blanks in a row, at an end, or with the mark itself at the end of a word go to the library whole.
    """

    def __init__(self, path: str, entries: int = CACHE_ENTRIES):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = (self.model.id_to_piece(i) for i in range(self.model.get_piece_size()))
        plain = "".join(self.model.decode([i]) for i in self.model.encode("A ﬁ　b①"))
        self.by_word = not any(_MARK in p.lstrip(_MARK) for p in pieces) and "ﬁ" in plain and "　" in plain
        self.entries, self.counts = entries, {"": None}

    def count(self, text: str) -> int:
        if not text:
            return 0
        if not self.by_word:
            return len(self.model.encode(text))
        words = text.split(" ")
        get = self.counts.get
        found = [get(w) for w in words]
        if None in found:
            missing = [w for w, c in zip(words, found, strict=True) if c is None]
            if any(not w or w[-1] == _MARK for w in missing):
                return len(self.model.encode(text))
            if len(self.counts) > self.entries:
                self.counts = {"": None}
            fresh = list(dict.fromkeys(missing))
            made = dict(zip(fresh, map(len, self.model.encode(fresh, num_threads=1)), strict=True))
            self.counts |= {w: c for w, c in made.items() if len(w) <= 64}
            return sum([made[w] if c is None else c for w, c in zip(words, found, strict=True)])
        return sum(found)


def normaliser(path: str) -> Callable[[str], str] | None:
    """The model's normaliser, or None where it leaves every text as it is but for its marks."""
    import sentencepiece

    plain = sentencepiece.SentencePieceNormalizer(model_file=path)

    def normalised(text: str) -> str:
        return plain.normalize(text)

    probes = ["A ﬁ　b①", " a  b ", "a\tb\nc\r\n", "e\u0301 é ﬃ Å Å", "\u200b\u00ad\ufeffx", "ｱABCＡ１", "한글 ᄒ", "x\u00a0y\u2003z"]
    undone = [normalised(p).replace(_MARK, " ") for p in probes]
    return None if all(u in (p, " " + p) for u, p in zip(undone, probes, strict=True)) else normalised


def _digest_batches(path: str) -> Batches:
    """Digest of the normalised content beside what is carried; the body is the last column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        change = normaliser(path) or str
        for batch in batches:
            shas = pa.array([hashlib.sha256(change(t).encode()).digest() for t in batch.column(batch.num_columns - 1).to_pylist()], pa.binary())
            yield pa.RecordBatch.from_arrays([*batch.columns, shas], [*batch.schema.names, "content_sha"])

    return run


def _places(shas: pa.Array, bits: int) -> np.ndarray:
    """Place of each digest in a bit set: its first bits."""
    heads = np.frombuffer(b"".join(x.as_buffer()[:8].to_pybytes() for x in shas), ">u8").astype(np.uint64)
    return (heads >> np.uint64(64 - bits)).astype(np.int64)


def _count_batches(path: str, sieve: bytes | None = None, bits: int = 0) -> Batches:
    """content_sha and tokens; given a bit set, of the digests only that aren't in it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = PieceCounter(path)
        taken = None if sieve is None else np.frombuffer(sieve, np.uint8)
        for batch in batches:
            if taken is not None:
                batch = batch.filter(pa.array(~_taken(taken, batch.column(0), bits)))
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                counts = pa.array([counter.count(t) for t in part.column(1).to_pylist()], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0), counts], ["content_sha", "n_tokens"])

    return run


def _taken(sieve: np.ndarray, shas: pa.Array, bits: int) -> np.ndarray:
    at = _places(shas, bits)
    return (sieve[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)


def _sieved_batches(sieve: bytes, bits: int) -> Batches:
    """Rows whose digest is in the bit set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        taken = np.frombuffer(sieve, np.uint8)
        for batch in batches:
            yield batch.filter(pa.array(_taken(taken, batch.column(0), bits)))

    return run


def bit_set(shas: DataFrame) -> tuple[bytes, int]:
    """Bit set of the first bits of digests, eight bits a digest up to 2**``MOST_SIEVE_BITS``."""
    bits = int(min(MOST_SIEVE_BITS, max(16, (8 * shas.count()).bit_length())))
    place = F.shiftright(F.conv(F.hex(F.substring("content_sha", 1, 4)), 16, 10).cast("long"), 32 - bits)
    words = shas.select(F.shiftright(place, 5).cast("int").alias("w"), F.call_function("shiftleft", F.lit(1).cast("long"), place.bitwiseAND(31).cast("int")).alias("m")).groupBy("w").agg(F.bit_or("m").alias("m")).toArrow()
    out = np.zeros(1 << (bits - 5), np.uint32)
    out[words.column("w").to_numpy()] = words.column("m").to_numpy().astype(np.uint32)
    return out.tobytes(), bits


def read_cache(spark: SparkSession, cache_path: str, tokenizer_sha: str) -> DataFrame:
    """Stored counts of one tokenizer version; a cache that doesn't exist yet is empty."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(cache_path)
    if target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(target):
        stored = spark.read.schema(CACHE_SCHEMA).parquet(cache_path)
    else:
        stored = spark.createDataFrame([], CACHE_SCHEMA)
    return stored.where(F.col("tokenizer_sha") == tokenizer_sha).groupBy("content_sha").agg(F.min("n_tokens").alias("n_tokens"))


def count_tokens(df: DataFrame, model_path: str, cache_path: str, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """One row per input row: id, bytes, tokens. Misses are appended to ``cache_path`` before the result is returned."""
    spark, version = df.sparkSession, file_digest(model_path)
    steps = Scratch(spark)
    body = df.select(F.col(id_column).alias("doc_id"), text_or_empty(text).alias("body"))
    if normaliser(model_path) is None:
        keyed = body.withColumn("content_sha", F.unhex(F.sha2(F.col("body"), 256)))
    else:
        kind = body.schema["doc_id"].dataType.simpleString()
        keyed = body.mapInArrow(tidy(_digest_batches(model_path)), f"doc_id {kind}, body string, content_sha binary")
    sizes = steps.store(keyed.select("doc_id", "content_sha", F.octet_length("body").cast("long").alias("n_bytes")), "count-sizes")
    stored = read_cache(spark, cache_path, version)
    twice = sizes.groupBy("content_sha").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("content_sha")
    sieve, bits = bit_set(steps.store(twice.union(stored.join(sizes, "content_sha", "left_semi").select("content_sha")).distinct(), "count-known"))
    bodies, shape = keyed.select("content_sha", "body"), "content_sha binary, n_tokens bigint"
    single = bodies.mapInArrow(tidy(_count_batches(model_path, sieve, bits)), shape)
    others = bodies.mapInArrow(tidy(_sieved_batches(sieve, bits)), "content_sha binary, body string")
    missing = others.join(stored.select("content_sha"), "content_sha", "left_anti").dropDuplicates(["content_sha"])
    counted = single.union(missing.mapInArrow(tidy(_count_batches(model_path)), shape))
    counted.select("content_sha", F.lit(version).alias("tokenizer_sha"), "n_tokens").write.mode("append").parquet(cache_path)
    counts = materialize(read_cache(spark, cache_path, version), "counts")  # stored, so that a hot digest's rows can be split
    return sizes.join(counts, "content_sha", "left").select("doc_id", "n_bytes", "n_tokens")


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole ``documents`` against a cache that starts empty, so that every distinct text is encoded in this run."""
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    counts = count_tokens(docs, public_tokenizers.path("piece_bpe_32k.model"), fresh_path(spark, "token-count-cache"))
    return counts.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > 4096).alias("over_limit"))
