"""Token counts behind a digest cache.

The cache is a Parquet table (content, n_tokens) in partitions by tokenizer: the SHA-256 of the normalised content, the
count, the SHA-256 of the tokenizer file. A run joins the digests of its rows to the cache, encodes each missing content once, and
appends what it encoded; counts are then read from the cache. Normalising means that null counts as empty; nothing else may
change, as counts must be the tokenizer's own for the exact text. Appending twice (a retried run) does no harm, as readers
keep one row per digest.

Edge cases: null and empty texts count 0 tokens; equal texts share one cache row; texts of any length are encoded whole;
an empty table appends nothing; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import bounded_batches, join_hot, materialise, read_table, scratch, text_of

CACHE = "content string, n_tokens long, tokenizer string"


def place_of(tokenizer: str) -> str:
    """A path stays; a bare name is looked up among the public tokenizers."""
    if "/" in tokenizer:
        return tokenizer
    import public_tokenizers

    return public_tokenizers.path(tokenizer)


def counter(path: str):
    """A function from texts to token counts, for .model (sentencepiece), .json (tokenizers) and .tiktoken files."""
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda texts: [len(ids) for ids in model.encode(texts, num_threads=1)]
    if path.endswith(".json"):
        from tokenizers import Tokenizer

        encoder = Tokenizer.from_file(path)
        encoder.no_truncation()
        encoder.no_padding()
        return lambda texts: [len(e.ids) for e in encoder.encode_batch(texts, add_special_tokens=False)]
    import public_tokenizers
    import tiktoken

    with open(path) as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(str.split, lines)}
    encoding = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return lambda texts: [len(encoding.encode_ordinary(t)) for t in texts]


def cached(spark, path: str) -> DataFrame:
    try:
        return spark.read.schema(CACHE).parquet(path)
    except AnalysisException as error:
        if "PATH_NOT_FOUND" not in str(error):
            raise
        return spark.createDataFrame([], CACHE)


def texts_of(texts: DataFrame, missing: DataFrame, total: int, share: float = 0.001) -> DataFrame:
    """Rows (content, text), one for each row of missing(content, n), where n rows of texts have the content.

    Contents with more than share of all rows (at most 1/share) are picked by a broadcast and reduced in each task before
    they meet; the rest go through one shuffle by content.
    """
    limit = max(1, int(total * share))
    hot = F.broadcast(missing.filter(F.col("n") > limit).select("content"))
    cold = missing.filter(F.col("n") <= limit).select("content")
    often = texts.join(hot, "content", "left_semi").groupBy("content").agg(F.first("text").alias("text"))
    seldom = texts.join(hot, "content", "left_anti").join(cold, "content", "left_semi").groupBy("content").agg(F.first("text").alias("text"))
    return often.unionByName(seldom)


def count_tokens(docs: DataFrame, tokenizer: str, cache: str) -> DataFrame:
    """Rows (doc_id, n_bytes, n_tokens), one for each row of docs; appends what was missing to the cache at path cache."""
    spark = docs.sparkSession
    bounded_batches(spark, 256)
    with open(place_of(tokenizer), "rb") as file:
        version = hashlib.sha256(file.read()).hexdigest()
    digest = F.sha2(text_of(), 256)
    rows = materialise(docs.select("doc_id", F.octet_length(text_of()).cast("long").alias("n_bytes"), digest.alias("content")), "token-digests")
    per = materialise(rows.groupBy("content").agg(F.count("*").alias("n")), "token-contents")
    known = cached(spark, cache).filter(F.col("tokenizer") == version).select("content")
    missing = materialise(per.join(known, "content", "left_anti"), "token-missing")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(place_of(tokenizer))
        for b in batches:
            n = count(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array([version] * len(n), pa.string())], names=["content", "n_tokens", "tokenizer"])

    todo = texts_of(docs.select(digest.alias("content"), text_of().alias("text")), missing, rows.count())
    todo.mapInArrow(run, CACHE).write.mode("append").partitionBy("tokenizer").parquet(cache)
    counts = cached(spark, cache).filter(F.col("tokenizer") == version).groupBy("content").agg(F.min("n_tokens").alias("n_tokens"))
    done = join_hot(rows, counts.join(per, "content"), ["content"], "n", rows.count())
    return done.select("doc_id", "n_bytes", "n_tokens")


def op6_digest_cache(spark, sf_dir: str) -> DataFrame:
    """Counts of the 32k byte-fallback BPE, through a cache that starts empty."""
    done = count_tokens(read_table(spark, sf_dir, "documents"), "piece_bpe_32k.model", scratch(spark, "token-cache"))
    return done.withColumn("over_limit", F.col("n_tokens") > 4096)


def token_cache_again(spark, sf_dir: str) -> DataFrame:
    """Two runs over one cache: the counts of the second, in which every content is stored, and how many it encoded anew (none)."""
    docs, cache = read_table(spark, sf_dir, "documents"), scratch(spark, "token-cache")
    count_tokens(docs, "piece_bpe_32k.model", cache)
    before = cached(spark, cache).count()
    done = count_tokens(docs, "piece_bpe_32k.model", cache)
    return done.withColumn("n_encoded", F.lit(cached(spark, cache).count() - before).cast("long"))
