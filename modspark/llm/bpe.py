"""BPE encoding and decoding with a minimal acyclic transducer of the corpus's frequent words.

One pass counts words with mergeable summaries (bounded counters per task; a word's count is too low by at most the words of
the task divided by its counters), the most frequent ones are compiled on the driver (their number is a parameter, so the
automaton's size is bounded) and every worker maps the compiled file. The second pass encodes and decodes. Which words the
lexicon holds has no influence on any id.

Defined results: a null text encodes as an empty one, to no ids; added tokens in a text are ids of their own, as in the library; a piece of
text with code points that no category table knows goes through the library; texts of any length are encoded whole; repeated rows are encoded each for itself; an
empty table gives an empty result and an empty lexicon; further columns of the input are kept apart.
"""

from __future__ import annotations

import hashlib
from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common, tokens

LEXICON_WORDS = 32_768
#: Counters that a task ends with, and those it holds while counting.
COUNTERS, HELD = 65_536, 200_000
#: Rows that leave an encoding worker at once.
CHUNK = 256


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _less(counts: Counter, most: int) -> Counter:
    """The summary with at most so many counters: the count of the first that is left out is taken from all."""
    if len(counts) <= most:
        return counts
    cut = sorted(counts.values(), reverse=True)[most]
    return Counter({w: n - cut for w, n in counts.items() if n > cut})


def frequent_words(docs: DataFrame, path: str, most: int, text_col: str = "text") -> list[str]:
    """The corpus's most frequent words, at most so many."""

    def count(batches):
        coder = tokens.worker_cache(("words", path), lambda: tokens.LexiconCoder(path))
        counts: Counter = Counter()
        for pdf in batches:
            for text in pdf["text"]:
                counts.update(coder.words(text))
                if len(counts) > HELD:
                    counts = _less(counts, HELD // 2)
        counts = _less(counts, COUNTERS)
        if counts:
            yield pd.DataFrame({"word": list(counts), "n": list(counts.values())})

    each = docs.select(common.whole_text(docs, text_col).alias("text")).mapInPandas(count, "word string, n long")
    total = common.keep(each.groupBy("word").agg(F.sum("n").alias("n")), "words")
    # the least count whose words, with all more frequent ones, are no more than asked for: one short row per distinct count
    room, least = most, None
    for r in total.groupBy("n").agg(F.count("*").alias("words")).orderBy(F.desc("n")).toLocalIterator():
        room -= r["words"]
        if room < 0:
            break
        least = r["n"]
    return sorted(r["word"] for r in total.where(F.col("n") >= least).select("word").collect()) if least is not None else []


def compile_lexicon(docs: DataFrame, path: str, most: int = LEXICON_WORDS, text_col: str = "text") -> bytes:
    coder = tokens.LexiconCoder(path)
    return tokens.pack_lexicon({w: coder.merged_ids(w) for w in frequent_words(docs, path, most, text_col)})


def coder_for(path: str, blob: bytes) -> tokens.LexiconCoder:
    """This worker's coder over the mapped lexicon."""
    return tokens.worker_cache(("coder", path), lambda: tokens.LexiconCoder(path, tokens.Lexicon.mapped(blob)), hashlib.sha256(blob).digest())


def encode(docs: DataFrame, path: str | None = None, lexicon_words: int = LEXICON_WORDS, text_col: str = "text", decoded: bool = True) -> DataFrame:
    """docs' columns with ``ids`` (array of int) and, if asked for, ``decoded``; columns of these names are replaced.

    Rows leave a worker some hundred at a time: ids take more room than their text.
    """
    path = path or default_path()
    blob = docs.sparkSession.sparkContext.broadcast(compile_lexicon(docs, path, lexicon_words, text_col))
    rest = docs.select(F.col(text_col).alias("_text"), *[c for c in docs.columns if c not in ("ids", "decoded")])
    new = [T.StructField("ids", T.ArrayType(T.IntegerType()))] + ([T.StructField("decoded", T.StringType())] if decoded else [])
    schema = T.StructType(rest.schema.fields[1:] + new)

    def code(batches):
        import pyarrow as pa

        coder = coder_for(path, blob.value)
        for batch in batches:
            for at in range(0, batch.num_rows, CHUNK):
                part = batch.slice(at, CHUNK)
                got = [coder.encode(t or "") for t in part.column(0).to_pylist()]
                ends = np.cumsum([0, *(len(x) // 4 for x, _ in got)]).astype(np.int32)
                ids = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(x for x, _ in got), "<i4")))
                more = [ids, pa.array([x for _, x in got], pa.string())] if decoded else [ids]
                yield pa.RecordBatch.from_arrays([*part.columns[1:], *more], names=schema.names)

    return rest.mapInArrow(code, schema)


DIGESTS = "n_tokens long, ids_sha256 string, decoded_sha256 string"


def encode_digests(docs: DataFrame, path: str | None = None, lexicon_words: int = LEXICON_WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """encode(), reduced to digests where it is made, so that no ids leave the worker."""
    path = path or default_path()
    blob = docs.sparkSession.sparkContext.broadcast(compile_lexicon(docs, path, lexicon_words, text_col))

    @F.pandas_udf(DIGESTS)
    def digest(texts: pd.Series) -> pd.DataFrame:
        coder, rows = coder_for(path, blob.value), []
        for text in texts:
            ids, decoded = coder.encode(text)
            rows.append((len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(decoded.encode("utf-8", "surrogatepass")).hexdigest()))
        return pd.DataFrame(rows, columns=["n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), digest(common.whole_text(docs, text_col)).alias("coded")).select("doc_id", "coded.*")


def op7_transducer_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_digests(common.documents(spark, sf_dir))
