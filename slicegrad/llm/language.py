"""Language identification by compression.

For each language, a raw-content dictionary of zstandard is made of pieces of texts known to be of it. A text, in lower
case and with all but letters as blanks, is compressed with each dictionary and takes the language whose output is
smallest. It is compressed a block at a time, so that a long text is held against the dictionaries to its end and not
against its own beginning. Outputs of equal size (a word or two compress with none) go to the language that is learned
from more documents. If the margin between the two smallest is narrow, the decision is marked as rejected
(``rejected``), though ``lang_pred`` still names the smallest.

A text that is null or has no letter is ``und`` with score 0. Nothing but the text is looked at. Repeated rows are
judged alike; null ids and other columns need no care; an empty table gives an empty result; without any
learned language every text is ``und``. Learning uses a bounded sample: ``SAMPLE_TEXTS`` distinct texts a language by
a hash of them, a piece of ``PIECE_CHARS`` from a place in the whole text that the hash gives, ``DICTIONARY_BYTES`` of
each language; predictions take whole texts, very long ones block by block.
"""

from __future__ import annotations

import hashlib
import math
import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from slicegrad.llm.common import process_cache, ship_by_value

ship_by_value(__name__)

SAMPLE_TEXTS = 400
PIECE_CHARS = 400
DICTIONARY_BYTES = 96 << 10
BLOCK_BYTES = 4 << 10
LEVEL = 6
NARROW = 0.02
FIELDS = {"lang_pred": "string", "score": "double", "rejected": "boolean"}


def learn_dictionaries(docs: DataFrame, text: str = "text", lang: str = "lang", sample: int = SAMPLE_TEXTS, size: int = DICTIONARY_BYTES) -> dict[str, bytes]:
    """Language to dictionary, from ``docs`` with both columns known; the one with most documents comes first.

    A threshold on the texts' hashes, by the number of distinct ones of each language, lets about three times the sample
    pass before anything moves, and all of a language that has fewer; copies of a text have one hash and are one row
    from the first aggregate on.
    """
    hashed = F.xxhash64(text)
    known = docs.filter(F.col(f"`{text}`").isNotNull() & F.col(f"`{lang}`").isNotNull()).select(F.col(f"`{lang}`").alias("lang"), F.col(f"`{text}`").alias("text"), hashed.alias("h"))
    sizes = known.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("h").alias("texts")).collect()  # a row a language
    if not sizes:
        return {}
    steps = 1 << 24
    share = F.lit(steps)
    for r in sizes:
        share = F.when(F.col("lang") == r["lang"], max(1, min(steps, 3 * sample * steps // max(r["texts"], 1)))).otherwise(share)
    start = F.pmod(F.shiftright("h", 24), F.greatest(F.length("text") - PIECE_CHARS, F.lit(0)) + 1).cast("int") + 1
    few = known.filter(F.pmod("h", F.lit(steps)) < share).groupBy("lang", "h").agg(F.min(F.substring("text", start, F.lit(PIECE_CHARS))).alias("text"))
    per_lang = Window.partitionBy("lang").orderBy("h", "text")
    picked = few.withColumn("n", F.row_number().over(per_lang)).filter(F.col("n") <= sample).orderBy("lang", "n").select("lang", "text").collect()
    out: dict[str, list[str]] = {r["lang"]: [] for r in sorted(sizes, key=lambda r: (-r["n"], r["lang"]))}
    for r in picked:
        out[r["lang"]].append(r["text"])
    return {k: dictionary(v, size) for k, v in out.items()}


_NOT_LETTERS = re.compile(r"[\W\d_]+")


def plain(text: str) -> bytes:
    """Lower-case letters, one blank between runs of them and at the ends."""
    return (" " + _NOT_LETTERS.sub(" ", text.lower()).strip() + " ").encode("utf-8", "surrogatepass")


def dictionary(texts: list[str], size: int = DICTIONARY_BYTES) -> bytes:
    """Raw content: the texts themselves, one after another."""
    return b"".join(map(plain, texts))[:size]


class Classifier:
    """``dictionaries`` in order of preference among equals."""

    def __init__(self, dictionaries: dict[str, bytes], level: int = LEVEL):
        import zstandard

        self.names = list(dictionaries)
        self.coders = []
        for name in self.names:
            raw = zstandard.ZstdCompressionDict(dictionaries[name], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            raw.precompute_compress(level=level)
            self.coders.append(zstandard.ZstdCompressor(level=level, dict_data=raw, write_checksum=False, write_content_size=False, write_dict_id=False))

    def sizes(self, text: str) -> list[int]:
        data = plain(text)
        blocks = [data[k : k + BLOCK_BYTES] for k in range(0, len(data), BLOCK_BYTES)]
        return [sum(len(c.compress(b)) for b in blocks) for c in self.coders]

    def judge(self, text: str | None) -> tuple[str, float, bool]:
        if not text or not self.names or not any(map(str.isalpha, text)):
            return "und", 0.0, True
        sizes = self.sizes(text)
        order = sorted(range(len(sizes)), key=lambda k: (sizes[k], k))
        if len(order) == 1:
            return self.names[0], 1.0, False
        margin = (sizes[order[1]] - sizes[order[0]]) / max(sizes[order[1]], 1)
        return self.names[order[0]], 1 - 0.5 * math.exp(-20 * margin), margin < NARROW


def _judged(dictionaries: dict[str, bytes]):
    key = hashlib.sha256(repr(list(dictionaries.items())).encode()).hexdigest()

    def run(batches):
        held = process_cache("language")
        if key not in held:
            held.clear()
            held[key] = Classifier(dictionaries)
        own = held[key]
        for batch in batches:
            rows = [own.judge(t.as_py()) for t in batch.column("_text")]
            yield pa.RecordBatch.from_arrays([batch.column("_row"), pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.bool_())], names=["_row", *FIELDS])

    return run


def predict_language(docs: DataFrame, dictionaries: dict[str, bytes], text: str = "text", carry: list[str] | None = None) -> DataFrame:
    """The columns ``carry`` (all, if None) and ``lang_pred``, ``score``, ``rejected``, which take the place of such columns."""
    carry = [c for c in (docs.columns if carry is None else carry) if c not in FIELDS]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in carry]).alias("_row"), F.col(f"`{text}`").cast("string").alias("_text"))
    schema = T.StructType([T.StructField("_row", rows.schema["_row"].dataType), *[T.StructField(k, T._parse_datatype_string(v)) for k, v in FIELDS.items()]])
    return rows.mapInArrow(_judged(dictionaries), schema).select(*[F.col("_row").getField(c).alias(c) for c in carry], *FIELDS)


def fold(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; a null id is hashed as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(parts))
