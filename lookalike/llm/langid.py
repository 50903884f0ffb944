"""Language ID by compression: the language whose dictionary makes a text smallest.

Each language gets a zstandard raw-content dictionary of its own training texts. Letters are
lower-cased and all else becomes one space. A text is cut into blocks, every block of the whole
text is encoded against every dictionary behind a few short carriers that the dictionary knows,
and the sizes, less the carriers' own, are summed. The carriers pay the encoder's fixed costs and
average out whole bytes, so one rule serves texts of three words and of a million.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ship

#: Bounds of the fitted model: training texts per language, bytes of each dictionary, bytes of all of them.
SAMPLE_PER_LANG = 400
DICT_BYTES, MODEL_BYTES = 112 * 1024, 32 * 1024 * 1024
BLOCK_BYTES = 2048
LEVEL = 5
#: A text is rejected when the runner-up is within this share of the best size, or ties with it.
MIN_MARGIN = 0.002
CARRIERS, CARRIER_BYTES = 4, 32

_NOT_LETTERS = re.compile(r"[\W\d_]+")

OUT = T.StructType(
    [
        T.StructField("doc_id", T.LongType()),
        T.StructField("lang_pred", T.StringType()),
        T.StructField("score", T.DoubleType()),
        T.StructField("margin", T.DoubleType()),
        T.StructField("rejected", T.BooleanType()),
    ]
)


def normalise(text: str) -> str:
    """Lower-cased runs of letters with one space between them."""
    return _NOT_LETTERS.sub(" ", text.lower()).strip()


def held_out_expr(id_col: str = "doc_id"):
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2


def fit(
    train: DataFrame,
    text_col: str = "text",
    lang_col: str = "lang",
    id_col: str = "doc_id",
    sample_per_lang: int = SAMPLE_PER_LANG,
    dict_bytes: int = DICT_BYTES,
) -> dict[str, bytes]:
    """Dictionaries by language from a bounded sample: a window of each of the ``sample_per_lang`` texts of each
    language with the smallest hash of their id, from a place in the whole text that the hash
    names. Rows with null text or language are not used.

    Aggregating bounded slices keeps the largest group from meeting in one task: ids are ranked
    within salted parts first. What reaches the driver is at most ``languages * sample_per_lang``
    windows (a few more by rounding), about ``dict_bytes`` a language; more languages than
    ``MODEL_BYTES`` hold get smaller dictionaries.
    """
    from pyspark.sql import Window

    ranked = (
        train.filter(F.col(text_col).isNotNull() & F.col(lang_col).isNotNull() & (F.trim(F.col(text_col)) != ""))
        .select(F.col(lang_col).cast("string").alias("lang"), F.col(id_col).alias("id"), F.xxhash64(F.col(id_col)).alias("h"))
        .withColumn("part", F.pmod("h", F.lit(64)))
    )
    per_part = max(1, math.ceil(sample_per_lang / 64))
    picked = ranked.withColumn("r", F.row_number().over(Window.partitionBy("lang", "part").orderBy("h", "id"))).filter(F.col("r") <= per_part)
    bound = picked.select("lang", "id")
    wide = math.ceil(1.1 * dict_bytes / sample_per_lang)
    text = F.col(text_col).cast("string")
    start = F.pmod(F.xxhash64(F.col(id_col), F.lit(1)), F.greatest(F.char_length(text) - wide, F.lit(0)) + 1) + 1
    windows = train.select(F.col(lang_col).cast("string").alias("lang"), F.col(id_col).alias("id"), F.substring(text, start.cast("int"), F.lit(wide)).alias("text"))
    # at most languages * 64 * per_part ids: their size is proven by the rank filter
    rows = windows.filter("text is not null").join(F.broadcast(bound), ["lang", "id"], "left_semi").collect()
    by: dict[str, list[tuple[int, str]]] = {}
    for r in rows:
        by.setdefault(r["lang"], []).append((r["id"], r["text"]))
    size = min(dict_bytes, MODEL_BYTES // max(1, len(by)))
    out = {}
    for lang, texts in sorted(by.items()):
        # sorted by id and text; texts that repeat teach nothing new
        body = " ".join(dict.fromkeys(normalise(t) for _, t in sorted(texts))).encode()[:size]
        if body.strip():
            out[lang] = body
    return out


@lru_cache(maxsize=4)
def _compressors(model: tuple[tuple[str, bytes], ...], level: int):
    import zstandard as zstd

    made = []
    for lang, raw in model:
        d = zstd.ZstdCompressionDict(raw, dict_type=zstd.DICT_TYPE_RAWCONTENT)
        d.precompute_compress(level=level)
        c = zstd.ZstdCompressor(dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)
        carriers = [raw[len(raw) * i // CARRIERS :][:CARRIER_BYTES] + b" " for i in range(CARRIERS)]
        made.append((lang, c.compress, carriers, sum(len(c.compress(x)) for x in carriers)))
    return made


def _blocks(raw: bytes, block: int) -> list[bytes]:
    return [raw[i : i + block] for i in range(0, len(raw), block)] or [b""]


def sizes(text: str, model: tuple[tuple[str, bytes], ...], level: int = LEVEL, block: int = BLOCK_BYTES) -> list[tuple[int, str]]:
    """Encoded bytes of the whole text per language, smallest first, ties by name."""
    parts = _blocks(normalise(text).encode(), block)
    return sorted((sum(len(enc(x + b + b" ")) for b in parts for x in carriers) - cost * len(parts), lang) for lang, enc, carriers, cost in _compressors(model, level))


def decide(text: str | None, model: tuple[tuple[str, bytes], ...], min_margin: float = MIN_MARGIN, level: int = LEVEL, block: int = BLOCK_BYTES):
    """``(lang, score, margin, rejected)`` of one text; ``und`` if it is null or has no letter."""
    if text is None or not model or not any(map(str.isalpha, text)):
        return "und", 0.0, 0.0, True
    found = sizes(text, model, level, block)
    best, lang = found[0]
    if len(found) == 1:
        return lang, 1.0, 1.0, False
    second = found[1][0]
    margin = (second - best) / max(second, 1)
    score = 1.0 / sum(math.exp(-min(60.0, (n - best) * 0.5 / CARRIERS)) for n, _ in found)
    return lang, score, margin, second == best or margin < min_margin


def predict(docs: DataFrame, model: dict[str, bytes], id_col: str = "doc_id", text_col: str = "text", min_margin: float = MIN_MARGIN) -> DataFrame:
    """``id_col, lang_pred, score, margin, rejected`` for every row, from the whole text alone.

    Null text, or text without a letter, gives ``und``, score 0 and rejected. Repeated rows each
    get their own row; a null id stays null; an empty model gives ``und``; other columns are not read.
    """
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(tuple(sorted(model.items())))  # languages * DICT_BYTES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dicts = shared.value
        for b in batches:
            got = [decide(t.as_py(), dicts, min_margin) for t in b.column(1)]
            cols = [b.column(0), *(pa.array([g[i] for g in got], t) for i, t in enumerate((pa.string(), pa.float64(), pa.float64(), pa.bool_())))]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "lang_pred", "score", "margin", "rejected"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, OUT).withColumnRenamed("doc_id", id_col)


def keep_identified(docs: DataFrame, model: dict[str, bytes], text_col: str = "text", min_margin: float = MIN_MARGIN) -> DataFrame:
    """The rows of ``docs`` whose text is not rejected, with all their columns, in one pass and no shuffle."""
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(tuple(sorted(model.items())))
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dicts = shared.value
        for b in batches:
            yield b.filter(pa.array([not decide(t.as_py(), dicts, min_margin)[3] for t in b.column(at)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
