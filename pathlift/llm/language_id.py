"""Language identification by compression.

Each language keeps a raw-content zstandard dictionary made of labelled text.  A
text is cut into blocks, every block is compressed with each dictionary, and the
language with the smallest total size wins.  Texts are normalised first (lower
case, every run of non-letters becomes one space), so digits and symbols, which
no language owns, cost nothing.
"""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
import regex
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .frames import add_columns

UNDETERMINED = "und"
_LETTER = regex.compile(r"\p{L}")
_NO_LETTER = regex.compile(r"[^\p{L}\p{M}]+")


def normalised(text: str) -> bytes:
    """Lower-case letters and their marks with single spaces between runs; empty if there is no letter (category L)."""
    if not _LETTER.search(text):
        return b""
    return f" {_NO_LETTER.sub(' ', text.lower()).strip()} ".encode()


@dataclass(frozen=True)
class LanguageModel:
    """Dictionaries by language, with the settings that compress a text."""

    dictionaries: dict[str, bytes]
    level: int = 5
    block_bytes: int = 4096
    narrow: float = 0.02

    def compressors(self) -> list[tuple[str, zstandard.ZstdCompressor]]:
        out = []
        for lang, content in sorted(self.dictionaries.items()):
            if content:
                shared = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                shared.precompute_compress(level=self.level)
                out.append((lang, zstandard.ZstdCompressor(dict_data=shared, level=self.level, write_checksum=False, write_content_size=False, write_dict_id=False)))
            else:
                out.append((lang, zstandard.ZstdCompressor(level=self.level, write_checksum=False, write_content_size=False)))
        return out

    def classify(self, text: str | None, compressors: list) -> tuple[str, float, bool]:
        """(language, score, rejected).

        The score is m / (m + narrow) for the relative margin m between the two
        smallest sizes, so 0.5 marks the margin below which a text is rejected.
        """
        body = normalised(text) if text else b""
        if not body or not compressors:
            return UNDETERMINED, 0.0, True
        blocks = [body[k : k + self.block_bytes] for k in range(0, len(body), self.block_bytes)]
        sizes = sorted((sum(len(z.compress(b)) for b in blocks), lang) for lang, z in compressors)
        if len(sizes) == 1:
            return sizes[0][1], 1.0, False
        margin = (sizes[1][0] - sizes[0][0]) / sizes[1][0]
        return sizes[0][1], margin / (margin + self.narrow), margin < self.narrow


def fit_language_model(labelled: DataFrame, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", *, rows_per_language: int = 400, max_languages: int = 64, dictionary_bytes: int = 96 * 1024, excerpt_chars: int = 1500, **settings) -> LanguageModel:
    """Dictionaries from a bounded, deterministic sample of labelled rows.

    Every label gets a dictionary.  Bounds: ``rows_per_language`` rows of each label in
    the order of a hash of their id, of which ``excerpt_chars`` characters from a
    hashed position enter the dictionary.  Beyond ``max_languages`` labels, all share
    the rows and bytes of that many.  Rows with null text or null label teach nothing.
    An empty table gives a model that answers ``und``.
    """
    named = labelled.where(F.col(lang_col).isNotNull())
    counted = named.groupBy(F.col(lang_col).alias("lang")).agg(F.count(F.lit(1)).alias("rows")).orderBy("lang").collect()
    langs = [r[0] for r in counted]
    part = min(1.0, max_languages / max(1, len(langs)))
    rows_per_language, dictionary_bytes = max(1, round(rows_per_language * part)), max(256, round(dictionary_bytes * part))
    # only hashes below this level of a language reach the sort: about four times the rows wanted, and 16 at least
    level = named.sparkSession.createDataFrame([(r[0], int(min(1.0, max(16, 4 * rows_per_language) / r[1]) * 2**62)) for r in counted], "lang string, level long")
    order = Window.partitionBy("lang").orderBy("h", "id")
    picked = (
        named.select(F.col(lang_col).alias("lang"), F.col(id_col).alias("id"), F.pmod(F.xxhash64(F.col(id_col)), F.lit(2**62)).alias("h"))
        .join(F.broadcast(level), "lang")  # one row a label
        .where("h <= level")
        .withColumn("n", F.row_number().over(order))
        .where(F.col("n") <= rows_per_language)
        .select("id", "lang", "n")
    )
    start = 1 + F.pmod(F.xxhash64("id", F.lit(1)), F.greatest(F.lit(1), F.length("text") - excerpt_chars + 1))
    texts = (
        named.select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
        .join(F.broadcast(picked), ["id", "lang"])  # at most max_languages * rows_per_language rows, or one a label
        .where(F.col("text").isNotNull())
        .select("lang", "n", F.substr("text", start.cast("int"), F.lit(excerpt_chars)).alias("text"))
        .collect()
    )
    contents = dict.fromkeys(langs, b"")
    for row in sorted(texts, key=lambda r: (r["lang"], r["n"], r["text"])):
        if len(contents[row["lang"]]) < dictionary_bytes:
            contents[row["lang"]] += normalised(row["text"])
    return LanguageModel({k: v[:dictionary_bytes] for k, v in contents.items()}, **settings)


def identify_language(df: DataFrame, model: LanguageModel, text_col: str = "text") -> DataFrame:
    """Adds lang_pred, score and rejected, from whole texts.

    Null texts and texts without a letter give ``und``, 0.0 and true, however long they
    are; ties go to the language whose name comes first.  Columns of these three names
    are replaced; all others are kept, repeated rows too.  A model without languages
    answers ``und``; an empty table stays empty.
    """

    def make(batch: pa.RecordBatch) -> list:
        compressors = model.compressors()
        found = [model.classify(x.as_py(), compressors) for x in batch.column(batch.schema.names.index(text_col))]
        return [pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64()), pa.array([f[2] for f in found], pa.bool_())]

    return add_columns(df, [("lang_pred", T.StringType()), ("score", T.DoubleType()), ("rejected", T.BooleanType())], make)
