"""Language identification by compression.

Each language has a raw-content zstandard dictionary: texts of a bounded, hash-chosen sample of the labelled rows (at
most ``SAMPLE_TEXTS`` texts and ``DICT_BYTES`` bytes a language), a longer one from its first letter for ``sample_chars``. A text is encoded, in blocks of ``BLOCK`` bytes so
that its own history never replaces the dictionary's, lower-cased, once with every dictionary; the smallest sum of sizes names the
language. ``score`` is the smallest size's share in a soft minimum; ``rejected`` marks margins too narrow to trust.

Defined results: null texts and texts without a letter are ``und`` with score 0; ties go to the language with more
training texts, then by name; with nothing to learn from every text is ``und``; repeated rows each get a row; empty
tables and other columns are fine.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import hash60, sliced

SAMPLE_TEXTS, SAMPLE_CHARS, DICT_BYTES = 120, 20_000, 32 << 10
BLOCK, SHORTEST_MATCH = 4096, 4
NARROW = 0.01
LEAST_BYTES = 8  # of a raw-content dictionary; shorter contents are repeated
SCHEMA = "doc_id long, lang_pred string, score double, rejected boolean"


def learn_dictionaries(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample_chars: int = SAMPLE_CHARS) -> list[tuple[str, bytes]]:
    """(language, raw content) for every language of a text with a letter, the one with most training texts first."""
    rows = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).rlike(r"\p{L}"))
    counts = {r[0]: r[1] for r in rows.groupBy(F.col(lang_col).cast("string")).count().collect()}  # one row a language
    if not counts:
        return []
    # the bound of a language's hashes keeps all but about twice the sample from being compared
    bounds = [(k, int(min(1.0, (2 * SAMPLE_TEXTS + 100) / n) * (1 << 60))) for k, n in counts.items()]
    listed = F.broadcast(docs.sparkSession.createDataFrame(bounds, "lang string, bound long"))
    order = Window.partitionBy("lang").orderBy("h", "doc_id")
    whole = F.col(text_col)
    piece = F.when(F.length(whole) <= sample_chars, whole).otherwise(F.substr(whole, F.regexp_instr(whole, F.lit(r"\p{L}")), F.lit(sample_chars)))
    usable = rows.select(
        F.col(lang_col).cast("string").alias("lang"), F.col(id_col).alias("doc_id"), piece.alias("text"), hash60(F.col(id_col), salt="lang:").alias("h")
    ).join(listed, "lang").where("h < bound")
    chosen = usable.withColumn("r", F.row_number().over(order)).where(F.col("r") <= SAMPLE_TEXTS).select("lang", "r", "text").collect()
    content: dict[str, bytes] = {}
    for r in sorted(chosen, key=lambda r: (r["lang"], r["r"])):
        held, more = content.get(r["lang"], b""), r["text"].lower().encode()
        more = more if held else more[: DICT_BYTES - 1]
        if len(held) + len(more) + 1 <= DICT_BYTES:
            content[r["lang"]] = held + more + b"\n"
    return sorted(((k, v * -(-LEAST_BYTES // len(v))) for k, v in content.items()), key=lambda kv: (-counts[kv[0]], kv[0]))


def compressors(dictionaries: list[tuple[str, bytes]]):
    import zstandard

    # letters repeat in short groups, so matches of four bytes must count
    how = zstandard.ZstdCompressionParameters.from_level(
        3, strategy=zstandard.STRATEGY_LAZY, min_match=SHORTEST_MATCH, search_log=3, write_content_size=0, write_checksum=0, write_dict_id=0
    )
    out = []
    for _, content in dictionaries:
        d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        d.precompute_compress(compression_params=how)
        out.append(zstandard.ZstdCompressor(dict_data=d, compression_params=how))
    return out


def judge(text: str | None, names: list[str], coders) -> tuple[str, float, bool]:
    if not names or text is None or not any(map(str.isalpha, text)):
        return "und", 0.0, True
    data = text.lower().encode()
    blocks = [data[i : i + BLOCK] for i in range(0, len(data), BLOCK)]
    sizes = [sum(len(c.compress(b)) for b in blocks) for c in coders]
    best = min(range(len(sizes)), key=sizes.__getitem__)
    least = sizes[best]
    scale = max(1.0, 0.02 * least)
    score = 1.0 / sum(math.exp(-min(50.0, (s - least) / scale)) for s in sizes)
    second = min((s for i, s in enumerate(sizes) if i != best), default=2 * least)
    return names[best], score, second - least < NARROW * least


def identify(docs: DataFrame, dictionaries: list[tuple[str, bytes]], *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score, rejected) for each document."""
    names = [n for n, _ in dictionaries]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coders = compressors(dictionaries)
        for b in sliced(batches):
            out = [judge(t.as_py(), names, coders) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x[0] for x in out], pa.string()), pa.array([x[1] for x in out], pa.float64()), pa.array([x[2] for x in out], pa.bool_())], ["doc_id", "lang_pred", "score", "rejected"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, SCHEMA)
