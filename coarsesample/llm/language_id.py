"""Language by compression.

One zstandard raw-content dictionary per language is cut from labelled texts. A text is compressed
with each in segments, and the language whose dictionary leaves the fewest bytes is chosen. A text
is rejected where it is null, has no letter, or where the runner-up needs less than ``narrow`` more of
the winner's bytes.

Dictionaries come from a bounded sample of learning rows: at most ``docs_per_language`` distinct texts
of the lowest content hashes, and from each ``sample_chars`` characters in ``pieces`` runs spread over
the whole text. Predictions read whole texts. Only the ``most_languages`` languages with most rows are
learnt, a bound on the dictionaries that each worker holds; a value beyond them is never predicted.

Defined results: null text or text without a letter is ``und`` with score 0 and rejected; equal
sizes go to the language with most learning rows; without learning rows all are ``und``; with one
language learnt no margin can be narrow; an empty table gives an empty result; the output has the key,
the prediction and the decision only.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UNKNOWN = "und"
_LETTER = regex.compile(r"\p{L}")
_OTHER = regex.compile(r"[^\p{L}\p{M}]+")


def letters(text: str) -> str:
    """Lower-case letters and their marks with one space between runs, before and after: noise and case say little of a language."""
    return f" {_OTHER.sub(' ', text.lower()).strip()} "


def held_out(key: Column) -> Column:
    """Rows kept from learning: crc32 of the key as text leaves 2 when divided by 4."""
    return F.pmod(F.crc32(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), F.lit(4)) == 2


def _spread(text: Column, chars: int, pieces: int) -> Column:
    """``chars`` characters in ``pieces`` runs at even distances from a text's start to its end."""
    run = chars // pieces
    room = F.char_length(text) - run
    cut = F.transform(F.sequence(F.lit(0), F.lit(pieces - 1)), lambda i: F.substr(text, (F.floor(i * room / max(1, pieces - 1)) + 1).cast("int"), F.lit(run)))
    return F.when(F.char_length(text) <= chars, text).otherwise(F.array_join(cut, " "))


def train_dictionaries(learn: DataFrame, text: str = "text", lang: str = "lang", docs_per_language: int = 200, sample_chars: int = 1000, pieces: int = 4, most_languages: int = 500) -> dict[str, bytes]:
    """Raw-content dictionaries by language, that with most learning rows first.

    The driver gets a row per language and ``docs_per_language`` samples of each, whatever the table's
    size: the hash threshold follows the distinct texts, and rows that repeat a text count once.
    """
    rows = learn.where(F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(lang).alias("l"), F.col(text).alias("t"), F.pmod(F.xxhash64(F.col(text), F.lit("dictionary")), F.lit(1 << 62)).alias("at"))
    sizes = rows.groupBy("l").agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("at", 0.02).alias("texts"))
    counts = {r["l"]: (r["n"], r["texts"]) for r in sizes.orderBy(F.desc("n"), "l").limit(most_languages).collect()}
    if not counts:
        return {}
    share = F.create_map(*[x for name, (_, texts) in counts.items() for x in (F.lit(name), F.lit(math.ceil(min(1.0, 1.5 * docs_per_language / texts) * (1 << 62))))])
    picked = rows.where(F.col("at") < share[F.col("l")]).groupBy("l", "at").agg(F.min(_spread(F.col("t"), sample_chars, pieces)).alias("t"))
    texts: dict[str, list] = {name: [] for name in counts}
    for name, at, part in picked.collect():
        texts[name].append((at, part))
    out = {}
    for name in sorted(texts, key=lambda name: (-counts[name][0], name)):
        content = "".join(letters(t) for _, t in sorted(texts[name])[:docs_per_language]).encode("utf-8", "surrogatepass")
        if content:
            out[name] = content.ljust(8, b" ")
    return out


class CompressionClassifier:
    """Sizes of a text under each dictionary."""

    def __init__(self, dictionaries: dict[str, bytes], level: int = 6, segment: int = 4096):
        import zstandard

        self.names = list(dictionaries)
        self.segment, self.coders = segment, []
        for name in self.names:
            content = zstandard.ZstdCompressionDict(dictionaries[name], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            params = zstandard.ZstdCompressionParameters.from_level(level, window_log=20, write_content_size=False, write_checksum=False, write_dict_id=False)
            self.coders.append(zstandard.ZstdCompressor(dict_data=content, compression_params=params).compress)

    def sizes(self, text: str) -> list[int]:
        """Bytes under each dictionary, segment by segment."""
        data = letters(text).encode("utf-8", "surrogatepass")
        parts = [data[i : i + self.segment] for i in range(0, len(data), self.segment)]
        return [sum(len(compress(p)) for p in parts) for compress in self.coders]

    def predict(self, text: str | None) -> tuple[str, float, float]:
        """Language, score from 0 to 1, and the runner-up's surplus as a share of the winner's bytes."""
        if not self.names or text is None or not _LETTER.search(text):
            return UNKNOWN, 0.0, 0.0
        sizes = self.sizes(text)
        best = min(sizes)
        at = sizes.index(best)
        others = sizes[:at] + sizes[at + 1 :]
        margin = (min(others) - best) / best if others else 1.0
        return self.names[at], 1.0 / sum(2.0 ** -min(60.0, s - best) for s in sizes), margin


NARROW = 0.02


def predict_language(docs: DataFrame, dictionaries: dict[str, bytes], narrow: float = NARROW, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, lang_pred, score, margin, rejected for each row."""
    kind = docs.schema[key].dataType
    given = docs.select(F.col(key).cast("string").alias(key), F.col(text).alias("text"))
    schema = f"`{key}` string, lang_pred string, score double, margin double, rejected boolean"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = CompressionClassifier(dictionaries)
        for batch in batches:
            found = [model.predict(t) for t in batch["text"]]
            yield pd.DataFrame({key: batch[key], "lang_pred": [f[0] for f in found], "score": [f[1] for f in found], "margin": [f[2] for f in found], "rejected": [f[0] == UNKNOWN or f[2] < narrow for f in found]})

    return given.mapInPandas(run, schema).withColumn(key, F.col(key).cast(kind))


def accepts(dictionaries: dict[str, bytes], narrow: float = NARROW):
    """A column function of the text: whether its language can be told. Never null."""

    @F.pandas_udf("boolean")
    def told(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = CompressionClassifier(dictionaries)
        for texts in batches:
            found = [model.predict(t) for t in texts]
            yield pd.Series([f[0] != UNKNOWN and f[2] >= narrow for f in found])

    return told
