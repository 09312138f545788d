"""Language identification by compression.

For each learned language a raw-content dictionary is cut from sample texts.  A text, in lower case and with anything between
letters as one space, is compressed piece by piece with each dictionary, and the language whose dictionary makes it smallest
wins.  The margin between the best and the second size says how sure the choice is; narrow margins are rejected.  What is narrow is
learned too: labelled rows that no dictionary was cut from are judged, and the margin rises to where their errors end.  Equal sizes
have no margin and are always rejected; their best guess is the language whose dictionary holds most of the words.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import pyarrow as pa
import regex
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corridor.llm.texthash import bounded, small, tidy

SAMPLE_ROWS = 300  # labelled rows of each language, at most, that dictionaries are cut from
SAMPLE_CHARS = 2000  # characters of each
DICTIONARY_BYTES = 96 << 10
PIECE_BYTES = 1024
LEVEL = 9
JUDGED_ROWS = 150  # further labelled rows of each language, at most, that the margin is learned from
LEAST_MARGIN = 0.005  # no margin below is accepted, whatever the rows say
RIGHT_LOST = 0.005  # share of the rightly judged rows that the learned margin may reject, at most
UNKNOWN = "und"
_LETTER = regex.compile(r"\p{L}")
_BETWEEN = re.compile(r"[\W\d_]+")


def plain(text: str) -> str:
    return f" {_BETWEEN.sub(' ', text.lower()).strip()} "


def held_out(doc_id: Column) -> Column:
    """Whether a document is kept from training: crc32 of the id as text, modulo 4, is 2."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


@dataclass(frozen=True)
class Languages:
    """What is learned: dictionaries by language, and the least margin that is accepted."""

    dictionaries: dict[str, bytes] = field(default_factory=dict)
    margin: float = LEAST_MARGIN


def learn(docs: DataFrame) -> Languages:
    """Dictionaries and margin from a bounded sample of labelled rows that aren't held out.

    Rows are picked by a hash of the id, spread over the whole table: of each language SAMPLE_ROWS for its dictionary, then JUDGED_ROWS for the
    margin, each cut to SAMPLE_CHARS.  Each language keeps the last DICTIONARY_BYTES of its own sample, or all of a smaller one; how much
    another language has doesn't matter.  No usable row: no language, and everything is ``und``.
    """
    usable = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    usable = usable.where(~held_out(F.col("doc_id")) & F.col("doc_id").isNotNull() & F.col("lang").isNotNull() & (F.col("lang") != UNKNOWN))
    have = {r[0]: r[1] for r in usable.groupBy("lang").count().collect()}  # a row for each language
    if not have:
        return Languages()
    draw = F.pmod(F.xxhash64("doc_id", F.lit(20240229)), F.lit(1 << 30))
    bar = F.create_map(*[F.lit(x) for lang, n in have.items() for x in (lang, int(min(1.0, 2 * (SAMPLE_ROWS + JUDGED_ROWS) / n) * (1 << 30)))])
    rows = usable.where(draw < bar[F.col("lang")]).select("lang", draw.alias("draw"), "doc_id", F.substring("text", 1, SAMPLE_CHARS).alias("text")).collect()
    pieces: dict[str, list[bytes]] = {}
    judged: dict[str, list[str]] = {}
    for r in sorted(rows, key=lambda r: (r.lang, r.draw, r.doc_id, r.text or "")):
        own, more = pieces.setdefault(r.lang, []), judged.setdefault(r.lang, [])
        if r.text and len(own) < SAMPLE_ROWS:
            own.append(plain(r.text).encode())
        elif r.text and len(more) < JUDGED_ROWS:
            more.append(r.text)
    joined = {lang: b"".join(x) for lang, x in pieces.items() if x}
    dictionaries = {lang: x[-DICTIONARY_BYTES:] for lang, x in sorted(joined.items())}
    judge = Judge(dictionaries)
    return Languages(dictionaries, narrow([(score, told == lang) for lang, texts in sorted(judged.items()) for told, score in map(judge.predict, texts)]))


def narrow(judged: list[tuple[float, bool]]) -> float:
    """The least margin to accept, from (score, right): above the highest wrong score that costs at most RIGHT_LOST of the right ones."""
    right = sorted(score for score, ok in judged if ok and score >= LEAST_MARGIN)  # below, they are lost anyway
    bar = right[int(RIGHT_LOST * len(right))] if right else LEAST_MARGIN
    return max([LEAST_MARGIN, *(score * 1.01 + 1e-6 for score, ok in judged if not ok and score < bar)])


class Judge:
    """Compressors for the learned languages."""

    def __init__(self, dictionaries: dict[str, bytes]) -> None:
        self.langs = list(dictionaries)
        self.words = [set(raw.split()) for raw in dictionaries.values()]
        self.compress = []
        for raw in dictionaries.values():
            d = zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(level=LEVEL)
            self.compress.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_checksum=False, write_content_size=False, write_dict_id=False).compress)

    def sizes(self, raw: bytes) -> list[int]:
        pieces = [raw[a : a + PIECE_BYTES] for a in range(0, len(raw), PIECE_BYTES)]
        return [sum(len(c(p)) for p in pieces) for c in self.compress]

    def predict(self, text: str | None) -> tuple[str, float]:
        """Language and score: the share, 0 to 1, by which the second size exceeds the best; of equal sizes the one with most words, at 0."""
        if not text or not _LETTER.search(text) or not self.langs:
            return UNKNOWN, 0.0
        raw = plain(text).encode()
        sizes = self.sizes(raw)
        least = min(sizes)
        best = [i for i, n in enumerate(sizes) if n == least]
        if len(self.langs) == 1:
            return self.langs[0], 1.0
        if len(best) == 1:
            second = sorted(sizes)[1]
            return self.langs[best[0]], (second - least) / second
        own = raw.split()
        votes = [sum(w in self.words[i] for w in own) for i in best]
        return self.langs[best[votes.index(max(votes))]], 0.0


def predict(docs: DataFrame, learned: Languages, least_margin: float | None = None) -> DataFrame:
    """``docs`` with lang_pred, score and rejected; columns of these names are replaced.

    A null text or one without a letter is ``und`` with score 0 and rejected.  A margin below the learned one, or ``least_margin`` if
    given, is rejected and keeps its best guess.  Only the text decides.  Without any learned language everything is ``und``.
    """

    least_margin = learned.margin if least_margin is None else least_margin
    dictionaries = learned.dictionaries
    plain_rows = bounded(docs).drop("lang_pred", "score", "rejected").withColumn("text", F.col("text").cast("string"))
    at = plain_rows.columns.index("text")

    def run(batches):
        judge = Judge(dictionaries)
        for batch in small(batches):
            got = [judge.predict(t.as_py()) for t in batch.column(at)]
            lang, score = [g[0] for g in got], [g[1] for g in got]
            no = [x == UNKNOWN or s < least_margin for x, s in got]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(no, pa.bool_())], [*batch.schema.names, "lang_pred", "score", "rejected"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in plain_rows.schema) + ", lang_pred string, score double, rejected boolean"
    return plain_rows.mapInArrow(tidy(run), schema)


def identify(docs: DataFrame, least_margin: float | None = None) -> DataFrame:
    """doc_id, held_out, lang_pred, score and rejected of every row of ``docs(doc_id, text, lang)``, learned from the table itself."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("string").alias("text"))
    return predict(rows, learn(docs), least_margin).select("doc_id", "held_out", "lang_pred", "score", "rejected")
