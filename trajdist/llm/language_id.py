"""Language identification by compression.

Each language gets a zstandard raw-content dictionary of sampled training text.  A text is
compressed once with every dictionary; the language whose dictionary makes it smallest wins, and
the call is rejected when the margin to the next language is narrow.

The sample is bounded: of each language, ``SAMPLES`` rows (one for each bucket of a hash of the
id) and at most ``SNIPPET`` characters of each.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import lean

SAMPLES = 128
SNIPPET = 1500
MAX_LANGUAGES = 500
CHUNK = 4096
LEVEL = 3
#: Texts of fewer bytes are also measured from each of their later words on: one size in whole bytes is too coarse for them.
SHORT = 400
#: Relative gain over the second language below which a call is rejected.
MARGIN = 0.004

UNDETERMINED = "und"
_OTHER = re.compile(r"[\W\d_]+")

Model = dict[str, bytes]


def letters_only(text: str) -> str:
    """Lower case, every run of characters that are not letters as one space."""
    return _OTHER.sub(" ", text).strip().lower()


def fit(docs: DataFrame, training: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """A dictionary for each language of the training rows.

    Rows without text, letters or language teach nothing.  The sample's size is bounded by
    SAMPLES * SNIPPET for a language and MAX_LANGUAGES languages (more raise ValueError).
    """
    h = F.xxhash64(F.col(id_col).cast("string"))
    rows = docs.where(training & F.col(lang_col).isNotNull())
    chosen = rows.groupBy(F.col(lang_col).alias("l"), F.pmod(h, F.lit(SAMPLES)).alias("b")).agg(F.min(h).alias("h"))
    picks = chosen.select("l", "h").limit(MAX_LANGUAGES * SAMPLES + 1).collect()
    if len({r.l for r in picks}) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages")
    if not picks:
        return {}
    small = docs.sparkSession.createDataFrame(picks, "l string, h long")
    got = (
        rows.select(F.col(lang_col).alias("l"), h.alias("h"), F.substring(text_col, 1, SNIPPET).alias("s"))
        .join(F.broadcast(small), ["l", "h"], "left_semi")
        .where("s is not null")
        .dropDuplicates(["l", "h"])
        .orderBy("l", "h")
        .collect()
    )
    parts: dict[str, list[str]] = {}
    for r in got:
        if any(c.isalpha() for c in r.s):
            parts.setdefault(r.l, []).append(letters_only(r.s))
    return {k: " ".join(v).encode() for k, v in sorted(parts.items())}


class Classifier:
    """Holds the prepared dictionaries in a worker."""

    def __init__(self, model: Model, margin: float = MARGIN):
        self.names = sorted(model)
        self.margin = margin
        self.coders = []
        for name in self.names:
            d = zstandard.ZstdCompressionDict(model[name], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(level=LEVEL)
            self.coders.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_checksum=False, write_content_size=False, write_dict_id=False))

    def sizes(self, text: str) -> list[int]:
        """Compressed bytes under each language, in fixed chunks so that the dictionaries serve all of a long text."""
        raw = letters_only(text).encode()
        total = [0] * len(self.coders)
        parts = [raw[at : at + CHUNK] for at in range(0, len(raw), CHUNK)]
        if len(raw) < SHORT:
            parts += [raw[at + 1 :] for at, b in enumerate(raw) if b == 32]
        for part in parts:
            for i, c in enumerate(self.coders):
                total[i] += len(c.compress(part))
        return total

    def __call__(self, text: str | None) -> tuple[str, float, bool]:
        """Language, score and whether the call is rejected.  The score is the relative gain over the second language, stretched to 0..1."""
        if not self.names or text is None or not any(map(str.isalpha, text)):
            return UNDETERMINED, 0.0, True
        size = self.sizes(text)
        if len(size) == 1:
            return self.names[0], 1.0, False
        best = min(range(len(size)), key=size.__getitem__)
        second = min(s for i, s in enumerate(size) if i != best)
        gain = 1 - size[best] / second if second else 0.0
        return self.names[best], min(1.0, 4 * gain), gain < self.margin


def _classifier(model: Model, margin: float) -> Classifier:
    key = (id(model), margin)
    if _cached.get("key") != key:
        # The model is held too, so that no other can come to have its identity.
        _cached.update(key=key, value=Classifier(model, margin), model=model)
    return _cached["value"]


_cached: dict = {}


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", margin: float = MARGIN) -> DataFrame:
    """One row per input row: its id, lang_pred, score, rejected.  Only the text is looked at.

    A null, empty or letterless text is `und`, score 0, rejected; without any training text all are.  Of languages with equal
    sizes the first name is taken, with score 0, and rejected.  Repeated rows get the same answer each.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classify = _classifier(shared.value, margin)
        for b in batches:
            calls = [classify(t.as_py()) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([c[0] for c in calls], pa.string()), pa.array([c[1] for c in calls], pa.float64()), pa.array([c[2] for c in calls], pa.bool_())],
                ["id", "lang_pred", "score", "rejected"],
            )

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = rows.schema["id"].dataType.simpleString()
    return rows.mapInArrow(lean(run), f"id {kind}, lang_pred string, score double, rejected boolean").withColumnRenamed("id", id_col)


def keep_identified(docs: DataFrame, model: Model, text_col: str = "text", margin: float = MARGIN) -> DataFrame:
    """The rows, with all their columns, whose language is not rejected."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classify = _classifier(shared.value, margin)
        for b in batches:
            yield b.filter(pa.array([not classify(t.as_py())[2] for t in b.column(at)], pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
