"""Language by compression: the language whose raw-content dictionary makes a text smallest.

Each language gives one zstandard dictionary: pieces of documents whose id's hash falls under a threshold, which is set so
that about ``SAMPLE`` of the language's documents are taken, up to ``DICTIONARY`` bytes (bounds of the fit; whole texts are
classified). A document gives its whole text, or, if that is longer than ``EACH`` characters, ``CUTS`` pieces evenly
spaced over the whole of it, so that no document fills a dictionary. All languages are learned; where there are so many
that dictionaries of full size would pass ``TOTAL`` bytes, each gets an equal share, and a share under ``LEAST`` is an error.

A text is compressed once with each dictionary; the least size wins, ties going to the first language in code-point order.
``margin`` is the gap to the second size as a share of it; a narrow one sets ``rejected`` (``lang_pred`` still names the
smallest). The score grows from the share of chance to 1 with the bytes that separate the winner from the others.

Null texts and texts without a letter are ``und``, score 0, rejected. Without any learned language all are. Repeated rows
and equal texts fare alike; a very long text is compressed whole.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import regex
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_mod, documents, map_rows

#: Bytes of a dictionary; documents looked at for each language; level of compression; margin below which a text is rejected.
DICTIONARY, SAMPLE, LEVEL, NARROW = 96 * 1024, 400, 9, 0.01
#: Characters that a document gives at most, and in how many pieces; most bytes of all dictionaries, least of one.
EACH, CUTS, TOTAL, LEAST = DICTIONARY // 8, 8, 64 << 20, 1024
_letter = regex.compile(r"\p{L}")


class Model:
    def __init__(self, contents: dict[str, bytes], level: int = LEVEL):
        self.contents, self.level = dict(sorted(contents.items())), level
        self._ready = None

    def __reduce__(self):
        return Model, (self.contents, self.level)

    def _coders(self):
        if self._ready is None:
            self._ready = []
            for content in self.contents.values():
                d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                d.precompute_compress(level=self.level)
                self._ready.append(zstandard.ZstdCompressor(dict_data=d, write_checksum=False, write_content_size=False, write_dict_id=False))
        return self._ready

    def sizes(self, text: str) -> list[int]:
        raw = text.encode("utf-8", "replace")
        return [len(c.compress(raw)) for c in self._coders()]

    def predict(self, text: str | None) -> tuple[str, float, float, bool]:
        if not self.contents or text is None or not _letter.search(text):
            return "und", 0.0, 0.0, True
        names, sizes = list(self.contents), np.array(self.sizes(text.casefold()), float)
        best = int(sizes.argmin())
        weight = np.exp(-np.minimum(sizes - sizes[best], 200.0) / 4.0)
        second = float(np.partition(sizes, 1)[1]) if len(sizes) > 1 else 2 * sizes[best] + 1
        margin = (second - sizes[best]) / max(second, 1.0)
        return names[best], float(1.0 / weight.sum()), float(margin), bool(margin < NARROW)


def some_of(text) -> F.Column:
    """The whole text, or evenly spaced pieces of a long one, a line each."""
    n, size = F.length(text), EACH // CUTS
    cuts = F.transform(F.sequence(F.lit(0), F.lit(CUTS - 1)), lambda i: F.substring(text, (i * (n - size) / (CUTS - 1)).cast("int") + 1, F.lit(size)))
    return F.when(n <= EACH, text).otherwise(F.array_join(cuts, "\n"))


def train(docs: DataFrame, learn) -> Model:
    """One row a language tells the share of its ids that is looked at; only the chosen texts are read. A language's pieces, at most
    about ``SAMPLE`` times ``EACH`` characters, meet in one task."""
    known = docs.where(learn & F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    langs = known.groupBy("lang").count()
    share = TOTAL // max(1, langs.count())
    if share < LEAST:
        raise ValueError("too many languages for one set of dictionaries; map them to fewer first")
    room = min(DICTIONARY, share)
    place = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 31))
    limits = langs.select("lang", (SAMPLE * (1 << 31) / F.col("count")).alias("limit"))
    picked = known.join(F.broadcast(limits), "lang").where(place < F.col("limit")).select("lang", place.alias("k"), some_of(F.col("text")).alias("text"))

    def content(part: pd.DataFrame) -> pd.DataFrame:
        out, seen, size = [], set(), 0
        for text in part.sort_values(["k", "text"])["text"]:
            piece = text.casefold().encode("utf-8", "replace")
            if piece and piece not in seen and size < room:
                seen.add(piece)
                out.append(piece)
                size += len(piece) + 1
        return pd.DataFrame({"lang": [part["lang"].iloc[0]], "content": [b"\n".join(out)[:room]]})

    rows = picked.groupBy("lang").applyInPandas(content, "lang string, content binary").collect()
    return Model({r["lang"]: bytes(r["content"]) for r in rows if r["content"]})


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, lang_pred, score, margin, rejected) of every whole text."""

    def rows(part: dict) -> dict:
        got = [model.predict(t) for t in part["text"]]
        return {"doc_id": part["doc_id"]} | {n: [g[i] for g in got] for i, n in enumerate(("lang_pred", "score", "margin", "rejected"))}

    return map_rows(docs.select("doc_id", "text"), rows, "doc_id bigint, lang_pred string, score double, margin double, rejected boolean")


def held_out():
    return crc_mod(F.col("doc_id"), 5) == 0


def op7_compression_lid(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return predict(docs, train(docs, ~held_out())).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "margin", "rejected")
