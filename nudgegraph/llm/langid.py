"""Language identification as inference of a mixture of languages.

A document is a bag of byte trigrams drawn from several languages. Expectation
maximisation estimates each language's share from the trigram likelihoods, over
all learned languages; of the nested sets of the largest shares that one is
chosen whose likelihood, less a charge for each further language, is largest.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.llm.text import need, trimmed
from nudgegraph.session import Scratch

BITS = 16
UNKNOWN = "und"
# fixed: ASCII letters become lower case, other ASCII becomes a blank, bytes of other letters stay
_TABLE = bytes(c + 32 if 0x41 <= c <= 0x5A else c if 0x61 <= c <= 0x7A or c >= 0x80 else 0x20 for c in range(256))


def trigrams(text: str | None) -> np.ndarray | None:
    """Hashed trigrams; None for a text without letters."""
    if text is None or not any(c.isalpha() for c in text):
        return None
    plain = text.lower().encode("utf-8", "surrogatepass").translate(_TABLE)
    a = np.frombuffer(b" " + b" ".join(plain.split()) + b" ", np.uint8).astype(np.uint32)
    if len(a) < 3:
        return None
    code = (a[:-2] << np.uint32(16)) | (a[1:-1] << np.uint32(8)) | a[2:]
    return ((code * np.uint32(2654435761)) >> np.uint32(32 - BITS)).astype(np.uint16)


def held_out(doc_id: int | None) -> bool:
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 4 == 2


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen: dict[str, np.ndarray] = {}
    for batch in batches:
        for text, lang in zip(*batch.columns, strict=True):
            grams = trigrams(text.as_py())
            if grams is not None:
                table = seen.setdefault(lang.as_py(), np.zeros(1 << BITS, np.int64))
                table += np.bincount(grams, minlength=1 << BITS)
    for lang, table in seen.items():
        at = np.flatnonzero(table)
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at, pa.int32()), pa.array(table[at], pa.int64())], ["lang", "gram", "n"])


class MixtureModel:
    """Trigram probabilities of each learned language."""

    def __init__(self, langs: list[str], counts: np.ndarray, smooth: float = 0.5, charge: float = 2.0, least: float = 1e-3):
        self.langs, self.charge, self.least = langs, charge, least
        self.p = ((counts + smooth) / (counts.sum(1, keepdims=True) + smooth * counts.shape[1])).T.copy()
        self.log = np.log(self.p)

    @staticmethod
    def _fit(p: np.ndarray, n: np.ndarray, share: np.ndarray, rounds: int) -> tuple[np.ndarray, float]:
        total = n.sum()
        for _ in range(rounds):
            new = share * ((n / (p @ share)) @ p) / total
            done = np.abs(new - share).max() < 1e-4
            share = new
            if done:
                break
        return share, float(n @ np.log(p @ share))

    def shares(self, grams: np.ndarray) -> dict[str, float]:
        """Share of each language in the chosen set, largest first."""
        at, n = np.unique(grams, return_counts=True)
        n = n.astype(float)
        alone = n @ self.log[at]
        first = int(np.argmax(alone))
        posterior = 1 / np.exp(np.maximum(alone - alone[first], -700)).sum()
        best, value = {self.langs[first]: float(posterior)}, alone[first]
        if len(alone) == 1:
            return {self.langs[0]: 1.0}
        p = self.p[at]
        full, _ = self._fit(p, n, np.full(len(alone), 1 / len(alone)), 20)
        order = np.lexsort((np.arange(len(alone)), -full))
        fee = self.charge * np.log(n.sum())
        # languages of a smaller share than ``least`` come into no set of two or more
        for m in range(2, max(2, int((full >= self.least).sum())) + 1):
            some = order[:m]
            start = np.maximum(full[some], 1e-6)
            share, fit = self._fit(p[:, some], n, start / start.sum(), 15)
            if fit - fee * (m - 1) > value:
                value = fit - fee * (m - 1)
                best = {self.langs[i]: float(x) for i, x in sorted(zip(some, share, strict=True), key=lambda z: (-z[1], z[0]))}
        return best

    def predict(self, text: str | None) -> tuple[str, float, dict[str, float]]:
        grams = trigrams(text)
        if grams is None or not self.langs:
            return UNKNOWN, 0.0, {}
        best = self.shares(grams)
        lang = next(iter(best))
        return lang, min(1.0, max(0.0, best[lang])), best


def learn(docs: DataFrame, *, text_col: str = "text", lang_col: str = "lang", most: int = 256) -> MixtureModel:
    """Count trigrams of all rows with a language; the model has a table of fixed size for each language.

    More than ``most`` distinct languages raise an error: the model is sent to
    every worker. Rows without a language or without letters teach nothing.
    """
    known = need(docs, text_col, lang_col).toDF("text", "lang").where("lang is not null and text is not null")
    scratch = Scratch(docs.sparkSession, "langid")
    summed = scratch.keep(known.mapInArrow(trimmed(_counts), "lang string, gram int, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")), "counts")
    langs = sorted(r.lang for r in summed.select("lang").distinct().limit(most + 1).collect())
    if len(langs) > most:
        raise ValueError(f"more than {most} languages")
    counts = np.zeros((len(langs), 1 << BITS))
    for lang, row in zip(langs, counts, strict=True):  # a table of fixed size for each
        t = summed.where(F.col("lang") == lang).select("gram", "n").toArrow()
        row[t.column(0).to_numpy()] = t.column(1).to_numpy()
    scratch.drop(summed)
    return MixtureModel(langs, counts)


def identify(docs: DataFrame, model: MixtureModel, *, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, mixture, *carry) for every row of ``docs``.

    ``lang_pred`` has the largest share of the chosen set of languages and
    ``score`` is that share; for a set of one it is the posterior among single
    languages. A null text, one without letters, or a model that learned
    nothing gives ``und`` with score 0 and an empty mixture. Ids only decide
    ``held_out``, which is false for a null id. Other columns than ``carry`` are
    ignored.
    """
    langs, log = model.langs, model.log.T.astype(np.float32) if model.langs else None
    sent = docs.sparkSession.sparkContext.broadcast((langs, log, {}))
    make, charge, least = MixtureModel, model.charge, model.least

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        langs, log, kept = sent.value
        judge = make.__new__(make)
        judge.langs, judge.charge, judge.least = langs, charge, least
        if langs:
            if not kept:
                kept["log"] = log.T.astype(float).copy()
                kept["p"] = np.exp(kept["log"])
            judge.log, judge.p = kept["log"], kept["p"]
        for batch in batches:
            rows = [judge.predict(t.as_py()) for t in batch.column(1)]
            out = [held_out(i) for i in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(out, pa.bool_()), pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.float64()), pa.array([list(r[2].items()) for r in rows], pa.map_(pa.string(), pa.float64())), *batch.columns[2:]],
                ["doc_id", "held_out", "lang_pred", "score", "mixture", *batch.schema.names[2:]],
            )

    own = need(docs, id_col, text_col, *carry).toDF("doc_id", "of", *carry)
    carried = "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in own.schema.fields[2:])
    return own.mapInArrow(trimmed(run), "doc_id long, held_out boolean, lang_pred string, score double, mixture map<string,double>" + carried)


def training_rows(docs: DataFrame) -> DataFrame:
    """Rows that may teach: those that aren't held out by their id's checksum."""
    return docs.where("coalesce(crc32(cast(cast(doc_id as string) as binary)) % 4, 0) <> 2")
