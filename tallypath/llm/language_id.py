"""Language identification by a byte convolutional network.

Texts are cut into windows of ``WINDOW`` bytes; each window passes through filters of
several widths over byte embeddings, max pooling and softmax, all trained in numpy. When
applied, a filter's response is a sum of rows looked up by byte pair, so whole texts cost a
few lookups a byte. A text's probabilities are the means of its windows', weighted by the
letters in them.

The network is fitted on a bounded sample: about ``per_language`` rows of each language and ``total`` rows
in all (with many languages each gets its share of them), ``windows_each`` windows of each, from a stretch
of at most ``LONGEST`` characters whose place in the text is drawn by hash; no language is left out. Predictions read whole texts of all rows.

Defined cases: a null text or one without letters (of any script; number signs are none) is ``und`` with
score 0; repeated rows get equal results; a null id is never learned from and counts as not held out; very long
texts are read whole; without labelled rows every text is ``und``; an empty table gives an empty
result; other columns are ignored, and columns called like the results are replaced in ``identify``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, release, table, written
from .convnet import ConvNet, softmax
from .textnum import utf8

WINDOW = 192
WIDTHS = (2, 3, 4)
PER_LANGUAGE = 1500
LONGEST = 1 << 15
WINDOWS_EACH = 4
TOTAL = 12_000  # rows of the sample at most: 400 MB of text
_ASCII_LETTER = re.compile("[A-Za-z]").search
_IS_LETTER = np.zeros(257, np.float32)
_IS_LETTER[1:][[*range(65, 91), *range(97, 123), *range(128, 256)]] = 1


def has_letter(text: str) -> bool:
    return bool(_ASCII_LETTER(text)) or any(map(str.isalpha, text))


def windows(data: bytes) -> np.ndarray:
    """Ids (byte + 1, 0 after the end) of all windows of ``data``, one a row."""
    n = max(1, -(-len(data) // WINDOW))
    out = np.zeros(n * WINDOW, np.int32)
    out[: len(data)] = np.frombuffer(data, np.uint8)
    out[: len(data)] += 1
    return out.reshape(n, WINDOW)


@dataclass
class LanguageModel:
    languages: list[str]
    net: ConvNet

    def prepare(self) -> "LanguageModel":
        """For each width the lookups (offset, table, by pair or by byte) whose sum is the filters' response."""
        self.plan = []
        for w, per in self.net.tables().items():
            steps = [(o, (per[o][:, None] + per[o + 1][None]).reshape(257 * 257, -1), True) for o in range(0, w - 1, 2)]
            if w % 2:
                steps.append((w - 1, per[w - 1], False))
            self.plan.append((w, steps))
        return self

    def window_probabilities(self, ids: np.ndarray) -> np.ndarray:
        """(windows, languages) for windows of one length."""
        out = []
        for lo in range(0, len(ids), 256):
            part = ids[lo : lo + 256]
            pairs = part[:, :-1] * 257 + part[:, 1:]
            best = []
            for w, steps in self.plan:
                n = part.shape[1] - w + 1
                c = None
                for o, t, by_pair in steps:
                    rows = t.take(np.ascontiguousarray((pairs if by_pair else part)[:, o : o + n]).ravel(), axis=0)
                    c = rows if c is None else np.add(c, rows, out=c)
                best.append(c.reshape(len(part), n, -1).max(1))
            out.append(softmax(self.net.logits(np.concatenate(best, 1))))
        return np.concatenate(out)

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        own = [i for i, t in enumerate(texts) if t and has_letter(t)]
        names, scores = ["und"] * len(texts), np.zeros(len(texts))
        if not self.languages:
            return names, scores
        lo = 0
        while lo < len(own):
            hi, held, parts = lo, 0, []
            while hi < len(own) and held < 1 << 22:
                parts.append(windows(utf8(texts[own[hi]])))
                held += parts[-1].size
                hi += 1
            ids = np.concatenate(parts)
            p = self.window_probabilities(ids) * (_IS_LETTER[ids].sum(1) + 1e-3)[:, None]
            cut = np.concatenate([[0], np.cumsum([len(x) for x in parts])[:-1]])
            total = np.add.reduceat(p, cut, axis=0)
            total /= total.sum(1, keepdims=True)
            for i, k, s in zip(own[lo:hi], total.argmax(1), total.max(1)):
                names[i], scores[i] = self.languages[k], min(1.0, float(s))
            lo = hi
        return names, scores


def fit(texts: list[str], langs: list[str], epochs: int = 4, windows_each: int = WINDOWS_EACH, seed: int = 5) -> LanguageModel:
    names = sorted(set(langs))
    if not names:
        return LanguageModel([], ConvNet.fresh(257, 1, 8, 8, WIDTHS))
    number = {x: i for i, x in enumerate(names)}
    rng = np.random.default_rng(seed)
    seqs, labels = [], []
    for t, x in zip(texts, langs):
        w = windows(utf8(t))
        for i in rng.permutation(len(w))[:windows_each]:
            if _IS_LETTER[w[i]].sum() >= 3:
                seqs.append(w[i][: int((w[i] > 0).sum())])
                labels.append(number[x])
    y = np.array(labels, int)
    net = ConvNet.fresh(257, len(names), 8, 8, WIDTHS)
    if len(y):
        share = np.bincount(y, minlength=len(names)) / len(y)
        net.fit(seqs, y, (1 / len(names) / np.maximum(share, 1e-9))[y].astype(np.float32), epochs, rate=0.01)
    return LanguageModel(names, net)


def _stretch():
    """``LONGEST`` characters of a longer text, from a place drawn by hash; shorter ones whole."""
    over = F.greatest(F.length("text") - LONGEST, F.lit(0))
    return F.substring("text", (F.pmod(F.xxhash64("text"), (over + 1).cast("long")) + 1).cast("int"), F.lit(LONGEST))


def train(docs: DataFrame, per_language: int = PER_LANGUAGE, total: int = TOTAL) -> LanguageModel:
    """Model from documents with a language whose crc32(doc_id) mod 4 isn't 2: about ``per_language`` of each and ``total`` in all, by hash of id and text."""
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & (F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) != 2))
    known = known.select("doc_id", "lang", _stretch().alias("text"))
    sizes = written(known.groupBy("lang").count(), "languages")
    languages = sizes.count()
    if not languages:
        return fit([], [])
    each = max(1, min(per_language, total // languages))
    # Equal rows have one chance together, so repeated rows are drawn once.
    order = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30))
    some = known.join(sizes, "lang").where(order / F.lit(float(1 << 30)) < F.lit(1.0 * each) / F.col("count"))
    rows = sorted(some.select("doc_id", "lang", "text").distinct().orderBy(order, "doc_id", "lang", "text").limit(total + total // 8).collect(), key=lambda r: (r["doc_id"], r["lang"], r["text"]))
    model = fit([r["text"] for r in rows], [r["lang"] for r in rows])
    del rows
    release()
    return model


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score``, from whole texts."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("struct<lang_pred:string,score:double>")
    def predicted(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        m = shared.value.prepare()
        for texts in batches:
            names, scores = m.predict(list(texts))
            yield pd.DataFrame({"lang_pred": pd.Series(names, dtype=object), "score": scores})
        del m.plan
        release()

    return bounded(docs).withColumn("__p", predicted("text")).withColumns({"lang_pred": F.col("__p.lang_pred"), "score": F.col("__p.score")}).drop("__p")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = identify(docs.select("doc_id", "text"), train(docs))
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2, F.lit(False))
    return found.select("doc_id", held.alias("held_out"), "lang_pred", "score")
