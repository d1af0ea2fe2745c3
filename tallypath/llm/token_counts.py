"""Token counts by the whole-token shortcut.

A text is cut where the vocabulary proves that no merge can cross: before each run of
the word mark, and around every character that occurs in no longer vocabulary piece.
Vocabulary strings that the tokenizer itself encodes alone as one token (proved once per
worker by encoding the vocabulary) count as 1 without any merging; only the other pieces
are merged, each distinct one once per worker while the bounded memo holds it.

Defined cases: a null text counts as empty (0 bytes, 0 tokens); a null id is kept as it is; very long texts
are counted whole, piece by piece; repeated rows give repeated results; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, table

MARK = "▁"
MEMO = 400_000


class _Memo(dict):
    """Token counts of pieces; misses are merged by the library. Bounded by ``MEMO`` entries beyond the proven ones."""

    def __init__(self, proven: dict[str, int], encode):
        super().__init__(proven)
        self.proven, self.encode = proven, encode

    def __missing__(self, piece: str) -> int:
        n = len(self.encode(piece))
        if len(piece) <= 64:
            if len(self) > MEMO + len(self.proven):
                self.clear()
                self.update(self.proven)
            self[piece] = n
        return n


class PieceCounter:
    """Exact token counts for a sentencepiece BPE model with an identity normaliser."""

    def __init__(self, model_file: str):
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
        sp = self.sp
        vocab = [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i))]
        crossing = [p for p in vocab if re.search(f"[^{MARK}]{MARK}", p)]
        unmoved = all(sp.encode(x, out_type=str) == sp.encode(x.replace(" ", MARK), out_type=str) for x in ("a  b", " a", "a ", "ﬁ Å"))
        #: Without these two facts texts are encoded whole.
        self.splits = not crossing and unmoved
        joined = {c for p in vocab if len(p) > 1 for c in p}
        loose = [c for c in map(chr, range(1, 128)) if c not in joined and c != " "]
        cut = "".join(re.escape(c) for c in loose)
        self.pieces = re.compile(f"{MARK}+[^{MARK}{cut}]*|[^{MARK}{cut}]+|[{cut}]" if cut else f"{MARK}+[^{MARK}]*|[^{MARK}]+").findall
        self.dummy = len(sp.encode("a", out_type=str)[0]) > 1
        proven = {}
        for p in vocab:
            if len(self._alone(p)) == 1:
                proven[p] = 1
        self.memo = _Memo(proven, self._alone)

    def _alone(self, piece: str) -> list[str]:
        """Tokens of ``piece`` as it stands within a text: a guard of its own is put before it and taken off again."""
        if piece.startswith(MARK):
            got = self.sp.encode(piece[1:], out_type=str) if self.dummy and len(piece) > 1 else self.sp.encode("\n" + piece, out_type=str)[2:]
            return got
        return self.sp.encode("\n" + piece, out_type=str)[2:]

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if not self.splits or "\0" in text:
            return len(self.sp.encode(text))
        marked = (MARK + text if self.dummy else text).replace(" ", MARK)
        return sum(map(self.memo.__getitem__, self.pieces(marked)))


@lru_cache(2)
def counter(model_file: str) -> PieceCounter:
    return PieceCounter(model_file)


@lru_cache(2)
def _tokenizers_json(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def count_tokens(docs: DataFrame, model: str, text_col: str = "text") -> DataFrame:
    """``docs`` with ``n_bytes`` and ``n_tokens``; ``model`` names a file of ``public_tokenizers``.

    A ``.model`` file goes through ``PieceCounter``; a ``.json`` file is encoded by its library.
    """

    def counted(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        import public_tokenizers

        path = str(public_tokenizers.path(model))
        for texts in batches:
            if path.endswith(".model"):
                c = counter(path)
                yield pd.Series([c.count(t) for t in texts], dtype="int64")
            else:
                t = _tokenizers_json(path)
                yield pd.Series([len(t.encode(x or "", add_special_tokens=False)) for x in texts], dtype="int64")

    n = F.pandas_udf(counted, "long")
    text = F.col(text_col)
    return bounded(docs).withColumns({"n_bytes": F.coalesce(F.octet_length(text), F.lit(0)).cast("long"), "n_tokens": n(text)})


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return count_tokens(docs, "piece_bpe_32k.model").select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > 4096).alias("over_limit"))
