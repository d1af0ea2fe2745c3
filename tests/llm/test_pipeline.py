"""The pipeline's stages, each on what its predecessor kept, against plain versions; and the registered queries' columns."""

import zlib

import numpy as np
import pandas as pd
import pytest
from test_operators import _near

import corpus_pipeline as cp
from tallypath.llm import decontamination, secrets, textnum, toxicity
from tallypath.llm.queries import queries

SF = "/root/testdata/sf0.001"
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    """Documents before and after each stage."""
    folder = tmp_path_factory.mktemp("stages")
    df, out = spark.read.parquet(f"{SF}/documents.parquet"), []
    for k, (name, f) in enumerate(cp.STAGES):
        f(spark, df, SF).write.parquet(f"file://{folder}/{k}")
        nxt = spark.read.parquet(f"file://{folder}/{k}")
        out.append((name, df.toPandas(), nxt.toPandas()))
        df = nxt
    return out


def test_columns_stay(stages):
    assert [n for n, _, _ in stages] == ["toxicity", "minhash_near_dedup", "decontamination", "secrets", "packing"]
    for _, before, after in stages[:-1]:
        assert list(after.columns) == list(before.columns) == COLUMNS


def test_toxicity_stage_drops_what_the_score_rejects(spark, stages):
    _, before, after = stages[0]
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = toxicity.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    score = model.prepare().score([textnum.utf8(t) for t in before["text"]])
    assert set(after["doc_id"]) == set(before["doc_id"][score < 0.5])


def test_near_duplicate_stage_keeps_one_of_each_group(stages):
    _, before, after = stages[1]
    label = _near(list(zip(before["doc_id"], before["text"])))
    assert set(after["doc_id"]) == {d for d, (_, c) in label.items() if d == c}


def test_decontamination_stage_drops_documents_with_items(spark, stages):
    _, before, after = stages[2]
    items = [textnum.words([decontamination.plain(t)]).hash for t in spark.read.parquet(f"{SF}/benchmark.parquet").toPandas()["text"]]
    bad = set()
    for d, t in zip(before["doc_id"], before["text"]):
        h = textnum.words([decontamination.plain(t)]).hash
        if any(decontamination.near_subsequence(x, h)[0] >= 0.6 * len(x) for x in items):
            bad.add(d)
    assert set(after["doc_id"]) == set(before["doc_id"]) - bad


def test_secret_stage_masks_live_values_and_keeps_documents(stages):
    _, before, after = stages[3]
    owners = {}
    for s, t in zip(before["source"], before["text"]):
        for _, _, _, v in secrets.base_spans(t):
            owners.setdefault(v, set()).add(s)
    after = after.set_index("doc_id")
    assert set(after.index) == set(before["doc_id"])
    for d, t in zip(before["doc_id"], before["text"]):
        got = after.loc[d]
        assert got["n_chars"] == len(got["text"]) or got["text"] == t
        for _, _, _, v in secrets.base_spans(t):
            if len(owners[v]) < 3:
                assert v not in got["text"]
        if not secrets.base_spans(t) and not secrets.CANDIDATE.search(t):
            assert got["text"] == t


def test_packing_stage_holds_every_token_once(stages):
    tokenizers = pytest.importorskip("tokenizers")
    public = pytest.importorskip("public_tokenizers")
    tok = tokenizers.Tokenizer.from_file(str(public.path("word_bpe_49k.json")))
    _, before, after = stages[4]
    want = {}
    for d, t in zip(before["doc_id"], before["text"]):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        for k, at in enumerate(range(0, len(ids), 4096)):
            want[d, k] = (at, len(ids[at : at + 4096]), zlib.crc32(ids[at : at + 4096].tobytes()))
    assert {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in after.itertuples()} == want
    for _, part in after.groupby("sequence_id"):
        part = part.sort_values("offset")
        assert (part["offset"].to_numpy() == np.concatenate([[0], np.cumsum(part["length"])[:-1]])).all() and part["length"].sum() <= 4096
    assert after["sequence_id"].nunique() <= -(-after["length"].sum() // 4096) + 1


def test_run_is_the_chain_of_stages(spark, stages):
    got = cp.run(spark, SF).toPandas().sort_values(["doc_id", "piece"])
    last = stages[4][2].sort_values(["doc_id", "piece"])
    cols = ["doc_id", "piece", "start", "length", "ids_crc32"]
    pd.testing.assert_frame_equal(got[cols].reset_index(drop=True), last[cols].reset_index(drop=True))


CONTRACT = {
    "op1": ["vec_id", "n_links", "component_id", "kept"],
    "op2": ["doc_id", "n_bytes", "n_tokens", "over_limit"],
    "op3": ["doc_id", "n_shingles", "component_id", "kept"],
    "op5": ["doc_id", "held_out", "score", "predicted"],
    "op6": ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"],
    "op7": ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
    "op8": ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"],
    "op9": ["doc_id", "held_out", "lang_pred", "score"],
    "op10": ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"],
}


@pytest.mark.parametrize("name", sorted(CONTRACT))
def test_queries_return_their_columns_for_every_row(spark, name):
    key = next(k for k in queries() if k.startswith(f"{name}_"))
    df = queries()[key](spark, SF)
    assert df.columns == CONTRACT[name]
    table = {"op1": "embeddings", "op8": "pages"}.get(name, "documents")
    n = spark.read.parquet(f"{SF}/{table}.parquet").count()
    assert df.select(df.columns[0]).distinct().count() == n and (name == "op10" or df.count() == n)
