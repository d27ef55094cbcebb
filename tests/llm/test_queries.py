"""The registered queries run on whole tables, with SQL where there is some; the pipeline's stages do what they say."""

import ast
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

import __spark_entry__
import corpus_pipeline
from shapebalance.llm import pii, quality, queries, toxicity
from tests.conftest import SF, plain
from tests.llm.test_operators import PII, brute_components, brute_spans


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_matches_sql(spark, duck, name):
    assert plain(queries.queries()[name](spark, SF).toPandas()) == plain(duck.execute(queries.oracle_sql()[name]).df())


def test_registered():
    names = __spark_entry__.queries()
    assert "pipeline" in names and {f"op{i}" for i in range(1, 11)} == {n.split("_")[0] for n in names if n.startswith("op")}


def test_pipeline_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        new = stage(spark, docs, SF).persist()
        assert new.columns == docs.columns
        before, after = {r["doc_id"] for r in docs.select("doc_id").collect()}, {r["doc_id"] for r in new.select("doc_id").collect()}
        assert after <= before
        kept[name], docs = len(after), new
    assert kept["pii"] == kept["near_dedup"]
    left = [pii.find_personal(r["text"]) for r in docs.select("text").collect()]
    assert not any(left)
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).select("doc_id").distinct().count() == kept["pii"]


def test_stages_on_edge_rows(spark):
    """Nulls in any column, empty and long texts, repeated rows, clashing column names, an empty table: each stage keeps its columns and says what it does."""
    long = " ".join(f"word{i % 977}" for i in range(200_000))
    rows = [(0, None, None, None, None), (1, "", "en", "s", 0), (2, long, "en", "s", len(long)), (2, long, "en", "s", len(long)), (None, "a b c d e f", "en", None, 11), (3, "write to a@b.co or a@b.co", "en", "s", None)]
    docs = spark.createDataFrame([(*r, 1, "k", 0.5) for r in rows], "doc_id long, text string, lang string, source string, n_chars long, component_id long, key string, score double")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns and out.count() <= len(rows)
        assert stage(spark, docs.where("false"), SF).count() == 0
        if name == "near_dedup":
            assert sorted(str(r["doc_id"]) for r in out.collect()) == ["0", "1", "2", "3", "None"]
        if name == "pii":
            assert out.where("doc_id = 3").first()["text"] == "write to [EMAIL] or [EMAIL]" and out.where("text IS NULL").count() == 1
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert pieces.where("doc_id = 1").first()["length"] == 1 and pieces.select("doc_id").distinct().count() == 5
    assert corpus_pipeline.STAGES[-1][1](spark, docs.where("false"), SF).count() == 0


def rejected(chain: toxicity.ToxicityChain, text: str) -> bool:
    """One text through the chain by its definition: each category from the features present and the probabilities before it."""
    places = {int(h): i for i, h in enumerate(chain.hashes)}
    present = {places[int(h)] for h in toxicity.token_hashes(pa.array([text]), chain.c.heads)[0] if int(h) in places}
    before: list[float] = []
    for model in chain.models:
        z = model.b + sum(model.w[i] for i in present) + sum(w * x for w, x in zip(model.w[model.n :], before, strict=True))
        before.append(1 / (1 + np.exp(-z)))
    return before[-1] >= chain.c.threshold


def good(machine: quality.FactorisationMachine, text: str) -> bool:
    """One text through the machine, every pair of features multiplied out."""
    _, ids, x = quality.features(pa.array([text]), machine.c)
    v = machine.v[ids].astype(float) * x[:, None]
    pairs = np.triu(v @ v.T, 1).sum()
    return 1 / (1 + np.exp(-(machine.w0 + (machine.w[ids].astype(float) * x).sum() + pairs))) >= machine.c.threshold


def test_pipeline_against_brute_force(spark):
    """Every stage's decisions, document by document in plain Python, against the rows of run()."""
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    chain, machine = toxicity.train_toxicity(docs, labels), quality.train_quality(docs, labels)
    rows = [(r["doc_id"], r["text"] or "") for r in docs.select("doc_id", "text").collect()]
    assert len({i for i, _ in rows}) == len(rows)
    clean = [r for r in rows if not rejected(chain, r[1])]
    fit = [r for r in clean if good(machine, r[1])]
    assert len(rows) > len(clean) > len(fit)
    alone = {d for d, _, _, kept in map(ast.literal_eval, brute_components(fit, 5)) if kept}
    left = {}
    for i, text in fit:
        if i in alone:
            left[i] = pii.redact(text)
            assert not brute_spans(left[i], PII)
    encode = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")).encode
    ids = {i: np.array([*encode(t, add_special_tokens=False).ids, 1], "<u4") for i, t in left.items()}
    got, seen, places = corpus_pipeline.run(spark, SF).collect(), {}, {}
    for r in got:
        own = ids[r["doc_id"]]
        assert r["doc_tokens"] == len(own) and r["ids_crc32"] == zlib.crc32(own[r["start"] : r["start"] + r["length"]].tobytes())
        seen.setdefault(r["doc_id"], []).append((r["start"], r["length"]))
        places.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert seen.keys() == ids.keys()
    for pieces, full in [*((p, len(ids[i])) for i, p in seen.items()), *((p, None) for p in places.values())]:
        pieces.sort()
        ends = np.cumsum([0, *[n for _, n in pieces]]).tolist()
        assert [at for at, _ in pieces] == ends[:-1] and (ends[-1] == full if full is not None else ends[-1] <= 2048)
