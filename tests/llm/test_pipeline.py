"""Each stage of the pipeline against plain Python over the stage's own input, on whole tables."""

import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from layercut.llm import packing, registry, secrets, toxicity
from test_operators import components, spans_of, targets_by_hand


def rows_of(df):
    return [tuple(r) for r in df.collect()]


@pytest.fixture(scope="module")
def staged(spark, tmp_path_factory):
    """(name, input, output) of each stage, written and read again."""
    sf, root, out = "/root/testdata/sf0.001", tmp_path_factory.mktemp("stages"), []
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, sf).write.parquet(str(root / name))
        made = spark.read.parquet(str(root / name))
        out.append((name, docs, made))
        docs = made
    return {name: (before, after) for name, before, after in out}


def test_stages_keep_the_columns(staged):
    assert [n for n, _ in corpus_pipeline.STAGES] == list(staged) == ["toxicity", "near_duplicates", "secrets", "mixing", "packing"]
    for name in list(staged)[:-1]:
        before, after = staged[name]
        assert after.columns == before.columns and after.count() > 0


def test_toxicity_stage(spark, staged):
    before, after = staged["toxicity"]
    scorer = toxicity.train(before, spark.read.parquet("/root/testdata/sf0.001/labels.parquet"))
    at = before.columns.index("text")
    assert sorted(rows_of(after), key=str) == sorted((r for r in rows_of(before) if scorer.score(r[at]) < toxicity.THRESHOLD), key=str)


def test_near_duplicate_stage(staged):
    before, after = staged["near_duplicates"]
    rows = rows_of(before.select("doc_id", "text"))
    first = {i: c for i, (_, c) in components(rows).items()}
    assert sorted(r[0] for r in rows_of(after.select("doc_id"))) == sorted(i for i, _ in rows if first[i] == i)
    assert set(rows_of(after)) <= set(rows_of(before))


def test_secret_stage(staged):
    before, after = staged["secrets"]
    texts = dict(rows_of(after.select("doc_id", "text")))
    assert len(texts) == before.count() == after.count()
    for i, text in rows_of(before.select("doc_id", "text")):
        found = sorted(tuple(int(x) for x in s.split(":")[1:]) for s in spans_of(text).split(",") if s)
        want, end = [], 0
        for a, b in found:
            if a >= end:
                want += [text[end:a], "[secret]"]
            end = max(end, b)
        assert texts[i] == ("".join([*want, text[end:]]) if found else text)
    assert all(not r["secret_spans"] for r in secrets.scan(after, secrets.BASE).collect())


def test_mixing_stage(staged):
    before, after = staged["mixing"]
    size = lambda t: len(re.findall("[^\x20\x09-\x0d]+", t or ""))
    held, most, taken, whole = {}, {}, {}, {}
    for i, text, source in rows_of(before.select("doc_id", "text", "source")):
        held[i] = (source, size(text))
        whole[source], most[source] = whole.get(source, 0) + size(text), max(most.get(source, 0), size(text))
    copies = {}
    for i, text, source in rows_of(after.select("doc_id", "text", "source")):
        assert held[i] == (source, size(text))
        copies[i], taken[source] = copies.get(i, 0) + 1, taken.get(source, 0) + size(text)
    assert max(copies.values()) <= 3
    for source, target in targets_by_hand(whole).items():
        assert abs(taken.get(source, 0) - target) <= most[source]


def test_packing_stage(staged):
    before, after = staged["packing"]
    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = {}
    for i, text in rows_of(before.select("doc_id", "text")):  # repeats of a document have the same ids
        want[i] = [*t.encode(text or "", add_special_tokens=False).ids, 2]
    got = after.toPandas()
    assert set(got.columns) == {"doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"}
    for r in got.itertuples():
        assert zlib.crc32(np.array(want[r.doc_id][r.start : r.start + r.length], dtype="<u4").tobytes()) == r.ids_crc32
    total = sum(len(want[i]) for (i,) in rows_of(before.select("doc_id")))
    assert got["length"].sum() == total
    for _, s in got.groupby("sequence_id"):
        s = s.sort_values("offset")
        assert s["length"].sum() <= 1024 and (s["offset"].to_numpy() == np.append(0, s["length"].cumsum()[:-1])).all()
    assert got["sequence_id"].nunique() <= -(-total // 1024) + 2


def test_run_and_empty_tables(spark, staged, tmp_path):
    out = corpus_pipeline.run(spark, "/root/testdata/sf0.001")
    assert out.count() == staged["packing"][1].count()
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    docs.limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    spark.read.parquet("/root/testdata/sf0.001/labels.parquet").write.parquet(str(tmp_path / "labels.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_ids_of_a_table_equal_the_library(spark):
    """packing's own encoder against the tokenizers library on whole texts of every kind in sf0.01."""
    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    encode = packing.default_encoder()
    for (text,) in rows_of(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("text")):
        assert list(encode(text or "")) == t.encode(text or "", add_special_tokens=False).ids


def test_ten_operators_are_registered():
    assert [n for n in range(1, 11) if not any(q.startswith(f"op{n}_") for q in registry.queries())] == []
