import zlib

import numpy as np
import pyarrow as pa
import pytest

from hazemedian.llm import langid, toxicity

SF = "/root/testdata/sf0.01"


def out(d):
    return zlib.crc32(str(d).encode()) % 5 == 0


def test_toxicity_on_held_out_documents(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    rows = toxicity.toxicity(docs, labels).join(labels, "doc_id").collect()
    held = [r for r in rows if r["held_out"]]
    assert all(r["held_out"] == out(r["doc_id"]) for r in rows)
    assert sum(r["predicted"] != r["toxic"] for r in held) <= 0.06 * len(held)
    assert sum(r["predicted"] and not r["toxic"] for r in held) <= 1


def test_toxicity_of_hard_rows(spark, frame):
    rows = [(k, f"calm words here {k}") for k in range(40)] + [(100 + k, f"you utter nincompoop {k}") for k in range(40)] + [(200, None), (201, ""), (None, "you nincompoop"), (300, "nincompoop " * 20_000)]
    labels = spark.createDataFrame([(d, int(d >= 100)) for d, _ in rows if d is not None and d < 200] + [(1, None), (None, 1)], "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity.toxicity(frame(rows), labels).collect()}
    assert got[300]["predicted"] == 1 and got[5]["predicted"] == 0 and 0 <= got[200]["score"] <= 1 and got[200]["score"] == got[201]["score"]
    assert got[None]["held_out"] is False
    none = spark.createDataFrame([], "doc_id long, toxic int")
    assert {r["score"] for r in toxicity.toxicity(frame(rows), none).collect()} == {0.0}
    assert toxicity.toxicity(frame([]), labels).count() == 0


def test_grams_are_of_characters_and_rows(spark):
    rows, features = toxicity.grams(pa.array(["äbcde", None, "ÄBCDE äbcde", ""], pa.string()))
    one, two = set(features[rows == 0]), set(features[rows == 2])
    assert one and one & two and not set(rows) & {1, 3}
    again = toxicity.grams(pa.array(["äbcde"], pa.string()))[1]
    assert set(again) == one


def test_language_on_held_out_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = langid.languages(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r["held_out"]]
    assert sum(r["lang_pred"] == r["lang"] for r in held) >= 0.98 * len(held)


def test_language_of_hard_rows(spark, frame):
    df = frame([(k, "the cat and the dog went home") for k in range(30)]).union(frame([(100 + k, "der hund und die katze gingen heim") for k in range(30)], lang="de"))
    hard = frame([(500, None), (501, ""), (502, "123 ½ !!!"), (503, "DER HUND"), (504, "katzen hunde heimgehen"), (505, "日本"), (None, "the dog")], lang=None)
    got = {r["doc_id"]: r for r in langid.languages(df.union(hard)).collect()}
    assert [got[k]["lang_pred"] for k in (500, 501, 502)] == ["und"] * 3 and got[500]["score"] == 0
    assert got[503]["lang_pred"] == "de" and got[504]["lang_pred"] == "de" and got[505]["lang_pred"] in ("de", "en") and got[None]["lang_pred"] == "en"
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert langid.languages(frame([])).count() == 0


def test_back_off_uses_the_longest_known_grams():
    model = langid.fit(["alpha alpha beta beta"] * 3 + ["gamma gamma delta delta"] * 3, ["a"] * 3 + ["b"] * 3)
    scorer = langid.Scorer(model)
    assert scorer(["alphas"])[0] == ["a"] and scorer(["gammas"])[0] == ["b"]
    known, table = model["grams"][4]
    want = table[[known.index(x) for x in langid.grams_of("alphas", 5) if x in known]].mean(0)
    assert np.allclose(scorer.back_off("alphas"), want)
    assert scorer.back_off("zzz") == pytest.approx([0, 0])
