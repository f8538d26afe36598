import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from hazemedian.llm.token_files import EliasFano, read_documents, read_token_files, token_file_digests, write_token_files
from hazemedian.llm.tokens import PieceEncoder, count_tokens, vocabulary_path

from .conftest import HARD

LIBRARY = Tokenizer.from_file(vocabulary_path())
COUNTS, IDS = PieceEncoder(vocabulary_path(), False), PieceEncoder(vocabulary_path(), True)
TRICKY = ["don't stop, I'm 3rd. <|endoftext|> yes<|endoftext|>no <|endoftext|>", "a  b\n\nc", " lead", "trail ", "x\n", "a.\nb! c? d;", "it's, we'll. 's", "nb sp a", "é è, ü.", "a\r\nb c", "été, a\u00a0 b\u2009 c × d×, ÿ! e\x1c f” g", "x<|endoftext|>y, <|endoftext|> z.", "%%% $$$a.", "  x"]


def whole(text):
    return LIBRARY.encode(text, add_special_tokens=False).ids


def check(text):
    column = pa.array([text, "", None, text], pa.string())
    assert COUNTS(column)[0].tolist() == [len(whole(text)), 0, 0, len(whole(text))]
    assert IDS(column)[1].tolist() == 2 * whole(text)


@pytest.mark.parametrize("text", TRICKY + [t or "" for _, t in HARD])
def test_pieces_equal_whole_text(text):
    check(text)


@settings(max_examples=600, deadline=None)
@given(st.text(alphabet="ab Z\n\t\u00a0\u2003\u0085”ñ×.,'!1é日 <|>s", max_size=60))
def test_pieces_equal_whole_text_at_random(text):
    check(text)


def test_counts_by_row(frame):
    got = {r["doc_id"]: r for r in count_tokens(frame([*HARD, (None, "no id"), (6, "word")])).collect() if r["doc_id"]}
    for d, t in HARD:
        assert (got[d]["n_bytes"], got[d]["n_tokens"]) == (len((t or "").encode()), len(whole(t or "")))
        assert got[d]["over_limit"] == (got[d]["n_tokens"] > 512)
    assert count_tokens(frame([])).count() == 0


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 5000), max_size=60))
def test_elias_fano_round_trip(values):
    values = sorted(values)
    code = EliasFano.from_bytes(EliasFano.encode(np.array(values, np.uint64)).to_bytes())
    assert code.values().tolist() == values
    assert [code.select(k) for k in range(len(values))] == values
    assert all(code.place_of(v) == values.index(v) for v in values) and code.place_of(9999) == len(values)


def test_select_over_long_gaps():
    values = np.cumsum(np.r_[np.ones(700, int), 10**7, np.ones(700, int), 5 * 10**6])
    code = EliasFano.from_bytes(EliasFano.encode(values).to_bytes())
    assert [code.select(k) for k in range(len(values))] == values.tolist() == code.values().tolist()


def test_elias_fano_is_small():
    bounds = np.cumsum(np.random.default_rng(1).integers(1, 2000, 20_000))
    assert len(EliasFano.encode(bounds).to_bytes()) < 20_000 * 13 / 8 + 64


def test_files_hold_all_documents_in_order(spark, frame, tmp_path):
    rows = [(d * 7 % 101, "w " * random.Random(d).randint(0, 30)) for d in range(100)] + [(1000 + d, t) for d, t in HARD]
    write_token_files(frame(rows), str(tmp_path / "t"))
    got = read_token_files(spark, str(tmp_path / "t")).orderBy("doc_id").collect()
    start = 0
    for (d, t), r in zip(sorted(rows, key=lambda x: x[0]), got, strict=True):
        ids = [*whole(t or ""), 2]
        assert (r["doc_id"], r["start"], r["n_tokens"]) == (d, start, len(ids))
        assert np.frombuffer(r["ids"], "<u4").tolist() == ids
        start += len(ids)
    some = [rows[3][0], 1007, 50_000, -4]
    assert {r["doc_id"]: np.frombuffer(r["ids"], "<u4").tolist() for r in read_documents(spark, str(tmp_path / "t"), some).collect()} == {d: [*whole(t or ""), 2] for d, t in rows if d in some}


def test_files_of_null_negative_and_repeated_ids(spark, frame, tmp_path):
    rows = [(None, "a b"), (None, None), (-(2**62), "low"), (2**62, "high"), (5, "x"), (5, "x"), (5, "y z")]
    write_token_files(frame(rows), str(tmp_path / "t"))
    got = read_token_files(spark, str(tmp_path / "t")).collect()
    assert sorted(r["n_tokens"] for r in got) == sorted(len(whole(t or "")) + 1 for _, t in rows)
    assert sorted(r["doc_id"] for r in got)[-5:] == [-(2**62), 5, 5, 5, 2**62]
    assert read_documents(spark, str(tmp_path / "t"), [5]).count() == 3 and read_documents(spark, str(tmp_path / "t"), []).count() == 0


def test_digests(frame):
    got = {r["doc_id"]: r["ids_crc32"] for r in token_file_digests(frame(HARD)).collect()}
    for d, t in HARD:
        assert got[d] == zlib.crc32(np.array([*whole(t or ""), 2], "<u4").tobytes())
    assert token_file_digests(frame([])).count() == 0
