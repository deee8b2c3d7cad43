"""Layout of the token files: row groups, encodings, page indexes, and reads that leave the token pages alone."""

import glob

import numpy as np
import pyarrow.parquet as pq

from sightline.llm import token_files
from sightline.llm.queries import BYTE_BPE


def test_row_groups_encodings_and_indexes(spark, tmp_path):
    rng = np.random.default_rng(3)
    words = [f"word{i}" for i in range(4000)]
    docs = spark.createDataFrame([(i, " ".join(rng.choice(words, 400)), "x") for i in range(1500)], "doc_id long, text string, tokens string")
    target = str(tmp_path / "files")
    token_files.write_token_files(docs, BYTE_BPE(), target, shards=2, row_group_bytes=400_000, page_bytes=64_000)
    files = sorted(glob.glob(f"{target}/*.parquet"))
    assert len(files) == 2
    for f in files:
        meta = pq.ParquetFile(f).metadata
        assert meta.num_row_groups > 1
        for g in range(meta.num_row_groups):
            columns = {meta.row_group(g).column(i).path_in_schema: meta.row_group(g).column(i) for i in range(meta.num_columns)}
            tokens = next(c for name, c in columns.items() if name.startswith("tokens"))
            assert tokens.compression == "ZSTD" and set(tokens.encodings) & {"RLE_DICTIONARY", "DELTA_BINARY_PACKED"}
            assert all(c.has_offset_index and c.has_column_index for c in columns.values() if not c.path_in_schema.startswith("tokens")) and tokens.has_offset_index
        ids = pq.read_table(f, columns=["doc_id"])["doc_id"].to_pylist()
        assert ids == sorted(ids)
    plan = token_files.read_token_files(spark, target, tokens=False).where("doc_id = 7")._jdf.queryExecution().executedPlan().toString()
    assert "tokens:array" not in plan and "ReadSchema" in plan and "EqualTo(doc_id,7)" in plan


def test_empty_table_and_odd_rows(spark, tmp_path):
    kind = "doc_id long, text string"
    token_files.write_token_files(spark.createDataFrame([], kind), BYTE_BPE(), str(tmp_path / "none"), shards=2)
    assert spark.read.parquet(str(tmp_path / "none")).count() == 0
    token_files.write_token_files(spark.createDataFrame([(None, "a b"), (2, None), (2, "c"), (1, "")], kind), BYTE_BPE(), str(tmp_path / "odd"), shards=3)
    got = [(r.start, r.doc_id, r.n_tokens) for r in token_files.verified(token_files.read_token_files(spark, str(tmp_path / "odd"))).orderBy("start").collect()]
    assert [r[1] for r in got] == [None, 1, 2, 2] and [r[0] for r in got] == np.concatenate([[0], np.cumsum([r[2] for r in got])[:-1]]).tolist()


def test_pieces_in_a_row_are_cut_as_alone(monkeypatch):
    from sightline.llm.bpe import newer_of

    own = token_files.LibraryEncoder(BYTE_BPE(), newer_of(BYTE_BPE()))
    plain = [" the", " straße", " Überlängen", " naïveté", " x", " слово", " antidisestablishmentarianism"]
    row, each = own._in_a_row(plain), own._each(plain)
    assert row[0].tolist() == each[0].tolist() and row[1].tolist() == each[1].tolist() and len(own._in_a_row([])[0]) == 0
    monkeypatch.setattr(own, "_each", lambda pieces: 1 / 0 if any(p in plain for p in pieces) else each_of(pieces))
    each_of = type(own)._each.__get__(own)
    text = "".join(plain) + " 12, end"
    assert np.frombuffer(own.encode([text])[0], "<u4").tolist() == own.library.encode(text, add_special_tokens=False).ids
    assert token_files._CACHE_ROWS >= 400_000
