import numpy as np
import pytest

from spark_nlops.llm import bpe
from spark_nlops.llm import token_scan as T
from spark_nlops.llm.common import Stage


def blocks_of(spark, files, size):
    rows = []
    for name, tokens in files.items():
        data = np.array(tokens, dtype=T.DTYPE)
        rows += [(name, b, data[b * size : (b + 1) * size].tobytes()) for b in range(-(-len(data) // size))]
    return spark.createDataFrame(rows, "file string, block long, data binary")


def slow(files, eod):
    out = []
    for name, tokens in files.items():
        n = k = 0
        for t in tokens:
            if t == eod:
                out.append((name, k, n, True))
                n, k = 0, k + 1
            else:
                n += 1
        if n:
            out.append((name, k, n, False))
    return sorted(out)


@pytest.mark.parametrize("size", [1, 3, 16, 1000])
def test_scan_against_loops(spark, size):
    rng = np.random.default_rng(size)
    files = {f"f{i}": np.where(rng.random(200) < p, 9, rng.integers(0, 9, 200)).tolist() for i, p in enumerate((0.0, 0.02, 0.3, 1.0))}
    files |= {"one": [9], "open": [1, 2, 3], "ends": [1, 9]}
    got = T.stitch(T.scan_blocks(blocks_of(spark, files, size), eod=9)).collect()
    assert sorted((r.file, r.ordinal, r.n_tokens, r.terminated) for r in got) == slow(files, 9)


def test_whole_table(spark, sf01):
    counts = {r.doc_id: r.n_tokens for r in bpe.op2_byte_bpe(spark, sf01).collect()}
    got = T.op4_token_counts(spark, sf01).collect()
    assert len(got) == len(counts)
    assert {r.doc_id: r.n_tokens for r in got} == counts and all(r.terminated for r in got)


def test_flat_files_and_edges(spark, tmp_path):
    (tmp_path / "a.bin").write_bytes(np.array([5, 6, 9, 9, 7], dtype=T.DTYPE).tobytes())
    (tmp_path / "b.bin").write_bytes(b"")
    blocks = T.read_flat_files(spark, str(tmp_path), block_tokens=2)
    got = sorted((r.ordinal, r.n_tokens, r.terminated) for r in T.stitch(T.scan_blocks(blocks, eod=9)).collect())
    assert got == [(0, 2, True), (1, 0, True), (2, 1, False)]
    df = spark.createDataFrame([(None, "x y"), (1, None), (1, ""), (2, "word " * 30_000)], "doc_id long, text string")
    files = Stage(spark, "test").keep(T.write_token_files(df, block_tokens=64), "files")
    found = T.stitch(T.scan_blocks(files.filter("data IS NOT NULL"))).collect()
    assert sorted(r.n_tokens for r in found) == sorted([2, 0, 0, len(bpe.Codec(bpe.vocabulary_bytes(bpe.default_vocabulary()[0]), bpe.default_vocabulary()[1]).encode("word " * 30_000))])
    empty = T.write_token_files(df.limit(0))
    assert T.stitch(T.scan_blocks(empty.filter("data IS NOT NULL"))).count() == 0
