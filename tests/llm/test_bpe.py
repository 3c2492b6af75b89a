import hashlib
import random

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from manifold_engine.llm import bpe as B

PATH = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def _want(library, rows):
    out = []
    for d, t in rows:
        ids = library.encode(t or "", add_special_tokens=False).ids
        out.append((d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    return sorted(out)


ODD = ["", None, "a<|endoftext|>b", "<|endoftext|><|endoftext|>", "  two  spaces \n\n x", "I'll we've 'S 'sx", " 　x​ \t\r\n", "日本語 ñandú éêè 123４５ x²", "\U0001f600\U0001f468‍\U0001f469", "aaaaaaaaaaaaaaaaaaaa" * 50, "\x00\x01\x1c\x1d\x85 a", "=" * 3000, "é ö", " " * 500, " a  b"]


def test_library_equality(spark, sf, library):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    rows += [(100000 + i, t) for i, t in enumerate(ODD)] + [(100000, "")]
    rng = random.Random(3)
    pool = "ab '\n\té中1<|>. \U0001f600stre"
    rows += [(200000 + i, "".join(rng.choice(pool) for _ in range(rng.randrange(80)))) for i in range(400)]
    got = sorted(tuple(r) for r in B.round_trip(spark.createDataFrame(rows, "doc_id long, text string"), PATH).collect())
    assert got == _want(library, rows)


def test_columns(spark):
    df = spark.createDataFrame([(1, "hello there", "x"), (2, None, "y")], "doc_id long, text string, ids string")
    back = B.decode(B.encode(df, PATH), PATH)
    assert [r.decoded for r in back.orderBy("doc_id").collect()] == ["hello there", ""]
    assert B.round_trip(df.limit(0), PATH).count() == 0


def test_very_long_texts(spark, library):
    """Megabytes in one text, and one pre-token of half a million characters."""
    rng = random.Random(8)
    rows = [(1, " ".join(rng.choice(("alpha", "beta", "gamma,", "x1")) for _ in range(400_000))), (2, "".join(rng.choice("abcde") for _ in range(500_000))), (3, "=-" * 300_000), (4, None)]
    got = sorted(tuple(r) for r in B.round_trip(spark.createDataFrame(rows, "doc_id long, text string"), PATH).collect())
    assert got == _want(library, rows)
