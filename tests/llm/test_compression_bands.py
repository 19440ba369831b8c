"""The verdict of the compression bands against a plain rule, and on labelled rows."""

import math
import random
from collections import Counter

import zstandard
from pyspark.sql import functions as F

from qacurate.llm import compression
from qacurate.llm.queries import LLM

SF = "/root/testdata/sf0.1"


def inside(text, bands=compression.BANDS):
    """Whether a text lies within the limits of its length, by the line through the two nearest lengths."""
    if len(text) < bands[0][0]:
        return True
    ratio = len(zstandard.ZstdCompressor(level=3).compress(text)) / len(text)
    below = [b for b in bands if b[0] <= len(text)][-1]
    above = next((b for b in bands if b[0] > len(text)), None)
    part = (math.log(len(text)) - math.log(below[0])) / (math.log(above[0]) - math.log(below[0])) if above else 0
    low, high = ((1 - part) * below[k] + part * (above or below)[k] for k in (1, 2))
    return low - 1e-12 <= ratio <= high + 1e-12


def kept_brute(text):
    words = text.split()
    runs = Counter(zip(words, words[1:], words[2:], strict=False))
    repeated = {j for i in range(len(words) - 2) if runs[tuple(words[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    if len(words) < 50 or 100 * len(repeated) > 50 * len(words):
        return False
    chunks = [text[i : i + 4096] for i in range(0, len(text), 4096)]
    bad = sum(len(c) for c in chunks if not inside(c)) if len(text) > 4096 else 0
    return inside(text) and bad < 0.3 * len(text)


def test_verdict_by_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    texts = {r.doc_id: (r.text or "").encode() for r in docs.collect()}
    got = {r.doc_id: r for r in LLM.queries["op7_compression_bands"](spark, "/root/testdata/sf0.01").collect()}
    assert {i: r.kept for i, r in got.items()} == {i: kept_brute(t) for i, t in texts.items()}
    assert any(not r.kept and not r.base_failed for r in got.values())


def test_bands_reject_bad_and_keep_good(spark):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    rows = LLM.queries["op7_compression_bands"](spark, SF).join(labels, "doc_id").where("not base_failed").groupBy("quality", "kept").count().collect()
    n = Counter({(r.quality, r.kept): r["count"] for r in rows})
    assert n[1, False] == 0
    assert n[0, False] > 0.3 * (n[0, False] + n[0, True])


def test_parts_of_noise_count(spark):
    rng = random.Random(2)
    good = spark.read.parquet(f"{SF}/documents.parquet").join(spark.read.parquet(f"{SF}/labels.parquet"), "doc_id").where("quality = 1 and n_chars between 12000 and 20000").orderBy("doc_id")
    prose = good.first().text
    noise = " ".join("".join(chr(rng.randrange(33, 127)) for _ in range(40)) for _ in range(len(prose) // 80))
    rows = [(1, prose), (2, prose + "\n" + noise), (None, prose), (None, None), (1, prose), (4, ""), (5, prose * 40)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumns({c: F.lit(3) for c in ("n_words", "ratio", "kept")})
    got = Counter((r.doc_id, r.kept) for r in compression.compression_bands(df).collect())
    assert got == Counter({(1, True): 2, (None, True): 1, (None, False): 1, (2, False): 1, (4, False): 1, (5, False): 1})
