"""Recipes without tables of texts: ids, hashes and verdicts are those of the operators that read the texts."""

import os

import numpy as np
from pyspark.sql import functions as F

from qacurate.functions.text import n_tokens, shingles
from qacurate.operators import extract, ingest, lines, minhash, refine
from qacurate.plans.recipe import Recipe, leaked, run_textbook, textbook_marks
from qacurate.queries.common import recipe_books
from qacurate.queries.decontam import items
from qacurate.staging import Staged, stage

ODD = [
    (1, "Why is it so that one two three. \n\nIt is so because it is so and then. It ends here!\nSee Page 5 of it and of what follows it  now\ttoo?"),
    (2, "   \n  "),
    (3, None),
    (4, "one two three four five six\r\nseven eight nine ten eleven twelve.\nÄrger über öde Straßen (see figure 3) und mehr, page 7 contradicts\n" + "go. " * 300 + "\n" + "one 2 three " * 9),
    (5, " ".join(f"w{i}" for i in range(5000)) + "\nlast line of many words is here\nand one more line of words!  "),
]


def odd(spark):
    books = spark.createDataFrame(ODD, "book_id long, text string").withColumn("subjects", F.array(F.lit("physics")))
    return ingest.chunk(books)


def given(spark, sf):
    return ingest.chunk(recipe_books(spark, sf).select("book_id", "subjects", "text"))


def test_lines_are_the_pairs_of_extraction(spark, sf):
    for chunks in (odd(spark), given(spark, sf)):
        texts = chunks.toArrow().combine_chunks()
        book, chunk = texts.column("book_id").to_pylist(), texts.column("chunk_no").to_pylist()
        got = {(f"{book[r]}:{chunk[r]}:{line}:{name}", q, a) for r, line, name, q, a in lines.pairs_of(texts.column("text").combine_chunks(), lines.rules("dual"))}
        assert got == {(r.qid, r.question, r.answer) for r in extract.extract_dual(chunks).collect()} and got


def test_bands_are_those_of_the_signature(spark):
    sets = spark.createDataFrame([(1, "a b c d e f g"), (2, "a b c d e f h"), (3, "x y z"), (4, "")], "id long, text string").select("id", shingles("text").alias("set"))
    asked = sets.select("id", F.transform("set", lambda w: F.conv(F.substring(F.md5(w), 1, 16), 16, -10).cast("long")).alias("hset"))

    def equal(rows):
        return {(a.id, b.id, a.band) for a in rows for b in rows if a.id < b.id and (a.band, a.key) == (b.band, b.key)}

    parts = [*lines.band_rows(asked, 0, 8).collect(), *lines.band_rows(asked, 8, 32).collect()]
    assert len(parts) == 96 and equal(parts) == equal(minhash.lsh_bands(minhash.minhash(sets)).collect())


def test_verdicts_are_those_of_the_operators(spark, sf):
    pool = items(spark, sf)
    for chunks in (odd(spark), given(spark, sf)):
        chunks = stage(chunks, "chunks")
        pairs = stage(extract.extract_dual(chunks), "pairs")
        recipes = [Recipe(), Recipe(supplement=False), Recipe(refine=False, supplement=False), Recipe(strength="weak")]
        found = stage(lines.verdicts(chunks, pool, recipes), "verdicts")
        for i, r in enumerate(recipes):
            made = refine.refine(pairs, chunks, r.strength) if r.refine else pairs
            made = refine.supplement(refine.flag_missing_reasoning(made)) if r.supplement else made
            want = made.select("qid", (F.size(refine.defects()) == 0).alias("sound"), n_tokens("answer").alias("words"), refine.missing_reasoning().alias("lacks"))
            leaks = {x.qid for x in leaked(made, pool).collect()}
            assert {(x.qid, x.sound, x.words, x.lacks, x.qid in leaks) for x in want.collect()} == {(x.qid, x.sound, x.words, x.lacks, x.leak) for x in found.select("qid", f"m{i}.*").collect()}


def test_marks_count_what_the_rows_are(spark, sf):
    chunks, pool = given(spark, sf), items(spark, sf)
    rows = run_textbook(recipe_books(spark, sf), chunks, pool)
    for (a, x), (b, y) in zip(rows, textbook_marks(chunks, pool), strict=True):
        assert a == b and sorted(map(tuple, x.select("qid", "subject").collect())) == sorted(map(tuple, y.collect()))


def test_no_signature_and_no_text_is_staged(spark, sf, monkeypatch):
    from qacurate.staging import Staged

    seen, init = [], Staged.__init__
    monkeypatch.setattr(Staged, "__init__", lambda self, df, name: (seen.append((name, set(df.columns))), init(self, df, name))[1])
    textbook_marks(given(spark, sf), items(spark, sf))
    assert seen and not any(columns & {"text", "question", "answer", "signature"} for _, columns in seen)


def test_large_buckets_keep_their_components(spark, sf):
    sets = stage(lines.question_lines(given(spark, sf)).select(F.col("id"), "hset").where(F.size("hset") > 0), "sets")
    banded = lines.band_rows(sets, 0, 32)
    want = minhash.components(minhash.verify(minhash.candidate_pairs(banded), sets).select("a", "b"))
    got = minhash.components(minhash.linking_edges(banded, sets, most=2))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_small_groups_lose_no_pair():
    rng = np.random.default_rng(3)
    sets = [rng.choice(60, rng.integers(1, 50), replace=False) for _ in range(300)]
    sets += [np.union1d(s[1:], [61]) for s in sets[:100]]
    g = np.sort(rng.integers(0, 60, len(sets)))
    fresh = rng.random(len(sets)) < 0.7
    bits = []
    for s in sets:
        width = max(64, 1 << (2 * len(s) - 1).bit_length())
        bits.append(np.packbits((np.bincount(s % width, minlength=width) & 1).astype(np.uint8), bitorder="little").tobytes())
    n = np.array([len(s) for s in sets])
    got = {(int(a), int(b)) for i, j in minhash._small_groups(g, n, bits, fresh, 0.5) for a, b in zip(i, j, strict=True)}
    want = set()
    for group in np.unique(g):
        rows = np.flatnonzero(g == group)
        for x, y in ((rows[fresh[rows]], None), (rows[fresh[rows]], rows[~fresh[rows]])):
            want |= {(int(min(a, b)), int(max(a, b))) for i, j in minhash._may_reach(n, bits, x, y, 0.5) for a, b in zip(i, j, strict=True)}
    assert got == want and got


def test_parts_of_bands_keep_all_components(spark, sf):
    made = lines.question_lines(given(spark, sf)).where(F.size("hset") > 0).groupBy("key").agg(F.first("hset").alias("hset"))
    sets = stage(made.select("hset", F.monotonically_increasing_id().alias("id")), "sets")
    banded = lines.band_rows(sets, 0, 32)
    want = sorted(map(tuple, minhash.components(minhash.verify(minhash.candidate_pairs(banded), sets).select("a", "b")).collect()))
    for most, wide in ((64, 1 << 14), (2, 1 << 14), (2, 4)):
        parts = (Staged(lines.band_rows(sets, k, k + 16), "some-bands") for k in (0, 16))
        assert sorted(map(tuple, minhash.components(minhash.linked(parts, sets, most=most, wide=wide, dense=True)).collect())) == want and want


def test_sets_of_ids_are_those_of_a_join(spark):
    sets = spark.createDataFrame([((p << 33) + k,) for p in range(3) for k in (0, 1, 7, 8, 32767, 32768, 32769, 70000)], "id long")
    ids = sets.where("id % 3 <> 1").union(sets.limit(2))
    assert sorted(minhash._only(sets, ids, True).collect()) == sorted(minhash._only(sets, ids, False).collect())


def test_bands_go_before_the_next_are_made(spark, sf, monkeypatch):
    seen, left, init = [], [], Staged.__init__

    def made(self, df, name):
        if name == "some-bands":
            left.append([n for n, x in seen if {"id", "band", "key"} <= set(x.schema.names) and os.path.exists(x.path.removeprefix("file://")) and n != "large-buckets"])
        init(self, df, name)
        seen.append((name, self))

    monkeypatch.setattr(Staged, "__init__", made)
    lines.kept_questions(lines.question_lines(given(spark, sf)))
    assert len(left) > 1 and not any(left)
    assert {n for n, x in seen if "hset" in x.schema.names} <= {"questions", "held-sets", "open-rows"}


def test_textbook_recipe_holds_sets_once(spark, sf, monkeypatch):
    seen, init = [], Staged.__init__
    monkeypatch.setattr(Staged, "__init__", lambda self, df, name: (init(self, df, name), seen.append((name, self)))[0])
    textbook_marks(given(spark, sf), items(spark, sf))
    held = [(name, x) for name, x in seen if "hset" in x.schema.names]
    assert held and {name for name, _ in held} <= {"questions", "held-sets", "open-rows"}
    assert not any(os.path.exists(x.path.removeprefix("file://")) for name, x in held if name == "questions")
