"""The ten operators against brute force, on small tables full of awkward rows."""

import base64
import bisect
import hashlib
import itertools
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from oracle import difference, spark_rows
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from qacurate.llm import compression, line_alignment, mixing, packing, quality_crf, radix_exact, simhash_cover, substring_cover, toxicity_chain, warc
from qacurate.llm.queries import LLM
from qacurate.staging import fresh_path

TOKENIZER = public_tokenizers.path("word_bpe_49k.json")
EXTRA = ("id", "fp", "rep", "h", "bucket", "grp", "digit", "rest", "node", "component", "keep_id", "name", "slot", "_id", "_slot", "_lines", "_removed", "score", "start", "a", "b", "g", "lines", "same", "first")


def awkward():
    """(doc_id, text, source): nulls, empties, copies, near copies, one hot source, long and repeated texts."""
    rng = random.Random(5)
    vocabulary = [f"w{i}" for i in range(400)] + ["Ünï", "é", "ß", "x.", "y,", "A-B"]
    rows = [(0, None, None), (1, "", "s1"), (2, "  \n\t ", None), (3, "one", "s1"), (4, "ONE", "s2"), (5, "a b c", "s1")]
    base = [rng.choice(vocabulary) for _ in range(300)]
    passage = " ".join(rng.choice(vocabulary) for _ in range(40))
    for i in range(10, 90):
        words = [rng.choice(vocabulary) for _ in range(rng.choice((5, 25, 60, 200)))]
        text = "".join(w + rng.choice((" ", " ", " ", "\n", "  ", "\t")) for w in words)
        if i % 4 == 0:
            text += "\n" + passage
        rows.append((i, text, "hot" if i % 3 else f"s{i % 5}"))
    for i in range(100, 130):
        words = list(base)
        words[i % 300] = "changed"
        rows.append((i, " ".join(words), "hot"))
    rows += [(i, "The same Text in every row of this group, " * 4, "hot") for i in range(200, 260)]
    rows += [(300, "word " * 20_000, "s1"), (301, "x" * 50_000, "s2"), (302, passage.upper(), "s2"), (303, passage + " " + passage, "s3")]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(awkward(), "doc_id long, text string, source string").withColumns({c: F.lit(7) for c in EXTRA}).repartition(5)


def words_of(text):
    return (text or "").encode().split()


def collected(df):
    return {r.doc_id: r for r in df.collect()}


# ---- 1 ----------------------------------------------------------------------------------------


@given(st.dictionaries(st.text("abcdef", min_size=1, max_size=2), st.floats(0.01, 100), min_size=1, max_size=12))
@settings(max_examples=40, deadline=None)
def test_schedule_never_lags_a_block(weights):
    period = 200
    shares = mixing.fractions(weights, period)
    assert sum(shares.values()) == period and min(shares.values()) >= 1
    done = Counter()
    for s, j, slot, release, deadline in mixing.schedule(shares, period):
        assert release <= slot < deadline and j == done[s]
        done[s] += 1
        for name, k in shares.items():
            assert abs(done[name] - (slot + 1) * k / period) < 1
    assert done == Counter(shares)


def test_mix_ranks_and_slots(spark, docs):
    rows = mixing.mix(docs, block=4, period=40).collect()
    assert sorted(r.doc_id for r in rows) == sorted(i for i, _, _ in awkward())
    by = defaultdict(list)
    for r in rows:
        by[r.source].append((r.block_no, r.in_block))
        assert r.release_slot <= r.slot < r.deadline_slot
    for got in by.values():
        assert sorted(got) == [(k // 4, k % 4) for k in range(len(got))]
    slots = defaultdict(set)
    for r in rows:
        slots[r.slot].add(r.source)
    assert all(len(s) == 1 for s in slots.values())
    mixed = mixing.interleave(docs, block=4)
    assert mixed.columns == docs.columns and Counter(r.doc_id for r in mixed.collect()) == Counter(i for i, _, _ in awkward())
    given_ = mixing.mix(docs, {"hot": 3.0, "s1": 1.0}, block=2).collect()
    assert len(given_) == len(rows)
    assert mixing.mix(docs.limit(0)).count() == 0
    assert mixing.mix(docs.union(docs.limit(3)).withColumn("doc_id", F.when(F.col("doc_id") != 3, F.col("doc_id")))).count() == len(rows) + 3


# ---- 2 ----------------------------------------------------------------------------------------


@given(st.binary(max_size=300), st.integers(1, 50))
@settings(max_examples=60, deadline=None)
def test_chunk_framing(body, size):
    assert warc.unframe(warc.frame(body, size)) == body


def pages(spark):
    rng = random.Random(2)
    texts = [None, "", "\r\n\r\n", "WARC/1.1\r\n\r\nx", "é" * 500, "a\r\n\r\n\r\n\r\nb\r\n"] + ["".join(rng.choice("abé\r\n <>") for _ in range(rng.choice((10, 400, 3000)))) for _ in range(30)]
    rows = [(i, f"http://h/{i}\r\nX: y", texts[i % len(texts)]) for i in range(90)]
    rows += [(None, None, "no id"), (None, "u", "no id"), (500, "u", "twice"), (500, "u", "twice"), (501, None, "twice")]
    return spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"first": F.lit(1), "sha": F.lit("x"), "payload": F.lit(2)})


def test_warc_round_trip(spark):
    df, path = pages(spark), fresh_path(spark, "warc-test")
    warc.write_warc(df, path, segment=300, chunk=64, per_file=40)
    got = warc.read_warc(spark, path).collect()
    rows = df.collect()
    low = {}
    for r in rows:
        p = (r.html or "").encode()
        low[p] = min((x for x in (low.get(p), r.page_id) if x is not None), default=None)
    want = Counter()
    for r in rows:
        p = (r.html or "").encode()
        revisit = low[p] is not None and r.page_id != low[p]
        want[r.page_id, len(p), base64.b32encode(hashlib.sha1(p).digest()).decode(), "revisit" if revisit else "response", low[p] if revisit else None, None if revisit else p] += 1
    assert Counter((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to, None if r.payload is None else bytes(r.payload)) for r in got) == want
    assert all(r.problem is None for r in got) and max(r.segments for r in got) > 5
    empty = fresh_path(spark, "warc-none")
    warc.write_warc(df.limit(0), empty)
    assert warc.read_warc(spark, empty).count() == 0


def test_damaged_segments_are_reported():
    parts = list(warc.records(1, "u", b"p" * 1000, "s", 0, None, 200, 100))
    read = []
    for k, p in enumerate(parts):
        head, _, block = p.partition(warc.END)
        fields = {a.strip().lower(): b.strip() for a, _, b in (x.partition(":") for x in head.decode().split("\r\n")[1:])}
        read.append((k + 1, fields, block))
    fields, block, problem = warc.assemble(read)
    assert problem is None and warc.unframe(block.partition(warc.END)[2]) == b"p" * 1000
    assert warc.assemble(read[:2] + read[3:])[2].startswith("segment numbers")
    assert warc.assemble(read[:-1])[2].startswith("total length")
    assert warc._decoded({"warc-type": "response", "warc-record-id": "x"}, b"HTTP\r\nTransfer-Encoding: chunked\r\n\r\nzz\r\n", 1, None, True)[8] is not None


# ---- 3 ----------------------------------------------------------------------------------------


def aligned_brute(rows, least, rare):
    """The rule again with plain loops."""
    table = {}
    for i, t, _ in rows:
        lines = [x.strip(" \t\x0b\x0c\r") for x in (t or "").split("\n")]
        lines = [x for x in lines if x]
        table[i] = ([xxhash.xxh64_intdigest(x.encode()) for x in lines], [len(x.encode().split()) for x in lines], t or "")
    first = {}
    for i in sorted(table):
        first.setdefault(table[i][2], i)
    gone = {i: set() for i in table}
    own = {}
    for i, (lines, words, text) in table.items():
        if first[text] != i and sum(words) >= least:
            gone[i] = set(range(len(lines)))
        else:
            own[i] = (lines, words)
    holders = defaultdict(set)
    for i, (lines, _) in own.items():
        for x in lines:
            holders[x].add(i)
    pairs = set()
    for ids in holders.values():
        ids = sorted(ids)
        pairs |= set(itertools.combinations(ids, 2)) if len(ids) <= rare else {(ids[0], j) for j in ids[1:]}
    for a, b in pairs:
        gone[b] |= set(line_alignment.cut_lines(own[a][0], own[b][0], own[b][1], least))
    return {i: sorted(g) for i, g in gone.items()}


def test_line_alignment(spark):
    rng = random.Random(9)
    pool = [" ".join(f"v{rng.randrange(50)}" for _ in range(rng.choice((3, 8, 15)))) for _ in range(25)] + [f"only {k} here and nowhere else at all" for k in range(200)]
    common = "a line of more than twenty words that very many of the documents have in the middle of their own text as it is"
    rows = [(i, "\n".join(rng.choice(pool[:25]) if rng.random() < 0.4 else rng.choice(pool[25:]) for _ in range(rng.randint(0, 14))) + ("\n" + common if i % 2 else ""), "s") for i in range(60)]
    rows += [(100 + k, rows[3][1], "s") for k in range(12)] + [(200, None, None), (201, "\n\n", "s"), (202, "  " + rows[7][1].replace("\n", " \r\n\n"), "s")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumns({c: F.lit(7) for c in EXTRA})
    got = collected(line_alignment.align_lines(df, 20, 4))
    want = aligned_brute(rows, 20, 4)
    assert {i: list(r.removed) for i, r in got.items()} == want
    assert sum(map(bool, want.values())) > 20 and got[200].n_lines == 0
    cleaned = collected(line_alignment.apply_cuts(df, line_alignment.align_lines(df, 20, 4)))
    for i, text, _ in rows:
        lines, k = [], 0
        for x in (text or "").split("\n"):
            blank = not x.strip(" \t\x0b\x0c\r")
            if blank or k not in want[i]:
                lines.append(x)
            k += not blank
        if text is not None:
            assert cleaned[i].text == "\n".join(lines)
    assert line_alignment.align_lines(df.limit(0)).count() == 0


@given(st.lists(st.integers(0, 6), max_size=14), st.lists(st.integers(0, 6), max_size=14))
@settings(max_examples=150, deadline=None)
def test_alignment_rises_and_matches(a, b):
    got = line_alignment.align(a, b)
    assert all(a[i] == b[j] for i, j in got)
    assert all(i < k and j < m for (i, j), (k, m) in zip(got, got[1:], strict=False))
    if a == b:
        assert len(got) == len(a)


# ---- 4 ----------------------------------------------------------------------------------------


def check_packed(rows, texts, window=2048):
    tok = Tokenizer.from_file(TOKENIZER)
    ids = [(i, np.append(np.array(e.ids, "<u4"), np.uint32(1)).astype("<u4")) for (i, _), e in zip(texts, tok.encode_batch([t or "" for _, t in texts], add_special_tokens=False), strict=True)]
    known = {i: x for i, x in ids}
    covered, sequences = defaultdict(list), defaultdict(list)
    for r in rows:
        w = known[r.doc_id]
        assert r.doc_tokens == len(w) and r.ids_crc32 == zlib.crc32(w[r.start : r.start + r.length].tobytes())
        covered[r.doc_id].append((r.start, r.length))
        sequences[r.sequence_id].append((r.offset, r.length))
    assert covered.keys() == known.keys()
    for i, parts in covered.items():
        at = 0
        for a, n in sorted(parts):
            assert a == at
            at += n
        assert at == len(known[i])
    padding = 0
    for parts in sequences.values():
        at = 0
        for a, n in sorted(parts):
            assert a == at and n > 0
            at += n
        assert at <= window
        padding += 0 if at & (at - 1) == 0 else window - at
    return padding


def test_packing_round_trip(docs):
    texts = [(i, t) for i, t, _ in awkward()]
    assert check_packed(packing.pack(docs, TOKENIZER).collect(), texts) == 0
    assert check_packed(packing.pack(docs, TOKENIZER, window=256, unit=8, block=4096).collect(), texts, 256) == 0
    with_ids = packing.pack(docs, TOKENIZER, with_ids=True).where("doc_id = 5").collect()
    assert [x for r in sorted(with_ids, key=lambda r: r.start) for x in r.ids][-1] == 1
    assert packing.pack(docs.limit(0), TOKENIZER).count() == 0


def test_words_have_the_ids_of_their_text():
    texts = ["Don't STOP, it's 12.5% of <|endoftext|> x<|startoftext|>", "l'eau é́ İstanbul ǅ  nbsp em 日本語 ½ a_b ... !! ,. x?!", "A\x1cB\x85C \x00 ﬁ ª Ⅷ", "", "<|ENDOFTEXT|> ok"]
    words = packing.WordIds(TOKENIZER, most=8)
    tok = Tokenizer.from_file(TOKENIZER)
    for _ in range(2):
        got = words.of([t.encode() for t in texts])
        assert [x.tolist() for x in got] == [tok.encode(t, add_special_tokens=False).ids for t in texts]


@given(st.lists(st.text(max_size=40), max_size=6))
@settings(max_examples=150, deadline=None)
def test_any_text_has_its_ids(texts):
    texts = [t.encode("utf-8", "ignore").decode() for t in texts]
    tok = Tokenizer.from_file(TOKENIZER)
    got = packing.WordIds(TOKENIZER).of([t.encode() for t in texts])
    assert [x.tolist() for x in got] == [tok.encode(t, add_special_tokens=False).ids for t in texts]


def test_least_squares():
    rng = np.random.default_rng(0)
    for _ in range(20):
        a, b = rng.random((8, 15)), rng.random(8) * 4 - 1
        x = packing.nnls(a, b)
        pull = a.T @ (b - a @ x)
        assert (x >= 0).all() and pull.max() < 1e-6 and abs(pull[x > 1e-9]).max(initial=0) < 1e-6


# ---- 5 ----------------------------------------------------------------------------------------


def test_marginals_by_enumeration():
    rng = np.random.default_rng(1)
    sizes = [3, 0, 1, 5, 2]
    bounds = np.concatenate([[0], np.cumsum(sizes)])
    emit, trans = rng.normal(size=(bounds[-1], 2)), rng.normal(size=(2, 2))
    prob, pairs = quality_crf.marginals(emit, trans, bounds)
    want, total = np.zeros_like(prob), np.zeros((2, 2))
    for a, b in zip(bounds, bounds[1:], strict=False):
        ways = list(itertools.product((0, 1), repeat=b - a))
        weights = np.array([np.exp(sum(emit[a + t, y] for t, y in enumerate(w)) + sum(trans[x, y] for x, y in zip(w, w[1:], strict=False))) for w in ways])
        for w, p in zip(ways, weights / weights.sum(), strict=True):
            for t, y in enumerate(w):
                want[a + t, y] += p
            for x, y in zip(w, w[1:], strict=False):
                total[x, y] += p
    assert np.allclose(prob, want) and np.allclose(pairs, total)


def test_quality_on_held_out_rows(spark, docs):
    sf = "/root/testdata/sf0.01"
    rows = LLM.queries["op5_quality_crf"](spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    assert len(rows) > 40 and sum(r.predicted == r.quality for r in rows) / len(rows) >= 0.95
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    model = quality_crf.fit(spark.read.parquet(f"{sf}/documents.parquet"), labels)
    got = quality_crf.score(docs, model).collect()
    assert Counter(r.doc_id for r in got) == Counter(i for i, _, _ in awkward()) and all(0 <= r.score <= 1 for r in got)
    kept = quality_crf.keep_good(docs, model)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {r.doc_id for r in got if r.predicted}
    assert quality_crf.fit(docs, labels.limit(0)) is None
    assert {r.score for r in quality_crf.score(docs, None).collect()} == {0.5}
    assert quality_crf.score(docs.limit(0), model).count() == 0


# ---- 6 ----------------------------------------------------------------------------------------


@pytest.mark.parametrize("bucket_bytes", [500, 8 << 20])
def test_substrings_by_brute_force(spark, docs, bucket_bytes):
    seen, want = set(), {}
    for i, text, _ in sorted(awkward()):
        words = words_of(text)
        gone = set()
        for k in range(len(words) - 19):
            key = tuple(words[k : k + 20])
            if key in seen:
                gone |= set(range(k, k + 20))
            seen.add(key)
        kept = b" ".join(w for k, w in enumerate(words) if k not in gone)
        want[i] = (len(words), len(gone), hashlib.sha256(kept).hexdigest())
    got = collected(substring_cover.remove_repeats(docs, bucket_bytes=bucket_bytes))
    assert {i: (r.n_words, r.n_removed, r.kept_sha256) for i, r in got.items()} == want
    assert all(sum(b - a for a, b in zip(r.cut_from, r.cut_to, strict=True)) == r.n_removed for r in got.values())
    assert sum(n > 0 for _, n, _ in want.values()) > 50


@pytest.mark.parametrize("period", [7, 13])
def test_covers(period):
    cover = substring_cover.COVERS[period]
    assert {(a - b) % period for a in cover for b in cover} == set(range(period))


def test_substring_edges(spark):
    rows = [(None, "a b " * 30), (5, "a b " * 30), (5, "a b " * 30), (None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = Counter((r.doc_id, r.n_words, r.n_removed) for r in substring_cover.remove_repeats(df).collect())
    assert got == Counter({(5, 60, 58): 2, (None, 60, 60): 1, (None, 0, 0): 1})
    assert substring_cover.remove_repeats(df.limit(0)).count() == 0


# ---- 7 ----------------------------------------------------------------------------------------


def test_compression_measures(docs):
    got = collected(compression.compression_bands(docs))
    for i, text, _ in awkward():
        t = text or ""
        words, r = words_of(text), got[i]
        runs = Counter(zip(words, words[1:], words[2:], strict=False))
        repeated = set()
        for k in range(len(words) - 2):
            if runs[words[k], words[k + 1], words[k + 2]] > 1:
                repeated |= {k, k + 1, k + 2}
        lines = [x for x in t.split("\n") if words_of(x)]
        assert (r.n_words, r.word_chars) == (len(words), sum(len(w.decode()) for w in words))
        assert r.n_symbols == sum(c in "#*$%&|<>" for c in t)
        assert r.n_dup_lines == sum(x in lines[:k] for k, x in enumerate(lines))
        assert r.n_repeat_words == len(repeated)
        assert r.base_failed == (len(words) < 50 or 100 * len(repeated) > 50 * len(words))
        assert not (r.base_failed and r.kept)
    assert not got[300].kept and not got[301].kept
    assert compression.compression_bands(docs.limit(0)).count() == 0


def test_compression_verdict_beyond_the_base_rules(spark):
    rng = random.Random(4)
    prose = " ".join("".join(rng.choice("etaoinshr") for _ in range(rng.randint(2, 9))) for _ in range(400))
    noise = " ".join(base64.b64encode(rng.randbytes(30)).decode() for _ in range(200))
    loops = " ".join(f"{k} aaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaa" for k in range(300))
    df = spark.createDataFrame([(1, prose), (2, noise), (3, loops)], "doc_id long, text string")
    got = collected(compression.compression_bands(df))
    assert got[1].kept and not got[2].kept and not got[3].kept
    assert not got[2].base_failed and not got[3].base_failed


# ---- 8 ----------------------------------------------------------------------------------------


def test_exact_classes(spark, docs):
    rows = [(i, t) for i, t, _ in awkward()] + [(400, "y" * 600), (401, "Y" * 600), (402, "y" * 601), (403, "y" * 64), (404, "y" * 64), (405, "y" * 512), (406, "y" * 512)]
    rows += [(i, "z" * 5000 + str(i % 2)) for i in range(500, 510)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumns({c: F.lit(7) for c in EXTRA}).repartition(7)
    lower = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    groups = defaultdict(list)
    for i, t in rows:
        groups[(t or "").translate(lower)].append(i)
    want = {i: (max(ids), len(ids), i == max(ids), hashlib.sha256(t.encode()).hexdigest()) for t, ids in groups.items() for i in ids}
    got = {i: (r.keep_id, r.group_size, r.kept, r.text_sha256) for i, r in collected(radix_exact.exact_classes(df)).items()}
    assert got == want
    assert {r.doc_id for r in radix_exact.drop_copies(df).collect()} == {i for i, w in want.items() if w[2]}
    nulls = spark.createDataFrame([(None, "a"), (None, "a"), (1, "A"), (1, "a"), (None, "b")], "doc_id long, text string")
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.kept) for r in radix_exact.exact_classes(nulls).collect()) == Counter({(None, 1, 4, False): 2, (1, 1, 4, True): 2, (None, None, 1, True): 1})
    assert radix_exact.exact_classes(df.limit(0)).count() == 0


# ---- 9 ----------------------------------------------------------------------------------------


def fingerprint_brute(text, width=4):
    words = [w.lower() for w in words_of(text)]
    if not words:
        return 0
    runs = [b" ".join(words[k : k + width]) for k in range(max(1, len(words) - width + 1))]
    hashes = [xxhash.xxh64_intdigest(r, 42) for r in runs]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


@given(st.integers(0, 2**64 - 1), st.sets(st.integers(0, 63), max_size=4), st.integers(0, 2**64 - 1))
@settings(max_examples=200, deadline=None)
def test_every_close_pair_meets(fp, bits, free):
    for own in (free, 2**64 - 1):
        other = fp ^ sum(1 << b for b in bits if own >> b & 1)
        assert any(fp & m == other & m for m in simhash_cover.masks(4, own))
        assert all(m & ~own == 0 and m.bit_count() >= own.bit_count() - 2**3 - own.bit_count() // 2 for m in simhash_cover.masks(4, own))


def test_third_level_is_bounded():
    free = {2**64 - 1}
    for _ in range(2):
        free = {f & ~m for f in free for m in simhash_cover.masks(4, f)}
    assert max((f & ~m).bit_count() for f in free for m in simhash_cover.masks(4, f)) <= 8


def classes_brute(prints, radius=4):
    label = dict(prints)
    ids = sorted(label)
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(ids, 2):
        if (label[a] ^ label[b]).bit_count() <= radius:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_near_classes(docs):
    prints = {i: fingerprint_brute(t) for i, t, _ in awkward()}
    got = collected(simhash_cover.near_classes(docs))
    assert {i: int(r.fingerprint, 16) for i, r in got.items()} == prints
    want = classes_brute(prints)
    assert {i: r.component_id for i, r in got.items()} == want
    assert {r.doc_id for r in simhash_cover.drop_near_copies(docs).collect()} == set(want.values())
    assert simhash_cover.near_classes(docs.limit(0)).count() == 0


def test_large_buckets_split_without_loss(spark):
    rng = random.Random(8)
    base = rng.getrandbits(64)
    prints = {i: base ^ sum(1 << b for b in rng.sample(range(64), rng.randint(0, 5))) for i in range(300)}
    rows = {}
    for i, f in sorted(prints.items()):
        rows.setdefault(f, i)
    df = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f, i) for f, i in rows.items()], "fp long, rep long")
    want = classes_brute({i: f for f, i in rows.items()})
    from qacurate.operators.graph import components

    for most in (8, 5000):
        named = {r.node: r.component for r in components(simhash_cover.links(df, 4, most)).collect()}
        assert {i: named.get(i, i) for i in want} == want


# ---- 10 ---------------------------------------------------------------------------------------


def test_chain_uses_earlier_categories():
    rng = random.Random(6)
    texts, labels = [], []
    for _ in range(900):
        a, c = rng.random() < 0.3, rng.random() < 0.4
        words = [f"n{rng.randrange(300)}" for _ in range(30)] + (["vile"] if a else []) + (["threaten"] if c else [])
        rng.shuffle(words)
        texts.append(" ".join(words).encode())
        labels.append((int(a), int(c), int(a and c)))
    f = toxicity_chain.Features()
    rows = [f.of(t) for t in texts]
    y = np.array(labels)
    chain = toxicity_chain.train(rows[:700], y[:700], ("insult", "threat", "severe"))
    p = chain.predict(rows[700:])
    assert ((p > 0.5) == y[700:]).mean(axis=0).min() > 0.95
    assert len(chain.links[2].earlier) == 2 and abs(chain.links[2].earlier).max() > 0


def test_toxicity_on_held_out_rows(spark, docs):
    sf = "/root/testdata/sf0.1"
    rows = LLM.queries["op10_toxicity_chain"](spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    toxic = [r for r in rows if r.toxic]
    assert sum(r.predicted for r in toxic) / len(toxic) > 0.8
    assert sum(r.predicted for r in rows if not r.toxic) / len(rows) < 0.01
    assert {r.score for r in toxicity_chain.score(docs, None, ("toxic",), "toxic").collect()} == {0.0}
    assert toxicity_chain.fit(docs, spark.createDataFrame([], "doc_id long, toxic int"), ("toxic",)) is None


# ---- all --------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", sorted(LLM.oracles))
def test_equals_oracle(spark, sf, name):
    assert difference(LLM.queries[name](spark, sf), LLM.oracles[name], sf) == ""


@pytest.mark.parametrize("name", sorted(LLM.queries))
def test_one_row_for_each_document(spark, sf, name):
    names, rows = spark_rows(LLM.queries[name](spark, sf))
    table, key = ("pages", "page_id") if name.startswith("op2") else ("documents", "doc_id")
    ids = {r[names.index(key)] for r in rows}
    assert ids == {float(r[0]) for r in spark.read.parquet(f"{sf}/{table}.parquet").select(key).collect()}
    if not name.startswith("op4"):
        assert sum(rows.values()) == len(ids)


def test_patience_helper():
    assert line_alignment._unique_matches([1, 2, 3, 9], [3, 1, 2, 9]) == [(0, 1), (1, 2), (3, 3)]
    assert bisect.bisect_left([1], 1) == 0
