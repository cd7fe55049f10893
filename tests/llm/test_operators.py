"""Operators against brute force, exact round trips and held-out accuracy, and their edge cases."""

import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from veilstream.llm import ann, common, decontam, fixity, language, line_dedup, packing, pii, simhash, token_counts, token_output, words
from veilstream.llm.queries import OP3_SQL, OP4_SQL, tokenizer_path

DOCS = "doc_id long, text string, lang string, source string, n_chars long, title string"
LONG = " ".join(f"word{i % 977}" for i in range(60_000))
ODD = [
    (None, "A text without an id, of some length it is.", "en", "s", 1, "t"),
    (1, None, "en", "s", 1, "t"),
    (2, "", "en", "s", 1, "t"),
    (3, "a b", None, None, None, None),
    (4, LONG, "en", "s", 1, "t"),
    (5, "The same text in two rows, twice.\nThe same text in two rows, twice.", "en", "s", 1, "t"),
    (5, "The same text in two rows, twice.\nThe same text in two rows, twice.", "en", "s", 1, "t"),
    (6, "1234 !!! \t\n 5678", "en", "s", 1, "t"),
    (7, "<|endoftext|> it's\x1codd İstanbul été", "fr", "s", 1, "t"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def docs(spark):
    return common.read_table(spark, "/root/testdata/sf0.001", "documents")


@pytest.fixture(scope="module")
def tok():
    return words.load_tokenizer(tokenizer_path())


# --- tokens ------------------------------------------------------------------------------


def test_word_encoder_and_merge_counter_equal_the_library(tok):
    rng = random.Random(1)
    alpha = [*"aAbzé ÉßİΣσςı́'stvrelmd0129.,!?-_\t\n\x0b\x1c\x85 각가😀<|>", "<|endoftext|>", "'s", " THE "]
    enc, count = words.WordEncoder(tokenizer_path()), words.MergeCounter(tokenizer_path())
    for _ in range(3000):
        t = "".join(rng.choices(alpha, k=rng.randint(0, 50)))
        ids = tok.encode(t, add_special_tokens=False).ids
        assert np.frombuffer(enc.raw(t), "<u4").tolist() == ids
        assert count.count(t) == len(ids)


def test_variable_length_round_trip():
    rng = random.Random(2)
    for n in (0, 1, 3, 4, 5, 100):
        r = np.asarray([rng.choice([rng.getrandbits(32), rng.randint(0, 255), rng.getrandbits(16), rng.getrandbits(24)]) for _ in range(n)], np.uint32)
        c, d = token_output.encode_ranks(r)
        assert len(c) == -(-n // 4)
        assert (token_output.decode_ranks(c, d, n) == r).all()


def expected_tokens(rows, tok, end):
    out, at = [], 0
    for r in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0)):
        ids = (tok.encode(r[1], add_special_tokens=False).ids if r[1] else []) + [end]
        out.append((r[0], at, len(ids), zlib.crc32(np.asarray(ids, "<u4").tobytes())))
        at += len(ids)
    return out


def test_token_output(docs, odd, none, tok):
    for df in (docs, odd):
        rows = [(r.doc_id, r.text) for r in df.collect()]
        got = [tuple(r) for r in token_output.token_output(df, tokenizer_path()).collect()]
        assert sorted(got, key=lambda r: r[1]) == expected_tokens(rows, tok, 1)
    assert token_output.token_output(none, tokenizer_path()).count() == 0


def test_token_files_ascend_and_start_without_gaps(spark, tmp_path, monkeypatch):
    rows = [((i * 37) % 500, f"text {i} of some length " * (i % 5)) for i in range(500)] + [(None, f"no id {i}") for i in range(300)] + [(7, "same")] * 200
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    monkeypatch.setattr(token_output, "PART_BYTES", 400)
    path = str(tmp_path / "out")
    token_output.write_tokens(df, tokenizer_path(), path, 1)
    files = sorted(p for p in __import__("os").listdir(f"{path}/docs") if p.endswith(".parquet"))
    assert len(files) > 10
    seen = [r.doc_id for f in files for r in spark.read.parquet(f"{path}/docs/{f}").orderBy("before").collect()]
    assert seen == sorted(seen, key=lambda d: (d is not None, d or 0)) and len(seen) == 1000
    assert max(Counter(r.part for r in spark.read.parquet(f"{path}/docs").filter("doc_id is null or doc_id = 7").collect()).values()) < 150
    at = 0
    for r in sorted(token_output.read_tokens(spark, path).collect(), key=lambda r: (r.start, r.n_tokens)):
        assert r.start == at
        at += r.n_tokens


def test_token_counts(odd, none, tok):
    got = Counter(tuple(r) for r in token_counts.token_counts(odd, tokenizer_path()).collect())
    n = lambda t: len(tok.encode(t, add_special_tokens=False).ids) if t else 0
    assert got == Counter((r[0], len((r[1] or "").encode()), n(r[1]), n(r[1]) > 2048) for r in ODD)
    assert token_counts.token_counts(none, tokenizer_path()).count() == 0


def brute_best_fit(lengths, cap):
    bins = []
    for n in sorted(lengths, reverse=True):
        fit = [i for i, r in enumerate(bins) if r >= n]
        if fit:
            bins[min(fit, key=lambda i: bins[i])] -= n
        else:
            bins.append(cap - n)
    return len(bins)


def test_best_fit_equals_brute_force():
    rng = random.Random(3)
    for _ in range(300):
        cap = rng.randint(1, 50)
        ls = [rng.randint(1, cap) for _ in range(rng.randint(0, 70))]
        assert packing.best_fit_decreasing(Counter(ls), cap)[1] == brute_best_fit(ls, cap)


def check_packed(rows, cap):
    seqs = {}
    for r in rows:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in seqs.values():
        at = 0
        for off, n in sorted(own):
            assert off == at
            at += n
        assert at <= cap
    return len(seqs)


def test_packing(docs, odd, none, tok, monkeypatch):
    for df, crowd in ((docs, 100_000), (odd, 100_000), (docs, 2)):
        monkeypatch.setattr(packing, "CROWD", crowd)
        rows = packing.pack_documents(df, tokenizer_path()).collect()
        assert check_packed(rows, 2048) == brute_best_fit([r.length for r in rows], 2048)
        pieces = Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows)
        plain = Counter()
        for r in df.collect():
            ids = np.asarray((tok.encode(r.text, add_special_tokens=False).ids if r.text else []) + [0], "<u4")
            plain.update((r.doc_id, k, s, len(ids[s : s + 2048]), zlib.crc32(ids[s : s + 2048].tobytes())) for k, s in enumerate(range(0, len(ids), 2048)))
        assert pieces == plain
        whole = Counter()
        for r in rows:
            whole[r.doc_id] += r.length
        want = Counter()
        for r in df.collect():
            want[r.doc_id] += (len(tok.encode(r.text, add_special_tokens=False).ids) if r.text else 0) + 1
        assert whole == want
    assert packing.pack_documents(none, tokenizer_path()).count() == 0


# --- near duplicates ---------------------------------------------------------------------


def plain_fingerprint(t, k):
    import xxhash

    w = re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + k]), 42) for i in range(max(1, len(w) - k + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_groups_equal_brute_force(spark, docs, odd, none):
    rng = random.Random(4)
    base = [(r.doc_id, r.text) for r in docs.collect()]
    near = [(10_000 + i, t + " " + "x" * rng.randint(1, 3)) for i, (_, t) in enumerate(base[:60])]
    df = spark.createDataFrame(base + near, "doc_id long, text string")
    rows = simhash.near_duplicates(df).collect()
    fp = {d: plain_fingerprint(t, 4) for d, t in base + near}
    assert {r.doc_id: int(r.fingerprint, 16) for r in rows} == fp
    comp = {d: d for d in fp}
    for _ in range(len(fp)):
        new = {d: min(comp[e] for e in fp if (fp[d] ^ fp[e]).bit_count() <= 4) for d in fp}
        if new == comp:
            break
        comp = new
    assert {r.doc_id: r.component_id for r in rows} == comp
    kept = {r.doc_id for r in simhash.keep_one(df).collect()}
    assert kept == set(comp.values())
    assert simhash.near_duplicates(odd).count() == len(ODD)
    assert sum(r.doc_id == 5 for r in simhash.keep_one(odd).collect()) == 1
    assert simhash.near_duplicates(none).count() == 0


def test_bits_counted_eight_to_a_word_equal_plain_counts():
    draw = np.random.default_rng(1)
    for n in (1, 254, 255, 256, 1000):
        for words64 in (1, 5):
            x = draw.integers(0, 1 << 64, (n, words64), np.uint64)
            plain = [sum((int(v) >> bit) & 1 for v in x[:, w]) for w in range(words64) for bit in range(64)]
            assert simhash.ones_of(x).tolist() == plain
            assert simhash.ones_of(np.full((n, words64), (1 << 64) - 1, np.uint64)).tolist() == [n] * 64 * words64


def test_near_dedup_stage_reaches_jaccard_080(spark, docs):
    import corpus_pipeline

    rng = random.Random(10)
    base = [(r.doc_id, r.text) for r in docs.collect()]
    for i, (_, t) in enumerate(base[:60]):
        w = t.split()
        for p in rng.sample(range(len(w)), max(1, min(len(w) // 60, 40))):  # of 55 shingles, 50 are left: around 0.8
            w[p] = f"changed{i}"
        base.append((10_000 + i, " ".join(w)))
    df = spark.createDataFrame(base, "doc_id long, text string")
    sets = {d: frozenset(tuple(w[i : i + 5]) for w in [re.sub("[A-Z]", lambda m: m[0].lower(), t).split()] for i in range(max(1, len(w) - 4))) for d, t in base}
    comp, pairs = {d: d for d in sets}, [(d, e) for d in sets for e in sets if d < e and 5 * len(sets[d] & sets[e]) >= 4 * len(sets[d] | sets[e])]
    assert sum(0.8 <= len(sets[d] & sets[e]) / len(sets[d] | sets[e]) < 0.95 for d, e in pairs) > 20
    for _ in range(len(sets)):
        before = dict(comp)
        for d, e in pairs:
            comp[d] = comp[e] = min(comp[d], comp[e])
        if comp == before:
            break
    assert {r.doc_id for r in corpus_pipeline.near_dedup(spark, df, "").collect()} == set(comp.values())


def test_rows_coded_together_equal_rows_coded_one_by_one():
    draw = np.random.default_rng(9)
    for most in (200, 60_000, 1 << 32):
        rows = [draw.integers(0, most, n, np.uint32) for n in (0, 1, 3, 4, 5, 0, 257, 0)]
        sizes = np.array([len(r) for r in rows])
        control, data = token_output.encode_rows(np.concatenate(rows), sizes)
        assert list(zip(control.to_pylist(), data.to_pylist())) == [token_output.encode_ranks(r) for r in rows]
        assert token_output.decode_rows(control.to_pylist(), data.to_pylist(), sizes).tolist() == np.concatenate(rows).tolist()
    empty = np.zeros(0, np.int64)
    assert len(token_output.encode_rows(empty, empty)[0]) == 0 and len(token_output.decode_rows([], [], empty)) == 0


def test_crowded_variants_lose_no_near_pair(spark):
    """4,096 fingerprints of which 79 or more meet at a variant; 100 pairs (4 bits apart there) have near sketches and all others far ones."""
    bits = 32
    tables = simhash.tables_for(0.8, bits)
    draw, rng = np.random.default_rng(3), random.Random(3)
    leads = [0x5A5A5A5A ^ m for m in range(1 << 12)]
    rest = [int.from_bytes(draw.bytes(4 * (tables - 1))) for _ in leads]
    planted = []
    for i in rng.sample(range(1 << 10), 100):
        j = i ^ 0b11 << 10 ^ 0b11 << rng.randrange(9)
        apart = sum(1 << (32 * t + b) for t in range(tables - 1) for b in rng.sample(range(32), 5))  # too far to meet elsewhere
        rest[j] = rest[i] ^ apart
        planted.append((i, j))
    planted = [(i, j) for i, j in planted if (rest[i] ^ rest[j]).bit_count() == 5 * (tables - 1)]
    assert len(planted) > 90
    whole = [x << (32 * (tables - 1)) | r for x, r in zip(leads, rest)]
    words = -(-tables // 2)
    rows = [(i, np.frombuffer((x << (64 * words - 32 * tables)).to_bytes(8 * words), ">u8").astype("<u8").view(np.int64).tolist()) for i, x in enumerate(whole)]
    once = common.materialize(spark.createDataFrame(rows, "sid long, sketch array<long>"), "crowded")
    links = simhash.candidates(once, bits, tables, 0.8)
    comp = {r.node: r.component for r in common.connected_components(links).collect()}
    assert all(comp.get(i, -1) == comp.get(j, -2) for i, j in planted)


def test_near_join_connects_what_all_pairs_connect(monkeypatch):
    """Families with equal and near leading bits, in one piece and in many, against brute force."""
    draw, rng, rows = np.random.default_rng(4), random.Random(4), []
    for k in range(30):
        x = int.from_bytes(draw.bytes(16))
        for _ in range(rng.choice((1, 2, 40))):
            y = x ^ sum(1 << b for b in rng.sample(range(96), rng.choice((2, 20, 40)))) ^ sum(1 << b for b in rng.sample(range(96, 128), rng.choice((0, 1, 3))))
            rows.append([y >> 64, y & (1 << 64) - 1])
    x = np.array(rows, np.uint64)
    up = list(range(len(x)))
    for a in range(len(x)):
        for b in range(a):
            if int(np.bitwise_count((x[a, 0] ^ x[b, 0]) >> np.uint64(32))) <= 4 and int(np.bitwise_count(x[a] ^ x[b]).sum()) <= 30:
                lo, hi = sorted((up[a], up[b]))
                up = [lo if u == hi else u for u in up]
    for limit in (1 << 13, 1 << 22):
        monkeypatch.setattr(simhash, "VARIANTS_IN_MEMORY", limit)
        ball = simhash.NearJoin(2, 32, 30, x)
        ball.join(ball.leads, np.full(len(ball.leads), 2), 32)
        got = list(range(len(x)))
        for a, b in ball.forest().tolist():
            lo, hi = sorted((got[a], got[b]))
            got = [lo if u == hi else u for u in got]
        assert got == up


def test_ball_join_splits_large_buckets_without_loss(monkeypatch):
    rng = random.Random(5)
    fps = []
    for _ in range(40):
        x = rng.getrandbits(64)
        fps += [x ^ sum(1 << b for b in rng.sample(range(64), rng.randint(0, 4))) for _ in range(3)]
    x = np.unique(np.asarray(fps, np.uint64))

    def components(limit):
        monkeypatch.setattr(simhash, "VARIANTS_IN_MEMORY", limit)
        ball = simhash.BallJoin(2)
        ball.join(x, np.full(len(x), 2), 64)
        return sorted(map(tuple, ball.forest().tolist()))

    assert components(1 << 14) == components(1 << 22)


def test_components_of_a_chain_and_a_hub(spark):
    chain = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 300)] + [(7, 7)]
    got = {r.node: r.component for r in common.connected_components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(201)) and all(got[1000 + i] == 1000 for i in range(300))


# --- lines -------------------------------------------------------------------------------


def test_banded_distance_equals_levenshtein(spark):
    rng, rows = random.Random(6), []
    for _ in range(1500):
        a = "".join(rng.choices("abcé", k=rng.randint(3, 30)))
        b = list(a)
        for _ in range(rng.randint(0, 4)):
            i = rng.randrange(len(b) + 1)
            b[i : i + rng.randint(0, 1)] = rng.choices("abcé", k=rng.randint(0, 1))
        rows.append(tuple(sorted((a, "".join(b)), key=len)))
    df = spark.createDataFrame(rows, "a string, b string")
    for k in (1, 2):
        q = df.filter(f"length(b) - length(a) <= {k} and length(a) >= {k}").select(line_dedup.banded_distance(F.col("a"), F.col("b"), k).alias("d"), F.levenshtein("a", "b").alias("e"))
        assert all(min(r.d, k + 1) == min(r.e, k + 1) for r in q.collect())


def test_edit_links_equal_brute_force(spark):
    rng, lines = random.Random(7), set()
    for _ in range(60):
        a = "".join(rng.choices("abcd ", k=rng.randint(20, 60)))
        lines.add(a)
        for _ in range(3):
            b = list(a)
            for _ in range(rng.randint(1, 3)):
                i = rng.randrange(len(b))
                b[i : i + rng.randint(0, 1)] = rng.choices("abcd ", k=rng.randint(0, 1))
            lines.add("".join(b))
    rows = [(i, x) for i, x in enumerate(sorted(lines))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["first"].doc_id, r.later.doc_id) for r in line_dedup.edit_links(df, line_dedup.line_keys(df)).collect()}
    l = spark.createDataFrame([r for r in rows if len(r[1]) >= line_dedup.MIN_CHARS], "i long, x string")
    r = l.select(F.col("i").alias("j"), F.col("x").alias("y"))
    want = l.join(r, F.expr("i < j and levenshtein(x, y) <= if(least(length(x), length(y)) >= 40, 2, 1)")).select("i", "j").collect()
    assert got == {(r.i, r.j) for r in want} and got


def test_edit_links_reach_lines_that_differ_by_a_dotted_capital_i(spark):
    rows = [(1, "a line of some length from \u0130zmir to the coast"), (2, "a line of some length from Izmir to the coast")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert line_dedup.edit_links(df, line_dedup.line_keys(df)).count() == 1


def test_crowded_segments_lose_no_link(spark, monkeypatch):
    rng = random.Random(14)
    head, tail = "".join(rng.choices("abcdef", k=30)), "".join(rng.choices("abcdef", k=30))
    lines = sorted({head + "".join(rng.choices("0123456789", k=4)) + tail for _ in range(300)})
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    want = {(i, j) for i in range(len(lines)) for j in range(i + 1, len(lines)) if sum(a != b for a, b in zip(lines[i], lines[j])) <= 2}

    def links(crowd):
        monkeypatch.setattr(line_dedup, "CROWD", crowd)
        return {(r["first"].doc_id, r.later.doc_id) for r in line_dedup.edit_links(df, line_dedup.line_keys(df)).collect()}

    got = links(16)
    assert got == links(10_000) and got >= want


def test_short_copies_go_and_blank_lines_stay(spark):
    df = spark.createDataFrame([(1, "one\n\nsame\n \t\nend\r"), (2, "two\n\nsame\n \t\n\r")], "doc_id long, text string")
    assert {r.doc_id: r.text for r in line_dedup.dedup_lines(df).collect()} == {1: "one\n\nsame\n \t\nend\r", 2: "two\n\n \t\n\r"}


def test_line_dedup_edges(odd, none):
    rep = line_dedup.line_report(odd).collect()
    assert len(rep) == len(ODD)
    out = {(r.doc_id, r.text) for r in line_dedup.dedup_lines(odd).collect()}
    assert (5, "The same text in two rows, twice.") in out and (1, None) in out and (2, "") in out and (4, LONG) in out
    assert line_dedup.line_report(none).count() == 0 and line_dedup.dedup_lines(none).count() == 0
    assert line_dedup.dedup_lines(odd).columns == odd.columns


# --- contamination, privacy, language, fixity --------------------------------------------


def test_decontamination(spark, odd, none):
    rng = random.Random(8)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    items = [(i, " ".join(word() for _ in range(30))) for i in range(20)] + [(99, "only four short words"), (100, None)]
    clean = [(i, " ".join(word() for _ in range(200))) for i in range(50)]
    leaks = []
    for i in range(20):
        w = items[i][1].split()
        for p in (5, 17):  # two substitutions in thirty
            w[p] = "changed"
        leaks.append((1000 + i, " ".join([word() for _ in range(50)] + w + [word() for _ in range(50)])))
    bench = spark.createDataFrame(items, "item_id long, text string")
    df = spark.createDataFrame(clean + leaks + [(5000, "x only four, short words y")], "doc_id long, text string")
    found = {(r.doc_id, r.item_id) for r in decontam.find_leaks(df, bench).collect()}
    assert found == {(1000 + i, i) for i in range(20)} | {(5000, 99)}
    assert {r.doc_id for r in decontam.decontaminate(df, bench).collect()} == set(range(50))
    assert decontam.find_leaks(odd, bench).count() == 0
    assert decontam.find_leaks(none, bench).count() == 0
    assert decontam.decontaminate(odd, spark.createDataFrame([], "item_id long, text string")).count() == len(ODD)


def test_decontamination_decides_by_the_rule():
    from itertools import combinations

    rng = np.random.default_rng(11)
    cases = [rng.random(n) < p for n in range(1, 45) for p in (0.5, 0.75, 0.9) for _ in range(5)]
    for x in cases:
        want = max((int(x[i:j].sum()) for i in range(len(x)) for j in range(i + 1, len(x) + 1) if 5 * x[i:j].sum() >= 4 * (j - i)), default=0)
        i, j, n = decontam.best_stretch(x)
        assert n == want == x[i:j].sum() and 5 * n >= 4 * (j - i)
    hash_ = decontam.TokenHasher().hashes
    for size, most in ((14, 1), (15, 2), (16, 3)):
        item = hash_(" ".join(f"w{i}" for i in range(size)))
        seeds = np.concatenate([decontam.seed_hashes(item, *m) for m in decontam.masks([])])
        for k in range(most + 1):
            for gone in combinations(range(size), k):
                t = item.copy()
                t[list(gone)] = 7
                own = np.concatenate([decontam.seed_hashes(t, *m) for m in decontam.masks([])])
                assert (own == seeds).any(), gone  # some seed is left at its place
                assert decontam.best_overlap(t, item, 0)[3] == size - k


def plain_leaks(docs, items):
    """(doc_id, item_id) -> matches of the best stretch over all diagonals, by brute force."""
    h, out = decontam.TokenHasher(), {}
    for d, text in docs:
        t = h.hashes(text)
        for i, passage in items:
            item = h.hashes(passage)
            for diagonal in range(-len(item) + 1, len(t)) if len(item) else ():
                a, b = max(0, diagonal), min(len(t), diagonal + len(item))
                same = t[a:b] == item[a - diagonal : b - diagonal]
                need = min(13, len(item))
                if same.sum() < need:
                    continue
                n = decontam.best_stretch(same)[2]
                if n >= need:
                    out[(d, i)] = max(n, out.get((d, i), 0))
    return out


def test_leaks_equal_a_search_of_all_diagonals(spark, monkeypatch):
    rng = random.Random(13)
    word = lambda: "".join(rng.choices("abcdefgh", k=4))
    items = [(i, " ".join(word() for _ in range(rng.choice((3, 8, 12, 15, 20, 30, 60))))) for i in range(40)] + [(40, "again and again " * 20), (7, "a second text under a used id, twelve tokens long at the least")]
    docs = []
    for d in range(400):
        w = [word() for _ in range(rng.randint(0, 40))]
        if d % 3:
            part = rng.choice(items)[1].split()
            a = rng.randrange(len(part))
            part = part[a : a + rng.randint(1, len(part))]
            for _ in range(rng.randint(0, 4)):
                part[rng.randrange(len(part))] = "zz" + word()
            w[len(w) // 2 : len(w) // 2] = part
        docs.append((d, " ".join(w)))
    docs += [(2000, "again and again " * 50), (2001, None), (2002, "")]
    frame_, bench = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    want = plain_leaks(docs, items)
    assert len(want) > 40
    for bits in (27, 8):  # a filter that lets nearly all windows through gives the same rows
        monkeypatch.setattr(decontam, "MOST_BITS", bits)
        assert {(r.doc_id, r.item_id): r.matches for r in decontam.find_leaks(frame_, bench).collect()} == want


def test_decontamination_judges_rows_that_share_an_id_by_their_text(spark):
    passage = " ".join(f"w{i}" for i in range(20))
    df = spark.createDataFrame([(1, passage), (1, "clean text"), (None, passage), (None, "clean too")], "doc_id long, text string")
    out = decontam.decontaminate(df, spark.createDataFrame([(5, passage)], "item_id long, text string")).collect()
    assert sorted(r.text for r in out) == ["clean text", "clean too"]


def test_pseudonyms_are_valid_linked_and_invertible(spark, odd, none):
    texts = ["+1 (555) 123-4567, 4539578763621486 on 2024-02-29; 10.0.0.255 and a.b@c.example.com", "again 4539578763621486 1234567890123456 123-45-6789", "12/31/1999 02/30/2024 300.1.1.1", None, ""]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    out = {r.doc_id: r for r in pii.pseudonymize(df).collect()}
    assert list(out[0].pii) == ["phone", "card", "date", "ipv4", "email"]
    assert list(out[1].pii) == ["card", "ssn"] and list(out[2].pii) == ["date"]
    cards = [re.search(r"\d{16}", out[i].text)[0] for i in (0, 1)]
    assert cards[0] == cards[1] != "4539578763621486"
    digits = [int(c) for c in cards[0]][::-1]
    assert (sum(digits[::2]) + sum(sum(divmod(2 * d, 10)) for d in digits[1::2])) % 10 == 0
    assert "1234567890123456" in out[1].text and "02/30/2024 300.1.1.1" in out[2].text
    back = pii.pseudonymize(pii.pseudonymize(df).drop("pii"), inverse=True)
    assert [r.text for r in back.orderBy("doc_id").collect()] == texts
    assert pii.pseudonymize(odd).count() == len(ODD) and pii.pseudonymize(none).count() == 0


def plain_feistel(a, b, m, n, kind):
    import hashlib

    for r in range(pii.ROUNDS):
        h = int(hashlib.sha256("\x1f".join([pii.TEST_KEY, kind, str(r), str(a if r % 2 else b)]).encode()).hexdigest()[:15], 16)
        a, b = (a, (b + h % n) % n) if r % 2 else ((a + h % m) % m, b)
    return a, b


def plain_digits(d, kind):
    u = len(d) // 2
    a, b = plain_feistel(int(d[:u] or 0), int(d[u:]), 10**u, 10 ** (len(d) - u), kind)
    return (str(a).zfill(u) if u else "") + str(b).zfill(len(d) - u)


def plain_refill(shape, digits):
    it = iter(digits)
    return "".join(next(it) if "0" <= c <= "9" else c for c in shape)


def plain_luhn(d):
    return sum(sum(divmod(2 * int(c), 10)) if i % 2 else int(c) for i, c in enumerate(reversed(d))) % 10


def plain_email(m):
    import hashlib

    local, domain = m.split("@")
    classes = [next((x for x in (range(97, 123), range(65, 91), range(48, 58)) if ord(c) in x), None) for c in local]
    v, u = [ord(c) for c in local], (len(local) + 1) // 2
    for r in range(pii.ROUNDS):
        mine, other = (range(u), range(u, len(v))) if r % 2 == 0 else (range(u, len(v)), range(u))
        seen = ",".join(str(v[i]) for i in other)
        for k, i in enumerate(mine):
            if classes[i] is not None:
                h = hashlib.sha256("\x1f".join([pii.TEST_KEY, "email", str(r), str(k // 16), seen]).encode()).hexdigest()
                shift = int(h[4 * (k % 16) : 4 * (k % 16) + 4], 16)
                v[i] = classes[i][(v[i] - classes[i][0] + shift) % len(classes[i])]
    return "".join(map(chr, v)) + "@" + domain


def plain_pseudonym(m):
    """(kind, text) by plain Python, from the documented formats alone."""
    from datetime import date, datetime, timedelta

    digits = re.sub("[^0-9]", "", m)
    if "@" in m:
        return "email", plain_email(m)
    if re.fullmatch(r"\d{1,3}(\.\d{1,3}){3}", m):
        o = m.split(".")
        if any(int(x) > 255 or (len(x) > 1 and x[0] == "0") for x in o):
            return None, m
        o = [int(x) for x in o]
        a, b = plain_feistel(o[0] * 256 + o[1], o[2] * 256 + o[3], 65536, 65536, "ipv4")
        return "ipv4", f"{a // 256}.{a % 256}.{b // 256}.{b % 256}"
    for shape, form in ((r"\d{4}-\d{2}-\d{2}", "%Y-%m-%d"), (r"\d{2}/\d{2}/\d{4}", "%m/%d/%Y"), (r"\d{2}\.\d{2}\.\d{4}", "%d.%m.%Y")):
        if re.fullmatch(shape, m):
            try:
                at = (datetime.strptime(m, form).date() - date(1900, 1, 1)).days
            except ValueError:
                return None, m
            if not 0 <= at < 17 * 4297:
                return None, m
            a, b = plain_feistel(at // 4297, at % 4297, 17, 4297, "date")
            return "date", (date(1900, 1, 1) + timedelta(a * 4297 + b)).strftime(form)
    if re.fullmatch(r"\d{3}-\d{2}-\d{4}", m):
        area, group, serial = int(m[:3]), int(m[4:6]), int(m[7:])
        if not (0 < area < 900 and area != 666 and group and serial):
            return None, m
        a, b = plain_feistel(area - (2 if area > 666 else 1), (group - 1) * 9999 + serial - 1, 898, 99 * 9999, "ssn")
        return "ssn", f"{a + (2 if a >= 665 else 1):03}-{b // 9999 + 1:02}-{b % 9999 + 1:04}"
    if re.match(r"\+|\(|1-\d{3}-|\d{3}[-. ]\d{3}[-. ]\d{4}$", m):
        code = re.match(r"(\+\d{1,3}|1-)?", m)[0]
        rest, d = m[len(code) :], re.sub("[^0-9]", "", m[len(code) :])
        if len(d) == 10 and not code.startswith("+"):
            x, y = int(d[:3]), int(d[3:6])
            lx, ly = (0 if x < 200 else 200), (0 if y < 200 else 200)
            a, b = plain_feistel(x - lx, (y - ly) * 10000 + int(d[6:]), 800 if lx else 200, (800 if ly else 200) * 10000, "phone10")
            return "phone", code + plain_refill(rest, f"{a + lx:03}{b // 10000 + ly:03}{b % 10000:04}")
        return "phone", code + plain_refill(rest, plain_digits(d, "phone"))
    if plain_luhn(digits):
        return None, m
    body = plain_digits(digits[:-1], "card")
    return "card", plain_refill(m, body + next(c for c in "0123456789" if not plain_luhn(body + c)))


def test_pseudonyms_equal_plain_python(spark, docs):
    made = [
        "\u0142ukasz.\u017cak@example.org, a.long.local.part.with.aaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaa@x.example.com",
        "+44 20 7946 0958, +1 (212) 555-0101, (415) 555-1234, 415-555-1234, 415.555.1234, 415 555 1234, 1-800-555-1234, (055) 123-9999",
        "25.12.2023, 31.02.2023, 12/31/1999, 2024-02-29; 10.0.0.255 and 300.1.1.1; 123-45-6789, 666-12-3456; 4539 5787 6362 1486",
    ]
    rows = [(r.doc_id, r.text) for r in docs.collect()] + [(10_000 + i, t) for i, t in enumerate(made)]
    out = {r.doc_id: r for r in pii.pseudonymize(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    import regex

    pattern, kinds = regex.compile(pii.ANY), Counter()
    for d, t in rows:
        own = [plain_pseudonym(m.group()) for m in pattern.finditer(t)]
        woven, at = [], 0
        for m, (_, new) in zip(pattern.finditer(t), own):
            woven += [t[at : m.start()], new]
            at = m.end()
        assert out[d].text == "".join(woven) + t[at:]
        assert list(out[d].pii) == [k for k, _ in own if k]
        kinds.update(k for k, _ in own if k)
    assert set(kinds) == set(pii.KINDS)
    email = out[10_000].text
    assert email.startswith("\u0142") and ".\u017c" in email and len({email.split("@")[1][-60 + i] for i in range(40)}) > 8
    back = pii.pseudonymize(pii.pseudonymize(spark.createDataFrame(rows, "doc_id long, text string")).drop("pii"), inverse=True)
    assert {r.doc_id: r.text for r in back.collect()} == dict(rows)


def test_domain_permutation_is_a_bijection(spark):
    df = spark.range(17 * 40).select(F.floor(F.col("id") / 40).alias("a"), (F.col("id") % 40).alias("b"))
    s = df.select(pii.feistel(F.col("a"), F.col("b"), F.lit(17), F.lit(40), "k", "x", False).alias("s"))
    assert s.distinct().count() == 17 * 40


def test_language_on_held_out_rows(spark, odd, none):
    docs = common.read_table(spark, "/root/testdata/sf0.01", "documents")
    rows = language.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    assert sum(r.lang == r.lang_pred for r in held) / len(held) > 0.97
    model = language.train(docs)
    got = {r.doc_id: r for r in language.classify(odd, model, ["doc_id"]).collect()}
    assert got[1].lang_pred == got[2].lang_pred == got[6].lang_pred == "und" and got[6].score == 0 and got[6].rejected
    assert language.identify(none).count() == 0
    assert language.keep_identified(docs).count() >= 0.99 * docs.count()


def test_fixity_finds_exactly_the_damage(spark):
    rows = [(i, f"http://h/{i}", f"<p>{i}</p>") for i in range(9000)] + [(None, None, None), (3, "http://h/3", "<p>3</p>"), (-7, "u", "v"), (77, "http://h/77", "second version"), (1 << 40, "far", "away")]
    a = spark.createDataFrame(rows, "page_id long, url string, html string")
    b = a.withColumn("html", F.when(F.col("page_id").isin(5, 8000) | ((F.col("page_id") == 77) & (F.col("html") == "second version")), "rotten").otherwise(F.col("html")))
    b = b.filter("page_id is null or page_id not in (10, 4500)").unionByName(spark.createDataFrame([(6000, "new", "new"), (9500, "n", "n"), (5, "two", "more")], a.schema))
    out = fixity.audit(a, b).collect()
    of = lambda s: Counter(r.page_id for r in out if r.status == s)
    assert of("corrupt") == Counter({5: 1, 8000: 1, 77: 1}) and of("missing") == Counter({10: 1, 4500: 1}) and of("extra") == Counter({6000: 1, 9500: 1, 5: 1})
    assert sum(r.status != "extra" for r in out) == 9004 and sum(r.copies for r in out if r.status != "extra") == 9005
    # offsets follow each other without gaps in the reference's segments
    own = {}
    for r in out:
        if r.status != "extra":
            own.setdefault(r.segment, []).append(r)
    for rs in own.values():
        at = 0
        for r in sorted(rs, key=lambda r: (r.page_id is not None, r.page_id, r.digest)):
            assert r.offset == at
            at += r.bytes * r.copies
    assert {r.status for r in fixity.audit(a, a.repartition(3)).collect()} == {"ok"}
    fewer = fixity.audit(a, a.dropDuplicates()).filter("status <> 'ok'").collect()
    assert [(r.page_id, r.status, r.copies) for r in fewer] == [(3, "missing", 2)]
    assert fixity.audit(a.limit(0), a.limit(0)).count() == 0
    hot = spark.range(3000).select(F.lit(1).cast("long").alias("page_id"), F.col("id").cast("string").alias("url"), F.lit("x").alias("html"))
    assert Counter(r.status for r in fixity.audit(hot, hot.filter("url <> '17'")).collect()) == {"ok": 2999, "missing": 1}


def test_a_sound_replica_is_read_at_its_root_alone(spark):
    a = spark.range(5000).select(F.col("id").alias("page_id"), F.lit("u").alias("url"), F.lit("h").alias("html"))
    rec = fixity.records(a)
    ours, theirs = fixity.tree(rec, 4), fixity.tree(fixity.records(a), 4)
    assert fixity.mismatches(ours, [None] * 4 + theirs[4:]) is None  # no other level is touched
    rot = fixity.tree(fixity.records(a.withColumn("html", F.when(F.col("page_id") == 4321, "x").otherwise(F.col("html")))), 4)
    assert [r.node for r in fixity.mismatches(ours, rot).collect()] == [4321]


def test_warc_files_round_trip(spark, tmp_path):
    rows = [(i, f"http://h/{i}", f"<p>{i}\r\n\r\nWARC/1.0\r\n\u00e9</p>" * (i % 3)) for i in range(200)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    fixity.write_warc(pages, str(tmp_path / "warc"))
    got = {(r.record_id, r.url, r.body) for r in fixity.read_warc(spark, str(tmp_path / "warc")).collect()}
    assert got == {(f"<urn:page:{i}>", u, h) for i, u, h in rows}


# --- neighbours --------------------------------------------------------------------------


def test_neighbours_recall_ties_and_odd_vectors(spark):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(1500, 16)).astype(np.float32)
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(2000 + i, x[50].tolist()) for i in range(40)]
    rows += [(5000, None), (5001, []), (5002, [0.0] * 16), (5003, [float("nan")] * 16), (None, x[0].tolist()), (3000, x[7].tolist()), (3000, x[7].tolist())]
    other = [(6000, [1.0, 0.0]), (6001, [1.0, 0.1]), (6002, [0.0, 1.0])]  # vectors of another length meet each other
    df = spark.createDataFrame(rows + other, "vec_id long, embedding array<float>")
    got = {}
    for r in ann.nearest(df, "vec_id", "embedding", lambda c: c % 50 == 0, shard=400).collect():
        got.setdefault(r.query_id, {})[r["rank"]] = (r.id, r.score)
    ids = np.array(sorted({r[0] for r in rows if r[0] is not None and r[0] < 5000}))
    vec = dict(rows)
    m = np.array([vec[i] for i in ids], np.float64)
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    hit = 0
    queries = [i for i in ids.tolist() if i % 50 == 0]
    assert {k: v[0] for k, v in got.pop(6000).items()} == {1: 6001, 2: 6002}
    assert set(got) == set(queries)
    for q in queries:
        s = m @ m[np.searchsorted(ids, q)]
        best = sorted((i for i in range(len(ids)) if ids[i] != q), key=lambda i: (-round(s[i], 12), ids[i]))[:5]
        hit += len({int(ids[i]) for i in best} & {v[0] for v in got[q].values()})
    assert hit >= 0.9 * 5 * len(queries)
    assert [got[50][k][0] for k in range(1, 6)] == [2000, 2001, 2002, 2003, 2004]
    assert ann.nearest(df.limit(0), "vec_id", "embedding", lambda c: c % 50 == 0).count() == 0


def test_an_id_with_several_vectors_is_found_once(spark):
    rng = np.random.default_rng(12)
    x = rng.normal(size=(300, 8))
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(7, (x[0] * 2 + 0.01).tolist()), (7, (x[0] + 0.02).tolist()), (50, x[100].tolist())]
    got = {}
    for r in ann.nearest(spark.createDataFrame(rows, "i long, v array<double>"), "i", "v", lambda c: c % 50 == 0).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.id, r.score))
    vec = {}
    for i, v in rows:
        vec.setdefault(i, []).append(np.array(v) / np.linalg.norm(v))
    for q, found in got.items():
        want = sorted(((-max(float(a @ b) for a in vec[q] for b in vec[i]), i) for i in vec if i != q))[:5]
        assert [i for _, i, _ in sorted(found)] == [i for _, i in want]
        assert np.allclose([s for *_, s in sorted(found)], [-s for s, _ in want])
    assert got[0][0][1] == 7 and len(got) == 6


# --- queries and the pipeline ------------------------------------------------------------


def test_sql_oracles(spark):
    import os

    import duckdb

    from veilstream.llm import queries as q

    sf = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for f in os.listdir(sf):
        con.execute(f"create view {f[:-8]} as select * from '{sf}/{f}'")
    for name, sql in (("op3_merkle_fixity", OP3_SQL), ("op4_line_dedup", OP4_SQL)):
        df = q.queries()[name](spark, sf)
        cols = ", ".join(f'"{c}"' for c in df.columns)
        assert sorted(map(repr, map(tuple, df.collect()))) == sorted(map(repr, con.execute(f"select {cols} from ({sql})").fetchall()))


def test_pipeline_stages_on_planted_cases(spark, docs):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    cur, sizes = docs, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        cur = common.materialize(stage(spark, cur, sf), name)
        assert cur.columns == docs.columns
        sizes.append(cur.count())
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 0.7 * sizes[0]
    assert decontam.find_leaks(cur, common.read_table(spark, sf, "benchmark")).count() == 0
    near = simhash.near_duplicates(cur, words=5)
    assert near.select("component_id").distinct().count() == near.count()
    packed = corpus_pipeline.STAGES[-1][1](spark, cur, sf).collect()
    check_packed(packed, 2048)
    assert {r.doc_id for r in packed} == {r.doc_id for r in cur.select("doc_id").collect()}
    assert corpus_pipeline.run(spark, sf).count() == len(packed)


def plain_pipeline(spark, rows, bench, tok, rejected):
    """The kept (doc_id, text) by plain Python: line copies and near lines, near copies, passages; rejected: doc_ids of the first stage."""
    rows = [(d, t) for d, t in rows if d not in rejected]

    def distance(a, b, k):
        prev = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            cur = [i]
            for j, y in enumerate(b, 1):
                cur.append(min(prev[j] + 1, cur[-1] + 1, prev[j - 1] + (x != y)))
            if min(cur) > k:
                return k + 1
            prev = cur
        return prev[-1]

    lines, first = {}, {}
    for d, t in rows:
        for i, x in enumerate(t.split("\n")):
            lines[(d, i)] = x
    for at in sorted(lines):
        if lines[at].strip(" \t\r\f\x0b"):
            first.setdefault(lines[at], at)
    letters = {x: Counter(x) for x in first}
    by_size = {}
    for x in first:
        by_size.setdefault(len(x), []).append(x)
    near = set()
    for x, at in first.items():
        if len(x) >= 20:
            for n in range(len(x) - 2, len(x) + 3):
                for y in by_size.get(n, ()):
                    k = 2 if min(len(x), n) >= 40 else 1
                    if n >= 20 and abs(n - len(x)) <= k and first[y] < at and sum((letters[x] - letters[y]).values()) <= k and sum((letters[y] - letters[x]).values()) <= k and distance(x, y, k) <= k:
                        near.add(x)
    gone = {at for at, x in lines.items() if x in first and (first[x] != at or x in near)}
    kept = []
    for d, t in rows:
        own = [x for i, x in enumerate(t.split("\n")) if (d, i) not in gone]
        if len(own) == len(t.split("\n")) or "".join(own).strip(" \t\r\f\x0b\n"):
            kept.append((d, "\n".join(own)))
    sets = {d: frozenset(tuple(w[i : i + 5]) for w in [re.sub("[A-Z]", lambda m: m[0].lower(), t).split()] for i in range(max(1, len(w) - 4))) for d, t in kept}
    comp = {d: d for d in sets}
    pairs = [(d, e) for d in sets for e in sets if d < e and 5 * len(sets[d] & sets[e]) >= 4 * len(sets[d] | sets[e])]
    for _ in sets:
        for d, e in pairs:
            comp[d] = comp[e] = min(comp[d], comp[e])
    kept = [(d, t) for d, t in kept if comp[d] == d]
    bad = {d for d, _ in plain_leaks(kept, bench)}
    return [(d, t) for d, t in kept if d not in bad]


def test_pipeline_equals_plain_python(spark, docs):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    rows = sorted((r.doc_id, r.text) for r in docs.collect())
    bench = [(r.item_id, r.text) for r in common.read_table(spark, sf, "benchmark").collect()]
    rejected = {r.doc_id for r in docs.collect()} - {r.doc_id for r in language.keep_identified(docs).collect()}
    tok = words.load_tokenizer(tokenizer_path())
    want = Counter()
    for d, t in plain_pipeline(spark, rows, bench, tok, rejected):
        ids = np.asarray(tok.encode(t, add_special_tokens=False).ids + [0], "<u4")
        want.update((d, k, s, len(ids[s : s + 2048]), zlib.crc32(ids[s : s + 2048].tobytes())) for k, s in enumerate(range(0, len(ids), 2048)))
    out = corpus_pipeline.run(spark, sf).collect()
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in out) == want
    assert check_packed(out, 2048) == brute_best_fit([r.length for r in out], 2048)


CLASHES = "score rejected lang_pred pii d t h th lost old new text_ leaks component first sid sketch _d _t _h _th _gone _bad _text _new _first _top".split()


def test_extra_columns_of_any_name_are_kept(spark, docs):
    import corpus_pipeline

    base = docs.limit(40)
    wide = base.select("*", *[F.concat_ws("-", F.lit(c), "doc_id").alias(c) for c in CLASHES])
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, wide, "/root/testdata/sf0.001")
        assert out.columns == wide.columns, name
        rows = out.collect()
        assert rows and all(r[c] == f"{c}-{r.doc_id}" for r in rows for c in CLASHES), name
        assert {(r.doc_id, r.text) for r in rows} == {(r.doc_id, r.text) for r in stage(spark, base, "/root/testdata/sf0.001").collect()}, name
    out = pii.pseudonymize(wide)
    assert out.columns[:-1] == wide.columns and all(r[c] == f"{c}-{r.doc_id}" for r in out.collect() for c in CLASHES)
    assert packing.pack_documents(wide, tokenizer_path()).count() == packing.pack_documents(base, tokenizer_path()).count()


def test_pipeline_stages_take_odd_and_empty_tables(spark, odd, none):
    import corpus_pipeline

    for df in (odd, none):
        for _, stage in corpus_pipeline.STAGES:
            assert stage(spark, df, "/root/testdata/sf0.001").count() >= 0
