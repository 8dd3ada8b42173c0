"""The training-data operators against brute force, exact round trips and held-out accuracy."""

import hashlib
import itertools
import pathlib
import random
import re
import time
import tracemalloc
import zlib
from array import array

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from graphloom.llm import bpe, chroma, lattice, lines, packing, quality, queries, set_join, sharding, shingles, toxicity, url_rules
from graphloom.plans.scratch import Scratch

VOCABULARY = bpe.vocabulary()


def components(ids, links):
    up = {i: i for i in ids}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def near_copies(seed, n, words=40):
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choices("abcdefgh", k=rng.randint(2, 6))) for _ in range(400)]
    out = []
    for _ in range(n):
        base = rng.choices(vocabulary, k=rng.randint(1, words))
        out.append(" ".join(base))
        for _ in range(rng.randint(0, 3)):
            copy = list(base)
            for _ in range(rng.randint(0, 2)):
                copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
            out.append(" ".join(copy))
    return out


# ---- 1 -----------------------------------------------------------------------------------------


def test_lattice_equals_brute_force(spark):
    rng = np.random.default_rng(5)
    base = rng.normal(size=(60, 16))
    x = np.concatenate([base, base[:30] + 0.08 * rng.normal(size=(30, 16)), base[:10] + 0.3 * rng.normal(size=(10, 16)), base[:5]]).astype(np.float32)
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)]
    odd = [None, [], [0.0] * 16, [float("nan")] * 16, [float("inf")] + [1.0] * 15, [None] + [1.0] * 15]
    rows += [(1000 + i, v) for i, v in enumerate(odd)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").withColumn("rid", F.lit(1)).withColumn("cell", F.lit("x"))
    got = {r.vec_id: r for r in lattice.near_duplicate_vectors(df).collect()}
    u = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    near = u @ u.T >= 0.9
    np.fill_diagonal(near, False)
    want = components(range(len(x)), zip(*np.nonzero(near), strict=True))
    assert len(got) == len(rows)
    assert all(got[i].n_links == near[i].sum() and got[i].component_id == want[i] and got[i].kept == (want[i] == i) for i in range(len(x)))
    assert all(got[1000 + i].n_links == 0 and got[1000 + i].kept for i in range(len(odd)))
    assert lattice.near_duplicate_vectors(df.limit(0)).count() == 0


def test_e8_points_are_lattice_points():
    x = np.random.default_rng(0).normal(size=(500, 8)) * 3
    first, second = lattice.e8_points(x)
    for p in (first, second):
        assert ((p % 2).sum(axis=1) % 8 == 0).all()  # all integers or all halves
        assert (p.sum(axis=1) % 4 == 0).all()
    assert (np.linalg.norm(x - first / 2, axis=1) <= 1 + 1e-9).all()  # the covering radius


# ---- 2 -----------------------------------------------------------------------------------------


def shingle_set(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return frozenset()
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)])


@pytest.mark.parametrize("k,num", [(3, 85), (5, 80)])
def test_set_join_equals_brute_force(make_docs, k, num, monkeypatch):
    monkeypatch.setattr(set_join, "SMALL", 8)  # so that nodes branch and blocks split on a small table
    monkeypatch.setattr(set_join, "BLOCK", 16)
    rng = random.Random(3)
    base = [f"w{rng.randint(0, 50)}" for _ in range(60)]
    crowd = []
    for _ in range(60):
        c = list(base)
        for _ in range(rng.randint(0, 4)):
            c[rng.randrange(60)] = f"x{rng.randint(0, 9)}"
        crowd.append(" ".join(c))
    texts = [*near_copies(1, 60), *crowd, None, "", " \t", "Aa bB", "aa BB", "aa bb"]
    got = {r.doc_id: r for r in set_join.near_duplicate_components(make_docs(texts), k, num, 100).collect()}
    sets = [shingle_set(t, k) for t in texts]
    links = [(i, j) for i in range(len(sets)) for j in range(i) if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j])]
    want = components(range(len(sets)), links)
    assert len(links) > 100
    assert all(got[i].n_shingles == len(sets[i]) and got[i].component_id == want[i] and got[i].kept == (want[i] == i) for i in range(len(texts)))


@pytest.mark.parametrize("most", [0, 8 << 20])
def test_set_join_sends_no_signatures_to_crowded_nodes(make_docs, most, monkeypatch):
    """Few pivots go to all tasks; a signature is dealt once by its document, not with each node it is in. Links are the same either way."""
    plans, save = [], set_join.Scratch.save

    def seen(self, df, name):
        if name == "branched":
            plans.append(df._jdf.queryExecution().optimizedPlan().toString())
        return save(self, df, name)

    monkeypatch.setattr(set_join.Scratch, "save", seen)
    monkeypatch.setattr(set_join, "SMALL", 8)
    monkeypatch.setattr(set_join, "PIVOT_BYTES", most)
    base = [f"w{i}" for i in range(40)]
    texts = [" ".join([*base[:i], f"x{i}", *base[i + 1 :]]) for i in range(0, 40, 2)] + near_copies(1, 10)
    got = {r.doc_id: r.component_id for r in set_join.near_duplicate_components(make_docs(texts)).collect()}
    sets = [shingle_set(t, 3) for t in texts]
    assert got == components(range(len(sets)), [(i, j) for i in range(len(sets)) for j in range(i) if 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j])])
    assert plans and all("collect_list" in p and ("strategy=broadcast" in p) == (most > 0) for p in plans)


def test_set_join_on_odd_tables(odd_docs, no_docs):
    got = set_join.near_duplicate_components(odd_docs).collect()
    assert len(got) == odd_docs.count()
    assert {r.doc_id: r.component_id for r in got}[6] == 5
    assert set_join.near_duplicate_components(no_docs).count() == 0


# ---- 3 -----------------------------------------------------------------------------------------


def test_url_rules(spark):
    urls = [None, "", "no scheme", "http://A.Example.ORG/es/1", "https://example.org/en/12", "https://xexample.org/en/2", "https://org", "https://m.x.com/fr/1?q#z", "https://x.com/de/", "http://m.casino-win.example.net/a", "http://x.net/a?affiliate_id=3"]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)], "page_id bigint, url string, rule string").withColumn("fits", F.lit(1))
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_rules.judge_urls(pages).collect()}
    assert got[0] == got[1] == got[2] == ("", "", None, "allow")
    assert got[3] == ("a.example.org", "/es/1", "example.org/es/", "block")
    assert got[4] == ("example.org", "/en/12", "example.org/en/1", "block")
    assert got[5] == ("xexample.org", "/en/2", "org/", "allow")
    assert got[6] == ("org", "", None, "allow")
    assert got[7] == ("m.x.com", "/fr/1", "com/fr/", "allow")
    assert got[8] == ("x.com", "/de/", "com/de/", "block")
    assert got[9][3] == got[10][3] == "block"


# ---- 4 and 8 -----------------------------------------------------------------------------------


def test_classifiers_on_the_held_out_fold(spark):
    d = "/root/testdata/sf0.1"
    truth = spark.read.parquet(f"{d}/labels.parquet")
    for fn, label, least in ((queries.op4_quality, "quality", 0.97), (queries.op8_toxicity, "toxic", 0.88)):
        rows = fn(spark, d).join(truth, "doc_id").where("held_out").select("score", label).collect()
        y, s = np.array([r[1] for r in rows]), np.array([r[0] for r in rows])
        rank = s.argsort().argsort()
        auc = (rank[y == 1].sum() - y.sum() * (y.sum() - 1) / 2) / (y.sum() * (1 - y).sum())
        assert auc > least


def test_classifiers_on_odd_tables(odd_docs, no_docs, labels, make_docs):
    for fn in (quality.classify_quality, toxicity.classify_toxicity):
        got = fn(odd_docs, labels).collect()
        assert len(got) == odd_docs.count() and all(0 <= r.score <= 1 for r in got)
        assert fn(no_docs, labels).count() == 0
        assert fn(make_docs(["a b"]), labels.limit(0)).count() == 1


def test_trees_learn_a_rule():
    rng = np.random.default_rng(0)
    x = rng.random((2000, 4))
    y = ((x[:, 1] > 0.5) ^ (x[:, 2] > 0.3)).astype(float)
    model = quality.grow(x[:1500], y[:1500])
    assert ((model.score(x[1500:]) > 0.5) == y[1500:]).mean() > 0.97


def test_clauses_count_by_context():
    symbols = toxicity.WordSymbols(toxicity.built_in())
    index = lambda negated, reported, aimed: negated + 2 * reported + 4 * aimed
    for text, event in (("such an idiot", index(0, 0, 0)), ("you idiot", index(0, 0, 1)), ("you are not an idiot", index(1, 0, 1)), ("he said you idiot", index(0, 1, 1))):
        counts, clauses = toxicity.clause_events(text, symbols)
        assert counts[event] == 1 and sum(counts) == 1 and clauses == 1
    assert toxicity.clause_events("not this. idiot", symbols)[0][0] == 1  # a clause ends the negation


# ---- 5 and 7 -----------------------------------------------------------------------------------

TEXTS = [None, "", " ", "Hello, World!", "aaaa aaaaa lololol", "ÀÉ réeuxment ñandú ŉ ﬁ Σας", "漢字 कि 😀🇫🇷 ١٢", "it's we're I'll 'd", "<|startoftext|>x <|endoftext|>", "a b c\x1cd\x85e", "x" * 5000, "İstanbul DŽ ß"]


def test_encoding_equals_the_library(make_docs):
    from tokenizers import Tokenizer

    rng = random.Random(2)
    alphabet = "aaabehinot'.,!  É1２Σςé́<|endoftext|>\n"
    texts = TEXTS + ["".join(rng.choices(alphabet, k=rng.randint(1, 30))) for _ in range(1500)] + ["".join(rng.choices("abehinost", k=rng.randint(1, 23))) for _ in range(1500)]
    tok = Tokenizer.from_file(VOCABULARY)
    got = {r.doc_id: r for r in bpe.round_trip_digests(make_docs(texts), VOCABULARY).collect()}
    for i, t in enumerate(texts):
        ids = tok.encode(t or "", add_special_tokens=False).ids
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), t
        assert got[i].decoded_sha256 == hashlib.sha256(tok.decode(ids, skip_special_tokens=False).encode()).hexdigest(), t


def test_scalar_and_array_paths_agree():
    a = bpe.TokenAutomaton(VOCABULARY)
    texts = [*TEXTS, *near_copies(4, 40)]
    assert a.encode_column(pa.array(texts)) == [a.encode(t or "") for t in texts]
    assert [array("I", x).tolist() for x in a.spell_many([b"hello", b"aaaaaa"])[1]]


def test_packing_places_every_id_once(make_docs, odd_docs, no_docs):
    rng = random.Random(1)
    texts = [" ".join(rng.choices(["alpha", "beta", "gamma"], k=rng.choice([0, 1, 5, 300, 2500]))) for _ in range(120)] + [None]
    docs = make_docs(texts)
    got = packing.pack_documents(docs, VOCABULARY, block_windows=6).collect()
    a = bpe.automaton(VOCABULARY)
    by_doc, by_sequence = {}, {}
    for r in got:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_sequence.setdefault(r.sequence_id, []).append(r)
    for i, t in enumerate(texts):
        ids, at = a.encode(t or "") + (1).to_bytes(4, "little"), 0
        for r in sorted(by_doc[i], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) // 4
            assert r.ids_crc32 == zlib.crc32(ids[4 * at : 4 * (at + r.length)])
            at += r.length
        assert 4 * at == len(ids)
    for rows in by_sequence.values():
        at = 0
        for r in sorted(rows, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048
    assert sum(r.length for r in got) > 0.9 * 2048 * (len(by_sequence) - 2 * docs.rdd.getNumPartitions())
    assert packing.pack_documents(odd_docs, VOCABULARY).select("doc_id").distinct().count() == 9
    assert packing.pack_documents(no_docs, VOCABULARY).count() == 0


def test_differencing_is_nearly_even():
    rng = random.Random(0)
    sizes = [rng.randint(1, 1000) for _ in range(200)]
    dealt = packing.difference(sizes, 12)
    loads = [sum(sizes[i] for i in w) for w in dealt]
    assert sorted(i for w in dealt for i in w) == list(range(200))
    assert max(loads) - min(loads) <= 20
    for capacity in (1000, 1024, 2048):
        windows = packing.pack(sizes, capacity)
        assert sorted(i for w in windows for i in w) == list(range(200))
        assert all(sum(sizes[i] for i in w) <= capacity for w in windows) and len(windows) <= 1.1 * sum(sizes) / capacity + 2
    # the count rises as often as it must: items over half the capacity need a window each
    assert len(packing.pack([600] * 50, 1000)) == 50
    assert packing.pack([], 10) == []


# ---- 6 -----------------------------------------------------------------------------------------


def plain_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_banded_distance_and_probes():
    rng = random.Random(2)
    for _ in range(3000):
        a = "".join(rng.choices("abc", k=rng.randint(0, 14)))
        b = list(a)
        for _ in range(rng.randint(0, 4)):
            p = rng.randint(0, len(b))
            b[p : p + rng.randint(0, 1)] = rng.choices("abc", k=rng.randint(0, 1))
        b = "".join(b)
        d = plain_distance(a, b)
        for most in (1, 2, 3):
            assert lines.edit_distance_within(a, b, most) == (d <= most)
            s, t = sorted((a, b), key=len)
            if d <= most < len(s):
                parts = lines.segments(len(s), most + 1)
                assert any(m == len(s) and t[at : at + n] == s[parts[i][0] : parts[i][0] + n] for m, i, at, n in lines.probes(len(t), most))


@pytest.mark.parametrize("distance", [1, 2])
def test_line_dedup_equals_brute_force(make_docs, distance):
    rng = random.Random(distance)
    pool = ["".join(rng.choices("abcdef ", k=rng.randint(5, 40))).strip() + "zzz" for _ in range(25)]
    texts = []
    for _ in range(40):
        own = []
        for _ in range(rng.randint(0, 5)):
            line = list(rng.choice(pool))
            for _ in range(rng.randint(0, 2)):
                line[rng.randrange(len(line))] = rng.choice("abcdef")
            own.append("".join(line))
        texts.append("\n".join(own))
    got = {r.doc_id: r for r in lines.remove_repeated_lines(make_docs(texts), distance=distance).collect()}
    place = [(i, k, x.strip()) for i, t in enumerate(texts) for k, x in enumerate(t.split("\n")) if len(x.strip()) >= lines.MIN_CHARS]
    distinct = sorted({x for _, _, x in place})
    ids = range(len(distinct))
    cls = components(ids, [(i, j) for i in ids for j in range(i) if plain_distance(distinct[i], distinct[j]) <= distance])
    group = {x: cls[i] for i, x in enumerate(distinct)}
    first, docs_of = {}, {}
    for i, k, x in place:
        first.setdefault(group[x], (i, k))
        docs_of.setdefault(group[x], set()).add(i)
    drop = {(i, k) for i, k, x in place if len(docs_of[group[x]]) >= lines.MIN_DOCS and first[group[x]] != (i, k)}
    assert drop
    for i, t in enumerate(texts):
        assert got[i].text == "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in drop)


def test_long_lines_with_edits_in_proportion_go(make_docs):
    rng = random.Random(6)
    letters = "abcdefghijklmnopqrstuvwxyz"
    base = ["x" + "".join(rng.choices(letters, k=rng.randint(60, 900))) + "x" for _ in range(300)]

    def edited(line, edits):
        line = list(line)
        for k in range(edits):  # evenly spread, the hardest case
            line[(2 * k + 1) * len(line) // (2 * edits)] = "#"
        return "".join(line)

    most = [len(x) // lines.SYMBOLS_PER_EDIT for x in base]
    near = [edited(x, m) for x, m in zip(base, most, strict=True)]
    shifted = ["y" * (m // 2) + x[: -(m // 2)] for x, m in zip(base, most, strict=True)]
    far = [edited(x, 2 * m + 2) for x, m in zip(base, most, strict=True)]
    for copies, least, greatest in ((near, 0.98, 1), (shifted, 0.98, 1), (far, 0, 0)):
        got = lines.remove_repeated_lines(make_docs(base + copies)).where("doc_id >= 300").collect()
        assert least <= sum(r.n_removed for r in got) / 300 <= greatest


def test_line_dedup_on_odd_tables(odd_docs, no_docs):
    got = lines.remove_repeated_lines(odd_docs)
    assert got.count() == odd_docs.count()
    assert set(odd_docs.columns) <= set(got.columns)
    assert lines.remove_repeated_lines(no_docs).count() == 0


def test_line_dedup_tells_rows_of_one_id_apart(spark):
    two = "first line of the text here\nsecond line of the text here"
    rows = [(1, two), (2, two), (2, "short"), (2, None), (None, two), (3, two), (3, two)]
    got = lines.remove_repeated_lines(spark.createDataFrame(rows, "doc_id bigint, text string"), short=True).collect()
    assert sorted((r.doc_id or 0, "-" if r.text is None else r.text, r.n_removed) for r in got) == [(0, two, 0), (1, two, 0), (2, "", 2), (2, "-", 0), (2, "short", 0), (3, "", 2), (3, "", 2)]


def test_crowded_keys_are_compared_in_blocks(make_docs, monkeypatch):
    monkeypatch.setattr(lines, "BLOCK", 8)
    rng = random.Random(4)
    start = "every line of this crowd starts with the same forty symbols and then "
    texts = [start + "".join(rng.choices("abcdefghijklmnop", k=45)) for _ in range(60)]
    copies = [t[:80] + "#" + t[81:] for t in texts[:20]]
    got = {r.doc_id: r.n_removed for r in lines.remove_repeated_lines(make_docs(texts + copies)).collect()}
    assert got == {i: int(i >= 60) for i in range(80)}


def test_rows_of_a_key_meet_however_batches_cut_them():
    rng = random.Random(8)
    for _ in range(300):
        rows = [((rng.randint(1, 4) << lines.KEY_AT) | (rng.choice([20, 21, 40]) << lines.CHARS_AT) | rng.choice([0, 1]), rng.randint(1, 4)) for _ in range(rng.randint(0, 14))]
        rows.sort(key=lambda r: r[0])  # lines of one code in any order
        cuts = sorted(rng.randint(0, len(rows)) for _ in range(rng.randint(0, 5)))
        parts = [rows[a:b] for a, b in zip([0, *cuts], [*cuts, len(rows)], strict=True)]
        batches = [pa.RecordBatch.from_arrays([pa.array([r[k] for r in p], pa.int64()) for k in (0, 1)], names=["code", "h"]) for p in parts]
        got = {(r["code"], r["h"]) for b in lines._meeting(1)(iter(batches)) for r in b.to_pylist()}
        chars = lambda code: code >> lines.CHARS_AT & lines.MOST_CHARS
        want = {a for a in rows for b in rows if a[1] != b[1] and a[0] >> lines.KEY_AT == b[0] >> lines.KEY_AT and abs(chars(a[0]) - chars(b[0])) <= 1}
        assert want <= got <= set(rows)


def test_many_pairs_are_compared_as_one_by_one_is():
    rng = random.Random(21)
    text = lambda n, letters: "".join(rng.choice(letters) for _ in range(n))
    for letters in ("ab", "abcdefgh ", [chr(c) for c in range(0x4E00, 0x4E00 + 900)]):
        base = [text(rng.choice([1, 3, 12, 30, 64, 65, 200, 400]), letters) for _ in range(60)]
        other = []
        for x in base:
            x = list(x)
            for _ in range(rng.randint(0, len(x) // 15 + 2)):
                at = rng.randint(0, len(x))
                x[at : at + rng.randint(0, 1)] = rng.choice([[], [rng.choice(letters)]])
            other.append("".join(x) or "z")
        compare = lines._Comparer(base + other)
        i = np.array([k for k in range(60) for _ in range(6)])
        j = np.array([60 + (k if r < 5 else rng.randint(0, 59)) for k in range(60) for r in range(6)])
        most = np.array([rng.choice([0, 1, 2, 5, 9, 20]) for _ in i])
        want = [lines.edit_distance_within((base + other)[a], (base + other)[b], m) for a, b, m in zip(i.tolist(), j.tolist(), most.tolist(), strict=True)]
        assert compare.within(i, j, most).tolist() == want and 0 < sum(want) < len(want)


def test_pairs_of_long_lines_are_compared_in_few_microseconds():
    """42 to 46 microseconds a pair of this thread as measured, 143 to 158 before diagonals were followed."""
    rng = random.Random(22)
    base = ["".join(rng.choice("etaoin shrdlu") for _ in range(500)) for _ in range(500)]
    other = ["".join(rng.choice("etaoin shrdlu") if rng.random() < 0.04 else c for c in x) for x in base]
    compare, took = lines._Comparer(base + other), []
    for _ in range(3):
        began = time.thread_time()
        compare.within(np.arange(500), np.arange(500, 1000), np.full(500, 20))
        took.append(time.thread_time() - began)
    assert min(took) < 500 * 120e-6


def test_packed_keys_come_back_sorted_and_once():
    rng = np.random.default_rng(23)
    code, h = rng.integers(0, 40, 400), rng.integers(0, 3, 400)
    parts = [(b, code[k], h[k]) for b in range(4) for k in np.array_split(np.flatnonzero(code // 10 == b), 3)]
    batch = pa.RecordBatch.from_pydict({"bucket": pa.array([b for b, *_ in parts], pa.int32()), "codes": [c.tobytes() for _, c, _ in parts], "hashes": [x.tobytes() for *_, x in parts]})
    got = [(r["code"], r["h"]) for b in lines._unpacked(iter([batch.slice(0, 5), batch.slice(5)])) for r in b.to_pylist()]
    assert got == sorted(set(zip(code.tolist(), h.tolist(), strict=True)))


# ---- 9 -----------------------------------------------------------------------------------------


def test_lines_lie_on_disk_once_when_keys_are_sent(make_docs, monkeypatch):
    seen, swept = [], []
    keys, sweep = lines.line_keys, lines.Scratch.sweep
    monkeypatch.setattr(lines.Scratch, "sweep", lambda self: (swept.append(self.root), sweep(self))[1])

    def spy(docs, *rest):
        root = swept[-1]  # shuffle files of the classes are let go before
        seen.extend(c for p in pathlib.Path(root.removeprefix("file:")).glob("*") if p.name.startswith(("lines", "places")) for c in docs.sparkSession.read.parquet(str(p)).columns)
        return keys(docs, *rest)

    monkeypatch.setattr(lines, "line_keys", spy)
    docs = make_docs(["one line that is common\nown line number %d" % i for i in range(30)])
    assert lines.repeated_lines(docs).count() == 29
    assert seen == ["h", "doc_id", "row", "line_no", "times"]


def test_chroma_finds_copies_excerpts_and_noise(spark):
    rng = np.random.default_rng(0)
    tunes = [chroma.melody(" ".join(f"w{i}{j}" for j in range(60))) for i in range(6)]
    media = [chroma.wav_bytes(t) for t in tunes]
    media += [media[0], chroma.wav_bytes(tunes[1] + 0.02 * rng.normal(size=len(tunes[1]))), chroma.wav_bytes(tunes[2][20 * chroma.HOP :]), None, b"broken"]
    df = spark.createDataFrame(list(enumerate(media)), "rec_id bigint, media binary")
    got = chroma.align_recordings(chroma.fingerprint_column(df, "rec_id", "media"), F.col("rec_id") < 6).collect()
    pairs = {(r.query_class, r.match_class): r for r in got}
    assert set(pairs) == {(i, i) for i in range(6)} | {(1, 7), (2, 8)}
    assert pairs[0, 0].n_copies == 2
    assert pairs[2, 8].offset == -20
    assert len(chroma.fingerprint(np.zeros(0))) == 0


def test_chroma_leaves_no_pair_within_the_bound_out(spark):
    rng = np.random.default_rng(3)
    prints = [rng.integers(0, 2**32, n, dtype=np.uint32) for n in (1, 2, 9, 40, 41, 70)]
    one_bit = prints[3] ^ (np.uint32(1) << rng.integers(0, 32, 40, dtype=np.uint32))  # no integer is equal any more
    decoy = np.r_[prints[5][:5], rng.integers(0, 2**32, 30, dtype=np.uint32), prints[5][20:] ^ np.uint32(1 << 7)]  # most equal integers where the rest differs
    prints += [one_bit, decoy, np.r_[rng.integers(0, 2**32, 30, dtype=np.uint32), prints[3][:20] ^ np.uint32(5)], prints[0] ^ np.uint32(63), prints[0] ^ np.uint32(127), np.zeros(0, np.uint32)]
    want = {}
    for q in range(6):
        for m, y in enumerate(prints):
            x, best = prints[q], None
            for o in range(-len(x) + 1, len(y)) if len(y) else ():
                lo, hi = max(0, -o), min(len(x), len(y) - o)
                if 2 * (hi - lo) >= min(len(x), len(y)):
                    error = int(np.bitwise_count(x[lo:hi] ^ y[lo + o : hi + o]).sum()) / (32 * (hi - lo))
                    best = min(best or (2.0,), (error, lo - hi, abs(o), o))
            if best and best[0] <= 0.2:
                want[q, m] = (best[3], -best[1], best[0])
    raw = [p.tobytes() for p in prints]
    rows = [(i, len(p), zlib.crc32(r), r) for i, (p, r) in enumerate(zip(prints, raw, strict=True))]
    got = chroma.align_recordings(spark.createDataFrame(rows, chroma.PRINTED), F.col("rec_id") < 6).collect()
    assert {(r.query_class, r.match_class): (r.offset, r.overlap, r.bit_error) for r in got} == want and len(got) == len(want)
    assert {(3, 6), (5, 7), (3, 8), (0, 9)} <= set(want) and (0, 10) not in want


def test_chroma_links_are_one_row_a_recording_and_count_every_pair(spark):
    rng = np.random.default_rng(11)
    base = [rng.integers(0, 2**32, n, dtype=np.uint32) for n in (3, 9, 30, 45)]
    noisy = lambda p, share: p ^ (rng.random((len(p), 32)) < share).astype(np.uint32) @ (np.uint32(1) << np.arange(32, dtype=np.uint32))
    prints = [noisy(base[i % 4], 0.04 * (i % 4 < 3))[i % 3 :] for i in range(80)] + [base[0], base[0], base[1], np.zeros(0, np.uint32), np.zeros(0, np.uint32)]
    raw = [p.tobytes() for p in prints]
    printed = spark.createDataFrame([(i, len(p), zlib.crc32(r), r) for i, (p, r) in enumerate(zip(prints, raw, strict=True))], chroma.PRINTED)
    asks = lambda i: i % 5 == 0
    pairs = chroma.align_recordings(printed, F.col("rec_id") % 5 == 0).collect()
    cls = {i: raw.index(r) for i, r in enumerate(raw) if r}
    near = {(p.query_class, p.match_class): p for p in pairs}
    got = {r.rec_id: r for r in chroma.link_recordings(printed, F.col("rec_id") % 5 == 0).collect()}
    assert sorted(got) == list(range(len(prints)))  # before: as many rows as pairs
    low = {c: c for c in cls.values()}
    for _ in low:
        for q, m in near:
            low[q] = low[m] = min(low[q], low[m])
    for i, r in got.items():
        if i not in cls:
            assert (r.class_id, r.n_links, r.component_id, r.match_class) == (None, 0, i, None)
            continue
        other = [j for j in cls if j != i and ((asks(i) and (cls[i], cls[j]) in near) or (asks(j) and (cls[j], cls[i]) in near))]
        assert (r.class_id, r.query, r.n_links, r.component_id) == (cls[i], asks(i), len(other), low[cls[i]])
        found = [(p.bit_error, -p.overlap, m, p.offset) for (q, m), p in near.items() if asks(i) and q == cls[i] != m]
        found += [(p.bit_error, -p.overlap, q, -p.offset) for (q, m), p in near.items() if not asks(i) and m == cls[i] != q]
        assert (r.bit_error, r.overlap, r.match_class, r.offset) == ((lambda e, n, c, o: (e, -n, c, o))(*min(found)) if found else (None,) * 4)
    assert len(pairs) > 3 * len(prints)


def test_chroma_votes_are_those_of_counting():
    rng = np.random.default_rng(12)
    prints = [rng.integers(0, 5, int(n), dtype=np.uint32) for n in rng.integers(1, 40, 30)]
    fresh = lambda p: [(k, w) for k, w in enumerate(p.tolist()) if not k or p[k - 1] != w]
    want = {}
    for q, x in enumerate(prints[:12]):
        for m, y in enumerate(prints):
            votes = {}
            for (i, w), (j, v) in itertools.product(fresh(x), fresh(y)):
                if w == v:
                    votes[j - i] = votes.get(j - i, 0) + 1
            if votes and max(votes.values()) >= min(4, len(x), len(y)):
                want[q, m] = max((n, -abs(o), o) for o, n in votes.items())[2]
    got = [row for part in chroma.voted_offsets(prints[:12], prints, 4) for row in zip(*(x.tolist() for x in part), strict=True)]
    assert {row[:2]: row[2] for row in got} == want and len(got) == len(want)


def test_chroma_compares_at_every_offset_short_and_long_ones():
    rng = np.random.default_rng(5)
    prints = [rng.integers(0, 2**32, n, dtype=np.uint32) for n in (1, 1, 2, 3, 5, 8, 13, 60, 61, 150, 299, 500, 700)]
    noisy = lambda p: p ^ (rng.random((len(p), 32)) < 0.17).astype(np.uint32) @ (np.uint32(1) << np.arange(32, dtype=np.uint32))
    prints += [noisy(prints[10])[130:], noisy(np.r_[prints[12][300:], prints[12][:90]]), noisy(prints[7])[:40], noisy(prints[11]), noisy(prints[9])]
    want = {}
    for q, x in enumerate(prints):
        for m, y in enumerate(prints):
            best = (2.0,)
            for o in range(-len(x) + 1, len(y)):
                lo, hi = max(0, -o), min(len(x), len(y) - o)
                if 2 * (hi - lo) >= min(len(x), len(y)):
                    best = min(best, (int(np.bitwise_count(x[lo:hi] ^ y[lo + o : hi + o]).sum()) / (32 * (hi - lo)), lo - hi, abs(o), o))
            if best[0] <= 0.2:
                want[q, m] = (best[3], -best[1], best[0])
    got = [row for part in chroma.near_offsets(prints, prints, 0.2) for row in zip(*(x.tolist() for x in part), strict=True)]
    assert {row[:2]: row[2:] for row in got} == want and len(got) == len(want)
    assert {(10, 13), (12, 14), (7, 15), (11, 16), (9, 17)} <= set(want)


def test_chroma_compares_pairs_in_some_microseconds():
    """A turn of the given conversations has up to 300 frames. 8 microseconds of this thread a pair as measured, 37 before groups of like length."""
    rng = np.random.default_rng(6)
    prints = [rng.integers(0, 2**32, int(n), dtype=np.uint32) for n in rng.integers(150, 300, 1024)]
    took = []
    for _ in range(2):
        began = time.thread_time()
        assert sum(len(part[0]) for part in chroma.near_offsets(prints[:64], prints, 0.2)) == 64
        took.append(time.thread_time() - began)
    assert min(took) < 64 * 1024 * 25e-6


def test_line_counts_take_little_memory():
    """One place of 8 bytes and one number of 4 for each symbol; four places before."""
    text = ["abcd \u00e9\u6f22\U0001f600" * 40, "", "a" * 300] * 400
    with np.errstate(over="ignore"):
        x = lines._Hashed(text)
        tracemalloc.start()
        got = x.counts()
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
    for line, row in zip(text[:3], got[:3].tolist(), strict=True):
        want = [0] * 32
        for c in line:
            want[(ord(c) * 2654435761 & 0xFFFFFFFF) >> 27] += 1
        assert row == [n % 256 for n in want]
    assert peak < 20 * len(x.code)


# ---- 10 ----------------------------------------------------------------------------------------


def test_shards_are_even_and_gapless(make_docs, odd_docs, no_docs):
    texts = ["same text"] * 400 + [f"text {i} " * (i % 17) for i in range(800)] + [None, ""]
    docs = make_docs(texts)
    rows = sharding.shard_documents(docs, shards=6).collect()
    assert len(rows) == len(texts)
    by: dict[int, list] = {}
    for r in rows:
        t = texts[r.doc_id] or ""
        assert r.size == len(t.encode()) + 8 and r.text_crc32 == zlib.crc32(t.encode())
        by.setdefault(r.shard, []).append(r)
    sizes = [sum(r["size"] for r in s) for s in by.values()]
    assert len(by) == 6 and max(sizes) <= 1.03 * min(sizes)
    assert all(sorted(r.slot for r in s) == list(range(len(s))) for s in by.values())
    assert sharding.shard_documents(odd_docs).count() == odd_docs.count()
    assert sharding.shard_documents(no_docs).count() == 0


# ---- hashing and SQL ----------------------------------------------------------------------------


def test_shingle_sets_count_like_plain_sets():
    texts = [*near_copies(9, 30), None, "", "A a", "a\x0bb\x0cc d"]
    for k in (3, 5):
        got = list(shingles.shingle_sets(pa.array(texts), k))
        assert [len(x) for x in got] == [len(shingle_set(t, k)) for t in texts]


def test_queries_with_sql_agree(spark, sf):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW pages AS SELECT * FROM '{sf}/pages.parquet'")
    df = queries.op3_url_rules(spark, sf)
    got = con.execute(queries.oracle_sql()["op3_url_rules"])
    at = [df.columns.index(d[0]) for d in got.description]
    assert sorted([tuple(r[i] for i in at) for r in df.collect()], key=repr) == sorted(got.fetchall(), key=repr)


def test_chroma_filters_are_sums_of_rectangles():
    image = np.random.default_rng(4).random((21, 12))
    wide = np.vstack([np.hstack([image, image])] + [np.hstack([image[-1:], image[-1:]])] * chroma.SPAN)
    got = chroma._responses(image)
    for i, (kind, y, h, w) in enumerate(chroma._FILTERS):
        for t in range(len(image)):
            box = lambda t0, t1, y0, y1: wide[t + t0 : t + t1, y0:y1].sum()  # noqa: B023, E731
            low, high = (y, y + h // 2), (y + h // 2, y + h)
            sides = {
                0: lambda: (box(0, w // 2, y, y + h), box(w // 2, w, y, y + h)),
                1: lambda: (box(0, w, *low), box(0, w, *high)),
                2: lambda: (box(0, w // 2, *low) + box(w // 2, w, *high), box(0, w // 2, *high) + box(w // 2, w, *low)),
                3: lambda: (box(0, w, y, y + h), box(0, w, 0, 12) * h / 12),
            }
            a, b = sides[kind]()
            assert abs(got[t, i] - (np.log1p(a) - np.log1p(b))) < 1e-9


def test_texts_are_sent_only_of_lines_in_clusters(spark, monkeypatch):
    held = {}
    save = Scratch.save

    def watched(self, df, name):
        out = save(self, df, name)
        if "h" in df.columns:
            held[name] = out.select("h").distinct().count(), "line" in df.columns
        return out

    monkeypatch.setattr(Scratch, "save", watched)
    rows = [(k, "same beginning " + 15 * c + "\nof two near lines the one" + "." * (k % 2)) for k, c in enumerate("abcdefgh")]
    cleaned = {r.doc_id: r.n_removed for r in lines.remove_repeated_lines(spark.createDataFrame(rows, "doc_id long, text string"), short=True).collect()}
    assert cleaned == {0: 0} | {k: 1 for k in range(1, 8)}
    assert held["met"] == (10, False)
    assert [name for name, (_, text) in held.items() if text] == ["clustered"]
    assert held["clustered"][0] == 2
