"""Each operator against a brute-force form, and on nulls, empty tables, repeats and clashing names."""

import base64
import hashlib
import os
import random
from pathlib import Path

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from spanfold.llm import queries as Q

CLASH = ["d", "p", "a", "s", "k", "q", "fp", "row", "size", "g_", "at_", "body", "ps", "rest", "h1", "u", "v", "root", "shard", "last", "id", "key", "target"]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def passage(n, seed):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefghij") for _ in range(r.randint(2, 8))) for _ in range(n))


def rows():
    shared, other = passage(70, 1), passage(55, 2)
    long = passage(4000, 3)
    out = [
        (1, f"{passage(20, 4)} {shared} {passage(9, 5)}", "en", "b", 1),
        (2, f"{shared} {passage(30, 6)} {other}", "en", "a", 2),
        (3, f"{other} x {other}", None, None, None),
        (4, None, "en", "b", 4),
        (5, "", None, "b", 5),
        (6, " \t\n ", "fr", "a", 6),
        (7, f"{long} {shared}", "en", "c", 7),
        (8, long, "en", "c", 8),
        (9, shared, "fr", None, 9),
        (9, shared, "fr", None, 9),
        (10, "éé çà 123 " * 30, "fr", "b", 10),
        (None, shared, "en", "a", None),
        (12, "one two", "en", "a", 12),
    ]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame(rows(), SCHEMA)
    return df.select("*", *[F.lit(i).alias(c) for i, c in enumerate(CLASH)]).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def data():
    return [(i, t) for i, t, *_ in rows()]


def windows_removed(parts, width):
    """Reference marks: parts are (doc, sequence); null documents neither give nor lose."""
    first = {}
    for doc, s in parts:
        if doc is not None:
            for q in range(len(s) - width + 1):
                w = tuple(s[q : q + width])
                first[w] = min(first.get(w, doc), doc)
    out = []
    for doc, s in parts:
        gone = np.zeros(len(s), bool)
        if doc is not None:
            for q in range(len(s) - width + 1):
                if first[tuple(s[q : q + width])] < doc:
                    gone[q : q + width] = True
        out.append(gone)
    return out


def test_window_dedup(docs, empty):
    from spanfold.llm.window_dedup import remove_repeated_windows

    parts = [(i, (t or "").encode().split()) for i, t in data()]
    want = sorted(
        ((i, len(w), int(g.sum()), hashlib.sha256(b" ".join(x for x, y in zip(w, g) if not y)).hexdigest()) for (i, w), g in zip(parts, windows_removed(parts, 50))), key=repr
    )
    got = sorted((tuple(r[:4]) for r in remove_repeated_windows(docs).collect()), key=repr)
    assert got == want and sum(x[2] for x in want) > 200
    assert remove_repeated_windows(empty).count() == 0


def test_windows_meet_across_batches(spark, monkeypatch):
    """Counts combined in batches of one document, of a few, and of all say the same: passages that
    many documents share, that one repeats in itself, and that stand a word apart."""
    from spanfold.llm import window_dedup

    rng = np.random.default_rng(5)
    passage = [f"p{i}" for i in rng.integers(0, 400, 120)]
    parts = []
    for i in rng.permutation(60):
        own = [f"w{x}" for x in rng.integers(0, 5000, int(rng.integers(0, 90)))]
        cut = int(rng.integers(0, 60))
        again = passage[cut:] if i % 3 else ["la"] * int(rng.integers(40, 120))
        parts.append((int(i), own + again + (own + again if i % 5 == 0 else [])))
    parts.append((7, list(passage)))  # a second row of one doc_id, judged apart below
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in parts if i != 7], "doc_id long, text string").repartition(3)
    alone = [(i, w) for i, w in parts if i != 7]
    want = {i: int(g.sum()) for (i, _), g in zip(alone, windows_removed(alone, 50))}
    for room in (1, 60, 1 << 19):
        monkeypatch.setattr(window_dedup, "_ROOM", room)
        assert {r.doc_id: r.n_removed for r in window_dedup.remove_repeated_windows(docs).collect()} == want
    assert sum(want.values()) > 1000
    both = spark.createDataFrame([(i, " ".join(w)) for i, w in parts if i == 7] + [(9, " ".join(passage))], "doc_id long, text string")
    got = sorted((r.doc_id, r.n_words, r.n_removed) for r in window_dedup.remove_repeated_windows(both).collect())
    assert [x for x in got if x[0] == 9] == [(9, 120, 120)] and sum(x[2] for x in got if x[0] == 7) == 0


def test_suffix_dedup(docs, empty):
    from spanfold.llm.suffix_dedup import remove_repeated_bytes

    parts = [(i, (t or "").encode()) for i, t in data()]
    want = []
    for (i, b), g in zip(parts, windows_removed(parts, 50)):
        kept = np.frombuffer(b, np.uint8)[~g].tobytes()
        want.append((i, len(b), int(g.sum()), int((np.diff(np.concatenate(([0], g.astype(np.int8)))) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    got = [tuple(r) for r in remove_repeated_bytes(docs).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)
    out = remove_repeated_bytes(docs, with_text=True, carry=("lang", "source", "n_chars", "d"))
    assert out.count() == len(want) and {"lang", "d", "kept_text"} <= set(out.columns)
    assert remove_repeated_bytes(empty).count() == 0


@pytest.mark.parametrize("hot", [4096, 5])
def test_suffix_dedup_crowded_keys(spark, monkeypatch, hot):
    from spanfold.llm import phrases, suffix_dedup

    monkeypatch.setattr(suffix_dedup, "BLOCK", 200)
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    monkeypatch.setattr(phrases, "HOT_SAMPLE", 1)
    core = passage(8, 77)[:44]
    texts = [(i, f"{passage(3, i)}{core}{passage(3, 500 + i % 7)}") for i in range(60)]
    got = {r.doc_id: r.n_removed for r in suffix_dedup.remove_repeated_bytes(spark.createDataFrame(texts, "doc_id long, text string")).collect()}
    parts = [(i, t.encode()) for i, t in texts]
    assert got == {i: int(g.sum()) for (i, _), g in zip(parts, windows_removed(parts, 50))}


def test_run_length_index():
    from spanfold.llm.rlbwt import RunLengthIndex, layout

    rng = np.random.default_rng(1)
    base = bytes(rng.integers(97, 100, 60, dtype=np.uint8))
    pieces = [base[rng.integers(0, 20) : rng.integers(30, 60)] + bytes(rng.integers(97, 99, rng.integers(0, 20), dtype=np.uint8)) for _ in range(30)] + [b"", b"a", base, base]
    width = 12
    index = RunLengthIndex(pieces, width).seal(np.arange(len(pieces)))
    patterns = [bytes(rng.integers(97, 101, rng.integers(0, 30), dtype=np.uint8)) + base[: rng.integers(0, 40)] for _ in range(40)] + [b"zzz", b""]
    symbols, ends = layout(patterns)
    length, at = index.stream(symbols, ends)
    for p, start in zip(patterns, np.concatenate(([0], ends[:-1] + 1))):
        for x in range(len(p)):
            m = 0
            while m < width and x + m < len(p) and any(p[x : x + m + 1] in q for q in pieces):
                m += 1
            assert m == length[start + x]
            if m == width:
                assert index.least_owner(at[start + x : start + x + 1])[0] == min(i for i, q in enumerate(pieces) if p[x : x + width] in q)
    assert index.runs < len(index.text) / 2


def reference_fingerprint(text):
    w = (text or "").encode().lower().split()
    sh = [b" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


def reference_components(fps, radius=2):
    root = {f: f for f in fps}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(fps):
        for b in fps[i + 1 :]:
            if (a ^ b).bit_count() <= radius:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {f: find(f) for f in fps}


def test_simhash(docs, empty):
    from spanfold.llm.simhash import near_duplicates

    fp = [(i, reference_fingerprint(t)) for i, t in data()]
    comp = reference_components(sorted({f for _, f in fp}))
    least = {}
    for i, f in fp:
        if i is not None:
            least[comp[f]] = min(least.get(comp[f], i), i)
    want = sorted(((i, f"{f:016x}", least.get(comp[f])) for i, f in fp), key=repr)
    assert sorted((tuple(r) for r in near_duplicates(docs).collect()), key=repr) == want
    assert near_duplicates(empty).count() == 0


def test_simhash_links_with_hot_blocks(spark, monkeypatch):
    from spanfold.llm import simhash
    from spanfold.llm.components import components

    monkeypatch.setattr(simhash, "HOT", 40)
    monkeypatch.setattr(simhash, "TILE", 16)
    rng = random.Random(5)
    fps = set()
    for _ in range(60):  # chains of near ones under few common blocks
        x = (rng.getrandbits(30) << 34) | 0x155555555
        for _ in range(6):
            fps.add(x)
            x ^= 1 << rng.randrange(34, 64)
    fps = sorted(fps)
    df = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f,) for f in fps], "fp long")
    roots = {r.node % (1 << 64): r.root % (1 << 64) for r in components(simhash.links(df)).collect()}
    classes = {}
    for f in fps:
        classes.setdefault(roots.get(f, f), set()).add(f)
    want = {}
    for f, r in reference_components(fps).items():
        want.setdefault(r, set()).add(f)
    assert {frozenset(c) for c in classes.values()} == {frozenset(c) for c in want.values()}


def test_components_on_a_path(spark):
    from spanfold.llm.components import components

    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (7, 7)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {i: 0 for i in range(1, 41)} | {101: 100}


def test_mixing(docs, empty, spark):
    from spanfold.llm.mixing import mixed_blocks, mixed_sizes

    got = mixed_sizes(docs, block=4, shard_slots=16).collect()
    sizes = [(i, len((t or "").encode().split()), s) for i, t, _, s, _ in rows()]
    assert sorted(((r.doc_id, r.size) for r in got), key=repr) == sorted(((i, n) for i, n, _ in sizes), key=repr)
    total = {}
    for _, n, s in sizes:
        total[s] = total.get(s, 0) + n
    order = sorted(total, key=lambda s: (s is None, s or ""))
    weight = {s: 1 + i % 3 for i, s in enumerate(order)}
    target, left, free = {}, sum(total.values()), set(order)
    while free:  # fill those above three times their size, share again
        level = left / sum(weight[s] for s in free)
        full = {s for s in free if level * weight[s] > 3 * total[s]}
        if not full:
            target |= {s: level * weight[s] for s in free}
            break
        for s in full:
            target[s] = 3.0 * total[s]
            left -= target[s]
        free -= full
    by_size = {total[s]: target[s] for s in order}
    taken = {}
    for r in got:
        assert r.taken <= 3 * r.size and r.target == pytest.approx(by_size[r.source_size])
        taken[r.source_size] = taken.get(r.source_size, 0) + r.taken
    for n, t in by_size.items():
        assert abs(taken[n] - t) <= 0.1 * t + 12
    again = mixed_sizes(docs.repartition(5), block=4, shard_slots=16).collect()
    assert sorted(map(tuple, again), key=repr) == sorted(map(tuple, got), key=repr)
    blocks = mixed_blocks(docs, block=4, shard_slots=16).collect()
    assert sum(len(r.text.split()) for r in blocks) == sum(r.taken for r in got)
    assert max(len(r.text.encode().split()) for r in blocks) <= 4
    assert mixed_sizes(empty).count() == 0
    none = spark.createDataFrame([(1, None, None), (2, "", "x")], "doc_id long, text string, source string")
    assert [tuple(r)[1:] for r in mixed_sizes(none).collect()] == [(0, 0, 0.0, 0)] * 2


def test_shuffled_index_is_a_permutation(spark):
    from spanfold.llm.mixing import shuffled_index

    for n in (1, 2, 7, 64, 1000):
        got = [r[0] for r in spark.range(n).select(shuffled_index(F.col("id"), F.lit(n).cast("long"), F.lit("s"))).collect()]
        assert sorted(got) == list(range(n))
        assert n < 64 or got != sorted(got)


def test_decontamination(spark, empty):
    from spanfold.llm.decontam import contaminated

    items = [(1, "Anna has 12 apples and gives 5 apples to Ben, how many apples remain with Anna?"), (2, "the quick brown fox jumps over the lazy dog near the river bank"), (3, "short one"), (4, None), (None, "nobody"), (2, "the quick brown fox jumps over the lazy dog near the river bank")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    texts = [
        (10, f"{passage(30, 1)} {items[1][1]} {passage(30, 2)}"),
        (11, f"{passage(30, 3)}. The Quick, brown fox -- jumps over the lazy dog near the river BANK {passage(9, 4)}"),
        (12, f"{passage(10, 5)} Clara has 31 apples and gives 7 apples to Dirk, how many apples remain with Clara? {passage(10, 6)}"),
        (13, f"the quick brown fox {passage(50, 7)}"),
        (14, None),
        (15, ""),
        (16, "short one"),
        (17, passage(500, 8)),
        (None, items[1][1]),
        (10, f"{passage(30, 1)} {items[1][1]} {passage(30, 2)}"),
    ]
    df = spark.createDataFrame(texts, "doc_id long, text string").select("*", *[F.lit(1).alias(c) for c in ("item_id", "h", "of", "coverage")])
    got = {(r.doc_id, r.item_id): r for r in contaminated(df, bench).collect()}
    assert set(got) == {(10, 2), (11, 2), (12, 1), (16, 3)}
    assert got[12, 1].n_slots > 0 and got[12, 1].slot_match >= 0.5 and not got[12, 1].same_slots
    assert contaminated(empty, bench).count() == 0 and contaminated(df, bench.where("false")).count() == 0


def test_language(spark, empty):
    from spanfold.llm.langid import identify

    r = random.Random(3)
    words = {"en": "the and with from this that have which there".split(), "de": "der und mit von dieser nicht auch werden über".split()}
    data = [(i, " ".join(r.choice(words[x]) for _ in range(40)), x) for i, x in enumerate(["en", "de"] * 60)]
    data += [(900, None, "en"), (901, "12 34 %%", "en"), (902, "", None), (None, "the and with", "en")]
    df = spark.createDataFrame(data, "doc_id long, text string, lang string").withColumn("x", F.lit(1)).withColumn("score", F.lit(9))
    got = {x.doc_id: x for x in identify(df, dims=256).collect()}
    truth = {i: x for i, _, x in data}
    held = [x for x in got.values() if x.held_out and x.lang_pred != "und"]
    assert len(held) > 20 and all(x.lang_pred == truth[x.doc_id] for x in held)
    assert {got[i].lang_pred for i in (900, 901, 902)} == {"und"} and got[None].lang_pred == "en"
    assert all(0 <= x.score <= 1 for x in got.values()) and len(got) == len(data)
    assert identify(empty).count() == 0


def test_license_scan(spark, empty):
    from spanfold.llm.license_scan import TEMPLATES, scan_licenses

    mit = TEMPLATES["MIT"]
    data = [
        (1, f"{passage(100, 1)}\nReleased under the MIT License.\n{passage(50, 2)}"),
        (2, f"{passage(300, 3)} {mit.upper().replace(',', ' ')} {passage(300, 4)}"),
        (3, passage(1000, 5)),
        (4, None), (5, ""), (6, "license"),
        (7, f"{passage(5, 6)} {mit.replace('software', 'program', 1)}"),
        (7, f"{passage(5, 6)} {mit.replace('software', 'program', 1)}"),
        (None, "Licensed under CC BY-NC 4.0."),
    ]
    df = spark.createDataFrame(data, "doc_id long, text string").withColumn("hits", F.lit(1)).withColumn("license", F.lit(2))
    got = sorted(((r.doc_id, r.licenses) for r in scan_licenses(df).collect()), key=repr)
    assert got == sorted([(1, "MIT-mention"), (2, "MIT"), (3, ""), (4, ""), (5, ""), (6, ""), (7, "MIT"), (7, "MIT"), (None, "CC-BY-NC-4.0-mention")], key=repr)
    assert scan_licenses(empty).count() == 0


def test_warc(spark, tmp_path):
    from spanfold.llm.warc import read_archives, write_archives

    data = [(i, f"http://x/{i}", f"<p>{i % 7} é</p>" * (i % 5)) for i in range(60)]
    data += [(70, None, None), (71, "bad\r\nurl", ""), (None, "http://n", "null id"), (72, "http://r", "same"), (72, "http://r", "same"), (73, "u", "x" * 300_000)]
    df = spark.createDataFrame(data, "page_id long, url string, html string").select("*", *[F.lit(1).alias(c) for c in ("id", "shard", "sha", "last", "payload")])
    files = []
    for n, parts in enumerate((2, 7)):
        target, manifest = write_archives(df.repartition(parts), f"file://{tmp_path}/w{n}", roll_bytes=1500)
        got = read_archives(target, manifest).collect()
        files.append({p.name: p.read_bytes() for p in (tmp_path / f"w{n}").glob("pages-*")})
        assert not list((tmp_path / f"w{n}").glob(".pages*")) and (tmp_path / f"w{n}" / "manifest.json").exists()
    assert files[0] == files[1] and len(files[0]) > 1
    last, n = {}, {}
    for i, _, h in data:
        h = h or ""
        n[h] = n.get(h, 0) + 1
        if i is not None:
            last[h] = max(last.get(h, i), i)
    want = []
    for i, _, h in data:
        b = (h or "").encode()
        refers = last.get(h or "") if n[h or ""] > 1 and i != last.get(h or "") else None
        want.append((i, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "response" if refers is None else "revisit", refers))
    assert sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got), key=repr) == sorted(want, key=repr)
    assert sorted(bytes(r.payload) for r in got if r.record_type == "response") == sorted((h or "").encode() for (i, _, h), w in zip(data, want) if w[3] == "response")
    target, manifest = write_archives(df.where("false"), f"file://{tmp_path}/none")
    assert read_archives(target, manifest).count() == 0


def test_toxicity(spark, empty):
    from spanfold.llm.toxicity import classify

    r = random.Random(9)
    bad = ["scum", "idiot", "loweient", "loweischaft"]
    data, labels = [], []
    for i in range(500):
        words = passage(60, i).split()
        toxic = int(i % 4 == 0)
        if toxic:
            for _ in range(3):
                words[r.randrange(60)] = r.choice(bad)
        data.append((i, " ".join(words), r.choice(["en", "de"])))
        labels.append((i, toxic))
    data += [(900, None, None), (901, "", "en"), (None, "you idiot scum", "en")]
    labels += [(900, 0), (None, 1), (901, None), (3, 0), (3, 0)]
    df = spark.createDataFrame(data, "doc_id long, text string, lang string").withColumn("toxic", F.lit(1)).withColumn("score", F.lit(1))
    lab = spark.createDataFrame(labels, "doc_id long, toxic int")
    got = {x.doc_id: x for x in classify(df, lab).collect()}
    truth = dict(labels[:500])
    held = [x for x in got.values() if x.held_out and x.doc_id in truth]
    assert len(got) == len(data) and sum(x.predicted == truth[x.doc_id] for x in held) / len(held) > 0.95
    assert got[900].predicted == 0 and got[901].predicted == 0 and all(0 <= x.score <= 1 for x in got.values())
    assert classify(empty, lab).count() == 0
    assert classify(df, lab.where("false")).select("score").distinct().count() == 1


def test_ann(spark):
    from spanfold.llm.ann import nearest

    rng = np.random.default_rng(4)
    x = rng.standard_normal((900, 16)).astype(np.float32)
    x[17] = x[40]
    data = [(i, [float(v) for v in row]) for i, row in enumerate(x)]
    data += [(1000, None), (1020, [0.0] * 16), (1040, [float("nan")] * 16), (1060, [1.0] * 3), (1080, [None] + [1.0] * 15), (None, [1.0] * 16), (1100, [float("inf")] * 16)]
    df = spark.createDataFrame(data, "vec_id long, embedding array<float>").select("*", *[F.lit(1).alias(c) for c in ("id", "v", "b", "g", "rank")])
    got = nearest(df, F.col("vec_id") % 20 == 0, k=10).collect()
    exact = x.astype(float) @ x.astype(float).T
    np.fill_diagonal(exact, -np.inf)
    found = {}
    for r in got:
        found.setdefault(r.query_id, {})[r["rank"]] = (r.vec_id, r.score)
        assert r.score == pytest.approx(exact[r.query_id, r.vec_id], abs=1e-12)
    assert set(found) == set(range(0, 900, 20))
    hits = 0
    for q, ranks in found.items():
        assert sorted(ranks) == list(range(1, 11))
        assert [(-s, i) for i, s in (ranks[k] for k in range(1, 11))] == sorted((-s, i) for i, s in ranks.values())
        hits += len({i for i, _ in ranks.values()} & set(np.argsort(-exact[q])[:10]))
    assert hits / (10 * len(found)) >= 0.9
    assert nearest(df.where("false"), F.col("vec_id") % 20 == 0).count() == 0
    few = nearest(df.where("vec_id < 3"), F.col("vec_id") % 20 == 0).collect()
    assert len(few) == 2


def test_chi_square():
    from spanfold.llm.ann import chi_square_cdf, chi_square_quantile

    assert chi_square_cdf(15.507, 8) == pytest.approx(0.95, abs=1e-4)
    assert chi_square_quantile(0.95, 8) == pytest.approx(15.507, abs=1e-3)


def test_queries_have_their_columns(spark, tiny):
    want = {
        "op1_mixing": ["doc_id", "size", "source_size", "target", "taken"], "op2_suffix_dedup": ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"], "op3_decontam": ["doc_id", "item_id"],
        "op4_langid": ["doc_id", "held_out", "lang_pred", "score"], "op5_license_scan": ["doc_id", "licenses"], "op6_warc": ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"],
        "op7_simhash": ["doc_id", "fingerprint", "component_id"], "op8_toxicity": ["doc_id", "held_out", "score", "predicted"], "op9_window_dedup": ["doc_id", "n_words", "n_removed", "kept_sha256"],
        "op10_ann": ["query_id", "rank", "vec_id", "score"],
    }
    known = Q.queries()
    assert set(known) == set(want)
    for name, cols in want.items():
        out = known[name](spark, tiny)
        assert set(cols) <= set(out.columns) and out.count() > 0


def test_pipeline(spark, tiny):
    import corpus_pipeline

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    names = docs.columns
    for n, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, tiny)
        before, after = docs.count(), out.count()
        assert 0 < after <= before
        if n < 4:
            assert out.columns == names and out.dtypes == docs.dtypes
            path = f"{spark.conf.get('spark.checkpoint.dir')}/pipe{n}"
            out.write.mode("overwrite").parquet(path)
            docs = spark.read.parquet(path)
    assert corpus_pipeline.run(spark, tiny).count() == after


def brute_survivors(rows):
    """Rows left when groups linked by five-word Jaccard >= 0.8 keep their smallest doc_id."""
    sets = []
    for _, t in rows:
        w = (t or "").lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    root = list(range(len(rows)))
    for x in range(len(rows)):
        for y in range(x):
            if rows[x][0] is not None and rows[y][0] is not None and (sets[x] == sets[y] or len(sets[x] & sets[y]) >= 0.8 * len(sets[x] | sets[y])):
                a, b = root[x], root[y]
                root = [b if r == a else r for r in root]
    best = {}
    for x, (i, _) in enumerate(rows):
        if i is not None:
            best[root[x]] = min(best.get(root[x], (i, x)), (i, x))
    return sorted((r for x, r in enumerate(rows) if r[0] is None or best[root[x]][1] == x), key=repr)


@pytest.mark.parametrize("part_rows", [32_768, 40])
def test_pipeline_near_copies(spark, tiny, monkeypatch, part_rows):
    import corpus_pipeline
    from spanfold.llm import resemblance

    monkeypatch.setattr(resemblance, "PART_ROWS", part_rows)
    r = random.Random(8)
    rows = [(1000, ""), (1001, None), (1002, "one two"), (1003, "One two"), (1004, "one three")]
    for i in range(60):  # near copies at similarities on both sides of the bound
        words = passage(r.choice([40, 150, 600]), 900 + i).split()
        rows.append((i, " ".join(words)))
        for n in range(3):
            other = list(words)
            for at in r.sample(range(len(words)), max(1, round(len(words) * r.choice([0.005, 0.01, 0.02, 0.04])))):
                other[at] = f"changed{at}"
            rows.append((100 + 3 * i + n, " ".join(other)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = corpus_pipeline.near_dedup(spark, df, tiny)
    want = brute_survivors(rows)
    assert sorted((tuple(x) for x in got.collect()), key=repr) == want and 65 < len(want) < 200


@pytest.mark.parametrize("part_rows", [16_384, 64])
def test_simhash_tiles_find_all_near_copies(spark, monkeypatch, part_rows):
    """Candidates are all pairs whose fingerprints and sizes allow the similarity, whatever else of
    the texts agrees: fingerprints alone are given here, sizes on both sides of the bands' borders."""
    from spanfold.llm import resemblance as R

    monkeypatch.setattr(R, "PART_ROWS", part_rows)
    r = random.Random(12)
    rows = []
    for i in range(120):
        f1, f2, size = r.getrandbits(64), r.getrandbits(64), r.choice([1, 3, 4, 5, 6, 20, 21, 25, 26, 500, 900, 20_000])
        rows.append((f1, f2, size))
        for _ in range(4):
            bits = [r.sample(range(64), r.randint(4, 21)) for _ in range(2)]
            f, g = (f ^ sum(1 << b for b in own) for f, own in zip((f1, f2), bits))
            rows.append((f, g, max(1, round(size * r.choice([0.78, 0.8, 0.82, 0.9, 1, 1.1, 1.24, 1.25, 1.27])))))
    root = list(range(len(rows)))
    for x in range(len(rows)):
        for y in range(x):
            (a1, a2, m), (b1, b2, n) = rows[x], rows[y]
            first, second = (a1 ^ b1).bit_count(), (a2 ^ b2).bit_count()
            if min(m, n) >= 4 and first <= R.FIRST and first + second <= R.BOTH and min(m, n) >= 0.8 * max(m, n):
                a, b = root[x], root[y]
                root = [min(a, b) if v in (a, b) else v for v in root]
    signed = lambda v: v - (1 << 64) if v >> 63 else v
    nodes = spark.createDataFrame([(i, n, signed(f), signed(g)) for i, (f, g, n) in enumerate(rows)], "sig long, size long, f1 long, f2 long")
    assert {x.node: x.root for x in R.components(R._candidate_links(nodes)).collect()} == {x: v for x, v in enumerate(root) if x != v}
    assert 60 < len(set(root)) < len(rows) - 60
    assert R._candidate_links(nodes.where("size < 4")).count() == 0


def test_pipeline_keeps_rows_of_null_and_repeated_ids(spark, tiny):
    import corpus_pipeline

    texts = [passage(80, 300 + i) for i in range(6)]
    item = spark.read.parquet(f"{tiny}/benchmark.parquet").orderBy("item_id").first().text
    rows = [(None, texts[0]), (None, texts[1]), (None, texts[1]), (7, texts[2]), (7, texts[3]), (8, texts[3]), (9, texts[4]), (9, texts[4]), (3, texts[5])]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = sorted(map(tuple, corpus_pipeline.near_dedup(spark, df, tiny).collect()), key=repr)
    assert got == sorted(rows[:5] + [rows[6], rows[8]], key=repr)
    leaky = df.unionByName(spark.createDataFrame([(7, item), (None, item)], df.schema))
    left = sorted(map(tuple, corpus_pipeline.decontamination(spark, leaky, tiny).collect()), key=repr)
    assert left == sorted(rows, key=repr)


def test_pipeline_copies_no_plain_files(spark, tiny, tmp_path):
    """Rows of Parquet files are told apart by file and place: same rows left as by a copy, none made."""
    import corpus_pipeline

    item = spark.read.parquet(f"{tiny}/benchmark.parquet").orderBy("item_id").first().text
    texts = [passage(80, 300 + i) for i in range(6)]
    rows = [(None, texts[0]), (None, texts[1]), (None, texts[1]), (7, texts[2]), (7, texts[3]), (8, texts[3]), (9, texts[4]), (9, texts[4]), (3, texts[5]), (7, item), (None, item)]
    df = spark.createDataFrame([(*r, n) for n, r in enumerate(rows)], "doc_id long, text string, row_ int")
    df.repartition(4, "row_").write.parquet(f"file://{tmp_path}/docs")
    docs = spark.read.parquet(f"file://{tmp_path}/docs")
    tables = Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file://"), "tables")
    copies = lambda: sorted(x.name for x in tables.glob("rows-*"))
    before = copies()
    keyed, row = corpus_pipeline._with_rows(docs)
    assert keyed.columns == [*docs.columns, row] and keyed.select(row).distinct().count() == len(rows)
    near = corpus_pipeline.near_dedup(spark, docs, tiny)
    assert near.columns == docs.columns
    assert sorted((tuple(r)[:2] for r in near.collect()), key=repr) == sorted([*rows[:5], rows[6], *rows[8:]], key=repr)
    assert sorted(r.row_ for r in corpus_pipeline.decontamination(spark, docs, tiny).collect()) == list(range(9))
    assert copies() == before
    corpus_pipeline._with_rows(docs.where("row_ > 0"))
    assert len(copies()) == len(before) + 1  # other rows than those of plain files still need one


def test_toxicity_learns_in_a_task(spark, monkeypatch):
    from spanfold.llm import toxicity as T

    driver, train = os.getpid(), T.train

    def elsewhere(docs, labels):
        assert os.getpid() != driver
        return train(docs, labels)

    monkeypatch.setattr(T, "train", elsewhere)
    monkeypatch.setattr(T, "STEP", 7)
    rows = [(i, passage(30, i) + (" swinish" if i % 3 == 0 else "")) for i in range(240)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(0, 240, 2)], "doc_id long, toxic int")
    net = T.fit(docs, labels, F.lit(True))
    below = sorted(r.doc_id for r in T.score(docs, net).collect() if r.score < 0.5)
    assert sorted(r.doc_id for r in T.drop_toxic(docs, net).collect()) == below and 0 < len(below) < 240
    assert T.fit(docs, labels.where("toxic = 1"), F.lit(True)) is None


def test_decontamination_of_short_items(spark):
    from spanfold.llm.decontam import contaminated

    bench = spark.createDataFrame([(1, "what is photosynthesis"), (2, "capital of Peru"), (3, "42"), (4, "lone")], "item_id long, text string")
    texts = [
        (10, f"{passage(60, 1)} what is photosynthesis {passage(60, 2)}"),
        (11, f"{passage(60, 3)} capital of Chile {passage(60, 4)} 42 {passage(9, 5)}"),
        (12, f"{passage(60, 6)} 17 what photosynthesis is {passage(60, 7)}"),
        (13, "lone what is photosynthesis"),
        (14, "it was Ann" + " Ann" * 60_000 + " and 1" + ".1" * 3_000),  # long runs of names and numbers
    ]
    got = {(r.doc_id, r.item_id) for r in contaminated(spark.createDataFrame(texts, "doc_id long, text string"), bench).collect()}
    assert got == {(10, 1), (11, 2), (11, 3), (13, 1), (13, 4)}


def test_ann_of_many_equal_vectors(spark):
    from spanfold.llm.ann import nearest

    rng = np.random.default_rng(6)
    x = rng.standard_normal((1500, 16)).astype(np.float32).astype(float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    ids = rng.permutation(1500)
    x[ids[:400]] = x[ids[0]]
    x[ids[400:700]] = x[ids[400]]
    asks = {int(i) for i in (*ids[:3], *ids[400:403])}
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = {}
    for r in nearest(df, F.col("vec_id").isin(sorted(asks)), k=10).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id))
    groups = [sorted(map(int, ids[:400])), sorted(map(int, ids[400:700]))]
    assert set(got) == asks
    for q, ranked in got.items():
        group = next(g for g in groups if q in g)
        assert [i for _, i in sorted(ranked)] == [i for i in group if i != q][:10]
