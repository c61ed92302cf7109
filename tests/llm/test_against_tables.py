"""Operators against brute force, SQL and held-out rows of the given tables; and on very long texts."""

import random

import duckdb
import numpy as np
import pytest
import regex
from pyspark.sql import functions as F

from spanfold.llm import queries as Q
from spanfold.llm.common import load

SMALL = "/root/testdata/sf0.01"


def words(n, seed):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefghij") for _ in range(r.randint(2, 8))) for _ in range(n))


@pytest.mark.parametrize("name", sorted(Q.oracle_sql()))
def test_queries_with_sql(spark, tiny, name):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    got = con.execute(Q.oracle_sql()[name])
    cols = [c[0] for c in got.description]
    df = getattr(Q, name)(spark, tiny)
    assert sorted(df.columns) == sorted(cols)
    assert sorted((tuple(r) for r in df.select(*cols).collect()), key=repr) == sorted(got.fetchall(), key=repr)


def test_language_on_held_out_documents(spark):
    truth = {r.doc_id: r.lang for r in load(spark, SMALL, "documents").select("doc_id", "lang").collect()}
    rows = [r for r in Q.op4_langid(spark, SMALL).collect() if r.held_out and truth[r.doc_id] is not None]
    assert len(rows) > 200 and sum(r.lang_pred == truth[r.doc_id] for r in rows) / len(rows) > 0.97


def test_toxicity_on_held_out_documents(spark):
    large = SMALL.replace("0.01", "0.1")  # the smaller tables have too few labels to tell
    truth = {r.doc_id: r.toxic for r in load(spark, large, "labels").collect()}
    rows = [r for r in Q.op8_toxicity(spark, large).collect() if r.held_out and r.doc_id in truth]
    assert len(rows) > 400 and sum(r.predicted == truth[r.doc_id] for r in rows) / len(rows) > 0.95


def test_labels_that_disagree_settle_alike(spark):
    from spanfold.llm.toxicity import fit

    docs = spark.createDataFrame([(i, f"{words(30, i)} {'scum' if i % 3 == 0 else 'fine'}", "en") for i in range(90)], "doc_id long, text string, lang string")
    labels = [(i, int(i % 3 == 0)) for i in range(90)]
    twice = [fit(docs, spark.createDataFrame(x, "doc_id long, toxic int"), F.lit(True)) for x in (labels + [(3, 0), (4, 1)], [(3, 0), (4, 1)] + labels[::-1])]
    assert all(np.array_equal(a, b) for a, b in zip(twice[0].tables, twice[1].tables)) and np.array_equal(twice[0].cuts, twice[1].cuts)


def test_neighbours_on_given_vectors(spark):
    rows = [(r.vec_id, np.array(r.embedding, dtype=float)) for r in load(spark, SMALL, "embeddings").collect()]
    ids, x = np.array([i for i, _ in rows]), np.stack([v for _, v in rows])
    found: dict = {}
    for r in Q.op10_ann(spark, SMALL).collect():
        found.setdefault(r.query_id, {})[r.rank] = r.vec_id
    hits = total = 0
    for q in ids[ids % 20 == 0]:
        score = x @ x[ids == q][0]
        want = sorted(((-s, i) for s, i in zip(score, ids) if i != q))[:20]
        hits += len(set(found[q].values()) & {i for _, i in want})
        total += 20
    assert hits / total >= 0.9


def test_licenses_against_every_window(spark):
    from spanfold.llm.license_scan import SHINGLE, TEMPLATES, _shingles, scan_licenses, words_of

    r = random.Random(4)
    names = sorted(TEMPLATES)
    data = []
    for i in range(120):
        own = words_of(TEMPLATES[names[i % len(names)]])
        for _ in range(r.choice([0, 1, 2, len(own) // 12, len(own) // 4, len(own) // 2])):
            own[r.randrange(len(own))] = "changed"
        data.append((i, f"{words(r.randint(0, 90), i)} {' '.join(own)} {words(r.randint(0, 90), -i)}"))
    got = {x.doc_id: x for x in scan_licenses(spark.createDataFrame(data, "doc_id long, text string")).collect()}

    def codes(ws):
        return _shingles([w.encode() for w in ws])

    sets = {n: set(codes(words_of(TEMPLATES[n])).tolist()) for n in names}
    for i, text in data:
        ws = words_of(text)
        row = codes(ws).tolist()
        best = {}
        for n in names:
            span = len(words_of(TEMPLATES[n])) - SHINGLE + 1
            best[n] = max(len(set(row[a : a + span]) & sets[n]) / len(sets[n]) for a in range(max(1, len(row) - span + 1)))
        top = max(best.values())
        hits = {h.license: h.containment for h in got[i].hits}
        assert all(c >= 0.8 for c in hits.values())
        if top >= 0.8:  # what some window holds best is found, with at least its share
            assert hits and max(hits.values()) >= top - 1e-9
        # the stretch around a window may hold a little more than any window of the template's length
        assert all(best[n] > 0.6 for n in hits)


def tokens_of(text):
    from spanfold.llm import decontam as D

    clean = text.translate({1: " ", 2: " ", 3: " "})
    named = regex.sub(D._NAME, D.NAME, clean)
    typed = regex.sub(D._NUMBER, f" {D.NUM} ", regex.sub(D._MEASURE, f" {D.NUM} {D.UNIT} ", named))
    return regex.findall(D._TOKEN, typed.lower())


def test_decontamination_against_brute_force(spark):
    from spanfold.llm import decontam as D

    r = random.Random(8)
    names, units = ["Anna", "Ben", "Clara Meyer", "Dirk", "Eve"], ["kg", "miles", "hours", "%"]

    def item():
        out = words(r.randint(3, 9), r.random()).split()
        for _ in range(r.randint(0, 3)):
            out.insert(r.randrange(len(out) + 1), r.choice([r.choice(names), str(r.randint(2, 99)), f"{r.randint(2, 99)} {r.choice(units)}"]))
        return " ".join(out) + r.choice([".", "?", ""])

    def changed(text):
        return regex.sub(r"\d+", lambda m: str(int(m.group()) + r.choice([0, 3])), text)

    items = [(i, " ".join(item() for _ in range(r.randint(1, 4)))) for i in range(25)]
    docs = []
    for i in range(80):
        parts = [words(r.randint(0, 25), i), changed(r.choice(items)[1]) if r.random() < 0.7 else "", words(r.randint(0, 25), -i)]
        if r.random() < 0.3:
            parts[1] = " ".join(parts[1].split()[: r.randint(1, 20)])
        docs.append((i, ". ".join(parts)))
    got = {(x.doc_id, x.item_id): x for x in D.contaminated(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    seen = set()
    for d, text in docs:
        mine = tokens_of(text)
        for i, ask in items:
            own = tokens_of(ask)
            n = min(D.WINDOW, len(own))
            asked = {tuple(own[a : a + n]) for a in range(len(own) - n + 1)}
            held = {tuple(mine[a : a + n]) for a in range(len(mine) - n + 1)}
            share = len(asked & held) / len(asked)
            worded = any(t not in (D.NUM, D.UNIT, D.NAME) for t in own)
            if (d, i) in got:
                assert got[d, i].coverage == pytest.approx(share) and share >= D.LEAST_COVER
            elif share >= D.LEAST_COVER and worded:
                seen.add((d, i))  # slots must contradict one another for a pair to go
                assert D.NUM in own or D.NAME in own
    assert len(got) > 30 and len(seen) < len(got) / 5
    whole = {(d, i) for d, t in docs for i, a in items if a in t and any(x not in (D.NUM, D.UNIT, D.NAME) for x in tokens_of(a))}
    assert len(whole) > 5 and all(got[p].slot_match == 1 and got[p].same_slots for p in whole if p in got and got[p].coverage == 1)


def test_slots_are_compared_where_the_windows_match(spark):
    from spanfold.llm.decontam import contaminated

    bench = spark.createDataFrame([(1, "a train leaves at 9 and runs 9 hours before it meets another train from the north")], "item_id long, text string")
    docs = spark.createDataFrame([
        (1, "we saw 4 and 4 there and later a train leaves at 7 and runs 7 hours before it meets another train from the north"),
        (2, "in 9 of 9 cases a train leaves at 5 and runs 6 hours before it meets another train from the north"),
        (3, "in 9 of 9 hours a train leaves at 9 and runs 9 hours before it meets another train from the north"),
    ], "doc_id long, text string")
    got = {r.doc_id: r for r in contaminated(docs, bench).collect()}
    # 9 is a number once and a measure once, so each slot text is a value of its own
    assert got[1].slot_match == 1 and not got[1].same_slots and got[3].same_slots
    assert got[2].slot_match == 1 and not got[2].same_slots


def test_names_at_the_start_of_sentences(spark):
    from spanfold.llm.decontam import contaminated

    bench = spark.createDataFrame([(1, "Anna buys nine red apples at market today. Ben eats them")], "item_id long, text string")
    docs = spark.createDataFrame([(1, "Clara buys nine red apples at market today. Dirk eats them"), (2, "The buys nine red apples at market")], "doc_id long, text string")
    assert [(r.doc_id, r.coverage) for r in contaminated(docs, bench).collect()] == [(1, 1.0)]


def test_very_long_texts(spark):
    from spanfold.llm.decontam import contaminated, slots, template
    from spanfold.llm.langid import identify
    from spanfold.llm.license_scan import TEMPLATES, scan_licenses
    from spanfold.llm.mixing import mixed_sizes
    from spanfold.llm.toxicity import score

    n = 100_000
    runs = ["Berg " * n, "12.5," * n, "7 kg " * n, "A" * n, "1" * n, "Ünder " * n, "-$9:" * n]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(runs)], "doc_id long, text string")
    sizes = [(r.t, r.s) for r in df.orderBy("doc_id").select(F.size(template(F.col("text"))).alias("t"), F.size(slots(F.col("text"))).alias("s")).collect()]
    assert sizes[0] == (1, 1) and sizes[2][1] == n and all(t >= 1 for t, _ in sizes)
    long = words(150_000, 1)
    docs = spark.createDataFrame([(1, f"{long} {TEMPLATES['MIT']} {long}", "en", "a"), (2, "the and with", "en", "b"), (3, words(50, 2), "de", "b")], "doc_id long, text string, lang string, source string")
    bench = spark.createDataFrame([(1, " ".join(long.split()[70_000:70_020]))], "item_id long, text string")
    assert [r.doc_id for r in contaminated(docs, bench).collect()] == [1]
    assert {r.doc_id: r.licenses for r in scan_licenses(docs).collect()}[1] == "MIT"
    assert identify(docs, dims=128).count() == 3 and score(docs, None).count() == 3
    taken = {r.doc_id: r for r in mixed_sizes(docs).collect()}
    assert taken[1].size == 300_000 + len(TEMPLATES["MIT"].split()) and taken[1].taken <= 3 * taken[1].size


def test_finished_archives_need_only_their_folder(spark, tiny, tmp_path):
    from spanfold.llm.warc import listed, read_archives, write_archives

    pages = load(spark, tiny, "pages")
    target, _ = write_archives(pages, f"file://{tmp_path}/w", roll_bytes=20_000)
    files = listed(spark, target)
    assert files.count() > 1 and read_archives(target, files).count() == pages.count()
    first = sorted((tmp_path / "w").glob("pages-*"))[0]
    first.write_bytes(first.read_bytes()[:-40])
    with pytest.raises(Exception, match="truncated|not the one"):
        read_archives(target, files).count()


def test_payloads_of_many_pages(spark, monkeypatch, tmp_path):
    from spanfold.llm import warc

    monkeypatch.setattr(warc, "HOT_COPIES", 5)
    monkeypatch.setattr(warc, "SHARD_BYTES", 100)
    rows = [(i, "u", "same" if i % 3 else f"own {i}") for i in range(60)] + [(100 + i, "u", "few") for i in range(3)]
    target, manifest = warc.write_archives(spark.createDataFrame(rows, "page_id long, url string, html string"), f"file://{tmp_path}/w")
    got = {r.page_id: (r.record_type, r.refers_to) for r in warc.read_archives(target, manifest).collect()}
    assert manifest.count() == 3 and got[59] == ("response", None) and got[1] == ("revisit", 59) and got[100] == ("revisit", 102) and got[0] == ("response", None)
