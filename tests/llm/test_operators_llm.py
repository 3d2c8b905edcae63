"""Each operator against brute force, an exact round trip or held-out accuracy, and on odd input."""

import hashlib
import itertools
import tracemalloc

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from bandloom.llm import bpe, chat, decontaminate, langid, maglev, maxscore, ngrams, quality, queries, simhash, toxicity, warc
from bandloom.runtime import scratch, table

ODD = "doc_id long, text string, lang string, source string, n_chars long, score double, fp long, slot int, cell string, component_id string"


@pytest.fixture(scope="module")
def odd_docs(spark):
    """Nulls, empty and long texts, repeated rows and ids, ties, and columns whose names an operator uses."""
    long_text = "lorem ipsum dolor " * 20_000
    rows = [(1, None), (2, ""), (3, "   \n\t "), (4, "one"), (5, "one two three"), (5, "one two three"), (6, long_text), (7, long_text), (None, "a b c d e f g"), (None, None), (8, "x" * 9000), (9, "é\U0001f600 日本 123"), (10, "12 34 !!")]
    return spark.createDataFrame([(i, t, None, None, None, 1.5, 7, 3, "c", "d") for i, t in rows], ODD)


@pytest.fixture(scope="module")
def no_docs(spark):
    return spark.createDataFrame([], ODD)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return table(spark, sf, "documents")


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(same, name):
    same(queries.QUERIES[name], queries.ORACLES[name])


# MaxScore


def brute_top(rows, k=5, every=50):
    out = []
    for qid, q in sorted({(i, tuple(v)) for i, v in rows if i % every == 0}):  # each distinct query row
        scored = sorted(((-sum(a * b for a, b in zip(q, v, strict=True)), i) for i, v in rows if i != qid and len(v) == len(q)))[:k]
        out += [(qid, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    return sorted(out)


def embeddings(spark, rows):
    return spark.createDataFrame(rows, "vec_id long, embedding array<double>")


def found_top(df, **kw):
    return sorted(tuple(r) for r in maxscore.top_k(df, **kw).collect())


def integers(rows):
    return [(i, [int(np.floor(256 * x)) if abs(x) < 2**40 else 256 * int(x) for x in v]) for i, v in rows]


def test_maxscore_equals_brute_force_with_ties_and_odd_rows(spark):
    rng = np.random.default_rng(1)
    good = [(i, [float(x) for x in rng.integers(-3, 4, 6)]) for i in range(400)] + [(1000 + i, [1.0] * 6) for i in range(40)] + [(77, [0.5] * 6), (77, [0.5] * 6), (50, [2.0, 1.0]), (100, [])]
    bad = [(None, [1.0] * 6), (2000, None), (2050, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (2051, [float("nan")] * 6), (2052, [float("inf")] * 6)]
    df = embeddings(spark, good + bad).withColumn("v", F.lit("clash")).repartition(5)
    assert found_top(df, block=4) == brute_top(integers(good)) == found_top(df)
    assert maxscore.top_k(df.limit(0)).count() == 0


def test_maxscore_large_components_and_many_dimensions(spark):
    rng = np.random.default_rng(7)
    huge = [(i, [float(x) * 10.0 ** int(rng.integers(0, 7)) for x in rng.normal(size=3)]) for i in range(60)] + [(50, [2_000_000.0, 1.5, -2.0]), (100, [0.0, 1e-9, 1e7])]
    assert found_top(embeddings(spark, huge)) == brute_top(integers(huge))
    wide = [(i, [float(x) for x in rng.integers(-(2**19), 2**19, 256)]) for i in range(40)] + [(50, [2.0**19] * 256), (51, [2.0**19] * 256), (52, [-(2.0**19)] * 256)]
    assert found_top(embeddings(spark, wide)) == brute_top(integers(wide))
    long_ = [(i, [float(x) for x in rng.normal(size=5000)]) for i in range(51)]
    assert found_top(embeddings(spark, long_)) == brute_top(integers(long_))
    with pytest.raises(Exception, match="exceeds a long"):
        found_top(embeddings(spark, [(0, [1e30]), (1, [1.0])]))
    exact = [(0, [0.0, 2.0**40]), (1, [2.0**40, 5.0]), (3, [2.0**50, -7.25]), (5, [-(2.0**60), 0.5])]
    assert found_top(embeddings(spark, exact)) == brute_top(integers(exact))


def test_maxscore_repeated_ids_agree_with_sql(spark, tmp_path):
    import duckdb

    rng = np.random.default_rng(3)
    rows = [(i % 70, [float(x) for x in rng.integers(-2, 3, 4)]) for i in range(200)] + [(50, [1.0, 2.0, 3.0, 4.0]), (50, [1.0, 2.0, 3.0, 4.0]), (None, [1.0] * 4), (0, []), (3, [])]
    df = embeddings(spark, rows)
    df.write.parquet(str(tmp_path / "e"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{tmp_path}/e/*.parquet')")
    got = found_top(df, block=3)
    assert got == sorted(con.execute(queries.OP1_SQL).fetchall()) == brute_top(integers([r for r in rows if r[0] is not None]))


def test_maxscore_prunes():
    rng = np.random.default_rng(2)
    rows, q = rng.integers(0, 3, (5000, 32)).astype(float), np.zeros(32)
    q[:2], q[2:10] = 50, 1
    best = maxscore.Best(1, 5)
    for at in range(0, 5000, 1000):
        maxscore.search_block(np.arange(at, at + 1000), rows[at : at + 1000], np.array([-1]), q[None], best, np.array([0]))
    want = np.lexsort((np.arange(5000), -(rows @ q)))[:5]
    assert best.ids[0].tolist() == want.tolist()
    assert best.touched < 0.4 * rows.size


# SimHash


def slow_fingerprint(text, size=4):
    import re

    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(words[i : i + size]).encode(), 42) for i in range(max(1, len(words) - size + 1))]
    return sum(1 << b for b in range(64) if 2 * sum((x >> b) & 1 for x in h) > len(h))


def slow_components(prints, radius=4):
    ids = list(prints)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(ids, 2):
        if bin(prints[a] ^ prints[b]).count("1") <= radius:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_simhash_equals_brute_force(spark, sf):
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op2_simhash_near_dedup(spark, sf).collect()}
    prints = {r.doc_id: slow_fingerprint(r.text) for r in table(spark, sf, "documents").collect()}
    want = slow_components(prints)
    assert got == {i: (f"{prints[i]:016x}", want[i]) for i in prints}


@settings(max_examples=40, deadline=None)
@given(st.text(alphabet="aBÄ  \t\n\x0b\x1f", max_size=40))
def test_fingerprint(text):
    assert simhash.fingerprint(text) == slow_fingerprint(text)


@pytest.mark.parametrize("most", [simhash.CELL_VARIANTS, 3_000])
def test_cells_find_every_link(most):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, 300).astype(np.uint64)
    near = base.copy()
    for i in range(len(near)):
        for b in rng.choice(64, i % 7, replace=False):
            near[i] ^= np.uint64(1) << np.uint64(b)
    fps = np.unique(np.concatenate([base, near]))
    links = set()
    for cell in range(32):
        own = fps[np.bitwise_count((fps >> np.uint64(59)) ^ np.uint64(cell)) <= 2]
        links |= {tuple(sorted((int(a), int(b)))) for a, b in zip(*simhash.cell_links(own, cell, 5, 4, most), strict=True)}
    parts = slow_components({int(f): int(f) for f in fps})
    root = {int(f): int(f) for f in fps}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in links:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    assert {f: find(f) for f in root} == parts


@pytest.mark.parametrize("radius", [0, 2, 4, 6])
def test_links_of_every_radius(spark, radius):
    rng = np.random.default_rng(radius)
    base = rng.integers(0, 2**63, 60).astype(np.uint64)
    fps = set(base.tolist())
    for i, f in enumerate(base.tolist()):
        for b in rng.choice(64, i % 8, replace=False).tolist():
            f ^= 1 << b
        fps.add(f)
    classes = spark.createDataFrame([(int(np.uint64(f).view(np.int64)),) for f in fps], "fp long")
    got = {r.fp & (2**64 - 1): r.root & (2**64 - 1) for r in simhash.rooted(classes, radius).collect()}
    want = slow_components({f: f for f in fps}, radius)
    assert {frozenset(f for f in fps if got[f] == r) for r in got.values()} == {frozenset(f for f in fps if want[f] == r) for r in want.values()}


def test_odd_radii_are_refused(spark):
    for radius in (1, 3, 5, 8):
        with pytest.raises(ValueError, match="radius"):
            simhash.links(spark.range(3).select(F.col("id").alias("fp")), 3, radius)


def test_components_of_a_long_chain(spark):
    chain = spark.range(300).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b")).unionByName(spark.createDataFrame([(1000, 1001), (1001, 1000)], "a long, b long"))
    got = {r.node: r.root for r in simhash.components(chain).collect()}
    assert all(got[i] == 0 for i in range(1, 301)) and got[1001] == 1000


def test_crowded_cell_stays_bounded():
    masks = simhash.flips(64, 2)
    fps = np.unique(masks ^ np.uint64(0x0123456789ABCDEF))
    tracemalloc.start()
    parts = [simhash.cell_links(fps[np.bitwise_count((fps >> np.uint64(59)) ^ np.uint64(c)) <= 2], c, 5, 4, 200_000) for c in range(32)]
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 64 << 20
    at = [np.searchsorted(fps, np.concatenate(ends)) for ends in zip(*parts, strict=True)]
    node, root = simhash.forest(fps, *at)
    assert len(node) == len(fps) - 1 and set(root.tolist()) == {int(fps[0])}


def test_simhash_odd_input(odd_docs, no_docs):
    rows = simhash.near_duplicates(odd_docs).collect()
    assert len(rows) == 13
    assert {r.component_id for r in rows if r.doc_id in (1, 2, 3)} == {1}
    assert {r.component_id for r in rows if r.doc_id in (6, 7)} == {6}
    assert {r.component_id for r in rows if r.doc_id == 5} == {5}
    assert simhash.near_duplicates(no_docs).count() == 0
    kept = simhash.one_of_each(odd_docs)
    assert kept.columns == odd_docs.columns
    assert sorted(r.doc_id for r in kept.where("doc_id is not null").collect()) == [1, 4, 5, 6, 8, 9, 10]


def test_one_of_each_goes_by_row(spark):
    a, b, c, d, e, f = (" ".join(f"{x}{i}" for i in range(40)) for x in "abcdef")
    rows = [(1, a), (1, b), (2, a), (3, e), (3, a), (4, f), (4, f), (None, c), (None, d), (None, a), (None, None), (5, c)]
    docs = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(rows)], "doc_id long, text string, fp int").repartition(3)
    got = simhash.one_of_each(docs)
    assert got.columns == docs.columns
    assert sorted(((r.doc_id, r.text) for r in got.collect()), key=repr) == sorted([(1, a), (1, b), (3, e), (4, f), (None, c), (None, d), (None, a), (None, None), (5, c)], key=repr)
    assert simhash.one_of_each(docs.limit(0)).count() == 0


# Decontamination


def test_decontamination_equals_planted_cases(spark):
    item = "the quick brown fox jumps over the lazy dog while seven small birds watch from an old fence in spring".split()
    other = [f"w{i}" for i in range(60)]

    def doc(words):
        return " ".join([*other[:25], *words, *other[25:]])

    swapped = [w if i % 7 != 3 else "zzz" for i, w in enumerate(item)]
    cases = {1: doc(item), 2: doc(swapped), 3: doc(item[3:17]), 4: doc(item[:7]), 5: " ".join(other), 6: doc(item).upper(), 7: None, 8: "", 9: doc([w if i % 2 else "q" for i, w in enumerate(item)]), 10: doc(item) + " " + doc(item)}
    df = spark.createDataFrame(list(cases.items()), "doc_id long, text string").withColumn("item_id", F.lit("clash"))
    bench = spark.createDataFrame([(1, " ".join(item)), (1, " ".join(item)), (2, "short one"), (None, "a"), (3, None), (4, "")], "item_id long, text string")
    got = decontaminate.contamination(df, bench)
    assert sorted({(r.doc_id, r.item_id) for r in got.collect()}) == [(1, 1), (2, 1), (3, 1), (6, 1), (10, 1)]
    kept = decontaminate.without_contaminated(df, bench)
    assert sorted(r.doc_id for r in kept.collect()) == [4, 5, 7, 8, 9] and kept.columns == df.columns
    assert decontaminate.contamination(df, bench.limit(0)).count() == 0 == decontaminate.contamination(df.limit(0), bench).count()
    assert decontaminate.without_contaminated(df, bench.limit(0)).count() == 10


def brute_window(equal, least):
    return any(5 * sum(equal[a:b]) >= 4 * (b - a) for a in range(len(equal)) for b in range(a + least, len(equal) + 1))


def test_decontamination_finds_substitutions_at_every_position():
    rng = np.random.default_rng(8)
    for size in (8, 12, 13, 15, 16, 20, 25):
        item = [f"t{i}" for i in range(size)]
        seeds = decontaminate.Seeds.build([(1, item)])
        most = size // 5
        spots = [c for k in (1, 2) if k <= most for c in itertools.combinations(range(size), k)]
        spots += [tuple(rng.choice(size, k, replace=False)) for k in range(3, most + 3) for _ in range(60)]
        lost = wanted = 0
        for spot in spots:
            equal = [i not in spot for i in range(size)]
            text = " ".join(["x"] * 9 + [w if e else "y" for w, e in zip(item, equal, strict=True)] + ["z"] * 9)
            want, got = brute_window(equal, min(13, size)), seeds.matches([text])[0]
            masks = decontaminate.MASKS + ((decontaminate.SHORT_MASK,) if size < decontaminate.SHORT_ITEM else ())
            hit = any(all(equal[s + o] for o in decontaminate.offsets(m)) for m in masks for s in range(size - len(m) + 1))
            assert bool(got) == (want and hit), (size, spot)
            wanted, lost = wanted + want, lost + (want and not hit)
            if len(spot) <= 2:
                assert got, (size, spot)
        assert lost <= 0.02 * wanted


@settings(max_examples=60, deadline=None)
@given(st.lists(st.booleans(), max_size=30))
def test_longest_window(equal):
    start, end, same = decontaminate.longest_window(np.array(equal, bool))
    assert same == sum(equal[start:end]) and 5 * same >= 4 * (end - start)
    assert not brute_window(equal, end - start + 1)


def slow_matches(items, text):
    """Ids of the items of which the text holds a window of 13 tokens (or a whole shorter item) with an identity of 0.8."""
    words, found = decontaminate.tokens(text), set()
    for item, own in items:
        least = min(13, len(own))
        for shift in range(least - len(own), len(words) - least + 1):
            a, b = max(0, -shift), min(len(own), len(words) - shift)
            score = np.concatenate([[0], np.cumsum([1 if own[k] == words[shift + k] else -4 for k in range(a, b)])])
            low = np.minimum.accumulate(score)
            if any(score[e] >= low[e - least] for e in range(least, len(score))):
                found.add(item)
                break
    return found


def test_decontamination_recall_on_the_tables(spark, sf):
    rng = np.random.default_rng(4)
    items = [(r.item_id, decontaminate.tokens(r.text)) for r in table(spark, sf, "benchmark").orderBy("item_id").collect()][:20]
    items += [(1000 + n, [f"s{n}{k}" for k in range(n)]) for n in (8, 10, 11, 13, 14)]
    bench = spark.createDataFrame([(i, " ".join(ts)) for i, ts in items], "item_id long, text string")
    plain = [r.text for r in table(spark, sf, "documents").where("length(text) < 600").orderBy("doc_id").limit(20).collect()]
    docs = [(n, t) for n, t in enumerate(plain)]
    for item, own in items:
        for share in (0.0, 0.1, 0.2, 0.3):
            copy = [w if rng.random() >= share else "zzz" for w in own]
            cut = copy[int(rng.integers(0, 3)) :]
            docs.append((len(docs), f"{plain[len(docs) % 20]} {' '.join(cut)} {plain[(len(docs) + 7) % 20]}"))
    want = {(d, i) for d, t in docs for i in slow_matches(items, t)}
    got = {(r.doc_id, r.item_id) for r in decontaminate.contamination(spark.createDataFrame(docs, "doc_id long, text string"), bench).collect()}
    assert got <= want and len(got) >= 0.97 * len(want) and len(want) > 60


def test_decontamination_of_repetitive_and_very_long_texts(spark):
    import time

    items = [(1, ["ha"] * 400), (2, ["ha", "ho"] * 60), (3, [f"u{k}" for k in range(30)])]
    seeds = decontaminate.Seeds.build(items)
    began = time.monotonic()
    long_ = " ".join(["ha"] * 60_000)
    got = seeds.matches([long_, "ha ho " * 20_000, None, "", " ".join([*[f"x{k}" for k in range(200_000)], *items[2][1], "y"]), "ha " * 12])
    assert time.monotonic() - began < 30
    assert [sorted(m[0] for m in ms) for ms in got] == [[1], [2], [], [], [3], []]
    assert got[0] == [(1, 400, 400, got[0][0][3], 0)] and got[4] == [(3, 30, 30, 200_000, 0)]


def test_decontamination_by_blocks_equals_one_block(spark, sf, monkeypatch):
    docs, bench = table(spark, sf, "documents"), table(spark, sf, "benchmark")
    whole = sorted(map(tuple, decontaminate.contamination(docs, bench).collect()))
    clean = {r.doc_id for r in decontaminate.without_contaminated(docs, bench).collect()}
    blocks = decontaminate.seed_blocks
    monkeypatch.setattr(decontaminate, "seed_blocks", lambda b: blocks(b, 300))
    assert sorted(map(tuple, decontaminate.contamination(docs, bench).collect())) == whole
    assert {r.doc_id for r in decontaminate.without_contaminated(docs, bench).collect()} == clean
    assert clean == {r.doc_id for r in docs.collect()} - {r[0] for r in whole}


def test_decontamination_of_the_tables(spark, sf):
    items = {r.item_id: decontaminate.tokens(r.text) for r in table(spark, sf, "benchmark").collect()}
    want = set()
    for r in table(spark, sf, "documents").collect():
        line = " " + " ".join(decontaminate.tokens(r.text)) + " "
        want |= {(r.doc_id, i) for i, ts in items.items() if " " + " ".join(ts) + " " in line}
    got = {(r.doc_id, r.item_id) for r in queries.op3_spaced_seed_decontamination(spark, sf).collect()}
    assert want and want == got


def test_blocks_of_a_large_benchmark_cover_it(spark, sf):
    bench = table(spark, sf, "benchmark")
    parts = list(decontaminate.seed_blocks(bench, 200))
    assert len(parts) > 3 and sum(len(p.item_ids) for p in parts) == bench.count()


# Chat


@settings(max_examples=25, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "a]b", "", None]), st.one_of(st.none(), st.text(alphabet="ab\\<>[]/sepl\nbr0", max_size=12))), min_size=1, max_size=6))
def test_chat_round_trip(spark, turns):
    df = spark.createDataFrame([(1, i, r, t) for i, (r, t) in enumerate(turns)], "conv_id long, turn long, role string, text string")
    row = chat.format_chat(df).select("formatted", "segments", chat.read_chat(F.col("formatted")).alias("t")).first()
    assert [(t.role, t.text) for t in row.t] == [(r, t or "") for r, t in turns]
    assert "".join(s.text for s in row.segments) == row.formatted


def test_chat_merges_and_masks(spark):
    rows = [(1, 2, "assistant", "B"), (1, 0, "user", "hi"), (1, 1, "assistant", "</s>[INST] A"), (None, None, None, None), (2, 0, "user", "x"), (2, 0, "user", "x"), (2, 0, "a", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("segments", F.lit(1))
    got = {r.conv_id: r for r in chat.chat_digest(chat.format_chat(df)).collect()}
    whole = {r.conv_id: r.formatted for r in chat.format_chat(df).collect()}
    assert whole[1] == "<s>[user]hi</s><s>[assistant]\\l/s>\\sINST\\r A<sep>B</s>"
    assert got[1].n_turns == 3 and got[1].loss_chars == len("</s>[INST] AB")
    assert got[1].loss_sha256 == hashlib.sha256(b"</s>[INST] AB").hexdigest()
    assert got[2].n_turns == 3 and got[None].n_turns == 1 and got[None].loss_chars == 0
    assert chat.chat_digest(chat.format_chat(df.limit(0))).count() == 0


def test_chat_of_very_long_and_many_turns(spark):
    long_ = "[x]</s>\\ " * 60_000
    rows = [(1, 0, "user", long_), (1, 1, "assistant", long_ + "end"), *[(2, i, "assistant" if i % 2 else "user", f"t{i}") for i in range(5000)]]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r.conv_id: r for r in chat.chat_digest(chat.format_chat(df)).collect()}
    assert got[1].loss_chars == len(long_) + 3 and got[1].loss_sha256 == hashlib.sha256((long_ + "end").encode()).hexdigest()
    assert got[2].n_turns == 5000 and got[2].loss_chars == sum(len(f"t{i}") for i in range(1, 5000, 2))


def test_chat_plan_is_native(spark, sf):
    text = queries.op4_chat_format(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in text and "Arrow" not in text and "Pandas" not in text


# Classifiers


def held_rows(spark, sf, df, label, folds, held):
    return df.join(table(spark, sf, "labels").select("doc_id", label), "doc_id").where("held_out").collect()


def test_toxicity_held_out(spark):
    sf = "/root/testdata/sf0.01"
    rows = held_rows(spark, sf, queries.op5_toxicity(spark, sf), "toxic", 3, 1)
    assert len(rows) > 80
    assert np.mean([r.predicted == r.toxic for r in rows]) >= 0.93
    assert all(0 <= r.score <= 1 for r in rows)


def test_quality_held_out(spark):
    sf = "/root/testdata/sf0.01"
    rows = held_rows(spark, sf, queries.op9_quality(spark, sf), "quality", 4, 2)
    assert len(rows) > 60
    assert np.mean([r.predicted == r.quality for r in rows]) >= 0.9


def test_language_held_out(spark):
    sf = "/root/testdata/sf0.01"
    got = queries.op10_language_id(spark, sf).where("held_out").join(table(spark, sf, "documents").select("doc_id", "lang"), "doc_id").collect()
    assert len(got) > 150
    assert np.mean([r.lang_pred == r.lang for r in got if r.lang_pred != "und"]) >= 0.95


def test_scores_of_odd_input(spark, odd_docs, no_docs, docs, sf):
    labels = table(spark, sf, "labels")
    tox = toxicity.scored(odd_docs, toxicity.fit(docs, labels), "t")
    assert tox.count() == 13 and set(odd_docs.columns) < set(tox.columns)
    assert tox.where("score = 1.5 and t between 0 and 1").count() == 13
    good = toxicity.scored(odd_docs, quality.fit(docs, labels), "q").where("q between 0 and 1")
    assert good.count() == 13
    got = langid.identified(odd_docs, langid.fit(docs), "x_").select("doc_id", "x_lang_pred", "x_score").collect()
    assert {r.x_lang_pred for r in got if r.doc_id in (1, 2, 3, 10)} == {"und"}
    assert all(r.x_lang_pred != "und" for r in got if r.doc_id in (4, 5, 6, 8, 9))
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert toxicity.toxicity(docs, none).where("predicted = 1").count() == 0
    assert quality.quality(docs, none).where("score = 0.5").count() == docs.count()
    assert langid.language_id(no_docs).count() == 0 == toxicity.toxicity(no_docs, labels).count() == quality.quality(no_docs, none).count()


def test_no_learning_from_held_out_rows_or_labels_of_other_columns(spark):
    from bandloom.llm.common import learnable

    df = spark.range(1000)
    import zlib

    assert {r.id for r in df.where(learnable(F.col("id"), 3, 1)).collect()} == {i for i in range(1000) if zlib.crc32(str(i).encode()) % 3 != 1}


def test_codewords_are_apart():
    for k in (2, 3, 4, 7, 8, 12, 40, 130):
        code = langid.codewords(k)
        assert len(code) == k
        assert min((code[i] != code[j]).sum() for i in range(k) for j in range(i)) >= (1 if k == 2 else 2 ** (k - 2) if k <= 7 else 15)
        columns = {(c ^ c[0]).tobytes() for c in code.T}
        assert len(columns) == code.shape[1] and all(0 < c.sum() < k for c in code.T) or k == 2
    code = langid.codewords(30)
    assert langid.nearest(code) == min((code[i] != code[j]).sum() for i in range(30) for j in range(i))


def test_many_languages(spark):
    words = [f"{chr(97 + k % 26)}{chr(97 + k // 26 % 26)}{chr(97 + k // 7 % 26)}qo" for k in range(600)]
    rows = [(4 * (600 * j + k), f"{w} {w}{j}a {w}", f"l{k:03d}") for k, w in enumerate(words) for j in range(3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.fit(docs)
    assert len(model.langs) > 400 and model.table.shape == (1 << langid.BITS, model.code.shape[1])
    got = [model.predict(f"{w} {w}")[0] for w in words[:50]]
    assert np.mean([g == f"l{k:03d}" for k, g in enumerate(got) if f"l{k:03d}" in model.langs]) > 0.8
    one = langid.language_id(docs.withColumn("lang", F.lit("xx")))
    assert one.where("lang_pred <> 'xx' or score < 0 or score > 1").count() == 0
    silent = langid.language_id(docs.withColumn("text", F.lit("12 34")))
    assert silent.where("lang_pred <> 'und' or score <> 0").count() == 0


def test_bounded_sample(spark):
    from bandloom.llm import common

    rows = spark.range(3000).select(F.col("id").alias("doc_id"), (F.col("id") % 300 % 7).alias("y"), F.lit(1).alias("_n"))
    got = common.bounded_per_class(rows, "doc_id", "y", 100)
    assert got.columns == rows.columns
    for r in got.groupBy("y").count().collect():
        assert 60 < r["count"] < 150
    before = {tuple(r) for r in got.collect()}
    common.SMALL, small = 0, common.SMALL  # the way without a broadcast
    try:
        assert {tuple(r) for r in common.bounded_per_class(rows, "doc_id", "y", 100).collect()} == before
    finally:
        common.SMALL = small
    texts = spark.createDataFrame([(i, "x" * 100) for i in range(50)], "h long, text string")
    assert [r.h for r in common.bounded_rows(texts, "text", "h", 1000)] == list(range(10))
    assert len(common.bounded_rows(texts, "text", "h", 10)) == 1


def ids_of_fold(folds, held, n, inside=False):
    import zlib

    return [i for i in range(5000) if (zlib.crc32(str(i).encode()) % folds == held) == inside][:n]


@pytest.mark.parametrize("case", ["ones", "zeros", "empty ones", "empty zeros", "all empty", "null", "contradictory"])
def test_scores_stay_probabilities(spark, case):
    rng = np.random.default_rng(5)
    ids = ids_of_fold(12, 10, 60)

    def text(i, y):
        if case == "all empty" or case == "empty ones" and y or case == "empty zeros" and not y:
            return ""
        return None if case == "null" else " ".join(rng.choice(["fine", "good", "useful"] if y else ["spam", "click", "win"], 30)) + str(i)

    mark = {i: 1 if case == "ones" else 0 if case == "zeros" else k % 2 for k, i in enumerate(ids)}
    docs = spark.createDataFrame([(i, text(i, y), "aa") for i, y in mark.items()] + [(None, "x", None), (9999, "", None)], "doc_id long, text string, lang string")
    marks = [(i, y, y) for i, y in mark.items()] + ([(i, 1 - y, 1 - y) for i, y in mark.items()] if case == "contradictory" else [(i, y, y) for i, y in mark.items()])
    labels = spark.createDataFrame([*marks, (None, 1, 1), (ids[0], None, None), (ids[0], 7, 7)], "doc_id long, quality int, toxic int")
    for got in (quality.quality(docs, labels), toxicity.toxicity(docs, labels), langid.language_id(docs)):
        assert got.count() == 62 and got.where("score between 0 and 1").count() == 62
    if case == "zeros":
        assert toxicity.toxicity(docs, labels).where("score <> 0").count() == 0
    if case == "ones":
        assert quality.quality(docs, labels).where("score <> 1").count() == 0


def slow_ngrams(text, orders):
    """Hashes of the distinct character n-grams, one character at a time."""
    out, top = set(), 2**64
    for n in orders:
        for i in range(len(text) - n + 1):
            h = 0
            for k, c in enumerate(text[i : i + n]):
                h = (h * 0xD6E8FEB86659FD93 + ord(c) + k + 1) % top
            out.add(h * 0x9E3779B97F4A7C15 % top)
    return out


def logistic(z):
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def test_toxicity_equals_plain_python(spark, docs, sf):
    labels = table(spark, sf, "labels")
    model = toxicity.fit(docs, labels)
    weight = dict(zip(model.features.tolist(), model.weights.tolist(), strict=True))
    got = {r.doc_id: r for r in toxicity.toxicity(docs, labels).collect()}
    rows = sorted(docs.collect(), key=lambda r: len(r.text or ""))[:120]
    for r in rows:
        line = " " + " ".join((r.text or "").lower().split()) + " " if r.text else ""
        want = logistic(sum(weight.get(h, 0.0) for h in slow_ngrams(line, (4, 5, 6))) + model.bias)
        assert got[r.doc_id].score == pytest.approx(want, abs=1e-9) and got[r.doc_id].predicted == int(want >= 0.7)


def test_quality_equals_plain_python(spark, docs, sf):
    import zstandard

    labels = table(spark, sf, "labels")
    model = quality.fit(docs, labels)
    got = {r.doc_id: r.score for r in quality.quality(docs, labels).collect()}

    def size(raw, data):
        c = zstandard.ZstdCompressor(level=3, dict_data=zstandard.ZstdCompressionDict(raw), write_content_size=False, write_dict_id=False, write_checksum=False)
        return len(c.compress(data))

    for r in docs.orderBy("doc_id").limit(40).collect():
        raw = (r.text or "").encode()
        parts = [raw[i : i + 2048] for i in range(0, len(raw), 2048)]
        x = sum(size(model.bad, p) - size(model.good, p) for p in parts) / max(len(raw), 1)
        want = logistic(x * model.beta[0] + min(max(x, -0.05), 0.05) * model.beta[1] + model.beta[2])
        assert got[r.doc_id] == pytest.approx(want, abs=1e-2)


def test_language_equals_plain_python(spark, docs):
    import math
    import unicodedata

    model = langid.fit(docs)
    got = {r.doc_id: r for r in langid.language_id(docs).collect()}
    rows = [r for r in docs.collect() if len(r.text or "") < 2000][:60]
    for r in rows:
        line, gap = [], False
        for c in (r.text or "").lower():
            if unicodedata.category(c)[0] == "L":
                line.append(ord(c))
                gap = True
            elif gap or not line:
                line.append(32)
                gap = False
        total, n = np.zeros(model.table.shape[1]), 0
        for size in (1, 2, 3):
            for i in range(len(line) - size + 1):
                h = 0
                for k, c in enumerate(line[i : i + size]):
                    h = (h * 0x01000193 + c + k + 1) % 2**32
                total += model.table[h * 0x9E3779B1 % 2**32 >> 17]
                n += 1
        if not any(c != 32 for c in line):
            assert got[r.doc_id].lang_pred == "und"
            continue
        logits = model.scale * total / n + model.shift
        losses = [sum(t * math.log1p(math.exp(-(2 * b - 1) * z)) for t, b, z in zip(model.trust, word, logits, strict=True)) for word in model.code.tolist()]
        best = min(range(len(losses)), key=losses.__getitem__)
        assert got[r.doc_id].lang_pred == model.langs[best]
        assert got[r.doc_id].score == pytest.approx(1 / sum(math.exp(losses[best] - x) for x in losses), abs=1e-4)


def test_pieces_lose_no_ngram():
    text = "".join(chr(97 + i % 23) for i in range(5000))
    whole = set(ngrams.hashed(text, (4, 6)).tolist())
    parts = set().union(*(ngrams.hashed(p, (4, 6)).tolist() for p in ngrams.pieces(text, 700)))
    assert whole == parts


# BPE


@pytest.fixture(scope="module")
def codecs():
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as f:
        return Tokenizer.from_file(path), bpe.Codec.from_json(f.read())


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=80) | st.text(alphabet="ab 'st\n<|endoftext|>1", max_size=80))
def test_bpe_equals_library(codecs, text):
    lib, own = codecs
    (got,) = own.encode_all([text])
    assert np.frombuffer(got, "<u4").tolist() == lib.encode(text, add_special_tokens=False).ids
    assert own.decode(got).decode() == text


def test_bpe_of_tables_and_odd_rows(spark, docs, odd_docs, no_docs, codecs):
    lib, _ = codecs
    path = public_tokenizers.path("byte_bpe_50k.json")
    for df in (docs, odd_docs):
        got = sorted(tuple(r) for r in bpe.bpe_encode(df, path).na.fill(-1, ["doc_id"]).collect())
        want = []
        for r in df.collect():
            ids = lib.encode(r.text or "", add_special_tokens=False).ids
            want.append((-1 if r.doc_id is None else r.doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
        assert got == sorted(want)
    assert bpe.bpe_encode(no_docs, path).count() == 0
    whole = bpe.bpe_encode(docs, path, digests=False).join(docs.select("doc_id", "text"), "doc_id")
    assert whole.where("decoded <> text").count() == 0


def test_long_and_short_trees_agree(codecs):
    _, own = codecs
    for raw in (b"abcabcabc" * 7, b"thethethe", bytes(range(64)), b"a" * 64, b"ab"):
        width = max(4, 1 << (len(raw) - 1).bit_length())
        assert np.frombuffer(own.encode_rows([raw], width)[0], "<u4").tolist() == own.encode_long(raw)


# WARC


def test_warc_is_deterministic_and_exact(spark, sf, tmp_path):
    rows = [(1, "http://a/1", "same"), (2, "http://a/2", "same"), (9, None, "same"), (3, "http://b/é x", "hé"), (4, "u", None), (5, "u", ""), (None, "n", "same"), (7, "t", "twice"), (7, "t", "twice"), (8, "l", "y" * 300_000), (None, "m", "alone")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("shard", F.lit("clash"))
    files = []
    for n, k in (("a", 1), ("b", 5)):
        m = warc.write_warc(df.repartition(k), f"file://{tmp_path}/{n}", roll=2000)
        files.append(sorted(tuple(r) for r in m.collect()))
    assert files[0] == files[1]
    got = {}
    for r in warc.read_warc(spark.read.parquet(f"file://{tmp_path}/a/manifest"), f"file://{tmp_path}/a").collect():
        got.setdefault(r.page_id, []).append((r.record_type, r.refers_to, r.payload_bytes, r.payload_digest))
    same_ = warc.sha1_base32(b"same")
    assert got[1] == [("revisit", 9, 4, same_)] and got[2] == [("revisit", 9, 4, same_)] and got[9] == [("response", None, 4, same_)]
    assert got[4] == [("revisit", 5, 0, warc.sha1_base32(b""))] and got[5][0][0] == "response"
    assert [x[0] for x in got[7]] == ["response", "response"]
    assert sorted(x[:2] for x in got[None]) == [("response", None), ("revisit", 9)]
    assert got[8][0][2] == 300_000
    assert not [p for p in (tmp_path / "a").iterdir() if p.name.startswith(".shard")]
    assert warc.warc_round_trip(df.limit(0)).count() == 0
    keep = warc.write_warc(df, scratch(spark, "warc"), least=5)
    assert keep.agg(F.sum("n_records")).first()[0] == len(rows)


def test_warc_headers_and_retries(spark, tmp_path):
    rows = [(1, "http://a/1", "same"), (9, "http://z/9", "same"), (9, "http://b/9 ä", "same"), (4, "http://c/4", "other")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    folder = f"file://{tmp_path}/w"
    warc.write_warc(df, folder)
    found = []
    for f in (tmp_path / "w").glob("*.warc.gz"):
        records = list(warc.read_records(f.read_bytes()))
        assert records[0][0]["WARC-Type"] == "warcinfo" and records[0][0]["WARC-Filename"] == f.name
        found += [h for h, _ in records[1:]]
    ids = {h["WARC-Record-ID"]: h for h in found}
    assert len(ids) == len(found) == 4
    (revisit,) = [h for h in found if h["WARC-Type"] == "revisit"]
    first = ids[revisit["WARC-Refers-To"]]
    assert first["WARC-Type"] == "response" and first["Page-ID"] == "9" == revisit["Refers-To-Page-ID"]
    assert revisit["WARC-Refers-To-Target-URI"] == first["WARC-Target-URI"] == "http://b/9%20%C3%A4" and revisit["WARC-Refers-To-Date"] == first["WARC-Date"]
    (tmp_path / "r").mkdir()
    for before in (None, b"same size or not", None):  # a first attempt, a broken file under the name, a finished one
        if before:
            (tmp_path / "r" / "shard-00000-00000.warc.gz").write_bytes(before)
        out = warc.ShardWriter(f"file://{tmp_path}/r", 0, 1 << 20)
        out.add(warc.record(1, "http://a", b"x", None))
        out.close()
        assert hashlib.sha256((tmp_path / "r" / out.lines[0][1]).read_bytes()).hexdigest() == out.lines[0][4]
    assert len(list((tmp_path / "r").iterdir())) == 1


def test_warc_reader_notices_damage():
    raw = warc.gzip_member(warc.record(1, "http://a", b"body", None))
    ((head, block),) = warc.read_records(raw)
    assert head["WARC-Type"] == "response" and block.endswith(b"body")
    bad = warc.gzip_member(warc.record(1, "http://a", b"body", None).replace(b"body", b"bodx"))
    with pytest.raises(ValueError, match="damaged"):
        list(warc.read_records(bad))


# Sharding


def test_lookup_table_is_fair_and_stable():
    names = [f"s{i:02d}" for i in range(13)]
    a = maglev.fill(names, 5003)
    assert np.bincount(a).max() - np.bincount(a).min() <= 1
    b = maglev.fill(names[:-1], 5003)
    kept = a < 12
    assert (a[kept] != b[kept]).mean() < 0.25
    with pytest.raises(ValueError):
        maglev.fill(names, 5000)


def test_lookup_table_equals_turns():
    import xxhash

    names, m = ["a", "b", "c"], 7
    prefer = [[(xxhash.xxh64_intdigest(n.encode(), 1) + j * (xxhash.xxh64_intdigest(n.encode(), 2) % (m - 1) + 1)) % m for j in range(m)] for n in names]
    slots = {}
    for i in itertools.cycle(range(3)):
        if len(slots) == m:
            break
        slots[next(s for s in prefer[i] if s not in slots)] = i
    assert maglev.fill(names, m).tolist() == [slots[i] for i in range(m)]


def test_placement(spark, odd_docs, no_docs, docs):
    got = maglev.place(odd_docs, F.col("doc_id"))
    assert got.count() == 13 and got.where("shard is null").count() == 0
    assert maglev.place(no_docs, F.col("doc_id")).count() == 0
    a, b = maglev.place(docs, F.col("doc_id")), maglev.place(docs, F.col("doc_id"), maglev.SHARDS[:-1])
    m = maglev.moved(a, b, "doc_id").first()
    assert m.n_moved < 0.3 * m.n_rows
    named = odd_docs.select(F.coalesce("text", F.lit("")).alias("shard"), F.col("doc_id").alias("slot"), "score")
    for key in ("shard", "slot"):
        placed = maglev.place(named, F.col(key))
        assert placed.count() == 13 and set(placed.columns) == {"score", "slot", "shard"} and placed.where("shard not like 'shard-__'").count() == 0
    table_ = maglev.fill(maglev.SHARDS)
    assert all(r.shard == sorted(maglev.SHARDS)[table_[r.slot]] for r in a.collect())
