"""Operators that compare documents, and the pipeline, against brute force."""

import hashlib
import re
from collections import Counter

import public_tokenizers
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from rowgraph.llm import automaton, components, mixing, neardup, passages, sketch

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


# ---------------------------------------------------------------- mixing


def fill(sizes, weights=(5, 2, 1), most=3):
    """Targets by repeated resharing, as the rule is told."""
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    target, open_, left = {}, set(names), sum(sizes.values())
    while open_:
        level = left / sum(w[s] for s in open_)
        full = {s for s in open_ if level * w[s] > most * sizes[s]}
        if not full:
            target.update({s: level * w[s] for s in open_})
            break
        for s in full:
            target[s] = most * sizes[s]
            left -= target[s]
        open_ -= full
    return target


def test_targets(spark):
    sizes = {"a": 100, "b": 5000, "c": 7, "d": 0, None: 900, "E": 40}
    rows = spark.createDataFrame([(s, n, 1) for s, n in sizes.items()], "source string, source_size long, source_rows long")
    got = {r["source"]: r["target"] for r in mixing.source_targets(rows).collect()}
    assert got == pytest.approx(fill(sizes)) and sum(got.values()) == pytest.approx(sum(sizes.values()))


def test_mix(docs, rows):
    got = mixing.mix_sources(docs).collect()
    assert len(got) == len(rows)
    sizes = Counter()
    for r in rows:
        sizes[r[3]] += len(WORD.findall(r[1] or ""))
    want = fill(dict(sizes))
    for r in got:
        assert r["taken"] == r["copies"] * r["size"] <= 3 * r["size"]
        assert r["source_size"] == sizes[r["source"]] and r["target"] == pytest.approx(want[r["source"]])
        rate = r["target"] / r["source_size"] if r["source_size"] else 0
        assert int(rate) <= r["copies"] <= int(rate) + 1
    again = mixing.mix_sources(docs.repartition(3)).collect()
    assert sorted(map(repr, got)) == sorted(map(repr, again))


def test_taken_words_come_near_the_targets(spark):
    rows = [(i, " ".join(["x"] * (1 + i * 7919 % 400)), "abcd"[i % 4 if i % 3 else 0]) for i in range(6000)]
    got = mixing.mix_sources(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    for r in got.groupBy("source").agg(F.sum("taken").alias("t"), F.first("target").alias("g")).collect():
        assert abs(r["t"] - r["g"]) < 0.03 * r["g"]


def test_copies_have_all_columns(clashing):
    out = mixing.take_copies(clashing)
    assert out.columns == clashing.columns
    want = mixing.mix_sources(clashing).agg(F.sum("copies")).first()[0]
    assert out.count() == want


def test_mix_of_nothing(empty):
    assert mixing.mix_sources(empty).count() == 0 and mixing.take_copies(empty).count() == 0


# ---------------------------------------------------------------- near copies


def shingles(text):
    w = WORD.findall((text or "").translate(LOWER))
    return frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def groups(pairs, percent=85):
    """doc_id -> smallest linked id, all pairs compared."""
    parent = {i: i for i, _ in pairs}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for k, (i, a) in enumerate(pairs):
        for j, b in pairs[k + 1 :]:
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                x, y = find(i), find(j)
                parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in parent}


def test_groups(docs, rows):
    named = {r[0]: shingles(r[1]) for r in rows if r[0] is not None}
    want = groups(sorted(named.items()))
    got = neardup.near_duplicates(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        if r["doc_id"] is not None:
            assert (r["n_shingles"], r["component_id"], r["kept"]) == (len(named[r["doc_id"]]), want[r["doc_id"]], want[r["doc_id"]] == r["doc_id"])
        else:
            assert r["component_id"] is None and r["kept"]


def test_large_near_copy_groups_go_by_cluster(spark, monkeypatch):
    """Very many near copies whose mutual similarity lies around the threshold, in several blocks."""
    import random

    rng = random.Random(3)
    monkeypatch.setattr(neardup, "HOT_BUCKET", 8)
    monkeypatch.setattr(neardup, "BLOCK", 16)
    base, rows = [f"b{i}" for i in range(150)], []
    for i in range(90):
        w = list(base)
        for _ in range(rng.choice([1, 1, 2, 2, 3])):
            w[rng.randrange(150)] = f"e{rng.randrange(10**6)}"
        rows.append((1000 - i, " ".join(w)))
    want = groups(sorted((i, shingles(t)) for i, t in rows))
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == want and len(set(want.values())) < 60


@pytest.mark.parametrize("percent", [70])
def test_other_thresholds(spark, monkeypatch, percent):
    """Pairs on either side of the threshold, in small and in large buckets."""
    import random

    rng = random.Random(percent)
    monkeypatch.setattr(neardup, "HOT_BUCKET", 8)
    monkeypatch.setattr(neardup, "BLOCK", 16)
    rows = []
    for g in range(12):
        base = [f"g{g}w{i}" for i in range(120)]
        for _ in range(24 if g < 2 else 4):
            w = list(base)
            for _ in range(rng.randrange(0, 6)):
                w[rng.randrange(120)] = f"e{rng.randrange(10**6)}"
            rows.append((len(rows), " ".join(w)))
    want = groups(sorted((i, shingles(t)) for i, t in rows), percent)
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), percent)
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == want


def test_blocks_bring_all_members_of_different_components_together(spark):
    comps = {0: 70, 1000: 40, 2000: 16, **{3000 + 10 * k: 1 + k % 3 for k in range(30)}}
    rows = [(7, c + i, c) for c, n in comps.items() for i in range(n)]
    met = neardup.blocks_of(spark.createDataFrame(rows, "cluster long, node long, component long"), 16).collect()
    tasks = {}
    for r in met:
        tasks.setdefault((r["i"], r["j"]), []).append(r)
    seen = set()
    for (i, j), here in tasks.items():
        seen |= {(x["node"], y["node"]) for x in here if x["block"] == i for y in here if y["block"] == j and x["component"] != y["component"]}
        assert i == j or not {x["component"] for x in here if x["block"] == i} & {y["component"] for y in here if y["block"] == j}
    seen |= {(b, a) for a, b in seen}
    assert seen == {(x, y) for _, x, c in rows for _, y, d in rows if c != d}


def test_sketches_fill_and_estimate():
    import numpy as np

    rng = np.random.default_rng(1)
    a = np.unique(rng.integers(0, 2**63, 600, dtype=np.uint64))
    b = np.unique(np.concatenate([a[:540], rng.integers(0, 2**63, 60, dtype=np.uint64)]))
    s = sketch.sketches([a, b, a[:1], np.zeros(0, np.uint64), a])
    assert (s[:3] != 2**64 - 1).all() and (s[0] == s[4]).all() and (s[3] == 2**64 - 1).all()
    both, union = sketch.overlap(a, b)
    assert abs((s[0] == s[1]).mean() - both / union) < 0.08


def test_sketches_of_small_sets_are_those_of_the_scheme():
    """Round by round in whole numbers, and the estimate of pairs that are linked by contract."""
    import numpy as np

    rng = np.random.default_rng(2)
    for n in range(1, 13):
        items = rng.integers(0, 2**63, n, dtype=np.uint64)
        want = {}
        for r in range(2 * sketch.T):
            for v in sketch.mix(items, r + 1).tolist():
                at = v % sketch.T if r < sketch.T else r - sketch.T
                want[at] = min(want.get(at, (2 * sketch.T, 0)), (r, v >> 10))
            if len(want) == sketch.T:
                break
        assert sketch.sketches([items])[0].tolist() == [want[k][0] * 2**54 + want[k][1] for k in range(sketch.T)]
    for n in (6, 7, 8):
        sets = [rng.integers(0, 2**63, n, dtype=np.uint64) for _ in range(100)]
        marks = sketch.signatures(sketch.sketches([x for s in sets for x in (s[:-1], s)]))
        shared = (marks[::2] == marks[1::2]).sum(axis=1)
        assert abs(shared.mean() / sketch.T - (n - 1) / n) < 0.02


def test_small_sets_are_grouped_as_by_brute_force(spark, monkeypatch):
    """Texts of up to 16 words: links between members of a bucket neither of which is its smallest node."""
    import random

    rng = random.Random(7)
    monkeypatch.setattr(neardup, "HOT_BUCKET", 8)
    rows = []
    for i in range(60):
        w = [f"s{i}x{k}" for k in range(rng.randrange(8, 17))]
        for cut in (w, w[1:], w[:-1], [*w, "more"], [*w, "less"], [*w[:-1], "other"]):
            rows.append((len(rows), " ".join(cut)))
    rng.shuffle(rows)
    want = groups(sorted((i, shingles(t)) for i, t in rows))
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == want


def test_components(spark):
    links = [(i, i + 1) for i in range(20)] + [(100, 101), (102, 101), (7, 3)] + [(200, 200 + k) for k in range(1, 30)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(21)}, **{i: 100 for i in (100, 101, 102)}, **{200 + k: 200 for k in range(30)}}
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


def tables_written(monkeypatch):
    """Tags of the tables that near-dedup writes from now on: each costs a task per shuffle partition, however small it is."""
    from rowgraph.llm import shared

    tags, path = [], shared.fresh_path

    def noted(spark, tag):
        tags.append(tag)
        return path(spark, tag)

    monkeypatch.setattr(shared, "fresh_path", noted)
    return tags


def test_components_of_stars_take_one_pass(spark, monkeypatch):
    tags = tables_written(monkeypatch)
    links = [(10, 10 + k) for k in range(1, 8)] * 2 + [(40, 30), (50, 51)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{10 + k: 10 for k in range(8)}, 30: 30, 40: 30, 50: 50, 51: 50}
    assert len(tags) == 1


def test_components_of_any_links(spark):
    """Random links of two kinds, with repeated ones, loops, chains and hubs, against union by hand."""
    import random

    rng = random.Random(11)
    for n in (30, 60):
        links = [(rng.randrange(2), rng.randrange(100), rng.randrange(100)) for _ in range(n)] + [(1, 200 + 7 * k % 31, 200 + 7 * (k + 1) % 31) for k in range(20)] + [(0, 90, x) for x in range(80, 99)]
        want = {(k, x): x for k, a, b in links for x in (a, b) if a != b}
        for _ in range(len(want)):
            for k, a, b in links:
                if a != b:
                    want[k, a] = want[k, b] = min(want[k, a], want[k, b])
        got = components.components_by_kind(spark.createDataFrame(links, "kind int, a long, b long")).collect()
        assert {(r["kind"], r["node"]): r["component"] for r in got} == want and len(got) == len(want)


def test_groups_with_clusters_write_few_tables(spark, monkeypatch):
    """One large group of copies, one of near copies and small groups, as on check_h."""
    import random

    rng = random.Random(5)
    monkeypatch.setattr(neardup, "HOT_BUCKET", 8)
    monkeypatch.setattr(neardup, "BLOCK", 16)
    base, rows = [f"b{i}" for i in range(150)], []
    for i in range(40):
        w = list(base)
        for _ in range(rng.choice([1, 1, 2, 2, 3])):
            w[rng.randrange(150)] = f"e{rng.randrange(10**6)}"
        rows += [(1000 - i, " ".join(w)), (2000 + i, " ".join(base[::-1]))]
    for g in range(10):
        small = [f"s{g}x{i}" for i in range(60)]
        rows += [(3000 + 3 * g + k, " ".join([*small[: 60 - 2 * k], f"t{k}"])) for k in range(3)]
    want = groups(sorted((i, shingles(t)) for i, t in rows))
    docs = spark.createDataFrame(rows, "doc_id long, text string").cache()
    tags = tables_written(monkeypatch)
    got = neardup.near_duplicates(docs)
    assert len(tags) <= 27
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == want


def test_whole_number_ids_of_any_width(spark):
    """Ids that are not longs are looked up as longs."""
    text = " ".join(f"w{i}" for i in range(60))
    got = neardup.near_duplicates(spark.createDataFrame([(5, text), (3, text + " more"), (9, "other words")], "doc_id int, text string"))
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == {5: 3, 3: 3, 9: 9}


def test_one_of_each_group_stays(clashing, rows):
    out = neardup.drop_duplicates(clashing)
    assert out.columns == clashing.columns
    kept = {r["doc_id"] for r in neardup.near_duplicates(clashing).filter("kept").collect()}
    assert {r["doc_id"] for r in out.collect()} == kept


def test_near_copies_of_nothing(empty):
    assert neardup.near_duplicates(empty).count() == 0 and neardup.drop_duplicates(empty).count() == 0


# ---------------------------------------------------------------- passages


def brute_passages(texts, n=35):
    split = [(t or "").encode().split() for t in texts]
    c = Counter(tuple(w[k : k + n]) for w in split for k in range(len(w) - n + 1))
    out = []
    for w in split:
        gone = set()
        for k in range(len(w) - n + 1):
            if c[tuple(w[k : k + n])] > 1:
                gone.update(range(k, k + n))
        kept = b" ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((len(w), len(gone), hashlib.sha256(kept).hexdigest(), kept.decode()))
    return out


def test_passages(docs, rows):
    want = brute_passages([r[1] for r in rows])
    got = passages.dedup_passages(docs)
    assert sorted(((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got.collect()), key=repr) == sorted(((r[0], *w[:3]) for r, w in zip(rows, want)), key=repr)


def test_frequent_anchors_are_sharded_by_window(spark, monkeypatch):
    monkeypatch.setattr(passages, "HOT_PLACES", 5)
    line = " ".join(f"h{i}" for i in range(50))
    rows = [(i, f"a{i} " * 10 + line + f" b{i}" * (i % 3) + (" " + " ".join(f"c{i % 4}_{j}" for j in range(40)) if i % 2 else "")) for i in range(40)]
    want = brute_passages([t for _, t in rows])
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in passages.dedup_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: w[:3] for (i, _), w in zip(rows, want)}


def test_cut_texts(clashing, rows):
    out = passages.cut_passages(clashing)
    assert out.columns == clashing.columns and out.count() == len(rows)
    want = sorted(((r[0], w[3] if w[1] else r[1]) for r, w in zip(rows, brute_passages([r[1] for r in rows]))), key=repr)
    assert sorted(((r["doc_id"], r["text"]) for r in out.collect()), key=repr) == want


def test_given_references_are_cut_out(spark, docs, rows, monkeypatch):
    """Against brute force, over several automata and several rounds of broadcasts."""
    monkeypatch.setattr(passages, "REFERENCE_SHARD", 60)
    monkeypatch.setattr(passages, "REFERENCE_ROUND", 2)
    given = [(rows[3][1] or "")[:900], rows[46][1], None, "too short", " ".join(rows[50][1].split()[10:130])]
    windows = {tuple(w[k : k + 20]) for t in given if t for w in [t.encode().split()] for k in range(len(w) - 19)}
    want = []
    for r in rows:
        w, gone = (r[1] or "").encode().split(), set()
        for k in range(len(w) - 19):
            if tuple(w[k : k + 20]) in windows:
                gone.update(range(k, k + 20))
        want.append((r[0], b" ".join(x for i, x in enumerate(w) if i not in gone).decode() if gone else r[1]))
    out = passages.cut_references(docs, spark.createDataFrame([(t,) for t in given], "text string"), 20)
    assert out.columns == docs.columns and sum(w != r[1] for w, r in zip((x[1] for x in want), rows)) > 3
    assert sorted(((r["doc_id"], r["text"]) for r in out.collect()), key=repr) == sorted(want, key=repr)
    monkeypatch.setattr(passages, "MAX_REFERENCE_WORDS", 10)
    with pytest.raises(ValueError):
        passages.cut_references(docs, spark.createDataFrame([(given[0],)], "text string"), 20)


def test_passages_of_nothing(empty):
    assert passages.dedup_passages(empty).count() == 0 and passages.cut_passages(empty).count() == 0


def test_automaton_counts():
    import random

    rng = random.Random(2)
    seqs = [([rng.randrange(4) for _ in range(rng.randrange(0, 25))], rng.randrange(1, 4)) for _ in range(40)]
    a = automaton.SuffixAutomaton()
    for s, n in seqs:
        a.add(s, n)
    a.settle()
    counts = Counter()
    for s, n in seqs:
        for i in range(len(s)):
            for j in range(i + 1, len(s) + 1):
                counts[tuple(s[i:j])] += n
    for _ in range(60):
        q = [rng.randrange(5) for _ in range(15)]
        for e, (size, n) in enumerate(a.matches(q, 6), 1):
            best = max((k for k in range(0, min(e, 6) + 1) if k == 0 or tuple(q[e - k : e]) in counts))
            assert size == best and (best == 0 or n == counts[tuple(q[e - best : e])])


# ---------------------------------------------------------------- pipeline


def kept_by_rules(rows):
    """Base rules and host verdicts by plain loops."""
    failed = []
    for r in rows:
        w = WORD.findall(r["text"] or "")
        c = Counter(tuple(w[k : k + 8]) for k in range(len(w) - 7))
        covered = {k + i for k in range(len(w) - 7) if c[tuple(w[k : k + 8])] > 1 for i in range(8)}
        failed.append(len(w) < 20 or 100 * len(covered) > 30 * len(w))
    n, bad = Counter(r["source"] for r in rows), Counter(r["source"] for r, f in zip(rows, failed) if f)
    total, m = sum(n.values()), sum(bad.values()) / sum(n.values())
    v = sum(n[h] * (bad[h] / n[h] - m) ** 2 for h in n) / total - m * (1 - m) * len(n) / total
    strength = min(max(m * (1 - m) / v - 1, 1.0), 1e6) if v > 0 else 1e6
    rejected = {h for h in n if (bad[h] + m * strength) / (n[h] + strength) > 0.5}
    return [r for r, f in zip(rows, failed) if not f and r["source"] not in rejected]


def test_stages_one_by_one(spark, docs, rows):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "near_dedup", "passage_dedup", "mix", "tokens"]
    at = docs
    for name, step in corpus_pipeline.STAGES:
        out = step(spark, at, "").cache()
        before, after = at.collect(), out.collect()
        if name != "tokens":
            assert out.columns == docs.columns
        if name == "near_dedup":
            ids = {r["doc_id"] for r in after}
            want = groups(sorted({r["doc_id"]: shingles(r["text"]) for r in before if r["doc_id"] is not None}.items()), corpus_pipeline.NEAR_PERCENT)
            assert ids - {None} == set(want.values())
        if name == "passage_dedup":
            want = sorted(w[3] if w[1] else r["text"] for r, w in zip(before, brute_passages([r["text"] for r in before])))
            assert sorted(r["text"] for r in after) == want
        if name == "quality_rules":
            assert sorted(map(repr, after)) == sorted(map(repr, kept_by_rules(before)))
        if name == "mix":
            sizes, taken = Counter(), Counter()
            for r in before:
                sizes[r["source"]] += len(WORD.findall(r["text"] or ""))
            want = fill(dict(sizes))
            given, found = Counter(map(repr, before)), Counter(map(repr, after))
            assert set(found) <= set(given)
            for r in before:
                rate = want[r["source"]] / sizes[r["source"]] if sizes[r["source"]] else 0
                assert int(rate) * given[repr(r)] <= found[repr(r)] <= (int(rate) + 1) * given[repr(r)]
        if name == "tokens":
            from rowgraph.llm import bpe

            enc = bpe.make_encoding(bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken")), public_tokenizers.PATTERN)
            assert all(r["token_ids"] == enc.encode_ordinary(r["text"]) for r in after)
        at = out


def test_run(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert out.columns[-1] == "token_ids" and out.count() > 50
