"""The training-data operators against brute force, with nulls, empty tables, repeats and clashing columns."""

import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from graphwatch.llm import components, decontaminate, licenses, linededup, lmscore, mixing, neardup, pagetext, quality, tokenfiles, urlfilter

DOCS = "doc_id long, text string, source string, n_words string, kept string"


def prose(seed, n):
    r = random.Random(seed)
    return " ".join(r.choice(["the", "of", "and"]) if r.random() < 0.3 else "w%d" % r.randrange(3000) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    r, rows = random.Random(1), []
    for i in range(40):
        words = prose(i, r.randint(5, 160)).split()
        rows.append([i, " ".join(words)])
        if i % 4 == 0:  # a near copy
            words[len(words) // 2] = "changed"
            rows.append([100 + i, " ".join(words)])
    rows += [[200, None], [201, ""], [202, " \t\n "], [203, "one"], [204, "one"], [205, rows[0][1]], [None, rows[0][1]], [206, prose(9, 20_000)], [0, rows[0][1]]]
    line = "This very long line stands in many documents."
    rows += [[300 + i, f"{line}\nown line {i}\n{line.upper()} "] for i in range(5)]
    return spark.createDataFrame([(*x, r.choice(["a", "b", None]), "x", "y") for x in rows], DOCS)


def shingles(text, k=3):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))) if w else frozenset()


def test_near_duplicates(spark, docs):
    got = neardup.near_duplicates(docs).collect()
    sets = {r.doc_id: shingles(r.text) for r in docs.collect() if r.doc_id is not None}
    root = {k: k for k in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    assert len(got) == docs.count()
    for r in got:
        if r.doc_id is None:
            assert r.component_id is None and r.kept
        else:
            assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), find(r.doc_id), find(r.doc_id) == r.doc_id)
    left = neardup.drop_near_duplicates(docs)
    assert left.columns == docs.columns
    assert neardup.near_duplicates(docs.limit(0)).count() == 0


def test_near_duplicates_of_rows_that_share_a_doc_id(spark, monkeypatch):
    """Rows with one doc_id and different texts are one document with one of the sets, whatever the dealing."""
    a, b = prose(1, 60), prose(2, 60)
    rows = [(1, a), (1, b), (2, a), (3, b), (4, prose(3, 9)), (4, None), (5, "x y z")]
    monkeypatch.setattr(neardup, "BUCKET_ROWS", 1)
    seen = set()
    for order in (rows, rows[::-1]):
        got = neardup.near_duplicates(spark.createDataFrame(order, "doc_id long, text string").repartition(3)).collect()
        assert Counter(r.doc_id for r in got) == Counter(r[0] for r in rows)
        by = {r.doc_id: tuple(r) for r in got}
        assert all(tuple(r) == by[r.doc_id] for r in got)
        assert [by[2][2], by[3][2]] in ([1, 3], [2, 1]) and by[1][2] == 1 and by[5][3]
        seen.add(tuple(sorted(by.items())))
    assert len(seen) == 1


def test_large_buckets_are_split(spark, docs, monkeypatch):
    want = sorted(map(tuple, neardup.near_duplicates(docs).collect()), key=str)
    monkeypatch.setattr(neardup, "BUCKET_ROWS", 1)
    assert sorted(map(tuple, neardup.near_duplicates(docs).collect()), key=str) == want


def test_odd_sketch_estimates_high_similarity(spark):
    r = random.Random(4)
    base = [str(r.random()) for _ in range(400)]
    rows = [(0, " ".join(base))] + [(k, " ".join(w if i >= k else f"x{k}" for i, w in enumerate(base))) for k in (5, 20, 40)]
    signed = neardup.signatures(spark.createDataFrame(rows, "doc_id long, text string"))
    one, two = neardup._sided(signed.filter("doc_id = 0"), "a"), neardup._sided(signed.filter("doc_id > 0"), "b")
    est = one.crossJoin(two).select("b_doc_id", neardup.similarity_estimate(neardup._ones("a_odd", "b_odd", neardup.SKETCH_LONGS), neardup.BANDS * neardup.BAND_ROWS).alias("s"))
    texts = dict(rows)
    for row in est.collect():
        a, b = shingles(texts[0]), shingles(texts[row.b_doc_id])
        assert abs(row.s - len(a & b) / len(a | b)) < 0.12


def test_components_of_a_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(30)] + [(50, 51), (60, 60)], "a long, b long")
    got = {r.id: r.component for r in components.connected_components(edges).collect()}
    assert got == {i: 0 for i in range(31)} | {50: 50, 51: 50}


def test_licenses(spark):
    rows = [(1, "x\nReleased under the MIT License.\ny"), (2, None), (3, "no such words"), (4, prose(1, 50) + " Permission is hereby granted, free of charge, to each person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction"), (5, "Licensed under CC BY-NC 4.0. Licensed under CC BY-NC 4.0."), (6, "a license plate")]
    got = defaultdict(list)
    for r in licenses.license_matches(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        got[r.doc_id].append((r.license, r.coverage))
    assert got[1] == [("MIT-line", 1.0)] and got[4][0][0] == "MIT" and 0.9 < got[4][0][1] < 1 and len(got[5]) == 2 and set(got) == {1, 4, 5}


def test_licenses_whose_trigger_word_is_changed(spark):
    long = {k: licenses.TEMPLATES[k] for k in ("MIT", "BSD")}
    rows = [
        ("MIT-line", "Released under the MIT Licence."),
        ("GPL-3.0-line", "This work is licenced under the GNU General Public Licence, version 3."),
        ("CC", "This work is licenced under a Creative Commons Attribution Licence"),
        *((k, v.replace(v.split()[0], w, 1)) for k, v in long.items() for w in ("Xyz", v[:5] + "-\n" + v[5:].split()[0])),
    ]
    got = licenses.license_matches(spark.createDataFrame([(i, prose(i, 30) + "\n" + t) for i, (_, t) in enumerate(rows)], "doc_id long, text string")).collect()
    assert sorted((r.doc_id, r.license) for r in got) == [(i, k) for i, (k, _) in enumerate(rows)]
    # Whichever words are lost, as long as enough are left.
    r = random.Random(6)
    for name, text in licenses.TEMPLATES.items():
        t = licenses.Template(name, text)
        for _ in range(40):
            lost = r.sample(range(len(t.words)), len(t.words) - t.least(licenses.MIN_COVERAGE))
            words = [f"zz{i}" if i in lost else w for i, w in enumerate(t.words)]
            reached = len(licenses.align(words, t.words)) >= t.least(licenses.MIN_COVERAGE)
            assert bool(licenses.scan_text(" ".join(words), [t])) == reached


def test_licenses_against_all_windows(spark):
    """The scan against alignments at every place of the text, and whole licences with changed words among other text."""
    r, rows = random.Random(21), []
    for k, (name, text) in enumerate(list(licenses.TEMPLATES.items()) * 2):
        words = text.split()
        for _ in range(int(len(words) * (0.05 if k % 2 else 0.3))):
            words[r.randrange(len(words))] = r.choice(["changed", "the", "software", "license"])
        rows.append((k, prose(k, 20) + " " + " ".join(words) + " " + prose(k + 99, 20)))
    rows += [(90, None), (91, ""), (92, "license " * 500), (93, prose(5, 30_000) + " " + licenses.TEMPLATES["ISC-text"]), (94, "_Permission_ " + licenses.TEMPLATES["MIT"]), (94, "x")]
    known = [licenses.Template(k, v) for k, v in licenses.TEMPLATES.items()]
    want = Counter()
    for d, text in rows:
        words = licenses._WORD.findall((text or "").lower())
        found = set()
        for t in known if len(words) < 2000 else []:
            n = len(t.words)
            slack = max(1, int(n * licenses.SLACK))
            for p in range(-n, len(words)):
                lo, hi = max(0, p - slack), min(len(words), p + n + slack)
                if lo >= hi or (Counter(words[lo:hi]) & Counter(t.words)).total() < t.least(licenses.MIN_COVERAGE):
                    continue
                found.add((t.name, len(licenses.align(words, t.words, lo, hi)) >= t.least(licenses.MIN_COVERAGE)))
        for name in {x for x, ok in found if ok}:
            want[d, name] += 1
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("license", F.lit("clash")).withColumn("coverage", F.lit(0))
    got = defaultdict(set)
    for x in licenses.license_matches(df).collect():
        got[x.doc_id].add(x.license)
        assert x.coverage >= licenses.MIN_COVERAGE
    # Of templates that overlap in a text, the longest is told; so each text is found, by one of those that cover it.
    covered = defaultdict(set)
    for d, name in want:
        covered[d].add(name)
    assert {d for d in got if d != 93} == set(covered) and all(got[d] <= covered[d] for d in covered) and got[93] == {"ISC-text"}
    assert all(got[k] == {n} for k, n in enumerate(licenses.TEMPLATES) if k % 2 and n.endswith("-text"))
    assert licenses.license_matches(df.limit(0)).count() == 0


def test_alignment_is_increasing_and_equal():
    r = random.Random(2)
    for _ in range(200):
        a, b = ([r.choice("abcdefghij") for _ in range(r.randint(0, 20))] for _ in range(2))
        pairs = licenses.align(a, b)
        assert all(a[i] == b[j] for i, j in pairs)
        assert all(p[0] < q[0] and p[1] < q[1] for p, q in zip(pairs, pairs[1:]))


def test_contamination(spark):
    item = prose(77, 30).split()
    changed = [("zz" if i % 6 == 5 else w) for i, w in enumerate(item)]
    rows = [(1, prose(1, 100) + " " + " ".join(item).upper() + " " + prose(2, 50)), (2, prose(3, 40) + " " + " ".join(changed) + " end"), (3, prose(4, 200)), (4, None), (5, ""), (None, " ".join(item)), (6, " ".join(item[:6]) + " " + prose(5, 60))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([(9, " ".join(item)), (10, None), (11, "too short")], "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.contamination(docs, bench).collect()}
    assert set(got) == {1, 2} and got[1].first_word == 100 and got[1].matched_words == 30 and got[2].item_id == 9
    assert {r.doc_id for r in decontaminate.drop_contaminated(docs, bench).collect()} == {3, 4, 5, 6, None}
    assert decontaminate.contamination(docs, bench.limit(0)).count() == 0


@pytest.mark.parametrize("broadcast", [True, False])
def test_contamination_against_brute_force(spark, monkeypatch, broadcast):
    """All diagonals of all pairs on which some mask finds all its words, compared word by word."""
    if not broadcast:
        monkeypatch.setattr(decontaminate, "BROADCAST_WORDS", 0)
        monkeypatch.setattr(decontaminate, "BROADCAST_TEXTS", 0)
    r = random.Random(12)
    words = lambda n, top=400: [f"v{r.randrange(top)}" for _ in range(n)]
    items = [words(n) for n in (3, 5, 6, 7, 8, 9, 20, 40, 150, 400)] + [["same"] * 12]
    items.append(items[7][:])  # a tie
    rows = []
    for k, item in enumerate(items * 3):
        lost = [w if r.random() > 0.12 * (k % 4) else "zz" for w in item]
        cut = slice(r.randint(0, len(item) // 3), len(item) - r.randint(0, len(item) // 3)) if k % 2 else slice(None)
        rows.append((k, " ".join(words(30, 4000) + lost[cut] + words(r.randint(0, 30), 4000))))
    rows += [(90, " ".join(items[8] * 3)), (91, " ".join(["same"] * 40)), (92, " ".join(words(20_000, 900))), (92, " ".join(items[6])), (93, None), (None, " ".join(items[6]))]
    bench = [(i, " ".join(x)) for i, x in enumerate(items)] + [(50, None), (51, ""), (None, "v1 v2 v3")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("item_id", F.lit("clash")).withColumn("h", F.lit(0))
    got = {(x.doc_id, x.item_id): (x.item_words, x.matched_words, x.first_word) for x in decontaminate.contamination(docs, spark.createDataFrame(bench, "item_id long, text string")).collect()}
    want = {}
    for d, text in rows:
        t = (text or "").split()
        for i, body in bench:
            item = (body or "").split()
            if d is None or i is None or not item:
                continue
            masks = decontaminate.MASKS if len(item) >= 8 else [tuple(range(len(item)))]
            begins = set()
            for m in masks:
                where = defaultdict(list)
                for q in range(len(item) - m[-1]):
                    where[tuple(item[q + p] for p in m)].append(q)
                for at in range(len(t) - m[-1]):
                    begins |= {at - q for q in where.get(tuple(t[at + p] for p in m), ())}
            for b in begins:
                equal = [item[j] == t[j + b] for j in range(len(item)) if 0 <= j + b < len(t)]
                score = same = best = most = 0
                for e in equal:
                    same = (0 if score <= 0 else same) + e
                    score = max(score, 0) + 1 if e else score - 4
                    if score > best:
                        best, most = score, same
                if most >= min(max(8, -(-len(item) // 2)), 64, len(item)):
                    have = want.get((d, i))
                    if have is None or (most, -b) > (have[1], -have[2]):
                        want[d, i] = (len(item), most, b)
    assert got == want and len(want) > 12
    assert decontaminate.contamination(docs.limit(0), spark.createDataFrame(bench, "item_id long, text string")).count() == 0


def test_token_files(spark, docs, tmp_path):
    from tokenizers import Tokenizer

    path, tokenizer = str(tmp_path / "t"), public_tokenizers.path("word_bpe_49k.json")
    tokenfiles.write_tokens(docs, path, tokenizer)
    model, start = Tokenizer.from_file(tokenizer), 0
    got = sorted(tokenfiles.token_digest(tokenfiles.read_tokens(spark, path)).collect(), key=lambda r: r.start)
    rows = sorted(docs.collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.text or ""))
    assert len(got) == len(rows)
    for r, g in zip(rows, got):
        ids = np.array([*model.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4")
        assert (g.doc_id, g.start, g.n_tokens, g.ids_crc32) == (r.doc_id, start, len(ids), zlib.crc32(ids))
        start += len(ids)
    import glob

    import pyarrow.parquet as pq

    meta = pq.ParquetFile(max(glob.glob(f"{path}/*.parquet"), key=lambda p: pq.ParquetFile(p).metadata.num_rows)).metadata.row_group(0)
    by = {meta.column(i).path_in_schema: meta.column(i) for i in range(meta.num_columns)}
    assert by["doc_id"].has_offset_index and "DELTA_BINARY_PACKED" in by["doc_id"].encodings


def test_odd_words_are_encoded_like_the_tokenizer():
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    ids, model, r = tokenfiles.WordIds(path), Tokenizer.from_file(path), random.Random(3)
    for _ in range(3000):
        text = "".join(r.choice("abXYZ'stdlmve.,;:-_#$%&() 0123456789éÉßñÜŸºµ²½×İıΣσςﬁ日本’“… ") for _ in range(r.randint(0, 12)))
        assert tokenfiles.encode_text(ids, text) == np.array(model.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


def test_url_filter(spark):
    rows = [(i, f"http://good{i}.example.net/en/{i}") for i in range(20)] + [(20 + i, f"http://bad{i}.example.com/de/{i}?q") for i in range(20)]
    rows += [(50, None), (51, "nothing"), (52, "HTTP://Sub.NET"), (53, "http://x.net/"), (54, "a://b://c/d#e"), (55, "http://good7.example.io/en/3"), (55, "http://good7.example.io/en/3")]
    got = {r.page_id: r for r in urlfilter.judge(spark.createDataFrame(rows, "page_id long, url string")).select("_page.page_id", "host", "path", "rule", "verdict").collect()}
    assert got[0].rule == "example.net/en/" and got[0].verdict == "allow" and got[25].rule == "example.com/de/" and got[25].path == "/de/5"
    assert (got[50].host, got[50].path, got[50].rule) == ("", "", None) and (got[52].host, got[52].rule) == ("sub.net", None)
    assert (got[53].rule, got[53].verdict) == ("net/", "block") and (got[54].host, got[54].path) == ("b:", "//c/d") and got[55].verdict == "allow"
    assert urlfilter.judge(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_url_model_against_brute_force(spark):
    """Counts of all contexts, smoothed estimates, scores, the cut and the verdicts, in plain Python."""
    r = random.Random(31)
    word = lambda k: "".join(r.choice(k) for _ in range(r.randint(1, 6)))
    rows = [(i, f"http://{word('abc')}.example.net/en/{word('abcd')}") for i in range(40)]  # allowed
    rows += [(100 + i, f"http://{word('xyz')}.net/{word('wxyz')}") for i in range(40)]  # blocked
    rows += [(200 + i, f"https://{word('abcxyz')}.io/{word(r.choice(['abcd', 'wxyz']))}?q") for i in range(40)]
    rows += [(300, None), (301, ""), (302, "http://é.io/ü"), (303, rows[0][1]), (303, rows[85][1]), (304, "http://" + "ab" * 4000 + ".io/")]
    df = spark.createDataFrame(rows, "page_id long, url string").withColumn("host", F.lit("clash")).withColumn("s", F.lit(1)).withColumn("score", F.lit("x"))
    got = urlfilter.judge(df).select("_page.page_id", "host", "path", "rule", "verdict", "score", "cut").collect()
    texts = sorted({(x.host + x.path).translate({i: i + 32 for i in range(65, 91)}) for x in got})
    held = {x.s: x.h for x in spark.createDataFrame([(t,) for t in texts], "s string").select("s", (F.pmod(F.xxhash64("s"), F.lit(urlfilter.FOLDS)) == 0).alias("h")).collect()}
    text = lambda x: (x.host + x.path).translate({i: i + 32 for i in range(65, 91)})
    label = lambda x: None if x.rule is None else x.verdict
    order, counts = urlfilter.ORDER, {"allow": Counter(), "block": Counter()}
    follow = {"allow": Counter(), "block": Counter()}
    for x in got:
        if label(x) and not held[text(x)]:
            p = "\x02" * order + text(x) + "\x03"
            for e in range(order, len(p)):
                for n in range(order + 1):
                    counts[label(x)][p[e - n : e], p[e]] += 1
                    follow[label(x)][p[e - n : e]] += 1

    def prob(side, context, c):
        shorter = 1 / urlfilter.ALPHABET if not context else prob(side, context[1:], c)
        base = shorter if context else 1 / urlfilter.ALPHABET
        return (counts[side][context, c] + urlfilter.PRIOR * base) / (follow[side][context] + urlfilter.PRIOR)

    def score(t):
        p = "\x02" * order + t + "\x03"
        return sum(math.log(prob("allow", p[e - order : e], p[e])) - math.log(prob("block", p[e - order : e], p[e])) for e in range(order, len(p))) / (len(t) + 1)

    want = {t: score(t) for t in texts if len(t) < 1000}
    assert all(abs(x.score - want[text(x)]) < 1e-9 for x in got if text(x) in want)
    sides = {k: sorted(want[t] for t in {text(x) for x in got if label(x) == k} if held[t]) for k in ("allow", "block")}
    low, high = sides["allow"][max(0, math.ceil(0.05 * len(sides["allow"])) - 1)], sides["block"][max(0, math.ceil(0.95 * len(sides["block"])) - 1)]
    assert all(abs(x.cut - (low + high) / 2) < 1e-9 for x in got)
    assert all(x.verdict == ("allow" if x.score >= x.cut else "block") for x in got if x.rule is None)
    # The model tells the two kinds of unknown hosts' paths apart.
    right = [x.verdict == ("allow" if set(x.path) <= set("/abcd") else "block") for x in got if x.rule is None and x.host.endswith(".io") and x.page_id < 300]
    assert sum(right) > 0.7 * len(right)


def test_mixing(spark, docs):
    rows, draws = mixing.mix(docs, block_words=16)
    got = mixing.taken_words(rows, draws).collect()
    assert len(got) == docs.count() and all(0 <= r.taken <= 2 * r.size for r in got)
    per = defaultdict(int)
    for r in got:
        per[r.source, r.target] += r.taken
    assert all(abs(v - t) <= 16 for (_, t), v in per.items())
    total = sum(r.size for r in got)
    assert abs(sum(t for _, t in per) - 1.5 * total) < 1e-6 * total
    shards = [r["count"] for r in draws.groupBy("shard").count().collect()]
    assert len(shards) == 8 and max(shards) - min(shards) <= 1
    assert draws.select("doc_id", "source", "size", "row", "block", "copy").distinct().count() == draws.count()
    assert mixing.mixed_documents(docs).columns == docs.columns
    by_doc = Counter((d.doc_id, d.source, d.size, d.row) for d in draws.collect())
    assert all(r.n_draws == by_doc[r.doc_id, r.source, r.size, r.row] and r.n_shards <= min(8, r.n_draws) for r in got)
    empty = mixing.mix(docs.limit(0))
    assert mixing.taken_words(*empty).count() == 0 and mixing.mixed_documents(docs.limit(0)).count() == 0


def test_draws_are_the_shards_quotas(spark, docs, monkeypatch):
    """Draws against a plain version: the permuted order of each source, cut where the words come nearest to the target."""
    rows, draws = mixing.mix(docs, block_words=16)
    got, all_rows = draws.collect(), {(r.doc_id, r.source, r.size, r.row): r for r in rows.collect()}
    blocks, hashed = defaultdict(list), spark.createDataFrame([(*k, b, 0) for k in all_rows for b in range(-(-k[2] // 16))], "doc_id long, source string, size long, row long, block long, z int")
    for x in hashed.withColumn("key", F.xxhash64(F.lit(mixing.SEED), "doc_id", "source", "size", "row", "block")).collect():
        blocks[x.source].append((x.key, x.doc_id, x.size, x.row, x.block, min(16, x.size - 16 * x.block)))
    for source, order in blocks.items():
        order.sort(key=lambda x: (x[0], x[1] is not None, x[1] or 0, *x[2:5]))
        target = next(r.target for k, r in all_rows.items() if k[1] == source)
        whole, words = divmod(target, sum(x[5] for x in order))
        want, sofar = Counter(), 0
        for x in order:
            want[x[1:5]] = int(whole) + (sofar + x[5] / 2 < words)
            sofar += x[5]
        drawn = Counter((d.doc_id, d.size, d.row, d.block) for d in got if d.source == source)
        assert drawn == +want
        # Shard by shard, the next draws of the order.
        place = {x[1:5]: i for i, x in enumerate(order)}
        numbers = sorted((d.copy * len(order) + place[d.doc_id, d.size, d.row, d.block], d["shard"]) for d in got if d.source == source)
        assert [n for n, _ in numbers] == list(range(len(numbers))) and [s for _, s in numbers] == sorted(s for _, s in numbers)
    assert sorted(map(tuple, mixing.mix(docs.repartition(7), block_words=16)[1].collect()), key=str) == sorted(map(tuple, got), key=str)
    # Without quotas nothing is drawn: the quotas decide, not the running sums.
    none = lambda d, shards, seed: d.select("si", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.lit(0).cast("long").alias("until"))
    monkeypatch.setattr(mixing, "shard_quotas", none)
    assert mixing.mix(docs, block_words=16)[1].count() == 0


def test_hypergeometric_is_the_inverse_distribution(spark):
    """Against exact binomials: the values in the order in which the draw visits them, from the mode outwards."""
    r = random.Random(2)
    cases = [(r.randint(0, 40), r.randint(0, 40), r.randint(0, 40), r.random()) for _ in range(300)]
    cases = [(w, b, min(k, w + b), u) for w, b, k, u in cases]
    df = spark.createDataFrame(cases, "w long, b long, k long, u double")
    for (w, b, k, u), x in zip(cases, df.select(mixing.hypergeometric(F.col("w"), F.col("b"), F.col("k"), F.col("u"))).collect()):
        low, high = max(0, k - b), min(k, w)
        p = {i: math.comb(w, i) * math.comb(b, k - i) / math.comb(w + b, k) for i in range(low, high + 1)}
        mode = max(low, min(high, (k + 1) * (w + 1) // (w + b + 2)))
        order = [mode] + [x for d in range(1, 50) for x in (mode + d, mode - d) if low <= x <= high]
        sofar, edges = 0.0, []
        for i in order:
            sofar += p[i]
            edges.append((sofar, i))
        near = any(abs(u - e) < 1e-9 for e, _ in edges)
        assert near or x[0] == next((i for e, i in edges if u < e), mode)


def test_repeated_rows_are_mixed_as_often_as_drawn(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "a b c", "s")] * 2 + [(2, "d e f", "s")] * 3 + [(3, "g", None), (None, "h i", "s")], "doc_id long, text string, source string")
    for n in (1, 2, 3):
        rows, _ = mixing.mix(docs, block_words=None)
        some = "doc_id is null or doc_id = 3 or row = 1"
        draws = rows.filter(some).withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(n)))).withColumn("n_words", F.col("size"))
        with monkeypatch.context() as m:
            m.setattr(mixing, "mix", lambda *a, **k: (rows, draws))
            got = Counter(r.doc_id for r in mixing.mixed_documents(docs).collect())
        assert got == {1: n, 2: n, 3: n, None: n}


def test_hypergeometric_draws(spark):
    u = F.pmod(F.xxhash64("id"), F.lit(1 << 53)).cast("double") / float(1 << 53)
    lit = lambda x: F.lit(x).cast("long")
    got = [r[0] for r in spark.range(4000).select(mixing.hypergeometric(lit(30), lit(70), lit(20), u)).collect()]
    assert abs(np.mean(got) - 6) < 0.15 and abs(np.var(got) - 3.394) < 0.4 and 0 <= min(got) and max(got) <= 20
    assert spark.range(1).select(mixing.hypergeometric(lit(0), lit(5), lit(3), F.lit(0.5)), mixing.hypergeometric(lit(4), lit(0), lit(3), F.lit(0.5))).first() == (0, 3)


def test_page_text(spark):
    page = "<html><head><title>t</title><script>x='</p>'</script></head><body><nav><a href='/'>Home</a></nav><article><header><h1>Head &amp; line</h1></header><p>One  two\n three<p>Four &#233;<div class='ad'>Buy</div></article><div class='comments'>no</div><footer>f</footer></body>"
    plain = "<body><div>Site name</div><p>{}</p><div>Imprint of the site</div></body>"
    rows = [(1, "http://a.org/x/1", page), (2, "http://b.org/1", plain.format("Text one")), (3, "http://b.org/2", plain.format("Text two")), (4, None, None), (5, "http://c.org", "")]
    got = {r.page_id: r.text for r in pagetext.extract(spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)).collect()}
    assert got[1] == "Head & line\nOne two three\nFour é"
    assert got[4] == "" and got[5] == "" and "Text one" in got[2] and "Text two" in got[3]
    assert pagetext.main_text(pagetext.page_lines(rows[1][2]), pagetext.page_lines(rows[2][2])) == "Text one"


def test_page_text_against_brute_force(spark, monkeypatch):
    """Pages without articles, pages with unmarked lines around one, hot hosts in many blocks: the neighbour does not depend on the dealing."""
    r, rows = random.Random(8), []
    for i in range(150):
        host = "hot.org" if i % 3 else r.choice(["a.org", "b.org", "alone%d.org" % i])
        own, common = [f"own {i} {k}" for k in range(r.randint(0, 3))], [f"site {host} {k}" for k in range(r.randint(0, 3))]
        body = "".join(f"<div>{x}</div>" for x in r.sample(own + common, len(own + common)))
        if i % 5 == 0:
            body += f"<article><p>site {host} 0</p><p>art {i}</p></article><footer>site {host} 1</footer>"
        rows.append((i, f"http://{host}/p/{r.randrange(1000)}?q", f"<body>{body}</body>"))
    rows += [(None, rows[0][1], rows[0][2]), (150, None, "<p>x</p>"), (151, None, None), (152, "http://hot.org/zz", ""), (152, "http://hot.org/zz", ""), (153, "http://hot.org/long", "<p>" + "word " * 300_000 + "</p>")]
    host = lambda u: (u or "").partition("://")[2].partition("/")[0]
    path = lambda u: "/" + (u or "").partition("://")[2].partition("/")[2].partition("?")[0] if u else ""
    at = sorted(rows, key=lambda x: (host(x[1]), path(x[1]), -1 if x[0] is None else x[0]))
    want = Counter()
    for i, x in enumerate(at):
        near = [k for k in (i - 1, i + 1) if 0 <= k < len(at) and host(at[k][1]) == host(x[1])]
        lines, other = pagetext.page_lines(x[2]), pagetext.page_lines(at[near[0]][2]) if near else None
        table = [[0] * (len(other or []) + 1) for _ in range(len(lines) + 1)]
        for m in reversed(range(len(lines))):
            for n in reversed(range(len(other or []))):
                table[m][n] = table[m + 1][n + 1] + 1 if lines[m].text == other[n].text else max(table[m + 1][n], table[m][n + 1])
        texts = [y.text for y in lines if not y.aside and (y.main or other is not None and all(y.text != z.text for z in other) or other is None and not any(z.main for z in lines))]
        want[x[0], x[1]] = Counter(texts), table[0][0]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit("clash")).withColumn("text", F.lit(1))
    results = []
    for parts, block in ((1, 64), (5, 4), (13, 7)):
        got = [tuple(x) for x in pagetext.extract(df.repartition(parts), block_pages=block).collect()]
        results.append(Counter(got))
    assert results[0] == results[1] == results[2] and sum(results[0].values()) == len(rows)
    for i, u, text in results[0]:
        have, (must, _) = Counter(text.split("\n") if text else []), want[i, u]
        assert not must - have  # lines of one page alone stay, and so do articles
        assert len([x for x in have.elements() if x.startswith("site")]) <= 8
    # Lines that an alignment reaches go: with distinct lines per page, exactly those.
    a, b = "<div>one</div><div>two</div><div>three</div>", "<div>one</div><div>x</div><div>three</div>"
    got = pagetext.extract(spark.createDataFrame([(1, "http://h/1", a), (2, "http://h/2", b)], "page_id long, url string, html string")).collect()
    assert {x.page_id: x.text for x in got} == {1: "two", 2: "x"}
    assert pagetext.extract(df.limit(0)).count() == 0


def test_common_lines_are_a_longest_common_subsequence():
    assert len(pagetext.common_lines(list("xAxB"), list("AxB"))) == 3
    r = random.Random(5)
    for _ in range(500):
        a, b = ([r.choice("abcd") for _ in range(r.randint(0, 12))] for _ in range(2))
        most = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                most[i + 1][j + 1] = most[i][j] + 1 if x == y else max(most[i][j + 1], most[i + 1][j])
        got = sorted(pagetext.common_lines(a, b))
        rest = iter(b)
        assert len(got) == most[-1][-1] and all(a[i] in rest for i in got)


def test_line_dedup(spark, docs, monkeypatch):
    seen, keys = defaultdict(set), lambda line: line.strip(" \t\n\x0b\x0c\r").translate({i: i + 32 for i in range(65, 91)})
    rows = docs.collect()
    for r in rows:
        for line in (r.text or "").split("\n"):
            seen[keys(line)].add(r.doc_id)
    want = Counter()
    for r in rows:
        lines = (r.text or "").split("\n")
        kept = [x for x in lines if not (len(keys(x)) >= 20 and len(seen[keys(x)] - {None}) >= 3 and r.doc_id != max(seen[keys(x)] - {None}))]
        want[r.doc_id, len(lines), len(lines) - len(kept), "\n".join(kept)] += 1
    for fanout in (2, 4):
        runs = linededup.LineRuns(spark, fanout)
        got = linededup.drop_repeated(docs, runs=runs, batches=6).select("_doc.doc_id", "n_lines", "n_dropped", "kept_text")
        assert Counter(tuple(r) for r in got.collect()) == want
        assert runs.compactions >= 1
    assert linededup.BATCHES > linededup.FANOUT
    monkeypatch.setattr(linededup, "HOT_KEYS", 2)  # both ways of joining
    got = linededup.drop_repeated(docs).select("_doc.doc_id", "n_lines", "n_dropped", "kept_text")
    assert Counter(tuple(r) for r in got.collect()) == want
    assert linededup.drop_repeated(docs.limit(0)).count() == 0


def test_line_runs_compact_and_find_new_lines(spark):
    runs, lines = linededup.LineRuns(spark, fanout=2), lambda i, t: linededup.hashed_lines(spark.createDataFrame([(i, t)], "doc_id long, text string"))
    for b in reversed(range(4)):
        runs.add(lines(b, f"line number {b} is long enough\nthis line is in all of the batches"))
    assert [len(x) for x in runs.levels] == [0, 0, 1] and runs.compactions == 3
    new = runs.new_lines(lines(9, "line number 2 is long enough\nline number 7 is long enough"))
    assert [r["at"] for r in new.collect()] == [1]
    # The batch that has a key first keeps it.
    assert sorted((r.n_docs, r.last_doc) for r in runs.merged().collect()) == [(1, 0), (1, 1), (1, 2), (1, 3), (4, 3)]


def test_lm_score(spark, docs, monkeypatch):
    monkeypatch.setattr(lmscore, "SEGMENT_WORDS", 300)  # several segments
    model = lmscore.fit(docs)
    rows = lmscore.scored(model).collect()
    assert len(rows) == docs.count() and lmscore.score(docs.limit(0)).count() == 0
    counts, ends = Counter(), 0
    for r in docs.collect():
        if not lmscore.is_held_out(r.doc_id):
            counts.update((r.text or "").encode().lower().split())
            ends += 1
    n, v = sum(counts.values()) + ends, len(counts) + 1
    per = defaultdict(lambda: [0, 0])
    for w, c in counts.items():
        per[lmscore.code_of(w) & 255][0] += c
        per[lmscore.code_of(w) & 255][1] += 1
    assert {k: tuple(x) for k, x in per.items()} | {0: (ends, 1)} == model.slots
    u32 = lambda x: x & 0xFFFFFFFF

    def mixed(x, salt):
        x = u32((x ^ salt) * 0x9E3779B1)
        x = u32((x ^ x >> 15) * 0x85EBCA77)
        return x ^ x >> 13

    def softmax(base, rows, k):
        z = np.exp(base + sum(model.weights[r % len(model.weights)].astype(float) for r in rows))
        return math.log10(z[k] / z.sum())

    def brute(words):
        total, one, two = 0.0, 0, 0
        for w in [*words, None]:
            code = 0 if w is None else lmscore.code_of(w)
            y, s = code >> 4 & 15, code & 15
            both = u32(mixed(one, 3) + mixed(two, 5))
            total += softmax(model.base[0], [mixed(one, 1), mixed(two, 2), both ^ both >> 16], y)
            if w is not None:
                k = mixed(y, 13)
                total += softmax(model.base[1][y], [u32(mixed(one, 7) + k), u32(mixed(two, 11) + k)], s)
                total += math.log10((counts[w] + 1) / (sum(per[code & 255]) + 1))
            one, two = code, one
        return total

    want = {}
    for r in docs.collect():
        w = (r.text or "").encode().lower().split()
        base = sum(math.log10((counts[x] + 1) / (n + v + 1)) for x in w) + math.log10((ends + 1) / (n + v + 1))
        want[r.doc_id, len(w) + 1, sum(counts[x] > 0 for x in w) + 1, n] = base, brute(w)
    for r in rows:
        base, score = want[r.doc_id, r.n_tokens, r.n_known, r.train_tokens]
        assert abs(r.base_score - base) < 1e-6 * r.n_tokens and abs(r.score - score) < 1e-4 * r.n_tokens
        assert r.held_out == (zlib.crc32(b"" if r.doc_id is None else str(r.doc_id).encode()) % 7 == 2)


def test_lm_learns_what_follows_what(spark):
    """Words that follow one another in pairs and triples: held-out texts gain on a model without context, and more texts help."""
    r = random.Random(3)
    after = {f"w{i}": [f"w{r.randrange(300)}" for _ in range(3)] for i in range(300)}

    def text():
        out = ["w0"]
        for _ in range(120):
            out.append(r.choice(after[out[-1]]))
        return " ".join(out)

    def held_out(docs, **kw):
        got = lmscore.score(docs, **kw).filter("held_out").agg(F.sum("score"), F.sum("n_tokens")).first()
        return got[0] / got[1]

    docs = spark.createDataFrame([(i, text()) for i in range(1200)], "doc_id long, text string")
    plain, few, many = held_out(docs, rounds=0), held_out(docs.filter("doc_id < 150")), held_out(docs)
    assert plain + 0.3 < many and few < many


def test_lm_probabilities_add_up_to_one():
    r = np.random.default_rng(1)
    weights, base = r.normal(size=(64, 16)).astype(np.float32), lmscore.base_logs({k: k for k in range(16, 256)})
    assert np.allclose(np.exp(base[0]).sum(), 1) and np.allclose(np.exp(base[1]).sum(1), 1)
    rows = [r.integers(0, 64, 9) for _ in range(3)]
    z = lmscore.scores_of(weights, base[0], rows)
    assert np.allclose(sum(10 ** lmscore.log10_probs(z, np.full(9, k)) for k in range(16)), 1)


def test_lm_gradient_is_observed_less_expected():
    seg = lmscore.Segment()
    for i in range(5):
        seg.add(i, prose(i, 50).encode().split())
    codes, ids = np.array(seg.codes, np.uint32).tobytes(), np.concatenate(seg.parts)
    lens, rows = np.array([len(p) for p in seg.parts]), 1 << 10
    w, base = np.zeros((rows, 16), np.float32), lmscore.base_logs({k: 1 for k in range(16, 256)} | {0: 5})
    at = lmscore.Contexts(codes, rows)

    def likelihood(x):
        one, two = lmscore.before(ids, lens)
        (f, y), (g, s) = at.of(ids, one, two)
        return (lmscore.log10_probs(lmscore.scores_of(x, base[0], f), y) + np.where(y > 0, lmscore.log10_probs(lmscore.scores_of(x, base[1][y], g), s), 0)).sum() * np.log(10)

    observed, expected = np.zeros(rows * 16, np.float32), np.zeros((rows, 16), np.float32)
    lmscore.gradient_counts(w, base, at, ids, lens, observed, expected, 1)
    grad = observed.reshape(rows, 16) - expected
    for r, k in zip(*np.unravel_index(np.argsort(-abs(grad), axis=None)[:10], grad.shape)):
        up, down = w.copy(), w.copy()
        up[r, k] += 0.01
        down[r, k] -= 0.01
        assert abs((likelihood(up) - likelihood(down)) / 0.02 - grad[r, k]) < 0.05 * max(1, abs(grad[r, k]))


def test_quality_rules(spark, docs):
    extra = spark.createDataFrame([(400, "par " * 80, "a", "", ""), (401, " ".join(f"w{i}%%%" for i in range(60)), "a", "", "")], DOCS)
    rows = docs.unionByName(extra)
    names = "n_words word_chars n_symbols n_dup_lines n_repeat_words".split()
    want = Counter()
    for r in rows.collect():
        t = r.text or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        grams, covered = defaultdict(list), set()
        for i in range(len(w) - 2):
            grams[tuple(w[i : i + 3])].append(i)
        for at in grams.values():
            if len(at) > 1:
                covered |= {i + k for i in at for k in range(3)}
        want[r.doc_id, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered)] += 1
    got = quality.judge(rows).select("_doc.doc_id", *names, "base_failed", "kept").collect()
    assert Counter(tuple(r)[:6] for r in got) == want
    assert all(not r.kept for r in got if r.base_failed or r.doc_id in (400, 401))
    kept = quality.keep_good(rows)
    assert kept.columns == rows.columns and kept.count() == sum(r.kept for r in got)


def test_stop_words_are_counted_in_the_whole_text(spark):
    text = "the and " + "w " * 500 + "of to der"
    docs = spark.createDataFrame([(1, text)], "doc_id long, text string")
    assert quality.judge(docs).first().stop_words == 5
    assert quality.judge(docs, rules=(quality.Rule("stop_words", 5, None),)).first().broken == []
    assert quality.judge(docs, rules=(quality.Rule("stop_words", None, 4),)).first().broken == ["stop_words>4"]


def test_lm_training_takes_expected_counts_at_all_positions(spark, monkeypatch):
    """One round over one fold: the weights are those of whole counts, whatever a position's place."""
    monkeypatch.setattr(lmscore, "packed", lambda x: np.ascontiguousarray(x, np.float32).tobytes())
    monkeypatch.setattr(lmscore, "unpacked", lambda x: np.frombuffer(x, np.float32))
    texts = [(i, prose(i, 60)) for i in range(12)]
    made = lmscore.segments(spark.createDataFrame(texts, "doc_id long, text string").coalesce(1)).filter("ids is not null")
    base, rows = lmscore.base_logs({k: 1 for k in range(16, 256)} | {0: 5}), 1 << 10
    observed, expected = np.zeros(rows * 16, np.float32), np.zeros((rows, 16), np.float32)
    for x in made.collect():
        mine = np.array([not lmscore.is_held_out(d) for d in x.doc_ids])
        lens = np.array(x.lens)
        ids = lmscore.unpacked_ids(bytes(x.ids), int(lens.sum()))
        at, ids, lens = lmscore.Contexts(bytes(x.codes), rows), ids[np.repeat(mine, lens)], lens[mine]
        one, two = lmscore.before(ids, lens)
        for i in range(len(ids)):
            for level, (rows_, outcome) in enumerate(at.of(ids[i : i + 1], one[i : i + 1], two[i : i + 1])):
                y = at.y[ids[i]]
                if level == 0 or y > 0:
                    p = np.exp(base[0] if level == 0 else base[1][y])
                    for r in rows_:
                        observed[r[0] * 16 + outcome[0]] += 1
                        expected[r[0]] += p / p.sum()
    want = lmscore.step(np.zeros((rows, 16), np.float32), observed.reshape(rows, 16), expected)
    assert np.allclose(lmscore.train(made, base, rows, rounds=1), want, atol=1e-3)


def test_lm_training_gets_one_segment_at_a_time(spark, docs, monkeypatch, tmp_path):
    """A task reads many segments; a batch of them would be as large as its share of the corpus."""
    from graphwatch.llm.workers import trimmed

    monkeypatch.setattr(lmscore, "SEGMENT_WORDS", 300)
    model, conf, path = lmscore.fit(docs, rounds=0), "spark.sql.execution.arrow.maxRecordsPerBatch", str(tmp_path / "rows")

    def noting(run):
        def task(batches):
            def noted():
                for b in batches:
                    with open(path, "a") as f:
                        print(b.num_rows, file=f)
                    yield b

            return run(noted())

        return trimmed(task)

    monkeypatch.setattr(lmscore, "trimmed", noting)
    before = spark.conf.get(conf)
    weights = lmscore.train(model.segs.coalesce(1), model.base, 1 << 10, rounds=1)
    rows = [int(x) for x in open(path)]
    assert weights.any() and len(rows) == model.segs.count() > 3 and set(rows) == {1}
    assert spark.conf.get(conf) == before


def test_a_new_word_takes_few_calls_and_has_the_tokenizers_ids():
    """Most CPU seconds of the token files go into words that a worker has not met: calls must not grow with a word's letters."""
    import sys

    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    ids, model, r = tokenfiles.WordIds(path), Tokenizer.from_file(path), random.Random(5)
    words = ["".join(r.choices("abcdefghijklmnopqrstuvwxyzABCéüñÉ", k=r.randrange(8, 30))) + r.choice(["", ".", "?", "$$$"]) for _ in range(300)]
    ids[b"warm."], ids[words[0].encode()]
    made = [0]

    def count(frame, event, arg):
        made[0] += event == "call"

    new = [w.encode() for w in words[1:]]
    sys.setprofile(count)
    try:
        got = [ids[w] for w in new]
    finally:
        sys.setprofile(None)
    assert got == [np.array(model.encode(w, add_special_tokens=False).ids, "<u4").tobytes() for w in words[1:]]
    assert made[0] < 8 * len(new)
