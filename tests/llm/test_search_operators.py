"""License scans, near duplicates, substrings and top-k against brute force."""

import hashlib
import random
import re

import numpy as np

from forestmine.llm import license_scan, near_dup, substring_dedup, topk_search
from forestmine.llm.components import components

SPACE = re.compile(r"[^\x20\x09-\x0D]+")


def lower(t):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")


def test_license_scan(docs, rows, empty):
    phrases = {("mit", "license"): "mit", ("apache", "license"): "apache", ("general", "public", "license"): "gpl"}
    got = sorted(license_scan.scan_licenses(docs).collect(), key=str)
    wanted = []
    for r in rows:
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(r[1]))
        hits = [(i, label) for p, label in phrases.items() for i in range(len(w)) if tuple(w[i : i + len(p)]) == p]
        starts = [i for i, _ in hits]
        wanted.append((r[0], len(w), len(hits), min(starts, default=None), max(starts, default=None), ",".join(sorted({x for _, x in hits}))))
    assert sorted((tuple(g[:6]) for g in got), key=str) == sorted(wanted, key=str)
    assert all(0 <= g["score"] <= 1 for g in got)
    assert license_scan.scan_licenses(empty).count() == 0
    notice = b"x licensed under the apache license, version 2.0 y"
    assert [s[0] for s in license_scan.LicenseScanner().scan(notice)[3]] == ["apache"]


def plain_spans(scanner, words, templates):
    """Spans from runs found by comparing all places of the text with all places of the templates."""
    sequences = [[w.decode() for w in license_scan.license_words(t.encode())] for _, t in templates]
    best = []  # for each end: the longest run of words that some template holds
    for i in range(1, len(words) + 1):
        n = 0
        for s in sequences:
            for j in range(1, len(s) + 1):
                k = 0
                while k < min(i, j) and s[j - 1 - k] == words[i - 1 - k]:
                    k += 1
                n = max(n, k)
        best.append(n)
    runs = [(i + 1, n) for i, n in enumerate(best) if n > 1 and (i + 1 == len(best) or best[i + 1] != n + 1)]
    spans = []
    for (label, _), s in zip(templates, sequences):
        current = None
        holds = lambda r: any(s[j : j + len(r)] == r for j in range(len(s)))
        for end, n in runs:
            if n < license_scan.MIN_RUN or not holds(words[end - n : end]):
                continue
            if current and end - n <= current[1] + license_scan.MAX_GAP:
                current = (min(current[0], end - n), max(current[1], end), current[2] | set(range(end - n, end)))
            else:
                spans += [(label, s, current)] if current else []
                current = (end - n, end, set(range(end - n, end)))
        spans += [(label, s, current)] if current else []
    out = []
    for n, label, a, b in sorted((-len(c[2]), label, c[0], c[1]) for label, s, c in spans if len(c[2]) >= min(license_scan.ENOUGH, license_scan.SHARE * len(s))):
        if all(b <= x or y <= a for _, x, y, _ in out):
            out.append((label, a, b, -n))
    return sorted(out, key=lambda s: (s[1], s))


def test_license_spans_and_labels(spark):
    rng = random.Random(12)
    templates = [("x", "a b c d e f g h i j"), ("y", "c d e f q r s t u v w"), ("x", "m n o p"), ("z", "a b c q r s k l")]
    scanner = license_scan.LicenseScanner(templates, {"b c": "x", "k": "one"})
    for _ in range(150):
        words = []
        while len(words) < 40:
            _, t = rng.choice(templates)
            t = t.split()
            i = rng.randrange(len(t))
            words += t[i : i + rng.randint(1, 8)] + [rng.choice("abckqz")] * rng.randint(0, 2)
        n, starts, base, spans = scanner.scan(" ".join(words).encode())
        assert spans == plain_spans(scanner, words, templates)
        want = sorted([i for i in range(len(words) - 1) if words[i : i + 2] == ["b", "c"]] + [i for i, w in enumerate(words) if w == "k"])
        assert n == len(words) and sorted(starts) == want and ("one" in base) == ("k" in words)


def test_whole_licenses_are_found():
    scanner = license_scan.LicenseScanner()
    for label, text in license_scan.TEMPLATES:
        found = scanner.scan(f"some words {text} and more".encode())[3]
        size = len(license_scan.license_words(text.encode()))
        assert len(found) == 1 and found[0][0] == label and found[0][2] - found[0][1] == size, (label, found, size)
    edited = license_scan.TEMPLATES[1][1].replace("merge, publish", "merge or publish")
    assert [s[0] for s in scanner.scan(edited.encode())[3]] == ["mit"]
    assert scanner.scan(b"permission is granted to use the software as it is")[3] == []


def test_automaton_matching_statistics():
    rng = random.Random(1)
    sequences = [[rng.randrange(3) for _ in range(rng.randint(1, 12))] for _ in range(6)]
    a = license_scan.SuffixAutomaton()
    for i, s in enumerate(sequences):
        a.add(s, i)
    runs = {tuple(s[i:j]) for s in sequences for i in range(len(s)) for j in range(i + 1, len(s) + 1)}
    text = [rng.randrange(3) for _ in range(300)]
    state = length = 0
    for i, word in enumerate(text):
        state, length = a.advance(state, length, word)
        assert length == max((n for n in range(1, 13) if n <= i + 1 and tuple(text[i + 1 - n : i + 1]) in runs), default=0)
        if length:
            own = tuple(text[i + 1 - length : i + 1])
            assert a.owners[state] == {k for k, s in enumerate(sequences) if any(tuple(s[j : j + length]) == own for j in range(len(s)))}


def shingles(t, k):
    w = SPACE.findall(lower(t))
    return set() if not w else {tuple(w)} if len(w) < k else {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}


def test_near_duplicates(docs, rows, empty):
    sets = [(r[0], shingles(r[1], 4)) for r in rows]
    known = [(i, s) for i, s in sets if i is not None]
    root = {i: i for i, _ in known}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in known:
        for j, b in known:
            if i < j and a and b and 100 * len(a & b) >= 80 * len(a | b):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    wanted = [(i, len(s), find(i) if i is not None else None, i is None or find(i) == i) for i, s in sets]
    got = [tuple(r) for r in near_dup.near_duplicates(docs, k=4).collect()]
    assert sorted(got, key=str) == sorted(wanted, key=str)
    assert near_dup.near_duplicates(empty, k=4).count() == 0


def test_near_copies_that_miss_the_leader_still_join(spark):
    rng = random.Random(2)
    base = [f"w{i}" for i in range(400)]
    texts = [" ".join(base)]
    for i in range(12):
        own = list(base)
        for j in rng.sample(range(400), 9):
            own[j] = f"x{i}-{j}"
        texts.append(" ".join(own))
    df = spark.createDataFrame([(100 - i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    assert {r["component_id"] for r in near_dup.near_duplicates(df, k=4).collect()} == {88}


def test_signature_estimates_similarity():
    rng = np.random.default_rng(0)
    a = rng.integers(0, 2**63, 1000).astype(np.uint64)
    b = np.concatenate((a[:800], rng.integers(0, 2**63, 200).astype(np.uint64)))
    s = near_dup.signatures(np.concatenate((np.sort(a), np.sort(b))), np.array([0, 1000, 2000]), 512)
    assert abs((s[0] == s[1]).mean() - 800 / 1200) < 0.1


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 30)] + [(7, 7), (None, 3)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, **{100 + i: 100 for i in range(30)}}


def remove_repeats(rows, k=13):
    least = {}
    for i, t, *_ in rows:
        w = SPACE.findall(t or "")
        for j in range(len(w) - k + 1):
            if i is not None:
                g = tuple(w[j : j + k])
                least[g] = min(least.get(g, i), i)
    out = []
    for i, t, *_ in rows:
        w = SPACE.findall(t or "")
        gone = {x for j in range(len(w) - k + 1) if i is not None and least[tuple(w[j : j + k])] < i for x in range(j, j + k)}
        kept = " ".join(x for j, x in enumerate(w) if j not in gone)
        out.append((i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


def test_substring_dedup(docs, rows, empty):
    wanted = sorted(remove_repeats(rows), key=str)
    for batches in (1, 3):
        got = substring_dedup.dedup_substrings(docs, batches=batches).drop("kept_text").collect()
        assert sorted((tuple(r) for r in got), key=str) == wanted
    assert substring_dedup.dedup_substrings(empty).count() == 0


def test_index_keeps_history_and_compacts(spark, docs, rows, empty, monkeypatch):
    wanted = [r for r in remove_repeats([r for r in rows if r[0] is not None])]
    for fanout, windows, runs, buckets in ((2, 1_000_000, 1, 8), (3, 500, 2, 32), (9, 1_000_000, 4, 8)):
        monkeypatch.setattr(substring_dedup, "FANOUT", fanout)
        monkeypatch.setattr(substring_dedup, "BUCKET_WINDOWS", windows)
        index = substring_dedup.FingerprintIndex(spark, buckets=8)
        got = []
        for low, high in ((0, 10), (10, 25), (25, 38), (38, 1000)):
            part = docs.filter(f"doc_id >= {low} and doc_id < {high}")
            got += substring_dedup.dedup_substrings(part, batches=1, index=index).drop("kept_text").collect()
        assert len(index.runs) == runs and index.buckets >= buckets
        assert sorted((tuple(r) for r in got), key=str) == sorted(wanted, key=str)
        assert index.add(empty).count() == 0
        index.drop()


def test_a_run_is_read_without_a_shuffle(spark, docs):
    index = substring_dedup.FingerprintIndex(spark, buckets=8)
    index.add(docs)
    run = index._run(index.runs[0])
    plan = run.groupBy("bucket").cogroup(run.groupBy("bucket")).applyInArrow(substring_dedup._compact(8, 1), substring_dedup._ROWS)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    index.drop()


def test_packing_round_trips():
    rng = np.random.default_rng(1)
    h = np.unique(rng.integers(0, 2**63, 1000).astype(np.uint64) * np.uint64(2))
    ids = rng.integers(-5, 2**40, len(h))
    assert (substring_dedup._unpack(substring_dedup._pack(h)) == h).all()
    assert (substring_dedup._unpack_ids(substring_dedup._pack_ids(ids)) == ids).all()


def test_top_k(spark, monkeypatch):
    monkeypatch.setattr(topk_search, "SHARD", 40)
    monkeypatch.setattr(topk_search, "STRIP", 7)
    monkeypatch.setattr(topk_search, "BLOCK", 4)
    rng = random.Random(4)
    rows = [(i, [rng.randint(-3, 3) for _ in range(6)]) for i in range(120)] + [(50, [1, 1, 1, 1, 1, 1]), (7, None), (8, [1, None]), (None, [1]), (121, [9, 9])]
    df = spark.createDataFrame(rows, "vec_id long, v array<long>")
    from pyspark.sql import functions as F

    got = [tuple(r) for r in topk_search.top_k(df, F.col("id") % 10 == 0, k=5).collect()]
    use = [(i, v + [0] * (6 - len(v))) for i, v in rows if i is not None and v is not None and None not in v]
    wanted = []
    for q in sorted({i for i, _ in use if i % 10 == 0}):
        vec = min(v for i, v in use if i == q)
        scores = sorted((-sum(a * b for a, b in zip(vec, v)), i) for i, v in use if i != q)[:5]
        wanted += [(q, n, i, -s) for n, (s, i) in enumerate(scores, 1)]
    assert sorted(got) == sorted(wanted)
    assert topk_search.top_k(df.filter("false"), F.lit(True)).count() == 0
    bad = spark.sql("SELECT 1L AS vec_id, array(float('NaN'), 1f) AS embedding UNION ALL SELECT 2L, array(0.5f, -0.01f) UNION ALL SELECT 3L, NULL")
    assert {r["vec_id"]: r["v"] for r in topk_search.scaled_embeddings(bad).collect()} == {1: None, 2: [32, -1], 3: None}


def test_top_k_prunes_and_handles_huge_numbers():
    rng = np.random.default_rng(5)
    for scale in (1, 1 << 40):
        rows, queries = rng.integers(-5, 6, (300, 8)) * scale, rng.integers(-5, 6, (4, 8)) * (scale if scale == 1 else 1 << 12)
        of, ids, score = topk_search.max_score(np.arange(300), rows, np.array([500, 501, 502, 503]), queries, 7)
        for q in range(4):
            full = sorted((-int(sum(int(a) * int(b) for a, b in zip(queries[q], r))), i) for i, r in enumerate(rows))[:7]
            assert sorted((-int(s), int(i)) for o, i, s in zip(of, ids, score) if o == q) == full


def test_windows_of_one_hash_but_other_words_are_no_repeats():
    import numpy as np
    import pyarrow as pa

    h, one, other = np.array([7], np.uint64), np.array([1], np.uint16), np.array([2], np.uint16)
    block = lambda doc, second: ("block", 0, None, substring_dedup._pack(h) + second.tobytes(), substring_dedup._pack_ids(np.array([doc], np.int64)))
    found = lambda *rows: [r for r in substring_dedup._settle(False, False)(pa.Table.from_batches([substring_dedup._rows(list(rows))])).to_pylist() if r["kind"] == "repeat"]
    assert [r["doc_id"] for r in found(block(1, one), block(2, one))] == [2] and not found(block(1, one), block(2, other))
    text = " ".join(f"w{i}" for i in range(13))
    (w,) = substring_dedup._text.words(pa.array([text]), lower=False)
    pair = np.empty(1, substring_dedup._PAIR)
    pair["h"] = w.windows(13)[0]
    for change, gone in ((0, 13), (1, 0)):
        pair["s"] = substring_dedup._second(w, 13) ^ np.uint16(change)
        batch = pa.RecordBatch.from_arrays([pa.array([5]), pa.array([text]), pa.array([[pair.tobytes()]])], names=["doc_id", "text", "payloads"])
        assert next(iter(substring_dedup._remove(13)(iter([batch])))).column("n_removed").to_pylist() == [gone]


def test_substrings_whose_blocks_come_in_any_order(spark):
    """A passage that an older run holds goes from every document of a batch, whichever block is met first."""
    from pyspark.sql import functions as F

    passage = " ".join(f"w{i}" for i in range(20))
    rows = [(i, f"{passage} own{i} {passage if i % 3 else ''}") for i in range(60)]
    docs = spark.createDataFrame(rows[::-1], "doc_id long, text string").repartitionByRange(12, F.desc("doc_id"))
    got = {r["doc_id"]: (r["n_words"], r["n_removed"]) for r in substring_dedup.dedup_substrings(docs).collect()}
    assert got == {i: (41 if i % 3 else 21, 0 if i == 0 else 40 if i % 3 else 20) for i in range(60)}


def test_settle_marks_all_places_of_a_window_that_a_run_holds():
    import pyarrow as pa

    pack = lambda docs: substring_dedup._pack_ids(np.array(docs, np.int64))
    one = substring_dedup._pack(np.array([5], np.uint64)) + np.array([1], np.uint16).tobytes()
    for docs in ((9, 4), (4, 9)):
        group = pa.Table.from_batches([substring_dedup._rows([("block", 0, None, one, pack([d])) for d in docs])])
        old = pa.Table.from_batches([substring_dedup._rows([("run", 0, None, one, None)])])
        out = substring_dedup._settle(False, False)(group, old)
        assert set(out.column("doc_id").to_pylist()) == {4, 9}
