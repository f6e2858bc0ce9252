import gzip
import hashlib
import math
import zlib
from collections import Counter

import numpy as np
import pytest

from walkfold.llm import decontaminate, fingerprints, jaccard_join, mixing, preferences, quality, secrets, suffix_tree, token_counts, warc
from walkfold.llm.components import components

SF = "/root/testdata/sf0.001"


def texts(df):
    return [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]


# -- fingerprints --------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("which", ["odd", "small"])
def test_fingerprints_match_sets(which, request):
    df = request.getfixturevalue(which)
    rows = sorted(((-1 if i is None else i, i, t or "") for i, t in texts(df)), key=lambda r: (r[0], r[2]))
    got = fingerprints.fingerprint_versions(df, parts=3).collect()
    like = lambda x, y: len(x & y) / len(x | y) if x | y else 1.0
    want = Counter()
    for k, (_, i, text) in enumerate(rows):
        following = rows[(k + 1) % len(rows)][2]
        version = fingerprints.edited(text, following)
        a, b, c = (set(fingerprints.digests(x).tolist()) for x in (text, version, following))
        want[i, len(text), hashlib.sha256(version.encode()).hexdigest(), round(like(a, b), 9), round(like(a, c), 9)] += 1
    assert Counter((r.doc_id, r.n_chars, r.edited_sha256, round(r.near_edited, 9), round(r.near_next, 9)) for r in got) == want
    by_text, of = {}, {i: t for _, i, t in rows}
    assert all(by_text.setdefault(of[r.doc_id], r.fingerprint) == r.fingerprint for r in got)


def test_sketch_differences_are_recovered_after_retries():
    draw = np.random.default_rng(1)
    a = [draw.integers(0, 2**63, n).astype(np.uint64) for n in (0, 3, 40, 400)]
    b = [np.concatenate([x[: len(x) // 2], draw.integers(0, 2**63, 5).astype(np.uint64)]) for x in a]
    for x, y, (only_a, only_b) in zip(a, b, fingerprints.differences(a, b), strict=True):
        assert only_a == set(x.tolist()) - set(y.tolist()) and only_b == set(y.tolist()) - set(x.tolist())


def test_long_texts_without_sentence_marks_keep_their_likeness():
    draw = np.random.default_rng(2)
    plain = " ".join("".join(chr(97 + c) for c in draw.integers(0, 26, 6)) for _ in range(300))
    unspaced = "".join(chr(0x4E00 + c) for c in draw.integers(0, 3000, 1500))
    for text in (plain, unspaced, "word " * 400, "the same line\n" * 40):
        a, b = (fingerprints.digests(x) for x in (text, fingerprints.edited(text, unspaced[::-1])))
        assert len(a) > 10 and fingerprints.likeness([a], [b])[0] > 0.4
    shifted = fingerprints.digests("Put before it " + plain)
    assert fingerprints.likeness([fingerprints.digests(plain)], [shifted])[0] > 0.8


# -- suffix tree ---------------------------------------------------------------------------------------------------


def test_scores_against_brute_force(small):
    got = {r.doc_id: r for r in suffix_tree.score_documents(small).collect()}
    docs = {i: suffix_tree.words((t or "").encode()) + [b"\n"] for i, t in texts(small)}
    counts = Counter(w for i, ws in docs.items() if not suffix_tree.held_out(i) for w in ws)
    n, v = sum(counts.values()), len(counts)
    for i, ws in docs.items():
        r = got[i]
        assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (len(ws), sum(w in counts for w in ws), n, zlib.crc32(str(i).encode()) % 10 == 0)
        assert r.base_score == pytest.approx(sum(math.log10((counts[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws))


def test_scores_beat_the_base_on_held_out_texts(spark):
    got = suffix_tree.score_documents(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).where("held_out").collect()
    assert sum(r.score for r in got) > sum(r.base_score for r in got)


def plain_tree_score(learnt, text, depth=2):
    """Retention, smoothing and the longest retained suffix, spelt out over dictionaries of counts."""
    counts = {}
    for ws in learnt:
        s = b"\n" * depth + b" ".join(ws) + b"\n"
        for at in range(depth, len(s)):
            for d in range(depth + 1):
                counts.setdefault(s[at - d : at], Counter())[s[at]] += 1
    root = counts.get(b"", Counter())
    total = sum(root.values())
    bar = suffix_tree.GAIN * math.log(max(total, 2))

    def p(context, x):
        own = counts[context] if context in counts else Counter()
        if not context:
            return (own[x] + 0.01) / (sum(own.values()) + 2.56)
        return (own[x] + suffix_tree.STRENGTH * p(context[1:], x)) / (sum(own.values()) + suffix_tree.STRENGTH)

    def diverges(context):
        own, n = counts[context], sum(counts[context].values())
        return sum(c * math.log(c / n / p(context[1:], x)) for x, c in own.items()) > bar

    kept = {c[at:] for c in counts if c and diverges(c) for at in range(len(c))} | {b""}
    s, out = b"\n" * depth + b" ".join(text) + b"\n", 0.0
    for at in range(depth, len(s)):
        state = next(s[at - d : at] for d in range(depth, -1, -1) if s[at - d : at] in kept)
        out += math.log10(p(state, s[at]))
    return out


def test_tree_against_a_plain_version():
    parts = [suffix_tree.words(t) for t in (b"the cat sat on the mat", b"the dog sat on the log", b"", b"a mat sat")] * 15
    codes, n = suffix_tree.count_codes(suffix_tree.chunks(iter(parts)), 2)
    rows = [(d, int(c), int(n[(codes & np.uint64((1 << (8 * (d + 1))) - 1)) == c].sum())) for d in range(3) for c in np.unique(codes & np.uint64((1 << (8 * (d + 1))) - 1))]
    tree = suffix_tree.SuffixTree(np.array(rows, [("depth", np.int8), ("code", np.int64), ("count", np.int64)]), int(n.sum()), 2)
    for text in (b"the cat sat on the log", b"zebra", b"", b"mat mat"):
        assert tree.score([suffix_tree.words(text)])[0] == pytest.approx(plain_tree_score(parts, suffix_tree.words(text)), rel=1e-5)


def test_tree_gives_a_distribution():
    parts = [suffix_tree.words(t) for t in (b"the cat sat on the mat", b"the dog sat on the log", b"")]
    codes, n = suffix_tree.count_codes(suffix_tree.chunks(iter(parts * 20)), 3)
    rows = []
    for d in range(4):
        low = codes & np.uint64((1 << (8 * (d + 1))) - 1)
        rows += [(d, int(c), int(n[low == c].sum())) for c in np.unique(low)]
    table = np.array(rows, [("depth", np.int8), ("code", np.int64), ("count", np.int64)])
    tree = suffix_tree.SuffixTree(table, int(n.sum()), 3)
    assert tree.states > 1
    p = 10.0 ** tree.logp.reshape(tree.states, tree.size).astype(float)
    unseen = 256 - (tree.size - 1)
    assert np.allclose(p[:, :-1].sum(1) + unseen * p[:, -1], 1, atol=1e-4)
    # the longest suffix state, found one symbol at a time
    text = [b"the", b"cat"]
    symbols = b"\n\n\n" + b"the cat\n"
    total = 0.0
    for at in range(3, len(symbols)):
        node = 0
        for d in range(1, 4):
            child = tree.child[node * tree.size + tree.classes[symbols[at - d]]]
            if not child:
                break
            node = child
        total += tree.logp[node * tree.size + tree.classes[symbols[at]]]
    assert tree.score([text])[0] == pytest.approx(total, rel=1e-5)


def test_scores_of_odd_rows(odd, empty):
    got = suffix_tree.score_documents(odd).collect()
    assert len(got) == odd.count() and all(r.score < 0 and r.base_score <= 0 for r in got)
    assert suffix_tree.score_documents(empty).count() == 0


def test_contexts_enter_the_tree_whatever_their_share(small, monkeypatch):
    """The dealt tree against the whole one in memory, of every context; a rare one that diverges is in it."""
    docs = texts(small)
    learnt = [suffix_tree.words((t or "").encode()) for i, t in docs if not suffix_tree.held_out(i)]
    codes, n = suffix_tree.count_codes(suffix_tree.chunks(iter(learnt)))
    rows = []
    for d in range(suffix_tree.DEPTH + 1):
        pair, of = np.unique(codes & np.uint64((1 << (8 * (d + 1))) - 1), return_inverse=True)
        rows.append(np.rec.fromarrays([np.full(len(pair), d), pair.astype(np.int64), np.bincount(of, weights=n).astype(np.int64)], names="depth,code,count"))
    tree = suffix_tree.SuffixTree(np.concatenate(rows), int(n.sum()))
    want = dict(zip((i for i, _ in docs), tree.score([suffix_tree.words((t or "").encode()) for _, t in docs]), strict=True))
    for piece in (1 << 24, 1 << 14):
        monkeypatch.setattr(suffix_tree, "PIECE", piece, raising=False)
        got = {r.doc_id: r.score for r in suffix_tree.score_documents(small).collect()}
        assert got == pytest.approx(want, rel=1e-4)


# -- jaccard join --------------------------------------------------------------------------------------------------


def brute_components(rows, k, percent):
    sets = {}
    for n, (_, t) in enumerate(rows):
        w = (t or "").encode().lower().split()
        sets[n] = {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                root[find(a)] = find(b)
    least = {}
    for n, (i, _) in enumerate(rows):
        if i is not None:
            least[find(n)] = min(i, least.get(find(n), i))
    return Counter((i, len(sets[n]), i if not sets[n] else least.get(find(n))) for n, (i, _) in enumerate(rows))


@pytest.mark.parametrize(("k", "percent"), [(3, 90), (5, 80)])
def test_components_match_brute_force(odd, small, k, percent):
    for df in (odd, small):
        got = Counter(map(tuple, jaccard_join.component_ids(df, k, percent).collect()))
        assert got == brute_components(texts(df), k, percent)


def test_family_links_connect_what_all_pairs_do():
    draw = np.random.default_rng(3)
    for percent in (80, 90):
        base = draw.integers(0, 2**62, 150).astype(np.uint64)
        sets = []
        for _ in range(260):
            x = base.copy()
            x[draw.choice(150, draw.integers(0, 14), replace=False)] = draw.integers(0, 2**62, 1)
            extra = draw.integers(0, 2**62, draw.integers(0, 9)).astype(np.uint64)
            sets.append(np.unique(np.concatenate([x, extra])))
        keys = np.arange(len(sets)) * 7
        found = jaccard_join.link_family(keys, sets, percent)
        want = [(a, b) for a in range(len(sets)) for b in range(a) if 100 * len(np.intersect1d(sets[a], sets[b])) >= percent * len(np.union1d(sets[a], sets[b]))]

        def groups(pairs):
            root = list(range(len(sets)))

            def find(x):
                while root[x] != x:
                    x = root[x]
                return x

            for a, b in pairs:
                root[max(find(a), find(b))] = min(find(a), find(b))
            return [find(x) for x in range(len(sets))]

        assert groups([(a // 7, b // 7) for a, b in found]) == groups(want)
        # every linked pair agrees on a segment
        sigs = [set(jaccard_join.signatures(s, percent / 100).tolist()) for s in sets]
        assert all(sigs[a] & sigs[b] or np.array_equal(sets[a], sets[b]) for a, b in want)
        # the sketches keep every link
        bits = jaccard_join.folded([jaccard_join.sketch(s) for s in sets], 128)
        sizes = np.array([len(s) for s in sets])
        assert all(b in jaccard_join.near(sizes, bits, a, np.array([b]), percent) for a, b in want)
        assert groups([*jaccard_join.cluster(sizes, bits, percent), *want]) == groups(jaccard_join.cluster(sizes, bits, percent))


def test_components_of_a_chain_and_a_star(spark):
    edges = [(i, i + 1) for i in range(40)] + [(1000, x) for x in range(1001, 1060)] + [(5, 5)]
    got = dict(map(tuple, components(spark.createDataFrame(edges, "x long, y long"), "x", "y").collect()))
    assert got == {i: 0 for i in range(41)} | {x: 1000 for x in range(1000, 1060)}


def test_keep_one(odd, empty):
    kept = [r.doc_id for r in jaccard_join.keep_one(odd, 5, 80).collect()]
    assert sorted(x for x in kept if x) == [1, 2, 3, 4, 5, 6, 7, 9] and jaccard_join.keep_one(odd, 5, 80).columns == odd.columns
    assert jaccard_join.keep_one(empty).count() == 0


# -- secrets -------------------------------------------------------------------------------------------------------


def test_forest_on_held_out_findings():
    forest = secrets.train()
    rows = secrets.example_findings(1500, seed=99)
    x = np.array([secrets.describe(t, next((c for c in secrets.candidates(t) if c.start <= s < c.end), secrets.Candidate(s, e, "run")), p) for t, s, e, p, _ in rows])
    y = np.array([r[4] for r in rows])
    assert ((forest.score(x) >= 0.5) == y).mean() > 0.97


def test_secrets_are_found_and_redacted(spark, odd, empty):
    token = "9f2c4e1ab87d6035e4c1a9b2d8f7360514cebad7"
    rows = [(1, f'before token = "{token}" after', "s"), (2, "card 4485168114407329 and mail an.12@mail3.example.com", "s"), (3, "commit 9f2c4e1ab87d6035e4c1a9b2d8f7360514cebad7 fixed", "s"), (4, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: r for r in secrets.scan(df).collect()}
    assert [got[i].n_secrets for i in (1, 2, 3, 4)] == [1, 0, 0, 0]
    f = [x for x in got[1].findings if x.secret][0]
    assert rows[0][1][f.start : f.end] == token
    clean = {r.doc_id: r.text for r in secrets.redact(df).collect()}
    assert clean[1] == 'before token = "[SECRET]" after' and clean[2] == rows[1][1] and clean[4] is None
    assert secrets.redact(odd).columns == odd.columns and secrets.scan(odd).count() == odd.count() and secrets.scan(empty).count() == 0


def test_all_planted_tokens_are_found(small):
    import re

    got = {(r.doc_id, f.start) for r in secrets.scan(small).collect() for f in r.findings if f.secret}
    want = {(i, m.start(1)) for i, t in texts(small) for m in re.finditer(r'token = "([0-9a-f]{40})"', t or "")}
    assert want <= got and len(got) <= len(want) + 2


# -- tokens --------------------------------------------------------------------------------------------------------


def test_token_counts_match_the_library(odd, small, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    own = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for df in (odd, small):
        got = Counter(map(tuple, token_counts.count_tokens(df).collect()))
        want = Counter()
        for i, t in texts(df):
            n = len(own.encode(t or "", add_special_tokens=False).ids)
            want[i, len((t or "").encode()), n, n > 1024] += 1
        assert got == want
    assert token_counts.count_tokens(empty).count() == 0


@pytest.mark.parametrize("text", ["<|endoftext|><|endoftext|> x", "a b  \n\n c", "日本語 テスト ١٢٣", "it's I'LL we'Re", "éx 𝒳 🙂🙂", "tab\t\tend  "])
def test_pre_tokens_encode_alone_as_together(text):
    rule = token_counts.PreTokenizer(token_counts.default_tokenizer())
    assert sum(rule.pieces(rule(text))) == len(rule.tokenizer.encode(text, add_special_tokens=False).ids)


# -- warc ----------------------------------------------------------------------------------------------------------


def test_archive_round_trip(spark):
    rows = [(1, "http://a/1", "<p>é</p>"), (2, None, "<p>é</p>"), (3, "http://a/3", None), (4, "u\r\nv", ""), (5, "http://a/5", "WARC/1.1\r\nfake"), (None, "x", "<p>é</p>"), (9, "y", "z" * 200_000), (9, "y", "z" * 200_000)]
    got = Counter(map(tuple, warc.archive_round_trip(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()))
    top = {}
    for i, _, h in rows:
        top[h or ""] = max([x for x in (i, top.get(h or "")) if x is not None], default=None)
    want = Counter()
    for i, _, h in rows:
        b = (h or "").encode()
        last = top[h or ""]
        want[i, len(b), warc._digest(b), "response" if i == last else "revisit", None if i == last else last] += 1
    assert got == want
    assert warc.archive_round_trip(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def record(n, body=b"hello"):
    return b"WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:x:%d>\r\nWARC-Block-Digest: sha1:%s\r\nContent-Length: %d\r\n\r\n%s\r\n\r\n" % (n, warc._digest(body).encode(), len(body), body)


@pytest.mark.parametrize("packed", [False, True])
def test_salvage_after_damage(packed):
    pack = gzip.compress if packed else lambda x: x
    parts = [pack(record(i)) for i in range(5)]
    damaged = bytearray(parts[1])
    damaged[-12] ^= 0xFF
    data = parts[0] + bytes(damaged) + parts[2] + b"\x00garbage" + parts[3] + parts[4][: len(parts[4]) // 2]
    found = list(warc.salvage(data))
    assert [x["names"]["warc-record-id"] for x in found if "names" in x] == ["<urn:x:0>", "<urn:x:2>", "<urn:x:3>"]
    gaps = [(x["offset"], x["length"]) for x in found if "reason" in x]
    a = len(parts[0])
    b = a + len(parts[1])
    c = b + len(parts[2])
    d = c + 8
    assert gaps == [(a, len(parts[1])), (c, 8), (d + len(parts[3]), len(parts[4]) // 2)]
    assert sum(x["length"] for x in found) == len(data)


def test_gaps_inside_members_and_late_damage():
    broken = bytearray(record(1))
    broken[-8] ^= 0xFF
    one = gzip.compress(record(0) + bytes(broken) + record(2))
    found = list(warc.salvage(one))
    assert [x["names"]["warc-record-id"] for x in found if "names" in x] == ["<urn:x:0>", "<urn:x:2>"]
    (gap,) = [x for x in found if "reason" in x]
    assert (gap["offset"], gap["length"], gap["inner_offset"], gap["inner_length"]) == (0, 0, len(record(0)), len(record(1)))
    # incompressible bodies: what comes before the damage unpacks
    big = [record(i, np.random.default_rng(i).integers(0, 256, 30_000, np.uint8).tobytes()) for i in range(4)]
    member = bytearray(gzip.compress(b"".join(big)))
    cut = bytes(member[: len(member) * 3 // 4])
    found = list(warc.salvage(cut + gzip.compress(record(9))))
    ids = [x["names"]["warc-record-id"] for x in found if "names" in x]
    assert ids[:2] == ["<urn:x:0>", "<urn:x:1>"] and ids[-1] == "<urn:x:9>"
    assert [(x["offset"], x["length"]) for x in found if "reason" in x] == [(0, len(cut))]


def test_long_archive_of_many_members_is_read_in_one_pass():
    data = b"".join(gzip.compress(record(i)) for i in range(20_000))
    assert sum("names" in x for x in warc.salvage(data)) == 20_000


def test_files_are_bounded_by_bytes(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(warc, "FILE_BYTES", 1 << 20)
    monkeypatch.setattr(warc, "CLASSES", (8 << 10, 128 << 10, 1 << 20))
    rows = [(i, f"http://a/{i}", chr(97 + i % 26) * (3_000_000 if i == 7 else 100_000 if i % 10 == 0 else 50 + i)) for i in range(200)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)
    warc.write_archive(warc.plan_records(df), str(tmp_path / "w"))
    sizes = [f.stat().st_size for f in (tmp_path / "w").rglob("part-*")]
    assert sorted(sizes)[-1] > 3_000_000 and sorted(sizes)[-2] <= 1 << 20
    got = warc.read_archive(spark, str(tmp_path / "w")).where("gap_reason IS NULL").count()
    assert got == 200


# -- preferences ---------------------------------------------------------------------------------------------------


def test_preference_pairs(spark):
    rows = [(0, 0, "system", "s"), (0, 1, "user", "hi"), (0, 2, "assistant", "good"), (1, 0, "system", "s"), (1, 1, "user", "hi"), (1, 2, "assistant", "bad!"), (1, 3, "user", None), (2, 0, "user", "alone"), (None, 0, "user", "x")]
    got = {r.pair_id: r for r in preferences.pair_neighbours(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    r = got[0]
    assert r.prefix_turns == 2 and r.prompt == "<|system|>\ns\n<|user|>\nhi\n"
    assert r.chosen == "<|assistant|>\ngood\n" and r.rejected == "<|assistant|>\nbad!\n<|user|>\n\n"
    a, b = map(int, r.rejected_mask.split("-"))
    assert r.rejected[a:b] == "bad!" and r.chosen_mask == "14-18"
    assert got[1].prefix_turns == 0 and got[1].rejected == "" and set(got) == {0, 1}


# -- decontamination -----------------------------------------------------------------------------------------------


def brute_hits(rows, items):
    import re

    cut = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
    items = [(str(i), cut(t)) for i, t in items]
    out = Counter()
    for i, t in rows:
        ws, hit, names = cut(t), set(), set()
        for name, own in items:
            n = min(10, len(own))
            wins = {tuple(own[j : j + n]) for j in range(len(own) - n + 1)} if own else set()
            for j in range(len(ws) - n + 1 if own else 0):
                if tuple(ws[j : j + n]) in wins:
                    hit |= set(range(j, j + n))
                    names.add(name)
        out[i, len(ws), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit)] += 1
    return out


def test_hits_match_brute_force(spark, odd, small, empty):
    bench = spark.createDataFrame([(1, "ALPHA beta gamma, delta epsilon zeta eta theta iota kappa lambda mu"), (2, "one"), (3, None), (4, "!!"), (10, "line two"), (11, "never seen words here"), (2, "the the the")], "item_id long, text string")
    rows = bench.collect()
    got = Counter(tuple(r)[:6] for r in decontaminate.hits(odd, bench).collect())
    assert got == brute_hits(texts(odd), [(r.item_id, r.text) for r in rows])
    kept = {r.doc_id for r in decontaminate.drop_contaminated(odd, bench).collect()}
    assert kept == {r[0] for r in got if not r[5]}
    given = spark.read.parquet(f"{SF}/benchmark.parquet")
    assert Counter(tuple(r)[:6] for r in decontaminate.hits(small, given).collect()) == brute_hits(texts(small), [(r.item_id, r.text) for r in given.collect()])
    assert decontaminate.hits(empty, bench).count() == 0
    assert not any(r.contaminated for r in decontaminate.hits(odd, bench.where("false")).collect())


def test_clashing_columns_are_carried(spark, odd):
    """Columns named like the operators' own, in any case, go through and stay."""
    names = ["_d", "_t", "_id", "_hash", "_HASH_", "_mix", "_mix_words", "_src", "_key", "epochs", "cut_key", "cut_words", "cut_group", "_row", "_text"]
    df = odd.drop("size", "target", "key").selectExpr("*", *[f"{i} AS `{c}`" for i, c in enumerate(names)])
    bench = spark.createDataFrame([(1, "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu")], "item_id long, text string")
    for out in (mixing.mix(df), decontaminate.drop_contaminated(df, bench), jaccard_join.keep_one(df)):
        rows = out.collect()
        assert rows and set(df.columns) <= set(out.columns)
        assert all(r[c] == i for r in rows for i, c in enumerate(names))
    plain = odd.drop("size", "target", "key")
    want = {(r.doc_id, r.taken) for r in mixing.mix(plain).collect()}
    assert {(r.doc_id, r.taken) for r in mixing.mix(df).collect()} == want


def test_links_through_rows_without_id(spark):
    words = [f"w{i}" for i in range(60)]
    a, b, c = (" ".join(words[i : i + 55]) for i in (0, 1, 2))
    rows = [(1, a), (None, b), (3, c), (None, "no partner here at all"), (5, a + " x"), (None, b)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = Counter(map(tuple, jaccard_join.component_ids(df, 3, 95).collect()))
    assert got == brute_components(rows, 3, 95)
    kept = jaccard_join.keep_one(df, 3, 95).collect()
    assert sorted((r.doc_id or -1, r.text) for r in kept) == sorted([(1, a), (-1, "no partner here at all")])


def test_keep_one_of_texts_with_one_id(spark):
    a = " ".join(f"v{i}" for i in range(40))
    rows = [(1, a), (1, a + " more"), (2, a), (7, ""), (7, ""), (8, None)]
    kept = jaccard_join.keep_one(spark.createDataFrame(rows, "doc_id long, text string"), 5, 80).collect()
    assert sorted((r.doc_id, (r.text or "")[:2]) for r in kept) == [(1, "v0"), (7, ""), (7, ""), (8, "")]


def test_proximity_counts_in_the_query(spark, odd):
    bench = spark.createDataFrame([(1, "omicron kappa"), (2, "quick absent"), (3, "fox bank")], "item_id long, text string")
    got = {r.doc_id: r.n_near for r in decontaminate.hits(odd, bench).collect()}
    assert {i for i, n in got.items() if n} == {1, 7, 8} and got[7] == 1


def test_proximity(spark, odd):
    bench = spark.createDataFrame([(1, "omicron kappa"), (2, "quick absent"), (3, "fox bank")], "item_id long, text string")
    # omicron stands five words after kappa; the text of document 1 is repeated, so fox stands five words after bank
    assert {tuple(r) for r in decontaminate.proximity_matches(odd, bench, 2, 5).collect()} == {(7, "1"), (8, "1"), (1, "3")}
    assert decontaminate.proximity_matches(odd, bench, 2, 4).count() == 0


# -- mixing --------------------------------------------------------------------------------------------------------


def test_mix_reaches_targets(odd, small, empty):
    for df in (odd, small):
        rows = mixing.mix(df).collect()
        assert len(rows) == df.count()
        sizes, took, target = Counter(), Counter(), {}
        for r in rows:
            assert r["size"] == len((r.text or "").encode().split()) and 0 <= r.taken <= 2 * r["size"]
            sizes[r.source] += r["size"]
            took[r.source] += r.taken
            target[r.source] = float(r.target)
        order = sorted(sizes, key=lambda s: (s is None, s or ""))
        weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
        budget, full = 1.5 * sum(sizes.values()), set()
        while True:  # the excess is shared again until no source is above its cap
            rest = [s for s in order if s not in full]
            level = (budget - sum(2 * sizes[s] for s in full)) / max(1, sum(weight[s] for s in rest))
            over = {s for s in rest if level * weight[s] > 2 * sizes[s]}
            if not over:
                break
            full |= over
        for s in order:
            assert target[s] == pytest.approx(2 * sizes[s] if s in full else level * weight[s], abs=1e-4)
            assert abs(took[s] - target[s]) <= 3
    assert mixing.mix(empty).count() == 0
    assert sorted(map(tuple, mixing.mix_report(small).collect())) == sorted(map(tuple, mixing.mix_report(small.repartition(5)).collect()))


# -- quality -------------------------------------------------------------------------------------------------------


def test_quality_held_out_accuracy(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    got = {r.doc_id: r for r in quality.score_documents(docs, labels).collect()}
    known = [(r.quality, got[r.doc_id]) for r in labels.collect() if got[r.doc_id].held_out]
    assert sum(q == r.predicted for q, r in known) / len(known) > 0.95
    assert all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in got.values())


def test_quality_odd_rows(spark, odd, empty):
    labels = spark.createDataFrame([(1, 1, 0), (6, 0, 0), (7, None, 0), (None, 1, 0), (9, 5, 1)], "doc_id long, quality int, toxic int")
    assert quality.score_documents(odd, labels).count() == odd.count()
    assert {r.score for r in quality.score_documents(odd, labels.where("false")).collect()} == {0.5}
    assert quality.keep_good(odd, labels).columns == odd.columns
    assert quality.score_documents(empty, labels).count() == 0


def test_quality_learns_from_every_labelled_row(spark, monkeypatch):
    """Blocks hold each labelled row of the training fold once (copies of the rare class apart) with both classes; there is no most."""
    from walkfold.llm import quality

    n = 7000
    docs = spark.range(n).selectExpr("id AS doc_id", "concat('word ', id, repeat(' 0', CAST(id % 7 AS INT))) AS text")
    labels = spark.range(n).selectExpr("id AS doc_id", "CAST(id % 50 = 0 AS INT) AS quality")
    seen = []
    made = quality._blocks
    monkeypatch.setattr(quality, "_blocks", lambda *a: seen.append(made(*a)) or seen[-1])
    quality.train(docs, labels, skip_held_out=False)
    own, both = 0, 0
    for r in seen[0].collect():
        y = np.frombuffer(r.y, np.int8)
        own, both = own + int(np.frombuffer(r.own, bool).sum()), both + (len(set(y.tolist())) == 2)
    assert own == n and both == seen[0].count() > 10
