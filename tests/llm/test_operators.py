"""Each operator against a plain version on small tables, and its defined edge cases."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash

from hybridrange.llm import attention_lm, common, exact_dedup, line_dedup, minhash, mixing, pieces, simhash, suffix_dedup, token_counts, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = "the of and to in is that for it on was with as be by this are at from tion er thea ondre bleha stou".split()


def prose(r, n):
    return " ".join(r.choice(WORDS) + r.choice(["", "", "", ".", ",", "\n"]) for _ in range(n))


def corpus(seed=3, n=60):
    """Copies, near copies, shared passages, white space, blanks, nulls and a periodic text."""
    r, texts = random.Random(seed), []
    for _ in range(n):
        texts.append(prose(r, r.randint(1, 160)))
    passage = prose(r, 120)
    for i in range(0, n, 6):
        texts.append(prose(r, 30) + " " + passage + " " + prose(r, 30))
        texts.append(texts[i].replace(" ", "  ", 3))
        words = texts[i + 1].split(" ")
        words[len(words) // 2] = "changed"
        texts.append(" ".join(words))
    texts += ["", None, "   ", " \n\t", "a", "ab " * 400, "漢字 é ▁   x" * 30, passage, passage]
    return [(i * 7 % 1009, t, "en", r.choice(["a", "b", "b", "b", None]), None if t is None else len(t)) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def rows():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def raw(t):
    return (t or "").encode()


def linked(ids, pairs):
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    return {i: find(i) for i in ids}


def test_components(spark):
    r = random.Random(1)
    pairs = [(r.randrange(300), r.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 440)] + [(5, 5)]
    got = {x.node: x.component for x in common.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    want = linked({x for p in pairs for x in p}, pairs)
    assert all(got.get(i, i) == c for i, c in want.items())
    assert common.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_exact_dedup(docs, rows, empty):
    norm = {i: re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for i, t, *_ in rows}
    groups = defaultdict(list)
    for i, t in norm.items():
        groups[t].append(i)
    got = {r.doc_id: r for r in exact_dedup.members(docs).collect()}
    for i, t in norm.items():
        r = got[i]
        assert (r.keep_id, r.group_size, r.kept, r.text_sha256) == (min(groups[t]), len(groups[t]), i == min(groups[t]), hashlib.sha256(t.encode()).hexdigest())
    kept = exact_dedup.dedup(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {min(g) for g in groups.values()}
    assert exact_dedup.members(empty).count() == 0


def test_exact_dedup_repeated_and_null_ids(spark):
    d = spark.createDataFrame([(1, "x y"), (1, "x  y"), (None, "x y"), (2, "z"), (2, "w")], "doc_id long, text string").selectExpr("*", "1 AS kept", "2 AS rid")
    assert sorted((r.doc_id, r.text) for r in exact_dedup.dedup(d).collect() if r.doc_id == 2) == [(2, "w"), (2, "z")]
    assert exact_dedup.dedup(d).where("doc_id = 1 or doc_id is null").count() == 1


def plain_print(t):
    w = raw(t).lower().split()
    h = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 3]), 42) for i in range(max(1, len(w) - 2))] if w else []
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def test_simhash(docs, rows, empty):
    prints = {i: plain_print(t) for i, t, *_ in rows}
    ids = list(prints)
    want = linked(ids, [(a, b) for a in ids for b in ids if a < b and (prints[a] ^ prints[b]).bit_count() <= 3])
    got = {r.doc_id: r for r in simhash.near_groups(docs).collect()}
    assert {i: r.component_id for i, r in got.items()} == want
    assert all(r.f0 % 2**64 == prints[i] for i, r in got.items())
    assert simhash.near_groups(empty).count() == 0


def test_simhash_tiles_find_every_link(spark):
    r = np.random.default_rng(2)
    f = r.integers(-(2**63), 2**63, 700)
    f = np.concatenate([f, f[:300] ^ (1 << r.integers(0, 63, 300)) ^ (1 << r.integers(0, 63, 300))])
    prints = spark.createDataFrame([(i, int(x)) for i, x in enumerate(f)], "rep long, f0 long")
    want = linked(range(1000), [(i, j) for i in range(1000) for j in (np.flatnonzero(np.bitwise_count(f[i + 1 :] ^ f[i]) <= 3) + i + 1).tolist()])
    for how in ({}, {"segments": 1, "bin_width": 3}, {"segments": 2, "bin_width": 2, "salts": 3}):
        got = {x.node: x.component for x in common.components(simhash.near_links(prints, 3, **how)).collect()}
        assert {i: got.get(i, i) for i in range(1000)} == want


def test_wide_simhash_catches_close_copies_and_leaves_others(spark):
    r = random.Random(8)
    texts = [" ".join("".join(r.choice("abcdefghij") for _ in range(6)) for _ in range(200)) for _ in range(20)]
    near = [t.split() for t in texts]
    for w in near:
        w[100], w[150] = "one", "two"
    d = spark.createDataFrame([(i, t) for i, t in enumerate(texts + [" ".join(w) for w in near])], "doc_id long, text string")
    assert {r.doc_id for r in simhash.dedup(d).collect()} == set(range(20))


def test_toxicity_locates_the_sentences(spark):
    r = random.Random(5)
    docs, labels = [], []
    for i in range(900):
        bad = i % 6 == 0
        parts = [prose(r, 12) for _ in range(5)]
        if bad:
            parts[2] += " you " + r.choice(["moronic", "moronish", "scum"]) + " thing"
        docs.append((i, ". ".join(parts)))
        labels.append((i, int(bad)))
    d, y = spark.createDataFrame(docs, "doc_id long, text string"), dict(labels)
    model = toxicity.train(d, spark.createDataFrame([*labels, (None, 1), (3, None)], "doc_id long, toxic int"))
    got = {r.doc_id: r.score for r in toxicity.scored(d, model).collect()}
    held = [i for i in y if zlib.crc32(str(i).encode()) % 5 == 0]
    assert np.mean([(got[i] >= 0.5) == y[i] for i in held]) > 0.97
    found = toxicity.offending(d, model).collect()
    assert found and all(re.search("moron|scum", r.sentence) for r in found) and all(docs[r.doc_id][1].encode()[r.start : r.end].decode() == r.sentence for r in found)
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "you scum thing " * 3000)], "doc_id long, text string")
    s = {r.doc_id: r.score for r in toxicity.scored(odd, model).collect()}
    assert 0 <= s[1] == s[2] < 0.5 <= s[3] <= 1
    assert toxicity.train(d, spark.createDataFrame([], "doc_id long, toxic int")).score(b"scum") < 0.5


def test_token_rollups(spark, tmp_path):
    roll = token_counts.Rollup(spark, f"{tmp_path}/roll")
    make = lambda *x: spark.createDataFrame(x, "kind string, source string, lang string, tokenizer_version string, tokens long, old_tokens long")
    first = make(("insert", "a", "en", "v1", 10, None), ("insert", "a", "en", "v1", 5, None), ("insert", None, None, "v1", 3, None))
    assert roll.totals().count() == 0 and roll.commit("1", first) and not roll.commit("1", first)
    roll.commit("2", make(("revise", "a", "en", "v1", 12, 10), ("delete", None, None, "v1", 3, None), ("insert", "b", "en", "v2", None, None)))
    want = {("a", "en", "v1", 2, 17), ("b", "en", "v2", 1, 0)}
    assert {tuple(r) for r in roll.totals().select("source", "lang", "tokenizer_version", "docs", "tokens").collect()} == want
    small = roll.compact(f"{tmp_path}/small")
    assert {tuple(r) for r in small.totals().select("source", "lang", "tokenizer_version", "docs", "tokens").collect()} == want and not small.commit("2", first)
    with pytest.raises(Exception, match="unknown kind"):
        roll.commit("3", make(("oops", "a", "en", "v1", 1, None)))


def test_bpe_counts(docs, rows):
    import base64

    import public_tokenizers as P
    import tiktoken

    file = P.path("byte_bpe_50k.tiktoken")
    with open(file, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    coder = tiktoken.Encoding("x", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = {r.doc_id: r.tokens for r in token_counts.bpe_counts(docs, file, "bpe").collect()}
    assert got == {i: len(coder.encode_ordinary(t or "")) for i, t, *_ in rows}


def test_lm_base_and_windows(docs, rows, empty):
    got = {r.doc_id: r for r in attention_lm.score_all(docs).collect()}
    words = {i: [*raw(t).lower().split(), b""] for i, t, *_ in rows}
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in words}
    c = Counter(w for i, ws in words.items() if not held[i] for w in ws)
    n, v = sum(c.values()), len(c)
    for i, ws in words.items():
        r = got[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[i], len(ws), sum(c[w] > 0 for w in ws), n)
        assert math.isclose(r.base_score, sum(math.log10((c[w] + 1) / (n + v + 1)) for w in ws), rel_tol=1e-9)
        assert r.score < 0 and math.isfinite(r.score)
    assert attention_lm.score_all(empty).count() == 0


def test_lm_scores_agree_with_a_plain_mixture(spark, docs, rows, monkeypatch):
    """Words in the table and words that are joined count alike, however few the table holds and however long they are."""
    long_ = "x" * 90
    more = docs.union(spark.createDataFrame([(5000 + i, f"{long_} of {long_}", "en", "a", 1) for i in range(4)], SCHEMA)).repartition(1)
    monkeypatch.setattr(attention_lm, "DISCOUNTS", (0.4,))
    laid_out = attention_lm.laid_out  # the table's words lay the classes out, which are held the same here
    monkeypatch.setattr(attention_lm, "laid_out", lambda seen, initial, company: laid_out(np.arange(len(seen))[::-1], initial))
    want = {r.doc_id: r.score for r in attention_lm.score_all(more).collect()}
    monkeypatch.setattr(attention_lm, "HOT", 3)
    got = {r.doc_id: r.score for r in attention_lm.score_all(more).collect()}
    assert want.keys() == got.keys() and all(math.isclose(want[i], got[i], rel_tol=1e-6) for i in want)
    known = attention_lm.score_all(more).where("doc_id >= 5000 and n_known < n_tokens").count()
    assert known == 0


def test_lm_shares_within_classes_add_up_to_one():
    import pyarrow as pa

    seen = np.random.default_rng(2).integers(0, 50, 5000)
    net = attention_lm.laid_out(seen, np.arange(5000) % 3 == 0)
    place = np.where(net.column < attention_lm.COLUMNS, net.column, attention_lm.COLUMNS + net.cls)[:5000]
    table, own = attention_lm.within(net, pa.table({"row": [0, 0, 3], "column": [int(place[4000]), 7, 9], "n": [5, 2, 8]}), seen)
    for row in (0, 3, 100):
        total = np.bincount(net.cls[:5000], 10.0 ** (table[row, place] + own), attention_lm.CLASSES)
        assert np.allclose(total[np.unique(net.cls[:5000])], 1, atol=1e-3)


def test_lm_groups_ids_by_their_company():
    r = np.random.default_rng(4)
    side = r.integers(0, 2, 300)
    company = np.abs(r.normal(0, 0.1, (300, 8))) + np.where(side[:, None] == (np.arange(8) < 4), 1.0, 0.0)
    to = attention_lm.alike(company * r.integers(1, 90, 300)[:, None], 2)
    assert len(set(zip(to.tolist(), side.tolist(), strict=True))) == 2
    assert len(attention_lm.alike(np.zeros((5, 8)), 2)) == 5


def test_lm_beats_the_unigram_where_texts_differ_in_kind(spark):
    """Two vocabularies that never mix: what stands in the window tells which words may follow."""
    r = np.random.default_rng(8)
    kinds = [[f"{a}{b}{c}" for a in x for b in "aeiou" for c in "lnrst"] for x in ("bdfg", "kmpv")]
    texts = [" ".join(r.choice(kinds[i % 2], 80)) for i in range(400)]
    got = attention_lm.score_all(spark.createDataFrame([(i, t, "en", "a", 1) for i, t in enumerate(texts)], SCHEMA).coalesce(1)).where("held_out").collect()
    assert sum(x.score for x in got) > sum(x.base_score for x in got)


def test_lm_gradient_and_distribution():
    r = np.random.default_rng(1)
    texts = [np.array([1, *r.integers(3, 40, n), 2], np.int32) for n in (5, 30, 61)]
    net = attention_lm.laid_out(np.bincount(np.concatenate(texts), minlength=50), np.arange(50) % 2 == 0)
    net.params["next"] = attention_lm.log_after(attention_lm.after_rows(net, texts))
    net = attention_lm.trained(net, texts)
    net.params = {k: v.astype(np.float64) for k, v in net.params.items()}
    ids, then, of = net.windows(texts)
    assert (then >= 0).sum() == sum(len(x) - 1 for x in texts)  # every id is scored once
    g, live = net.gradient(ids, then), then >= 0
    for name in net.params:
        at = np.unravel_index(np.abs(g[name]).argmax(), g[name].shape)
        before, loss = net.params[name][at], []
        for e in (1e-5, -1e-5):
            net.params[name][at] = before + e
            loss.append(-net.log_class(ids, then)[live].mean())
        net.params[name][at] = before
        assert math.isclose((loss[0] - loss[1]) / 2e-5, g[name][at], rel_tol=0.02, abs_tol=1e-4)
    total = sum(np.exp(net.log_class(ids[:1], np.full_like(then[:1], i))) for i in [int(np.flatnonzero(net.cls[:50] == k)[0]) for k in set(net.cls[:50].tolist())])
    assert (total <= 1 + 1e-6).all()


def test_pieces_round_trip_and_parallel_scan(docs, rows, empty):
    p = pieces.loaded(pieces.MODEL)
    want = {i: p.encode(t or "") for i, t, *_ in rows}
    for chunk in (7, 40, pieces.CHUNK):
        got = {r.doc_id: r for r in pieces.encode(docs, chunk=chunk).collect()}
        assert all(r.exact for r in got.values()) and {i: list(r.ids) for i, r in got.items()} == want
    assert pieces.encode(empty).count() == 0


def test_pieces_are_of_greatest_score():
    p, r = pieces.loaded(pieces.MODEL), random.Random(3)
    for _ in range(150):
        t = "".join(r.choice(["the", "  ", " ", "a", "aaaa", "é", "漢", "▁", "\n", "tion", "----------------", "=", "represent", "\x00"]) for _ in range(r.randint(0, 30)))
        w = pieces.marked(t)
        best, last = [0] + [-(10**18)] * len(w), [0] * (len(w) + 1)
        for e in range(1, len(w) + 1):
            for size in range(min(p.reach, e), 0, -1):
                x = w[e - size : e]
                s = p.score.get(x, p.fall * len(p.raw(x)) if size == 1 else None)
                if s is not None and best[e - size] + s > best[e]:
                    best[e], last[e] = best[e - size] + s, size
        assert p.encode(t) == p.backtrace(w, last, len(w)) and p.decode(p.encode(t)) == t


def test_suffix_array():
    r = random.Random(1)
    for _ in range(300):
        t = bytes(r.choice(b"ab\x00\xff") for _ in range(r.randint(0, 50)))
        order = suffix_dedup.suffix_array(t, 100)
        assert order.tolist() == sorted(range(len(t)), key=lambda i: t[i:])
        common_ = suffix_dedup.common_prefixes(t, order)
        for k in range(1, len(t)):
            a, b = t[order[k - 1] :], t[order[k] :]
            assert common_[k] == next((i for i in range(min(len(a), len(b))) if a[i] != b[i]), min(len(a), len(b)))


@pytest.mark.parametrize("group", [2, 150_000])
def test_suffix_dedup(docs, rows, empty, group, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "GROUP", group)
    size, seen = suffix_dedup.LENGTH, Counter()
    for _, t, *_ in rows:
        seen.update(raw(t)[j : j + size] for j in range(len(raw(t)) - size + 1))
    got = {r.doc_id: r for r in suffix_dedup.remove_repeats(docs).collect()}
    some = 0
    for i, t, *_ in rows:
        x = raw(t)
        gone = np.zeros(len(x) + 1, bool)
        for j in range(len(x) - size + 1):
            if seen[x[j : j + size]] > 1:
                gone[j : j + size] = True
        left = bytes(b for b, g in zip(x, gone, strict=False) if not g)
        assert (got[i].n_bytes, got[i].n_removed, bytes(got[i].kept)) == (len(x), int(gone.sum()), left)
        assert got[i].n_spans == int((gone[:-1] & ~np.concatenate([[False], gone[:-2]])).sum()) if len(x) else got[i].n_spans == 0
        some += int(gone.sum())
    assert some and suffix_dedup.remove_repeats(empty).count() == 0


def test_counting_agrees_with_sorting():
    r = random.Random(2)
    base = bytes(r.randrange(97, 100) for _ in range(200))
    parts = [(base[i : i + 60] + bytes([r.randrange(97, 100)]) + base[50:90], 40, i * 1000, i % 5 == 0) for i in range(0, 100, 7)]
    a, b = suffix_dedup.repeats(parts, 30), suffix_dedup.counted(parts, 30)
    assert all((x == y).all() for x, y in zip(a, b, strict=True)) and any(x.any() for x in a)


def test_targets():
    t = mixing.targets({"b": 100, "a": 100, None: 10, "c": 1000})
    assert math.isclose(sum(t.values()), 1210) and t[None] == 30 and all(t[k] <= 3 * v + 1e-9 for k, v in {"a": 100, "b": 100, "c": 1000}.items())
    assert mixing.targets({}) == {} and mixing.targets({"a": 0}) == {"a": 0.0}


def test_flight_keeps_both_totals():
    r = np.random.default_rng(4)
    p, size = np.full(500, 0.37), r.integers(0, 900, 500)
    q = mixing.flight(p, size, r)
    open_ = (q > 0) & (q < 1)
    assert open_.sum() <= 2 and math.isclose((q * size).sum(), (p * size).sum(), rel_tol=1e-6) and math.isclose(q.sum(), p.sum(), rel_tol=1e-6)
    q = mixing.flight(p, size, r, mixing.LAND)
    done = mixing.land(q, size)
    assert set(done) <= {0.0, 1.0} and abs((done * size).sum() - (p * size).sum()) <= 0.001 * (p * size).sum()


def test_one_large_document_is_made_up_for():
    size = np.array([20_000, *range(100, 900, 10)])
    start = np.full(len(size), 0.4)
    done = mixing.made_up(mixing.land(mixing.flight(start, size, np.random.default_rng(1), mixing.LAND), size), float(start @ size), size, np.arange(len(size)), 20.0)
    assert set(done) <= {0.0, 1.0} and abs(done @ size - start @ size) <= 20


def test_every_source_comes_near_its_target(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = mixing.mix(docs).join(docs.select("doc_id", "source"), "doc_id").groupBy("source", "target").sum("taken").collect()
    assert len(rows) > 5 and all(abs(r[2] - r.target) <= 0.02 * r.target for r in rows)


@pytest.mark.parametrize("block", [5, 2000])
def test_mixing(docs, rows, empty, block):
    got = mixing.mix(docs, block=block).collect()
    size = {i: len(raw(t).split()) for i, t, *_ in rows}
    by = defaultdict(int)
    for i, _, _, s, _ in rows:
        by[s] += size[i]
    goal, source = mixing.targets(dict(by)), {i: s for i, _, _, s, _ in rows}
    taken = defaultdict(int)
    for r in got:
        s = source[r.doc_id]
        assert r["size"] == size[r.doc_id] and r.source_size == by[s] and math.isclose(r.target, goal[s]) and r.taken == r.copies * r["size"] <= 3 * r["size"]
        taken[s] += r.taken
    assert len(got) == len(rows) and all(abs(taken[s] - goal[s]) <= max(size.values()) for s in by)
    assert {(r.doc_id, r.taken) for r in mixing.mix(docs, block=block).collect()} == {(r.doc_id, r.taken) for r in got}
    assert mixing.mix(empty).count() == 0
    again = mixing.mixed_rows(docs, block=block)
    assert again.columns == docs.columns and again.count() == sum(r.copies for r in got)


def test_line_dedup(spark, empty):
    r = random.Random(6)
    pool = [f"line {i}" for i in range(12)]
    rows = [(i * 3, "\n".join(r.choice([*pool, "", f"own {i} {j}"]) for j in range(r.randint(0, 14)))) for i in range(40)] + [(200, None), (201, "a\nb\nc\na\nb\nc"), (202, "a\n\n b \nc")]
    lines = {i: (t or "").split("\n") for i, t in rows}
    at = {i: [j for j, x in enumerate(ls) if x.strip(" \t\r\x0b\x0c")] for i, ls in lines.items()}
    seen, gone = set(), defaultdict(set)
    for i in sorted(lines):
        for k in range(len(at[i]) - 2):
            key = tuple(lines[i][j].strip(" \t\r\x0b\x0c") for j in at[i][k : k + 3])
            if key in seen:
                gone[i] |= set(at[i][k : k + 3])
            seen.add(key)
    d = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    for x in line_dedup.dedup_lines(d).collect():
        assert bytes(x.kept).decode() == "\n".join(y for j, y in enumerate(lines[x.doc_id]) if j not in gone[x.doc_id]) and x.n_removed == len(gone[x.doc_id])
    assert gone[201] == {3, 4, 5} or gone[201] and line_dedup.dedup_lines(empty).count() == 0


def test_minhash(docs, rows, empty, spark):
    got, seen = {r.doc_id: r for r in minhash.against_next(docs).collect()}, minhash.WordHashes()
    ordered = sorted((i, t or "") for i, t, *_ in rows)
    sets = lambda x: set(minhash.shingles(x.encode(), seen).tolist())
    off = []
    for (i, a), (_, b) in zip(ordered, ordered[1:] + ordered[:1], strict=True):
        part = len(a) // 4
        edited = a[: len(a) - part] + b[:part]
        r = got[i]
        assert r.n_chars == len(a) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        for other, likeness in ((edited, r.near_edited), (b, r.near_next)):
            x, y = sets(a), sets(other)
            off.append(abs(likeness - (len(x & y) / len(x | y) if x | y else 1.0)))
    assert np.mean(off) < 0.05 and minhash.against_next(empty).count() == 0
    one = minhash.against_next(spark.createDataFrame([(4, "x y z w v u t s")], "doc_id long, text string")).collect()
    assert len(one) == 1 and one[0].near_next == 1.0


def test_minhash_pairs(docs, rows):
    seen = minhash.WordHashes()
    classes = {}
    for i, t, *_ in sorted(rows, key=lambda r: r[0]):
        w = b" ".join(raw(t).lower().split())
        if w:
            classes.setdefault(w, i)
    s = {i: set(minhash.shingles(w, seen).tolist()) for w, i in classes.items()}
    want = {(a, b) for a in s for b in s if a < b and len(s[a] & s[b]) / len(s[a] | s[b]) >= 0.8}
    got = {(r.a, r.b) for r in minhash.near_pairs(docs).collect()}
    assert got <= want and len(got) >= 0.9 * len(want)


def test_extra_columns_with_clashing_names(spark):
    d = spark.createDataFrame([(1, "a b c d e f", 1, 2, 3, "s"), (2, "a b c d e g", 1, 2, 3, "s")], "doc_id long, text string, rid long, key long, size long, source string").selectExpr("*", "1 AS copies", "'v' AS lang", "0.5D AS score", "4 AS bucket", "1 AS f0")
    for f in (exact_dedup.members, simhash.near_groups, mixing.mix, line_dedup.dedup_lines, suffix_dedup.remove_repeats, minhash.against_next, pieces.encode):
        assert f(d).count() == 2
    assert exact_dedup.dedup(d).columns == mixing.mixed_rows(d).columns == simhash.dedup(d).columns == d.columns


def test_internal_names_are_free(spark):
    own = "'r' AS _rid", "'c' AS _copies", "'t' AS _turn", "'s' AS _score", "'g' AS _gone"
    d = spark.createDataFrame([(1, "a b c d e f", "s"), (2, "a b c d e g", "s"), (3, "a b c  d e g", "s")], "doc_id long, text string, source string").selectExpr("*", *own)
    labels = spark.createDataFrame([(1, 0)], "doc_id long, toxic int")
    for out in (exact_dedup.dedup(d), mixing.mixed_rows(d), toxicity.clean(d, labels), simhash.dedup(d)):
        got = out.collect()
        assert out.columns == d.columns and got and all(tuple(r)[3:] == ("r", "c", "t", "s", "g") for r in got)


def test_a_hot_key_is_joined_by_broadcast(spark):
    rows = spark.range(30_000).selectExpr("CASE WHEN id % 3 = 0 THEN -1 ELSE id END AS key", "id")
    keyed = rows.groupBy("key").count()
    got = common.join_on_key(rows, keyed.withColumn("twice", keyed["key"] * 2), ["key"], "count", 30_000)
    assert got.count() == 30_000 and got.where("twice <> 2 * key").count() == 0
    assert exact_dedup.members(spark.range(30_000).selectExpr("id AS doc_id", "CASE WHEN id % 3 = 0 THEN 'hot' ELSE cast(id AS string) END AS text")).where("text_sha256 = sha2('hot', 256) and keep_id = 0 and group_size = 10000").count() == 10_000


def test_a_word_counts_once_in_a_sentence_however_punctuated():
    m = toxicity.Model({b"=scum": 3.0}, -6.0, 0.01)
    assert m.score(b"scum scum, (scum)") == m.score(b"scum") < 0.5 and m.sentence([b"scum", b"scum,"]) == m.sentence([b"scum"])


def test_toxicity_of_an_empty_table(spark, empty):
    m = toxicity.train(empty, spark.createDataFrame([], "doc_id long, toxic int"))
    assert toxicity.scored(empty, m).count() == 0 and toxicity.clean(empty, spark.createDataFrame([], "doc_id long, toxic int")).count() == 0


def test_signatures_of_long_texts_stay_apart():
    r = np.random.default_rng(3)
    a, b = (r.integers(0, 2**63, 1_000_000).astype(np.uint64) for _ in range(2))
    assert minhash.likeness(minhash.signature(a), minhash.signature(b)) <= 0.02
    assert minhash.likeness(minhash.signature(a), minhash.signature(np.concatenate([a[:900_000], b[:100_000]]))) > 0.7
