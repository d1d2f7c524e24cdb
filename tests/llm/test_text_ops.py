"""The text operators against brute force, on rows with every odd case."""

import collections
import hashlib
import json
import random
import re
import time
import tracemalloc

import numpy as np
import pandas as pd
import pyarrow as pa
import public_tokenizers
import pytest
import tiktoken

from annspark.llm import bpe, bytespans, jaccard, language, mixing, ordersketch, pii, queries, repeats, toxicity, wordspans

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def by_row(df):
    """Rows of a result as a multiset."""
    return collections.Counter(map(tuple, df.collect()))


def sha(b):
    return hashlib.sha256(b).hexdigest()


# --- 2, 9: repeated windows


def cover(seqs, w):
    """Flags of units under windows that start twice, over a list of sequences."""
    n = collections.Counter(tuple(s[k : k + w]) for s in seqs for k in range(len(s) - w + 1))
    out = []
    for s in seqs:
        flags = [False] * len(s)
        for k in range(len(s) - w + 1):
            if n[tuple(s[k : k + w])] > 1:
                flags[k : k + w] = [True] * w
        out.append(flags)
    return out


# the last keeps one bit of a window's hash, so that every class of hashes fails its check
@pytest.mark.parametrize("hot,keep", [(0, 64), (3, 64), (repeats.HOT, 64), (0, 1)])
@pytest.mark.parametrize("window,gram", [(35, 10), (6, 3)])
def test_word_windows(spark, docs, rows, window, gram, hot, keep):
    got = by_row(repeats.search(docs, wordspans.Words(window, gram), hot, keep))
    seqs = [(r[1] or "").encode().split() for r in rows]
    want = collections.Counter()
    for r, s, f in zip(rows, seqs, cover(seqs, window)):
        want[(r[0], len(s), sum(f), sha(b" ".join(x for x, y in zip(s, f) if not y)))] += 1
    assert got == want


@pytest.mark.parametrize("hot,keep", [(0, 64), (repeats.HOT, 64), (0, 1)])
@pytest.mark.parametrize("length,gram", [(400, 160), (50, 20)])
def test_byte_strings(spark, docs, rows, length, gram, hot, keep):
    got = by_row(repeats.search(docs, bytespans.Bytes(length, gram), hot, keep))
    raw = [(r[1] or "").encode() for r in rows]
    n = collections.Counter(hash(s[k : k + length]) for s in raw for k in range(len(s) - length + 1))
    want = collections.Counter()
    for r, s in zip(rows, raw):
        flags = bytearray(len(s))
        for k in range(len(s) - length + 1):
            if n[hash(s[k : k + length])] > 1:
                flags[k : k + length] = b"\1" * length
        want[(r[0], len(s), sum(flags), len(re.findall(b"\1+", bytes(flags))), sha(bytes(x for x, y in zip(s, flags) if not y)))] += 1
    assert got == want


def test_passages_are_judged_by_their_bytes(spark, tmp_path):
    """A passage of over 50 words that texts share stays one byte short of 400 and goes from 400 on; other white space makes other bytes. n_removed tells it, n_bytes is of the input."""
    rng = random.Random(6)
    short, long = (" ".join("".join(rng.choices("abcdefgh", k=6)) for _ in range(70))[:n] for n in (399, 400))
    assert min(len(short.split()), len(long.split())) > 50
    texts = [f"p{short}q", f"r{short}s", f"p{long}q", f"r{long}s", f"t{long.replace(' ', chr(10))}u"]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = queries.QUERIES["op2_suffix_dedup"](spark, str(tmp_path)).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    kept = [texts[0], texts[1], "pq", "rs", texts[4]]
    assert by_row(got) == collections.Counter((i, len(t), len(t) - len(k), int(t != k), sha(k.encode())) for i, (t, k) in enumerate(zip(texts, kept)))


def test_suffix_sort_is_a_suffix_sort():
    rng = np.random.default_rng(3)
    data = rng.integers(97, 99, 600).astype(np.uint8)
    place = np.sort(rng.choice(600, 200, replace=False))
    group, end = place // 150, (place // 150 + 1) * 150
    order = bytespans.Suffixes(data).sort(place, end, group)
    want = sorted(range(200), key=lambda i: (group[i], bytes(data[place[i] : end[i]])))
    assert [bytes(data[place[i] : end[i]]) for i in order] == [bytes(data[place[i] : end[i]]) for i in want]


def test_suffixes_of_one_line_repeated():
    """A bucket of texts that repeat one line with a change here and there: 116,363 suffixes are sorted at once (0.2 s; merged on hashes: 19 s), ends and zero bytes in order."""
    rng = random.Random(3)
    line = bytes(rng.randrange(97, 123) for _ in range(60)) + b"\n"
    texts = []
    for _ in range(50):
        x = bytearray(line * 45)
        for _ in range(2):
            x[rng.randrange(len(x))] = rng.randrange(97, 123)
        texts.append(bytes(x[: rng.randrange(2000, len(x))]))
    got = {(k, x) for k, lo, hi in bytespans.Bytes(400, 160).decide(np.zeros(len(texts), np.int64), texts) for x in range(lo, hi)}
    times = collections.Counter(t[i : i + 400] for t in texts for i in range(len(t) - 399))
    ends = {(k, i + j) for k, t in enumerate(texts) for i in range(len(t) - 399) if times[t[i : i + 400]] > 1 for j in (0, 399)}
    assert ends <= got and {(k, i) for k, i in got if (k, i - 1) not in got} <= ends
    data, size = np.frombuffer(b"".join(texts), np.uint8), np.array([len(t) for t in texts])
    place, end = np.arange(len(data)), np.repeat(np.cumsum(size), size)
    began = time.process_time()
    order = bytespans.Suffixes(data).sort(place, end, np.zeros(len(data), np.int64))
    assert time.process_time() - began < 8
    told = [bytes(data[place[i] : end[i]]) for i in order]
    assert all(a <= b for a, b in zip(told, told[1:], strict=False))
    # suffixes that end in the first bytes compared, equal ones, and zero bytes, by rank as by bytes
    for seed in range(200):
        rng = np.random.default_rng(seed)
        data = rng.choice(np.array([0, 97], np.uint8), 60)
        place = np.arange(60)
        group, end = place // 20, (place // 20 + 1) * 20
        order = bytespans.Suffixes(data).sort(place, end, group)
        told = [(group[i], bytes(data[place[i] : end[i]])) for i in order]
        assert told == sorted(told)


def test_hash_collision_falls_back_to_bytes(monkeypatch):
    """With every hash equal, extensions are verified and buckets searched on real bytes."""
    rng = random.Random(1)
    text = bytes(rng.randrange(256) for _ in range(300))
    strings = [text[:120], text[40:160], bytes(rng.randrange(256) for _ in range(100))]
    monkeypatch.setattr(bytespans.Suffixes, "hashes", lambda self, p, n: np.zeros(len(p), np.uint64))
    found = {k for k, _, _ in bytespans.Bytes._search(strings, np.zeros(3, np.int64), 50)}
    assert found == {0, 1}


def test_empty_tables(spark, none):
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    for df in (wordspans.remove_repeats(none), bytespans.remove_repeats(none), jaccard.join(none), ordersketch.neighbours(none), mixing.mix(none), pii.find(none), bpe.encode(none, RANKS, public_tokenizers.PATTERN), toxicity.grade(none, toxicity.train(none, labels)), language.predict(none, language.train(none))):
        assert df.count() == 0
    for df in (toxicity.keep_clean(none, labels), jaccard.one_of_each(none), pii.redact(none), mixing.take(none)):
        assert df.count() == 0 and df.columns == none.columns


# --- 7: similarity join


def shingles(text, n=5):
    w = (text or "").encode().split()
    return frozenset(tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))) if w else frozenset()


@pytest.mark.parametrize("crowd", [jaccard.CROWD, 4])
def test_similarity_join(spark, docs, rows, crowd):
    sets = [shingles(r[1]) for r in rows]
    n, up = [0] * len(rows), list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            same = (rows[i][1] or "") == (rows[j][1] or "")
            alike = bool(sets[i]) and bool(sets[j]) and len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8
            n[i] += alike
            n[j] += alike
            if same or alike:
                up[max(root(i), root(j))] = min(root(i), root(j))
    least = collections.defaultdict(list)
    for i, r in enumerate(rows):
        least[root(i)].append(r[0])
    want = collections.Counter((r[0], min((x for x in least[root(i)] if x is not None), default=None), n[i]) for i, r in enumerate(rows))
    assert by_row(jaccard.join(docs, crowd=crowd)) == want


def test_links_are_the_pairs(spark, docs, rows):
    sets = {shingles(r[1]): (r[1] or "") for r in rows}
    texts = {r[1] or "" for r in rows}
    want = sum(1 for a in texts for b in texts if a < b and shingles(a) and shingles(b) and len(shingles(a) & shingles(b)) / len(shingles(a) | shingles(b)) >= 0.8)
    assert jaccard.links(docs).count() == want and sets


def test_bands_meet_the_recall():
    for threshold in (0.5, 0.7, 0.8, 0.9):
        bands, n = jaccard.bands_for(threshold)
        assert bands * n <= jaccard.HASHES
        assert 1 - (1 - threshold**n) ** bands >= jaccard.RECALL or n == 1


def test_one_of_each(spark, docs, rows):
    kept = jaccard.one_of_each(docs)
    assert kept.columns == docs.columns
    classes = {r.class_id for r in jaccard.join(docs).collect()}
    ids = [r.doc_id for r in kept.collect()]
    assert len(ids) == len(set(ids)) and set(ids) == classes


def test_a_dense_group_writes_no_pairs(spark):
    rng = random.Random(2)
    base = [f"w{i}" for i in range(300)]
    texts = []
    for i in range(150):
        w = list(base)
        w[rng.randrange(300)] = f"x{i}"
        texts.append((i, " ".join(w)))
    df = spark.createDataFrame(texts, "doc_id long, text string")
    out = jaccard.join(df).collect()
    assert {r.class_id for r in out} == {0} and all(r.n_links == 149 for r in out)
    assert jaccard.links(df, pairs=False).count() <= 150 * 25


def near_copies(n):
    rng = random.Random(2)
    base = [f"w{i}" for i in range(300)]
    for i in range(n):
        w = list(base)
        w[rng.randrange(300)] = f"x{i}"
        yield " ".join(w).encode()


def test_what_kernels_send_grows_with_the_members():
    """Bytes that either kernel is sent, and writes, on n near copies are in proportion to n; no column is a list."""
    bands, n_rows = jaccard.bands_for(0.8)
    meeting, signer = jaccard.Meeting(bands, n_rows, 0.8), jaccard.Signer(bands, n_rows)

    def sent(n):
        texts = list(near_copies(n))
        buckets = collections.Counter(h for t in texts for h in signer.band_hashes(signer.sign(jaccard.ngrams(t))).tolist())
        keys = pa.array(range(n), pa.int64())
        lists = [[{"h": h, "band": k, "n": buckets[h]} for k, h in enumerate(signer.band_hashes(signer.sign(jaccard.ngrams(t))).tolist()) if buckets[h] > 1] for t in texts]
        members = pa.Table.from_batches(jaccard._to_buckets(bands, n_rows, jaccard.CROWD)(iter([pa.RecordBatch.from_arrays([keys, keys, pa.array(texts), pa.array(lists)], names=["t1", "t2", "text", "buckets"])])))
        found = pa.Table.from_batches(jaccard._candidates(meeting)(iter(members.sort_by([("h", "ascending"), ("t1", "ascending")]).to_batches())))
        asks = collections.defaultdict(list)
        for r in found.to_pylist():
            asks[r["t1"]].append({c: r[c] for c in ("h", "side", "band")})
        own = pa.array(sorted(asks), pa.int64())
        batch = pa.RecordBatch.from_arrays([own, own, pa.array([texts[k] for k in sorted(asks)]), pa.array([1] * len(own), pa.int64()), pa.array([asks[k] for k in sorted(asks)])], names=["t1", "t2", "text", "copies", "asks"])
        sets = pa.Table.from_batches(jaccard._with_sets(bands, n_rows)(iter([batch])))
        out = pa.Table.from_batches(jaccard._verify(meeting, 0.8, False)(iter(sets.sort_by([("h", "ascending"), ("t1", "ascending")]).to_batches())))
        away = collections.Counter()
        for r in out.to_pylist():
            away[r["t1"]] += r["away"]
        assert set(away.values()) == {n - 1} and len(away) == n  # every link is counted once
        assert not any(pa.types.is_list(f.type) for t in (members, found, sets, out) for f in t.schema)
        return [t.nbytes for t in (members, found, sets, out)]

    for a, b in zip(sent(150), sent(600), strict=True):
        assert b < 4 * a * 1.25


def test_sets_are_met_exactly_both_ways():
    rng = np.random.default_rng(3)
    raw = [np.unique(rng.integers(0, 200, rng.integers(1, 90), dtype=np.uint64)).tobytes() for _ in range(40)]
    by = [set(np.frombuffer(x, np.uint64).tolist()) for x in raw]
    for room in (0, 1 << 20):
        sets = jaccard.Sets(raw, room)
        for i in range(39):
            others = np.arange(i + 1, 40)
            assert sets.shared(i, others).tolist() == [len(by[i] & by[j]) for j in others]


# --- 4: byte-level BPE


def test_bpe_is_the_library(spark, docs, rows):
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(RANKS), special_tokens={})
    want = collections.Counter()
    for r in rows:
        ids = enc.encode_ordinary(r[1] or "")
        want[(r[0], len(ids), sha(",".join(map(str, ids)).encode()), sha((r[1] or "").encode()))] += 1
    assert by_row(bpe.encode(docs, RANKS, public_tokenizers.PATTERN, ids=False)) == want


def test_bpe_random_strings():
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(RANKS), special_tokens={})
    codec, rng = bpe.Codec(bpe.read_ranks(RANKS), public_tokenizers.PATTERN), random.Random(4)
    parts = ["a", "b", " ", "\n", "é", "ß", "1", "'s", "日本", "😀", "the", "ing", "  ", "½", "<|endoftext|>"]
    for _ in range(300):
        s = "".join(rng.choice(parts) for _ in range(rng.randint(0, 200)))
        ids = next(codec.encode_block([s]))
        assert ids == enc.encode_ordinary(s) and codec.decode(ids) == s.encode()
    long = "ab" * 30_000
    assert next(codec.encode_block([long])) == enc.encode_ordinary(long)


def test_a_lower_rank_made_by_a_merge_goes_first():
    """ab (rank 12) makes abc (rank 11) possible, which must be taken before the next ab."""
    ranks = {bytes([i]): i for i in range(256)} | {b"ab": 258, b"abc": 257, b"bab": 256}
    codec = bpe.Codec(ranks, r".+")
    enc = tiktoken.Encoding("own", pat_str=r".+", mergeable_ranks=ranks, special_tokens={})
    for s in ("abcab", "ababcab", "abab", "babab", "cabab", "abcabcbab"):
        assert next(codec.encode_block([s])) == enc.encode_ordinary(s)


# --- 5: identifiers

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")


def test_base_spans_follow_the_patterns():
    rng = random.Random(6)
    for _ in range(3000):
        s = "".join(rng.choice("ab@.-_ 1+()") for _ in range(40))
        assert pii.emails(s) == [m.span() for m in EMAIL.finditer(s)]
        assert pii.phones(s) == [m.span() for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", s) if 8 <= len(re.findall("[0-9]", m.group())) <= 15]
    assert pii.cards("pay 4111 1111-1111 1111 now") == [(4, 23)] and pii.cards("4111 1111 1111 1112") == []
    assert pii.ips("at 10.0.0.255, 10.0.0.256 and 1.2.3.4.5") == [(3, 13), (30, 37)]


PLAIN = {
    "email": (EMAIL.pattern, lambda m: True),
    "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(p) <= 255 for p in m.split("."))),
    "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 16 <= len(d := re.sub("[^0-9]", "", m)) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(d[::-1])) % 10 == 0),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 8 <= len(re.sub("[^0-9]", "", m)) <= 15),
}


def plain_spans(s):
    return {k: [m.span() for m in re.finditer(p, s) if ok(m.group())] for k, (p, ok) in PLAIN.items()}


def test_base_spans_of_all_kinds_by_brute_force(spark):
    rng = random.Random(8)
    bits = ["a", "b@c.de", "@", ".", "-", " ", "+", "(", ")", "00", "10.0.0.1", "255", "256", "4111111111111111", "4111 1111 1111 1111", "+1 415 555 0199", "00000001", "1", "é", "five", " dot ", " at ", "（"]
    made = ["".join(rng.choice(bits) for _ in range(rng.randint(1, 25))) for _ in range(4000)]
    some = collections.Counter()
    for s in made:
        want = plain_spans(s)
        base, both = pii.scan(s)
        assert base == want and all(set(want[k]) <= set(both[k]) for k in pii.KINDS)
        some.update({k: len(v) for k, v in want.items()})
    assert all(some[k] > 20 for k in pii.KINDS)
    for r in pii.find(spark.createDataFrame(list(enumerate(made[:500])), "doc_id long, text string")).collect():
        want = plain_spans(made[r.doc_id])
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(len(want[k]) for k in pii.KINDS)
        assert r.base_sha256 == sha(",".join(f"{k}:{a}:{b}" for k in pii.KINDS for a, b in sorted(want[k])).encode())


N = 1_000_000
LONG = {
    "zeros": "0" * N + "1.1.1.1",
    "spaces and a bracket": " " * N + "(",
    "spaces and a digit word": "five" + " " * N + "(",
    "underscores": "_" * N + " at b dot dot",
    "a long gap in an address": "x" + " " * (N // 2) + "dot" + " " * (N // 2) + "y at h dot com",
    "a long gap at the sign": "x" + " " * N + "at" + " " * N + "h dot z dot com",
    "at signs": "a@" * (N // 2),
    "plus signs": "+1" + "(" * N,
}


def test_very_long_runs_take_linear_time(spark):
    """Quadratic scans of these would take hours."""
    df = spark.createDataFrame(list(enumerate(LONG.values())), "doc_id long, text string")
    start = time.monotonic()
    got = {name: r for name, r in zip(LONG, sorted(pii.find(df).collect()), strict=True)}
    new = {name: r.text for name, r in zip(LONG, sorted(pii.redact(df).collect()), strict=True)}
    assert time.monotonic() - start < 90
    assert got["zeros"].n_ip == 1 and got["zeros"].spans == f"ip:0:{N + 7}" and new["zeros"] == "[IP]"
    assert new["underscores"] == new["a long gap in an address"] == "[EMAIL]" and new["spaces and a bracket"] == LONG["spaces and a bracket"]


@pytest.mark.parametrize(
    "text,kind,part",
    [
        ("write to john.doe (at) example (dot) com now", "email", "john.doe (at) example (dot) com"),
        ("or jane@mail dot example dot org too", "email", "jane@mail dot example dot org"),
        ("reach jane at example dot com today", "email", "jane at example dot com"),
        ("jоhn@exаmple.com", "email", "jоhn@exаmple.com"),
        ("ｊｏｈｎ＠ｅｘａｍｐｌｅ．ｃｏｍ", "email", "ｊｏｈｎ＠ｅｘａｍｐｌｅ．ｃｏｍ"),
        ("😀 plus one four one five five five five zero one two three ok", "phone", "plus one four one five five five five zero one two three"),
        ("card four one one one 1111 1111 one one one one end", "card", "four one one one 1111 1111 one one one one"),
        ("ip one nine two dot one six eight dot one dot one ok", "ip", "one nine two dot one six eight dot one dot one"),
        ("+1 (4​15) 555-0123", "phone", "+1 (4​15) 555-0123"),
    ],
)
def test_disguises(text, kind, part):
    base, both = pii.scan(text)
    assert not base[kind] and [text[a:b] for a, b in both[kind]] == [part]
    assert part not in pii.mask(text)


@pytest.mark.parametrize("text", ["He was at home. The dot is small.", "zero one two three", "look at the dot on the map", "Привет, мир. Как дела?", "one two three go, four five six"])
def test_clean_prose_is_left_alone(text):
    assert not any(pii.scan(text)[1].values()) and pii.mask(text) == text


@pytest.mark.parametrize(
    "text,kind,part",
    [
        ("call +1 415 five five five 0199 now", "phone", "+1 415 five five five 0199"),
        ("call plus one 415 555 0199 now", "phone", "plus one 415 555 0199"),
        ("card 4111 1111 1111 111 one end", "card", "4111 1111 1111 111 one"),
        ("ip 192 dot 168 dot one dot 1 ok", "ip", "192 dot 168 dot one dot 1"),
        ("ip 10 dot 0 dot 0 dot 1 ok", "ip", "10 dot 0 dot 0 dot 1"),
        ("jane@mail dot xyz too", "email", "jane@mail dot xyz"),
        ("or jane7 at example dot shop today", "email", "jane7 at example dot shop"),
        ("or jane dot doe at example dot it today", "email", "jane dot doe at example dot it"),
        ("or jane at mail dot example dot be today", "email", "jane at mail dot example dot be"),
        ("my e-mail: jane at example dot online today", "email", "jane at example dot online"),
    ],
)
def test_few_spelled_digits_and_any_ending(text, kind, part):
    base, both = pii.scan(text)
    assert not base[kind] and [text[a:b] for a, b in both[kind]] == [part]


@pytest.mark.parametrize("text", ["we looked at red dot on the map", "one of 2000 people, 3 plus two", "in 2019, one point 5 of 1000", "section 1.2.3. one thing", "he glanced at blue dot me at one"])
def test_few_digits_of_prose_are_left_alone(text):
    assert pii.mask(text) == text


def test_pii_rows(spark, docs, rows):
    more = spark.createDataFrame([(900, "a@b.co and c@d.org", "en", "s", 1, 1, 1, 0.0, "h")], docs.schema)
    got = {r.doc_id: r for r in pii.find(docs.unionByName(more)).collect()}
    assert got[900].n_email == 2 and got[900].spans == "email:0:6,email:11:18" and got[900].base_sha256 == sha(b"email:0:6,email:11:18")
    assert got[0].spans == "" and len(got) == len({r[0] for r in rows}) + 1
    new = {r.doc_id: r for r in pii.redact(docs.unionByName(more)).collect()}
    assert new[900].text == "[EMAIL] and [EMAIL]" and new[900].n_chars == 19 and new[0].text is None


# --- 6: mixing


def test_apportionment_is_highest_quotients():
    rng = random.Random(8)
    for _ in range(50):
        votes, seats = [rng.randint(0, 1000) for _ in range(rng.randint(1, 9))], rng.randint(0, 60)
        got = [0] * len(votes)
        for _ in range(seats if sum(votes) else 0):
            i = max(range(len(votes)), key=lambda k: (votes[k] / (2 * got[k] + 1), -k))
            got[i] += 1
        assert mixing.apportion(np.array(votes), seats).tolist() == got


def test_water_fill():
    t = mixing.water_fill(np.array([10.0, 1000.0, 0.0]), np.array([5.0, 2.0, 1.0]))
    assert t.tolist() == [30.0, 980.0, 0.0]


def test_mix(spark, docs, rows):
    out = mixing.mix(docs, shard_docs=5)
    got = [r.asDict() for r in out.collect()]
    assert by_row(out) == by_row(mixing.mix(docs.repartition(3), shard_docs=5))
    size = collections.Counter()
    for r in rows:
        size[r[3]] += len((r[1] or "").encode().split())
    assert len(got) == len(rows) and sum(r["size"] for r in got) == sum(size.values())
    taken, target = collections.Counter(), {}
    for r in got:
        assert r["source_size"] == size[r["source"]] and 0 <= r["taken"] <= 3 * r["size"]
        taken[r["source"]] += r["taken"]
        target[r["source"]] = r["target"]
    order = sorted(size, key=lambda s: (s is None, s or ""))
    want = mixing.water_fill(np.array([size[s] for s in order], float), np.array([(5, 2, 1)[i % 3] for i in range(len(order))], float))
    for s, w in zip(order, want):
        assert target[s] == pytest.approx(w) and abs(taken[s] - w) <= 64


def test_block_choice():
    """Each seeded map is one to one, blocks cover a cell once, and cells give whole blocks near their quota."""
    rng = random.Random(5)
    for n in (1, 2, 7, 12, 30, 97, 360):
        mult, shift = mixing.permutation(n, "s", None, n)
        assert sorted((mult * i + shift) % n for i in range(n)) == list(range(n))
    size = np.array([rng.choice([0, 1, 31, 33, 500, 4000]) for _ in range(60)])
    words = np.array([rng.randint(0, 3 * s) for s in size])
    cuts, rounds, chosen = mixing.block_quotas(size, words, 32)
    assert ((0 <= chosen) & (chosen <= cuts)).all() and ((rounds + (chosen > 0)) <= 3).all()
    assert abs((rounds * size + chosen * size / cuts).sum() - words.sum()) <= 32


def test_taken_against_brute_force(spark):
    """Runs recomputed word by word: the words of chosen blocks, of the documents in their seeded order."""
    rows = [(i, " ".join(f"w{i}x{k}" for k in range(i * 7 % 90)), "ab"[i % 7 == 0]) for i in range(60)] + [(3, None, "a"), (4, "one two", None), (5, "x " * 5000, "b")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(df, shard_docs=20, runs=True, carry=("text",)).collect()
    taken = {r.source: 0 for r in got}
    for r in got:
        picked = [i for x in r.runs for i in range(x.a, x.z)]
        assert len(picked) == len(set(picked)) and all(0 <= i < r["size"] for i in picked)
        assert r.taken == r.rounds * r["size"] + len(picked) <= 3 * r["size"]
        taken[r.source] += r.taken
        if picked:
            assert mixing.some_words(r.text or "", [x.asDict() for x in r.runs]).split() == [r.text.split()[i] for i in picked]
    for r in got:
        assert abs(taken[r.source] - r.target) <= 64
    part = [r for r in got if 0 < r.taken % max(1, r["size"])]
    assert part and any(r.runs[0].a > 0 for r in part)  # blocks are not read from the start


def test_take(spark, docs):
    mixed, out = mixing.mix(docs, shard_docs=5), mixing.take(docs, shard_docs=5)
    assert out.columns == docs.columns
    words = sum(len(r.text.encode().split()) for r in out.collect())
    assert words == mixed.agg({"taken": "sum"}).first()[0]


def test_suffixes_of_near_copies(monkeypatch):
    """Near copies in one bucket: each place is left-maximal, so all suffixes are sorted; comparing them by hashes took minutes on large groups."""
    rng = random.Random(4)
    base = bytes(rng.randrange(97, 123) for _ in range(640))
    texts = []
    for _ in range(1500):
        x = bytearray(base)
        for _ in range(3):
            x[rng.randrange(640)] = rng.randrange(97, 123)
        texts.append(bytes(x))
    kind, bucket = bytespans.Bytes(400, 160), np.zeros(1500, np.int64)
    monkeypatch.setattr(bytespans.Suffixes, "sort", None)  # the way by hashes is not taken here
    rows = list(kind.decide(bucket, texts))
    assert len(rows) == len({r for r, _, _ in rows})  # a span a text, not one a suffix
    times = collections.Counter(t[i : i + 400] for t in texts for i in range(241))
    want = {(k, i + j) for k, t in enumerate(texts) for i in range(241) if times[t[i : i + 400]] > 1 for j in (0, 399)}
    assert want <= {(r, x) for r, lo, hi in rows for x in range(lo, hi)} and {r for r, _ in want} == {r for r, _, _ in rows}
    assert {(r, lo) for r, lo, _ in rows} | {(r, hi - 1) for r, _, hi in rows} <= want


def test_suffixes_both_sorts(monkeypatch):
    """Zero bytes, ends and periodic strings: sorted by rests, in small pieces, and by hashes, as brute force has it."""
    kind = bytespans.Bytes(5, 3)
    for keys in (bytespans.KEYS, 60, 0):
        monkeypatch.setattr(bytespans, "KEYS", keys)
        for seed in range(40):
            rng = random.Random(seed)
            texts = [bytes(rng.choice(b"ab\0") for _ in range(rng.randrange(5, 40))) for _ in range(rng.randrange(1, 12))]
            times = collections.Counter(t[i : i + 5] for t in texts for i in range(len(t) - 4))
            want = {(k, i + j) for k, t in enumerate(texts) for i in range(len(t) - 4) if times[t[i : i + 5]] > 1 for j in range(5)}
            assert {(r, x) for r, lo, hi in kind.decide(np.zeros(len(texts), np.int64), texts) for x in range(lo, hi)} == want


def test_suffix_sort_memory():
    """The keys of many classes are made a few megabytes at a time, without an index for every byte of them."""
    rng = np.random.default_rng(0)
    n, data = 60_000, rng.integers(97, 99, 400_000, dtype=np.uint8)
    place = rng.integers(0, len(data) - 1_000, n)
    end, group = place + rng.integers(400, 900, n), np.sort(rng.integers(0, 300, n))
    text, raw = bytespans.Suffixes(data), data.tobytes()
    tracemalloc.start()
    order = text.sort_rests(place, end, group, 0)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 50_000_000
    told = [(g, raw[a:b]) for g, a, b in zip(group[order].tolist(), place[order].tolist(), end[order].tolist(), strict=True)]
    assert told == sorted(told)


# --- 8: order MinHash


def test_order_minhash_rows(spark, docs, rows):
    got = ordersketch.neighbours(docs).collect()
    assert len(got) == len(rows)
    text = {}
    for r in rows:
        k = -(1 << 63) if r[0] is None else r[0]
        text[k] = min(text.get(k, r[1] or ""), r[1] or "", key=lambda x: hashlib.md5(x.encode()).hexdigest())
    keys = sorted(text, reverse=True)
    follow = dict(zip(keys, keys[1:] + keys[:1]))
    own = collections.Counter()
    for r in rows:
        t, k = r[1] or "", -(1 << 63) if r[0] is None else r[0]
        third = len(t) // 3
        own[(r[0], len(t), sha((t[: len(t) - third] + text[follow[k]][:third]).encode()))] += 1
    assert collections.Counter((r.doc_id, r.n_chars, r.edited_sha256) for r in got) == own
    assert all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in got)
    by_text = collections.defaultdict(set)
    for r, t in ((r, t) for r in got for t in [next((x[1] or "") for x in rows if x[0] == r.doc_id)]):
        by_text[t].add(r.fingerprint)
    assert all(len(v) == 1 for v in by_text.values())


def reference_fingerprint(words):
    """Numbered k-mers in plain Python; only equality between texts is compared."""
    seen, out = collections.Counter(), []
    k = ordersketch.K
    for i in range(max(1, len(words) - k + 1) if words else 0):
        g = tuple(words[i : i + k])
        out.append((g, seen[g]))
        seen[g] += 1
    return out


def test_order_matters(spark):
    rng = random.Random(9)
    w = [f"w{i}" for i in range(240)]
    blocks = [w[i : i + 40] for i in range(0, 240, 40)]
    rng.shuffle(blocks)
    texts = [(1, " ".join(w)), (2, " ".join(sum(blocks, []))), (3, " ".join(w[:230] + ["z"] * 10)), (4, "rep " * 200), (5, "rep " * 100)]
    f = {r.i: r for r in ordersketch.fingerprint_columns(spark.createDataFrame(texts, "i long, text string"), "text", "fp").collect()}
    like = lambda a, b: np.mean(np.array(f[a].fp) == np.array(f[b].fp))
    assert like(1, 1) == 1 and like(1, 3) > like(1, 2) > 0.1
    assert like(4, 5) < 1  # occurrence numbers tell repeats apart
    assert len(set(reference_fingerprint(["a"] * 6))) == 4


def test_order_minhash_sorts_plain_longs(spark):
    """Arrays that may hold nulls by type are sorted as objects, and parts were found by a filter for each: both doubled the CPU time."""
    texts = [(1, "a b c d a b c d"), (2, None), (3, "one")]
    plan = ordersketch.fingerprint_columns(spark.createDataFrame(texts, "i long, text string"), "text", "fp")._jdf.queryExecution().optimizedPlan()
    seen = [x for x in json.loads(plan.toJSON()) if x.get("name") in ("_s", "_e", "_i") and "dataType" in x]
    seen += [y for x in json.loads(plan.toJSON()) for e in x.get("projectList", []) for y in e if y.get("name") in ("_s", "_e", "_i") and "dataType" in y]
    assert {x["name"] for x in seen} == {"_s", "_e", "_i"} and not any(x["dataType"]["containsNull"] for x in seen)


# --- 10, 1: classifiers


def test_language_profiles(spark):
    rng, letters = random.Random(3), {"aa": "abcde", "bb": "vwxyz", "cc": "яюэыъ"}
    rows = [(i, " ".join("".join(rng.choice(letters[g]) for _ in range(6)) for _ in range(20)), g) for i, g in enumerate(sorted(letters) * 30)]
    df = spark.createDataFrame([*rows, (900, None, "aa"), (901, "12 34 !?", "bb"), (902, "abcde", None)], "doc_id long, text string, lang string")
    model = language.train(df.where(~language.held_out(df["doc_id"])))
    got = {r.doc_id: r for r in language.predict(df, model).collect()}
    assert all(got[i].lang_pred == g for i, _, g in rows) and got[900].lang_pred == got[901].lang_pred == "und" and got[902].lang_pred == "aa"
    again = language.train(df.repartition(7).where(~language.held_out(df["doc_id"])))
    assert model.equals(again)


def test_language_accuracy(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang")
    held = language.held_out(df["doc_id"])
    out = language.predict(df.where(held), language.train(df.where(~held)), carry=("doc_id", "lang")).toPandas()
    assert (out.lang == out.lang_pred).mean() > 0.97


def toy(n, rng):
    bad = ["vile", "nasty", "rotten", "wretched"]
    rows = []
    for i in range(n):
        w = words_of(rng, 30)
        y = int(rng.random() < 0.25)
        if y:
            w += rng.sample(bad, rng.randint(1, 4))
        rows.append((" ".join(w), y))
    return rows


def words_of(rng, n):
    return ["".join(rng.choice("abcdefg") for _ in range(5)) for _ in range(n)]


def test_severity_grades():
    rng = random.Random(11)
    model = toxicity.fit(toy(1200, rng))
    assert model.cuts == sorted(model.cuts) and len(model.cuts) == toxicity.GRADES
    score = lambda t: sum(model.weight.get(f, 0.0) for f in toxicity.features(t))
    hits = [(model.above(score(t))[0] > 0.5) == bool(y) for t, y in toy(400, rng)]
    assert np.mean(hits) > 0.97
    expected = [sum(model.above(score(t))) for t in ("plain text", "a vile one", "vile nasty one", "vile nasty rotten wretched one")]
    assert expected == sorted(expected)


def test_severity_defined_cases(spark, docs, rows):
    empty = spark.createDataFrame([], "doc_id long, toxic int")
    got = toxicity.grade(docs, toxicity.train(docs, empty)).collect()
    assert len(got) == len(rows) and not any(r.toxic for r in got) and all(r.severity == 0 for r in got)
    kept = toxicity.keep_clean(docs, empty)
    assert by_row(kept) == by_row(docs) and kept.columns == docs.columns


def test_toxicity_on_labels(spark):
    sf = "/root/testdata/sf0.1"
    d = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "toxic")
    train = labels.where("crc32(string(doc_id)) % 2 = 0")
    model = toxicity.train(d, train)
    out = toxicity.grade(d, model).join(labels.where("crc32(string(doc_id)) % 2 = 1").withColumnRenamed("toxic", "label"), "doc_id").toPandas()
    assert out[out.label == 1].toxic.mean() > 0.9 and out[out.label == 0].toxic.mean() < 0.01
    assert isinstance(out, pd.DataFrame)
