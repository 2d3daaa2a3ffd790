"""The ten operators against brute force on small tables with nulls, empty and long texts, ties, repeats and clashing names."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from boolmat.llm import ann, bpe, chat_format, common, minhash, mixing, pii, quality_model, quality_rules, suffix_dedup, warc

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id bigint, text string, source string, lang string"


def texts(seed=0, n=60):
    rng = random.Random(seed)
    words = ["ab", "cat", "dog", "é", "tree", "x|y", "HI!", "one", "two", "of", "the", "12", "a#b"]
    make = lambda k: " ".join(rng.choice(words) + rng.choice(["", "", ".", "\n"]) for _ in range(k))
    out = [make(rng.randint(0, 90)) for _ in range(n)]
    out += [None, "", "  \n\t ", "solo", out[3], out[3], out[4] + " tail", "For " * 60, make(900)]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, ["s1", "s2", None, "Z"][i % 4], "en") for i, t in enumerate(texts())]
    return spark.createDataFrame([*rows, (5, rows[5][1], rows[5][2], "en"), (None, "null id here", "s1", "en")], DOCS).withColumn("n_words", F.lit(-1)).withColumn("kept", F.lit("x")).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def test_chat_round_trip(spark):
    said = r"\### Assistant: </turn> ok"
    turns = [(1, 0, "user", "a<b>\\l"), (1, 1, "assistant", None), (1, 1, "assistant", "zz"), (2, None, None, said), (2, 0, "assistant", said), (None, 0, "user", ""), (1, 0, "user", "a<b>\\l")]
    df = spark.createDataFrame(turns, "conv_id bigint, turn bigint, role string, text string")
    got = {r.conv_id: r for r in chat_format.conversation_digests(chat_format.format_conversations(df)).collect()}
    order = {1: [0, 6, 1, 2], 2: [3, 4], None: [5]}
    for conv, at in order.items():
        all_turns = "".join(f"{turns[i][2] or ''}\n{turns[i][3] or ''}\n" for i in at)
        loss = "".join(turns[i][3] or "" for i in at if turns[i][2] == "assistant")
        assert got[conv].turns_sha256 == hashlib.sha256(all_turns.encode()).hexdigest()
        assert got[conv].loss_sha256 == hashlib.sha256(loss.encode()).hexdigest() and got[conv].loss_chars == len(loss)
    assert chat_format.format_conversations(df.limit(0)).count() == 0


def test_chat_typed_parts(spark):
    parts = [[{"kind": "text", "text": "see "}, {"kind": "image", "ref": "u1", "width": 28, "height": 15}, {"kind": "audio", "ref": "u2", "seconds": 2.0}], [{"kind": "document", "ref": "u3", "pages": 2}, {"kind": "text", "text": "<image:0>"}]]
    df = spark.createDataFrame([(1, i, r, [{k: p.get(k) for k in ("kind", "text", "ref", "width", "height", "seconds", "pages")} for p in ps]) for i, (r, ps) in enumerate(zip(["user", "assistant"], parts))], f"conv_id bigint, turn bigint, role string, parts {chat_format.PARTS}")
    row = chat_format.format_conversations(df).first()
    assert [(a.kind, a.ref, a.n_tokens) for a in row.attachments] == [("image", "u1", 4), ("audio", "u2", 50), ("document", "u3", 1024)]
    assert all(row.formatted[a.start :].startswith(f"<{a.kind}:{a.ordinal}>") for a in row.attachments)
    assert chat_format.parse_formatted(row.formatted)[1] == ("assistant", "<document:2><image:0>") and row.expanded_tokens == 1078


def brute_spans(t):
    out = [(m.start(), m.end(), 0) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), m.end(), 1) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = [int(c) for c in m[0] if c in "0123456789"]
        if 14 <= len(d) <= 19 and sum(x if i % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x) for i, x in enumerate(d[::-1])) % 10 == 0:
            out.append((m.start(), m.end(), 2))
    out += [(m.start(), m.end(), 3) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 10 <= sum(c.isdigit() for c in m[0]) <= 15]
    return sorted(out, key=lambda s: (s[0], s[2]))


def test_pii_base_spans_match_the_plain_patterns():
    rng = random.Random(4)
    bits = ["@", ".", "+1", "(017)", "555-", "7713", "4845168114407329", "4417 7442 8035 1547", "1.2.3.4", "300.1.1.1", "a.b@c-d.e", " ", "-", "é", "x", "00001.2.3.4.5.6.7.8", "+", "9" * 25, "٣"]
    for _ in range(3000):
        t = "".join(rng.choice(bits) for _ in range(rng.randint(0, 14)))
        assert pii.base_spans(t) == brute_spans(t), t
    assert pii.base_spans("1" * 200_000 + "." + "1" * 1000) == []


def test_pii_model_and_redaction(spark, empty):
    rows = [(i, f'word token = "{hashlib.sha1(str(i).encode()).hexdigest()}" and mail me.{i}@host{i}.example.com from 10.0.0.{i}') for i in range(30)] + [(90, None), (91, ""), (92, "nothing to see here"), (92, "nothing to see here")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    model = pii.fit(df)
    got = {r.doc_id: r for r in pii.find_spans(df, model).collect()}
    assert got[3].n_email == 1 and got[3].n_ip == 1 and "secret:14:54" in got[3].spans and got[92].spans == "" and got[90].n_added == 0
    clean = {r.doc_id: r.text for r in pii.redact(df, model).collect()}
    assert clean[3] == 'word token = "<SECRET>" and mail <EMAIL> from <IP>' and clean[90] is None and clean[92] == "nothing to see here"
    assert pii.fit(empty) is None and pii.find_spans(empty, None).count() == 0


def test_neighbours_recall_ties_and_odd_vectors(spark):
    rng = np.random.default_rng(0)
    v = rng.standard_normal((700, 16)) * rng.uniform(0.5, 2, (700, 1))
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(1000 + i, v[7].tolist()) for i in range(40)] + [(2000, None), (2001, [0.0] * 16), (2002, [float("nan")] * 16), (2003, [None] * 16), (2004, [1.0, 2.0]), (2005, [])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>")
    asked = df.where("vec_id % 20 = 0")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    got = ann.nearest(df, asked, 20, block=300, query_block=16).collect()
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "true")
    want = ann.nearest_exact(df, asked, 20).collect()
    key = lambda r: (r.query_id, r.vec_id)
    assert len({*map(key, got)} & {*map(key, want)}) >= 0.95 * len(want)
    exact = {key(r): r.score for r in want}
    assert all(abs(exact[key(r)] - r.score) < 1e-12 for r in got if key(r) in exact)
    of = lambda rows: [(r.rank, r.vec_id) for r in sorted((r for r in rows if r.query_id == 1000), key=lambda r: r.rank)]
    assert of(got) == of(want)  # 40 equal vectors: ties go to the smaller id
    assert ann.nearest(df.limit(0), df.limit(0)).count() == 0


def test_own_row_takes_no_neighbours_place():
    rng = np.random.default_rng(5)
    v = rng.standard_normal((400, 8))
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    index = ann.CollisionIndex(np.arange(400), v, reach=50.0, surety=50.0)  # the first windows hold the whole block
    for i in range(0, 400, 20):
        scores = v @ v[i]
        scores[i] = -np.inf
        assert [x for _, x in index.search(i, v[i], 5)] == np.argsort(-scores)[:5].tolist()


def brute_stats(t):
    t = t or ""
    w = WORD.findall(t)
    lines = [x for x in t.split("\n") if WORD.search(x)]
    windows = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    covered = {j for i in range(len(w) - 7) if windows[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered)


def test_rule_statistics(docs, empty):
    rules = quality_rules.DecisionList(((quality_rules.Condition("upper_share", True, 0.5),),))
    got = quality_rules.apply_rules(docs.select("doc_id", "text"), rules).collect()
    for r in got:
        want = brute_stats(r.text)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, r.text
        assert r.base_failed == (want[0] < 20 or 100 * want[4] > 30 * want[0]) and not (r.kept and r.base_failed)
    assert quality_rules.apply_rules(empty, quality_rules.DecisionList(())).count() == 0


def test_lines_of_form_feeds_and_of_the_letter_f(spark):
    odd = ["a\n\f\nb\n\f\n\f", "f\nx\nf", "ff\n f \nff\nff", "\f\n\f", "\x0b\n\x0b\na\na"]
    df = spark.createDataFrame(list(enumerate(odd)), "doc_id bigint, text string")
    got = {r.doc_id: (r.n_dup_lines, r.dup_line_share) for r in quality_rules.text_stats(df).collect()}
    assert got == {0: (0, 0.0), 1: (1, 1 / 3), 2: (2, 0.5), 3: (0, 0.0), 4: (1, 0.5)}
    assert all(got[i][0] == brute_stats(t)[3] for i, t in enumerate(odd))


def test_rules_are_learned_and_clean_rows_stay():
    rng = np.random.default_rng(0)
    x = rng.random((600, len(quality_rules.FEATURES)))
    junk = (x[:, 1] > 0.8) | ((x[:, 3] > 0.7) & (x[:, 5] <= 0.4))
    rules = quality_rules.fit_list(x, junk)
    hit = np.zeros(600, bool)
    for rule in rules.rules:
        hit |= quality_rules._covers(list(rule), x)
    assert (hit & junk).sum() > 0.85 * junk.sum() and (hit & ~junk).sum() <= 0.05 * hit.sum()
    assert quality_rules.fit_list(x, np.zeros(600, bool)).rules == ()


def brute_repeats(all_texts, length):
    data = [(t or "").encode() for t in all_texts]
    count = Counter(d[i : i + length] for d in data for i in range(len(d) - length + 1))
    out = []
    for d in data:
        gone = np.zeros(len(d), bool)
        for i in range(len(d) - length + 1):
            if count[d[i : i + length]] > 1:
                gone[i : i + length] = True
        out.append((len(d), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(bytes(np.frombuffer(d, np.uint8)[~gone])).hexdigest()))
    return out


def test_suffix_arrays_match_sorting():
    rng = np.random.default_rng(3)
    for _ in range(60):
        lanes, ends, n = [[0]], [], 1
        for _ in range(rng.integers(1, 5)):
            a = [*(rng.integers(0, rng.integers(1, 4) + 1, rng.integers(0, 30)) + 1).tolist(), 0]
            lanes.append(a)
            n += len(a)
            ends.append(n)
        sa, at = suffix_dedup.lyndon_suffix_arrays(np.array(sum(lanes, []), np.int64), np.array(ends)), 1
        for a, e in zip(lanes[1:], ends):
            assert (sa[at:e] - at).tolist() == sorted(range(len(a)), key=lambda i: a[i:])
            at = e


@pytest.mark.parametrize("lane", [16_000, 400])
def test_suffix_dedup_against_brute_force(spark, monkeypatch, lane):
    monkeypatch.setattr(suffix_dedup, "LANE", lane)
    rng = random.Random(1)
    say = lambda k: "".join(rng.choice("abcdé ") for _ in range(k))
    passage = say(90)
    pool = [say(rng.randint(0, 200)) for _ in range(40)] + [say(rng.randint(0, 60)) + passage[rng.randint(0, 9) :] + say(rng.randint(0, 60)) for _ in range(40)]
    edited = list(pool[45] * 2)
    edited[50] = "#"
    pool += [pool[45], pool[45], "".join(edited), "ab" * 150, "z" * 170, None, "", passage, say(2000)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(pool)] + [(2, pool[2]), (None, passage)], "doc_id bigint, text string").repartition(4)
    got = sorted(((r.doc_id if r.doc_id is not None else -1), r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(df, 50).collect())
    everything = [*pool, pool[2], passage]
    want = sorted((i, *x) for i, x in zip([*range(len(pool)), 2, -1], brute_repeats(everything, 50)))
    assert got == want
    assert suffix_dedup.remove_repeats(df.limit(0), 50).count() == 0


def test_warc_round_trip(spark, tmp_path):
    import base64

    pages = [(1, "http://a/x", "<p>é\r\n\r\nWARC/1.1</p>"), (2, None, None), (3, "http://b/\r\ny", ""), (4, "http://a/x", "<p>é\r\n\r\nWARC/1.1</p>"), (5, "http://c", "solo"), (5, "http://c", "solo"), (None, "http://d", "alone")]
    df = spark.createDataFrame(pages, "page_id bigint, url string, html string")
    records = warc.read_records(spark, warc.write_archives(df, str(tmp_path / "w"), 4))
    assert Counter(r.warc_type for r in records.collect()) == {"request": 7, "metadata": 7, "response": 5, "revisit": 2}
    got = warc.page_captures(warc.assemble(records)).collect()
    assert len(got) == 7 and all(r.digest_ok is not False for r in got)
    by = {r.page_id: r for r in got}
    for i, _, html in pages:
        raw = (html or "").encode()
        assert by[i].payload_bytes == len(raw) and by[i].payload_digest == base64.b32encode(hashlib.sha1(raw).digest()).decode()
    assert (by[1].record_type, by[1].refers_to) == ("revisit", 4) and (by[2].record_type, by[2].refers_to) == ("revisit", 3) and by[5].record_type == by[None].record_type == "response"
    assert warc.page_captures(warc.assemble(warc.read_records(spark, warc.write_archives(df.limit(0), str(tmp_path / "e"))))).count() == 0


def test_bpe_equals_the_library(spark, docs):
    import public_tokenizers as P
    import tiktoken

    path = P.path("byte_bpe_50k.tiktoken")
    t = bpe.Tokenizer(path, P.PATTERN)
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=t.ranks, special_tokens={})
    rng = random.Random(2)
    odd = ["'", "'s", "'re", " ", "  ", "\n", "\t", "a", "é", "ß", "7", "!", "don't", "汉", " ", "word", "I'll", "🙂"]
    for _ in range(400):
        s = "".join(rng.choice(odd) for _ in range(rng.randint(0, 120)))
        assert t.encode(s) == lib.encode_ordinary(s)
        assert t.encode(s, 16, 6) == lib.encode_ordinary(s)
    for s in ("a" * 3000, " " * 500 + "x", "!" * 700, "ab'" * 300):
        assert t.encode(s, 64, 16) == lib.encode_ordinary(s) and t.decode(t.encode(s)) == s.encode()
    got = bpe.digests(bpe.encode(docs, path, P.PATTERN, 200, 40), path, P.PATTERN).collect()
    want = Counter((r.doc_id, hashlib.sha256(" ".join(map(str, lib.encode_ordinary(r.text or ""))).encode()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest()) for r in docs.collect())
    assert Counter((r.doc_id, r.ids_sha256, r.decoded_sha256) for r in got) == want


def test_bpe_marks_and_merges_many_texts_at_once(monkeypatch):
    import public_tokenizers as P

    assert P.PATTERN == bpe.FAMILIAR
    t = bpe.Tokenizer(P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    assert t.familiar and not bpe.Tokenizer(P.path("byte_bpe_50k.tiktoken"), r"\S+|\s+").familiar
    rng = random.Random(7)
    odd = ["'", "'", "'s", "'t", "'r", "e", "'ve", "'l", "l", "'m", "'d", "S", " ", " ", "  ", "\n", "\t", "\x1c", "\x85", "\xa0", "\u2003", "\u3000", "a", "é", "ß", "7", "²", "٣", "Ⅷ", "!", "…", "汉", "🙂", "𝔘", "𝟘", "e\u0301", "\u200d"]
    made = ["".join(rng.choice(odd) for _ in range(rng.randint(0, 25))) for _ in range(3000)]
    made += ["", "'s", "'", "x'", "'re", "'r", " 's", "\n's", "'s's", "''s", "\u2003x", "x\u2003", "\u2003 \u2003y", "", "thethethe" * 7, "ab" * 32, "汉字" * 40, "x" * 900]
    raw = [x.encode() for x in made]
    data, cuts = np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)])
    bounds = bpe.pretokens(data, cuts)
    pieces = [data[a:b].tobytes() for a, b in zip(bounds, bounds[1:])]
    assert pieces == [p.encode() for x in made for p in t.split.findall(x)]
    assert all(t.ends(x) == [m.end() for m in t.split.finditer(x)] for x in made)
    assert bpe.pretokens(data[:0], np.zeros(3, np.int64)).tolist() == [0]

    pieces += [bytes(rng.choice(b"aehnt") for _ in range(rng.randint(1, 70))) for _ in range(500)] + [bytes(rng.randbytes(rng.randint(1, 64))) for _ in range(500)]
    want = [list(t.merge(p)) for p in pieces]
    monkeypatch.setattr(bpe, "STEP", 100)
    ids, counts = t.merge_all(pieces)
    assert [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])] == want

    want = [t.encode_pieces(t.split.findall(x)) for x in made]
    for most in (bpe.REMEMBERED, 50):  # all remembered, or forgotten again and again
        monkeypatch.setattr(bpe, "REMEMBERED", most)
        t.forget()
        got = [t.encode_texts(data[cuts[a] : cuts[b]], cuts[a : b + 1] - cuts[a]).to_pylist() for a, b in ((0, 0), (0, 1500), (0, 1500), (1500, len(made)))]
        assert got == [[], want[:1500], want[:1500], want[1500:]]
    lists = pa.array([[], want[0], [], want[1]], pa.list_(pa.int32())).slice(1)
    words = pa.array([t.bytes_of.get(i) for i in range(max(t.bytes_of) + 1)], pa.large_binary())
    assert [bytes(x) for x in bpe.joined(words, lists.flatten(), lists.offsets.to_numpy())] == [raw[0], b"", raw[1]]


def brute_components(rows, size, percent):
    sets = {}
    for i, t in rows:
        w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        s = {tuple(w[k : k + size]) for k in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set())
        sets.setdefault(i, []).append(frozenset(s))
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    flat = [(i, s) for i, ss in sets.items() for s in ss if s]
    for a in range(len(flat)):
        for b in range(a):
            (i, s), (j, u) = flat[a], flat[b]
            if 100 * len(s & u) >= percent * len(s | u):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return {i: find(i) for i in root}


@pytest.mark.parametrize("bucket", [32, 1])
def test_near_duplicates_against_brute_force(spark, docs, bucket, monkeypatch):
    monkeypatch.setattr(minhash, "SMALL_BUCKET", bucket)
    monkeypatch.setattr(minhash, "ASKED", 8 if bucket == 1 else 256)
    monkeypatch.setattr(minhash, "HELD", 16 if bucket == 1 else 1024)
    rng = random.Random(9)
    say = lambda k: [rng.choice(["Ab", "cd", "ef", "gh", "ij", "kl", "mn"]) + str(rng.randint(0, 30)) for _ in range(k)]
    rows, base = [], say(120)
    for i in range(60):  # a chain and a star of edits, so that neighbours link and ends do not
        copy = list(base)
        for _ in range(rng.randint(0, 6)):
            copy[rng.randint(0, 119)] = say(1)[0]
        rows.append((100 + i, " ".join(copy)))
        if i % 9 == 8:
            base = copy
    rows += [(300 + i, " ".join(say(rng.randint(0, 40)))) for i in range(40)] + [(400, None), (401, ""), (402, "one"), (403, "ONE"), (404, "one two"), (405, rows[0][1]), (405, rows[40][1]), (406, rows[0][1].upper())]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("n", F.lit(1)).withColumn("root", F.lit("r")).repartition(3)
    for size, percent in ((3, 85),) if bucket == 1 else ((3, 85), (5, 80)):
        want = brute_components(rows, size, percent)
        got = minhash.near_duplicates(df, size, percent).collect()
        assert len(got) == len(rows) and all(r.component_id == want[r.doc_id] and r.kept == (r.doc_id == r.component_id) for r in got)
    assert minhash.near_duplicates(df.limit(0)).count() == 0
    lone = minhash.near_duplicates(spark.createDataFrame([(None, "a b c"), (1, "a b c")], "doc_id bigint, text string")).collect()
    assert sorted((r.doc_id is None, r.component_id, r.kept) for r in lone if r.doc_id is not None) == [(False, 1, True)] and all(r.kept for r in lone)


def test_bands_follow_from_the_threshold(spark, monkeypatch):
    assert minhash.bands_for(85) == minhash.BANDS and minhash.bands_for(80) == 39
    assert all((1 - (p / 100) ** 5) ** minhash.bands_for(p) <= 2.5e-7 for p in range(50, 100)) and minhash.bands_for(100) == 1
    used = []
    sign = minhash.signatures
    monkeypatch.setattr(minhash, "signatures", lambda docs, size, bands, rows: used.append(bands) or sign(docs, size, bands, rows))
    df = spark.createDataFrame([(1, "a b c"), (2, "a b c")], "doc_id bigint, text string")
    for percent in (80, 85):
        assert [r.kept for r in minhash.near_duplicates(df, 5, percent).orderBy("doc_id").collect()] == [True, False]
    assert used == [39, 26]


def test_few_rows_make_few_files(spark, monkeypatch):
    made = {}

    def counted(df, tag, *files):
        out = common.written(df, tag, *files)
        made.setdefault(tag, []).append(len(out.inputFiles()))
        return out

    monkeypatch.setattr(minhash, "written", counted)
    most, text = spark.sparkContext.defaultParallelism, lambda k: [f"w{k}x{i}" for i in range(60)]
    docs = spark.createDataFrame([(3 * k + c, " ".join([*text(k), "tail"][c % 2 : 61 - (c == 2)])) for k in range(40 * most) for c in range(3)], "doc_id bigint, text string")
    wide = {"spark.sql.shuffle.partitions": str(8 * most), "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    before = {k: spark.conf.get(k) for k in wide}
    try:
        for k, v in wide.items():
            spark.conf.set(k, v)
        got = {r.doc_id: r.component_id for r in minhash.near_duplicates(docs).collect()}
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    assert got == {i: i - i % 3 for i in range(120 * most)}
    assert {"near-classes", "near-pairs", "near-sets", "near-links", "cc"} <= made.keys()
    assert all(n <= most for counts in made.values() for n in counts) and min(made["cc"]) == 1
    assert common.files_for(spark, 5_000 * most * 7) == 7 * most and common.files_for(spark, 1, 2_000_000 * most * 3 + 1) == 3 * most + 1


def test_connected_components(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 120), (120, 110), (110, 105)] + [(500, x) for x in range(501, 560)] + [(7, 7)]
    got = dict(minhash.connected(spark.createDataFrame(edges, "a bigint, b bigint")).collect())
    assert got == {**{i: 0 for i in range(1, 41)}, 105: 100, 110: 100, 120: 100, **{x: 500 for x in range(501, 560)}}


def test_ranking_learns_and_scores_all_rows(spark, empty):
    rng = random.Random(3)
    good = lambda: " ".join(rng.choice(["alpha", "beta", "gamma", "delta", "eps"]) + str(rng.randint(0, 500)) for _ in range(60))
    rows = [(i, good() if i % 3 else "BUY!! " * rng.randint(20, 60)) for i in range(240)] + [(900, None), (901, "")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(160)] + [(None, 1), (5, None)], "doc_id bigint, quality int")
    got = {r.doc_id: r.score for r in quality_model.score(df, quality_model.fit(df, labels)).collect()}
    assert len(got) == 242 and all(0 <= s <= 1 for s in got.values())
    assert np.mean([(got[i] >= 0.3) == (i % 3 > 0) for i in range(160, 240)]) > 0.95
    blank = quality_model.score(df, quality_model.fit(df, labels.limit(0))).select("score").distinct().collect()
    assert [r.score for r in blank] == [0.5] and quality_model.score(empty, quality_model.fit(df, labels)).count() == 0


def test_ranking_takes_all_pairs_of_all_labelled_rows(spark, monkeypatch):
    rng = np.random.default_rng(8)
    x, good = rng.normal(size=(300, len(quality_model.FEATURES))), rng.random(300) < 0.7
    x[good] += 0.4
    model = quality_model.fit_pairs(x, good)
    bins = model.bins(x)
    hot = (bins[:, :, None] == np.arange(len(model.weights))).sum(1).astype(float)
    raw = hot @ model.weights
    pull = 1 / (1 + np.exp(raw[good][:, None] - raw[~good][None, :]))  # of each pair
    slope = (hot[~good].T @ pull.sum(0) - hot[good].T @ pull.sum(1)) / pull.size + 1e-3 * model.weights
    assert np.abs(slope).max() < 1e-8 and np.abs(model.weights).max() > 0.1
    assert model.cut == pytest.approx(np.quantile(raw, 1 - good.mean()))
    monkeypatch.setattr(quality_model, "FIT_ROWS", 50, raising=False)
    rows = spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(x)], "doc_id bigint, " + ", ".join(f"{f} double" for f in quality_model.FEATURES)).repartition(5)
    spread = quality_model.fit(rows, spark.createDataFrame([(i, int(g)) for i, g in enumerate(good)], "doc_id bigint, quality int"))
    assert np.allclose(spread.weights, model.weights, atol=1e-8) and spread.cut == pytest.approx(model.cut)
    assert all(np.allclose(a, b) for a, b in zip(spread.borders, model.borders, strict=True))


def test_quantiles_of_ties(spark):
    values = [0.0] * 50 + [1.5, -2.0, 7.25, 7.25] + [float(i) for i in range(30)]
    rows = spark.createDataFrame([(k, v * (k + 1)) for v in values for k in range(3)], "kind int, value double").repartition(4)
    shares = np.array([0, 0.1, 0.37, 0.5, 0.93, 1])
    got = quality_model.quantiles(rows, shares)
    assert all(np.allclose(got[k], np.quantile(np.array(values) * (k + 1), shares)) for k in range(3))


def test_text_features_do_not_depend_on_neighbours():
    from boolmat.llm.common import text_buffers

    all_texts = [t or "" for t in texts()]
    raw, cuts = text_buffers(pa.array(all_texts))
    together = quality_model.features(raw[: cuts[-1]], cuts)
    for i, t in enumerate(all_texts):
        one = quality_model.features(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t.encode())]))
        assert np.allclose(one[0], together[i]), t


def brute_targets(sizes, weights=(5, 2, 1), cap=3):
    names = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + ([None] if None in sizes else [])
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    left, open_, out = sum(sizes.values()), set(names), {}
    while open_:
        share = {s: left * w[s] / sum(w[x] for x in open_) for s in open_}
        over = {s for s in open_ if share[s] > cap * sizes[s]}
        if not over:
            return out | share
        for s in over:
            out[s] = cap * sizes[s]
            left -= out[s]
        open_ -= over
    return out


def test_mixing(spark, docs, empty):
    rows = mixing.mix(docs, block=8).collect()
    words = Counter()
    for r in docs.collect():
        words[r.source] += len(WORD.findall(r.text or ""))
    want = brute_targets(words)
    assert len(rows) == docs.count()
    for r in rows:
        assert r.target == pytest.approx(want[r.source]) and r.source_size == words[r.source] and r.taken <= 3 * r.size
    for s in want:
        got = sum(r.taken for r in rows if r.source == s)
        assert abs(got - want[s]) <= 2 * max(r.size for r in rows if r.source == s)
    again = sorted(map(str, mixing.mix(docs.repartition(5), block=8).collect()))
    assert again == sorted(map(str, rows)) and mixing.mix(empty).count() == 0
    copies = mixing.mixed_documents(docs, block=8)
    assert copies.columns == docs.columns
    assert sum(len(WORD.findall(r.text)) for r in copies.collect()) == sum(r.taken for r in rows)


def test_whole_copies_sum_over_many_blocks(spark):
    df = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat_ws(" ", F.array_repeat(F.lit("w"), (F.col("id") % 50 + 1).cast("int"))).alias("text"), F.when(F.col("id") % 7 == 0, "a").otherwise("b").alias("source"))
    rows = mixing.mix(df, block=16).groupBy("source").agg(F.sum("taken").alias("t"), F.first("target").alias("goal"), F.sum("size").alias("s"), F.sum("copies").alias("c"), F.count("*").alias("n")).collect()
    for r in rows:
        assert abs(r.t - r.goal) / r.goal < 0.02 and abs(r.c - r.n * r.goal / r.s) <= 1


def test_repeated_rows_are_mixed_one_by_one(spark):
    words = " ".join(["w"] * 100)
    rows = [(1, words, "a")] * 1000 + [(2, words, "b")] * 1000 + [(i, words, "c") for i in range(10, 1010)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string").repartition(5)
    got = mixing.mix(df)
    for r in got.groupBy("source").agg(F.sum("taken").alias("taken"), F.first("target").alias("target"), F.count("*").alias("n")).collect():
        assert r.n == 1000 and abs(r.taken - r.target) <= 100
    copies = mixing.mixed_documents(df).groupBy("source").count().collect()
    want = {r.source: r.c for r in got.groupBy("source").agg(F.sum("copies").alias("c")).collect()}
    assert {r.source: r["count"] for r in copies} == want
    some = spark.createDataFrame([(7, "one two", "a")], "doc_id bigint, text string, source string").withColumn("n", F.lit(25_000).cast("long"))
    assert mixing._spread(some, "n").count() == 25_000


def test_targets_over_many_sources(spark):
    rng = random.Random(8)
    sizes = {f"s{i:04d}": rng.randint(0, 40) for i in range(500)} | {None: 17}
    df = spark.createDataFrame(list(sizes.items()), "source string, size bigint")
    got = {r.source: r.target for r in mixing.source_targets(df).collect()}
    want = brute_targets(sizes)
    assert got.keys() == want.keys() and all(abs(got[s] - want[s]) < 1e-6 for s in want)


def test_a_repeated_query_is_one_query(spark):
    rng = np.random.default_rng(1)
    rows = [(i, rng.standard_normal(8).tolist()) for i in range(200)] + [(20, None), (40, [1.0] * 8)]
    df = spark.createDataFrame([*rows, rows[20]], "vec_id bigint, embedding array<double>")
    asked = df.where("vec_id % 20 = 0")
    got = ann.nearest(df, asked, 5).groupBy("query_id").agg(F.sort_array(F.collect_list("rank")).alias("ranks")).collect()
    want = {i: [1, 2, 3, 4, 5] for i in range(0, 200, 20)} | {40: [1, 1, 2, 2, 3, 3, 4, 4, 5, 5]}  # 40 has two vectors
    assert {r.query_id: r.ranks for r in got} == want


def test_spans_of_a_long_log_take_linear_time():
    import time

    line = "10.0.0.1 user@host.org 555-123-4567 token=ab12cd34ef56ab78cd90ef12 "
    text = line * 20_000
    began = time.perf_counter()
    base = pii.base_spans(text)
    found = pii.candidates(text, base)
    assert len(base) == 40_000 and len(found) == 40_000 and time.perf_counter() - began < 30
    taken = [(s, e) for s, e, _ in base[:200]]
    assert all(e <= a or s >= b for s, e, _ in found[:200] for a, b in taken)


def test_a_capture_without_metadata(spark, tmp_path):
    df = spark.createDataFrame([(1, "http://a", "x"), (2, "http://b", "x")], "page_id bigint, url string, html string")
    records = warc.read_records(spark, warc.write_archives(df, str(tmp_path / "m"))).where("warc_type <> 'metadata'")
    got = warc.page_captures(warc.assemble(records)).collect()
    assert sorted(r.record_type for r in got) == ["response", "revisit"] and all(r.page_id is None for r in got)


def test_a_part_of_unknown_kind_keeps_its_reference(spark):
    parts = [{"kind": "video", "ref": "v1", "text": "clip <"}, {"kind": "text", "text": "ok"}, {"kind": "add", "text": "t"}]
    df = spark.createDataFrame([(1, 0, "user", [{k: p.get(k) for k in ("kind", "text", "ref", "width", "height", "seconds", "pages")} for p in parts])], f"conv_id bigint, turn bigint, role string, parts {chat_format.PARTS}")
    row = chat_format.format_conversations(df).first()
    assert [(a.kind, a.ref) for a in row.attachments] == [("video", "v1")] and chat_format.parse_formatted(row.formatted) == [("user", "clip <<other:0>okt")]


def test_joins_with_frequent_keys(spark):
    from boolmat.llm.common import keyed_join

    rows = spark.createDataFrame([(1, i) for i in range(3000)] + [(k, k) for k in range(2, 2000)] + [(None, -1)], "k bigint, x bigint")
    side = rows.where("k < 1000").groupBy("k").agg(F.count("*").alias("n"))
    for how in ("inner", "left"):
        got, want = keyed_join(rows, side, ["k"], "n", how), rows.join(side, "k", how)
        assert sorted(map(str, got.select("k", "x", "n").collect())) == sorted(map(str, want.select("k", "x", "n").collect()))


@pytest.mark.parametrize("lane", [16_000, 2_000])
def test_suffix_dedup_over_several_buckets(spark, monkeypatch, lane):
    """Passages shared by many documents, dealt to several buckets and lanes."""
    monkeypatch.setattr(suffix_dedup, "LANE", lane)
    monkeypatch.setattr(suffix_dedup, "BUCKET", 20_000)
    rng = random.Random(5)
    say = lambda k: " ".join(rng.choice(["ab", "cde", "fé", "ghij"]) + str(rng.randint(0, 999)) for _ in range(k))
    passages = [say(60) for _ in range(12)]
    pool = [f"{say(rng.randint(0, 40))} {rng.choice(passages)} {say(rng.randint(0, 40))}" for _ in range(500)] + [passages[0]] * 200
    df = spark.createDataFrame(list(enumerate(pool)), "doc_id bigint, text string").repartition(6)
    got = sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(df, 100).collect())
    assert got == [(i, *x) for i, x in enumerate(brute_repeats(pool, 100))]


def test_votes_on_spans_without_digits():
    text = "write to jo@host.example.org now"
    (span,) = pii.base_spans(text)
    assert len(pii.votes(text, span)) == len(pii.LABELERS) and len(pii.properties(text, span)) == 6
