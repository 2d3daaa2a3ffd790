"""The registered queries: their columns, their SQL twins, and brute force where there is none."""

import hashlib
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from harness import compare, duck
from test_operators import WORD, brute_spans, brute_stats, brute_targets

from boolmat.llm import queries as q
from boolmat.llm.sql import ORACLES

COLUMNS = {
    "op1_chat_formatting": "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint",
    "op2_weakly_supervised_pii": "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string",
    "op3_collision_counting_neighbours": "query_id bigint, rank int, vec_id bigint, score double",
    "op4_decision_list_rules": "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean",
    "op5_suffix_array_dedup": "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string",
    "op6_warc_transactions": "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint",
    "op7_byte_bpe": "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string",
    "op8_minhash_near_duplicates": "doc_id bigint, n_shingles bigint, component_id bigint, kept boolean",
    "op9_pairwise_quality": "doc_id bigint, held_out boolean, score double, predicted int",
    "op10_pivotal_mixing": "doc_id bigint, size bigint, source_size bigint, target double, taken bigint",
}


@pytest.fixture(scope="module")
def made(spark, sf):
    """The result of each query, made once."""
    done = {}

    def get(name):
        if name not in done:
            df = q.queries()[name](spark, sf)
            have = dict(df.dtypes)
            assert all(have.get(c) == t for c, t in (x.split() for x in COLUMNS.get(name, "").split(", ") if x)), (name, have)
            done[name] = df.collect(), df.schema
        return done[name]

    return get


@pytest.fixture(scope="module")
def documents(spark, sf):
    return {r.doc_id: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql_twins(spark, sf, made, name):
    rows, schema = made(name)
    assert not compare(spark.createDataFrame(rows, schema), duck(sf), ORACLES[name])


def test_personal_data(made, documents):
    for r in made("op2_weakly_supervised_pii")[0]:
        base = brute_spans(documents[r.doc_id].text or "")
        names = ("email", "ip", "card", "phone")
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(k == i for _, _, k in base) for i in range(4))
        said = ",".join(f"{names[k]}:{s}:{e}" for s, e, k in base)
        assert r.base_sha256 == hashlib.sha256(said.encode()).hexdigest()
        assert set(said.split(",")) - {""} <= set(r.spans.split(","))


def test_neighbours(spark, sf, made):
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").collect()
    ids, v = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], float)
    found = defaultdict(list)
    for r in sorted(made("op3_collision_counting_neighbours")[0], key=lambda r: (r.query_id, r.rank)):
        found[r.query_id].append(r)
    hits = 0
    assert set(found) == {i for i in ids.tolist() if i % 20 == 0}
    for query, got in found.items():
        scores = v @ v[ids == query][0]
        order = [i for i in sorted(range(len(ids)), key=lambda i: (-scores[i], ids[i])) if ids[i] != query][:20]
        assert [r.rank for r in got] == list(range(1, 21)) and all(abs(r.score - scores[ids == r.vec_id][0]) < 1e-12 for r in got)
        assert [(-r.score, r.vec_id) for r in got] == sorted((-r.score, r.vec_id) for r in got)
        hits += len({r.vec_id for r in got} & set(ids[order].tolist()))
    assert hits >= 0.9 * 20 * len(found)


def test_rules(made, documents):
    rows = made("op4_decision_list_rules")[0]
    assert len(rows) == len(documents)
    for r in rows:
        want = brute_stats(documents[r.doc_id].text)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (want[0] < 20 or 100 * want[4] > 30 * want[0]) and not (r.base_failed and r.kept)


def test_encoding(made, documents):
    import public_tokenizers as P
    import tiktoken

    from boolmat.llm.bpe import tokenizer

    path = P.path("byte_bpe_50k.tiktoken")
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=tokenizer(path, P.PATTERN).ranks, special_tokens={})
    for r in made("op7_byte_bpe")[0]:
        text = documents[r.doc_id].text or ""
        ids = lib.encode_ordinary(text)
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(text.encode()).hexdigest())


def test_quality(spark, sf, made, documents):
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    rows = made("op9_pairwise_quality")[0]
    assert len(rows) == len(documents)
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)
    judged = [(r.score, labels[r.doc_id]) for r in rows if r.held_out and labels.get(r.doc_id) is not None]
    better = [(a > b) + 0.5 * (a == b) for a, x in judged for b, y in judged if x == 1 and y == 0]
    assert not better or np.mean(better) > 0.8


def test_mixture(made, documents):
    rows = made("op10_pivotal_mixing")[0]
    words = Counter()
    for d in documents.values():
        words[d.source] += len(WORD.findall(d.text or ""))
    want, taken, largest = brute_targets(words), Counter(), Counter()
    for r in rows:
        source = documents[r.doc_id].source
        assert r.target == pytest.approx(want[source]) and r.source_size == words[source] and r.taken <= 3 * r.size
        taken[source] += r.taken
        largest[source] = max(largest[source], r.size)
    assert all(abs(taken[s] - want[s]) <= 2 * largest[s] for s in want)
