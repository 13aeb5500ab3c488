"""Token files, packing and mixing against brute force."""

import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from temporal_rules.llm import mixing, packing, token_store
from temporal_rules.llm.queries import vocabulary
from temporal_rules.llm.tokens import BatchEncoder

DOCS = "doc_id long, text string, lang string, source string, n_chars long, __rank long, salt string"


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(vocabulary())


@pytest.fixture(scope="module")
def odd(spark):
    rows = [
        (5, "Hello, world.\nNext line", "en", "b", 1, 1, "x"), (3, None, None, None, None, None, None), (4, "", "en", "a", 0, 2, "y"),
        (9, "word " * 4000, "en", None, 9, 3, "z"), (7, "same text", "en", "a", 9, 3, "z"), (7, "same text", "en", "a", 9, 3, "z"), (None, "no id here", "fr", "", 3, 3, "z"),
        (11, " \t\n ", "de", "b", 4, 5, "q"), (12, "x" * 30_000, "de", "é", 4, 5, "q"),
    ]
    return spark.createDataFrame(rows, DOCS)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.text(alphabet="aé÷× \n\t,.!'1_<|endoftext>»漢’😀\x01\x1c\rß", max_size=20) | st.none(), max_size=6))
def test_encoder_is_exact(library, texts):
    ids, off = BatchEncoder.encode(test_encoder_is_exact.enc, pa.array(texts, pa.string()), at_once=16)
    assert [ids[a:b].tolist() for a, b in zip(off, off[1:])] == [library.encode(t or "", add_special_tokens=False).ids for t in texts]


test_encoder_is_exact.enc = BatchEncoder(vocabulary(), remember=40)


def expected_ids(library, text, end):
    return library.encode(text or "", add_special_tokens=False).ids + [end]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_token_files_round_trip(spark, odd, library):
    store = token_store.write_store(odd, vocabulary(), 0, shard_bytes=150)
    got = [tuple(r) for r in store.documents(spark).collect()]
    rows = sorted(odd.collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0))
    want = [(r.doc_id, len(x := expected_ids(library, r.text, 0)), crc(x)) for r in rows]
    got.sort(key=lambda r: r[1])
    # Rows that repeat a doc_id may stand in any order.
    assert sorted((g[0] is not None, g[0] or 0, *g[2:]) for g in got) == sorted((w[0] is not None, w[0] or 0, *w[1:]) for w in want)
    assert [g[0] for g in got] == [w[0] for w in want] and [g[1] for g in got] == np.cumsum([0, *(g[2] for g in got)])[:-1].tolist()
    assert len(store.shards) > 1
    for name, _, _ in store.shards:
        for one in token_store.read_document(store.path, name, 7):
            assert one == expected_ids(library, "same text", 0)
    assert sum(len(token_store.read_document(store.path, n, 9)) for n, _, _ in store.shards) == 1
    assert all(token_store.read_document(store.path, n, 1000) == [] for n, _, _ in store.shards)


def test_token_files_of_table(spark, sf, library):
    from temporal_rules.llm.queries import op2_token_files

    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in op2_token_files(spark, sf).collect()}
    at = 0
    docs = spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()
    for r in docs:
        ids = expected_ids(library, r.text, 0)
        assert got[r.doc_id] == (at, len(ids), crc(ids))
        at += len(ids)
    assert len(got) == len(docs)


def test_token_files_of_nothing(spark, odd):
    assert token_store.write_store(odd.limit(0), vocabulary(), 0).documents(spark).collect() == []


def check_packing(rows, docs, library, size=1024):
    by = defaultdict(list)
    for r in rows:
        by[r.sequence_id].append(r)
    for rs in by.values():
        at = 0
        for r in sorted(rs, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= size
    want = Counter()
    for d in docs:
        ids = expected_ids(library, d.text, 2)
        k = -(-len(ids) // size)
        first = len(ids) - (k - 1) * size
        cut = [0, *(first + i * size for i in range(k))]
        for i, (a, b) in enumerate(zip(cut, cut[1:])):
            want[(d.doc_id, i, a, b - a, crc(ids[a:b]))] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows) == want
    return len(by), -(-sum(r.length for r in rows) // size)


def test_packing_of_table(spark, sf, library):
    from temporal_rules.llm.queries import op10_pattern_packing

    used, least = check_packing(op10_pattern_packing(spark, sf).collect(), spark.read.parquet(f"{sf}/documents.parquet").collect(), library)
    assert used <= least * 1.02 + 2


def test_packing_of_odd_rows(spark, odd, library):
    check_packing(packing.pack_documents(odd, vocabulary()).collect(), odd.collect(), library)
    assert packing.pack_documents(odd.limit(0), vocabulary()).collect() == []
    with_ids = packing.pack_documents(odd, vocabulary(), with_ids=True).collect()
    assert all(crc(r.ids) == r.ids_crc32 for r in with_ids)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 40), min_size=24, max_size=24))
def test_plan_places_every_piece_once(counts):
    h = np.array([0, *counts])
    made = packing.plan(h, 24)
    seen = Counter()
    for what, n in made:
        assert n > 0 and sum(what) <= 24
        for k in what:
            seen[k] += n
    assert [seen[k] for k in range(25)] == h.tolist()
    total = int((h * np.arange(25)).sum())
    single = packing.best_fit(h.tolist(), 24)
    assert sum(n for _, n in made) <= 1.25 * max(-(-total // 24), sum(n for _, n in single)) + 3


def test_targets_are_reshared():
    assert mixing.targets({"b": 100, "a": 100, None: 100}) == pytest.approx({"a": 200, "b": 250 / 3, None: 250 * 2 / 3})
    t = mixing.targets({"a": 10, "b": 1000, "c": 0})
    assert t["a"] == 20 and t["c"] == 0 and t["b"] == pytest.approx(1515 - 20)


def test_mix(spark, odd, sf):
    for docs in (odd, spark.read.parquet(f"{sf}/documents.parquet")):
        m = mixing.mix(docs)
        rows = mixing.taken_words(m).collect()
        words = Counter(len((r.text or "").encode().split()) for r in docs.collect())
        assert Counter(r["size"] for r in rows) == words
        by = defaultdict(list)
        for r in rows:
            assert 0 <= r.taken <= 2 * r["size"]
            by[r.source].append(r)
        assert sum(r[0].target for r in by.values()) == pytest.approx(1.5 * sum(r["size"] for r in rows))
        for rs in by.values():
            assert rs[0].source_size == sum(r["size"] for r in rs)
            assert abs(sum(r.taken for r in rs) - rs[0].target) <= 1
        again = mixing.taken_words(mixing.mix(docs.repartition(3))).collect()
        assert sorted(map(str, rows)) == sorted(map(str, again))
        spans = m.spans.orderBy("slot", "src").collect()
        assert all(r.from_word < r.to_word <= r["size"] for r in spans)
    assert mixing.taken_words(mixing.mix(odd.limit(0))).collect() == []


def test_schedule_follows_weights(spark):
    rows = sorted(mixing.schedule(spark, [3000, 1000, 2000], 10, slots_per_task=64).collect())
    src = [r.src for r in rows]
    for i in range(60, len(src), 60):
        assert abs(src[:i].count(0) - i / 2) <= 5 and abs(src[:i].count(1) - i / 6) <= 5
    for s in range(3):
        assert [r.k for r in rows if r.src == s] == list(range(src.count(s)))


def test_mixed_documents_keep_clashing_columns(spark):
    names = ["salt", "__size", "__taken", "__rows", "__id", "__salt", "__row", "slot", "key", "a.b"]
    rows = [(i, f"word{i} and five more words here", "ab"[i % 2], *(f"{n}{i}" for n in names)) for i in range(30)] + [(3, "word3 and five more words here", "b", *("x" * len(names)))]
    rows += [(None, "no id but words", None, *("y" * len(names))), (40, None, "a", *("z" * len(names))), (41, "", "a", *("z" * len(names)))]
    docs = spark.createDataFrame(rows, ["doc_id", "text", "source", *names])
    got = mixing.mixed_documents(docs).collect()
    assert got and got[0].__fields__ == docs.columns
    known = {(r[0], r[3], r[12]) for r in rows}
    assert all((r[0], r[3], r[12]) in known for r in got) and not any(r.doc_id in (40, 41) for r in got)
    have, want = Counter(), Counter()
    for r in got:
        have[r.doc_id] += len(r.text.split())
    for r in mixing.taken_words(mixing.mix(docs)).collect():
        want[r.doc_id] += r.taken
    assert have == +want
    assert mixing.mixed_documents(docs.limit(0)).collect() == []


def brute_mix(docs, weights=(3, 1, 2), share=1.5, most=2.0):
    """Words taken of each document, slot by slot: the schedule's points, the sources' shuffled words, lap after lap."""
    sizes = Counter()
    for d in docs:
        sizes[d["source"]] += d["size"]
    wanted = mixing.targets(dict(sizes), weights, share, most)
    names = list(wanted)
    quota = [min(int(wanted[s] + 0.5), int(most * sizes[s])) for s in names]
    stream = {s: [] for s in names}
    for d in sorted(docs, key=lambda d: (d["salt"], d["doc_id"])):
        stream[d["source"]] += [d["doc_id"]] * d["size"]
    out = Counter()
    for s, q in zip(names, quota):
        for w in range(q):
            out[stream[s][w % len(stream[s])]] += 1
    return wanted, out


def test_taken_words_by_brute_force(spark):
    rng = np.random.default_rng(3)
    rows = [(i, " ".join(["w"] * int(rng.integers(0, 30))), "abcd"[int(rng.integers(0, 4))]) for i in range(120)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.taken_words(mixing.mix(docs)).collect()
    wanted, taken = brute_mix([{"doc_id": r.doc_id, "source": r.source, "size": len(rows[r.doc_id][1].split()), "salt": r.salt} for r in got])
    by_source = Counter()
    for r in got:
        assert r.target == pytest.approx(wanted[r.source]) and r["size"] == len(rows[r.doc_id][1].split())
        by_source[r.source] += r.taken
    assert {r.doc_id: r.taken for r in got if r.taken} == dict(taken)
    assert all(abs(by_source[s] - wanted[s]) <= 1 for s in wanted)
