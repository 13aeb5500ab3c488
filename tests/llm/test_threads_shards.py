"""Quotation linking and sharding against plain Python."""

import json
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from temporal_rules.llm import chat_threads as ct
from temporal_rules.llm import shard_table as st

MAIL = "I agree with this.\nReally.\n\nOn Monday, Ann wrote:\n> The meeting is at noon. Bring the\n> red folder!\n>> Who comes?\n> > And when?\nFine with me."


def test_levels():
    own, quotes = ct.split_levels(MAIL)
    assert own == "I agree with this.\nReally.\n\nFine with me."
    assert quotes == [(1, "The meeting is at noon. Bring the\nred folder!"), (2, "Who comes?\nAnd when?")]
    assert ct.sentences("The  meeting is at NOON. Bring the\nred folder!") == ["the meeting is at noon", "bring the red folder"]
    assert ct.split_levels(None) == ("", []) and ct.split_levels("a > b") == ("a > b", [])


def brute(rows):
    info = {(c, t): ct.split_levels(x) for c, t, _, x in rows}
    own = {}
    for k, (body, _) in sorted(info.items()):
        for s in ct.sentences(body):
            own.setdefault((k[0], s), k)
            own.setdefault(s, k)
    parent, ahead = {}, set()
    before = {k: max((q for q in info if q[0] == k[0] and q[1] < k[1]), default=None) for k in info}
    for k, (_, quotes) in info.items():
        votes = Counter()
        for level, p in quotes:
            for s in ct.sentences(p):
                here, first = own.get((k[0], s)), own.get(s)
                if here and here < k:
                    votes[level, here] += 1
                elif first and (first < k or first[0] > k[0]):
                    votes[level, first] += 1
        best = max(votes, key=lambda q: (-q[0], q[1][0] <= k[0], votes[q], q[1])) if votes else None
        parent[k] = best[1] if best else before[k]
        if best and best[1][0] > k[0]:
            ahead.add(k)

    def ends(k):
        for _ in range(len(info) + 1):
            if k is None:
                return True
            k = parent[k]
        return False

    for k in [k for k in ahead if not ends(k)]:
        parent[k] = before[k]
    out = {}
    for k in info:
        root, depth = k, 0
        while parent[root] is not None:
            root, depth = parent[root], depth + 1
        out[k] = (info[k][0], parent[k], root, depth)
    return out


def test_threads(spark):
    rng = random.Random(8)
    rows = []
    for c in range(12):
        said = []
        for t in range(rng.randrange(1, 9)):
            lines = [f"Point {rng.randrange(4)} of {c}. It is so." if rng.random() < 0.8 else "Hello."]
            for q in rng.sample(said, min(len(said), rng.randrange(3))):
                lines += ["", "> " + q.replace(". ", ".\n> ")]
            if rows and rng.random() < 0.2:
                lines += ["> " + rng.choice(rows)[3].split("\n")[0].lstrip("> ")]
            if rng.random() < 0.15:
                lines += [f"> Point {rng.randrange(4)} of {rng.randrange(12)}."]
            if rng.random() < 0.15:
                lines += ["> nobody said this", f">> Point {rng.randrange(4)} of {rng.randrange(12)}."]
            text = "\n".join(lines)
            said.append(lines[0])
            rows.append((c, t, rng.choice(["user", "assistant"]), text))
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = ct.threads(df).collect()
    want = brute(rows)
    assert len(got) == len(rows)
    for r in got:
        body, parent, root, depth = want[r.conv_id, r.turn]
        assert (r.body, r.depth, (r.thread_conv, r.thread_turn)) == (body, depth, root)
        assert ((r.parent_conv, r.parent_turn) if r.parent_conv is not None else None) == parent
    assert any(r.parent_conv is not None and r.parent_conv > r.conv_id for r in got)
    assert any(r.by_quote for r in got) and any(r.thread_conv != r.conv_id for r in got)
    chats = ct.conversations(df, most=3).collect()
    assert sum(len(json.loads(x.chat)) for x in chats) == len(rows)
    by = {}
    for r in sorted(got, key=lambda r: r.place):
        by.setdefault((r.thread_conv, r.thread_turn), []).append(r.body)
    for k, bodies in by.items():
        parts = sorted([x for x in chats if (x.thread_conv, x.thread_turn) == k], key=lambda x: x.part)
        assert [m["content"] for x in parts for m in json.loads(x.chat)] == bodies


def test_threads_odd_rows(spark):
    df = spark.createDataFrame([(1, 0, "user", None, 5), (1, 1, None, "", 5), (None, 3, "user", "x", 5), (1, 2, "user", "word " * 50_000, 5), (1, 2, "user", "> word", 5)], "conv_id long, turn long, role string, text string, depth int")
    got = ct.threads(df).collect()
    assert len(got) == 5 and {r.depth for r in got if r.turn == 2} == {2} and [r.place for r in got if r.conv_id is None] == [None]
    assert ct.threads(df.where(F.lit(False))).collect() == []


def test_table_is_even_and_stable():
    names = [f"shard-{i}" for i in range(13)]
    a = st.fill_table(names, 4099)
    shares = Counter(a.tolist())
    assert max(shares.values()) - min(shares.values()) <= 1 and len(shares) == 13
    b = st.fill_table(names[:-1], 4099)
    moved = sum(x != y for x, y in zip(a.tolist(), b.tolist()) if x != 12)
    assert moved < 0.1 * 4099
    again = st.fill_table(names[::-1], 4099)
    assert [names[x] for x in a] == [names[::-1][x] for x in again]
    for bad in ([], ["a", "a"]):
        with pytest.raises(ValueError):
            st.fill_table(bad, 7)
    with pytest.raises(ValueError):
        st.fill_table(["a"], 8)


def test_turns_by_definition():
    names, size = ["b", "a", "c"], 11
    order = sorted(names)
    prefs = {n: [(st._hash(n, b"offset") + k * (st._hash(n, b"step") % (size - 1) + 1)) % size for k in range(size)] for n in names}
    assert all(sorted(p) == list(range(size)) for p in prefs.values())
    taken, turn = {}, 0
    while len(taken) < size:
        n = order[turn % 3]
        taken[next(s for s in prefs[n] if s not in taken)] = n
        turn += 1
    assert [names[i] for i in st.fill_table(names, size)] == [taken[s] for s in range(size)]


def test_placement(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet").withColumn("shard", F.lit(1))
    names = [f"s{i}" for i in range(5)]
    got = st.place(docs, names, ["doc_id"], 1009)
    rows = got.collect()
    table = st.fill_table(names, 1009)
    assert len(rows) == docs.count() and all(r.shard == names[table[r.slot]] for r in rows)
    assert "BroadcastHashJoin" in got._jdf.queryExecution().executedPlan().toString()
    st.write_shards(docs.drop("shard"), str(tmp_path / "out"), names, ["doc_id"], 2)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.count() == len(rows) and {r.shard for r in back.select("shard").distinct().collect()} == set(names)
    odd = spark.createDataFrame([(None, "a"), (1, None), (1, "b")], "doc_id long, text string")
    assert len({r.shard for r in st.place(odd, names, ["doc_id"]).where("doc_id = 1").collect()}) == 1 and st.place(odd, names, ["doc_id"]).count() == 3
    assert st.place(odd.limit(0), names, ["doc_id"]).collect() == []


def test_circles_of_quotes_are_cut(spark):
    rows = [(1, 0, "user", "Alpha is here.\n> Beta is here."), (2, 0, "user", "Beta is here.\n> Alpha is here."), (0, 0, "user", "Gamma.\n> Beta is here."), (3, 0, "user", "Delta.\n> unknown words\n>> Alpha is here.")]
    got = {r.conv_id: r for r in ct.threads(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert (got[2].parent_conv, got[1].parent_conv, got[3].parent_conv) == (1, None, 1)
    assert got[0].parent_conv is None and got[3].thread_conv == got[2].thread_conv == 1
