import collections
import hashlib
import itertools
import math
import random
import re
import textwrap
import tracemalloc
import zlib
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from vecgraph.llm import bpe, class_lm, crf, decontaminate, entry, language_id, licenses, line_dedup, mtree, near_join, packing, pii, warc
from vecgraph.llm.common import connected_components, materialize
from vecgraph.llm.words import shingles, slices, word_hashes

ODD = [(1, "a b c d e f\nsame line"), (1, "a b c d e f\nsame line"), (2, None), (3, ""), (None, "x"), (None, None), (4, "é " * 40_000), (5, "\n\n  \n")]


def docs(spark, rows=ODD, extra=False):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return df.withColumns({c: F.lit("mine") for c in ("n_lines", "key", "score", "_x", "lang", "id", "row")}) if extra else df


def words(t):
    return re.findall(r"[a-z0-9\x80-\U0010ffff]+", (t or "").lower())


def shingle_set(t):
    w = words(t)
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


# -- words


def test_word_hashes_and_shingles():
    texts = pa.array(["The cat, sat! on the mat", None, "", "x y", "THE CAT sat on the mat", "Été été"])
    h, o = word_hashes(texts)
    assert np.diff(o).tolist() == [6, 0, 0, 2, 6, 2] and (h[o[0] : o[1]] == h[o[4] : o[5]]).all() and h[-1] == h[-2]
    assert np.diff(shingles(h, o)[1]).tolist() == [2, 0, 0, 1, 2, 1]
    assert list(slices(pa.array(["a" * 9, "b", None, "c"]), 5)) == [(0, 1), (1, 4)]


def test_components(spark):
    edges = [(i, i + 1) for i in range(30)] + [(100, 101), (103, 102), (101, 102)]
    got = {r["node"]: r["root"] for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(31)) and {got[i] for i in (100, 101, 102, 103)} == {100}


# -- op1


def test_patterns_equal_the_plain_regexes():
    plain = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def ref(x):
        out = []
        for k, p in plain.items():
            for m in re.finditer(p, x):
                d = re.sub("[^0-9]", "", m[0])
                if (k != "ip" or all(int(z) <= 255 for z in m[0].split("."))) and (k != "card" or (16 <= len(d) <= 19 and pii.luhn(d))) and (k != "phone" or 8 <= len(d) <= 15):
                    out.append((k, *m.span()))
        return out

    r = random.Random(3)
    for _ in range(5000):
        x = "".join(r.choice(["a@", "b.c", "1", "23", "255.", "+1 ", "(555) ", " ", "-", "4111111111111111", "@", ".", "é", "x%", "0"]) for _ in range(r.randint(1, 16)))
        assert sorted(ref(x)) == sorted(pii.base_spans(x)), x


@pytest.fixture(scope="module")
def model():
    return pii.train()


def test_crf_adds_disguised_data_and_leaves_plain_text(model):
    texts = ["mail jane.doe [at] example [dot] com now", "call (555) 123-4567 today", "cards 4111.1111.1111.1111 ok", "host 10[.]0[.]0[.]1 x", 'token = "11acdfb36bb72224148e6160f674b4be45601bff" an', "on 2024-01-15 version 1.2.3 at page 12", "1234 5678 9012 3456", "Licensed under CC BY-NC 4.0.", "The dot is at the end.", "commit 11acdfb36bb72224148e6160f674b4be45601bff ok"]
    got = [[k for k, _, _ in added] for _, added in pii.find(texts, model)]
    assert got[:5] == [["email"], ["phone"], ["card"], ["ip"], ["secret"]] and not any(got[5:])


def test_crf_is_accurate_on_held_out_rows(model):
    rows = pii.example_rows(400, seed=99)
    want = {(i, *s) for i, (_, spans) in enumerate(rows) for s in spans}
    got = {(i, *s) for i, both in enumerate(pii.find([t for t, _ in rows], model)) for spans in both for s in spans}
    assert len(got & want) / len(got) > 0.95 and len(got & want) / len(want) > 0.88


def test_long_addresses_and_long_lines_lose_nothing(model):
    name = "x" * 130
    text = "word " * 20_000 + f"{name} [at] example [dot] com " + "word " * 20_000 + "\n" + "more\n" * 1000 + "call (555) 123-4567 today"
    (_, added), = pii.find([text], model)
    assert [(k, text[a:b]) for k, a, b in added] == [("email", f"{name} [at] example [dot] com"), ("phone", "(555) 123-4567")]
    # passing over lines without a trigger equals decoding every line
    texts = ["\n".join(t for t, _ in pii.example_rows(40, seed)) + "\nplain words only\n\n" for seed in range(5)]
    for t, (base, added) in zip(texts, pii.find(texts, model), strict=True):
        at, every = 0, []
        for line in t.split("\n"):
            x = crf.Line(line, model)
            every += [(k, s + at, e + at) for k, s, e in model.spans(x.tokens, model.decode([x])[0])]
            at += len(line) + 1
        assert added == [x for x in every if not any(x[1] < b and a < x[2] for _, a, b in base) and pii.plausible(x[0], t[x[1] : x[2]])]


def test_viterbi_and_expectations_equal_all_paths():
    r = np.random.default_rng(1)
    model = crf.ShapeCRF(["a"]).fit([("x 1 y", [("a", 2, 3)]), ("22 z", [("a", 0, 2)]), ("b c", [])], steps=5)
    model.emit, model.move = r.normal(size=model.emit.shape), r.normal(size=(3, 3))
    lines = [crf.Line(t, model) for t in ("x 1 y z 1", "22 z x", "b", "")]
    batch = crf.together(lines[:3])
    score, size = model.scores(*batch), np.array([5, 3, 1])
    own, moves, total = model.expected(score, size)
    want_own, want_moves, want_total, start = np.zeros_like(own), np.zeros((3, 3)), 0.0, 0
    for line, n, states in zip(lines, size, model.decode(lines), strict=False):
        paths = list(itertools.product(range(3), repeat=int(n)))
        values = np.array([sum(score[start + i, s] for i, s in enumerate(p)) + model.start_allowed[p[0]] + sum((model.move + model.allowed)[a, b] for a, b in zip(p, p[1:], strict=False)) for p in paths])
        assert tuple(states) == paths[int(values.argmax())]
        w = np.exp(values - values.max())
        want_total += math.log(w.sum()) + values.max()
        for p, x in zip(paths, w / w.sum(), strict=True):
            for i, s in enumerate(p):
                want_own[start + i, s] += x
            for a, b in zip(p, p[1:], strict=False):
                want_moves[a, b] += x
        start += n
    assert np.allclose(own, want_own) and np.allclose(moves, want_moves) and total == pytest.approx(want_total)
    # the gradient of the log of the sums is the expected number of uses of a weight
    key = list(model.features(*batch))[0]
    w, f = 1e-6, int(np.searchsorted(model.keys, key[0]))
    model.emit[f, 1] += w
    assert (model.expected(model.scores(*batch), size)[2] - total) / w == pytest.approx(own[key == key[0], 1].sum(), abs=1e-4)


def test_model_is_stored_by_its_labels(spark, monkeypatch):
    rows = [("call 555 now", [("phone", 5, 8)]), ("no", [])]
    first = pii.model_of(spark, rows)
    monkeypatch.setattr(pii, "train", lambda rows: pytest.fail("trained again"))
    again = pii.model_of(spark, rows)
    assert (again.emit == first.emit).all() and again.shapes == first.shapes


def test_op1_output(spark, sf):
    for r in entry.QUERIES["op1_pii"](spark, sf).collect():
        spans = [s.split(":") for s in r["spans"].split(",") if s]
        assert len(spans) == r["n_spans"] == r["n_email"] + r["n_ip"] + r["n_card"] + r["n_phone"] + r["n_added"]
        assert [(pii.ALL_KINDS.index(k), int(a)) for k, a, _ in spans] == sorted((pii.ALL_KINDS.index(k), int(a)) for k, a, _ in spans)
        if not r["n_added"]:
            assert hashlib.sha256(r["spans"].encode()).hexdigest() == r["base_sha256"]


def test_pii_odd_rows(spark, model):
    rows = [*ODD, (9, "a@b.co 1.2.3.4 é +1 (415) 555-2671")]
    got = pii.detect(docs(spark, rows, True), model=model).collect()
    assert len(got) == len(rows)
    last = next(r for r in got if r["doc_id"] == 9)
    assert [(s["kind"], s["start"], s["end"]) for s in last["spans"]] == [("email", 0, 6), ("ip", 7, 14), ("phone", 17, 34)] and last["_x"] == "mine"
    assert pii.detect(docs(spark, []), model=model).count() == 0


# -- op2


def test_containment_equals_brute_force(spark):
    r = random.Random(5)
    vocab = [f"w{i}" for i in range(400)]
    items = [(i, " ".join(r.choices(vocab, k=r.choice([6, 9, 20, 45])))) for i in range(30)] + [(90, None), (91, "one two")]
    rows = []
    for i in range(120):
        text = " ".join(r.choices(vocab, k=r.choice([5, 300, 3000])))
        if i % 3 == 0:
            own = items[r.randrange(30)][1].split()
            if i % 2:
                own[0] = "changed"
            text = f"{text[: len(text) // 2]} {' '.join(own)} {text[len(text) // 2 :]}"
        rows.append((i, text))
    rows += [(500, None), (501, ""), (502, "One  two!")]
    want = {(d, i) for d, t in rows for i, x in items if shingle_set(x) and len(shingle_set(x) & shingle_set(t)) >= 0.8 * len(shingle_set(x)) - 1e-9}
    left, right = docs(spark, rows, True), spark.createDataFrame(items, "item_id long, text string")
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.contained(left, right).collect()} == want and (502, 91) in want
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.contained(left, right, item_block=7).collect()} == want
    assert {r["doc_id"] for r in decontaminate.flag_contaminated(left, right, item_block=20).where("contaminated").collect()} == {d for d, _ in want}
    assert decontaminate.contained(left, right.where("false")).count() == 0 and decontaminate.contained(docs(spark, []), right).count() == 0


def test_containment_of_repeated_and_very_long_rows(spark):
    item = "the quick brown fox jumps over the lazy dog again today"
    long = "filler words here " * 40_000 + item + " more filler" * 1000
    left = docs(spark, [(1, long), (2, item), (2, item), (3, "nothing")], True)
    right = spark.createDataFrame([(7, item), (7, item)], "item_id long, text string")
    got = sorted((r["doc_id"], r["item_id"]) for r in decontaminate.contained(left, right).collect())
    assert set(got) == {(1, 7), (2, 7)}
    flags = sorted((r["doc_id"], r["contaminated"]) for r in decontaminate.flag_contaminated(left, right).collect())
    assert flags == [(1, True), (2, True), (2, True), (3, False)]


# -- op3


def dedup_reference(rows, least):
    keys = [[x.strip(" \t\n\x0b\x0c\r").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")) for x in (t or "").split("\n")] for _, t in rows]
    n = collections.Counter(k for ks in keys for k in set(ks) if k)
    return [(i, "\n".join(x for x, k in zip((t or "").split("\n"), ks, strict=True) if not (k and n[k] >= least))) for (i, t), ks in zip(rows, keys, strict=True)]


def test_line_dedup_equals_brute_force(spark):
    r = random.Random(1)
    rows = [(i, "\n".join(r.choice(["Same", " same\t", "SAME", f"own {i} {j}", "", "rare", "é", "É"]) for j in range(r.choice([1, 5, 200])))) for i in range(60)] + ODD
    for batches in (1, 4):
        got = line_dedup.dedup_lines(docs(spark, rows, True), 10, batches).collect()
        assert sorted((str(g["doc_id"]), g["kept_text"]) for g in got) == sorted((str(i), t) for i, t in dedup_reference(rows, 10))
    assert "_x" in got[0].asDict() and line_dedup.dedup_lines(docs(spark, [])).count() == 0


def test_runs_compact_and_answer_new_batches(spark, tmp_path):
    store = line_dedup.LineRuns(spark, str(tmp_path), fanout=2, buckets=4)
    for b in range(5):
        store.add(docs(spark, [(b, f"shared\nonly {b}"), (b, "Shared ")]))
    assert sum(map(len, store.levels)) <= 3 and len(store.levels) >= 2
    assert store.frequent(10).count() == 1 and store.frequent(1).count() == 6
    assert store.runs().where("new").count() == 6  # the anti-join counts a key as new once
    fresh = store.new_lines(docs(spark, [(9, "SHARED\nonly 3\nnever seen")]))
    assert [r["line"] for r in fresh.collect()] == ["never seen"]
    # the manifest opens the store again, and it goes on
    again = line_dedup.LineRuns(spark, str(tmp_path), fanout=2)
    assert again.levels == store.levels and again.buckets == 4 and again.frequent(10).count() == 1
    again.add(docs(spark, [(6, "only 6"), (7, "shared")]))
    assert again.frequent(11).count() == 1 and again.runs().where("new").count() == 7
    store.close()
    again.close()


def test_runs_merge_where_they_lie(spark, tmp_path):
    store = line_dedup.LineRuns(spark, str(tmp_path), fanout=8, buckets=4)
    for b in range(2):
        store.add(docs(spark, [(b, f"shared\nonly {b}")]))
    assert "Exchange" not in store.frequent(1)._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    with line_dedup.shuffled_into(spark, 4):
        counted = store._lines(docs(spark, [(9, "a\nb")]), []).groupBy("h1", "h2").count()
        plan = counted.join(store.runs().select("h1", "h2").hint("merge"), ["h1", "h2"], "left_anti")._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    assert "SortMergeJoin" in plan and plan.count("Exchange") == 1  # of the new lines only
    store.close()


def test_common_lines_are_spread(spark):
    rows = [(i, "every\n" + "\n".join(f"{i} {j}" for j in range(3)) + ("\ntwelve" if i < 12 else "")) for i in range(4000)]
    got = line_dedup.dedup_lines(docs(spark, rows)).collect()
    assert {(g["doc_id"], g["kept_text"]) for g in got} == {(i, t.replace("every\n", "").replace("\ntwelve", "")) for i, t in rows}


# -- op4


def test_class_model(spark):
    r = random.Random(2)
    rows = []
    for i in range(300):  # two topics whose words follow each other
        t = "ab"[i % 2]
        rows.append((i, " ".join(f"{t}{r.randrange(40)}{t * 2}" for _ in range(40))))
    rows += [(1000, None), (1001, ""), (1002, "never Seen words"), (1000, None)]
    train = docs(spark, rows[:250])
    model = class_lm.ClassModel.fit(train)
    got = {x["doc_id"]: x for x in model.score(docs(spark, rows, True)).collect()}
    n = collections.Counter(w for _, t in rows[:250] for w in [*(t or "").lower().split(), None])
    total, v = sum(n.values()), len(n)
    for i, t in rows:
        tokens = [*(t or "").lower().split(), None]
        assert got[i]["n_tokens"] == len(tokens) and got[i]["n_known"] == sum(n[w] > 0 for w in tokens)
        assert got[i]["base_score"] == pytest.approx(sum(math.log10((n[w] + 0.5) / (total + 0.5 * (v + 1))) for w in tokens))
    held = [got[i] for i, _ in rows[250:300]]
    assert sum(h["score"] for h in held) > sum(h["base_score"] for h in held)
    # emissions of a class with one unseen word, and the moves out of a class, are probabilities
    assert np.allclose((10**model.log_move).sum(axis=1), 1, atol=1e-6)
    some = [c for c in range(class_lm.CLASSES) if model.class_words[c] > 0]
    counts = {x["h"]: x["n"] for x in model.counts.collect()}
    h = np.array(list(counts), np.int64).view(np.uint64)
    assert len(h) == v and some
    empty = class_lm.ClassModel.fit(docs(spark, []))
    assert empty.score(docs(spark, [(1, "a b"), (2, None)])).count() == 2


def test_exchange_finds_the_groups():
    n = np.zeros((13, 13))
    n[:6, 6:12] = 5
    n[6:12, :6] = 5
    got = class_lm.exchange(n, 2, 1)
    assert len(set(got[:6])) == 1 and len(set(got[6:12])) == 1 and got[0] != got[6] and got[12] == 2


def test_words_outside_the_core_take_classes_by_their_neighbours(spark):
    r = random.Random(3)
    filler = [f"f{i}" for i in range(class_lm.CORE)]
    rows = [(i, " ".join(r.choices(filler, k=400))) for i in range(100)]
    # rare words with one ending, in the settings of two common words
    rows += [(1000 + i, f"{a} x{a} {b} " * 6 + f"{a} {i}{a}qqq {b} {a} {i}{a}qqq {b}") for i in range(60) for a, b in (("one", "two"), ("red", "blue")) for _ in range(2)]
    got = {x["h"]: x["c"] for x in class_lm.ClassModel.fit(docs(spark, rows)).counts.collect()}
    assert len(got) > class_lm.CORE
    named = {}
    for a in ("one", "red"):
        h, _, _ = class_lm.token_stream(pa.array([" ".join(f"{i}{a}qqq" for i in range(60))]))
        named[a] = {got[int(x)] for x in h[:-1].view(np.int64)}
    assert not named["one"] & named["red"]


def test_words_are_looked_up_without_sorting_the_tokens(monkeypatch):
    r = np.random.default_rng(0)
    spread = lambda n: r.integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2)
    for keys in (spread(0), spread(1), np.append(spread(5000), [class_lm.END, np.uint64(2**64 - 1)]), np.arange(300, dtype=np.uint64)):
        look, asked = class_lm.Lookup(keys), np.concatenate([keys, spread(3000), keys[:50], np.array([0, 7, 2**64 - 1], np.uint64)])
        rows = {int(k): i for i, k in enumerate(keys)}
        with monkeypatch.context() as m:
            m.setattr(class_lm.np, "unique", lambda *a, **k: pytest.fail("tokens are sorted"))
            got = look.find(asked)
        assert got.tolist() == [rows.get(int(h), -1) for h in asked]


def test_tokens_are_hashed_in_pieces_of_bounded_memory():
    some = [None, "", "a b", "x" * 40, *(f"Word{i} other{i % 7} the end" for i in range(70_000)), None, "last"]
    texts = pa.array(some)
    class_lm.token_stream(texts[:1000])  # the table of powers is made once
    tracemalloc.start()
    h, tail, offsets = class_lm.token_stream(texts)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert texts.nbytes > 1 << 20 and peak < 64 * (1 << 18) + 64 * len(h)
    for at in (0, 2, 3, 9_999, 60_000, len(some) - 1):
        one, end, _ = class_lm.token_stream(texts[at : at + 1])
        assert (h[offsets[at] : offsets[at + 1]] == one).all() and (tail[offsets[at] : offsets[at + 1]] == end).all()
    assert offsets[-1] == len(h) and len(offsets) == len(some) + 1


def test_sums_of_contexts_run_one_python_process_for_a_task(spark, monkeypatch):
    plans = []
    monkeypatch.setattr(class_lm, "materialize", lambda df, name: plans.append(df._jdf.queryExecution().executedPlan().toString()) or materialize(df, name))
    class_lm.ClassModel.fit(docs(spark, [(1, "a b a b"), (2, "b a c")]))
    assert plans
    for plan in plans:
        below = [line for line in plan.splitlines() if line.strip(" +-:*()0123456789")]
        assert not any("MapInArrow" in a and "MapInArrow" in b for a, b in zip(below, below[1:]))


def test_class_scores_equal_a_plain_sum(spark, monkeypatch):
    monkeypatch.setattr(class_lm, "COMMON", 40)  # most words stand outside the table
    r = random.Random(5)
    texts = [" ".join(f"w{int(r.paretovariate(0.7)) % 900}" for _ in range(r.randint(0, 40))) for _ in range(300)]
    train, held = texts[:250], texts[250:] + ["w1 never seen", None, "", "w2 " * 70_000, "w2 w2", "w2 w2"]
    model = class_lm.ClassModel.fit(docs(spark, list(enumerate(train))))
    toks = lambda t: [*(t or "").lower().split(), None]
    h = lambda w: class_lm.END if w is None else class_lm.token_stream(pa.array([w]))[0][0]
    known = {x["h"]: x for x in model.counts.collect()}
    seen = collections.Counter(w for t in train for w in toks(t))
    assert {int(h(w).view(np.int64)): n for w, n in seen.items()} == {k: x["n"] for k, x in known.items()}
    assert len(model.common_n) <= 41 < len(known)

    def cls(w):
        x = known.get(int(h(w).view(np.int64)))
        return x["c"] if x else int(model.place(*class_lm.token_stream(pa.array([w]))[:2])[1][0])

    c = class_lm.CLASSES + 1
    moves, mass, types = np.zeros((c, c)), np.zeros(c), np.zeros(c)
    for t in train:
        s = [cls(w) for w in toks(t)]
        for a, b in zip([class_lm.CLASSES, *s[:-1]], s, strict=True):
            moves[a, b] += 1
    for w, n in seen.items():
        mass[cls(w)] += n
        types[cls(w)] += 1
    prior = (moves.sum(axis=0) + 0.5) / (moves.sum() + 0.5 * c)
    move = np.log10((moves + class_lm.SMOOTHING * prior) / (moves.sum(axis=1, keepdims=True) + class_lm.SMOOTHING))
    got = {x["doc_id"]: x for x in model.score(docs(spark, list(enumerate(held))), "text").collect()}
    for i, t in enumerate(held):
        s = [cls(w) for w in toks(t)]
        want = sum(move[a, b] for a, b in zip([class_lm.CLASSES, *s[:-1]], s, strict=True)) + sum(math.log10((seen[w] + 0.5) / (mass[k] + 0.5 * (types[k] + 1))) for w, k in zip(toks(t), s, strict=True))
        assert got[i]["score"] == pytest.approx(want, rel=1e-9) and got[i]["n_tokens"] == len(s)


def test_reassign_raises_the_likelihood():
    r = np.random.default_rng(5)
    n = r.integers(0, 4, (9, 9)) + 6 * (np.arange(9)[:, None] % 2 != np.arange(9) % 2)
    of = np.array([0, 0, 0, 0, 1, 1, 1, 1, 2])
    one = np.eye(3)[of]
    pairs = one.T @ n @ one
    for w in range(8):  # one word alone: the choice is that of moving it and counting again
        sums = np.concatenate([n[w] @ one, n[:, w] @ one]).astype(np.int64)
        key = np.flatnonzero(sums)
        to = class_lm.reassign(pairs, of[[w]], np.zeros(len(key), np.int64), key, sums[key])[0]
        if to != of[w]:
            moved = np.where(np.arange(9) == w, to, of)
            assert class_lm.likelihood(np.eye(3)[moved].T @ n @ np.eye(3)[moved]) > class_lm.likelihood(pairs)


# -- op5


def test_licenses(spark):
    rows = [(1, "Released under the MIT License."), (2, "text\n  RELEASED UNDER THE MIT LICENCE!!\nmore"), (3, "we talk of the MIT license here"), (4, "Copyright (c) 2020 A. Person\n\n" + licenses.NOTICES[12][1].upper().replace(", ", ",\n")), (5, "Licensed under the Apache License, v 2.0"), (2, "text\n  RELEASED UNDER THE MIT LICENCE!!\nmore"), *ODD]
    for fragments in (None, licenses.anchors()):
        got = sorted((r["doc_id"], ",".join(r["licenses"]), r["whole_text"]) for r in licenses.scan_licenses(docs(spark, rows, True), licenses.known_licenses(spark), fragments=fragments).collect())
        assert got == [(1, "MIT", True), (2, "MIT", False), (2, "MIT", False), (4, "MIT", True), (5, "Apache-2.0", True)]


def test_licenses_inside_documents(spark):
    named = dict(licenses.NOTICES)
    mit, bsd, gpl = named["MIT"], named["BSD-3-Clause"], named["GPL-3.0-or-later"]
    wrapped = lambda t, lead: "\n".join(lead + x for x in textwrap.wrap(t, 60))
    rows = [
        (1, "MIT License\n\nCopyright (c) 2020 A. Person\n\n" + wrapped(mit, "")),
        (2, "int main;\n/*\n" + wrapped(gpl, " * ") + "\n */\ncode"),
        (3, "intro\n\n" + bsd.replace("1. ", "* ").replace("2. ", "* ").replace("3. ", "* ") + "\n\nand then\n" + wrapped(mit, "# ") + "\n" + mit),
        (4, mit[:-30] + " something else at the end of it"),
        (5, "word " * 200_000 + mit),
        (6, "The BSD 3-Clause License\nCopyright 2001 by B\nAll rights reserved.\n\n" + bsd),
        (7, "see " + mit[:-1] + "x"),
    ]
    got = sorted((r["doc_id"], ",".join(r["licenses"]), r["n_units"], r["whole_text"]) for r in licenses.scan_licenses(docs(spark, rows), licenses.known_licenses(spark), fragments=licenses.anchors()).collect())
    # a licence on one line is a line and a stretch; one that fills a document is its whole and a stretch
    assert got == [(1, "MIT", 2, True), (2, "GPL-3.0-or-later", 1, False), (3, "BSD-3-Clause,MIT", 4, False), (5, "MIT", 1, False), (6, "BSD-3-Clause", 2, True)]
    assert licenses.scan_licenses(docs(spark, []), licenses.known_licenses(spark)).count() == 0


@pytest.mark.skipif(not Path("/usr/share/common-licenses/GPL-3").exists(), reason="needs the public licence texts of the system")
def test_digests_of_long_licenses(spark):
    names = {"Apache-2.0": "Apache-2.0", "GPL-2.0": "GPL-2", "GPL-3.0": "GPL-3", "LGPL-3.0": "LGPL-3", "MPL-2.0": "MPL-2.0", "CC0-1.0": "CC0-1.0"}
    rows = [(i, "preface\n" + Path("/usr/share/common-licenses", f).read_text()) for i, f in enumerate(names.values())]
    got = {r["doc_id"]: r["licenses"] for r in licenses.scan_licenses(docs(spark, rows), licenses.known_licenses(spark), fragments=licenses.anchors()).collect()}
    assert all(n in got[i] for i, n in enumerate(names))


# -- op6


def brute_top(rows, k):
    ok = [(i, [math.floor(1024 * x) for x in v]) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for n, (q, v) in enumerate(ok):
        if q % 100 == 0:
            best = sorted((-sum(a * b for a, b in zip(v, w, strict=True)), i) for m, (i, w) in enumerate(ok) if m != n and len(w) == len(v))[:k]
            out += [(q, r + 1, i, -s) for r, (s, i) in enumerate(best)]
    return sorted(out)


@pytest.mark.parametrize("same", [False, True])
def test_mtree_equals_brute_force(spark, monkeypatch, same):
    r = np.random.default_rng(4)
    rows = [(i, [float(x) for x in ([0.25] * 6 if same and i % 3 else r.normal(size=6))]) for i in range(700)]
    rows += [(900, None), (1000, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (1100, [float("nan")] * 6), (1200, [float("inf")] * 6), (1300, []), (1301, [0.0] * 6), (None, [1.0] * 6)]
    # components beyond 2^16, repeated ids and repeated rows, another length
    rows += [(300, rows[300][1]), (300, rows[300][1]), (300, [9.0] * 6), (7, rows[7][1]), (1400, [70_000.5, -(2.0**17), 0.1, 0.2, 0.3, 0.4]), (1401, [2.0**22, 0.5, 0.5, 0.5, 0.5, 0.5]), (1402, [-(2.0**22), 1.0, 0.0, 0.0, 0.0, 1.0]), (1500, [1.5, 2.5]), (1501, [2.5, 1.5])]
    df = spark.createDataFrame(rows, "vec_id long, v array<double>").withColumns({c: F.lit("mine") for c in ("score", "rank", "id", "q", "tree", "dim")})
    monkeypatch.setattr(mtree, "TREE_ROWS", 150)
    q = df.where("vec_id % 100 = 0").select(F.col("vec_id").alias("query_id"), mtree.scaled("v").alias("v")).where("v is not null")
    got = mtree.search(mtree.index(df, "vec_id", "v"), q, 5)
    assert sorted((x["query_id"], x["rank"], x["vec_id"], x["score"]) for x in got.collect()) == brute_top(rows, 5)
    assert mtree.search(mtree.index(df.where("false"), "vec_id", "v"), q.where("false")).count() == 0


def test_scores_beyond_a_long_are_exact_or_an_error(spark):
    big = 2.0**45 + 2.0**-6
    rows = [(100, [big, 1.0]), (1, [-big, 3.0]), (2, [2.0**-8, 1.0]), (3, [2.0**-9, 5.0]), (4, [2.0**-9, 4.0])]
    df = spark.createDataFrame(rows, "vec_id long, v array<double>")
    run = lambda k: [(x["rank"], x["vec_id"], x["score"]) for x in mtree.search(mtree.index(df, "vec_id", "v"), df.where("vec_id = 100").select(F.col("vec_id").alias("query_id"), mtree.scaled("v").alias("v")), k).orderBy("rank").collect()]
    assert run(3) == [(r, i, s) for r, (_, i, s) in enumerate(sorted((-x, i, x) for i, x in ((i, sum(math.floor(1024 * a) * math.floor(1024 * b) for a, b in zip(v, rows[0][1], strict=True))) for i, v in rows[2:])), 1)]
    with pytest.raises(Exception, match="does not fit a long"):
        run(4)
    with pytest.raises(Exception, match="beyond 1e150"):
        mtree.index(spark.createDataFrame([(1, [1e200])], "vec_id long, v array<double>"), "vec_id", "v")


def test_mtree_spares_computations():
    import pandas as pd

    r = np.random.default_rng(6)
    x = np.concatenate([r.integers(-60, 60, (400, 4)) + c for c in (0, 4000, -4000, 9000)])
    t = mtree.Tree(pd.DataFrame(mtree.build(np.arange(len(x)), x, 0, page=32)))
    for q in (x[5], x[900], x[-1]):
        want = sorted((-int(s), i) for i, s in enumerate(x @ q))[:10]
        assert [(-s, i) for s, i, _ in t.top(-1, q, 10)] == want
    assert t.computed < 3 * len(x)


# -- op7


def test_language_id(spark):
    r = random.Random(8)
    parts = {"aa": ["ka", "lo", "mi", "tu"], "bb": ["shr", "eth", "ing", "ou"], "cc": ["ñez", "ción", "ó", "ra"]}
    make = lambda k: " ".join("".join(r.choices(parts[k], k=3)) for _ in range(40))
    rows = [(i, make(k), k) for i in range(200) for k in [r.choice(list(parts))]]
    df = spark.createDataFrame([*rows[:150], (900, None, "aa"), (901, "kalomi", None)], "doc_id long, text string, lang string")
    m = language_id.LanguageFilters.fit(df)
    test = spark.createDataFrame([*rows[150:], (1, None, "x"), (2, "12 !?", "x"), (3, "", "x"), (4, "zq", "x")], "doc_id long, text string, lang string").withColumn("lang_pred", F.lit("clash"))
    got = m.predict(test).collect()
    assert np.mean([g["lang"] == g["lang_pred"] for g in got if g["doc_id"] >= 150]) > 0.98
    assert {g["doc_id"]: g["lang_pred"] for g in got if g["doc_id"] < 4} == {1: "und", 2: "und", 3: "und"}
    assert all(0 <= g["score"] <= 1 for g in got) and next(g for g in got if g["doc_id"] == 4)["lang_pred"] in parts
    assert language_id.LanguageFilters.fit(df.where("false")).predict(test).where("lang_pred <> 'und'").count() == 0
    many = language_id.LanguageFilters([f"l{i:03d}" for i in range(70)], [1.0] * 70, [(69, 12345), (3, 12345)])
    assert many.bits.shape[0] == 2 and many.bits.dtype == np.uint64


def test_language_of_repeated_and_very_long_rows(spark):
    rows = [(i, " ".join(["kalo mitu", "shreth ingou"][i % 2] for _ in range(30)), "ab"[i % 2]) for i in range(40)]
    df = spark.createDataFrame([*rows, rows[0], rows[0]], "doc_id long, text string, lang string")
    m = language_id.LanguageFilters.fit(df)
    test = spark.createDataFrame([(1, "kalo mitu " * 50_000, None), (2, "shreth ingou", None), (2, "shreth ingou", None)], "doc_id long, text string, lang string")
    assert sorted((r["doc_id"], r["lang_pred"]) for r in m.predict(test).collect()) == [(1, "a"), (2, "b"), (2, "b")]


# -- op8


def test_word_encoder_equals_the_library():
    e = bpe.WordEncoder(packing.default_tokenizer())
    texts = ["It's Don'T ÀÉ naïve, ﬁ İx 12,5 ... a.b ,x x,, ×÷ a×b", "ß ẞ Σας ", None, "", "   ", "a b c\x1cd", "x" * 100 + "!", "Éa. ÉA. éa.", "é Ét́", "wh,*** $$$ AKIA7Q== token=\"9f\"", "日本語 текст"]
    for t in (texts, [*texts, "<|endoftext|> a<|startoftext|>b"]):
        ids, cuts, _, _ = e.encode(pa.array(t, pa.string()), 2)
        want = e.tokenizer.encode_batch([x or "" for x in t], add_special_tokens=False)
        assert [ids[a:b].tolist() for a, b in zip(cuts[:-1], cuts[1:], strict=True)] == [[*w.ids, 2] for w in want]


def test_packing_round_trip(spark):
    r = random.Random(3)
    rows = [(i, " ".join(r.choice(["alpha", "beta,", "Gamma", "δ", "qz7"]) + str(r.randrange(50)) for _ in range(r.choice([3, 40, 900, 6000])))) for i in range(80)] + ODD
    got = packing.pack(docs(spark, rows, True), shard_docs=30).collect()
    e = bpe.WordEncoder(packing.default_tokenizer())
    ids = collections.defaultdict(list)
    for i, t in rows:
        ids[i].append(e.encode(pa.array([t], pa.string()), 2)[0])
    total = sum(len(x) for xs in ids.values() for x in xs)
    assert sum(g["length"] for g in got) == total
    for g in got:
        assert any(g["doc_tokens"] == len(x) and zlib.crc32(x[g["start"] : g["start"] + g["length"]].astype("<u4").tobytes()) == g["ids_crc32"] for x in ids[g["doc_id"]])
    seqs = collections.defaultdict(list)
    for g in got:
        seqs[g["sequence_id"]].append((g["offset"], g["length"]))
    sizes = []
    for s in seqs.values():
        at = 0
        for o, n in sorted(s):
            assert o == at
            at += n
        sizes.append(at)
    assert max(sizes) <= 4096
    padded = sum(n if n & (n - 1) == 0 else 4096 for n in sizes)
    assert total / padded > 0.9
    assert packing.pack(docs(spark, [])).count() == 0


def test_bm25_scores_and_statistics_equal_a_plain_sum(spark):
    r = random.Random(8)
    texts = [" ".join(f"w{int(r.paretovariate(0.8)) % 300}" for _ in range(r.randint(1, 60))) for _ in range(120)] + ["w1 " * 70_000 + "w2 w2", "w1 w2", None, ""]
    rows = packing.measured(docs(spark, list(enumerate(texts))), "doc_id", "text", packing.default_tokenizer(), 2)
    idf, mean = packing._statistics(rows)
    got = {x["id"]: x for x in rows.collect()}
    order = sorted(got)
    column = lambda c, kind: [np.frombuffer(got[i][c], kind) for i in order]
    shard = packing.Shard(column("terms", np.uint32), column("times", np.uint16), idf, mean)
    e = packing.encoder(packing.default_tokenizer())
    words = []
    for t in texts:
        h = e.encode(pa.array([t], pa.string()), 2)[2]
        words.append(collections.Counter((h >> np.uint64(32)).tolist()))
    group = lambda t: t >> (32 - packing.GROUPS)
    df = collections.Counter(group(t) for w in words for t in w)
    length = [sum(w.values()) for w in words]
    assert mean == pytest.approx(sum(length) / len(texts)) and max(length) > 70_000
    for seed in (0, 5, 120, 121, 122):
        want = [sum(math.log1p((len(texts) - df[group(t)] + 0.5) / (df[group(t)] + 0.5)) * w[t] * 2.2 / (w[t] + 1.2 * (0.25 + 0.75 * n / mean)) for t in words[seed] if t in w) for w, n in zip(words, length, strict=True)]
        assert np.allclose(shard.scores(seed), want)


def test_windows_take_the_best_neighbours_first():
    idf = np.ones(1 << packing.GROUPS)
    terms = [np.array(x, np.uint32) << np.uint32(20) for x in ([1, 2, 3, 4], [9, 10, 11], [1, 2, 3, 5], [1, 7, 8])]
    sizes = np.array([2000, 1000, 1500, 1800])
    out = packing.pack_shard(sizes, packing.Shard(terms, [np.ones(len(t), np.uint16) for t in terms], idf, 4.0))
    assert [p[0] for p in out[0]] == [0, 2, 3] and sum(p[2] for p in out[0]) <= 4096  # most shared words first, then the cut one


def test_crc_algebra():
    t = packing._operators()
    ids = np.random.default_rng(0).integers(0, 50_000, 333).astype("<u4")
    parts = np.array([zlib.crc32(ids[i : i + 64].tobytes()) for i in range(0, 333, 64)], np.uint32)
    assert packing.joined_crc(parts, (333 - 1) % 64 + 1, t) == zlib.crc32(ids.tobytes())


# -- op9


def test_chunking_and_segments():
    body = bytes(range(256)) * 40
    assert warc.unchunked(warc.chunked(body, 7)) == (body, True)
    assert not warc.unchunked(warc.chunked(body)[:-9])[1] and warc.unchunked(b"5;x=y\r\nhello\r\n0\r\nT: 1\r\n\r\n") == (b"hello", True)
    records = list(warc.page_records("<urn:x>", 7, "http://a/\r\nb", body, None, 1000))
    parsed = [p for r in records for p in warc.parse(r)]
    assert len(parsed) == len(records) > 5 and [int(f["warc-segment-number"]) for f, _ in parsed] == list(range(1, len(parsed) + 1))
    assert int(parsed[-1][0]["warc-segment-total-length"]) == sum(len(b) for _, b in parsed)


def test_warc_round_trip(spark, tmp_path):
    big = "é<p>" * 30_000 + "\r\n\r\nWARC/1.1\r\n"
    rows = [(1, "u", "x" * 1000), (5, "u", "x" * 1000), (3, None, "x" * 1000), (2, "u", "small"), (4, "u", "small"), (6, "u", None), (7, "u", ""), (8, "u", big), (9, "u", big + "!"), (8, "u", big), (None, "u", "y" * 2000), (10, "u", "y" * 2000), (None, "u", "z" * 1000)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("type", F.lit("clash"))
    warc.write(df, str(tmp_path / "a"), segment=3000, per_file=5)
    got = warc.read(spark, str(tmp_path / "a")).collect()
    assert len(got) == len(rows) and all(g["intact"] for g in got)
    want = []
    for i, _, h in rows:
        b = (h or "").encode()
        ids = [j for j, _, x in rows if (x or "") == (h or "") and j is not None]
        first = max(ids, default=None)
        revisit = len(b) >= 1000 and first is not None and i != first
        want.append((i, len(b), hashlib.sha1(b).hexdigest(), "revisit" if revisit else "response", first if revisit else None))
    key = lambda x: tuple(map(str, x))
    assert sorted(((g["page_id"], g["payload_bytes"], g["payload_digest"], g["record_type"], g["refers_to"]) for g in got), key=key) == sorted(want, key=key)


def test_warc_of_an_empty_table(spark, tmp_path):
    df = spark.createDataFrame([], "page_id long, url string, html string")
    warc.write(df, str(tmp_path / "none"))
    assert warc.read(spark, str(tmp_path / "none")).count() == 0


def test_lost_segment_is_reported(spark, tmp_path):
    (tmp_path / "b").mkdir()
    records = list(warc.page_records("<urn:x>", 7, "u", b"abc" * 5000, None, 1000))
    (tmp_path / "b" / "x.warc").write_bytes(b"".join(records[:3] + records[4:]))
    assert [g["intact"] for g in warc.read(spark, str(tmp_path / "b")).collect()] == [False]


# -- op10


def near_reference(rows, t=0.8):
    sets = [shingle_set(x) or {("",)} for _, x in rows]
    links = [0] * len(rows)
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            n = len(sets[i] & sets[j])
            if n >= t * (len(sets[i]) + len(sets[j]) - n) - 1e-9:
                links[i] += 1
                links[j] += 1
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return links, [find(i) for i in range(len(rows))]


def test_near_join_equals_brute_force(spark, monkeypatch):
    r = random.Random(12)
    vocab = [f"v{i}" for i in range(500)]
    rows = []
    for g in range(25):
        base = r.choices(vocab, k=r.choice([6, 40, 150]))
        for _ in range(r.choice([1, 2, 6, 30])):
            own = list(base)
            for _ in range(r.choice([0, 0, 1, 2, 4])):
                own[r.randrange(len(own))] = r.choice(vocab)
            rows.append((len(rows), " ".join(own)))
    rows += [(2000, None), (2001, ""), (2002, "two words"), (2003, "TWO  words!")]
    links, root = near_reference(rows)
    monkeypatch.setattr(near_join, "TILE", (8, 8, 1))  # runs over several tiles
    got = {x["doc_id"]: x for x in near_join.near_classes(docs(spark, rows, True)).collect()}
    assert [got[i]["n_links"] for i, _ in rows] == links
    assert [got[i]["class_id"] for i, _ in rows] == [rows[k][0] for k in root]
    kept = near_join.keep_one(docs(spark, rows, True))
    assert sorted(x["doc_id"] for x in kept.collect()) == sorted({rows[k][0] for k in root}) and kept.columns == docs(spark, rows, True).columns


def test_forest_meets_each_pair_once_at_its_greatest_depth():
    r = np.random.default_rng(3)
    sig = r.integers(0, 2, (60, 4, 5)).astype(np.uint16)
    labels = near_join.prefixes(pa.array([x.tobytes() for x in sig], pa.binary()), 4, 5, 2)
    side = np.arange(60) % 2
    for cross in (False, True):
        seen = {}
        for tree in range(4):
            for a, b, same in near_join.tiles(side, cross):
                d = near_join.pair_depths(labels, tree, a, b, same, 2)
                for x, y in zip(*np.nonzero(d), strict=True):
                    assert seen.setdefault(frozenset((int(a[x]), int(b[y]))), (int(d[x, y]), tree)) == (d[x, y], tree)
        for i in range(60):
            for j in range(i):
                if not cross or side[i] != side[j]:
                    common = [next((k for k in range(5) if sig[i, t, k] != sig[j, t, k]), 5) for t in range(4)]
                    assert seen.get(frozenset((i, j))) == ((max(common), common.index(max(common))) if max(common) >= 2 else None)


def test_recall_estimate_shortens_until_the_target():
    assert near_join.recall({}, 0.8, 8, 16) == 0 and near_join.recall({1000: 10**6}, 0.8, 8, 16) > 0.9999
    few, many = near_join.recall({800: 10}, 0.8, 3, 16), near_join.recall({800: 10**6}, 0.8, 3, 16)
    assert few < many and near_join.recall({800: 10**6}, 0.8, 8, 16) < 0.95 < 0.9999 < many


def test_near_join_odd_rows(spark):
    got = near_join.near_classes(docs(spark, ODD, True)).collect()
    assert len(got) == len(ODD) and near_join.keep_one(docs(spark, ODD)).count() == 4
    assert near_join.near_classes(docs(spark, [])).count() == 0 and near_join.keep_one(docs(spark, [])).count() == 0


def test_near_join_keeps_classes_apart_that_share_an_id(spark):
    one, two = " ".join(f"a{i}" for i in range(40)), " ".join(f"b{i}" for i in range(40))
    rows = [(1, one), (1, two), (2, two + " more"), (None, "x y z"), (None, "X, y z"), (None, "p " * 3 + one.replace("a", "c")), (None, one.replace("a", "c"))]
    kept = [x["text"] for x in near_join.keep_one(docs(spark, rows)).collect()]
    assert len(kept) == 4 and one in kept and two in kept
    got = near_join.near_classes(docs(spark, rows)).collect()
    assert len({x["class_key"] for x in got}) == 4 and {x["class_id"] for x in got} == {1, None}


def test_prefix_is_shortened_to_the_target():
    assert near_join.prefix_length(0.8) == 3 and near_join.prefix_length(0.8, trees=100) > 3 and near_join.prefix_length(0.5, target=0.999999) == 1
