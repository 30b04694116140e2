"""Training-data operators against brute force, with nulls, empty and long texts, ties, repeated rows, empty tables, extra columns."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest

from graphrefresh.llm import bpe, chat, decontaminate, grading, katz, lengths, mixing, near_dup, quality, repeats, token_files
from graphrefresh.llm.common import work_path
from graphrefresh.llm.oracles import ORACLES
from graphrefresh.llm.queries import QUERIES
from tests.conftest import SF, rows_of, sql_rows

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, rep long, content string, line_no string"


def word(rng):
    return "".join(rng.choice("abcdeéß") for _ in range(rng.randint(1, 7)))


def texts(seed=3):
    rng = random.Random(seed)
    base = [" ".join(word(rng) for _ in range(120)) for _ in range(6)]
    out = [None, "", "   \n\t", "abc", "x" * 399, "x" * 400, "y" * 1500, "ab" * 900, "one two three four", base[3], base[3], base[3], " ".join(["long"] * 30_000)]
    for _ in range(25):
        a = rng.choice(base)
        k, n = rng.randint(0, len(a) - 300), rng.randint(280, 900)
        out.append(" ".join(word(rng) for _ in range(rng.randint(0, 60))) + "\n" + a[k : k + n] + " " + " ".join(word(rng) for _ in range(rng.randint(0, 60))))
    for _ in range(20):
        ws = base[0].split()
        for _ in range(rng.randint(0, 4)):
            ws[rng.randrange(len(ws))] = word(rng)
        out.append(" ".join(ws))
    return out


def rows(ts):
    out = [(None if i in (4, 9) else i, t, ["en", None, "de"][i % 3], None if i == 5 else f"src{i % 4}", None, 1, "x", "y") for i, t in enumerate(ts)]
    return out + [out[-1], out[-1]]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(texts()), SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, sql, name):
    got = QUERIES[name](spark, SF)
    columns, want = sql_rows(sql, ORACLES[name])
    assert sorted(got.columns) == columns and rows_of(got) == want


def test_chat_round_trip(spark):
    odd = ["\\### Assistant: </turn> ok", "### User: #### Role a: ", " </turn>\n", "\\\\", None, "", "a\\"]
    data = [(1, i, r, t) for i, (r, t) in enumerate([("system", "s"), *[(("user", "assistant")[k % 2], t) for k, t in enumerate(odd)]])] + [(2, 0, "Odd: ro\\le", "x: y"), (2, 0, None, "z"), (None, None, "user", "q"), (3, 0, "user", "u"), (3, 0, "user", "u")]
    df = spark.createDataFrame(data, "conv_id long, turn long, role string, text string")
    out = chat.format_conversations(df)
    got = {r["conv_id"]: [(x["role"], x["text"]) for x in r["t"]] for r in out.select("conv_id", chat.parse_turns(out["formatted"]).alias("t")).collect()}
    assert got[1] == [(r, t or "") for _, _, r, t in data[:8]]
    assert got[2] == [("", "z"), ("Odd: ro\\le", "x: y")] and got[None] == [("user", "q")] and len(got[3]) == 2
    valid = {r["conv_id"]: r["valid"] for r in out.collect()}
    assert not valid[3] and not valid[2] and not valid[1]
    assert chat.segment_rows(out).where("loss").count() == 3
    assert chat.digest(chat.format_conversations(df.limit(0))).count() == 0


def test_quality_edges(docs, empty, spark):
    out = quality.judge(docs)
    assert out.count() == docs.count() and quality.judge(empty).count() == 0 and quality.clean(empty).count() == 0
    assert not [r for r in out.collect() if r["kept"] and r["n_words"] < 50]
    line, rng = "The same line on every page.", random.Random(8)
    many = spark.createDataFrame([(i, f"{line}\n" + " ".join(word(rng) for k in range(60 if i else 4)), "h") for i in range(30)], "doc_id long, text string, source string")
    kept = {r["doc_id"]: r["text"] for r in quality.clean(many).collect()}
    assert set(kept) == set(range(1, 30)) and not any(line in t for t in kept.values())


def test_grading(spark, empty):
    rng = random.Random(1)
    filler = [word(rng) for _ in range(200)]
    make = lambda g: " ".join(rng.sample(filler, 30) + ([["scum", "trash"], ["@@@", "zzz"], ["fine", "good"]][g]))
    data = [(i, make(i % 3), i % 3) for i in range(1500)]
    df = spark.createDataFrame(data, "doc_id long, text string, grade long")
    m = grading.train(df.where("doc_id < 1200"), df.where("doc_id < 1200").select("doc_id", "grade"), 1000)
    got = {r["doc_id"]: r for r in grading.grade(df, m).collect()}
    hits = [got[i]["kept"] == (g == 2) for i, _, g in data if i >= 1200]
    assert sum(hits) / len(hits) > 0.9 and (np.diff(m.thresholds) > 0).all()
    assert all(abs(r["expected_grade"] - r["p_ge_1"] - r["p_ge_2"]) < 1e-9 and r["p_ge_1"] >= r["p_ge_2"] for r in got.values())
    assert grading.grade(empty, m).count() == 0
    assert grading.grade(spark.createDataFrame([(None, None)], "doc_id long, text string"), m).count() == 1


def reference_ids(ts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(bpe.tokenizer_path())
    return [t.encode(x or "", add_special_tokens=False).ids for x in ts]


def test_grading_slopes_and_fit(docs, monkeypatch):
    """Slopes against differences of the loss; the fit against another optimiser of the same likelihood; grades against a loop."""
    rng = np.random.default_rng(3)
    th, grades, scores = np.array([-0.5, 0.75]), rng.integers(0, 3, 40), rng.normal(size=40)
    by_score, by_threshold = grading.slopes(scores, th, grades)
    step = 1e-6
    for i in range(0, 40, 7):
        move = np.where(np.arange(40) == i, step, 0)
        assert by_score[i] == pytest.approx(40 * (grading.loss(scores + move, th, grades) - grading.loss(scores - move, th, grades)) / (2 * step), abs=1e-5)
    for j in range(2):
        move = np.where(np.arange(2) == j, step, 0)
        assert by_threshold[:, j].sum() == pytest.approx(40 * (grading.loss(scores, th + move, grades) - grading.loss(scores, th - move, grades)) / (2 * step), abs=1e-4)
    x = (rng.random((600, 4)) < 0.5).astype(float)
    y = np.digitize(x @ [1.5, -1.0, 0.5, 0.0] + rng.logistic(size=600), [-0.5, 1.0])
    monkeypatch.setattr(grading, "EPOCHS", 600)
    model = grading.fit([np.flatnonzero(row) for row in x], y, 3)
    w, t = np.zeros(4), np.array([-0.5, 0.5])
    for _ in range(3000):
        by_score, by_threshold = grading.slopes(x @ w, t, y)
        w, t = w - 0.5 * (x.T @ by_score / 600 + grading.PENALTY * w), t - 0.5 * by_threshold.sum(axis=0) / 600
    assert grading.loss(x @ model.weights[:4], model.thresholds, y) < grading.loss(x @ w, t, y) + 0.01
    assert np.abs(model.weights[:4] - w).max() < 0.3
    weights = np.zeros(grading.N_WEIGHTS)
    weights[grading.features("the cat")] = [0.5, -0.25]
    m = grading.CumulativeLink(weights, np.array([-1.0, 1.0]))
    got = sorted(((r.doc_id, r.expected_grade, r.p_ge_1, r.p_ge_2, r.kept) for r in grading.grade(docs, m).collect()), key=str)
    want = []
    for doc, text in (r[:2] for r in rows(texts())):
        score = sum(weights[i] for i in set(grading.features(text or "").tolist()))
        p = [1 / (1 + math.exp(-(score - c))) for c in (-1.0, 1.0)]
        want.append((doc, sum(p), *p, p[1] >= grading.MIN_TAIL))
    for a, b in zip(got, sorted(want, key=str), strict=True):
        assert a[0] == b[0] and a[4] == b[4] and a[1:4] == pytest.approx(b[1:4])


def test_one_grade_for_a_repeated_id(spark):
    docs = spark.createDataFrame([(1, "a b")] * 50 + [(2, "c")], "doc_id long, text string")
    grades = spark.createDataFrame([(1, 0), (2, 2)], "doc_id long, grade long")
    assert len(grading.train(docs, grades).thresholds) == 2


def test_orc_skips_by_index(spark):
    """Ids are run-length encoded integers in several stripes' groups; a filter on an id reads a group of rows, not the file."""
    import glob

    from pyarrow import orc

    path = work_path(spark, "orc")
    docs = spark.range(0, 20_000, 2, 1).selectExpr("id AS doc_id", "concat('some words ', id) AS text")
    token_files.write_tokens(docs, path, file_bytes=1 << 30)
    local = path.removeprefix("file:")
    files = [orc.ORCFile(f) for f in sorted(glob.glob(f"{local}/*.orc"))]
    assert sum(f.nrows for f in files) == 10_000 and {f.compression.lower() for f in files} == {"zstd"} and {f.row_index_stride for f in files} == {1000}
    for wanted, found in ((4444, 1), (4445, 0)):
        df = token_files.read_tokens(spark, path).where(f"doc_id = {wanted}")
        assert len(df.collect()) == found
        leaf = df._jdf.queryExecution().executedPlan().collectLeaves().apply(0)
        assert leaf.metrics().apply("numOutputRows").value() <= 1000


def test_hot_id_is_dealt_to_several_files(spark):
    path = work_path(spark, "hot")
    docs = spark.range(0, 4000).selectExpr("1L AS doc_id", "repeat(concat('w', id, ' '), 20) AS text")
    token_files.write_tokens(docs, path, file_bytes=20_000)
    per = [r["count"] for r in token_files.read_tokens(spark, path).groupBy("_metadata.file_name").count().collect()]
    assert len(per) > 10 and max(per) < 1000
    rows_ = sorted(token_files.summary(spark, path).collect(), key=lambda r: r.start)
    assert all(a.start + a.n_tokens == b.start for a, b in zip(rows_, rows_[1:], strict=False)) and len(rows_) == 4000


@pytest.mark.parametrize("stage", ["quality", "near", "leaks", "mix"])
def test_clashing_columns_stay(spark, stage):
    words = " ".join(f"w{i}" for i in range(80))
    names = ["_key", "_k", "_lines", "_verdict", "_c", "_d", "_content", "content", "lost_words", "slot"]
    values = [f"'{n}' AS `{n}`" for n in names]
    docs = spark.range(3).selectExpr("id AS doc_id", f"concat('{words} ', id, ' tail', id * 7) AS text", "'en' AS lang", "'src0' AS source", *values)
    bench = spark.createDataFrame([(1, "some thing else that is not there at all")], "item_id long, text string")
    run = {"quality": quality.clean, "near": near_dup.one_of_each, "leaks": lambda d: decontaminate.clean(d, bench), "mix": lambda d: mixing.mixed(d, (1, 1))}[stage]
    out = run(docs)
    assert out.columns == docs.columns
    got = out.collect()
    assert got and all(r[n] == n for r in got for n in names)


def test_mixing_is_the_same_at_any_depth(docs):
    """Buckets of buckets choose what one level of buckets does."""
    plain = rows_of(mixing.select_prefixes(docs))
    assert rows_of(mixing.select_prefixes(docs, bucket_rows=0.001)) == plain


def test_passages_are_caught_from_400_bytes_on(spark):
    """A passage that three texts share goes when it has 400 bytes or more, of any number of words; a shorter one stays."""
    rng = random.Random(9)
    word = lambda n=5: "".join(rng.choice("abcdefghijklmnop") for _ in range(n))
    prose = lambda n: " ".join(word() for _ in range(n))
    long, short = prose(80), prose(60)
    texts_ = [(i, f"{prose(50)} {p} {prose(50)}") for i, p in enumerate([long] * 3 + [short] * 3 + ["-"])]
    got = {r.doc_id: r.n_removed for r in repeats.repeated_bytes(spark.createDataFrame(texts_, "doc_id long, text string")).collect()}
    assert all(got[i] >= len(long) for i in range(3)) and not any(got[i] for i in range(3, 7))


def test_strings_with_one_hash_are_told_apart(monkeypatch):
    """With a hash that makes all strings equal, bytes alone decide."""
    rng = np.random.default_rng(1)
    base = rng.integers(97, 110, repeats.SPAN + repeats.ROOM).astype(np.uint8).tobytes()
    other = rng.integers(97, 110, repeats.SPAN + repeats.ROOM).astype(np.uint8).tobytes()
    room = repeats.ROOM
    lefts, rights = [base[:room], base[:room], other[:room]], [base[room:], base[room:], base[room : room + 300] + other[:100]]
    args = (rights, lefts, np.zeros(3, np.int64), np.ones(3, np.int64), np.zeros(3, np.int64))
    want = repeats._equal_strings(*args)
    monkeypatch.setattr(repeats, "mix", lambda x: np.zeros_like(x))
    got = repeats._equal_strings(*args)
    assert [x.tolist() for x in got] == [x.tolist() for x in want] and want[0].tolist() == [room, room, -1]


def test_encoder_equals_library():
    rng = random.Random(2)
    ts = [*texts(), "a<|endoftext|>b", "x²y 3¹ ½", "it's we'll 'S  \n\n  x\t\ty __a_b 12ab", "日本 語\x1c\x85 z", "ª º µ ÿ×÷"] + ["".join(rng.choice("abé ÿ 's\n\t_19.,!'\xa0\xad\x00\x1b\x84~") for _ in range(rng.randint(1, 60))) for _ in range(2000)]
    assert [np.frombuffer(x, "<u4").tolist() for x in bpe.Encoder().encode(ts)] == reference_ids(ts)


def test_token_files(spark, docs, empty):
    path = work_path(spark, "t")
    token_files.write_tokens(docs, path)
    got = sorted(map(tuple, token_files.summary(spark, path).collect()), key=lambda r: r[1])
    data = sorted(rows(texts()), key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    start, want = 0, []
    for r, ids in zip(data, reference_ids([r[1] for r in data]), strict=True):
        raw = np.array([*ids, 0], "<u4").tobytes()
        want.append((r[0], start, len(ids) + 1, zlib.crc32(raw)))
        start += len(ids) + 1
    assert got == want
    assert token_files.read_tokens(spark, path).where("doc_id = 20").count() == 1
    path = work_path(spark, "t")
    token_files.write_tokens(empty, path)
    assert token_files.summary(spark, path).count() == 0


def test_length_histogram(docs, empty):
    h = lengths.histogram(docs)
    ns = [len(x) for x in reference_ids([r[1] for r in rows(texts())])]
    for r in h.collect():
        assert r["n_docs"] == ns.count(r["length"]) and r["docs_ge"] == sum(n >= r["length"] for n in ns)
        assert r["truncated_tokens"] == sum(min(n, r["length"]) for n in ns) and r["total_tokens"] == sum(ns)
    assert {tuple(r) for r in lengths.at_limits(h, [5, 10**6]).collect()} == {(5, sum(min(n, 5) for n in ns), sum(n > 5 for n in ns)), (10**6, sum(ns), 0)}
    assert lengths.quantile(h, 0.5) == sorted(ns)[math.ceil(len(ns) / 2) - 1]
    assert lengths.histogram(empty).count() == 0


def test_leaks(spark, docs, empty):
    rng = random.Random(5)
    items = [(i, " ".join(word(rng) for _ in range(n))) for i, n in enumerate([30, 50, 64, 12, 3])] + [(9, None), (10, "")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    edited = items[2][1].split()
    edited[-1] = "other"
    leak = [(100, "before " + items[0][1].replace("a", "A") + " after"), (101, "a b " + " ".join(edited) + " c"), (102, items[1][1][: len(items[1][1]) // 2]), (103, items[3][1] + " " + items[1][1]), (104, None), (105, "q " + items[4][1] + " r"), (103, items[3][1] + " " + items[1][1])]
    df = spark.createDataFrame(leak, "doc_id long, text string")
    got = sorted((r["doc_id"], r["item_id"]) for r in decontaminate.leaks(df, bench).collect())
    assert got == [(100, 0), (101, 2), (103, 1), (103, 1), (103, 3), (103, 3), (105, 4)]
    assert {r["doc_id"] for r in decontaminate.clean(df, bench).collect()} == {102, 104}
    assert decontaminate.leaks(empty, bench).count() == 0 and decontaminate.leaks(docs, bench.limit(0)).count() == 0


@pytest.fixture(scope="module")
def cut_items():
    """Items quoted without a tenth to a fifth of their words at either end or at both, also at the ends of a text; one item repeats itself."""
    rng = random.Random(11)
    some = lambda n: [word(rng) + word(rng) for _ in range(n)]
    items = [some(rng.randint(15, 59)) for _ in range(40)] + [["same"] * 30, some(4) * 8]
    docs = []
    for w in items:
        for tenths in (1, 2):
            for lost in {len(w) * tenths // 10, len(w) * tenths // 20, 2}:
                docs += [["in", "front"] + some(lost) + w[lost:] + some(9), some(9) + w[: len(w) - lost] + some(lost) + ["and", "so"], some(5) + some(lost // 2) + w[lost // 2 : len(w) - lost // 2] + some(lost), w[lost:], some(6) + w[: len(w) - lost]]
    return [(i, " ".join(w)) for i, w in enumerate(docs)], [(i, " ".join(w)) for i, w in enumerate(items)]


def test_leaks_of_cut_items(spark, cut_items):
    import duckdb

    con = duckdb.connect()
    frames = []
    for name, key, data in zip(("documents", "benchmark"), ("doc_id", "item_id"), cut_items, strict=True):
        con.execute(f"CREATE TABLE {name} ({key} BIGINT, text VARCHAR)")
        con.executemany(f"INSERT INTO {name} VALUES (?, ?)", data)
        frames.append(spark.createDataFrame(data, f"{key} long, text string").repartition(4))
    columns, want = sql_rows(con, ORACLES["op5_decontamination"])
    got = decontaminate.leaks(*frames)
    assert sorted(got.columns) == columns and rows_of(got) == want and len(want) > 100
    leaking = {r["doc_id"] for r in got.collect()}
    assert {r["doc_id"] for r in decontaminate.clean(*frames).collect()} == {i for i, _ in cut_items[0]} - leaking


def shingle_set(t):
    w = WORD.findall(t or "")
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


@pytest.mark.parametrize("block", [8 << 20, 3000])
def test_near_duplicates(docs, empty, block):
    data = rows(texts())
    sets = [shingle_set(r[1]) for r in data]
    same = lambda i, j: (data[i][1] or "") == (data[j][1] or "") or (sets[i] and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]))
    links = [[j for j in range(len(data)) if j != i and same(i, j)] for i in range(len(data))]
    want = []
    for i in range(len(data)):
        seen, todo = {i}, [i]
        while todo:
            for j in links[todo.pop()]:
                if j not in seen:
                    seen.add(j)
                    todo.append(j)
        want.append((data[i][0], min((data[j][0] for j in seen if data[j][0] is not None), default=None), len(links[i])))
    got = near_dup.near_duplicates(docs, block_bytes=block).select("doc_id", "class_id", "n_links").collect()
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, want))
    if block > 10_000:
        assert near_dup.near_duplicates(empty).count() == 0 and near_dup.one_of_each(empty).count() == 0
        assert near_dup.one_of_each(docs).count() == near_dup.near_duplicates(docs).select("class_key").distinct().count()


def test_band_choice():
    bands, width = near_dup.choose_bands()
    assert 1 - (1 - 0.8**width) ** bands >= near_dup.RECALL and bands * width <= near_dup.MAX_HASHES


def brute_katz(data):
    def toks(t):
        return WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or ""))) + ["</s>"]

    def off(n):
        try:
            cut = 6 * n[6] / n[1]
            d = [((r + 1) * n[r + 1] / (r * n[r]) - cut) / (1 - cut) for r in range(1, 6)]
            if not all(0 < x < 1 for x in d):
                raise ZeroDivisionError
        except ZeroDivisionError:
            d = [(r - 0.5) / r for r in range(1, 6)]
        return lambda c: c * (1 if c > 5 else d[c - 1])

    held = lambda d: zlib.crc32(("" if d is None else str(d)).encode()) % 7 == 2
    u, b, hist = collections.Counter(), collections.Counter(), collections.defaultdict(dict)
    for d, t in data:
        if not held(d):
            p = "<s>"
            for w in toks(t):
                u[w] += 1
                b[p, w] += 1
                p = w
    total, types = sum(u.values()), len(u)
    d1, d2 = off(collections.Counter(u.values())), off(collections.Counter(b.values()))
    mass = sum(d1(c) for c in u.values())
    over = total if mass < total else total + 1
    p1 = lambda w: d1(u[w]) / over if u[w] else 1 - mass / over
    for (h, w), c in b.items():
        hist[h][w] = c
    back = {}
    for h, ws in hist.items():
        n, seen = sum(ws.values()), sum(d2(c) for c in ws.values())
        n = n if seen < n else n + 1
        back[h] = (n, (1 - seen / n) / (1 - sum(p1(w) for w in ws)))
        assert abs(seen / n + back[h][1] * (1 - sum(p1(w) for w in ws)) - 1) < 1e-9
    out = []
    for d, t in data:
        ts, s, p = toks(t), 0.0, "<s>"
        for w in ts:
            s += math.log10((d2(b[p, w]) / back[p][0] if b[p, w] else back[p][1] * p1(w)) if p in back else p1(w))
            p = w
        out.append((d, held(d), len(ts), sum(u[w] > 0 for w in ts), total, sum(math.log10((u[w] + 1) / (total + types + 1)) for w in ts), s))
    return out


def test_katz(spark, docs, empty, monkeypatch):
    monkeypatch.setattr(katz, "BLOCK", 400)
    data = [r[:2] for r in rows(texts())] + [(i + 200, "the cat sat on the mat " * (i % 4) + f"w{i % 7} The w{i % 3}") for i in range(60)]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    key = lambda r: (str(r[0]), r[2], round(r[5], 4))
    got, want = sorted(map(tuple, katz.score(df).collect()), key=key), sorted(brute_katz(data), key=key)
    assert len(got) == len(want)
    for g, w in zip(got, want, strict=True):
        assert g[:5] == w[:5] and g[5:] == pytest.approx(w[5:], rel=1e-6)
    assert katz.score(empty).count() == 0


def test_mixing_edges(docs, empty):
    out = mixing.select_prefixes(docs, (1, 2), 2)
    sizes = docs.count()
    assert 0 < out.count() <= sizes and mixing.select_prefixes(empty).count() == 0 and mixing.mixed(empty).count() == 0
    every = mixing.select_prefixes(docs, (1, 1), 1)
    assert every.count() == sizes


def test_mixing_gives_shortage_to_siblings(spark):
    leaf = spark.createDataFrame([("d0", "en", "a", 10), ("d0", "de", "b", 100), ("d1", "en", "c", 1000)], "domain string, lang string, source string, available long")
    w = {"domain": {"d0": 1, "d1": 1}, "lang": {"en": 9, "de": 1}, "source": {}}
    got = {r["source"]: r["budget"] for r in mixing.budgets(leaf, (18, 111), 1, w).collect()}
    assert got == {"a": 10, "b": 80, "c": 90}


def brute_repeats(ts):
    data = [(t or "").encode() for t in ts]
    n = collections.Counter(b[i : i + 400] for b in data for i in range(len(b) - 399))
    out = []
    for b in data:
        gone = bytearray(len(b))
        for i in range(len(b) - 399):
            if n[b[i : i + 400]] > 1:
                gone[i : i + 400] = b"\1" * 400
        kept = bytes(c for c, r in zip(b, gone, strict=True) if not r)
        out.append((len(b), sum(gone), sum(1 for i, g in enumerate(gone) if g and (not i or not gone[i - 1])), hashlib.sha256(kept).hexdigest()))
    return out


def test_repeats(spark, docs, empty):
    ts = [r[1] for r in rows(texts()) if len(r[1] or "") < 20_000]
    df = docs.where("text IS NULL OR length(text) < 20000")
    got = [tuple(r)[1:5] for r in repeats.repeated_bytes(df).collect()]
    assert sorted(got) == sorted(brute_repeats(ts))
    assert repeats.repeated_bytes(empty).count() == 0


def test_long_texts_are_cut_with_overlap(monkeypatch):
    monkeypatch.setattr(repeats, "CHUNK", 1000)
    rng = random.Random(4)
    data = bytes(rng.randrange(97, 123) for _ in range(5000))
    found = set()
    for group in repeats._pieces([data]):
        piece, place, before, after, _ = repeats.anchors([p for _, _, p in group])
        for i, p, b, a in zip(piece, place, before, after, strict=True):
            found |= {group[i][1] + p - k for k in range(a, b + 1)}
    assert found == set(range(len(data) - 399))


def test_repeats_across_pieces_of_one_text(spark, monkeypatch):
    monkeypatch.setattr(repeats, "CHUNK", 1000)
    rng = random.Random(9)
    noise = lambda n: "".join(rng.choice("abcdefghij klm") for _ in range(n))
    a, b, c = noise(450), noise(700), noise(1500)
    ts = [noise(700) + a + noise(2500) + a + noise(900), b + noise(3000) + b[:399], c + noise(1200) + c, noise(4000), "z" * 3000]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(ts)], "doc_id long, text string").repartition(5)
    got = {r["doc_id"]: tuple(r)[1:5] for r in repeats.repeated_bytes(df).collect()}
    assert [got[i] for i in range(len(ts))] == brute_repeats(ts)
    assert [g > 0 for g in (got[i][1] for i in range(len(ts)))] == [True, False, True, False, True]


def test_repeats_in_a_text_of_megabytes(spark):
    rng = np.random.default_rng(9)
    noise = lambda n: rng.integers(97, 123, n, np.uint8).tobytes().decode()
    a, near, far = noise(400), 10_000, repeats.CHUNK + 500_000
    text = noise(near) + "." + a + "," + noise(far - near - 402) + ";" + a + ":" + noise(1000)
    got = repeats.repeated_bytes(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()
    assert [tuple(s) for s in got["spans"]] == [(near + 1, near + 401), (far + 1, far + 401)]


def test_loser_tree_merges_and_shares():
    rng = random.Random(6)
    runs = [sorted("".join(rng.choice("ab") for _ in range(rng.randint(0, 9))).encode() for _ in range(rng.randint(0, 30))) for _ in range(5)]
    coded = [zip(repeats.front_code(r)[0].tolist(), r, r, strict=True) for r in runs]
    out = list(repeats.merge_runs([iter(c) for c in coded]))
    keys = [k for _, k, _ in out]
    assert keys == sorted(k for r in runs for k in r)
    for (_, a, _), (s, b, _) in zip(out, out[1:], strict=False):
        assert s == repeats.common(a, b, 0)


def test_pipeline(spark):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in p.STAGES[:-1]:
        after = stage(spark, docs, SF)
        assert after.columns == docs.columns and 0 < after.count() <= docs.count(), name
        path = work_path(spark, name)
        after.write.parquet(path)
        docs = spark.read.parquet(path)
    got = p.run(spark, SF).collect()
    rs = docs.collect()
    want = {r["doc_id"]: len(ids) + 1 for r, ids in zip(rs, reference_ids([r["text"] for r in rs]), strict=True)}
    assert {r["doc_id"]: r["n_tokens"] for r in got} == want
    items = {shingle_set(r["text"].lower()) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()}
    left = [shingle_set(r["text"].lower()) for r in rs]
    assert not any(i <= s for i in items for s in left)
    assert not any(5 * len(a & b) >= 4 * len(a | b) for k, a in enumerate(left) for b in left[:k])


def test_pieces_by_array_are_those_of_the_pattern():
    """Runs of blanks, contractions, spaces at ends, empty texts and control characters, many texts at a time."""
    import re

    rng = random.Random(5)
    parts = ["'", "'s", "'re", "'ll", "'ve", "'t", "l", "re", "S", " ", "  ", "\n", "\t", "\xa0", "\r", "7", "12", "_", "-", "''", "é", "ª", "\x00", "don't", "\x85"[:0], "x"]
    texts = ["", " ", "'", "\n\n", "a ", "a  ", " 's", "\n's", "'s's", "''s", *["".join(rng.choice(parts) for _ in range(rng.randint(0, 12))) for _ in range(4000)], ""]
    assert not any(re.search(bpe.ODD, t) for t in texts)
    data, starts, ends = bpe.pieces([t.encode("latin-1") for t in texts])
    cut = [data[a:z].decode("latin-1") for a, z in zip(starts, [*starts[1:], len(data)], strict=True)]
    got, one = [], []
    for piece, end in zip(cut, ends, strict=True):
        if end:
            got.append(one)
            one = []
        else:
            one.append(piece)
    assert got == [re.findall(bpe.PIECES, t) for t in texts]


def test_pieces_forgotten_and_found_again(monkeypatch):
    """With room for few pieces, ids stay those of the library, texts by texts."""
    monkeypatch.setattr(bpe, "REMEMBER", 20)
    monkeypatch.setattr(bpe, "TOGETHER", 50)
    rng = random.Random(6)
    texts = [" ".join(rng.choice("alpha beta's gam9ma \n\n delta42 é _x_ it's  y".split(" ")) + str(rng.randint(0, 60)) for _ in range(8)) for _ in range(60)]
    encoder = bpe.Encoder()
    for _ in range(2):
        got = [np.frombuffer(x, "<u4").tolist() for i in range(0, 60, 7) for x in encoder.encode([*texts[i : i + 7], None, "日本"])]
        assert got == [ids for i in range(0, 60, 7) for ids in reference_ids([*texts[i : i + 7], "", "日本"])]
    assert len(encoder.pieces.known) < 400
