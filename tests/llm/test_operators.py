"""The training-data operators against brute force, round trips and held-out accuracy, on small and odd inputs."""

import hashlib
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from longweave.llm import binary, decontaminate, hnsw, line_dedup, near_dup, packing, pii, quality, secrets, tokens, warc
from longweave.llm.files import new_folder

P = tokens.default_path()
BASE = " ".join(f"w{i}" for i in range(120))
NEAR = BASE.replace("w60", "x60")
ODD = [
    (1, BASE, "a"), (2, NEAR, "a"), (3, BASE, None), (4, None, "b"), (5, "", "b"), (6, "one two", "c"), (7, "one two", "c"),
    (7, "one two", "c"), (None, BASE, "d"), (8, "long " * 30000, "d"), (9, "é😀  x\n\n  y\t", "e"), (10, "a@b.co token = abcdef123456 4111111111111111", "f"),
]
CLASH = {"score": 1.0, "predicted": 5, "secrets": "s", "pii": "p", "h1": 1, "h2": 2, "token": "t", "line": 3, "node": 4, "component": 5, "band": 6, "own": 7, "a": 8, "b": 9, "id": 10, "n": 11}


@pytest.fixture(scope="module")
def docs(spark):
    d = spark.createDataFrame(ODD, "doc_id long, text string, lang string").withColumns({"source": F.lit("s"), "n_chars": F.length("text").cast("long")})
    return d.withColumns({k: F.lit(v) for k, v in CLASH.items()})


@pytest.fixture(scope="module")
def none(docs):
    return docs.filter("false")


def sets(t):
    ws = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
    return {tuple(ws[i : i + 5]) for i in range(len(ws) - 4)} if len(ws) >= 5 else {tuple(ws)} if ws else set()


def brute_components(rows):
    s = {i: sets(t) for i, t in rows}
    ids, comp = sorted(s), {i: i for i in s}
    for i in ids:
        for j in ids:
            if i < j and s[i] and s[j] and 100 * len(s[i] & s[j]) >= 75 * len(s[i] | s[j]):
                low = min(comp[i], comp[j])
                comp = {k: low if v in (comp[i], comp[j]) else v for k, v in comp.items()}
    return comp


def test_near_dup(spark, docs, none):
    got = near_dup.near_duplicates(docs).collect()
    assert len(got) == len(ODD)
    by = {r["doc_id"]: r for r in got if r["doc_id"] is not None}
    assert {i: by[i]["component_id"] for i in (1, 2, 3, 4, 5, 6, 7)} == {1: 1, 2: 1, 3: 1, 4: 4, 5: 5, 6: 6, 7: 6}
    assert by[4]["n_shingles"] == 0 and by[6]["n_shingles"] == 1 and by[8]["n_shingles"] == 1
    assert [r["kept"] for r in got if r["doc_id"] is None] == [True]
    assert near_dup.near_duplicates(none).count() == 0
    kept = near_dup.keep_representatives(docs)
    assert kept.columns == docs.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 1, 4, 5, 6, 8, 9, 10]


def test_near_dup_equals_brute_force(spark):
    g = np.random.default_rng(5)
    words = [f"v{i}" for i in range(4000)]
    rows, n = [], 0
    for _ in range(12):  # families of near copies, some of them chains
        own = [words[i] for i in g.integers(0, 4000, 60)]
        for _ in range(8):
            rows.append((n, " ".join(own)))
            n += 1
            own = list(own)
            for i in g.integers(0, 60, int(g.integers(0, 3))):
                own[i] = words[int(g.integers(0, 4000))]
    want = brute_components(rows)
    got = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == want


def test_sketches_fill_and_estimate():
    g = np.random.default_rng(0)
    for n in (1, 3, 50, 2000):
        s = np.unique(g.integers(0, 2**63, n, dtype=np.uint64))
        assert (near_dup.sketch(s) != near_dup.EMPTY).all()
    a = g.integers(0, 2**63, 1000, dtype=np.uint64)
    est = [(near_dup.sketch(a) == near_dup.sketch(np.concatenate([a[k:], g.integers(0, 2**63, k, dtype=np.uint64)]))).mean() for k in (143,)]
    assert abs(est[0] - 857 / 1143) < 0.13


def test_line_dedup(spark, docs, none):
    rows = [(1, "the quick brown fox jumps over it\nshort"), (2, "short\nOVER it the quick brown fox jumps\nanother line of some length here"), (3, None), (None, "the quick brown fox jumps over it"), (4, "the quick brown fox jumps over it")]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted((r["doc_id"], r["line"], r["of_doc_id"], r["of_line"]) for r in line_dedup.repeated_lines(d).collect()) == [(2, 0, 1, 1), (2, 1, 1, 0), (4, 0, 1, 0)]
    left = {r["doc_id"]: r["text"] for r in line_dedup.remove_repeated_lines(d).collect()}
    assert left == {1: rows[0][1], 2: "another line of some length here", 3: None, None: rows[3][1]}
    out = line_dedup.remove_repeated_lines(docs)
    assert out.columns == docs.columns and sorted(r["doc_id"] or 0 for r in out.collect()) == [0, 1, 4, 5, 6, 8, 9, 10]  # 2 and 3 repeat 1, 7 repeats 6
    assert line_dedup.remove_repeated_lines(none).count() == 0


def test_line_dedup_equals_brute_force(spark):
    g = np.random.default_rng(2)
    rows = []
    for i in range(40):
        base = [f"t{k}" for k in g.integers(0, 60, 14)]
        rows += [(3 * i + j, "\n".join(" ".join(base[: int(g.integers(10, 15))]) for _ in range(3))) for j in range(3)]
    lines = sorted((d, k, frozenset(x.split())) for d, t in rows for k, x in enumerate(t.split("\n")))
    want = set()
    for i, (d, k, s) in enumerate(lines):
        if any(100 * len(s & o) >= line_dedup.PERCENT * len(s | o) for _, _, o in lines[:i]):
            want.add((d, k))
    few, earliest = line_dedup.FEW, {}
    for i, (d, k, s) in enumerate(lines):
        earliest[d, k] = next(((x, y) for x, y, o in lines[:i] if 100 * len(s & o) >= line_dedup.PERCENT * len(s | o)), None)
    try:
        for line_dedup.FEW in (1, 2, few):  # with few, the second round has to find the rest
            got = line_dedup.repeated_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()
            assert {(r["doc_id"], r["line"]) for r in got} == want
            assert {(r["doc_id"], r["line"]): (r["of_doc_id"], r["of_line"]) for r in got} == {k: earliest[k] for k in want}
    finally:
        line_dedup.FEW = few


def test_line_dedup_names_the_earliest_match(spark):
    a, c, r, g = ([f"{k}{i}" for i in range(n)] for k, n in (("a", 10), ("c", 270), ("r", 20), ("g", 299)))
    apart = [a + g[: 9 * i] + g[9 * i + 9 :] for i in range(9)]  # share the words of a with the last line, and pass the filters
    first, second, last = a + c + [f"e{i}" for i in range(20)], c + r + [f"m{i}" for i in range(10)], a + c + r
    rows = [[*apart, first], [second], [last], [c + g] * 40]  # the many copies make the words of c and g the frequent ones
    lines = [(d, k, frozenset(x)) for d, t in enumerate(rows) for k, x in enumerate(t)]
    want = {}
    for i, (d, k, s) in enumerate(lines):
        of = next(((x, y) for x, y, o in lines[:i] if 100 * len(s & o) >= line_dedup.PERCENT * len(s | o)), None)
        if of:
            want[d, k] = of
    assert want[2, 0] == (0, 9)
    texts = [(d, "\n".join(map(" ".join, t))) for d, t in enumerate(rows)]
    got = line_dedup.repeated_lines(spark.createDataFrame(texts, "doc_id long, text string"))
    assert {(r["doc_id"], r["line"]): (r["of_doc_id"], r["of_line"]) for r in got.collect()} == want


def test_decontamination(spark, docs, none):
    item = "Alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon"
    w = item.split()
    bench = spark.createDataFrame([(1, item), (2, None), (3, "too short"), (4, "")], "item_id long, text string")
    d = spark.createDataFrame([(1, f"x, {item}! y"), (2, "z " + " ".join(w[10:]) + " and then " + " ".join(w[:10])), (3, " ".join(w[:8])), (4, None), (5, "clean")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in decontaminate.contamination(d, bench).collect()}
    assert set(got) == {1, 2} and got[1]["tiles"] == 1 and got[2]["tiles"] == 2 and got[2]["coverage"] == 1.0
    assert {r["doc_id"] for r in decontaminate.contamination(d, bench, chunk_chars=30).collect()} == {1, 2}  # in slices
    assert [r["doc_id"] for r in decontaminate.decontaminate(d, bench).orderBy("doc_id").collect()] == [3, 4, 5]
    assert decontaminate.decontaminate(docs, bench).columns == docs.columns
    assert decontaminate.contamination(d, bench.filter("false")).count() == 0 and decontaminate.contamination(none, bench).count() == 0


def plain_tiles(item, doc, least):
    """Greedy string tiling as it is told: mark the longest common unmarked run, the leftmost of equals, until none is left."""
    fi, fd, out = [True] * len(item), [True] * len(doc), []
    while True:
        best = (least - 1, 0, 0)
        for i in range(len(item)):
            for d in range(len(doc)):
                n = 0
                while i + n < len(item) and d + n < len(doc) and fi[i + n] and fd[d + n] and item[i + n] == doc[d + n]:
                    n += 1
                if n > best[0]:
                    best = (n, i, d)
        n, i, d = best
        if n < least:
            return out
        fi[i : i + n], fd[d : d + n] = [False] * n, [False] * n
        out.append((i, d, n))


def test_tiles_equal_plain_tiling():
    g = np.random.default_rng(4)
    for k in range(120):
        item, doc = (g.integers(0, 2 + k % 4, int(n)).astype(np.uint64) for n in g.integers(5, 40, 2))
        if k % 3 == 0:
            doc = np.concatenate([item[len(item) // 2 :], doc, item[: len(item) // 2]])
        assert decontaminate.tile(item, doc, 3) == plain_tiles(item.tolist(), doc.tolist(), 3)
    a = np.zeros(400, np.uint64)
    assert decontaminate.tile(a, np.zeros(20_000, np.uint64), 5) == [(0, 0, 400)]


def test_contamination_equals_brute_force(spark):
    g = np.random.default_rng(9)
    word = lambda n: [f"q{x}" for x in g.integers(0, 400, n)]
    items = [word(int(n)) for n in g.integers(4, 30, 12)]
    docs = []
    for k in range(60):
        own, it = word(40), items[k % 12]
        cut = int(g.integers(0, len(it)))
        docs.append([*own[:10], *it[cut:], *own[10:20], *it[: cut if k % 2 else cut // 2], *own[20:]])
    want = set()
    for d, doc in enumerate(docs):
        for i, it in enumerate(items):
            if len(it) >= decontaminate.LEAST and sum(t[2] for t in plain_tiles(it, doc, decontaminate.LEAST)) >= decontaminate.COVERAGE * len(it):
                want.add((d, i))
    frames = [spark.createDataFrame([(k, " ".join(x)) for k, x in enumerate(rows)], f"{name} long, text string") for name, rows in (("doc_id", docs), ("item_id", items))]
    got = decontaminate.contamination(*frames).collect()
    assert want and {(r["doc_id"], r["item_id"]) for r in got} == want
    left = {r["doc_id"] for r in decontaminate.decontaminate(*frames, chunk_chars=200).collect()}
    assert left == set(range(60)) - {d for d, _ in want}


def luhn(m):
    digits = [int(c) for c in m if c.isdigit()][::-1]
    return 13 <= len(digits) <= 19 and sum(x if k % 2 == 0 else sum(divmod(2 * x, 10)) for k, x in enumerate(digits)) % 10 == 0


PII_PLAIN = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m.split("."))),
    "card": (r"[0-9]([\x20-]?[0-9])+", luhn),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= sum(c.isdigit() for c in m) <= 15),
}


def test_pii_base_equals_plain_reading(spark):
    g = np.random.default_rng(6)
    pieces = ["a", "b.c", "@", ".", "-", " ", "+", "1", "22", "4111111111111111", "4111-1111 1111 1111", "192.168.0.1", "300.1.1.1", "+49 (30) 123456", "x@y.zz", "é", "😀", "(", "7", "\n", "5500005555555559"]
    rows = [(k, "".join(pieces[i] for i in g.integers(0, len(pieces), int(g.integers(1, 14))))) for k in range(1500)]
    rows += [(9000, " ".join(f"u{k}@h.example {k % 256}.1.2.3" for k in range(3000)))]
    got = {r["doc_id"]: [(x["kind"], x["start"], x["end"]) for x in r["pii"] if x["kind"] in PII_PLAIN] for r in pii.find_pii(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    n = dict.fromkeys(PII_PLAIN, 0)
    for k, t in rows:
        want = [(kind, m.start(), m.end()) for kind, (p, ok) in PII_PLAIN.items() for m in re.compile(p).finditer(t) if ok(m.group())]
        assert got[k] == want, t
        for kind, *_ in want:
            n[kind] += 1
    assert min(n.values()) > 20
    odd = spark.createDataFrame([("keep", "a@b.co", "own")], "text string, body string, hit_email string")
    out = pii.find_pii(odd, "body").first()
    assert out["text"] == "keep" and out["hit_email"] == "own" and out["pii"][0]["kind"] == "email"
    assert pii.redact(odd, "body").first()["body"] == "<email>"


def test_secrets_base_equals_plain_reading():
    g = np.random.default_rng(8)
    pieces = ["password", "Token", "api_key", "APIKEY", "secret", "=", ":", " ", '"', "'", "abcdef", "AKIA", "ABCDEFGH12345678", "deadbeef", "0123456789abcdef", "é", "\n", "x", "/+=", "passwd"]
    plain = ((r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A, lambda m: len(m.group(2)) >= 6), (r"AKIA[A-Z0-9]+", 0, lambda m: len(m.group()) >= 20), (r"[0-9a-f]+", 0, lambda m: len(m.group()) >= 24))
    found = 0
    for _ in range(4000):
        t = "".join(pieces[i] for i in g.integers(0, len(pieces), int(g.integers(1, 16))))
        want = sorted((m.start(), m.end(), k) for k, (p, f, ok) in enumerate(plain) for m in re.compile(p, f).finditer(t) if ok(m))
        assert secrets.base_spans(t) == sorted(want, key=lambda x: (x[0], x[2])), t
        found += len(want)
    assert found > 300


def test_secrets_beyond_the_core_are_read():
    assert secrets.views(0, 48) == [(0, 48)] and secrets.views(5, 105) == [(5, 53), (29, 77), (53, 101), (57, 105)]
    covered = {i for a, z in secrets.views(0, 333) for i in range(a, z)}
    assert covered == set(range(333)) and all(z - a <= secrets.CORE for a, z in secrets.views(0, 333))


def test_ftrl_equals_plain_updates():
    g = np.random.default_rng(1)
    rows = [(np.unique(g.integers(0, 50, 6)).astype(np.int32), None) for _ in range(40)]
    rows = [(s, g.random(len(s)).astype(np.float32)) for s, _ in rows]
    y = (g.random(40) < 0.4).astype(float)
    alpha, beta, l1, l2 = 0.3, 1.0, 0.02, 0.1
    z, n, order = {}, {}, np.random.default_rng(5)
    weight = lambda i: 0.0 if abs(z.get(i, 0)) <= l1 else -(z[i] - np.sign(z[i]) * l1) / ((beta + n[i] ** 0.5) / alpha + l2)
    for _ in range(quality.EPOCHS):
        for r in order.permutation(40):
            x = [*zip(rows[r][0].tolist(), rows[r][1].tolist(), strict=True), (-1, 1.0)]
            w = {i: weight(i) for i, _ in x}
            p = 1 / (1 + np.exp(-sum(w[i] * v for i, v in x)))
            for i, v in x:
                d = (0.5 / y.mean() if y[r] else 0.5 / (1 - y.mean())) * (p - y[r]) * v
                old = n.get(i, 0.0)
                z[i] = z.get(i, 0.0) + d - ((old + d * d) ** 0.5 - old**0.5) / alpha * w[i]
                n[i] = old + d * d
    got = quality.ftrl(rows, y)
    np.testing.assert_allclose(got.weight[:50], [weight(i) for i in range(50)], atol=1e-5)
    assert abs(got.bias - weight(-1)) < 1e-6


def test_packing_equals_plain_sum_of_squares():
    g = np.random.default_rng(3)
    for cap in (10, 64):
        shard, gaps = packing.Shard(cap, 0), {}  # sequence: gap
        for size in g.integers(1, cap + 1, 300).tolist():
            count = lambda gs: sum(c * c for c in np.unique(gs, return_counts=True)[1]) if gs else 0
            options = sorted({v for v in gaps.values() if v >= size})
            seq, offset = shard.place(size)
            if options:
                after = {v: count([x for x in [*sorted(gaps.values())] if x > 0 and x != v] + [v] * (list(gaps.values()).count(v) - 1) + ([v - size] if v > size else [])) for v in options}
                assert seq in gaps and after[gaps[seq]] == min(after.values()) and offset == cap - gaps[seq]
                gaps[seq] -= size
            else:
                assert seq not in gaps and offset == 0
                gaps[seq] = cap - size


def test_pii(spark, docs, none):
    got = {r["doc_id"]: r["pii"] for r in pii.find_pii(docs).collect()}
    assert [(x["kind"], x["start"], x["end"]) for x in got[10]] == [("email", 0, 6)]  # digits run on over the space: too many for a card
    assert got[4] == [] and got[5] == [] and pii.find_pii(none).count() == 0
    d = spark.createDataFrame([(1, "mail a@b.co now, iban GB82WEST12345698765432 and GB82WEST12345698765433, 1.2.3.4 999.1.1.1")], "doc_id long, text string")
    assert pii.redact(d).first()["text"] == "mail <email> now, iban <iban> and GB82WEST12345698765433, <ip> 999.1.1.1"


def test_secrets(spark, docs, none):
    model = secrets.CharCNN.fresh()
    f = secrets.seeded_findings()
    x, y = np.stack([secrets.encode(t, a, z) for t, a, z, _ in f]), np.array([k for *_, k in f], np.float32)
    held = (np.arange(len(x)) // 2) % 4 == 3
    model.train(x[~held], y[~held], epochs=3)
    model.calibrate(x[held], y[held])
    p = model.score(x[held])
    assert (p[y[held] > 0] >= model.threshold).mean() >= secrets.RECALL and (p[y[held] == 0] >= model.threshold).mean() < 0.1
    out = secrets.find_secrets(docs, model)
    got = {r["doc_id"]: r["secrets"] for r in out.collect()}
    assert [(s["kind"], s["start"], s["end"]) for s in got[10] if s["kind"] != "model"] == [("assign", 7, 27)]
    assert got[4] == [] and secrets.find_secrets(none, model).count() == 0
    key = "key ghp_" + "aB3dE5fG7hJ9kL1mN2pQ4rS6tU8vW0xY2zA4" + " end"
    assert [s["kind"] for s in secrets.find_secrets(spark.createDataFrame([(1, key)], "doc_id long, text string"), model).first()["secrets"]] == ["model"]
    assert secrets.base_spans("secret=token:abcdef") == [] and secrets.base_spans("TOKEN = 'a1b2c3'")[0] == (0, 15, 0)


def test_secrets_recall_binds_on_what_no_pattern_meets(spark):
    g = np.random.default_rng(1)
    pick = lambda chars, k: "".join(chars[i] for i in g.integers(0, len(chars), k))
    base = lambda: pick("0123456789abcdef", 32)
    keys = lambda: "ghp_" + pick("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 36)
    rows = [(i, "\n".join([*(f"key = {keys()} end" for _ in range(5)), *(f"sum {base()} of" for _ in range(20))])) for i in range(200)]
    model = secrets.train_model(spark.createDataFrame(rows, "doc_id long, text string"))
    f = [x for x in secrets.seeded_findings(600, seed=17) if x[3] and not secrets.base_spans(x[0])]
    p = model.score(np.stack([secrets.encode(t, a, z) for t, a, z, _ in f]))
    assert (p >= model.threshold).mean() >= 0.9
    late = "x " * 15_000 + base()
    assert secrets.base_windows(late) == [secrets.encode(late, 30_000, 30_032).tobytes()]


def test_quality(spark, sf, docs, none):
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = quality.train(d, lab)
    s = quality.score_quality(d, model).join(lab, "doc_id").filter(quality.held_out(F.col("doc_id"))).select("predicted", "quality").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in s]) > 0.85
    out = quality.score_quality(docs, model)
    assert out.count() == len(ODD) and {r["score"] for r in out.filter("doc_id in (6, 7)").collect()}.__len__() == 1
    assert quality.score_quality(none, model).count() == 0
    blank = quality.train(d, lab.filter("false"))
    assert quality.score_quality(docs, blank).filter("score <> 0.5").count() == 0


def test_tokens_packing_and_files(spark, docs, none):
    tk = tokens.tokenizer(P)
    want = [tk.encode(t or "", add_special_tokens=False).ids for _, t, _ in ODD]
    assert [np.frombuffer(b, "<u4").tolist() for b in tokens.ids_of([t for _, t, _ in ODD], P)] == want
    placed = packing.pack_documents(docs)
    rows = placed.collect()
    assert sum(r["length"] for r in rows) == sum(len(w) + 1 for w in want)
    seqs: dict = {}
    for r in rows:
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in seqs.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 1024
    assert len(seqs) <= -(-sum(r["length"] for r in rows) // 1024) + 1
    few = docs.filter("doc_id in (1, 6, 10)")
    whole = packing.assemble(few, packing.pack_documents(few))
    assert sum(len(r["ids"]) for r in whole.collect()) == 4 * sum(len(want[i]) + 1 for i in (0, 5, 11))
    back = binary.read_token_files(binary.write_token_files(docs, new_folder(spark, "t"), P)).orderBy("start").collect()
    ids = sorted(zip([i if i is not None else -1 for i, *_ in ODD], [t or "" for _, t, _ in ODD], want, strict=True))
    assert [np.frombuffer(r["ids"], "<u4").tolist() for r in back] == [w + [2] for *_, w in ids]
    assert [r["start"] for r in back] == np.cumsum([0, *[len(w) + 1 for *_, w in ids]])[:-1].tolist()
    assert packing.pack_documents(none).count() == 0
    assert binary.read_token_files(binary.write_token_files(none, new_folder(spark, "t"), P)).count() == 0


def test_ids_are_those_of_the_plain_call():
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(P)
    added = [a.content for a in plain.get_added_tokens_decoder().values()]
    assert "<|endoftext|>" in added
    texts = ["one two", *(t for a in added for t in (a, f"one{a}two", f"one {a} two\n{a}\nthree.", f"{a}{a} é", a[:-1], a.upper())), "two three."]
    want = [plain.encode(t, add_special_tokens=False).ids for t in texts]
    assert [np.frombuffer(b, "<u4").tolist() for b in tokens.ids_of(texts, P)] == want


def test_planes_round_trip():
    g = np.random.default_rng(0)
    for n in (1, 7, 70_000):
        x = g.integers(0, 2**32 if n == 7 else 50_000, n, dtype=np.uint32)
        assert np.array_equal(binary.from_planes(binary.to_planes(x), n), x)


def test_cuts():
    assert packing.cuts(0) == [] and packing.cuts(1024) == [(0, 1024)] and packing.cuts(2049) == [(0, 1), (1, 1024), (1025, 1024)]


def test_warc(spark):
    big = "<p>" + "x" * 200
    rows = [(1, "u1", big), (2, "u\r\n2", big), (2, None, big), (3, "u3", None), (4, "u4", "small"), (5, "u5", "small"), (None, "u6", big), (6, "u7", "é" * 50_000)]
    d = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("clash"))
    m = warc.write_archives(d, new_folder(spark, "w"))
    got = warc.read_archives(m, with_payload=True).collect()
    kinds = sorted((r["page_id"] or 0, r["record_type"], r["refers_to"], r["payload_bytes"]) for r in got)
    assert kinds == [(0, "revisit", 1, 203), (1, "response", None, 203), (2, "revisit", 1, 203), (2, "revisit", 1, 203), (3, "response", None, 0), (4, "response", None, 5), (5, "response", None, 5), (6, "response", None, 100_000)]
    want = {hashlib.sha256((h or "").encode()).hexdigest() for *_, h in rows}
    assert {r["payload_digest"] for r in got} == want
    assert {r["payload"].decode() for r in got if r["record_type"] == "response"} == {h or "" for *_, h in rows}
    empty = warc.write_archives(d.filter("false"), new_folder(spark, "w"))
    assert warc.read_archives(empty).count() == 0


def test_neighbours(spark):
    g = np.random.default_rng(0)
    v = g.normal(size=(900, 16)).astype(np.float32)
    v[300:420] = v[300]  # copies
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(900, None), (901, [0.0] * 16), (902, [float("nan")] * 16), (903, [1.0, 2.0]), (904, [None] * 16), (None, [1.0] * 16)]
    d = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    index, shards = hnsw.build_index(d, shard_rows=300)
    q = hnsw._usable(d, "embedding").filter("vec_id % 20 = 0").select(F.col("vec_id").alias("query_id"), "v")
    got: dict = {}
    for r in hnsw.search(index, shards, q).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    x, hit = v.astype(np.float64), 0
    for i in range(0, 900, 20):
        s = x @ x[i]
        s[i] = -np.inf
        best = np.lexsort((np.arange(900), -s))[:20].tolist()
        hit += len(set(best) & {j for j, _ in got[i]})
        assert len(got[i]) == 20 and all(abs(s[j] - k) < 1e-9 for j, k in got[i]) and got[i] == sorted(got[i], key=lambda p: (-p[1], p[0]))
    assert hit >= 0.9 * 45 * 20
    few = d.filter("vec_id < 5")
    index, shards = hnsw.build_index(few)
    assert hnsw.search(index, shards, hnsw._usable(few, "embedding").select(F.col("vec_id").alias("query_id"), "v")).count() == 20
    index, shards = hnsw.build_index(d.filter("false"))
    assert hnsw.search(index, shards, q).count() == 0


def test_pipeline(spark, sf, docs, none):
    import corpus_pipeline

    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, sf).count() == 0, name
        out = stage(spark, docs.drop(*CLASH), sf)
        assert name == "packing" or out.columns == docs.drop(*CLASH).columns
        out.count()
    rows = corpus_pipeline.run(spark, sf)
    assert set(rows.columns) == {"doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"} and rows.count() > 50
