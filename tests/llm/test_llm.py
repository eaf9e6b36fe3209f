"""The training-data operators against brute force, on fixtures with nulls, copies and odd rows."""

import hashlib
import random
import re
import textwrap
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F
from tissuebalance.llm import bpe, common, licenses, lines, minhash, packing, pii, pivots, substrings, suffixes, tree
from tissuebalance.llm.language import UNKNOWN, Settings, identify, train
from tissuebalance.llm.op2_packing import library_encoder
from tissuebalance.llm.op10_bpe import encode_decode

public_tokenizers = pytest.importorskip("public_tokenizers")
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, rank int, node string"
BASE = "the quick brown fox jumps over the lazy dog and runs away from the big bad wolf again tonight"


def documents(spark, texts, start=0):
    """Rows with extra columns whose names clash with the operators' own."""
    rows = [(start + k, t, ("en", "de", None)[k % 3], "s", None if t is None else len(t), 1, "x") for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


def odd_texts():
    rng = random.Random(5)
    words = BASE.split()
    out = [None, "", " ", "\n\n", "x", "...", BASE, BASE, BASE.upper(), BASE + " now", "é漢字 😀 " * 30, "a" * 3000, (BASE + "\n") * 40]
    for _ in range(60):
        own = list(words)
        for _ in range(rng.randint(0, 3)):
            own[rng.randrange(len(own))] = rng.choice(["cat", "ran", "42", "wolf's"])
        out.append(" ".join(own) + "\n" + " ".join(rng.choice(words) for _ in range(rng.randint(0, 30))))
    return out


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


def test_bpe_matches_the_library(library):
    rng = random.Random(2)
    alphabet = [*"ab cdest  '\n\t01é漢,.-S😀 ١", "'s", "'re", "'ll ", "<|endoftext|>", " 's"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 50))) for _ in range(2000)]
    texts += ["", "a" * 1500, "abc" * 700, "-" * 3000, "".join(rng.choice("abcdehinorst") for _ in range(2000))]
    machine = bpe.Encoder(bpe.Vocabulary(public_tokenizers.path("byte_bpe_50k.json")))
    for text, ids in zip(texts, machine.encode(texts), strict=True):
        want = library.encode(text, add_special_tokens=False).ids
        assert ids.tolist() == want, text
        decoder = bpe.Decoder(machine.v)
        assert "".join(decoder.feed(ids[k : k + 3]) for k in range(0, len(ids), 3)) + decoder.finish() == library.decode(want, skip_special_tokens=False)


def test_bpe_long_text_and_full_table(library):
    machine = bpe.Encoder(bpe.Vocabulary(public_tokenizers.path("byte_bpe_50k.json")))
    machine.table = bpe.WordTable(bits=7, most_ids=200)
    text = " ".join(f"{BASE} word{k}" for k in range(12000))
    assert next(iter(machine.encode([text]))).tolist() == library.encode(text, add_special_tokens=False).ids


def test_bpe_query_rows(spark, library):
    texts = odd_texts()
    got = {r.doc_id: r for r in encode_decode(documents(spark, texts)).collect()}
    assert len(got) == len(texts)
    for k, t in enumerate(texts):
        ids = library.encode(t or "", add_special_tokens=False).ids
        assert got[k].n_tokens == len(ids)
        assert got[k].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got[k].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert encode_decode(documents(spark, [])).count() == 0


def test_language(spark):
    rng = random.Random(1)
    tongues = {"en": "the of and to in is was that with for".split(), "de": "der die und ich nicht ein zu mit auf ist".split()}
    rows = [(k, " ".join(rng.choice(tongues[lang]) for _ in range(30)), lang, "s", 0, 1, "x") for k in range(120) for lang in [("en", "de")[k % 2]]]
    rows += [(1000, None, "en", "s", 0, 1, "x"), (1001, "12 . !", "de", "s", 0, 1, "x"), (1002, "der und die", None, "s", 0, 1, "x"), (None, "the and of", None, "s", 0, 1, "x")]
    got = identify(spark.createDataFrame(rows, SCHEMA), Settings(sample=100)).collect()
    assert len(got) == len(rows)
    by = {r.doc_id: r for r in got}
    assert by[1000].lang_pred == by[1001].lang_pred == UNKNOWN and by[1002].lang_pred == "de" and by[None].held_out is False
    assert all(by[k].held_out == (zlib.crc32(str(k).encode()) % 3 == 1) and 0 <= by[k].score <= 1 for k in range(120))
    assert np.mean([by[k].lang_pred == ("en", "de")[k % 2] for k in range(120)]) > 0.95
    assert {r.lang_pred for r in identify(documents(spark, ["some text", None])).collect()} <= {UNKNOWN, "en"}
    assert identify(documents(spark, [])).count() == 0


def test_packing(spark, library):
    texts = odd_texts()
    rows = packing.pack(documents(spark, texts), library_encoder, 64).collect()
    ids = [library.encode(t or "", add_special_tokens=False).ids + [0] for t in texts]
    for k, own in enumerate(ids):
        at = 0
        for r in sorted((r for r in rows if r.doc_id == k), key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(own)
            at += r.length
            assert r.ids_crc32 == zlib.crc32(np.array(own[r.start : at], "<u4").tobytes())
        assert at == len(own)
    padding = 0
    for s in {r.sequence_id for r in rows}:
        at = 0
        for r in sorted((r for r in rows if r.sequence_id == s), key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 64
        padding += 64 - at if at & (at - 1) else 0
    assert padding == 0
    assert packing.pack(documents(spark, []), library_encoder).count() == 0


def test_least_squares_reaches_an_exact_histogram():
    h = np.zeros(16, int)
    h[[3, 13]], h[[5, 11]], h[8] = 4, 2, 3
    p = packing.plan(h, 16)
    assert p.residual_tokens in (0, 8) and (p.used[[3, 5, 11, 13]] == h[[3, 5, 11, 13]]).all()


def jaccard_components(texts, words, percent):
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), t or ""))
        sets.append({tuple(w[i : i + words]) for i in range(len(w) - words + 1)} if len(w) >= words else {tuple(w)} if w else set())
    parent = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = a, b
                while parent[x] != x:
                    x = parent[x]
                while parent[y] != y:
                    y = parent[y]
                parent[max(x, y)] = min(x, y)
    out = []
    for a in range(len(texts)):
        while parent[a] != a:
            a = parent[a]
        out.append(a)
    return [len(s) for s in sets], out


def test_near_duplicates(spark):
    texts = odd_texts()
    got = {r.doc_id: r for r in minhash.near_duplicates(documents(spark, texts), minhash.Settings(words=4)).collect()}
    sizes, groups = jaccard_components(texts, 4, 80)
    assert [got[k].n_shingles for k in range(len(texts))] == sizes
    assert [got[k].component_id for k in range(len(texts))] == groups
    assert all(got[k].kept == (groups[k] == k) for k in range(len(texts)))
    assert minhash.near_duplicates(documents(spark, [])).count() == 0


def test_near_duplicates_behind_larger_documents(spark):
    rng = random.Random(8)

    def own(n):
        return [f"w{rng.randrange(10**9)}" for _ in range(n)]

    passage = own(100)
    texts = [" ".join(passage + own(40)) for _ in range(200)]
    texts += [" ".join(passage + own(4)) for _ in range(2)]
    got = {r.doc_id: r.component_id for r in minhash.near_duplicates(documents(spark, texts), minhash.Settings(words=4)).collect()}
    _, groups = jaccard_components(texts, 4, 80)
    assert groups[201] == 200 and [got[k] for k in range(len(texts))] == groups


def test_union_find_over_several_tasks(spark):
    from tissuebalance.llm.common import Workspace

    space = Workspace(spark, "test")
    edges = space.write(spark.createDataFrame([(k + 1, k) for k in range(0, 40) if k % 10 != 9], "a bigint, b bigint"), "edges")
    got = {r.node: r.component for r in minhash.components(edges, space, per_task=5).collect()}
    assert got == {k: k // 10 * 10 for k in range(40)}


def kept_lines(texts, least=5):
    """By brute force: the texts without lines that repeat an earlier one, and how many went as equals and as near ones."""
    seen, out = {}, []
    for t in texts:
        kept, exact, near = [], 0, 0
        for line in (t or "").split("\n"):
            w = tuple(x for x in re.split(r"[\x20\x09\x0B\x0C\x0D]+", line) if x)
            number = {x: i for i, x in enumerate({x for s in (w, *seen) for x in s})}
            code = lambda s: np.array([number[x] for x in s])  # noqa: B023, E731
            if w in seen:
                exact += 1
            elif len(w) >= least and any(lines.within_one(code(w), code(s)) for s in seen if len(s) >= least):
                near += 1
            else:
                kept.append(line)
            if w:
                seen[w] = None
        out.append(("\n".join(kept), exact, near))
    return out


ODD_LINES = ["All rights reserved.", " All  rights reserved. ", "Les.", "}", "漢字" * 150, "https://example.org/" + "a/" * 80, "", "  ", "漢字", BASE, BASE + " now"]


def line_texts():
    rng = random.Random(9)
    return [*odd_texts(), *("\n".join(rng.choice(ODD_LINES) for _ in range(rng.randint(1, 12))) for _ in range(30))]


def test_long_chain_of_rising_ids(spark):
    from tissuebalance.llm.common import Workspace

    space = Workspace(spark, "chain")
    n = 100_000
    edges = space.write(spark.range(n).select((F.col("id") + 1).alias("a"), F.col("id").alias("b")).unionByName(spark.range(10).select((F.col("id") * 7 + 200_003).alias("a"), F.lit(200_001).cast("bigint").alias("b"))), "edges")
    got = minhash.components(edges, space, per_task=20_000).groupBy("component").agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("low")).collect()
    assert sorted((r.component, r.n, r.low) for r in got) == [(0, n + 1, 0), (200_001, 11, 200_001)]


def test_near_duplicates_with_hot_classes_and_hubs(spark, monkeypatch):
    """Copies and near copies beyond the limit of a hot key, repeated and missing ids, rows without words."""
    monkeypatch.setattr(minhash, "hot_limit", lambda rows: 8)
    words = [f"w{k}" for k in range(60)]
    near = [" ".join([*words[:k], f"x{k}", *words[k + 1 :]]) for k in range(58, 38, -1)]
    texts = [" ".join(words)] + [BASE] * 30 + near + [None, "", " "] * 4 + odd_texts()
    frame = documents(spark, texts)
    got = {r.doc_id: r for r in minhash.near_duplicates(frame, minhash.Settings(words=4)).collect()}
    sizes, groups = jaccard_components(texts, 4, 80)
    assert [(got[k].n_shingles, got[k].component_id) for k in range(len(texts))] == list(zip(sizes, groups, strict=True))
    odd = spark.createDataFrame([(5, BASE), (5, BASE), (9, BASE), (None, BASE), (None, None)], "doc_id bigint, text string")
    rows = sorted((str(r.doc_id), str(r.component_id), r.kept) for r in minhash.near_duplicates(odd).collect())
    assert rows == [("5", "5", True), ("5", "5", True), ("9", "5", False), ("None", "None", True), ("None", "None", True)]


def test_lines_against_brute_force(spark):
    texts = line_texts()
    got = {r.doc_id: r for r in lines.dedupe_lines(documents(spark, texts)).collect()}
    for k, want in enumerate(kept_lines(texts)):
        assert (got[k].text, got[k].n_exact, got[k].n_near) == want, k
    assert lines.dedupe_lines(documents(spark, [])).count() == 0


def test_lines_of_repeated_and_missing_ids(spark):
    rows = [(1, "a b c d e\nx"), (1, "a b c d e\nx"), (1, "y\nx"), (None, "x\nnew"), (None, None)]
    got = sorted((str(r.doc_id), r.text) for r in lines.dedupe_lines(spark.createDataFrame(rows, "doc_id bigint, text string")).collect())
    assert sum("x" in t.split("\n") for _, t in got) in (1, 2)  # rows of one id and text are one document
    assert ("None", "new") in got and ("None", "") in got


def test_stage_drops_short_repeats(spark):
    texts = line_texts()
    frame = documents(spark, texts).withColumns({"_doc": F.lit(7), "_version": F.lit("v"), "gone": F.lit(1.5), "row": F.lit("r")})
    out = lines.without_repeated_lines(frame)
    got = {r.doc_id: r for r in out.collect()}
    assert out.columns == frame.columns
    for k, (text, _, _) in enumerate(kept_lines(texts)):
        assert got[k].text == (None if texts[k] is None else text), k
        assert got[k].n_chars == (None if texts[k] is None else len(text)) and (got[k]["_doc"], got[k].gone, got[k].row) == (7, 1.5, "r")


PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def base_spans(text):
    def passes(kind, m):
        d = re.sub("[^0-9]", "", m)
        if kind == "ip":
            return all(int(x) <= 255 for x in m.split("."))
        if kind == "phone":
            return 9 <= len(d) <= 15
        if kind == "card":
            return 13 <= len(d) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(d))) % 10 == 0
        return True

    return [f"{k}:{m.start()}:{m.end()}" for k, p in PATTERNS.items() for m in re.finditer(p, text) if passes(k, m.group())]


def test_personal_data(spark):
    rng = random.Random(3)
    alphabet = [*"ab12345.@+- ()_%\n😀é", "192.168.1.1", "a.b@c.de", "+49 30 1234567", "4111 1111 1111 1111", "call ", "555-123-4567", "joe at foo dot com"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 60))) for _ in range(300)] + [None, "", "1" * 3000, "1-" * 2000, "a" * 50000, "x@y.com_foo@bar.com", "999.1.1.1.5"]
    got = {r.doc_id: r for r in pii.personal_data(documents(spark, texts)).collect()}
    for k, t in enumerate(texts):
        want = base_spans(t or "")
        assert got[k].base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest(), t
        assert set(want) <= set(got[k].spans.split(",")) | {""}
        assert [got[k][f"n_{x}"] for x in PATTERNS] == [sum(s.startswith(x) for s in want) for x in PATTERNS]
    assert pii.personal_data(documents(spark, [])).count() == 0
    out = pii.masked(documents(spark, ["write to a.b@c.de or 10.0.0.1, card 4111 1111 1111 1111", None]))
    assert out.columns == documents(spark, []).columns
    assert [r.text for r in out.orderBy("doc_id").collect()] == ["write to [EMAIL] or [IP], card [CARD]", None]


def loose_corpus():
    """Texts with one looser span each, true or not, and where the true ones stand."""
    rng = random.Random(21)
    names, hosts = ["joe", "ann.lee", "m_kim", "pat9"], ["mail", "corp", "uni-x"]
    texts, true = [], set()
    for k in range(600):
        if k % 4 == 0:
            span = f"{rng.choice(names)} at {rng.choice(hosts)} dot com"
            ahead = rng.choice(["contact ", "please write ", "email: ", "e-mail "])
            kind = "email"
        elif k % 4 == 1:
            span, kind = f"{rng.randint(200, 999)}-{rng.randint(200, 999)}-{rng.randint(1000, 9999)}", "phone"
            ahead = rng.choice(["call ", "phone: ", "tel ", "dial "])
        elif k % 4 == 2:
            span, kind = f"{rng.randint(200, 999)} {rng.randint(200, 999)} {rng.randint(1000, 9999)}", "phone"
            ahead = rng.choice(["order ", "invoice ", "isbn ", "version "])
        else:
            span, kind = ":".join(f"{rng.randint(4096, 65535):x}" for _ in range(8)), "ip"
            ahead = rng.choice(["host ", "from address ", "server "])
        lead = " ".join(rng.choice(BASE.split()) for _ in range(rng.randint(2, 8)))
        texts.append(f"{lead} {ahead}{span} {lead}. Mail a.b@c.com, call +49 30 1234567, host 10.0.0.{k % 250}")
        if k % 4 != 2:
            at = len(lead) + 1 + len(ahead)
            true.add((k, f"{kind}:{at}:{at + len(span)}"))
    return texts, true


def test_added_spans_are_right(spark):
    """Precision and recall of what the classifier adds to the base, against planted spans."""
    texts, true = loose_corpus()
    added = set()
    for r in pii.personal_data(documents(spark, texts)).collect():
        base = set(base_spans(texts[r.doc_id]))
        added |= {(r.doc_id, s) for s in r.spans.split(",") if s and s not in base}
    precision, recall = len(added & true) / max(1, len(added)), len(added & true) / len(true)
    print("added spans: precision", precision, "recall", recall)
    assert precision >= 0.9 and recall >= 0.9
    rows = [(1, "call 555-123-4567"), (1, "call 555-123-4567"), (1, "x"), (None, "a@b.de"), (None, None)]
    odd = pii.personal_data(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert len(odd) == 5 and sum(r.n_email for r in odd) == 1


def vectors(spark, n, seed=1):
    rng = np.random.default_rng(seed)
    x = np.round(rng.normal(0, 0.15, (n, 8)), 3)
    x[n // 2 : n // 2 + n // 4] = x[0]  # one vector held by a quarter of the rows
    return x, spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id bigint, embedding array<double>")


def test_pivots_are_exact(spark):
    x, _ = vectors(spark, 300)
    z = np.floor(256 * x)
    frame = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(z)], "vec_id bigint, embedding array<double>")
    got = pivots.search(frame, frame.where("vec_id % 50 = 0").select(F.col("vec_id").alias("query_id"), "embedding"), 5, n_pivots=4, row_block=64, query_block=2).collect()
    for q in range(0, 300, 50):
        s = z @ z[q]
        order = [k for k in np.lexsort((np.arange(300), -s)).tolist() if k != q][:5]
        assert [(r.vec_id, r.score) for r in sorted((r for r in got if r.query_id == q), key=lambda r: r["rank"])] == [(k, int(s[k])) for k in order]
    assert pivots.search(frame.limit(0), frame.limit(0).select(F.col("vec_id").alias("query_id"), "embedding"), 5).count() == 0


def test_pivots_skip_cells_and_hold_odd_rows(spark):
    from pyspark.sql import Observation

    rng = np.random.default_rng(3)
    far = np.eye(8)[rng.integers(0, 8, 4000)] * 200 + rng.normal(0, 2, (4000, 8))
    z = np.floor(far)
    rows = [(k, v.tolist()) for k, v in enumerate(z)]
    frame = spark.createDataFrame([*rows, (7, z[7].tolist()), (7, (z[7] + 1).tolist()), (None, z[1].tolist()), (9000, [1.0, 2.0])], "vec_id bigint, embedding array<double>").withColumns({"pivots": F.lit(1), "query_id": F.lit("x")})
    seen = Observation("tested")
    queries = frame.where("vec_id % 200 = 0 or vec_id = 9000").select(F.col("vec_id").alias("query_id"), "embedding")
    got = pivots.search(frame, queries, 5, n_pivots=8, row_block=256, query_block=4, observation=seen).collect()
    for q in range(0, 4000, 200):
        s = z @ z[q]
        order = [k for k in np.lexsort((np.arange(4000), -s)).tolist() if k != q][:5]
        assert [(r.vec_id, r.score) for r in sorted((r for r in got if r.query_id == q), key=lambda r: r["rank"])] == [(k, int(s[k])) for k in order]
    assert len(got) == 100 and 0 < seen.get["tested"] < 0.5 * 20 * 4000


def test_tree_with_odd_rows_and_small_leaves(spark):
    x, _ = vectors(spark, 200)
    rows = [(k, v.tolist()) for k, v in enumerate(x)] + [(3, x[3].tolist()), (None, x[1].tolist()), (999, [1.0])]
    frame = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").withColumns({"leaf": F.lit("x"), "block": F.lit(1)})
    got = tree.search(frame, frame.where("vec_id % 20 = 0").select(F.col("vec_id").alias("query_id"), "embedding"), 30, tree.Settings(leaf=2, recall=0.01)).collect()
    assert {r.query_id for r in got} == set(range(0, 200, 20)) and len(got) == 300
    assert tree.search(frame.limit(0), frame.limit(0).select(F.col("vec_id").alias("query_id"), "embedding"), 5).count() == 0


def test_usable_vectors(spark):
    from tissuebalance.llm.vectors import usable

    rows = [(0, [1.0, 2.0]), (1, None), (2, [0.0, 0.0]), (3, [1.0, None]), (4, [1.0, float("nan")]), (5, [float("inf"), 1.0]), (6, [])]
    frame = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    assert [r.vec_id for r in frame.where(usable()).collect()] == [0]
    assert [r.vec_id for r in frame.where(usable(zero=True)).orderBy("vec_id").collect()] == [0, 2]


def test_tree_recall_and_ties(spark):
    x, frame = vectors(spark, 400)
    got = tree.search(frame, frame.where("vec_id % 20 = 0").select(F.col("vec_id").alias("query_id"), "embedding"), 10, tree.Settings(leaf=16, block=40)).collect()
    hits = 0
    for q in range(0, 400, 20):
        s = (x * x[q]).sum(axis=1)
        best = {k for k in np.lexsort((np.arange(400), -s)).tolist() if k != q} and [k for k in np.lexsort((np.arange(400), -s)).tolist() if k != q][:10]
        own = sorted((r for r in got if r.query_id == q), key=lambda r: r["rank"])
        assert [r["rank"] for r in own] == list(range(1, 11)) and all(r.score == s[r.vec_id] for r in own)
        hits += len({r.vec_id for r in own} & set(best))
    assert hits / 200 >= 0.9
    few = frame.where("vec_id < 3")
    assert tree.search(few, few.select(F.col("vec_id").alias("query_id"), "embedding"), 10).count() == 6


def test_tables_between_steps_have_no_checksum_files(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(common, "shared_dir", lambda _: f"file://{tmp_path}")
    space = common.Workspace(spark, "plain")
    table = space.write(spark.range(0, 1000, 1, 8), "ids")
    assert table.count() == 1000
    assert not list(tmp_path.rglob("*.crc"))
    space.drop(table)
    assert not list(tmp_path.rglob("*.parquet"))


def test_suffix_order():
    rng = random.Random(4)
    for _ in range(100):
        s = np.array([rng.randint(1, rng.choice([1, 2, 4])) for _ in range(rng.randint(1, 90))])
        order = suffixes.suffix_array(s, 10**6)
        assert order.tolist() == sorted(range(len(s)), key=lambda i: s[i:].tolist())


def repeats(rows):
    """By brute force: bytes, removed bytes, spans and kept digest of each (id, text)."""
    first: dict[bytes, float] = {}
    for d, t in rows:
        b = (t or "").encode()
        for i in range(len(b) - 49):
            first[b[i : i + 50]] = min(first.get(b[i : i + 50], float("inf")), float("inf") if d is None else d)
    out = []
    for d, t in rows:
        b = (t or "").encode()
        gone = [False] * len(b)
        for i in range(len(b) - 49):
            if first[b[i : i + 50]] < (float("inf") if d is None else d):
                gone[i : i + 50] = [True] * 50
        spans = sum(g and (i == 0 or not gone[i - 1]) for i, g in enumerate(gone))
        out.append((d, len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    return sorted(out, key=str)


def passages(rng):
    return [*odd_texts(), *("ab" * rng.randint(0, 90) + BASE[rng.randint(0, 40) :] + rng.choice(["", "漢" * 40, "a" * 120]) for _ in range(40))]


@pytest.mark.parametrize("heavy", [4096, 3])
def test_substrings_against_brute_force(spark, heavy):
    rng = random.Random(6)
    rows = [(70000 * k, t) for k, t in enumerate(passages(rng))]
    # Clashing columns, repeated rows and ids, null ids, a long text that later ones quote.
    long = " ".join(f"{rng.randrange(10**6)} {x}" for x in BASE.split() for _ in range(700))
    rows += [(5, long), (9_000_000, long[3000:9000] + "x"), (9_000_001, "y" + long[-700:]), (9_000_001, long[:400]), (None, BASE), (None, long[50:150]), (None, long[50:150]), *rows[:3]]
    frame = spark.createDataFrame([(d, t, 1, b"", "x") for d, t in rows], "doc_id bigint, text string, group int, raw binary, shard string")
    got = substrings.without_repeats(frame, heavy=heavy, n_parts=3).collect()
    assert sorted((tuple(r) for r in got), key=str) == repeats(rows)
    assert substrings.without_repeats(documents(spark, [])).count() == 0


def test_texts_that_share_a_piece_but_no_half():
    rng = random.Random(9)
    met = 0
    for _ in range(40):
        noise = [bytes(rng.randrange(32, 127) for _ in range(45)) for _ in range(5)]
        raw = [noise[0] + noise[4][:21] + noise[1], noise[2] + noise[4][:21] + noise[3]]
        docs = substrings.pa.table({"doc": [1, 2], "group": [0, 0], "raw": raw})
        listed = substrings.pa.Table.from_batches(list(substrings.listed(iter(docs.to_batches()), 1)))
        hot = substrings.shared(listed, 9)
        for r in [substrings.sent(docs, hot, 1, 3)] if hot.num_rows else []:
            met += 1
            assert substrings.judged(r).num_rows == 0
    assert met


def test_a_group_is_gathered_once_for_all_shards(monkeypatch):
    rng = random.Random(8)
    raw = [" ".join(rng.choice(BASE.split()) + str(rng.randrange(90)) for _ in range(4000)).encode() for _ in range(24)]
    ids = list(range(len(raw)))
    docs = substrings.pa.table({"doc": ids, "group": [0] * len(raw), "raw": raw})
    calls = []
    monkeypatch.setattr(substrings, "spread", lambda *a: (calls.append(1), suffixes.spread(*a))[1])
    bodies, counts = [], []
    for shards in (1, 800):
        listed = substrings.pa.Table.from_batches(list(substrings.listed(iter(docs.to_batches()), shards)))
        calls.clear()
        found = substrings.sent(docs, listed.set_column(2, "hashes", [[bytes([x[k] & 254 if k % 5 == 0 else x[k] for k in range(len(x))]) for x in listed["hashes"].to_pylist()]]), shards, 3).to_pylist()
        counts.append(len(calls))
        assert len(found) >= 0.9 * shards
        runs = []
        for r in found:
            at = 0
            for row, start, size in zip(np.frombuffer(r["row"], "<i4"), np.frombuffer(r["start"], "<u4"), r["size"], strict=True):
                if r["shard"] >= 0:
                    assert r["text"][at : at + size] == raw[row][start : start + size]
                    at += size
                runs.append((row, start, size))
        bodies.append(sorted(runs))
    assert bodies[0] == bodies[1]
    assert counts[0] == counts[1] <= 2 * len(list(substrings.parts(raw)))


def test_licenses(spark):
    texts = [None, "", "nothing here", "Hello.\nReleased under the MIT License.\nBye.", "licensed under the apache license version 2.0", "Licensed under CC BY-NC 4.0.", "Our license is odd."]
    got = {r.doc_id: r for r in licenses.scan_licenses(documents(spark, texts)).collect()}
    assert {k: r.license for k, r in got.items()} == {3: "MIT", 4: "Apache-2.0", 5: "CC-BY-NC-4.0", 6: None}
    assert got[3].line == 1 and got[3].missing == ""


def test_licenses_wrapped_and_several(spark):
    mit, bsd = licenses.TEMPLATES["MIT"][2], licenses.TEMPLATES["BSD-3-Clause"][1]
    every = [(name, s) for name, statements in licenses.TEMPLATES.items() for s in statements]
    texts = [
        "\n".join(["Notes.", *(f" * {x}" for x in textwrap.wrap(mit, 60)), "", "Other text."]),
        bsd.replace("without ", "without\n"),
        "Released under the MIT License.\nLicensed under the Apache License, Version 2.0.\nReleased under the ISC License.",
        "Our code: Released under the MIT License. Our texts: Licensed under CC BY-SA 4.0. Our license is odd otherwise.",
        "This is free and unencumbered software released into the public\n# domain.",
        " ".join(f"{s} And then some words of prose stand here." for _, s in every),
        mit.replace("any person", "any living person").replace("free of charge, ", "") + "\n" * 3 + "Our license is odd.",
    ]
    rows = licenses.scan_licenses(documents(spark, texts)).orderBy("doc_id", "line").collect()
    got = [[(r.line, r.n_lines, r.license) for r in rows if r.doc_id == k] for k in range(len(texts))]
    assert got[:3] == [[(1, len(textwrap.wrap(mit, 60)), "MIT")], [(0, 2, "BSD-3-Clause")], [(0, 1, "MIT"), (1, 1, "Apache-2.0"), (2, 1, "ISC")]]
    assert got[3] == [(0, 1, "MIT"), (0, 1, "CC-BY-SA-4.0")] and got[4] == [(0, 2, "Unlicense")]
    assert [x[2] for x in got[5]] == [name for name, _ in every]
    assert [x[2] for x in got[6]] == ["MIT", None]
    assert [(r.missing, r.extra) for r in rows if r.doc_id == 6] == [("free of charge", "living"), ("", "")]


def best_common(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        last, row = row, [0]
        for j, y in enumerate(b):
            row.append(last[j] + 1 if x == y else max(row[-1], last[j + 1]))
    return row[-1]


def test_alignments_against_all_stretches():
    rng = random.Random(11)
    for _ in range(60):
        statement = np.array([rng.randrange(5) for _ in range(rng.randint(1, 6))])
        text = np.array([rng.randrange(6) for _ in range(rng.randint(0, 12))], np.int64)
        ends, starts, scores = licenses.alignments(statement, text)
        for e, s, score in zip(ends.tolist(), starts.tolist(), scores.tolist(), strict=True):
            every = [2 * best_common(statement.tolist(), text[a:e].tolist()) - (e - a) for a in range(e + 1)]
            assert score == max(every) == 2 * best_common(statement.tolist(), text[s:e].tolist()) - (e - s)
        for e in range(1, len(text) + 1):
            best = max(2 * best_common(statement.tolist(), text[a:e].tolist()) - (e - a) for a in range(e))
            if best == len(statement):
                assert e in ends.tolist()


def test_licenses_planted_in_prose(spark):
    """Statements with a few words changed, wrapped anywhere, between paragraphs: each is found where it stands."""
    rng = random.Random(12)
    prose = "the river runs past old houses where people sell bread and tell stories about winter".split()
    texts, want = [], []
    for name, statements in licenses.TEMPLATES.items():
        for s in statements:
            w = s.split()
            for _ in range(len(w) // 12):
                w[rng.randrange(1, len(w) - 1)] = "altered"
            lines = [" ".join(prose[: rng.randint(3, 14)]) for _ in range(rng.randint(1, 4))]
            body = textwrap.wrap(" ".join(w), rng.choice([60, 72, 10**6]), break_long_words=False, break_on_hyphens=False)
            want.append((len(lines), len(body), name))
            texts.append("\n".join([*lines, *body, *lines]))
    rows = licenses.scan_licenses(documents(spark, texts)).orderBy("doc_id", "line").collect()
    got = {k: [(r.line, r.n_lines, r.license) for r in rows if r.doc_id == k and r.license] for k in range(len(texts))}
    found = sum(w in got[k] for k, w in enumerate(want))
    named = sum(w[2] in [x[2] for x in got[k]] for k, w in enumerate(want))
    assert named >= len(want) - 1 and found >= 0.9 * len(want), [(w, got[k]) for k, w in enumerate(want) if w not in got[k]]
    assert all(r.missing.count(" ") < 60 for r in rows)


def held_out_quality(spark, folder):
    """Accuracy and expected calibration error (ten bins) on the labelled documents that are not learned from."""
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    said = identify(docs).where("held_out").join(docs.where("lang is not null").select("doc_id", "lang"), "doc_id").toPandas()
    right = (said.lang_pred == said.lang).to_numpy()
    score = said.score.to_numpy()
    which = np.minimum((score * 10).astype(int), 9)
    error = sum(abs(right[which == b].mean() - score[which == b].mean()) * (which == b).mean() for b in range(10) if (which == b).any())
    return right.mean(), error


def test_language_held_out(spark):
    accuracy, error = held_out_quality(spark, "/root/testdata/sf0.01")
    print("held out: accuracy", accuracy, "calibration error", error)
    assert accuracy >= 0.95 and error <= 0.05


def test_many_labels(spark):
    """Every label value among the rows that may be learned from is one of the model's."""
    rows = [(k, f"q{k % 300}z " * 5, f"l{k % 300}", "s", 0, 1, "x") for k in range(1800)]
    model = train(spark.createDataFrame(rows, SCHEMA), Settings(epochs=1))
    assert set(model.languages) == {r[2] for r in rows if zlib.crc32(str(r[0]).encode()) % 3 != 1} and len(model.languages) > 256


def pipeline_texts():
    rng = random.Random(31)
    body = [" ".join(rng.choice(BASE.split()) + str(rng.randrange(50)) for _ in range(40)) for _ in range(25)]
    texts = [*body, *body[:3], body[4] + " end", body[5].replace(" ", "  "), None, "", "12 34", "é" * 40]
    texts += [f"{body[6]}\n{body[7]}\nown words number {k} stand here" for k in range(4)]
    texts += ["write to ann.lee@corp.com or +49 30 1234567 about " + body[8][:60], "host 10.0.0.1 pays 4111 1111 1111 1111 with " + body[9][:60]]
    return texts


def test_pipeline(spark, tiny, tmp_path, library):
    """Every stage's rows, and those of run(), against plain Python on what the stage before left."""
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    texts = pipeline_texts()
    rows = [(k, t, ("en", "de", None)[k % 3], "web", None if t is None else len(t)) for k, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    now = docs
    for name, stage in corpus_pipeline.STAGES:
        before = {r.doc_id: r.text for r in now.collect()}
        now = stage(spark, now, str(tmp_path))
        after = {r.doc_id: r for r in now.collect()} if name != "packing" else {}
        if name != "packing":
            assert now.columns == docs.columns, name
            assert all(r.n_chars == len(r.text) for r in after.values())
        if name == "language":
            said = {r.doc_id: r for r in identify(docs).collect()}
            assert {k: r.lang for k, r in after.items()} == {k: r.lang_pred for k, r in said.items() if r.lang_pred != UNKNOWN and r.score >= 0.5}
        elif name == "lines":
            ids = sorted(before)
            assert [after[k].text for k in ids] == [t for t, _, _ in kept_lines([before[k] for k in ids])]
        elif name == "near_copies":
            ids = sorted(before)
            groups = jaccard_components([before[k] for k in ids], 5, 80)[1]
            assert sorted(after) == [k for i, k in enumerate(ids) if groups[i] == i]
        elif name == "personal":
            for k, t in before.items():
                want = re.sub(PATTERNS["email"], "[EMAIL]", t)
                want = re.sub(PATTERNS["ip"], "[IP]", want)
                want = re.sub(PATTERNS["card"], lambda m: "[CARD]" if len(base_spans(m.group())) and base_spans(m.group())[0].startswith("card:0") else m.group(), want)
                want = re.sub(PATTERNS["phone"], lambda m: "[PHONE]" if 9 <= len(re.sub("[^0-9]", "", m.group())) <= 15 else m.group(), want)
                assert after[k].text == want
        else:
            for out in (now, corpus_pipeline.run(spark, str(tmp_path))):
                pieces = {}
                for r in out.collect():
                    pieces.setdefault(r.doc_id, []).append(r)
                assert pieces.keys() == before.keys()
                for k, own in pieces.items():
                    ids, at = library.encode(before[k], add_special_tokens=False).ids + [0], 0
                    for r in sorted(own, key=lambda r: r.start):
                        assert r.start == at and r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
                        at += r.length
                    assert at == len(ids)
    assert any("[EMAIL]" in (t or "") for t in before.values()) and len(before) < len(texts)


def test_pipeline_of_odd_tables(spark, tiny, tmp_path):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{tiny}/documents.parquet").withColumns({"hashes": F.lit(1), "component": F.lit("x")})
    twice = docs.limit(30).union(docs.limit(30)).union(docs.limit(1).withColumns({"text": F.lit(None).cast("string"), "doc_id": F.lit(None).cast("bigint")}))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, twice, tiny)
        assert out.columns == twice.columns and out.count() <= 61, name
        assert stage(spark, docs.limit(0), tiny).count() == 0, name
    docs.drop("hashes", "component").limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
