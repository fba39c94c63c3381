"""Every registered text query on written tables: nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns; and independent forms of the models."""

import collections
import glob
import heapq
import itertools
import math
import os
import random
import zlib
from fractions import Fraction

import numpy as np
import pytest
import regex

from volume_engine.llm import html_layout, language_id, lm_scoring, mixing, quality_rules, registry, secret_scan, toxicity

POOL = [a + b for a in "ba de ti ko mu ra ne so li gu".split() for b in "ra te mo ki su".split()]
#: Extra columns with the names of the operators' working columns.
CLASHES = ["pid", "idx", "upto", "ends", "end", "row", "block", "slot", "position", "release", "_rank", "words", "size", "shard", "label", "token", "cls", "n", "shingles", "length", "score", "held_out"]
PER_ROW = ["op1_language_mixture", "op2_context_tree_score", "op5_jaccard_components", "op6_minimax_shards", "op7_pfair_mix", "op8_quality_votes", "op9_factorization_toxicity"]


def ws(text):
    return regex.findall(r"[^\x20\x09-\x0D]+", text or "")


def lower(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def some_texts():
    rng = random.Random(3)
    prose = [". ".join(" ".join(rng.choice(POOL) for _ in range(9)).capitalize() for _ in range(8)) + "." for _ in range(30)]
    texts = [*prose, prose[0], prose[1] + " More.", None, "", " \n ", "one", "one", "\U0001f600 é", " ".join(rng.choice(POOL) for _ in range(40_000))]
    texts[4] += " token = \"04dbebab91ab85687d33eeaaf9ac699e1188f962\""
    return texts


ITEM = "quick proof of every even number above two written out"


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    """A directory of tables, one of the same without rows, and the rows of documents."""
    texts = some_texts()
    texts[6] += " " + ITEM
    rows = [(i, t, ["en", "de", None][i % 3], ["a", "b", None][i % 3 if i % 5 else 0], len(t or "")) for i, t in enumerate(texts)]
    rows += [rows[2], rows[2], rows[32]]  # repeated in full, one of them without a text
    documents = spark.createDataFrame([(*r, *["x"] * len(CLASHES)) for r in rows], "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in CLASHES))
    given = {
        "documents": documents,
        "benchmark": spark.createDataFrame([(0, ITEM), (1, None), (2, "")], "item_id long, text string"),
        "labels": spark.createDataFrame([(i, i % 2, i % 4 == 0 and 1 or 0) for i in range(30)] + [(30, None, None)], "doc_id long, quality int, toxic int"),
        "pages": spark.createDataFrame([(0, "u", "<p>a<p>b"), (1, None, None), (2, "u", ""), (2, "u", "")], "page_id long, url string, html string"),
    }
    full, empty = (str(tmp_path_factory.mktemp(k)) for k in ("full", "empty"))
    for name, df in given.items():
        df.repartition(3).write.parquet(f"{full}/{name}.parquet")
        df.limit(0).write.parquet(f"{empty}/{name}.parquet")
    return full, empty, rows


@pytest.mark.parametrize("name", PER_ROW)
def test_one_result_per_row(spark, tables, name):
    full, _, rows = tables
    out = registry.QUERIES[name](spark, full).collect()
    assert collections.Counter(r.doc_id for r in out) == collections.Counter(r[0] for r in rows)


@pytest.mark.parametrize("name", sorted(registry.QUERIES))
def test_empty_tables(spark, tables, name):
    assert registry.QUERIES[name](spark, tables[1]).collect() == []


def test_shards_query(spark, tables):
    full, _, rows = tables
    out = registry.QUERIES["op6_minimax_shards"](spark, full).collect()
    text = {r[0]: r[1] or "" for r in rows}
    shard_of_text = {}
    for r in out:
        raw = text[r.doc_id].encode()
        assert (r.size, r.text_crc32, r.law, r.grown_shard) == (len(raw) + 1, zlib.crc32(raw), "bytes", None)
        assert shard_of_text.setdefault(text[r.doc_id], r.shard) == r.shard and 0 <= r.shard < 8
    for k in range(8):
        slots = sorted(r.slot for r in out if r.shard == k)
        assert slots == list(range(len(slots)))


def test_leaks_secrets_and_pages_queries(spark, tables):
    leaks = registry.QUERIES["op3_simhash_leaks"](spark, tables[0]).collect()
    assert [(r.doc_id, r.item_id, r.similarity) for r in leaks] == [(6, 0, 1.0)]
    secrets = registry.QUERIES["op4_secret_forest"](spark, tables[0]).collect()
    assert {r.doc_id for r in secrets if r.secret} == {4}
    pages = registry.QUERIES["op10_layout_text"](spark, tables[0]).collect()
    assert sorted((r.page_id, r.text) for r in pages) == [(0, "a\n\nb"), (1, ""), (2, ""), (2, "")]


def test_an_empty_benchmark_leaks_nowhere(spark, tables):
    from volume_engine.llm.decontamination import leaks

    docs = spark.read.parquet(f"{tables[0]}/documents.parquet")
    assert leaks(docs, spark.read.parquet(f"{tables[1]}/benchmark.parquet")).count() == 0


def test_operators_leave_clashing_columns_alone(spark, tables):
    """The operators themselves on rows whose extra columns have the names of working columns."""
    from pyspark.sql import functions as F

    from volume_engine.llm import decontamination, jaccard_join, sharding

    docs = spark.read.parquet(f"{tables[0]}/documents.parquet")
    n = docs.count()
    labels = spark.createDataFrame([(i, i % 2, "x") for i in range(20)], "doc_id long, label int, text string")
    assert toxicity.score_toxicity(docs, labels, F.lit(False)).count() == n
    assert decontamination.leaks(docs, spark.read.parquet(f"{tables[0]}/benchmark.parquet")).count() == 1
    assert jaccard_join.link_components(docs).count() == lm_scoring.score_texts(docs, F.lit(False)).count() == language_id.identify(docs, F.lit(False)).count() == n
    assert secret_scan.scan_secrets(docs).filter("secret").count() == 1 and quality_rules.judge(docs).count() == n
    mixed = mixing.mix(docs)
    assert set(mixed.columns) == set(docs.columns) | set(mixing.ADDED) and sorted(r.position for r in mixed.collect()) == list(range(n))
    assert {r.pid for r in mixed.collect()} == {"x"}
    rows = docs.withColumn("weight", F.lit(1).cast("long"))
    cut = sharding.minimax_shards(rows, ["doc_id", "text"], "weight", 3)
    assert cut.count() == n and {r.pid for r in cut.collect()} == {"x"} and {r.shard for r in cut.collect()} == {0, 1, 2}


def test_pipeline_on_empty_tables_and_chained(spark, tables):
    import corpus_pipeline as p

    assert p.run(spark, tables[1]).count() == 0
    docs = spark.read.parquet(f"{tables[0]}/documents.parquet")
    kept = p.near_duplicates(spark, p.quality(spark, docs, tables[0]), tables[0])  # nothing written in between
    ids = sorted(r.doc_id for r in kept.collect())
    assert kept.columns == p.COLUMNS and ids == [0, 1, *[2] * 3, *range(3, 30)]


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_oracles(spark, name):
    import duckdb

    folder = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for f in glob.glob(f"{folder}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = registry.QUERIES[name](spark, folder)
    columns = sorted(got.columns)
    want = con.sql(f"SELECT {', '.join(columns)} FROM ({registry.ORACLES[name]}) AS q").fetchall()
    assert sorted(map(tuple, got.select(columns).collect())) == sorted(want)


# --- independent forms of the models ---------------------------------------------------------------


def coded(text):
    return " ".join(ws(lower(text))).encode() + b"\n"


class PlainTree:
    """Context-tree weighting node by node, contexts as byte strings, nothing shared with the operator."""

    def __init__(self, texts, depth):
        self.depth, self.counts, self.children = depth, collections.defaultdict(lambda: [0, 0]), collections.defaultdict(set)
        for t in texts:
            for context, byte in self.steps(t):
                for bit in range(8):
                    prefix, value = byte >> (8 - bit), byte >> (7 - bit) & 1
                    for d in range(depth + 1):
                        node = (context[depth - d :], bit, prefix)
                        self.counts[node][value] += 1
                        if d < depth:
                            self.children[node].add((context[depth - d - 1 :], bit, prefix))
        self.known = {}

    def steps(self, text):
        data = coded(text)
        padded = b"\n" * self.depth + data
        return [(padded[i : i + self.depth], byte) for i, byte in enumerate(data)]

    def kt(self, node):
        a, b = self.counts[node]
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)

    def weight(self, node):
        if node not in self.known:
            own = self.kt(node)
            if len(node[0]) == self.depth:
                self.known[node] = own
            else:
                below = sum(self.weight(c) for c in self.children[node])
                self.known[node] = math.log(0.5) + max(own, below) + math.log1p(math.exp(-abs(own - below)))
        return self.known[node]

    def log10(self, text):
        total = 0.0
        for context, byte in self.steps(text):
            for bit in range(8):
                prefix, value = byte >> (8 - bit), byte >> (7 - bit) & 1
                p = None
                for d in range(self.depth, -1, -1):
                    node = (context[self.depth - d :], bit, prefix)
                    if node in self.counts:
                        a, b = self.counts[node]
                        estimate = ((a, b)[value] + 0.5) / (a + b + 1)
                        stop = 1.0 if d == self.depth else math.exp(math.log(0.5) + self.kt(node) - self.weight(node))
                        p = estimate if p is None else stop * estimate + (1 - stop) * p
                total += math.log10(0.5 if p is None else p)
        return total


def test_context_tree_equals_a_plain_one(spark):
    from pyspark.sql import functions as F

    rng = random.Random(8)
    texts = [" ".join(rng.choice(POOL) for _ in range(rng.randrange(1, 25))) for _ in range(30)] + [None, "", "Zz zz", "never seen Ω"]
    train = [t for i, t in enumerate(texts) if i % 4 != 1]
    plain = PlainTree(train, lm_scoring.DEPTH)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in lm_scoring.score_texts(docs, F.col("doc_id") % 4 == 1).collect():
        assert math.isclose(r.score, plain.log10(texts[r.doc_id]), rel_tol=1e-9), r.doc_id


def test_label_model_equals_one_over_single_texts():
    """Expectation-maximisation text by text, with arrays of one-hot votes."""
    rng = np.random.RandomState(2)
    good = rng.rand(400) < 0.7
    votes = np.stack([np.where(rng.rand(400) < 0.3, 0, np.where((rng.rand(400) < q) == good, 1, -1)) for q in (0.9, 0.8, 0.7)], axis=1)
    model = quality_rules.fit_label_model(list(collections.Counter(map(tuple, votes.tolist())).items()), 3)
    hot = votes[:, :, None] == np.array([-1, 0, 1])
    silent = np.clip((votes == 0).mean(axis=0), 0.01, 0.98)
    begin = np.stack([np.stack([0.9 * (1 - silent), silent, 0.1 * (1 - silent)], 1), np.stack([0.1 * (1 - silent), silent, 0.9 * (1 - silent)], 1)])
    theta, prior = begin.copy(), 0.5
    for _ in range(50):
        like = np.exp((np.log(theta)[:, None] * hot[None]).sum(axis=(2, 3)))
        p = prior * like[1] / (prior * like[1] + (1 - prior) * like[0])
        prior = np.clip(p.mean(), 1e-3, 1 - 1e-3)
        mass = np.stack([(hot * (1 - p)[:, None, None]).sum(0), (hot * p[:, None, None]).sum(0)]) + 0.01 * 400 * begin
        theta = mass / mass.sum(axis=2, keepdims=True)
    assert math.isclose(model.prior, prior, rel_tol=1e-9)
    assert np.allclose(model.bad, theta[0]) and np.allclose(model.good, theta[1])


def test_margins_equal_the_sum_over_pairs():
    rng = np.random.RandomState(4)
    machine = toxicity.Machine(0.3, np.arange(0, 40, 2), rng.normal(size=20), rng.normal(size=(20, 3)))
    doc, slot, count = np.repeat(np.arange(6), 9), np.tile(np.arange(9) * 3, 6), rng.randint(1, 5, 54)
    got = machine.margins(doc, slot, count, 6)
    for d in range(6):
        x = {int(s) // 2: math.log1p(c) for s, c in zip(slot[doc == d], count[doc == d]) if s % 2 == 0 and s < 40}
        want = 0.3 + sum(machine.weights[i] * v for i, v in x.items())
        want += sum(float(machine.vectors[i] @ machine.vectors[j]) * x[i] * x[j] for i, j in itertools.combinations(sorted(x), 2))
        assert math.isclose(got[d], want, rel_tol=1e-9)


def test_schedule_equals_one_made_slot_by_slot():
    rng = random.Random(11)
    for _ in range(40):
        names = "abcdefg"[: rng.randrange(1, 7)]
        weights, blocks = {s: Fraction(rng.randrange(1, 30), rng.randrange(1, 9)) for s in names}, {s: rng.randrange(0, 12) for s in names}
        total = sum(weights.values())
        order = [(s, j) for s, j, *_ in mixing.blocks_in_order({s: float(w) if float(w) == w else w for s, w in weights.items()}, blocks)]
        done, want, slot = dict.fromkeys(names, 0), [], 0
        while len(want) < sum(blocks.values()):
            ready = []
            for s in names:
                j, share = done[s], weights[s] / total
                if j < blocks[s] and math.floor(j / share) <= slot:
                    heapq.heappush(ready, (math.ceil((j + 1) / share), -weights[s], s))
            if ready:
                s = ready[0][2]
                want.append((s, done[s]))
                done[s] += 1
            slot += 1
        assert order == want


def test_language_shares_equal_plain_expectation_maximisation():
    rng = np.random.RandomState(6)
    prob = rng.dirichlet(np.ones(language_id.BINS) * 0.05, 3) + 1e-9
    prob /= prob.sum(axis=1, keepdims=True)
    for mix in ([0.7, 0.3, 0.0], [1.0, 0.0, 0.0], [0.4, 0.3, 0.3]):
        code = np.concatenate([rng.choice(language_id.BINS, int(600 * m), p=prob[k]) for k, m in enumerate(mix)]).astype(np.int64)
        share = language_id.infer(code, np.array([len(code)]), np.log(prob))[:, 0]
        plain = np.array([m > 0 for m in mix]) / sum(m > 0 for m in mix)
        for _ in range(60):
            joint = plain[:, None] * prob[:, code]
            plain = (joint / joint.sum(axis=0)).mean(axis=1)
        assert ((share > 0) == (np.array(mix) > 0)).all() and np.allclose(share, plain, atol=0.02)


def test_held_out_findings(spark):
    words = spark.createDataFrame([("then",), ("page",), ("values",)], "word string")
    quality = secret_scan.held_out_quality(secret_scan.example_findings(spark), words)
    assert quality["findings"] > 1000 and quality["precision"] > 0.95 and quality["recall"] > 0.95


def test_dictionary_and_coverage(spark):
    docs = spark.createDataFrame([(0, "Values, values values page page values Values. abc1 x"), (1, None)], "doc_id long, text string")
    known = secret_scan.dictionary(docs)
    assert [r.word for r in known.collect()] == ["values"]
    found = spark.createDataFrame([("myValues12345",), ("04dbebab91ab",)], "candidate string")
    assert {r.candidate: r.spelled for r in secret_scan.spelled(found, known).collect()} == {"myValues12345": 6 / 13, "04dbebab91ab": 0.0}


HOSTILE = {
    "unclosed tags": "<a " * 300_000, "open blocks": "<p>x<div>" * 100_000, "nested lists": "<ul><li>x" * 50_000, "nested tables": "x<table><tr><td>" * 50_000, "selects": "<select><option>a" * 50_000,
    "wide cell": "<table><tr><td>" + "w" * 500_000 + "</td></tr>" + "<tr><td>a<td>b" * 50_000, "spans": "<table>" + "<tr><td colspan=999 rowspan=60000>a<td>b" * 30_000, "comments": "<!--" * 200_000, "rules": "<style>" + ".a.b{display:none}" * 50_000 + "</style>",
}


@pytest.mark.parametrize("kind", HOSTILE)
def test_hostile_pages_take_time_in_proportion(kind):
    import time

    begin = time.process_time()
    html_layout.render(HOSTILE[kind])
    assert time.process_time() - begin < 20


@pytest.mark.parametrize("page,text", [
    ("<table><tr><td rowspan=2>A<td>B<tr><td>C<td>D</table>", "A  B\n   C  D"),
    ("<table><tr><td rowspan=0>A<td>B<tr><td>C<tr><td>D</table>", "A  B\n   C\n   D"),
    ("<style>.h{display:none} @media print{.p{display:none}} @media screen{.s{display:none}} p.k{visibility:hidden}</style><p class=h>a<p class=p>b<p class=s>c<p class=k>d<i style='visibility:visible'>e</i><p class=h style='display:block'>f", "b\n\ne\n\nf"),
    ("<style>#x{display:none} div#x{display:block} /* .y{display:none} */</style><div id=x>a</div><div class=y>b</div>", "a\nb"),
    ("<p>a <b title=\"x>c</b> d", "a c d"),
    ("a<b", "a"),
    ("a < b <3 c", "a < b <3 c"),
])
def test_layout_of_spans_sheets_and_broken_tags(page, text):
    assert html_layout.render(page) == text
