"""Toxicity and quality: automaton, model and thresholds against plain versions, and held-out accuracy."""

import math
from collections import Counter, defaultdict

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from skewroute.llm import quality, toxicity
from skewroute.llm.common import read_table


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, old = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(row[-1] + 1, old[j] + 1, old[j - 1] + (x != y)))
    return row[-1]


TERMS = [("idiot", False), ("moron", False), ("scum", False), ("vequ", True), ("lostra", True), ("abcde", False), ("abcdf", True)]


@settings(max_examples=300, deadline=None)
@given(st.one_of(st.text("abcdefilmoqrstuv", max_size=9), st.sampled_from(["idiot", "idoit", "idio", "idiott", "xidiot", "scumm", "vequart", "vqu", "lstrada", "lostraa", "abcde"])))
def test_automaton_is_the_edit_distance(word):
    terms = [toxicity.Term(t, 1.0, s) for t, s in TERMS]
    hit = toxicity.LexiconAutomaton(terms).find(word)

    def near(text, stem):
        ways = [distance(word[:k], text) for k in range(len(word) + 1)] if stem else [distance(word, text)]
        best = min(ways)
        return best if best == 0 or best == 1 and len(text) >= toxicity.FUZZY_LENGTH else None

    found = [d for t, s in TERMS if (d := near(t, s)) is not None]
    assert (hit.edits if hit else None) == (min(found) if found else None)


def test_windows_tell_quotation_from_abuse():
    scorer = toxicity.Scorer([toxicity.Term("idiot", 4.0, False)])
    plain = scorer.features("he is an idiot and that is all there is")
    quoted = scorer.features('the report says "idiot" was the word they wrote down')
    aimed = scorer.features("you are an idiot and that is all there is")
    assert quoted[0] < plain[0] < aimed[0] and quoted[5] > 0 == plain[5]
    assert scorer.features("he is an idoit there")[2] == 0 < scorer.features("he is an idiots there")[2]
    assert scorer.features(None) == scorer.features("") == [0.0] * 6


def test_toxicity_learns_from_training_rows_only(spark, odd, empty):
    rows = [(i, f"calm words here {i} and some more of them" + (" zorgle" if i % 4 == 0 else "")) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1, int(i % 4 == 0)) for i, _ in rows] + [(None, 1, 1), (5, 1, None)], "doc_id long, quality int, toxic int")
    model = toxicity.train(docs, labels)
    assert [t.text for t in model.terms] == ["zorgle"]
    tests = spark.createDataFrame([(1, "a zorgle b"), (2, "a zorgl b"), (3, "nothing at all"), (4, None), (5, ""), (4, None), (None, "zorgle")], "doc_id long, text string")
    got = toxicity.score(tests, model).collect()
    assert len(got) == 7 and all(0 <= r["score"] <= 1 for r in got)
    by = {r["doc_id"]: r["score"] for r in got}
    assert by[1] >= 0.5 and by[None] >= 0.5 and by[3] < 0.5 and by[4] == by[5] == by[3]
    assert toxicity.score(empty, model).count() == 0 and toxicity.score(odd, model).count() == odd.count()
    none = toxicity.train(docs, labels.where("toxic = 0"))
    assert toxicity.score(tests, none).where("score >= 0.5").count() == 0
    held = labels.where(toxicity.held_out(F.col("doc_id"))).select("doc_id", F.lit(1).alias("quality"), (1 - F.col("toxic")).alias("toxic"))
    flipped = labels.where(~toxicity.held_out(F.col("doc_id")) & F.col("doc_id").isNotNull()).unionByName(held)
    assert [t.text for t in toxicity.train(docs, flipped).terms] == ["zorgle"]


def test_held_out_accuracy(spark):
    folder = "/root/testdata/sf0.01"
    scored = toxicity.op1_toxicity(spark, folder).join(read_table(spark, folder, "labels"), "doc_id").where("held_out")
    right = scored.agg(F.avg((F.col("predicted") == F.col("toxic")).cast("int")), F.sum(F.when(F.col("toxic") == 0, F.col("predicted")).otherwise(0))).first()
    assert right[0] >= 0.93 and right[1] == 0


class SlowModel:
    """Interpolated modified Kneser-Ney over UTF-16 units with dictionaries."""

    def __init__(self, texts):
        grams = Counter(g for t in texts for g in self.grams(t))
        self.levels = []
        for order in (4, 3, 2):
            n = Counter(min(c, 5) for c in grams.values())
            y = n[1] / max(n[1] + 2 * n[2], 1)
            cuts = {k: min(k, max(0.05, k - (k + 1) * y * n5(grams, k + 1) / n5(grams, k))) if n5(grams, k) and n5(grams, k + 1) else k / 2 for k in (1, 2, 3)}
            ctx = defaultdict(list)
            for g, c in grams.items():
                ctx[g[:-1]].append(c)
            self.levels.append((dict(grams), dict(ctx), cuts))
            grams = Counter(g[1:] for g in grams)
        self.one, self.total = grams, sum(grams.values())

    @staticmethod
    def grams(text):
        raw = text.encode("utf-16-le")
        units = [0, 0, 0] + [int.from_bytes(raw[i : i + 2], "little") for i in range(0, len(raw), 2)]
        return [tuple(units[i : i + 4]) for i in range(len(units) - 3)]

    def p(self, gram):
        p = (self.one.get(gram[-1:], 0) + 1 / 65536) / (self.total + 1)
        for grams, ctx, cuts in reversed(self.levels):
            g = gram[-len(next(iter(grams))) :] if grams else gram
            seen = ctx.get(g[:-1])
            if seen:
                c = grams.get(g, 0)
                left = sum(cuts[min(x, 3)] for x in seen)
                p = (max(c - (cuts[min(c, 3)] if c else 0), 0) + left * p) / sum(seen)
        return p

    def nats(self, text):
        g = self.grams(text)
        return -sum(math.log(self.p(x)) for x in g) / len(g) if g else None


def n5(grams, k):
    return sum(1 for c in grams.values() if c == k)


def test_perplexity_is_the_models(spark, odd, odd_rows):
    trusted = [r[0] for r in odd_rows if r[0] and r[0] >= 100]
    labels = spark.createDataFrame([(i, 1, 0) for i in trusted] + [(1, 0, 0), (None, 1, 0)], "doc_id long, quality int, toxic int")
    held = {r["doc_id"] for r in labels.where(quality.held_out(F.col("doc_id"))).collect()}
    model = SlowModel([r[1] for r in odd_rows if r[0] in set(trusted) - held])
    got = defaultdict(list)
    for r in quality.perplexities(odd.select("doc_id", "lang", "text"), labels).collect():
        got[r["id"]].append(r["nats"])
    for d in (1, 2, 7, 14, 15, 17, 105):
        want = [model.nats(r[1]) for r in odd_rows if r[0] == d]
        assert sorted(got[d]) == pytest.approx(sorted(want), rel=1e-9)
    assert got[4] == [None] and got[5] == [None]


def test_rejection(spark, odd, odd_rows, empty):
    labels = spark.createDataFrame([(r[0], 1, 0) for r in odd_rows if r[0] and r[0] >= 100], "doc_id long, quality int, toxic int")
    junk = spark.createDataFrame([(900, "§§ ØØØØ %%% ### qqqq zzzz ÞÞÞ" * 20, "en", "a", 1)], "doc_id long, text string, lang string, source string, n_chars long")
    both = odd.select("doc_id", "text", "lang", "source", "n_chars").unionByName(junk)
    keep = {r["doc_id"]: r["keep"] for r in quality.classify(both, labels).collect()}
    assert not keep[900] and keep[4] and keep[5] and keep[14] and sum(not keep[i] for i in keep if i and i >= 100 and i != 900) == 0
    assert quality.classify(both, labels.where("quality = 0")).where("NOT keep").count() == 0
    assert quality.classify(empty, labels).count() == 0


def test_quality_on_the_given_table(spark):
    folder = "/root/testdata/sf0.01"
    told = quality.op8_quality(spark, folder).join(read_table(spark, folder, "labels"), "doc_id")
    rate = {r["quality"]: r["k"] for r in told.groupBy("quality").agg(F.avg(F.col("keep").cast("int")).alias("k")).collect()}
    assert rate[1] >= 0.98 and rate[0] <= 0.3
