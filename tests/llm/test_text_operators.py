"""Quality rules, near-duplicates, decontamination and byte repeats against brute force."""

import hashlib
import math
from collections import Counter

import numpy as np
import pytest

from layout_ie.llm import decontaminate, quality_rules, simhash, suffix_dedup
from layout_ie.llm.simhash import RADIUS

from .data import TAIL, frame, prose, rows

SPACE = " \t\n\x0b\x0c\r"


def words_of(text):
    out, word = [], ""
    for c in text or "":
        if c in SPACE:
            if word:
                out.append(word)
            word = ""
        else:
            word += c
    return [*out, word] if word else out


def metrics_by_hand(text):
    w = words_of(text)
    tri = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    n = Counter(tri)
    covered = {i + k for i, t in enumerate(tri) if n[t] > 1 for k in range(3)}
    lines = [x for x in (text or "").split("\n") if words_of(x)]
    return (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered))


def test_quality_metrics(spark):
    got = quality_rules.text_metrics(frame(spark), keep=("doc_id", "text")).collect()
    assert len(got) == len(rows())
    for r in got:
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == metrics_by_hand(r["text"])


def test_binomial_tail(spark):
    from pyspark.sql import functions as F

    for n, k, p in ((10, 0, 0.1), (200, 3, 0.05), (1000, 20, 0.03), (90_000, 100, 0.01)):
        got = spark.range(1).select(quality_rules._log_tail(F.lit(n).cast("long"), F.lit(k).cast("long"), p)).first()[0]
        logs = [math.lgamma(n + 1) - math.lgamma(j + 1) - math.lgamma(n - j + 1) + j * math.log(p) + (n - j) * math.log1p(-p) for j in range(k + 1)]
        top = max(logs)
        assert got == pytest.approx(top + math.log(sum(math.exp(x - top) for x in logs)), rel=1e-9)


def labelled(spark):
    """1500 good documents, one of them with many symbols, and junk."""
    data = [(i, prose(80, i), "en", "s", 1, *TAIL) for i in range(200)]
    good = [(i + 200 * k, t, *rest) for k in range(8) for i, t, *rest in data]
    junk = [(10_000 + i, "".join(w + "*** " for w in prose(80, i).split()), "en", "s", 1, *TAIL) for i in range(50)]
    docs = frame(spark, good + junk)
    labels = spark.createDataFrame([(r[0], 1, 0) for r in good] + [(r[0], 0, 0) for r in junk] + [(77_777, 1, 0), (None, 1, 0), (5, None, None)], "doc_id long, quality int, toxic int")
    return docs, labels


def test_certified_cutoffs_keep_the_good(spark):
    docs, labels = labelled(spark)
    got = quality_rules.apply_rules(docs, labels).select("doc_id", "kept", "failed_rules").collect()
    assert all(r["kept"] for r in got if r["doc_id"] < 10_000)
    assert not any(r["kept"] for r in got if r["doc_id"] >= 10_000)
    kept = quality_rules.stage(docs, labels)
    assert kept.columns == docs.columns and kept.count() == 1600


def test_no_labels_no_cutoffs(spark):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r["kept"] for r in quality_rules.apply_rules(frame(spark), labels).collect()}
    assert got[5] and got[8] and not got[0] and not got[11]
    assert quality_rules.apply_rules(frame(spark, []), labels).count() == 0
    assert quality_rules.stage(frame(spark, []), labels).count() == 0


# ---------------------------------------------------------------- near-duplicates
def print_by_hand(text):
    import xxhash

    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = words_of(w)
    grams = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or ([" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def components_by_hand(prints):
    ids = sorted(prints)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in ids:
        for b in ids:
            if a < b and (prints[a] ^ prints[b]).bit_count() <= RADIUS:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_near_duplicates(spark):
    got = simhash.near_duplicates(frame(spark)).collect()
    assert len(got) == len(rows())
    prints = {r[0]: print_by_hand(r[1]) for r in rows() if r[0] is not None}
    want = components_by_hand(prints)
    for r in got:
        if r["doc_id"] is None:
            assert r["component_id"] is None
        else:
            assert (r["fingerprint"], r["component_id"]) == (f"{prints[r['doc_id']]:016x}", want[r["doc_id"]])
    left = simhash.stage(frame(spark))
    assert left.columns == frame(spark).columns
    assert {r["doc_id"] for r in left.collect()} == {None, *want.values()}
    assert simhash.near_duplicates(frame(spark, [])).count() == 0


@pytest.mark.parametrize("parts", [1, 7])
def test_index_finds_every_link(spark, parts):
    """Chains and dense balls of fingerprints, in one task and over the borders of many."""
    r = np.random.default_rng(parts)
    fps = set(int(x) for x in r.integers(0, 2**63, 300))
    for centre in list(fps)[:4]:
        for _ in range(150):
            x = centre
            for b in r.integers(0, 64, 3):
                x ^= 1 << int(b)
            fps.add(x)
    fps = sorted(fps)
    df = spark.createDataFrame([(i, x - 2**64 if x >= 2**63 else x) for i, x in enumerate(fps)], "doc_id long, fp long")
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", parts)
    try:
        got = {r["node"]: r["root"] for r in simhash.cluster(df).collect()}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)
    assert got == components_by_hand(dict(enumerate(fps)))


def test_components_of_long_chains(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101), (101, 100), (7, 7)], "a long, b long")
    got = {r["node"]: r["root"] for r in simhash.components(edges).collect()}
    assert got == {**{i: 0 for i in range(1, 61)}, 101: 100}


def test_components_of_small_groups_alone(spark):
    """Each graph in a run of its own, as a group that needs more rounds would hide a stop that comes too early."""
    r = np.random.default_rng(5)
    graphs = [[(3, 1), (4, 3), (5, 4), (5, 2)]]
    for n in (6, 8):
        ids = r.permutation(n).tolist()
        graphs.append(list(zip(ids, ids[1:])))
    ids = r.permutation(12).tolist()
    graphs.append([(ids[i], ids[int(r.integers(0, i))]) for i in range(1, 12)])
    for edges in graphs:
        nodes = {x for e in edges for x in e}
        got = {x["node"]: x["root"] for x in simhash.components(spark.createDataFrame(edges, "a long, b long")).collect()}
        assert got == {x: min(nodes) for x in nodes - {min(nodes)}}, edges


# ---------------------------------------------------------------- decontamination
ITEMS = [(1, prose(40, 2)), (2, "one two"), (3, None), (4, " .,; "), (None, prose(20, 2)), (10, "Alpha, beta; GAMMA"), (11, "alpha beta gamma"), (1, prose(30, 77))]


@pytest.mark.parametrize("max_chars", [10**6, 200])
def test_decontamination(spark, max_chars):
    docs = [*rows(), (50, "xx ONE -- two alpha beta gamma", "en", "s", 1, *TAIL), (51, "we say Alpha.beta/gamma twice alpha beta gamma", "en", "s", 1, *TAIL)]
    items = spark.createDataFrame([(*i, "c") for i in ITEMS], "item_id long, text string, body string")
    found = decontaminate.find_contamination(frame(spark, docs), items, max_chars=max_chars)
    got = Counter((r["doc_id"], r["n_words"], sum(x["stop"] - x["first"] for x in r["runs"]), len(r["items"]), hashlib.sha256(",".join(r["items"]).encode()).hexdigest(), bool(r["runs"])) for r in found.collect())
    assert got == Counter(decontaminate.brute_force([r[:2] for r in docs], [i for i in ITEMS if i[0] is not None]))


def test_spans_map_back(spark):
    text = "é — we say  Alpha.beta/gamma; end"
    items = spark.createDataFrame([(10, "alpha beta gamma")], "item_id long, text string")
    r = decontaminate.find_contamination(frame(spark, [(1, text, "en", "s", 1, *TAIL)]), items).first()
    assert [text[s["start"] : s["end"]] for s in r["spans"]] == ["Alpha.beta/gamma"]
    left = decontaminate.stage(frame(spark), items)
    assert left.columns == frame(spark).columns and left.count() == len(rows())
    assert decontaminate.report(frame(spark, []), items).count() == 0


# ---------------------------------------------------------------- byte repeats
def test_byte_repeats(spark):
    shared = prose(60, 42)
    data = [*rows(), (60, "x" + shared + "y", "en", "s", 1, *TAIL), (61, prose(30, 5) + shared + shared, "en", "s", 1, *TAIL), (62, shared[:250], "en", "s", 1, *TAIL), (63, shared[100:299], "en", "s", 1, *TAIL)]
    got = Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(frame(spark, data)).collect())
    assert got == Counter(suffix_dedup.brute_force([r[:2] for r in data]))
    assert suffix_dedup.remove_repeats(frame(spark, [])).count() == 0


def test_hot_grams_and_small_pieces(spark, monkeypatch):
    """A phrase that many documents share in different surroundings, split finely."""
    """Windows of hot grams become contexts of their own; classes of many members go to several tasks."""
    monkeypatch.setattr(suffix_dedup, "HOT", 3)
    monkeypatch.setattr(suffix_dedup, "MEMBERS", 4)
    monkeypatch.setattr(suffix_dedup, "PIECE", 700)
    line = prose(25, 8)
    data = [(i, prose(30, 100 + i % 9) + line + prose(30, 200 + i % 7), "en", "s", 1, *TAIL) for i in range(40)]
    data += [data[3], data[3], (None, data[5][1], *data[5][2:]), (None, prose(90, 5), *data[5][2:]), (None, prose(90, 5), *data[5][2:])]
    got = Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(frame(spark, data)).collect())
    assert got == Counter(suffix_dedup.brute_force([r[:2] for r in data]))


def test_equal_hashes_are_not_taken_for_equal_bytes(spark):
    """Members of a class are compared with its representative; a difference raises."""
    row = lambda kind, doc, body: (7, kind, 1, 2, doc, 0, 0, False, body)
    rows_ = spark.createDataFrame([row(suffix_dedup.REPRESENTATIVE, 1, b"a" * 200), row(suffix_dedup.MEMBER, 1, b"a" * 200), row(suffix_dedup.MEMBER, 2, b"a" * 200)], suffix_dedup._CONTEXT_DDL).coalesce(1)
    assert [tuple(r) for r in suffix_dedup._decided_runs(rows_, 200).collect()] == [(1, 0, 0, 1), (2, 0, 0, 1)]
    other = rows_.unionByName(spark.createDataFrame([row(suffix_dedup.MEMBER, 3, b"b" * 200)], suffix_dedup._CONTEXT_DDL)).coalesce(1).sortWithinPartitions("kind")
    with pytest.raises(Exception, match="hash"):
        suffix_dedup._decided_runs(other, 200).collect()


def test_deep_shallow_sorting():
    r = np.random.default_rng(4)
    text = bytes(r.integers(97, 99, 400, dtype=np.uint8)) * 3 + bytes(r.integers(97, 100, 600, dtype=np.uint8))
    buf = np.frombuffer(text, np.uint8)
    for length in (40, 64, 101):
        starts = np.arange(len(buf) - length + 1)
        group = suffix_dedup.deep_shallow(buf, starts, length, shallow=16)
        seen = Counter(text[i : i + length] for i in starts)
        assert [g >= 0 for g in group] == [seen[text[i : i + length]] > 1 for i in starts]
        names = {}
        for i, g in enumerate(group):
            if g >= 0:
                assert names.setdefault(g, text[i : i + length]) == text[i : i + length]
        assert len(names) == sum(v > 1 for v in seen.values())
