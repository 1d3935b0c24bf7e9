"""Classifier, extraction, archives, mixing, chat formatting, token store."""

import hashlib
import io
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from layout_ie.llm import chat, html_text, mixing, quality_model, token_store, warc
from layout_ie.llm.common import fresh_path

from .data import TAIL, frame, prose, rows


# ---------------------------------------------------------------- classifier
def graded_data(n=900):
    bad = ["vile", "rotten", "nasty"]
    out, labels = [], []
    for i in range(n):
        t = prose(60, i)
        g = i % 3
        if g == 0:
            w = t.split()
            w[7], w[20] = bad[i % len(bad)] + ",", bad[(i + 1) % len(bad)].upper()
            t = " ".join(w)
        elif g == 1:
            t = " ".join(x + "$$$" for x in t.split())
        out.append((i, t, "en", "s", 1, *TAIL))
        labels.append((i, 0 if g == 1 else 1, 1 if g == 0 else 0))
    return out, labels


def test_classifier_held_out(spark):
    data, labels = graded_data()
    known = spark.createDataFrame([x for x in labels if x[0] < 600] + [(None, 1, 0), (5, None, None), (99_999, 1, 0)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality_model.grade_documents(frame(spark, data), known).collect()}
    held = [i for i in range(600, 900)]
    assert np.mean([got[i]["grade"] == i % 3 for i in held]) > 0.95
    assert not any(got[i]["kept"] for i in held if i % 3 == 0)
    assert all(0 <= got[i]["expected_grade"] <= 2 and got[i]["p_good"] <= got[i]["p_decent"] for i in held)
    assert np.mean([got[i]["expected_grade"] for i in held if i % 3 == 2]) > np.mean([got[i]["expected_grade"] for i in held if i % 3 == 1])


def test_classifier_edges(spark):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert quality_model.grade_documents(frame(spark), none).count() == len(rows())
    assert quality_model.grade_documents(frame(spark, []), none).count() == 0


# ---------------------------------------------------------------- html
PAGES = {
    1: ("<html><head><title>T</title><style>p{}</style><script>var t=\"</p>\";</script></head><body><nav><ul><li><a href=x>Home</a></li></ul></nav><!-- ad --><div class=\"ad\">Buy the best of all</div>"
        "<article><h1>The  title &amp; more</h1><p><b>The title of it<br><p>A second of the\n parts &copy;.</p><p>Short.</p></article><aside>Side of the page</aside>"
        "<div id=\"comments\"><p>The first reader of this says it is the best of all the pages.</p></div><footer>&copy; x</footer>", "The title & more\nThe title of it\nA second of the parts ©.\nShort."),
    2: (None, ""), 3: ("", ""), 4: ("just text", ""),
    5: ("<div class=\"menu\"><a>one</a> <a>two</a></div><div><p>" + "This is the text of a page that has no article and it is as long as it has to be for the rules to see that it was a text. " * 3 + "</p><p>Short one.</p></div><div class='footer'>end</div>",
        " ".join(("This is the text of a page that has no article and it is as long as it has to be for the rules to see that it was a text. " * 3).split()) + "\nShort one."),
    6: ("<article><p>In <!-- not closed", "In"), 7: ("<article><p>a &lt;b&gt; c &#233; &am &nbsp; d<script>no</article>", "a <b> c é &am d"),
    8: ("<article><header><h1>Head of it</h1></header><form><p>Mail of the reader</p></form><p>Body of the text</p><div class='related posts'>The other</div></article>", "Head of it\nBody of the text"),
}


def test_main_text(spark):
    df = spark.createDataFrame([(k, f"u{k}", h, "x", 5) for k, (h, _) in PAGES.items()], "page_id long, url string, html string, text string, n_chars long")
    got = {r["page_id"]: r for r in html_text.extract(df).collect()}
    for k, (_, want) in PAGES.items():
        assert got[k]["text"] == want, k
        assert got[k]["n_chars"] == len(want)
    assert html_text.extract(df.limit(0)).count() == 0


def test_articles_are_not_lost():
    """Wrappers with a state in their class, marked wrappers, self-closed drawings, a head without its end."""
    article = "<article><p>Body of the text</p></article>"
    for name in ("has-sidebar", "no-sidebar", "with-ads", "post-share-enabled", "widget", "sidebar layout"):
        assert html_text.main_text(f"<div class='{name}'>{article}</div><div class='related'><article>Card</article></div>") == "Body of the text", name
    assert html_text.main_text(f"<body><svg viewBox='0 0 1 1'/>{article}<math/><article>More</article>") == "Body of the text\nMore"
    assert html_text.main_text(f"<html><head><title>T</title><meta charset=x><script>var t='<div>no';</script><body>{article}") == "Body of the text"
    for name in ("site-footer", "comment-list", "widget_text", "ad-300", "shareButtons"):
        assert html_text.main_text(f"<article><p>Body of the text</p><div class='{name}'>Other</div></article>") == "Body of the text", name


# ---------------------------------------------------------------- archives
def test_archives(spark):
    big, other = "ab é" * 400, "zz" * 700
    data = [(1, "http://a b/é", big), (5, None, big), (3, "u", big), (4, "u", "small"), (6, "u", "small"), (7, "u", None), (None, "u", big), (8, "u", other), (-2, "u", "x" * 200_000), (-2, "u", "x" * 200_000)]
    df = spark.createDataFrame([(*d, "c", 1) for d in data], "page_id long, url string, html string, payload string, digest long")
    files = warc.write_archives(df, fresh_path(spark, "warc"))
    got = Counter((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in warc.read_archives(files).collect())
    sha = lambda t: hashlib.sha1((t or "").encode()).hexdigest()
    want = Counter((p, len((h or "").encode()), sha(h), "revisit" if h == big and p in (1, 3) else "response", 5 if h == big and p in (1, 3) else None) for p, _, h in data)
    assert got == want
    back = {r["page_id"]: bytes(r["payload"]).decode() for r in warc.read_archives(files, payloads=True).collect() if r["payload"] is not None}
    assert back[5] == big and back[-2] == "x" * 200_000 and back[7] == ""
    assert warc.round_trip(df.limit(0)).count() == 0


def test_long_headers_and_full_archives(spark, monkeypatch):
    """No header is too long to read, and a task's archives are cut without losing a record."""
    url = "u" * 300_000
    (head, block), = warc.read_records(io.BytesIO(warc.make_record(1, url, b"payload")))
    assert head["warc-target-uri"] == url and warc.http_payload(block) == (7, b"payload")
    pages = spark.createDataFrame([(i, url if i == 3 else f"u{i}", f"<p>{i}</p>" * 300) for i in range(40)], "page_id long, url string, html string")
    monkeypatch.setattr(warc, "ARCHIVE_BYTES", 1)
    files = warc.write_archives(pages, fresh_path(spark, "warc"))
    assert files.agg(F.sum("n_records"), F.count("*"), F.countDistinct("path")).first() == (40, 40, 40)
    assert sorted((r["page_id"], r["url"]) for r in warc.read_archives(files).collect()) == sorted((r["page_id"], r["url"]) for r in pages.collect())


def test_damage_is_found():
    good = warc.make_record(1, "u", b"payload" * 300) + warc.make_record(2, "u", b"", None)
    assert len(list(warc.read_records(io.BytesIO(good)))) == 2
    with pytest.raises((ValueError, zlib.error)):
        list(warc.read_records(io.BytesIO(good[:-5])))
    raw = zlib.decompress(warc.make_record(1, "u", b"payload"), 31).replace(b"payload", b"paYload")
    press = zlib.compressobj(6, zlib.DEFLATED, 31)
    with pytest.raises(ValueError, match="digest"):
        list(warc.read_records(io.BytesIO(press.compress(raw) + press.flush())))


# ---------------------------------------------------------------- mixing
def test_mixing(spark):
    data = [(i, prose(20 + i % 9, i), "en", "hot" if i % 4 else f"c{i % 3}", 1, *TAIL) for i in range(1200)] + [(5000, None, "en", None, 0, *TAIL), (None, "a b", "en", "hot", 0, *TAIL)]
    plan = mixing.mix(frame(spark, data), max_epochs=2.5, block_tokens=500).collect()
    assert len(plan) == len(data)
    tokens, used, epochs = Counter(), Counter(), {}
    for r in plan:
        assert r["copies"] >= 1
        tokens[r["source"]] += r["n_tokens"]
        used[r["source"]] += r["n_tokens"] * r["copies"]
        epochs[r["source"]] = r["epochs"]
    assert min(epochs.values()) == pytest.approx(1) and max(epochs.values()) <= 2.5 + 1e-6
    for s in ("hot", "c0", "c1", "c2"):
        assert used[s] == pytest.approx(epochs[s] * tokens[s], abs=40)
    weights = {r["source"]: r["weight"] for r in plan}
    assert sum(weights.values()) == pytest.approx(1)
    # Each source's places are a permutation without gaps.
    for s in ("hot", "c1"):
        at = 0
        for r in sorted((r for r in plan if r["source"] == s and r["n_tokens"]), key=lambda r: r["place"]):
            assert r["place"] == at
            at += r["n_tokens"]
    # Every copy has a block; a block holds each source's share, up to a document at either end.
    filled = Counter()
    for r in plan:
        assert len(r["blocks"]) == r["copies"] and r["blocks"] == sorted(r["blocks"])
        for b in r["blocks"]:
            filled[r["source"], b] += r["n_tokens"]
    last = max(b for _, b in filled)
    assert last > 20
    for (s, b), n in filled.items():
        if b < last - 1 and s is not None:
            assert n == pytest.approx(500 * weights[s], abs=60), (s, b)
    stream = mixing.block_stream(spark.createDataFrame(plan, mixing.mix(frame(spark, [])).schema)).collect()
    assert Counter((r["source"], r["block"]) for r in stream) == Counter((r["source"], b) for r in plan for b in r["blocks"])
    out = mixing.stage(frame(spark, data), max_epochs=2.5)
    assert out.columns == frame(spark, data).columns
    told = {(r["doc_id"], r["source"]): r["copies"] for r in mixing.mix(frame(spark, data), max_epochs=2.5).collect() if r["doc_id"] is not None}
    assert Counter(r["doc_id"] for r in out.select("doc_id").collect()) == Counter({d: n for (d, _), n in told.items()}) + Counter([None])
    assert {r[0] for r in out.select("doc_id").distinct().collect()} == {d[0] for d in data}
    assert mixing.mix(frame(spark, [])).count() == 0 and mixing.stage(frame(spark, [])).count() == 0


def test_mixing_equals_brute_force(spark):
    """Places, copies and blocks of every document, counted one by one in the order of the permutation."""
    import math

    from pyspark.sql import functions as F

    data = [(i, prose(5 + i * 7 % 31, i), "en", ["big", "big", "big", "mid", None][i % 5] if i % 60 else "rare", 1, *TAIL) for i in range(900)] + [(7, "a b c", "en", "mid", 0, *TAIL), (901, " \n", "en", "big", 0, *TAIL)]
    docs = frame(spark, data)
    plan = mixing.mix(docs, max_epochs=3.3, block_tokens=300).withColumn("order", F.xxhash64("doc_id", "source", F.lit(mixing.SEED))).collect()
    tokens = Counter()
    for r in plan:
        tokens[r["source"]] += r["n_tokens"]
    most, least = max(tokens.values()), min(tokens.values())
    a = max(0.0, 1 - math.log(3.3) / math.log(most / least))
    z = sum((t / sum(tokens.values())) ** a for t in tokens.values())
    for s, total in tokens.items():
        own = sorted((r for r in plan if r["source"] == s), key=lambda r: ((r["order"] % 2**64 >> 24) % mixing.SLICES, r["order"], r["doc_id"]))
        epochs, weight = (most / total) ** (1 - a), (total / sum(tokens.values())) ** a / z
        assert own[0]["epochs"] == pytest.approx(epochs, rel=1e-3) and own[0]["weight"] == pytest.approx(weight, rel=1e-3)
        epochs, weight, place = own[0]["epochs"], own[0]["weight"], 0
        for r in own:
            copies = 1 if not r["n_tokens"] else math.floor(epochs) + (place < (epochs - math.floor(epochs)) * total)
            quota = max(weight * 300, 1.0)
            assert (r["place"], r["copies"]) == (place, copies)
            assert r["blocks"] == [math.floor((place + k * total) / quota) for k in range(copies)]
            place += r["n_tokens"]


def test_entropy_target(spark):
    import math

    shares = [0.7, 0.2, 0.1]
    totals = spark.createDataFrame([(str(i), int(s * 1000), s) for i, s in enumerate(shares)], "source string, tokens long, share double")
    for target in (0.85, 1.0, 1.09):
        a = mixing.find_exponent(totals, 100.0, target)
        z = sum(s**a for s in shares)
        assert -sum(s**a / z * math.log(s**a / z) for s in shares) == pytest.approx(target, abs=1e-3)
    assert mixing.find_exponent(totals, 1.0) == 1.0 and mixing.find_exponent(totals, 1e9) == 0.0


# ---------------------------------------------------------------- chat
TURNS = [(1, 0, "user", "Hi <|end|>\n there"), (1, 1, "assistant", "<|\\x [INST] <\\|a</s>"), (2, 0, None, None), (3, 2, "assistant", "b"), (3, 0, "system", ""), (3, 1, "role\nwith | <|turn|> %20+", "a\n\n<<SYS>>é"), (3, 2, "assistant", "b"), (None, 0, "assistant", "lost"), (4, 0, "assistant", "x" * 70_000)]


def test_chat_round_trip(spark):
    rows_ = spark.createDataFrame([(*t, "clash") for t in TURNS], "conv_id long, turn long, role string, text string, formatted string").unionByName(chat.probe(spark).selectExpr("*", "'c' formatted"))
    formatted = chat.format_turns(rows_)
    got = {r["conv_id"]: r for r in chat.digests(formatted).collect()}
    said = {}
    for c, t, role, text in [*TURNS, (-7, 0, "user", "</s>[INST] ok [/INST]"), (-7, 1, "assistant", "</s>[INST] ok [/INST]")]:
        said.setdefault(c, []).append((t, role or "", text or ""))
    for c, turns in said.items():
        turns.sort()
        loss = "".join(t[2] for t in turns if t[1] == "assistant")
        whole = "".join(f"{r}\n{x}\n" for _, r, x in turns)
        r = got.pop(c)
        assert (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"]) == (len(turns), hashlib.sha256(whole.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert not got
    text = {r["conv_id"]: r["formatted"] for r in formatted.collect()}
    assert text[-7].count("[INST]") == 0 and text[1].count("<|end|>") == 2
    assert chat.digests(chat.format_turns(rows_.limit(0))).count() == 0
    with pytest.raises(ValueError):
        chat.format_turns(rows_.drop("role"))
    # Another vocabulary of columns has another fingerprint and gives the same conversations.
    named = rows_.drop("formatted").toDF("conversation_id", "message_index", "role", "content")
    assert chat.table_layout(named.schema)[1].name == "message_rows" and chat.table_layout(rows_.schema)[1].name == "turn_rows"
    assert chat.table_layout(named.schema)[0] != chat.table_layout(rows_.schema)[0]
    assert sorted(map(str, chat.digests(chat.format_turns(named)).collect())) == sorted(map(str, chat.digests(formatted).collect()))
    lone = spark.createDataFrame([(None, 0, "user", "a"), (None, 1, "user", "b"), (None, 0, "user", "a")], "conv_id long, turn long, role string, text string")
    assert sorted(r["n_turns"] for r in chat.digests(chat.format_turns(lone)).collect()) == [1, 2]


def test_table_fingerprints(spark):
    """Python and the JVM name the same paths alike; typed tables of records go by their fields."""
    table = spark.createDataFrame([(1, [("human", "q"), ("gpt", "a")]), (2, [])], "id int, conversations array<struct<from:string,value:string>>")
    assert chat.schema_paths(table.schema) == ["id", "conversations", "conversations[].from", "conversations[].value"]
    got = {r["id"]: r for r in chat.canonical_table(table, ("id",)).collect()}
    assert [(t["role"], t["text"]) for t in got[1]["turns"]] == [("user", "q"), ("assistant", "a")] and got[2]["turns"] == []
    known = [p for p in chat.schema_paths(table.schema) if p != "id"]
    assert got[1]["fingerprint"] == chat.print_of(known) == spark.range(1).select(chat.paths_hash(F.array(*map(F.lit, known)))).first()[0]
    with pytest.raises(ValueError):
        chat.canonical_table(table.select("id"))


def test_layouts(spark):
    records = [
        '{"messages": [{"role": "User", "content": "q"}, {"role": "assistant", "content": "a", "extra": 1}], "id": 7}',
        '{"conversations": [{"from": "human", "value": "q"}, {"from": "gpt", "value": "a"}]}',
        '{"instruction": "do", "input": "it", "output": "done"}', '{"instruction": "do", "input": "", "output": "done"}', '{"prompt": "p", "completion": "c", "meta": {"x": 1}}',
        '{"question": "q", "answer": null}', '{"what": 1}', "not json", None, '{"system": "s", "conversations": [{"from": "human", "value": "q"}]}',
    ]
    df = spark.createDataFrame(list(enumerate(records)), "i int, record string")
    got = {r["i"]: r for r in chat.canonical_records(df, keep=("i",)).collect()}
    flat = lambda i: [(t["role"], t["text"]) for t in got[i]["turns"]]
    assert got[0]["layout"] == "messages" and flat(0) == [("user", "q"), ("assistant", "a")] == flat(1)
    assert flat(2) == [("user", "do\n\nit"), ("assistant", "done")] and flat(3) == [("user", "do"), ("assistant", "done")]
    assert flat(4) == [("user", "p"), ("assistant", "c")] and flat(5) == [("user", "q"), ("assistant", "")]
    assert flat(9) == [("system", "s"), ("user", "q")]
    assert all(got[i]["layout"] is None and got[i]["turns"] is None for i in (6, 7, 8))


def test_layouts_of_mixed_records(spark):
    """Elements that differ from the first one, and records with paths of a second layout."""
    records = [
        '{"messages": [{"role": "assistant", "tool_calls": [1]}, {"role": "user", "content": "q"}]}', '{"messages": []}',
        '{"messages": [{"role": "user", "content": "q"}, {"from": "gpt", "value": "a"}]}',
        '{"messages": [{"role": "user", "content": "q"}], "prompt": "q", "system": "s"}',
        '{"instruction": "do", "input": "it", "output": "done", "system": "s"}', '{"system": "", "prompt": "p", "response": "r"}',
        '{"messages": [{"what": 1}]}', '{"messages": [], "prompt": "p", "completion": "c"}',
    ]
    df = spark.createDataFrame(list(enumerate(records)), "i int, record string")
    got = {r["i"]: r for r in chat.canonical_records(df, keep=("i",)).collect()}
    flat = lambda i: [(t["role"], t["text"]) for t in got[i]["turns"]]
    assert flat(0) == [("assistant", ""), ("user", "q")] and got[1]["layout"] == "messages" and flat(1) == []
    assert flat(2) == [("user", "q"), ("assistant", "a")] and flat(3) == [("system", "s"), ("user", "q")]
    assert flat(4) == [("system", "s"), ("user", "do\n\nit"), ("assistant", "done")]
    assert got[5]["layout"] == "system_prompt_response" and flat(5) == [("system", ""), ("user", "p"), ("assistant", "r")]
    assert got[6]["layout"] is None and got[6]["turns"] is None
    assert flat(7) == [("user", "p"), ("assistant", "c")]


# ---------------------------------------------------------------- token store
def test_token_store(spark):
    from tokenizers import Tokenizer

    path = fresh_path(spark, "tokens")
    token_store.write_store(frame(spark), path, token_store.default_tokenizer())
    tok = Tokenizer.from_file(token_store.default_tokenizer())
    ids = lambda t: [*tok.encode(t or "", add_special_tokens=False).ids, token_store.END_ID]
    want, start = [], 0
    for r in sorted(rows(), key=lambda r: (r[0] is not None, r[0] or 0)):
        x = ids(r[1])
        want.append((r[0], start, len(x), zlib.crc32(np.array(x, "<u4").tobytes())))
        start += len(x)
    got = sorted((tuple(r) for r in token_store.document_digests(spark, path).collect()), key=lambda r: r[1])
    assert got == want
    back = {r["start"]: list(r["ids"]) for r in token_store.read_documents(spark, path).collect()}
    assert [back[w[1]] for w in want] == [ids(r[1]) for r in sorted(rows(), key=lambda r: (r[0] is not None, r[0] or 0))]
    assert token_store.verify(spark, path)
    names = [bytes(r["digest"]) for r in token_store.read_chunks(spark, path).select("digest").collect()]
    assert len(names) == len(set(names))


def test_store_damage_and_empty(spark):
    path = fresh_path(spark, "tokens")
    token_store.write_store(frame(spark, []), path, token_store.default_tokenizer())
    assert token_store.document_digests(spark, path).count() == 0
    assert token_store.merkle_root([b"a", b"b", b"c"]) != token_store.merkle_root([b"a", b"c", b"b"])
    sha = lambda *x: hashlib.sha256(b"".join(x)).digest()
    leaves = [bytes([i]) for i in range(7)]
    assert token_store.merkle_root(leaves) == sha(sha(sha(leaves[0], leaves[1]), sha(leaves[2], leaves[3])), sha(sha(leaves[4], leaves[5]), leaves[6]))


@pytest.mark.parametrize("damage", ["root", "recipe", "lost chunk"])
def test_reading_a_damaged_store_raises(spark, damage):
    path = fresh_path(spark, "tokens")
    token_store.write_store(frame(spark), path, token_store.default_tokenizer())

    def replace(table, df):
        df.write.parquet(f"{path}/new")
        spark.read.parquet(f"{path}/new").write.mode("overwrite").parquet(f"{path}/{table}")

    if damage == "root":
        replace("manifest", token_store.read_manifest(spark, path).withColumn("merkle", F.unhex(F.sha2(F.hex("merkle"), 256))))
    elif damage == "recipe":
        replace("recipes", token_store.read_recipes(spark, path).withColumn("n_tokens", F.col("n_tokens") + F.coalesce((F.col("doc_id") == 9).cast("long"), F.lit(0))))
    else:
        gone = token_store.read_chunks(spark, path).orderBy("digest").first()["digest"]
        replace("rows/kind=chunk", spark.read.parquet(f"{path}/rows/kind=chunk").where(F.col("digest") != F.lit(bytes(gone))))
    with pytest.raises(Exception, match="manifest|recipes"):
        token_store.document_digests(spark, path).collect()


@pytest.mark.parametrize("seed", range(3))
def test_word_encoding_equals_whole_texts(seed):
    import random

    r = random.Random(seed)
    alphabet = "abcXYZ .,;:!'\t\n0123éÉßüñ中文́  <|>-_\x1f\x85İſΣς’"
    texts = ["".join(r.choice(alphabet) for _ in range(r.randrange(120))) for _ in range(400)] + ["<|endoftext|> A<|ENDOFTEXT|>b", "don't I'LL we'Re", "été É", ""]
    coder = token_store.encoder(token_store.default_tokenizer())
    flat, counts = coder.encode([t.encode() for t in texts])
    at = 0
    for t, n in zip(texts, counts.tolist(), strict=True):
        assert flat[at : at + n].tolist() == coder.tokenizer.encode(t, add_special_tokens=False).ids, t
        at += n


def test_crc_join():
    parts = [b"abc", b"", b"x" * 1000, b"\0" * 77]
    want = zlib.crc32(b"".join(parts))
    assert token_store.join_crcs([(zlib.crc32(p), len(p)) for p in parts]) == want
    many = token_store.join_many(np.array([0, 4, 5]), np.array([*(zlib.crc32(p) for p in parts), 9]), np.array([*map(len, parts), 4]))
    assert many.tolist() == [want, 9]


def test_equal_passages_share_chunks():
    r = np.random.default_rng(1)
    shared = r.integers(0, 49_000, 30_000)
    a, b = np.concatenate((r.integers(0, 49_000, 500), shared)), np.concatenate((r.integers(0, 49_000, 3000), shared, r.integers(0, 49_000, 50)))
    names = []
    for x in (a, b):
        x = x.astype("<u4")
        ends = token_store.cut(x)
        assert ends[-1] == len(x) and max(np.diff([0, *ends])) <= token_store.MOST
        names.append({token_store.digest_of(x[s:e].tobytes()) for s, e in zip([0, *ends], ends)})
    assert len(names[0] & names[1]) > 15
