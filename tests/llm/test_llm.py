"""The training-data operators against brute force, round trips and odd input."""

import hashlib
import os
import random
import re
import subprocess
import sys
import zlib
from collections import Counter
from pathlib import Path

import pyspark
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from motifspark.llm import chat, components, decontam, html, langid, neardup, packing, pii, quality, secrets, simhash, warc

SF = "/root/testdata/sf0.001"
LOW = {c: c + 32 for c in range(65, 91)}
ODD = [(1, None), (2, ""), (3, " \n\t "), (4, "word"), (5, "Straße ÄÖ über"), (5, "Straße ÄÖ über"), (None, "no id here"), (6, "same " * 3000), (7, "\U0001f600 ok \U0001f600")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").cache()


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, repeated rows, and columns named like the operators' own."""
    own = spark.createDataFrame(ODD, "doc_id long, text string")
    return own.withColumns({c: F.lit("x") for c in ("w", "t", "fp", "cut", "tk", "score", "row", "spans")})


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")


def fingerprint(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOW))
    sh = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] * bool(w)
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def groups(rows):
    """Least id reachable over at most two differing bits, by all pairs."""
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, (_, a) in enumerate(rows):
        for j in range(i):
            if bin(a ^ rows[j][1]).count("1") <= 2:
                parent[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), d), d)
    return {d: least[find(i)] for i, (d, _) in enumerate(rows)}


def test_simhash_against_all_pairs(docs):
    rows = docs.select("doc_id", "text").collect()
    truth = [(r["doc_id"], fingerprint(r["text"])) for r in rows]
    want = groups(truth)
    got = simhash.near_duplicates(docs).collect()
    assert {(r["doc_id"], r["fingerprint"], r["component_id"]) for r in got} == {(d, f"{f:016x}", want[d]) for d, f in truth}
    assert len(got) == len(rows)


def test_covering_masks_meet_every_pair_within_the_radius():
    masks = simhash.covering_masks(2)
    assert len(masks) == 7
    for i in range(64):
        for j in range(i, 64):
            assert any(not m & (1 << i | 1 << j) for m in masks)


@pytest.mark.parametrize("small", [1, 8])
def test_links_of_large_buckets_are_exact(spark, small):
    rng = random.Random(1)
    centre = rng.getrandbits(64)
    fps = {centre ^ sum(1 << rng.randrange(64) for _ in range(rng.randrange(4))) for _ in range(300)} | {rng.getrandbits(64) for _ in range(50)}
    signed = [(x - (1 << 64) if x >> 63 else x,) for x in fps]
    edges = simhash.near_edges(spark.createDataFrame(signed, "fp long"), small=small)
    comp = {r["node"]: r["root"] for r in components.connected_components(edges).collect()}
    want = groups([(s[0], s[0] & (1 << 64) - 1) for s in signed])
    assert {s[0]: comp.get(s[0], s[0]) for s in signed} == want


def test_components_of_a_long_path(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(500, 500), (900, 901), (900, 901)], "u long, v long")
    got = {r["node"]: r["root"] for r in components.connected_components(edges).collect()}
    assert got == {i: 0 for i in range(201)} | {900: 900, 901: 900}


def test_near_copies_by_exact_similarity(spark):
    rng = random.Random(5)
    base = [" ".join(rng.choice("abcdefghij") + str(rng.randrange(300)) for _ in range(rng.randrange(3, 200))) for _ in range(9)]
    texts = [None, "", "one word", "ONE  word", *base]
    for t in base:
        for k in range(40):
            w = t.split()
            for _ in range(k % 7 + k // 20):
                w[rng.randrange(len(w))] = f"new{rng.randrange(9999)}"
            texts.append(" ".join(w))
    sets = []
    for t in texts:
        w = (t or "").lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    root = list(range(len(texts)))
    pairs = [(i, j) for i in range(len(texts)) for j in range(i) if sets[i] == sets[j] or 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])]
    for _ in range(30):
        for i, j in pairs:
            root[i] = root[j] = min(root[i], root[j])
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r["component_id"] for r in neardup.similar_groups(docs).collect()}
    assert got == dict(enumerate(root)) and len(set(root)) < len(texts) - 50
    kept = dict(corpus_pipeline.STAGES)["near_dedup"](spark, docs, SF)
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(set(root))
    again = neardup.similar_groups(docs, frequent=0, broadcast_bytes=0).collect()
    assert {r["doc_id"]: r["component_id"] for r in again} == got
    assert neardup.similar_groups(docs.limit(0)).count() == 0


def brute_quality(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
    lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    c = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    cover = {j for i in range(len(w) - 7) if c[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(cover)


def test_quality_counts(docs, odd):
    for table in (docs, odd):
        text = Counter((r["doc_id"], *brute_quality(r["text"])) for r in table.collect())
        got = quality.quality_rules(table).collect()
        assert Counter((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in got) == text
        for r in got:
            assert r["base_failed"] == (r["n_words"] < 20 or 100 * r["n_repeat_words"] > 30 * r["n_words"])
            assert not (r["base_failed"] and r["kept"])


def test_quality_agrees_with_labels(spark):
    got = quality.quality_rules(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).select("doc_id", "kept", "base_failed")
    both = got.join(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), "doc_id").where("not base_failed").collect()
    assert sum(r["kept"] == (r["quality"] == 1) for r in both) >= 0.98 * len(both)


def test_language_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.fit(docs)
    got = langid.identify(docs, model)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in got.collect())
    per = langid.accuracy(got, docs).collect()
    assert len(per) == 4 and all(r["accuracy"] >= 0.95 for r in per)
    assert got.where("rejected").count() < 0.02 * docs.count()


def test_letters_are_of_category_l():
    assert langid.letters_only("½ ² ① ⅷ 3 _") == "" and langid.letters_only("Ab½cⅧ d_1e") == "ab c d e"


def test_secrets_in_a_very_long_text(spark):
    tokens = [hashlib.md5(str(i).encode()).hexdigest() for i in range(20_000)]
    docs = spark.createDataFrame([(1, " ".join(tokens)), (2, "password=\ufdd0abcdefgh" + tokens[0])], "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in secrets.redact(docs).collect()}
    assert got[1] == " ".join(["[SECRET]"] * len(tokens)) and got[2] == "password=\ufdd0abcdefgh[SECRET]"


def test_language_of_odd_texts(spark, docs, odd, empty):
    model = langid.fit(docs)
    got = langid.identify(odd, model).collect()
    assert len(got) == len(ODD)
    assert {r["lang_pred"] for r in got if r["doc_id"] in (1, 2, 3)} == {"und"}
    assert langid.identify(empty, model).count() == 0
    assert {r["lang_pred"] for r in langid.identify(odd, langid.fit(empty)).collect()} == {"und"}


def test_packing_covers_every_token_once(docs, odd, spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for table in (docs, odd.where("doc_id <> 5")):
        ids = {r["doc_id"]: [*tok.encode(r["text"] or "", add_special_tokens=False).ids, 0] for r in table.collect()}
        pieces = packing.pack_documents(table).collect()
        seqs, seen = {}, {}
        for p in pieces:
            own = ids[p["doc_id"]]
            part = own[p["start"] : p["start"] + p["length"]]
            assert len(part) == p["length"] > 0 and p["doc_tokens"] == len(own)
            assert zlib.crc32(b"".join(i.to_bytes(4, "little") for i in part)) == p["ids_crc32"]
            seqs.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
            seen.setdefault(p["doc_id"], []).append((p["start"], p["length"]))
        for parts in [*seqs.values(), *seen.values()]:
            at = 0
            for start, n in sorted(parts):
                assert start == at
                at += n
        assert all(sum(n for _, n in s) <= 1024 for s in seqs.values())
        assert {d: sum(n for _, n in s) for d, s in seen.items()} == {d: len(i) for d, i in ids.items()}
        report = packing.packing_report(packing.pack_documents(table)).first()
        assert report["n_padding"] == 0


@pytest.mark.parametrize("text", ["a <|endoftext|> b", "x" + " " * 2_000_000 + "y", "\n" * 2_000_000], ids=["added", "spaces", "newlines"])
def test_packing_of_added_tokens_and_long_white_space(spark, text):
    import public_tokenizers
    from tokenizers import Tokenizer

    ids = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")).encode(text, add_special_tokens=False).ids + [0]
    got = sorted((p["start"], p["length"], p["ids_crc32"]) for p in packing.pack_documents(spark.createDataFrame([(1, text)], "doc_id long, text string")).collect())
    assert sum(n for _, n, _ in got) == len(ids)
    assert all(zlib.crc32(b"".join(i.to_bytes(4, "little") for i in ids[a : a + n])) == c for a, n, c in got)


def test_assign_balances_cost():
    placed, left = packing.assign([900, 600, 500, 400, 300, 300], [1024] * 3, packing.PackingSpec())
    assert not left and sum(n for s in placed for _, _, n in s) == 3000
    assert all(sum(n for _, _, n in s) <= 1024 for s in placed)


TURNS = [
    (1, 0, "user", "hi"), (1, 1, "assistant", "hello"), (2, 0, "user", "hi"), (2, 1, "assistant", "hello"), (2, 2, "user", "more"), (3, 0, "user", "hi"),
    (4, 0, "user", "hi there"), (5, 0, "user", "hi there"), (5, 0, "user", "hi there"), (6, 0, None, None), (None, 0, "user", "<|im_end|>"),
]


def test_chat_collapse(spark, empty):
    turns = spark.createDataFrame(TURNS, "conv_id long, turn long, role string, text string").withColumn("prefixes", F.lit(1))
    got = {r["conv_id"]: r for r in chat.format_chats(turns).collect()}
    assert set(got) == {2, 4, 6, None}
    assert got[2]["text"] == "<|im_start|>user\nhi<|im_end|>\n<|im_start|>assistant\nhello<|im_end|>\n<|im_start|>user\nmore<|im_end|>\n"
    assert got[4]["n_copies"] == 2 and "< |im_end|>" in got[None]["text"]
    assert chat.format_chats(turns.limit(0)).count() == 0
    lost = spark.createDataFrame([(None, 0, "user", "a"), (None, 0, "user", "b"), (None, 0, "user", "a"), (9, 0, "user", "a")], "conv_id long, turn long, role string, text string")
    assert sorted((str(r["conv_id"]), r["n_copies"]) for r in chat.format_chats(lost).collect()) == [("9", 2), ("None", 1)]


PAGE = """<html><head><title>T</title><script>var a="</p>";</script></head><body><nav><li>Menu</li></nav><div class="ad">Buy</div>
<article><h1>Head &amp; line</h1><p><b>One   two<br>three<p>Four&nbsp;five<form>in<p>put</form><div class="comments"><div>said</div></div></article><footer>&copy; x</footer>"""


def main_text(page, shared=()):
    return html.main_lines(html.parse(page), set(shared))[0]


def test_html_article():
    assert main_text(PAGE) == ["Head & line", "One two three", "Four five"]
    assert main_text("") == [] and main_text("<div class=ad><article>kept</article>") == ["kept"]
    assert main_text("a < b <p>c") == ["a < b", "c"]
    assert main_text("<div><a href=x>Menu</a> <a href=y>two</a></div><p>text with <a>a link</a></p><div>&copy; us</div>") == ["text with a link"]
    lines = html.parse(PAGE)
    assert [x.text for x in lines if x.noisy] == ["Menu", "Buy", "in", "put", "said", "© x"]


def longest_common_length(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        new = [0]
        for j, y in enumerate(b):
            new.append(row[j] + 1 if x == y else max(new[-1], row[j + 1]))
        row = new
    return row[-1]


def test_longest_common_against_the_table():
    rng = random.Random(8)
    for _ in range(200):
        a, b = ([rng.randrange(6) for _ in range(rng.randrange(15))] for _ in "ab")
        at = html.longest_common(a, b)
        rest = iter(b)
        assert at == sorted(set(at)) and len(at) == longest_common_length(a, b) and all(a[i] in rest for i in at)


def test_html_differencing(spark, empty):
    page = lambda body: f"<body><div>Site name</div><div>{body}</div><div>All about us</div></body>"
    words = [" ".join(f"w{i}x{j}" for j in range(30)) for i in range(6)]
    rows = [(i, f"https://www.h.example/{i // 3}/{i}", page(w)) for i, w in enumerate(words)] + [(10, "https://other/x", page("alone")), (11, None, None), (12, "https://h.example/0/1b", page(words[1]))]
    rows += [(20 + i, f"https://h.example/0/1{c}", page(words[1] + " again")) for i, c in enumerate("cdefg")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({c: F.lit(1) for c in ("cut", "keys", "rank", "hk")})
    for table in (pages, pages.repartition(7)):
        found = html.extract_text(table).collect()
        got = {r["page_id"]: r["text"] for r in found}
        assert {i: got[i] for i in range(6)} == dict(enumerate(words))
        assert got[10] == "Site name\n\nalone\n\nAll about us" and got[11] == "" and got[12] == words[1]
        assert {got[20 + i] for i in range(5)} == {words[1] + " again"}
        assert all(r["n_lines"] == 3 and r["n_shared"] == 2 for r in found if r["page_id"] not in (10, 11))
    assert html.longest_common([1, 2, 3, 4, 2], [2, 9, 3, 2]) == [1, 2, 4]
    none = spark.createDataFrame([], "page_id long, url string, html string")
    assert html.extract_text(none).count() == 0 and html.extract_text(none).columns == html.extract_text(pages).columns


def test_html_differencing_against_brute_force(spark):
    """All pages of a few hosts with shared and own lines; neighbours by a sort in Python, lines by the table."""
    rng = random.Random(9)
    pool = [f"template {i}" for i in range(12)]
    rows = []
    for i in range(60):
        lines = [rng.choice(pool) if rng.random() < 0.5 else f"own {i} {j} " + "x" * 20 for j in range(rng.randrange(1, 9))]
        rows.append((i, f"http://h{i % 3}.example/{rng.randrange(3)}/{rng.randrange(4)}/{i}", "".join(f"<p>{x}</p>" for x in lines), lines))
    want = {}
    for host in range(3):
        own = sorted((html._address(u)[1], i, x) for i, u, _, x in rows if i % 3 == host)
        seen, alone = set(), []
        for r in own:  # pages with the same lines are one
            if tuple(r[2]) not in seen:
                seen.add(tuple(r[2]))
                alone.append(r)
        for r in own:
            k = next(j for j, x in enumerate(alone) if x[2] == r[2])
            near = [j for j in range(max(0, k - 3), min(len(alone), k + 4)) if j != k]
            near.sort(key=lambda j: (-html._near(alone[k][0], alone[j][0]), abs(j - k)))
            kept = r[2]
            for j in near:
                n = longest_common_length(r[2], alone[j][2])
                at = html.longest_common(r[2], alone[j][2])
                assert n == len(at)
                if at and sum(len(r[2][i]) for i in at) < 0.8 * sum(map(len, r[2])):
                    kept = [x for i, x in enumerate(r[2]) if i not in at]
                    break
            want[r[1]] = "\n\n".join(kept)
    pages = spark.createDataFrame([r[:3] for r in rows], "page_id long, url string, html string")
    assert {r["page_id"]: r["text"] for r in html.extract_text(pages).collect()} == want


def test_html_given_pages(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    got = html.extract_text(pages)
    assert got.count() == pages.count() and got.where("n_chars <> length(text) or text like '%<%p>%'").count() == 0


ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)


def test_secret_spans(spark, docs, odd, empty):
    extra = spark.createDataFrame([(100, "\U0001f600 token=secret:abcdefgh PASSWORD: 'hunter2hunter2' AKIAABCDEFGHIJKL " + "0f" * 20), (101, "api_key=short api-key: longenough1")], "doc_id long, text string")
    for table in (docs.select("doc_id", "text"), odd.select("doc_id", "text"), extra):
        want = Counter()
        for r in table.collect():
            t = r["text"] or ""
            sp = [(m.start(), 0, m.end(), "assign") for m in ASSIGN.finditer(t) if len(m[2]) >= 8]
            sp += [(m.start(), 1, m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 16]
            sp += [(m.start(), 2, m.end(), "hex") for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 32]
            want[r["doc_id"], hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, _, b, k in sorted(sp)).encode()).hexdigest()] += 1
        assert Counter((r["doc_id"], r["base_sha256"]) for r in secrets.secret_report(table).collect()) == want


def test_random_tokens_are_found_and_names_are_not(spark):
    rng = random.Random(3)
    draw = lambda abc, n: "".join(rng.choice(abc) for _ in range(n))
    b64 = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    good = [draw(b64, 40) for _ in range(40)] + [draw("0123456789abcdef", 28) for _ in range(40)]
    plain = ["get_user_account_settings_page_2", "2024-01-15-weekly-meeting-notes", "releases/version-2/changes/overview", "aaaaaaaaaaaaaaaaaaaa1111"] * 5
    rows = [(i, f"see {x} here") for i, x in enumerate(good + plain)]
    got = {r["doc_id"]: r["spans"] for r in secrets.secret_report(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert sum(bool(got[i]) for i in range(len(good))) >= 0.9 * len(good)
    assert not any(got[i] for i in range(len(good), len(rows)))
    masked = secrets.redact(spark.createDataFrame(rows[:1], "doc_id long, text string")).first()["text"]
    assert masked == "see [SECRET] here"


def test_tokens_after_an_equals_sign_are_found(spark):
    hidden, key = "Zx9Kq2LmP0vTr8WsYb3NcDf6Gh1J", "q7RkT2vXz9LmB4nHs8JdW1pYc6GfA3eUo5iNtKxV"
    texts = [f"auth={hidden}", f"CREDENTIAL={hidden}", f"https://h.x/y?sig={hidden}&b=1", f"AccountKey={hidden}==", f"AWS_SECRET_ACCESS_KEY={key}", f"x=={hidden}=== y", f"{hidden}=1"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in secrets.redact(docs).collect()}
    want = ["auth=#", "CREDENTIAL=#", "https://h.x/y?sig=#&b=1", "AccountKey=#", "AWS_SECRET_ACCESS_KEY=#", "x==#=== y", "#=1"]
    assert got == {i: t.replace("#", "[SECRET]") for i, t in enumerate(want)}


def test_random_tokens_without_digits_are_found(spark):
    rng = random.Random(4)
    lower = "abcdefghijklmnopqrstuvwxyz"
    good = ["".join(rng.choice(abc) for _ in range(40)) for abc in (lower, lower.upper(), lower + lower.upper()) for _ in range(30)]
    plain = ["internationalization", "Donaudampfschifffahrtsgesellschaft", "getUserAccountSettingsPageTitle", "src/main/java/com/example/service", "some-long-hyphenated-name-here", "12345678901234567890", "-" * 40, "_" * 20]
    docs = spark.createDataFrame([(i, f"see {x} here") for i, x in enumerate(good + plain)], "doc_id long, text string")
    got = {r["doc_id"]: r["spans"] for r in secrets.secret_report(docs).collect()}
    assert sum(bool(got[i]) for i in range(len(good))) >= 0.9 * len(good)
    assert [x for i, x in enumerate(plain, len(good)) if got[i]] == []


def brute_contamination(text, windows):
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(LOW))
    cover, items = set(), set()
    for n in {len(x) for x in windows}:
        for i in range(len(w) - n + 1):
            if found := windows.get(tuple(w[i : i + n])):
                cover |= set(range(i, i + n))
                items |= found
    return len(w), len(cover), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(cover) and 20 * len(cover) >= len(w)


def test_decontamination(spark, docs, odd, empty):
    given = [(str(r["item_id"]), r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    for table, items in ((docs, given), (odd, [("a", "Über same"), ("b", "same " * 20), ("c", None), ("d", ""), ("e", "word"), (None, "ok")])):
        windows = {}
        for k, t in items:
            w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOW))
            n = min(13, len(w))
            for i in range(len(w) - n + 1 if n and k is not None else 0):
                windows.setdefault(tuple(w[i : i + n]), set()).add(k)
        bench = spark.createDataFrame(items, "item_id string, text string")
        want = Counter((r["doc_id"], *brute_contamination(r["text"], windows)) for r in table.collect())
        for limit in (48 << 20, 0):
            got = decontam.decontaminate(table, bench, broadcast_bytes=limit).collect()
            assert Counter((r["doc_id"], r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in got) == want
    none = decontam.decontaminate(docs, spark.createDataFrame([], "item_id string, text string"))
    assert none.count() == docs.count() and none.where("contaminated").count() == 0
    assert decontam.decontaminate(empty, spark.createDataFrame(given, "item_id string, text string")).count() == 0


def test_pii_surrogates(spark):
    rows = [
        (1, "Mail Ann.Lee7@mail3.example.com or ANN.LEE7@MAIL3.EXAMPLE.COM, call +1 (555) 123-4567 from 10.20.30.40."),
        (2, "Again ann.lee7@mail3.example.com, card 4111 1111 1111 1111, 4952935900253052, Frau Weber met Mr. John Smith."),
        (3, None), (4, ""), (5, "nothing here"), (6, "call +1 (555) 123-4567"), (6, "call +1 (555) 123-4567"), (7, "+15551234567"),
    ]
    got = pii.pseudonymise(spark.createDataFrame(rows, "doc_id long, text string").withColumn("found", F.lit(1)), "k").collect()
    text = {r["doc_id"]: r["text"] for r in got}
    assert len(got) == len(rows) and text[3] is None and text[4] == "" and text[5] == "nothing here"
    whole = " ".join(t or "" for t in text.values()).lower()
    for private in ("ann.lee7@", "123-4567", "10.20.30.40", "4111 1111", "4952935900253052", "weber", "smith"):
        assert private not in whole
    mails = re.findall(r"[\w.]+@[\w.]+\w", text[1] + " " + text[2])
    assert len({m.lower() for m in mails}) == 1 and mails[1] == mails[0].upper() and mails[0].endswith(".com")
    assert re.search(r"\+\d \(\d{3}\) \d{3}-\d{4}", text[1]) and text[6] in text[1].replace("call ", "x call ") + text[6]
    assert re.sub(r"\D", "", text[6]) == re.sub(r"\D", "", text[7])
    card = re.sub(r" ", "", re.search(r"\d{4} \d{4} \d{4} \d{4}", text[2])[0])
    assert sum(int(c) if i % 2 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(card)) % 10 == 0
    assert re.search(r"Frau [A-Z][a-z]+ met Mr\. \w+ \w+\.", text[2]) and all(int(x) < 256 for x in re.findall(r"\d+(?=\.\d+\.)", text[1])[-2:])


def replaced(table, key="k"):
    return {r["doc_id"]: r["text"] for r in pii.pseudonymise(table, key).collect()}


def test_pii_of_a_crowded_format(spark):
    """All 10,000 addresses of one-digit octets: a permutation without a fixed point."""
    rows = [(i, ".".join(f"{i:04d}")) for i in range(10_000)]
    got = replaced(spark.createDataFrame(rows, "doc_id long, text string"))
    assert set(got.values()) == {t for _, t in rows} and not any(got[i] == t for i, t in rows)


def test_pii_of_more_names_than_short_surrogates(spark):
    rows = [(i, f"Mr. N{''.join('abcdefghij'[int(c)] for c in str(i))} said") for i in range(20_000)]
    got = replaced(spark.createDataFrame(rows, "doc_id long, text string"))
    assert len(set(got.values())) == len(rows) and not set(got.values()) & {t for _, t in rows}
    assert all(re.fullmatch(r"Mr\. [A-Z][a-z]+ said", t) for t in got.values())
    some = spark.createDataFrame([(i, t) for i, t in rows if i % 3 == 0] * 2, "doc_id long, text string")
    by_join = {r["doc_id"]: r["text"] for r in pii.pseudonymise(some, "k", broadcast_bytes=0).collect()}
    assert by_join == replaced(some) and len(set(by_join.values())) == len(by_join)


NAMES = "Mr. Иван Петров met Mr. O'Brien, Mr. McDonald, MR. JOHN SMITH, Ms. J. Doe, Frau Müller-Lüdenscheidt and Mrs. Anna Maria Schmidt. Later Smith and Schmidt's friend O'Brien left. Mr. Smith, Dr.Smith."


def test_pii_names_by_script_gender_and_mention(spark):
    text = replaced(spark.createDataFrame([(1, NAMES), (2, "Herr von Braun, г-жа Иванова; κυρία Παπαδοπούλου. 王 Dr. 王小明")], "doc_id long, text string"))
    for private in ("Иван", "Петров", "Brien", "Donald", "JOHN", "SMITH", "Smith", "Doe", "Müller", "Lüdenscheidt", "Anna", "Maria", "Schmidt", "Braun", "Иванова", "Παπαδοπούλου", "王小明"):
        assert private not in text[1] + text[2]
    m = re.match(r"Mr\. ([А-Я][а-я]+) ([А-Я][а-я]+) met Mr\. ([A-Z]'[A-Z][a-z]+), Mr\. Mc[A-Z][a-z]+, MR\. ([A-Z]+) ([A-Z]+), Ms\. [A-IK-Z]\. [A-Z][a-z]+, Frau [A-Z][a-z]+-[A-Z][a-z]+ and Mrs\. ([A-Z][a-z]+) [A-Z][a-z]+ ([A-Z][a-z]+)\. Later ([A-Z][a-z]+) and ([A-Z][a-z]+)'s friend ([A-Z]'[A-Z][a-z]+) left\. Mr\. ([A-Z][a-z]+), Dr\.([A-Z][a-z]+)\.", text[1])
    assert m and m[5].title() == m[8] == m[11] == m[12] and m[7] == m[9] and m[3] == m[10]
    ends = lambda w, role: any(w.lower().endswith(e) for e in pii.STOCK["latin"][role].split())
    assert ends(m[4], "given_m") and ends(m[6], "given_f")
    assert re.match(r"Herr von [A-Z][a-z]+, г-жа [А-Я][а-я]+; κυρία [Α-Ω][α-ω]+\.", text[2])


def brute_surrogate(kind, mention, key):
    """Permutation of a format by the definition: rounds over halves, a step, the rounds undone."""
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    norm = mention.lower() if kind == "email" else re.sub(r"[^0-9]+", "", mention) if kind in ("phone", "ssn", "card") else mention.replace(" ", "") if kind == "iban" else mention
    units = []
    if kind == "ip":
        for i, o in enumerate(norm.split(".")):
            lo, size = (0, 10 ** (len(o) - 1) * (10 if len(o) == 1 else 1)) if len(o) == 1 or o[0] == "0" else (10, 90) if len(o) == 2 else (100, 156) if int(o) < 256 else (256, 744)
            units.append((i, lo, 1, size, int(o) - lo))
    else:
        last = norm.rfind(".") if kind == "email" else len(norm) - 1
        allowed = {"email": lambda i: i < last, "iban": lambda i: i >= 4, "phone": lambda i: i >= 1, "card": lambda i: i < last, "ssn": lambda i: True}[kind]
        for i, c in enumerate(norm):
            for lo, hi, step in pii.RANGES:
                if lo <= ord(c) <= hi and (ord(c) - lo) % step == 0 and allowed(i):
                    units.append((i, lo, step, (hi - lo) // step + 1, (ord(c) - lo) // step))
    if not units:
        return mention
    tag = f"{key}|{kind}|{len(norm)}|" + ",".join(f"{i}:{lo}:{size}" for i, lo, _, size, _ in units)
    a, half = [u[4] for u in units], len(units) // 2

    def turn(i, sign):
        seed = f"{tag}|{i}|" + ",".join(map(str, a[half:] if i % 2 == 0 else a[:half]))
        s = sha(seed) + sha("+" + seed)
        for j in range(len(a)):
            if (j < half) == (i % 2 == 0):
                a[j] = (a[j] + sign * int(s[4 * (j % 32) : 4 * (j % 32) + 4], 16)) % units[j][3]

    for i in range(4):
        turn(i, 1)
    a[0] = (a[0] + 1 + int(sha(tag + "|step")[:6], 16) % (units[0][3] - 1)) % units[0][3]
    for i in range(3, -1, -1):
        turn(i, -1)
    if kind == "ip":
        return ".".join(str(u[1] + x).rjust(len(o), "0") for u, x, o in zip(units, a, norm.split("."), strict=True))
    new = list(norm)
    for (i, lo, step, _, _), x in zip(units, a, strict=True):
        new[i] = chr(lo + step * x)
    if kind == "card":
        luhn = lambda d: -sum(int(c) if j % 2 else sum(divmod(2 * int(c), 10)) for j, c in enumerate(reversed(d))) % 10
        new[-1] = str((luhn("".join(new[:-1])) + int(norm[-1]) - luhn(norm[:-1])) % 10)
    if kind == "iban":
        check = lambda x: 98 - int("".join(str(int(c, 36)) for c in x[4:] + x[:2]) + "00") % 97
        new[2:4] = f"{(check(''.join(new)) + int(norm[2:4]) - check(norm)) % 100:02d}"
    if kind == "email":
        return "".join(x if c == c.lower() else x.upper() for c, x in zip(mention, new, strict=True))
    left = iter(new)
    return "".join(next(left) if (c.isdigit() if kind != "iban" else c != " ") else c for c in mention)


def test_pii_against_brute_force(spark):
    import regex

    odd = "DE89 3704 0044 0532 0130 00, GB82WEST12345698765432, 4111 1111 1111 1111, 4952935900253052, 123-45-6789, 1.02.003.999, é.ü@bücher.example.de 用户@例子.公司 X.Y@Z.ORG +1 (555) 123-4567 +15551234567 555-123-4567"
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").union(spark.createDataFrame([(-1, odd)], "doc_id long, text string"))
    kinds = [(k, regex.compile(p)) for k, p in pii.PATTERNS]
    whole, met = regex.compile(pii._ANY), Counter()

    def swap(m):
        kind = next(k for k, p in kinds if p.fullmatch(m[0]))
        met[kind] += 1
        return brute_surrogate(kind, m[0], "k")

    got = replaced(docs)
    for r in docs.collect():
        assert got[r["doc_id"]] == (None if r["text"] is None else whole.sub(swap, r["text"]))
    assert set(met) == {"email", "iban", "ip", "ssn", "card", "phone"}


def test_warc_round_trip(spark):
    big = "é\r\n\r\nWARC/1.1\r\n" * 40_000
    rows = [(1, "http://a/", "x"), (2, "http://b/", "x"), (3, None, None), (4, "http://c/", ""), (5, "http://d/", big), (6, "http://e/", big), (7, "u", "y"), (7, "u", "y"), (None, "n", "z")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("d", F.lit(0))
    got = warc.round_trip(pages, warc.ArchiveSpec(segment_bytes=10_000, chunk_bytes=999)).collect()
    assert not [r for r in got if r["problem"]] and len(got) == len(rows)
    assert Counter(warc.round_trip(pages, warc.ArchiveSpec(segment_bytes=10_000, chunk_bytes=999, broadcast_bytes=0)).collect()) == Counter(got)
    first = {}
    for i, _, h in rows:
        if i is not None:
            first[h or ""] = min(first.get(h or "", i), i)
    want = Counter()
    for i, _, h in rows:
        b = (h or "").encode()
        f = first.get(h or "")
        revisit = i is not None and f != i
        want[i, len(b), warc.sha1_base32(b), "revisit" if revisit else "response", f if revisit else None] += 1
    assert Counter((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in got) == want
    assert warc.round_trip(pages.limit(0)).count() == 0


def test_warc_problems_are_told():
    assert warc.restore([(2, 4, b"cd"), (1, None, b"ab")]) == (b"abcd", None)
    assert warc.restore([(1, None, b"ab"), (3, 4, b"cd")])[1] and warc.restore([(1, None, b"ab"), (2, 9, b"cd")])[1]
    assert warc.unchunk(warc.chunked(b"abc" * 10, 7)) == b"abc" * 10
    with pytest.raises(ValueError):
        warc.unchunk(b"5\r\nab\r\n0\r\n\r\n")


def test_pipeline_stages_against_brute_force(spark, docs):
    kept = corpus_pipeline.keep_identified(spark, docs, SF)
    model = langid.fit(docs)
    enc = langid._encoders(model)
    rows = docs.collect()
    assert {r["doc_id"] for r in kept.collect()} == {r["doc_id"] for r in rows if not langid.classify(r["text"], enc, model)[2]}
    one = corpus_pipeline.keep_one_of_each_group(spark, docs, SF)
    want = groups([(r["doc_id"], fingerprint(r["text"])) for r in rows])
    assert sorted(r["doc_id"] for r in one.collect()) == sorted(set(want.values())) and one.columns == docs.columns
    again = corpus_pipeline.keep_one_of_each_group(spark, docs.union(docs), SF)
    assert again.count() == one.count()
    clean = corpus_pipeline.drop_contaminated(spark, docs, SF)
    flagged = decontam.decontaminate(docs, spark.read.parquet(f"{SF}/benchmark.parquet")).where("contaminated")
    assert clean.count() == docs.count() - flagged.count() and clean.columns == docs.columns
    masked = corpus_pipeline.redact_secrets(spark, docs, SF)
    assert masked.count() == docs.count() and secrets.secret_report(masked).where("n_hex > 0 or n_access > 0").count() == 0
    out = corpus_pipeline.run(spark, SF)
    tokens = out.groupBy("doc_id").agg(F.sum("length").alias("n"), F.max("doc_tokens").alias("m")).collect()
    assert tokens and all(r["n"] == r["m"] for r in tokens)


def test_odd_and_empty_tables(odd, empty, spark):
    for table, n in ((odd, len(ODD)), (empty, 0)):
        assert simhash.near_duplicates(table).count() == n
        assert quality.quality_rules(table).count() == n
        assert secrets.secret_report(table).count() == n
        assert pii.pseudonymise(table, "k").count() == n
        assert packing.pack_documents(table).select("doc_id").distinct().count() == (8 if n else 0)
        assert secrets.redact(table).columns == table.columns
    zero = [r for r in simhash.near_duplicates(odd).collect() if r["doc_id"] in (1, 2, 3)]
    assert {(r["fingerprint"], r["component_id"]) for r in zero} == {("0" * 16, 1)}


def test_near_copies_collect_the_drivers_garbage(spark):
    beans = lambda: {b.getName(): b.getCollectionCount() for b in spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()}
    words = " ".join(f"w{i}" for i in range(60))
    docs = spark.createDataFrame([(1, words), (2, words + " x"), (3, "other words that nobody else has here at all")], "doc_id long, text string")
    before = beans()
    assert {tuple(r) for r in neardup.similar_groups(docs).collect()} == {(1, 1), (2, 1), (3, 3)}
    full = next(n for n in before if "Old" in n or "MarkSweep" in n)
    assert beans()[full] >= before[full] + 3


ON_A_CLUSTER = """
import os, re, time
import pyarrow as pa
from pyspark.sql import SparkSession
from motifspark.sources.shared import release

conf = {"spark.master": "local-cluster[2,1,1024]", "spark.executor.memory": "700m", "spark.ui.enabled": "false", "spark.driver.host": "127.0.0.1"}
spark = SparkSession.builder.config(map=conf).getOrCreate()

def held(batches):
    for b in batches:
        time.sleep(1)  # so that each executor gets a task
        daemon = os.getppid()
        executor = open(f"/proc/{daemon}/stat").read().rsplit(")", 1)[1].split()[1]
        mb = sum(map(int, re.findall(r"Pss_Anon: +([0-9]+)", open(f"/proc/{executor}/smaps_rollup").read()))) // 1024
        yield pa.RecordBatch.from_arrays([pa.array([int(executor)]), pa.array([mb])], ["executor", "mb"])

look = lambda: dict(map(tuple, spark.range(0, 2, 1, 2).mapInArrow(held, "executor long, mb long").collect()))
look()
spark.range(0, 4_000_000, 1, 4).selectExpr("repeat(cast(id as string), 5) t").sort("t").write.format("noop").mode("overwrite").save()
before = look()
release(spark)
after = look()
print("held", sorted(before), sorted(after), min(before[e] - after.get(e, 9999) for e in before), len(before))
"""


def test_release_gives_the_executors_memory_back(tmp_path):
    home = tmp_path / "home"
    (home / "work").mkdir(parents=True)
    for p in Path(pyspark.__file__).parent.iterdir():  # executors keep their logs in Spark's home
        if p.name != "work":
            (home / p.name).symlink_to(p)
    env = {k: v for k, v in os.environ.items() if k != "PYSPARK_SUBMIT_ARGS"}
    env |= {"SPARK_HOME": str(home), "SPARK_LOCAL_DIRS": str(tmp_path / "local"), "SPARK_LOCAL_IP": "127.0.0.1", "SPARK_SCALA_VERSION": "2.13", "PYSPARK_PYTHON": sys.executable}
    ran = subprocess.run([sys.executable, "-c", ON_A_CLUSTER], env=env, cwd=tmp_path, capture_output=True, text=True, timeout=120)
    said = re.search(r"held .* (-?\d+) (\d+)$", ran.stdout, re.M)
    assert said, ran.stderr[-2000:]
    assert int(said[2]) == 2 and int(said[1]) > 50
