"""The training-data operators against brute force, round trips and the cases their docstrings state."""

from __future__ import annotations

import base64
import collections
import datetime
import hashlib
import re
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from hyperslab.llm import chat, common, decontam, graph, neardup, packing, pii, queries, repetition, secrets, tokenfile, tokens, urls, warc
from hyperslab.shipping import ship

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LONG = " ".join(f"w{k % 977}x{k % 31}" for k in range(30_000))
ODD = [None, "", " ", "\n\n", "a", "a  b", "a   b  c ", "\u00e9\u0301 \ud7ff", "x\ty\u00a0z's don't", "!!! <|endoftext|> ok", "</s>[INST] ok [/INST]", "[\\INST] <\\\\s>", LONG]
DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="module")
def spark(session):
    ship(session)
    return session


def documents(spark, texts):
    return spark.createDataFrame([(k, t, "en", "s", 0) for k, t in enumerate(texts)], DOCS)


def shingle_sets(texts, size=5):
    out = []
    for t in texts:
        w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        out.append({tuple(w[k : k + size]) for k in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set()))
    return out


# Tokens


@pytest.mark.parametrize(("name", "word_ends"), [("byte_bpe_50k.json", False), ("word_bpe_49k.json", True)])
def test_pieces_give_the_ids_of_whole_texts(name, word_ends):
    path = public_tokenizers.path(name)
    ids, at = tokens.encoder(path, word_ends)(pa.array(ODD))
    whole = Tokenizer.from_file(path)
    for k, text in enumerate(ODD):
        assert ids[at[k] : at[k + 1]].tolist() == whole.encode(text or "", add_special_tokens=False).ids


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(st.sampled_from("ab \n\t'\u00a0\u00e9\u0301A1.!<|"), max_size=14), min_size=1, max_size=6), st.booleans())
def test_pieces_give_the_ids_of_any_text(texts, word_ends):
    path = public_tokenizers.path("word_bpe_49k.json" if word_ends else "byte_bpe_50k.json")
    ids, at = tokens.encoder(path, word_ends)(pa.array(texts))
    whole = Tokenizer.from_file(path)
    for k, text in enumerate(texts):
        assert ids[at[k] : at[k + 1]].tolist() == whole.encode(text, add_special_tokens=False).ids, repr(text)


# 1 Chat formatting


@given(st.text(st.sampled_from("<>/s[]INTROLESY\\ "), max_size=24))
def test_escaping_is_undone_and_leaves_no_marker(text):
    out = chat.escaped(text)
    assert chat.unescaped(out) == text
    assert not any(m in out for m in chat.MARKERS)


def test_conversations_read_back(spark):
    rows = [(1, 0, "system", "be <s>good</s>", 9), (1, 1, "user", None, 9), (1, 2, "assistant", "s> <", 9), (1, 3, "assistant", "s> [INST]", 9), (2, 0, None, "x", 9), (2, 1, "tool[ROLE]", LONG, 9), (None, 0, "assistant", "", 9), (3, 0, "user", "a", 9), (3, 0, "user", "a", 9)]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string, part int")
    got = {r["conv_id"]: r for r in chat.digests(chat.formatted(df, queries.byte_tokenizer(), 50_257, part_ids=64), queries.byte_tokenizer(), 50_257).collect()}
    assert set(got) == {1, 2, 3, None}
    for conv in got:
        turns = [(r[2] or "", r[3] or "") for r in rows if r[0] == conv]
        lost = "".join(t for role, t in turns if role == "assistant")
        assert got[conv]["n_turns"] == len(turns)
        assert got[conv]["turns_sha256"] == hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in turns).encode()).hexdigest()
        assert (got[conv]["loss_chars"], got[conv]["loss_sha256"]) == (len(lost), hashlib.sha256(lost.encode()).hexdigest())
    assert chat.formatted(df.where("false"), queries.byte_tokenizer(), 50_257).count() == 0


# 2 Repetition


def repetition_brute(text, window):
    w = WORD.findall(text or "")
    seen = collections.Counter(tuple(w[k : k + window]) for k in range(len(w) - window + 1))
    return len({j for k in range(len(w) - window + 1) if seen[tuple(w[k : k + window])] > 1 for j in range(k, k + window)})


@settings(max_examples=150, deadline=None)
@given(st.lists(st.lists(st.sampled_from("abc"), max_size=40), min_size=1, max_size=5))
def test_suffix_array_finds_what_windows_find(docs):
    texts = [" ".join(d) for d in docs]
    found = repetition.measures(pa.array(texts), repetition.Limits(window=3, repeat_words=6))
    assert found[4].tolist() == [repetition_brute(t, 3) for t in texts]
    assert found[5].tolist() == [repetition_brute(t, 6) for t in texts]
    for text, longest in zip(texts, found[6].tolist(), strict=True):
        assert (repetition_brute(text, longest) > 0 if longest else True) and repetition_brute(text, longest + 1) == 0


def test_rules_on_odd_texts(spark):
    texts = [*ODD, "one two three four five six seven eight nine ten", "same line here\n" * 40]
    got = {r["doc_id"]: r for r in repetition.measure(documents(spark, texts)).collect()}
    assert [got[k]["n_repeat_words"] for k in range(len(texts))] == [repetition_brute(t, 5) for t in texts]
    assert got[0]["base_failed"] and not got[0]["kept"] and got[len(ODD)]["kept"] and got[len(ODD) + 1]["n_dup_lines"] == 39
    kept = repetition.kept_rows(documents(spark, texts))
    assert kept.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert {r["doc_id"] for r in kept.collect()} == {k for k in got if got[k]["kept"]}
    assert repetition.measure(documents(spark, texts).where("false")).count() == 0


# 3 Packing


def test_knapsack_and_program():
    values = np.full(11, -1.0)
    values[[3, 4, 5]] = 3.1, 4.0, 5.3
    best, pattern = packing.knapsack(values, 10)
    assert best == pytest.approx(10.6) and pattern[5] == 2
    demand = np.zeros(11, np.int64)
    demand[[3, 4, 5, 6]] = 7, 9, 4, 5
    patterns, rates, _ = packing.solve(demand, 10, gap=0)
    assert ((patterns.T @ rates) >= demand - 1e-6).all() and (patterns @ np.arange(11) <= 10).all()
    assert rates.sum() <= 13


def test_packing_places_every_id_once(spark):
    texts = [*ODD, *("tok en " * n for n in (3, 700, 1500, 340, 341, 20)), *[LONG[: 37 * k] for k in range(60)]]
    cut = common.written(packing.pieces(documents(spark, texts).repartition(3), queries.byte_tokenizer()), "test-pieces")
    rows = packing.pack(cut).collect()
    whole = Tokenizer.from_file(queries.byte_tokenizer())
    by_doc, by_sequence = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        by_doc[r["doc_id"]].append((r["start"], np.frombuffer(r["ids"], "<u4").tolist(), r["doc_tokens"]))
        by_sequence[r["sequence_id"]].append((r["offset"], r["length"]))
    for k, text in enumerate(texts):
        ids = [*whole.encode(text or "", add_special_tokens=False).ids, 0]
        assert sum((p[1] for p in sorted(by_doc[k])), []) == ids and {p[2] for p in by_doc[k]} == {len(ids)}
    for pieces in by_sequence.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 1024
    total = sum(r["length"] for r in rows)
    assert len(by_sequence) * 1024 <= total * 1.05 + 3 * 1024
    assert packing.pack(common.written(packing.pieces(documents(spark, []), queries.byte_tokenizer()), "test-none")).count() == 0


# 4 Pseudonyms


def luhn(x):
    return sum(sum(divmod(2 * int(d), 10)) if k % 2 else int(d) for k, d in enumerate(reversed(x))) % 10 == 0


def test_pseudonyms_keep_format_and_links(spark):
    card, other = "4111111111111111", "4111111111111112"
    texts = [f"pay {card} or 4111 1111 1111 1111 12, not {other}.", f"again {card} at 97.51.17.173. mail a.b@mail7.example.com!", "call +1 (017) 555-7713 on 1999-02-28, or 31.12.2004", "no 300.1.1.1 and no 2001-02-30", "GB82 WEST 1234 5698 7654 32 and 123-45-6789", None, "", LONG]
    got = {r["doc_id"]: r for r in pii.report(documents(spark, texts), "k").collect()}
    out = [got[k]["text"] for k in range(len(texts))]
    assert card not in out[0] and "4111 1111 1111 1111" not in out[0] and other in out[0]
    made = re.search(r"pay (\d{16}) or (\d{4} \d{4} \d{4} \d{4}) 12, not", out[0])
    assert luhn(made[1]) and made[2].replace(" ", "") == made[1] and made[1] in out[1]
    assert "97.51.17.173" not in out[1] and re.search(r"at \d+\.\d+\.\d+\.\d+\. mail", out[1]) and "example.com" not in out[1]
    assert re.fullmatch(r"call \+\d \(\d{3}\) \d{3}-\d{4} on \d{4}-\d\d-\d\d, or \d\d\.\d\d\.\d{4}", out[2]) and out[2] != texts[2]
    assert out[3] == texts[3] and "123-45-6789" not in out[4] and "WEST 1234" not in out[4]
    assert out[5] is None and out[6] == "" and out[7] == LONG
    wide = documents(spark, texts).selectExpr("*", "lang AS _x")
    assert pii.pseudonymised(wide, "k").columns == wide.columns
    assert pii.report(documents(spark, []), "k").count() == 0


def test_dates_of_all_years_and_orders(spark):
    dates = ["1898-04-12", "2099-12-31", "0001-01-01", "9999-12-31", "12/31/2004", "31/12/2004", "31.12.2004", "2004-12-31", "02/29/2000", "29/02/2000", "03/04/2004", "1600-02-29"]
    bad = ["02/29/2001", "13/32/2004", "12.31.2004", "0000-01-01", "00/10/2004", "1900-02-29", "31/04/0000"]
    got = {r["doc_id"]: r["text"] for r in pii.report(documents(spark, dates + bad), "k").collect()}
    out = dict(zip(dates, (got[k] for k in range(len(dates))), strict=True))
    assert [got[len(dates) + k] for k in range(len(bad))] == bad
    assert all(made != x and re.sub("[0-9]", "0", made) == re.sub("[0-9]", "0", x) for x, made in out.items())
    fields = lambda x, order: tuple(int(re.split("[-./]", x)[k]) for k in order)
    same = {fields(out["12/31/2004"], (2, 0, 1)), fields(out["31/12/2004"], (2, 1, 0)), fields(out["31.12.2004"], (2, 1, 0)), fields(out["2004-12-31"], (0, 1, 2))}
    assert len(same) == 1 and fields(out["02/29/2000"], (2, 0, 1)) == fields(out["29/02/2000"], (2, 1, 0))
    datetime.date(*same.pop())


def test_dates_are_permuted_one_to_one(spark):
    days = [datetime.date(1, 1, 1) + datetime.timedelta(int(k)) for k in np.random.default_rng(6).choice(3_652_059, 4000, replace=False)]
    rows = [r["text"] for r in pii.report(documents(spark, [d.isoformat() for d in days]).repartition(8), "k").collect()]
    assert len({datetime.date.fromisoformat(x) for x in rows}) == len(days)


class Pseudonyms:
    """The pseudonyms once more, one value at a time in plain Python."""

    def __init__(self, key):
        self.key = key
        self.every = re.compile("|".join(f"(?:{p})" for p in pii.KINDS.values()), re.ASCII)

    def walk(self, tweak, left, right, low, high):
        for i in range(10):
            half = right if i % 2 == 0 else left
            step = int(hashlib.sha256(f"{self.key}|{tweak}|{i}|{half}".encode()).hexdigest()[:15], 16)
            left, right = ((left + step) % low, right) if i % 2 == 0 else (left, (right + step) % high)
        return left, right

    def digits(self, tweak, d):
        a = len(d) // 2
        one, two = self.walk(f"{tweak}/{len(d)}", int(d[:a] or 0), int(d[a:]), 10**a, 10 ** (len(d) - a))
        return (f"{one:0{a}d}" if a else "") + f"{two:0{len(d) - a}d}"

    @staticmethod
    def refilled(mask, digits):
        left = iter(digits)
        return "".join(next(left) if c in "0123456789" else c for c in mask)

    def email(self, x):
        return "u" + hashlib.sha256(f"{self.key}|email|{x.lower()}".encode()).hexdigest()[:24] + "@mail.invalid"

    def iban(self, x):
        s = x.replace(" ", "")
        rest = lambda t: int("".join(str(ord(c) - 55) if c.isalpha() else c for c in t)) % 97
        if rest(s[4:] + s[:4]) != 1:
            return x
        account = s[4:]
        d = re.sub("[^0-9]", "", account)
        tail = self.refilled(account, self.digits("iban", d)) if len(d) > 1 else account
        return s[:2] + f"{98 - rest(tail + s[:2] + '00'):02d}" + tail

    def date(self, x):
        n = [int(v) for v in re.split("[-./]", x)]

        def day(y, m, d):
            try:
                return datetime.date(y, m, d)
            except ValueError:
                return None

        if x[4] == "-":
            at, form = day(*n), "{0:04d}{1:02d}{2:02d}"
        elif day(n[2], n[1], n[0]) or x.count("/") < 2:
            at, form = day(n[2], n[1], n[0]), "{2:02d}{1:02d}{0:04d}"
        else:
            at, form = day(n[2], n[0], n[1]), "{1:02d}{2:02d}{0:04d}"
        if not at:
            return x
        month = (at.year - 1) * 12 + at.month - 1
        if at.day <= 12:
            one, two = self.walk("date/early", *divmod(month * 12 + at.day - 1, 1212), 1188, 1212)
            m, d = divmod(one * 1212 + two, 12)
            d += 1
        else:
            place = month * 19 + at.day - 13
            while True:
                one, two = self.walk("date/late", *divmod(place, 1818), 1254, 1818)
                place = one * 1818 + two
                m, d = place // 19, place % 19 + 13
                if m < 9999 * 12 and day(m // 12 + 1, m % 12 + 1, d):
                    break
        return self.refilled(x, form.format(m // 12 + 1, m % 12 + 1, d))

    def address(self, x):
        p = [int(v) for v in x.split(".")]
        if max(p) > 255:
            return x
        a, b = self.walk("address", p[0] * 256 + p[1], p[2] * 256 + p[3], 65536, 65536)
        return f"{a // 256}.{a % 256}.{b // 256}.{b % 256}"

    def phone(self, x):
        d = re.sub("[^0-9]", "", x) if x[0] == "+" else "1" + re.sub("[^0-9]", "", x)
        country = re.match(pii.COUNTRY, d)
        country = country[1] if country else ""
        rest = d[len(country) :]
        if not country or not 7 <= len(rest) <= 14 or len(d) > 15:
            return x
        made = self.digits(f"phone/{country}", rest)
        return self.refilled(x, country + made if x[0] == "+" else made)

    def social(self, x):
        if re.search("^(000|666|9)|-00-|-0000$", x):
            return x
        areas = [a for a in range(1, 900) if a != 666]
        place = (areas.index(int(x[:3])) * 99 + int(x[4:6]) - 1) * 9999 + int(x[7:]) - 1
        a, b = self.walk("social", *divmod(place, 9999), 898 * 99, 9999)
        return f"{areas[a // 99]:03d}-{a % 99 + 1:02d}-{b + 1:04d}"

    def card(self, x):
        d = re.sub("[^0-9]", "", x)
        if not luhn(d) or not d.strip("0"):
            return x
        made = d[:6] + self.digits(f"card/{d[:6]}", d[6:-1])
        return self.refilled(x, next(made + str(c) for c in range(10) if luhn(made + str(c))))

    def of(self, x):
        kind = next(k for k, p in pii.KINDS.items() if re.fullmatch(p, x, re.ASCII))
        return getattr(self, kind)(x)

    def text(self, t):
        return None if t is None else self.every.sub(lambda m: self.of(m[0]), t)


def test_pseudonyms_against_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    brute, n = Pseudonyms(queries.PSEUDONYM_KEY), 0
    texts = {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}
    for r in queries.op4_pseudonyms(spark, "/root/testdata/sf0.01").collect():
        assert r["text"] == brute.text(texts[r["doc_id"]])
        n += r["n_replaced"]
    assert n > 50


def test_each_kind_against_brute_force(spark):
    rng = np.random.default_rng(7)
    number = lambda n: "".join(map(str, rng.integers(0, 10, n)))
    checked = lambda body: next(body + str(c) for c in range(10) if luhn(body + str(c)))
    texts = [*ODD, "", "0000000000000000", "+000 12 345 678", "+1 (017) 555-7713", "(017) 555-7713", "+4915 1234 5678", "+358 40 1234567", "+12 345 678"]
    for _ in range(40):
        amex = checked("37" + number(12))
        card = checked("4" + number(14))
        texts += [f"{amex[:4]} {amex[4:10]} {amex[10:]} {amex}", f"{card[:4]}-{card[4:8]}-{card[8:12]}-{card[12:]} {card}", checked(number(12)), checked(number(18)), number(16)]
        texts += [f"{number(3)}-{number(2)}-{number(4)}", ".".join(str(v) for v in rng.integers(0, 300, 4)), f"+{number(2)} {number(3)} {number(4)} {number(3)}", f"({number(3)}) {number(3)}-{number(4)}", f"{number(2)}/{number(2)}/{number(4)} {number(2)}.{number(2)}.{number(4)} {number(4)}-{number(2)}-{number(2)}"]
        account = number(4) + "ABCD" + number(10)
        spelt = lambda t: int("".join(str(ord(c) - 55) if c.isalpha() else c for c in t))
        texts += [f"DE{98 - spelt(account + 'DE00') % 97:02d}{account}", f"x.{number(3)}@Mail{number(1)}.example.org,"]
    df = documents(spark, texts)
    got = {r["doc_id"]: r["text"] for r in pii.report(df, "k").collect()}
    brute = Pseudonyms("k")
    assert got == {k: brute.text(t) for k, t in enumerate(texts)}
    for k, t in enumerate(texts):  # a pseudonym is of its value's kind again
        for m in brute.every.finditer(t or ""):
            kind = next(x for x, p in pii.KINDS.items() if re.fullmatch(p, m[0], re.ASCII))
            assert kind == "email" or re.fullmatch(pii.KINDS[kind], brute.of(m[0]), re.ASCII)


def test_no_column_name_meets_those_of_the_pseudonyms(spark):
    text = "mine GB82 WEST 1234 5698 7654 32 is"
    df = spark.createDataFrame([(1, text, "f", "m", "t", "F")], "doc_id bigint, text string, _found string, _made string, _text string, found string")
    row = pii.pseudonymised(df.withColumnRenamed("_made", "AFTER"), "k").first()
    assert (row["_found"], row["AFTER"], row["_text"], row["found"]) == ("f", "m", "t", "F") and "WEST 1234" not in row["text"]
    assert pii.pseudonymised(df, "k").columns == df.columns


def test_feistel_is_a_permutation(spark):
    from pyspark.sql import functions as F

    made = spark.range(1000).select(pii.digits_permuted("key", F.lit("t"), F.lpad(F.col("id").cast("string"), 3, "0")).alias("x")).distinct()
    assert made.where("length(x) = 3").count() == 1000


# 5 Secrets


def secrets_brute(text):
    out = []
    for k, rule in enumerate(secrets.BASE + secrets.MORE):
        out += [(m.start(), k, m.end(), rule.kind) for m in re.finditer(rule.pattern, text or "") if len(m[rule.group]) >= rule.least]
    return ",".join(f"{kind}:{a}:{b}" for a, _, b, kind in sorted(out))


def test_secrets_by_index(spark):
    texts = [*ODD, "token=token:abcdefghi", "\u00e9 API_KEY = 'abcdefgh12345678'", "AKIA" + "A" * 20, "f" * 33 + " secret: short", "ghp_" + "a1" * 18, "-----BEGIN RSA PRIVATE KEY-----", "PassWord\":  \"xx.yy=zz/12"]
    found = secrets.scan(documents(spark, texts))
    got = {r["doc_id"]: r["s"] for r in found.select("doc_id", secrets.written_spans(found["spans"]).alias("s")).collect()}
    assert got == {k: secrets_brute(t) for k, t in enumerate(texts)}
    assert secrets.scan(documents(spark, [])).count() == 0


def test_secrets_of_many_matches_hot_ids_and_many_candidates(spark, monkeypatch):
    texts = ["token=abcdefgh%d, " * 1 % k for k in range(3)] + ["\u00e9 " + " ".join(f"secret: value{k:08d}" for k in range(20_000))] + ["plain"] * 5
    rows = [(None if k % 2 else 7, t, "x", "y") for k, t in enumerate(texts)] + [(None, "AKIA" + "B" * 16, "x", "y"), (None, None, "x", "y")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, kinds string, mask string")
    want = collections.Counter((r[0], secrets_brute(r[1])) for r in rows)
    for most in (1_000_000, 0):
        monkeypatch.setattr(secrets, "BROADCAST_ROWS", most)
        found = secrets.scan(df)
        assert collections.Counter((r["doc_id"], r["s"]) for r in found.select("doc_id", secrets.written_spans(found["spans"]).alias("s")).collect()) == want


def test_trigram_queries():
    assert secrets.trigram_query(r"[0-9a-f]+") is None
    assert secrets.trigram_query(r"AKIA[A-Z]+") == [frozenset({"aki", "kia"})]
    assert set(secrets.trigram_query(r"(foo|ba[rz])qu?x")) == {frozenset(x) for x in (("foo", "ooq", "oqu", "qux"), ("foo", "ooq", "oqx"), ("bar", "arq", "rqu", "qux"), ("bar", "arq", "rqx"), ("baz", "azq", "zqu", "qux"), ("baz", "azq", "zqx"))}


@given(st.text(st.sampled_from("abfoquxrz"), max_size=12))
def test_trigram_queries_miss_no_match(text):
    for pattern in (r"(foo|ba[rz])+x?[a-f]?qux", r"fo{2}(ba)?r", r"(a|b|fox)oqu"):
        if re.search(pattern, text):
            assert any(all(t in text for t in s) for s in secrets.trigram_query(pattern) or [frozenset()])


# 6 URLs


def test_url_rules_and_model(spark):
    cases = [("HTTP://A.Example.COM/en/7x?q", "a.example.com", "/en/7x", "example.com/en/7", "allow"), ("http://notexample.com/en/7", "notexample.com", "/en/7", "com/en/", "block"), ("https://example.net/de/81#f", "example.net", "/de/81", "example.net/de/8", "block"), ("http://com/en/", "com", "/en/", "com/en/", "block"), (None, "", "", None, None), ("nothing", "", "", None, None), ("x://h?a", "h", "", None, None)]
    df = spark.createDataFrame([(k, c[0], "p") for k, c in enumerate(cases)], "page_id bigint, url string, host string")
    for r in urls.judged(df).collect():
        want = cases[r["page_id"]]
        assert (r["host"], r["path"], r["rule"]) == want[1:4] and r["verdict"] == (want[4] or r["verdict"]) and r["verdict"] in ("allow", "block")
    assert urls.judged(df.where("false")).count() == 0
    assert {r["verdict"] for r in urls.judged(df.where("page_id = 5")).collect()} == {"allow"}


def test_each_rule_decides_its_own_pages(spark):
    cases = {"http://a.com/en/1": ("com/en/", "block"), "http://example.com/en/70": ("example.com/en/7", "allow"), "http://b.net/de/1": ("net/de/", "allow"), "https://example.net/de/79": ("net/de/", "allow"), "http://example.net/de/8": ("example.net/de/8", "block"), "http://c.org/es/": ("org/es/", "block")}
    rows = urls.judged(spark.createDataFrame(list(enumerate(cases)), "page_id bigint, url string")).collect()
    assert {r["page_id"]: (r["rule"], r["verdict"]) for r in rows} == dict(enumerate(cases.values()))


def judged_brute(url):
    """host, path, rule of one URL, by splitting."""
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        end = min((rest.find(c) for c in "/?#" if c in rest), default=len(rest))
        host, rest = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:end]), rest[end:]
        path = rest[: min((rest.find(c) for c in "?#" if c in rest), default=len(rest))]
    fits = [r.rule for r in urls.RULES if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    return host, path, max(fits, key=len, default=None)


def test_urls_against_brute_force(spark):
    given_pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet").select("page_id", "url")
    odd = ["", "://", "x://", "http:/a", "HTTP://\u00c4.EXAMPLE.com/en/", "http://h?://b/c", "a://b://c/d", "http://com/en", "http://com/en/", "http://xcom/en/1", "http://a.com#/en/1", "http://a.com/en/1?x#y", "http://example.net/de/\n8", "http://" + "h" * 70_000, "http://a.com/en/" + "7" * 70_000, None]
    more = spark.createDataFrame([(-k, u) for k, u in enumerate(odd)] + [(None, "http://com/en/"), (-1, "://")], "page_id bigint, url string")
    df = given_pages.union(more).selectExpr("*", "'s' as suffix", "'x' as rule", "'f' as FOLD", "1 as score")
    rows = urls.judged(df).collect()
    assert len(rows) == df.count()
    want = collections.Counter((r["page_id"], *judged_brute(r["url"])) for r in df.collect())
    assert collections.Counter((r["page_id"], r["host"], r["path"], r["rule"]) for r in rows) == want
    verdict = {r.rule: r.verdict for r in urls.RULES}
    assert all(r["verdict"] == verdict[r["rule"]] for r in rows if r["rule"]) and {r["verdict"] for r in rows if not r["rule"]} == {"allow", "block"}


def test_filter_beats_the_majority_on_hosts_it_has_not_seen(spark):
    row = urls.held_out(spark.read.parquet("/root/testdata/sf0.1/pages.parquet")).first()
    assert row["n"] > 50 and row["accuracy"] > row["majority"] + 0.05 and row["precision"] > 0.85 and row["recall"] > 0.85


def many_urls(spark, n):
    """n URLs that rules label by a digit in the middle of other lexical differences."""
    host = "concat(repeat(substr('abcdefghij', cast(h % 10 as int) + 1, 2), cast(h % 5 as int) + 1), h % 400, '.', element_at(array('com', 'net', 'org'), cast(id % 3 as int) + 1))"
    path = "concat(element_at(array('/en/', '/de/', '/es/'), cast(id % 3 as int) + 1), repeat('x', cast(h % 17 as int)), h % 900, if(h % 7 = 0, '?a=1&b=2', ''))"
    return spark.range(n).selectExpr("id", "pmod(xxhash64(id), 1000003) as h").selectExpr("id as page_id", f"concat('http', if(h % 3 = 0, 's', ''), '://', {host}, {path}) as url")


def test_url_trees_come_from_all_labelled_urls(spark):
    ready = urls.prepared(many_urls(spark, 30_000)).cache()
    some = urls.with_rate(ready.where(f"rule is not null and fold < {urls.FIT}"), urls.statistics(ready))
    rows = some.select(*(F.col(f).cast("double") for f in urls.FEATURES), F.col("rule").isin("com/en/", "org/es/", "example.net/de/8").cast("double")).toPandas().to_numpy()
    x, y = rows[:, :-1], rows[:, -1]
    assert ready.where(f"rule is not null and fold < {urls.CHOOSE}").count() > 20_000
    want = urls.boosted(x, y, np.where(y > 0, 0.5 / y.mean(), 0.5 / (1 - y.mean())), trees=6)
    got = urls.fitted(ready, trees=6)
    assert got.trees.splits == want.splits and np.allclose(got.trees.leaves, want.leaves, rtol=0, atol=1e-12)
    kept = ready.where(f"rule is not null and fold >= {urls.FIT} and fold < {urls.CHOOSE}")
    pairs = urls.scored(kept, got).select("score", F.col("rule").isin("com/en/", "org/es/").cast("double")).toPandas().to_numpy()
    hit = lambda t: ((pairs[pairs[:, 1] > 0, 0] > t).mean() + (pairs[pairs[:, 1] == 0, 0] <= t).mean()) / 2
    assert hit(got.threshold) >= max(map(hit, [0.0, *np.unique(pairs[:, 0])])) - 1e-9


def test_url_trees_from_tasks_are_those_of_the_driver(spark):
    ready = urls.prepared(many_urls(spark, 3_000)).cache()
    assert urls.fitted(ready, most_held=0, trees=2) == urls.fitted(ready, trees=2)


def test_entropy_is_that_of_the_counts(spark):
    words = ["", "a", "aab", "abcabc", "h" * 5_000 + "x"]
    df = spark.createDataFrame([(w,) for w in words], "w string")
    got = [r["e"] for r in df.select("w", urls.entropy(df["w"]).alias("e")).collect()]
    for w, e in zip(words, got, strict=True):
        share = np.array(list(collections.Counter(w).values())) / max(1, len(w))
        assert e == pytest.approx(float(-(share * np.log2(share)).sum()) if w else 0.0, abs=1e-9)


def test_trees_hold_on_held_out_rows():
    rng = np.random.default_rng(5)
    x = rng.random((4000, len(urls.FEATURES)))
    y = ((x[:, 0] > 0.5) ^ (x[:, 3] > 0.7)).astype(float)
    fitted = urls.boosted(x[:3000], y[:3000])
    assert ((fitted.raw(x[3000:]) > 0) == y[3000:]).mean() > 0.95


# 7 Near duplicates


def components_brute(texts):
    sets, parent = shingle_sets(texts), list(range(len(texts)))

    def top(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for a in range(len(sets)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((top(a), top(b)))
                parent[y] = x
    return [top(k) for k in range(len(texts))]


def test_near_duplicates_against_all_pairs(spark):
    rng = np.random.default_rng(3)
    texts = list(ODD)
    for _ in range(12):
        words = [f"v{k}" for k in rng.integers(0, 5000, 80)]
        for _ in range(int(rng.integers(1, 9))):
            own = list(words)
            for k in rng.integers(0, 80, int(rng.integers(0, 4))):
                own[k] = "changed"
            texts.append(" ".join(own))
    texts += ["a b c", "A b C", "a b", *["shared opening words of many texts " + " ".join(f"q{j}x{k}" for j in range(9)) for k in range(90)]]
    got = {r["doc_id"]: r for r in neardup.linked(documents(spark, texts)).collect()}
    assert [got[k]["component_id"] for k in range(len(texts))] == components_brute(texts)
    assert [got[k]["n_shingles"] for k in range(len(texts))] == [len(s) for s in shingle_sets(texts)]
    assert neardup.linked(documents(spark, [])).count() == 0


def test_each_row_has_the_depth_of_its_neighbourhood():
    """The shortest prefix of the order that few rows share, against all prefixes."""
    rng, forest = np.random.default_rng(6), neardup.Forest(window=3)
    hashes = rng.choice(5, (400, 8), p=[0.6, 0.1, 0.1, 0.1, 0.1]).astype(np.uint64)
    region, onward = hashes[:, 0].astype(np.int64) * 5 + hashes[:, 1].astype(np.int64), (hashes[:, 2] << np.uint64(48) | hashes[:, 3] << np.uint64(32) | hashes[:, 4] << np.uint64(16) | hashes[:, 5]).view(np.int64)
    order = np.lexsort((onward, region))
    rows = [tuple([int(region[k]), *hashes[k, 2:6].tolist()]) for k in order]
    number, deeper = neardup._neighbourhoods(region[order], onward[order], forest)
    shared = collections.Counter(r[:n] for r in rows for n in range(1, 6))
    own = [next((n for n in range(1, 6) if shared[r[:n]] <= 4), 5) for r in rows]
    assert deeper.tolist() == [n - 1 for n in own] and len(set(own)) > 2
    assert [number[i] == number[j] for i in range(400) for j in range(i)] == [rows[i][: own[i]] == rows[j][: own[j]] for i in range(400) for j in range(i)]


def test_components_of_a_long_path_and_a_hub(spark):
    links = [(k, k + 1) for k in range(100, 400)] + [(5, 1000 + k) for k in range(300)] + [(7, 7), (100, 5)]
    found = {r["node"]: r["component"] for r in graph.components(spark.createDataFrame(links, "a bigint, b bigint")).collect()}
    assert set(found.values()) == {5, 7} and found[7] == 7 and len(found) == 301 + 301 + 1


def test_dense_regions_are_settled_by_blocks(spark):
    """Small windows and blocks take the ways of very large groups."""
    rng = np.random.default_rng(4)
    base = [f"v{k}" for k in range(120)]
    texts = []
    for _ in range(150):
        own = list(base)
        for k in rng.integers(0, 120, 3):
            own[k] = f"z{rng.integers(0, 9)}"
        texts.append(" ".join(own))
    forest = neardup.Forest(window=2, block=16)
    got = {r["doc_id"]: r["component_id"] for r in neardup.linked(documents(spark, texts), forest).collect()}
    assert [got[k] for k in range(len(texts))] == components_brute(texts)


def test_rows_without_id_and_with_one_id(spark):
    df = spark.createDataFrame([(None, LONG, 1), (4, LONG, 2), (4, LONG, 3), (None, "x y", 4)], "doc_id bigint, text string, component_id int")
    assert sorted((r["doc_id"] or -1, r["component_id"] or -1) for r in neardup.linked(df).collect()) == [(-1, -1), (-1, 4), (4, 4), (4, 4)]
    assert set(neardup.deduplicated(df).columns) == set(df.columns)


def survivors_brute(ids, texts):
    """Places of the rows that stay: one per component, where rows of one id are in one."""
    label, sets = components_brute(texts), shingle_sets(texts)
    for i in set(ids) - {None}:
        of_id = {label[k] for k in range(len(ids)) if ids[k] == i}
        label = [min(of_id) if x in of_id else x for x in label]
    order = lambda k: (ids[k] is None, ids[k] or 0, -len(sets[k]), k)
    return {min((k for k in range(len(ids)) if label[k] == x), key=order) for x in label}


def odd_id_rows():
    base = [[f"{c}{k}" for k in range(60)] for c in "pqrstu"]
    near = lambda c, *at: " ".join("changed" if k in at else w for k, w in enumerate(base[c]))
    rows = [(None, near(0))] * 20 + [(7, near(1)), (None, near(1)), (3, near(1, 9)), (None, near(1, 30))] + [(5, near(2))] * 9 + [(6, near(3)), (6, near(4)), (8, near(4)), (None, near(5, 1)), (None, near(5)), (None, near(5, 50)), (9, "9 only")]
    return [r[0] for r in rows], [r[1] for r in rows]


def test_deduplicated_keeps_one_row_per_component(spark):
    ids, texts = odd_id_rows()
    ids, texts = [*ids, None, None, 11, 11, 12], [*texts, None, "", "", "eleven words are not here", ""]
    df = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(zip(ids, texts, strict=True))], "doc_id bigint, text string, _row int")
    kept = neardup.deduplicated(df)
    assert kept.columns == df.columns
    assert sorted(r["_row"] for r in kept.collect()) == sorted(survivors_brute(ids, texts))


def test_pipeline_run_against_brute_force(spark, tmp_path):
    import corpus_pipeline

    ids, texts = odd_id_rows()
    item = " ".join(f"leak{k}" for k in range(20))
    ids, texts = [*ids, 20, 21, 22], [*texts, "too short", " ".join(f"z{k}" for k in range(70)) + " " + item, " ".join(f"y{k}" for k in range(70)) + " 4111111111111111"]
    documents_at = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in zip(ids, texts, strict=True)], DOCS)
    documents_at.coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(0, item)], "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    good = [k for k, t in enumerate(texts) if len(t.split()) >= repetition.Limits().least_words]
    left = [good[k] for k in survivors_brute([ids[k] for k in good], [texts[k] for k in good])]
    left = [k for k in left if item not in texts[k]]
    made = {r["doc_id"]: r["text"] for r in pii.report(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"), queries.PSEUDONYM_KEY).collect()}
    whole = Tokenizer.from_file(queries.byte_tokenizer())
    want = collections.Counter((ids[k], tuple([*whole.encode(made[k], add_special_tokens=False).ids, 0])) for k in left)
    got = collections.Counter((r["doc_id"], tuple(np.frombuffer(r["ids"], "<u4").tolist())) for r in corpus_pipeline.run(spark, str(tmp_path)).collect())
    assert max(len(x) for _, x in want) <= 1024 and got == want


# 8 Token files


@pytest.mark.parametrize("bits", [1, 7, 13, 16, 17, 32])
def test_bits_round_trip(bits):
    ids = np.random.default_rng(bits).integers(0, 2**bits, 1001, dtype=np.uint64).astype(np.uint32)
    data = tokenfile.packed(ids, bits)
    assert len(data) == -(-1001 * bits // 8) and tokenfile.unpacked(data, bits, 1001).tolist() == ids.tolist()


def test_shards_allow_random_access(tmp_path):
    rng = np.random.default_rng(1)
    docs = [rng.integers(0, 5000, n).astype(np.uint32) for n in (0, 1, 999, 64, 3)]
    with common.whole_file(str(tmp_path / "x.tokens")) as out:
        writer = tokenfile.ShardWriter(out, 13, 64)
        for k, d in enumerate(docs):
            writer.add(k, d)
        writer.close()
    shard, every = tokenfile.Shard(str(tmp_path / "x.tokens")), np.concatenate(docs)
    assert shard.firsts.tolist() == np.concatenate(([0], np.cumsum([len(d) for d in docs]))).tolist()
    for a, b in ((0, 1067), (63, 65), (5, 5), (640, 1000)):
        assert shard.ids(a, b).tolist() == every[a:b].tolist()


def test_token_files_read_back(spark, tmp_path):
    df = spark.createDataFrame([(9 - k, t, "bits") for k, t in enumerate(ODD)] + [(None, "end", "b"), (9, "again", "c")], "doc_id bigint, text string, start string")
    shards = tokenfile.write(df, queries.word_tokenizer(), True, 1, 49_408, str(tmp_path / "f"))
    whole = Tokenizer.from_file(queries.word_tokenizer())
    want = collections.Counter((r["doc_id"], zlib.crc32(np.array([*whole.encode(r["text"] or "", add_special_tokens=False).ids, 1], "<u4").tobytes())) for r in df.collect())
    rows = sorted(tokenfile.digests(shards).collect(), key=lambda r: r["start"])
    assert collections.Counter((r["doc_id"], r["ids_crc32"]) for r in rows) == want
    at = 0
    for r in rows:
        assert r["start"] == at
        at += r["n_tokens"]
    ids = [r["doc_id"] for r in rows]
    assert ids[0] is None and ids[1:] == sorted(ids[1:])
    assert tokenfile.digests(tokenfile.write(df.where("false"), queries.word_tokenizer(), True, 1, 49_408, str(tmp_path / "g"))).count() == 0


@pytest.mark.parametrize("vocabulary", [49_408, 49_408 << 1, 1 << 20])
def test_files_of_any_width_read_back(spark, tmp_path, vocabulary):
    """16, 17 and 20 bits an id: the packed ones, from the table to the files and back."""
    least = -(2**63)
    df = spark.createDataFrame([(k, t) for k, t in enumerate(ODD)] + [(None, "end"), (least, "least"), (least, None)] + [(5, "again and again")] * 300, "doc_id bigint, text string").repartition(3)
    shards = tokenfile.write(df, queries.word_tokenizer(), True, 1, vocabulary, str(tmp_path / "f"), block=4093)
    whole = Tokenizer.from_file(queries.word_tokenizer())
    want = collections.Counter((r["doc_id"], tuple([*whole.encode(r["text"] or "", add_special_tokens=False).ids, 1])) for r in df.collect())
    assert collections.Counter((r["doc_id"], tuple(r["ids"])) for r in tokenfile.read(shards).collect()) == want
    shard = tokenfile.Shard(shards.first()["path"])
    assert shard.bits == (vocabulary - 1).bit_length()


# 9 WARC


def test_archives_read_back_by_chunks(spark, tmp_path):
    bodies = ["same", None, "", "same", "x" * 1000, "same", "\u00e9" * 333, "\r\n\r\nWARC/1.1\r\n"]
    df = spark.createDataFrame([(k, f"http://h/\n{k}", b, k) for k, b in enumerate(bodies)] + [(None, None, "same", 0), (3, "u", "same", 0)], "page_id bigint, url string, html string, record int")
    archives = warc.write(df, str(tmp_path / "w"), chunk=64)
    rows = warc.summary(warc.read(archives, chunk=50)).collect()
    assert len(rows) == 10
    first = {"same": 0, "": 1}
    for r in rows:
        body = "same" if r["page_id"] is None else bodies[r["page_id"]] or ""
        assert r["payload_bytes"] == len(body.encode()) and r["payload_digest"] == base64.b32encode(hashlib.sha1(body.encode()).digest()).decode()
        revisit = body in first and r["page_id"] != first[body]
        assert (r["record_type"], r["refers_to"]) == (("revisit", first[body]) if revisit else ("response", None))
    chunks = [r for r in warc.read(archives, chunk=50).where("page_id = 4").orderBy("chunk_no").collect()]
    assert b"".join(r["data"] for r in chunks) == b"x" * 1000 and len(chunks) == 20 and [r["so_far"] for r in chunks][-1] == 1000
    assert warc.summary(warc.read(warc.write(df.where("page_id in (0, 3)"), str(tmp_path / "v"), least_bytes=5))).where("record_type = 'revisit'").count() == 0
    assert warc.write(df.where("false"), str(tmp_path / "e")).count() == 0


def records_of(path):
    """The records of a gzipped archive by a plain reading of the format: (fields, block)."""
    import gzip

    data, out = gzip.open(path).read(), []
    while data:
        head, data = data.split(b"\r\n\r\n", 1)
        first, *lines = head.decode().split("\r\n")
        assert first == "WARC/1.1"
        fields = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines)
        n = int(fields["Content-Length"])
        out.append((fields, data[:n]))
        assert data[n : n + 4] == b"\r\n\r\n"
        data = data[n + 4 :]
    return out


def test_archives_are_valid_and_keep_urls_and_large_payloads(spark, tmp_path):
    urls_of = ["http://h/a?b=%20c", "http://h/a b\n\u00e9", None, "", "http://h/2"]
    bodies = ["one", "one", "two", "x" * (9 << 20), "one"]
    df = spark.createDataFrame([(k, u, b) for k, (u, b) in enumerate(zip(urls_of, bodies, strict=True))], "page_id bigint, url string, html string")
    archives = warc.write(df, str(tmp_path / "w"))
    back = {}
    for r in warc.read(archives).orderBy("page_id", "chunk_no").collect():
        back.setdefault(r["page_id"], [r["url"], r["record_type"], b""])[2] += r["data"]
    assert [back[k][0] for k in range(5)] == urls_of
    assert [(back[k][1], back[k][2].decode()) for k in range(5)] == [("response", "one"), ("revisit", ""), ("response", "two"), ("response", bodies[3]), ("revisit", "")]
    assert warc.read(archives).where("page_id = 3").agg({"so_far": "max", "chunk_no": "max"}).first()["max(chunk_no)"] == (9 << 20) // (256 << 10) - 1
    every = [x for r in archives.collect() for x in records_of(r["path"])]
    ids = {f["WARC-Record-ID"]: f for f, _ in every}
    assert len(ids) == len(every)
    for fields, block in every:
        datetime.datetime.strptime(fields["WARC-Date"], "%Y-%m-%dT%H:%M:%SZ")
        if fields["WARC-Type"] == "response":
            assert fields["Content-Type"] == "application/http; msgtype=response" and block.startswith(b"HTTP/1.1 200 OK\r\n")
            payload = block.split(b"\r\n\r\n", 1)[1]
            assert fields["WARC-Payload-Digest"] == "sha1:" + base64.b32encode(hashlib.sha1(payload).digest()).decode()
        if fields["WARC-Type"] == "revisit":
            assert ids[fields["WARC-Refers-To"]]["WARC-Payload-Digest"] == fields["WARC-Payload-Digest"] and ids[fields["WARC-Refers-To"]]["WARC-Target-URI"] == fields["WARC-Refers-To-Target-URI"]
    assert sum(f["WARC-Type"] == "warcinfo" for f, _ in every) == archives.count()


# 10 Decontamination


def contamination_brute(texts, items):
    def bag(t):
        w = WORD.findall((t or "").lower())
        return [tuple(w[k : k + 5]) for k in range(len(w) - 4)] if len(w) >= 5 else ([tuple(w)] if w else [])

    out = set()
    for d, text in enumerate(texts):
        x = bag(text)
        for i, item in enumerate(items):
            y = bag(item)
            m = min(len(x), len(y))
            for at in range(len(x) - m + 1 if y and m else 0):
                a, b = collections.Counter(x[at : at + m]), collections.Counter(y)
                if 100 * sum((a & b).values()) >= 75 * sum((a | b).values()):
                    out.add((d, i))
    return out


def test_decontamination_against_all_windows(spark):
    rng = np.random.default_rng(8)
    items = [" ".join(f"b{k}" for k in rng.integers(0, 400, n)) for n in (3, 5, 14, 30, 59)] + [None, ""]
    texts = list(ODD)
    for item in items[:5]:
        words = item.split()
        for edits in (0, 1, 2, 4):
            own = list(words)
            for k in rng.integers(0, len(own), edits):
                own[k] = "edited"
            texts.append("some words before it " + " ".join(own).upper() + " and after")
        texts += [item, " ".join(words[: len(words) * 9 // 10])]
    bench = spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string")
    found = {(r["doc_id"], r["item_id"]) for r in decontam.matches(documents(spark, texts), bench).collect()}
    assert found == contamination_brute(texts, items)
    blocks = decontam.Match(most_items=2)
    assert {(r["doc_id"], r["item_id"]) for r in decontam.matches(documents(spark, texts), bench, blocks).collect()} == found
    clean = decontam.clean_rows(documents(spark, texts), bench, blocks)
    assert {r["doc_id"] for r in clean.collect()} == set(range(len(texts))) - {d for d, _ in found}
    assert decontam.matches(documents(spark, texts), bench.where("false")).count() == 0
    assert decontam.matches(documents(spark, []), bench).count() == 0


def repeated_pair(rng, n, k):
    words = [f"r{x}" for x in rng.integers(0, 10**6, n)]
    return " ".join([*words, *["spam"] * k]), " ".join([*words, *["eggs"] * k])


def test_repeated_shingles_lose_no_window(spark):
    """Items and documents that differ in one word said many times: all windows against all items."""
    rng = np.random.default_rng(11)
    pairs = [repeated_pair(rng, 60, k) for k in (4, 8, 12, 14) for _ in range(6)] + [(" ".join(["again"] * 70), " ".join(["again"] * n)) for n in (60, 70, 300)]
    items = [a for a, _ in pairs]
    texts = [f"before it came this {b} and this after" for _, b in pairs] + items
    bench = spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string")
    found = {(r["doc_id"], r["item_id"]) for r in decontam.matches(documents(spark, texts), bench).collect()}
    assert found == contamination_brute(texts, items)


def test_recall_at_the_bound_and_the_share_that_passes():
    """2,000 pairs at 75 to 78 %, long repeats among them; and how many unrelated pairs a near block lets through."""
    rng, lost, pairs = np.random.default_rng(12), 0, 0
    for trial in range(400):
        item, text = repeated_pair(rng, 200, int(rng.integers(20, 34)))
        exact, index = (decontam.Index([trial], [item], decontam.Match(exact=e)) for e in (True, False))
        want, got = (list(i.of_texts(pa.array([text]))) for i in (exact, index))
        pairs, lost = pairs + len(want), lost + len(want) - len(got)
    assert pairs >= 300 and lost <= pairs // 100
    index = decontam.Index(list(range(300)), [" ".join(f"n{x}" for x in rng.integers(0, 10**6, 60)) for _ in range(300)], decontam.Match())
    prints = index.prints[56]
    near = (np.bitwise_count(index.parts(prints)[:, None] ^ index.parts(prints)[None]) <= index.match.radius // index.match.blocks).any(axis=2)
    assert (near.sum() - 300) / (300 * 299) < 0.06


def test_sliding_prints_are_those_of_the_windows():
    rng = np.random.default_rng(13)
    hashes = rng.integers(0, 7, 600).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    index = decontam.Index([1], ["x"], decontam.Match(windows=37))
    for size in (1, 5, 40):
        windows = np.flatnonzero(rng.random(600 - size + 1) < 0.2)
        got = list(index.window_prints(hashes, decontam.Places(hashes), windows, size))
        assert np.concatenate([w for w, _ in got]).tolist() == windows.tolist()
        want = np.concatenate([index.print_of(hashes[w : w + size]) for w in windows])
        assert (np.concatenate([x for _, x in got]) == want).all()


def test_fingerprint_blocks_find_all_within_the_radius():
    match = decontam.Match()
    index = decontam.Index([1, 2], ["a b c d e f g", "h i j k l m n"], match)
    own = index.prints[3]
    rng = np.random.default_rng(2)
    prints = np.concatenate([own[k % 2 : k % 2 + 1] ^ np.packbits(np.isin(np.arange(256), rng.choice(256, n, replace=False)), bitorder="little").view("<u8")[None] for k, n in enumerate(range(1, 256))])
    found = {(i, j) for w, k in index.candidates(3, prints) for i, j in zip(w.tolist(), k.tolist(), strict=True)}
    assert found == {(i, j) for i in range(len(prints)) for j in (0, 1) if int(np.bitwise_count(prints[i] ^ own[j]).sum()) <= match.radius}


def test_a_long_text_that_repeats_an_item_takes_bounded_memory():
    import tracemalloc

    words = [f"x{k}" for k in range(40)]
    text = " ".join(words * 5_000)
    index = decontam.Index([1, 2], [" ".join(words), " ".join(reversed(words))], decontam.Match())
    array = pa.array([text])
    tracemalloc.start()
    found = list(index.of_texts(array))
    peak = tracemalloc.get_traced_memory()[1]
    assert [f[1] for f in found] == [0] and peak < 100 * len(text)
