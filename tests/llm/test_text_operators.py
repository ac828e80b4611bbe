"""Encoding, secrets, language, toxicity, licences and lines: references, brute force and edge cases."""

import base64
import hashlib
import json
import random
import re
import zlib

import pytest
from pyspark.sql import functions as F

from spanwalk.llm import bpe, langid, license_scan, line_dedup, secret_scan, toxicity
from spanwalk.llm.common import lower_ascii

ODD = [None, "", " ", "\n", "\n\n", "\x00", "é", "a" * 5000, "Ünïcode İ ß ſ K", "\x1c\x1d x", "日本語のテキスト", "x\r\ny"]


def frame(spark, texts, **more):
    """Documents with extra columns that clash with names used inside."""
    rows = [(k, t, "l", "s", 1, 2, 3) for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, key long, row long, component_id long")


def test_bpe_equals_the_library(spark):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(bpe.default_vocabulary())
    r = random.Random(1)
    alphabet = "abcdefgh 'stre'lléİΣß \x1c\x85²½Ⅷ中文한국́Å  \t\n€_-😀‍0123٠%#"
    texts = ["".join(r.choice(alphabet) for _ in range(r.randint(0, 40))) + r.choice(["", "", "<|endoftext|>x"]) for _ in range(3000)] + ODD
    texts += ["".join(r.choice("etaoin") for _ in range(20_000))]
    enc = bpe.ForcedSplitEncoder(bpe.default_vocabulary())
    for t in texts:
        want = lib.encode(t or "", add_special_tokens=False).ids
        assert enc.encode(t) == want
        assert enc.decode(want) == lib.decode(want, skip_special_tokens=False)
    some = texts[-20:]
    for row in bpe.digest(bpe.encode_documents(frame(spark, some))).collect():
        ids = lib.encode(some[row.doc_id] or "", add_special_tokens=False).ids
        assert row.n_tokens == len(ids) and row.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert row.decoded_sha256 == hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_bpe_cuts_are_certain():
    enc = bpe.ForcedSplitEncoder(bpe.default_vocabulary())
    word = "qqxzjjqkvvw"
    assert "".join(enc.split(word)) == word and len(enc.split(word)) > 1
    assert all(pair in enc.inside for part in enc.split(word) for pair in map("".join, zip(part, part[1:])))


def plain_base(text):
    out = []
    for m in re.finditer(r"""(?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text):
        if len(m.group(1)) >= 6:
            out.append(("assign", *m.span()))
    out += [("access", *m.span()) for m in re.finditer("AKIA[A-Z0-9]+", text) if m.end() - m.start() >= 20]
    out += [("hex", *m.span()) for m in re.finditer("[0-9a-f]+", text) if m.end() - m.start() >= 24]
    return secret_scan.listed(out)


def test_secret_base_spans():
    r = random.Random(3)
    bits = ["password", "PassWd", "secret", "token", "api_key", "APIKEY", "'", '"', " ", "  ", ":", "=", "AKIA", "ABCDEFGH12345678", "deadbeef", "0123456789abcdef", "é", "\n", "x", "ſecret", "toKen", "abc123", "=="]
    for _ in range(5000):
        text = "".join(r.choice(bits) for _ in range(r.randint(0, 14)))
        assert secret_scan.listed(secret_scan.base_spans(text)) == plain_base(text)


def der(tag, body):
    n = len(body)
    size = bytes([n]) if n < 128 else (lambda b: bytes([0x80 | len(b)]) + b)(n.to_bytes((n.bit_length() + 7) // 8, "big"))
    return bytes([tag]) + size + body


def test_secret_confirmation(spark):
    r = random.Random(5)
    noise = bytes(r.randrange(256) for _ in range(300))
    rsa = der(0x30, der(2, b"\0") + b"".join(der(2, b"\x01" + noise[:64]) for _ in range(8)))
    pkcs8 = der(0x30, der(2, b"\0") + der(0x30, der(6, bytes.fromhex("2b6570"))) + der(4, der(4, noise[:32])))
    ssh = lambda *f: b"".join(len(x).to_bytes(4, "big") + x for x in f)
    public = ssh(b"ssh-ed25519", noise[:32])
    b64 = lambda b: base64.b64encode(b).decode()
    url = lambda o: base64.urlsafe_b64encode(json.dumps(o).encode()).decode().rstrip("=")
    jwt = f"{url({'alg': 'HS256', 'typ': 'JWT'})}.{url({'sub': 'someone'})}.c2lnbmF0dXJl"
    real = {"der": [b64(rsa), b64(pkcs8), rsa.hex()], "jwt": [jwt], "pem": [f"-----BEGIN RSA PRIVATE KEY-----\n{b64(rsa)}\n-----END RSA PRIVATE KEY-----"], "sshkey": [b64(public)]}
    for kind, texts in real.items():
        for t in texts:
            assert kind in {k for k, _, _ in secret_scan.confirmed_spans(f"see {t} there")}, (kind, t[:40])
    broken = [b64(rsa[:-3]), b64(noise), jwt.replace("eyJ", "eyX", 1), f"{url({'typ': 'JWT'})}.{url({})}.x", "-----BEGIN RSA PRIVATE KEY-----\nAAAA\n-----END RSA PRIVATE KEY-----", rsa.hex()[:-2], b64(public[:-1])]
    for t in broken:
        assert secret_scan.confirmed_spans(f"see {t} there") == [], t[:40]
    got = {x.doc_id: x for x in secret_scan.digest(secret_scan.scan_secrets(frame(spark, [*ODD, f"é token = {jwt}"]))).collect()}
    last = got[len(ODD)]
    assert last.n_assign == 1 and f"assign:2:{2 + 8 + len(jwt)}" in last.spans and f"jwt:10:{10 + len(jwt)}" in last.spans
    assert got[0].spans == "" and got[0].n_hex == 0


def test_more_kinds_of_keys():
    r = random.Random(8)
    noise = bytes(r.randrange(256) for _ in range(400))
    b64 = lambda b: base64.b64encode(b).decode()
    rsa = der(0x30, der(2, b"\0") + b"".join(der(2, b"\x01" + noise[:64]) for _ in range(8)))
    dsa = der(0x30, der(2, b"\0") + b"".join(der(2, b"\x01" + noise[:n]) for n in (128, 20, 128, 128, 20)))
    locked = der(0x30, der(0x30, der(6, bytes.fromhex("2a864886f70d01050d")) + der(0x30, b"")) + der(4, noise[:64]))
    wrapped = "\n".join(b64(rsa)[k : k + 64] for k in range(0, len(b64(rsa)), 64))
    loose = base64.urlsafe_b64encode(b'{ "alg": "none"}').decode().rstrip("=") + "." + base64.urlsafe_b64encode(b'\n{"sub":1}').decode().rstrip("=") + "."
    headed = f"-----BEGIN RSA PRIVATE KEY-----\nProc-Type: 4,ENCRYPTED\nDEK-Info: AES-128-CBC,00FF\n\n{b64(noise[:128])}\n-----END RSA PRIVATE KEY-----"
    for kind, t in (("der", b64(dsa)), ("der", b64(locked)), ("der", wrapped), ("jwt", loose), ("pem", headed)):
        (span,) = secret_scan.confirmed_spans(f"see {t} there")
        assert span == (kind, 4, 4 + len(t)), (kind, t[:40])
    for t in (headed.replace("DEK-Info", "Other"), wrapped.replace("\n", "\n\n", 1), b64(dsa[:-1]), loose.replace(".", ":", 1)):
        assert not [s for s in secret_scan.confirmed_spans(f"see {t} there") if s[0] != "der" or s[2] - s[1] > 500]


def corpus(seed, n, words, extra=()):
    r = random.Random(seed)
    return [" ".join([*(r.choice(words) for _ in range(r.randint(20, 60))), *r.sample(list(extra), min(len(extra), 2))]).capitalize() + "." for _ in range(n)]


def test_letters():
    assert not any(map(langid.has_letter, [None, "", "½", "² ₃", "Ⅷ", "1234 _-", "٣"])) and all(map(langid.has_letter, ["a", "½ é", "日", "ß"]))


def test_stretches(spark):
    from spanwalk.llm.common import stretch

    texts = [None, "", "short", "x" * 50, "abcdefghij" * 30]
    got = [r.s for r in frame(spark, texts).orderBy("doc_id").select(stretch(F.col("text"), 50).alias("s")).collect()]
    assert got[:4] == texts[:4] and len(got[4]) == 50 and got[4] in texts[4]


def test_repeated_rows_empty_tables_and_null_ids(spark):
    long = "token = abcdefgh " + "word and " * 20_000 + "MIT License"
    rows = [(1, "password = hunter22", "en"), (1, "password = hunter22", "en"), (None, "MIT License", "en"), (2, long, None)]
    docs = spark.createDataFrame([(*x, "clash", 1, 1.0) for x in rows], "doc_id long, text string, lang string, key string, row long, score double")
    labels = spark.createDataFrame([(1, 0)], "doc_id long, toxic int")
    jobs = [lambda d: bpe.digest(bpe.encode_documents(d)), lambda d: secret_scan.digest(secret_scan.scan_secrets(d)), lambda d: license_scan.digest(license_scan.scan_licenses(d)), lambda d: langid.digest(langid.identify(d)), lambda d: toxicity.digest(toxicity.score_documents(d, labels))]
    for job in jobs:
        got = sorted(map(tuple, job(docs).collect()), key=str)
        assert len(got) == 4 and len(set(got)) == 3 and sum(x[0] is None for x in got) == 1
        assert job(docs.limit(0)).collect() == []


def test_language(spark):
    sets = {"aa": ["the", "thing", "other", "with", "that", "and"], "bb": ["der", "schule", "und", "nicht", "über", "ein"], "cc": ["que", "été", "nous", "leur", "dans", "une"]}
    rows = [(k, t, lang) for k, (t, lang) in enumerate((t, lang) for s, lang in enumerate(sets) for t in corpus(s, 150, sets[lang]))]
    rows += [(1000 + k, t, None) for k, t in enumerate(ODD)] + [(None, "the other thing", "aa")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r.doc_id: r for r in langid.digest(langid.identify(docs)).collect()}
    assert len(got) == len(rows)
    for k, _, lang in rows[:450]:
        assert got[k].lang_pred == lang and 0 <= got[k].score <= 1 and got[k].accepted
        assert got[k].held_out == (zlib.crc32(str(k).encode()) % 4 == 2)
    for k in range(6):
        assert got[1000 + k].lang_pred == "und" and got[1000 + k].score == 0 and not got[1000 + k].accepted
    assert not got[1000 + ODD.index("日本語のテキスト")].accepted  # far from every centroid
    kept = langid.accepted_documents(docs)
    assert kept.columns == docs.columns and kept.where("doc_id < 450").count() == 450
    none = langid.identify(docs.limit(0)).collect()
    assert none == []
    blank = langid.identify(docs.withColumn("lang", docs.lang.cast("string")).where("lang is null")).collect()
    assert {r.lang_pred for r in blank} == {"und"}


def test_toxicity(spark):
    words = ["the", "river", "house", "walk", "green", "over", "stone", "light", "table"]
    plain, toxic = corpus(1, 200, words), corpus(2, 120, words, ["idiot", "scumbag", "moron", "worthless"])
    texts = plain + toxic
    labels = spark.createDataFrame([(k, int(k >= 200), 1) for k in range(320)], "doc_id long, toxic int, quality int")
    got = {r.doc_id: r for r in toxicity.digest(toxicity.score_documents(frame(spark, texts + ODD), labels)).collect()}
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got.values())
    held = [k for k in range(320) if zlib.crc32(str(k).encode()) % 5 == 0]
    assert all(got[k].held_out for k in held)
    right = [got[k].predicted == int(k >= 200) for k in held]
    assert sum(right) / len(right) >= 0.95
    assert {r.score for r in toxicity.score_documents(frame(spark, texts[:3]), labels.limit(0)).collect()} == {0.0}
    assert toxicity.score_documents(frame(spark, texts).limit(0), labels).collect() == []


def test_toxicity_learns_short_words():
    words = ["the", "river", "house", "walk", "green", "over", "stone", "light", "table"]
    plain, toxic = corpus(4, 300, words), corpus(5, 200, words, ["vex", "zug", "kaf"])
    toxic = [f"{t[-30:]} {t}" for t in toxic]  # in the middle, too: zstandard starts no match in the last bytes
    own = toxicity.fit(toxic[:150], plain[:200])
    assert (own.scores(toxic[150:]) >= 0.5).mean() >= 0.9 and (own.scores(plain[200:]) >= 0.5).mean() <= 0.1


def test_toxicity_trains_on_all_ordinary_texts(monkeypatch):
    plain = [f"{chr(97 + k % 26)} " + f"w{k % 26:02d}x{k} abcdefg " * 90 for k in range(1300)]
    shown = []
    monkeypatch.setattr(toxicity, "_dictionary", lambda samples, *_, **__: shown.append(samples) or b" ")
    toxicity.fit(["some toxic text", "another one"], plain)
    assert len(shown[0]) <= 20_000 < sum(len(toxicity.windows(t)) for t in plain)
    text = b"\n".join(shown[0])
    assert all(text.count(b"w%02dx" % k) > 500 for k in range(26))


def plain_words(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)


def test_licenses(spark):
    notices = ["Released under the MIT License.", "MIT-license; apache\nLICENSE", "Licensed under the Apache License, Version 2.0.", "This work is licensed under the GNU General Public License, version 3.", "general public licence", "mit license mit license", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:", "Licensed under CC BY-NC 4.0.", "a mit of license", "permission and use of the source"]
    notices += ["redistribution and use in source and binary forms with or without modification are permitted provided", "the software is provided as is without warranty of any kind express"]
    texts = [*ODD, *notices, *corpus(3, 30, ["and", "use", "in", "the", "license", "under"]), "one " * 3000 + "MIT License"]
    got = {r.doc_id: r for r in license_scan.digest(license_scan.scan_licenses(frame(spark, texts))).collect()}
    for k, t in enumerate(texts):
        w, found = plain_words(t), []
        for phrase, label in license_scan.PHRASES.items():
            p = phrase.split()
            found += [(i, label) for i in range(len(w)) if w[i : i + len(p)] == p]
        r = got[k]
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (len(w), len(found), min(found)[0] if found else None, max(found)[0] if found else None, ",".join(sorted({x for _, x in found}))), (k, t)
        assert set(r.base_labels.split(",")) <= set(r.labels.split(",")) | {""} and 0 <= r.score <= 1
    # the method's labels against every place of every template
    for rare, agree in ((license_scan.RARE, license_scan.AGREE), (20, 0.3)):
        wordy = [plain_words(t) for t in texts]
        counts = {x: sum(x in set(w) for w in wordy) for x in {y for _, _, body in license_scan.TEMPLATES for y in body.split()}}
        index = license_scan.build_index(counts, len(texts), rare)
        labelled = {r.doc_id: r.labels for r in license_scan.digest(license_scan.scan_licenses(frame(spark, texts), rare, agree)).collect()}
        for k, w in enumerate(wordy):
            want = set()
            for n in {p[0] for p in index}:
                own = [p for p in index if p[0] == n]
                for at in range(-40, len(w)):
                    there = [p for p in own if 0 <= at + p[4] < len(w) and w[at + p[4]] == p[3]]
                    whole = sum(p[5] for p in own)
                    share = 1.0 if own[0][2] == "phrase" else round(sum(p[5] for p in there) / whole, 6) if whole else 0
                    if sum(p[6] for p in there) == sum(p[6] for p in own) and share >= agree:
                        want.add(own[0][1])
            assert labelled[k] == ",".join(sorted(want)), (k, texts[k][:80])
    by = lambda text: got[texts.index(text)].labels
    assert by(notices[6]) == "bsd" and by(notices[7]) == "cc-by,cc-by-nc" and by(notices[8]) == "" and by(notices[9]) == ""
    assert license_scan.scan_licenses(frame(spark, texts).limit(0)).collect() == []


def plain_lines(rows, least=10):
    strip = " \t\n\x0b\x0c\r"
    key = lambda s: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s.strip(strip))
    holders = {}
    for k, t in rows:
        if k is not None:
            for line in (t or "").split("\n"):
                holders.setdefault(key(line), set()).add(k)
    out = []
    for k, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if k is None or len(key(x)) < least or len(holders[key(x)]) < 2 or min(holders[key(x)]) == k]
        out.append((k, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("batches,fanout", [(1, 3), (4, 2), (6, 3)])
def test_lines(spark, batches, fanout):
    r = random.Random(8)
    pool = ["Common line of text", "common LINE of text ", "\tCommon line of text\r", "short", "", "École élémentaire", "école élémentaire", "ÉCOLE ÉLÉMENTAIRE", *[f"line number {k}" for k in range(60)]]
    rows = [(k, "\n".join(r.choice(pool) for _ in range(r.randint(0, 9)))) for k in range(120)]
    rows += [(200, None), (201, ""), (202, "Common line of text\nCommon line of text"), (None, "Common line of text"), (5, rows[5][1]), (7, "another text, line number 3\nline number 3"), (300, "\n".join(f"line number {k % 90}" for k in range(3000)))]
    docs = spark.createDataFrame([(*x, 1, 2, 3) for x in rows], "doc_id long, text string, pos long, k1 long, kept_text long")
    got = line_dedup.digest(line_dedup.dedup_lines(docs, batches=batches, fanout=fanout)).collect()
    assert sorted(map(tuple, got), key=str) == plain_lines(rows)


def test_lines_rewrite(spark):
    docs = spark.createDataFrame([(1, "the same long line\nown", "x", 9), (2, "the same long line\nother", "y", 9), (3, None, None, None)], "doc_id long, text string, source string, n_chars long")
    assert {tuple(r) for r in line_dedup.rewrite(docs).collect()} == {(1, "the same long line\nown", "x", 22), (2, "other", "y", 5), (3, "", None, 0)}
    assert line_dedup.rewrite(docs.limit(0)).collect() == []


def test_lower_ascii(spark):
    from pyspark.sql import functions as F

    texts = ["ABC", "ÀBC", "İX", "\u212a"]
    got = [r.l for r in spark.createDataFrame([(t,) for t in texts], "t string").select(lower_ascii(F.col("t")).alias("l")).collect()]
    assert got == ["abc", "Àbc", "İx", "\u212a"]


def test_runs_are_compacted_and_not_moved_again(spark):
    rows = [(k, f"line number {k % 9} of all\nown line {k} here\nshared by every text") for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    runs = line_dedup.LineRuns()
    gone = line_dedup.repeated_lines(docs, runs=runs).collect()
    assert runs.compacted == 1 and sorted(len(level) for level in runs.levels) == [1, 2]
    assert len(gone) == 31 + 39
    keys = line_dedup._lines(docs, 10).groupBy("k1", "k2").agg({"doc_id": "min"})
    plan = runs.unknown(keys)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("SortMergeJoin") == 3 and plan.count("Exchange hashpartitioning") == 1 and plan.count("Sort [") == 1


def test_batches_follow_the_size(spark, monkeypatch, tmp_path):
    docs = spark.createDataFrame([(k, "text " * 50) for k in range(100)], "doc_id long, text string")
    docs.write.parquet(str(tmp_path / "d"))
    docs = spark.read.parquet(str(tmp_path / "d"))
    assert line_dedup.batches_for(docs) == line_dedup.LEAST_BATCHES
    monkeypatch.setattr(line_dedup, "BATCH_BYTES", 100)
    assert line_dedup.batches_for(docs) == line_dedup.MOST_BATCHES
