"""URL rules, quality rules and classifier, licenses, backoff scores: brute force and odd rows."""

import glob
import os
import re
from collections import Counter

import duckdb
import numpy as np
import pytest
import regex

from tests.conftest import MIDDLE, SMALL
from vecquant.llm import backoff_joins, backoff_lm, license_scan, quality_rules, queries, rule_ensemble, textstats, url_rules

ODD = [(1, None), (2, ""), (3, " \n\t"), (4, "one"), (5, "a b c " * 60), (6, "X" * 5000), (7, "x\nx\n\nx"), (7, "x\nx\n\nx"), (None, "no id here"), (8, "ÄÖ ß # * $")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, None if i == 1 else "en", 1, "k") for i, t in ODD], "doc_id long, text string, lang string, n_words int, kept string")


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for f in glob.glob(f"{MIDDLE}/*.parquet"):
        c.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


@pytest.mark.parametrize("name", ["op1_url_rules", "op10_backoff_lm"])
def test_equals_sql(spark, duck, name):
    df = queries.queries()[name](spark, MIDDLE)
    columns = sorted(df.columns)
    own = sorted(repr(tuple(r[c] for c in columns)) for r in df.collect())
    result = duck.sql(queries.oracle_sql()[name])
    place = [result.columns.index(c) for c in columns]
    assert own == sorted(repr(tuple(r[i] for i in place)) for r in result.fetchall())


def test_url_rules_odd(spark):
    urls = [None, "", "no scheme", "http://", "HTTP://A.B.Net", "http://net/x", "http://a.net", "http://a.net/?q", "x://www.Example.NET/en/1#a", "x://example.net/en", "x://notnet/", "x://a..net/", "x://org/fr/"]
    pages = spark.createDataFrame([(i, u, "h", "r") for i, u in enumerate([*urls, urls[5]])], "page_id int, url string, host string, rule string")
    rows = {r.page_id: r for r in url_rules.judge_urls(pages, url_rules.rule_table(spark, queries.URL_RULES)).collect()}
    assert len(rows) == len(urls) + 1
    assert [rows[i].rule for i in range(len(urls))] == [None, None, None, None, None, "net/", None, "net/", "example.net/en/", "net/", None, "net/", "org/fr/"]
    assert rows[4].host == "a.b.net" and rows[8].path == "/en/1" and rows[5].verdict == "block" == rows[13].verdict and rows[0].verdict == "allow"
    none = url_rules.rule_table(spark, queries.URL_RULES).where("verdict = 'x'")
    assert {r.verdict for r in url_rules.judge_urls(pages, none).collect()} == {"allow"}
    assert url_rules.judge_urls(pages.where("page_id > 99"), url_rules.rule_table(spark, queries.URL_RULES)).count() == 0


def base_counts(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    seen, repeats = set(), 0
    for line in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            repeats += line in seen
            seen.add(line)
    windows = Counter(tuple(words[k : k + 3]) for k in range(len(words) - 2))
    covered = {k + j for k in range(len(words) - 2) if windows[tuple(words[k : k + 3])] > 1 for j in range(3)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), repeats, len(covered)


NAMES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def test_quality_counts(spark, odd):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    texts = dict(docs.select("doc_id", "text").collect())
    rows = quality_rules.quality_rules(docs).collect()
    assert len(rows) == len(texts)
    for r in rows:
        n = base_counts(texts[r.doc_id] or "")
        assert tuple(r[c] for c in NAMES) == n
        assert r.base_failed == (n[0] < 50 or 100 * n[4] > 50 * n[0]) and not (r.base_failed and r.kept)
    rows = quality_rules.quality_rules(odd).collect()
    assert len(rows) == len(ODD) and all(tuple(r[c] for c in NAMES) == base_counts(dict(ODD)[r.doc_id] or "") for r in rows)
    assert quality_rules.quality_rules(odd.where("doc_id > 99")).count() == 0
    assert quality_rules.keep_clean(odd).count() == 0 and quality_rules.keep_clean(docs).columns == docs.columns


CLASS_CHARS = {"upper": "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "digit": "0123456789", "space": " \t\x0b\x0c\r", "line": "\n", "stop": ".,;:?", "mark": "!\"'()-", "symbol": "#*$%&|<>"}


def plain_shares(text):
    """Distributions of classes and of common words, by character and word."""
    classes = Counter()
    for c in text:
        named = [k for k, chars in CLASS_CHARS.items() if c in chars]
        classes[named[0] if named else "lower" if "a" <= c <= "z" else "wide" if ord(c) > 127 else "other"] += 1
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    listed = textstats.common_word_list()
    form = {f: w for w in listed for f in (w, w.capitalize(), w.upper())}
    common = Counter(form.get(w, "") for w in words)
    a = [classes[c] / max(1, len(text)) for c in textstats.CLASSES]
    b = [common[w] / max(1, len(words)) for w in [*listed, ""]]
    return a, b


def plain_distance(p, q):
    kl = lambda x, m: sum(a * np.log2(a / b) for a, b in zip(x, m, strict=True) if a > 0)
    m = [(a + b) / 2 for a, b in zip(p, q, strict=True)]
    return float(np.sqrt(max(0.0, (kl(p, m) + kl(q, m)) / 2)))


def plain_verdicts(rows, prior=20.0):
    """kept, class_distance and word_distance of (text, language) rows, from first principles."""
    shares, counts = [plain_shares(t or "") for t, _ in rows], [base_counts(t or "") for t, _ in rows]
    failed = [n[0] < 50 or 100 * n[4] > 50 * n[0] for n in counts]
    members = {}
    for i, (_, lang) in enumerate(rows):
        if not failed[i]:
            members.setdefault(lang or "und", []).append(i)
    means = {k: (len(v), *(np.mean([shares[i][s] for i in v], axis=0) for s in (0, 1))) for k, v in members.items()}
    out = []
    for i, (t, lang) in enumerate(rows):
        if not means:
            out.append((False, None, None))
            continue
        near = min(means, key=lambda k: (plain_distance(shares[i][0], means[k][1]) + plain_distance(shares[i][1], means[k][2]), -means[k][0], k))
        n = means.get(lang or "und", (0,))[0]
        mixed = [(n * means[lang or "und"][s] + prior * means[near][s]) / (n + prior) if n else means[near][s] for s in (1, 2)]
        by_class = plain_distance(shares[i][0], mixed[0]) if len(t or "") >= 200 else None
        by_word = plain_distance(shares[i][1], mixed[1]) if counts[i][0] >= 100 else None
        far = (by_class or 0) > 0.26 or (by_word or 0) > 0.335 or (by_class or 0) + (by_word or 0) > 0.45
        out.append((not failed[i] and not far, by_class, by_word))
    return out


@pytest.mark.parametrize("lang", ["lang", "case when lang = 'de' and doc_id % 2 = 0 then 'en' else lang end", "case when lang = 'de' then concat('x', doc_id % 9) else lang end", "null"])
def test_quality_verdicts_match_brute_force(spark, lang):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").selectExpr("doc_id", "text", f"cast({lang} as string) as lang")
    rows = docs.collect()
    truth = dict(zip([r.doc_id for r in rows], plain_verdicts([(r.text, r.lang) for r in rows]), strict=True))
    near = lambda a, b: (a is None) == (b is None) and (a is None or abs(a - b) < 1e-5)
    for r in quality_rules.quality_rules(docs).collect():
        kept, by_class, by_word = truth[r.doc_id]
        assert r.kept == kept and near(r.class_distance, by_class) and near(r.word_distance, by_word)


def test_many_languages_are_joined(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").selectExpr("doc_id", "text", "concat('l', doc_id % 30) as language")
    stats = textstats.text_statistics(docs, "text", ("doc_id", "language"))
    sums = quality_rules.language_sums(stats)
    both = [sorted((r.doc_id, r.kept, r.class_distance, r.word_distance) for r in quality_rules.judge(stats, sums, quality_rules.RuleLimits(), n).where("class_distance is not null and word_distance is not null").collect()) for n in (4_096, 3)]
    assert both[0] == both[1] and len(both[0]) > 50


def test_mislabelled_documents_go(spark):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    moved = docs.selectExpr("doc_id", "text", "case when lang = 'de' and doc_id % 2 = 0 then 'en' else lang end as lang", "lang as was")
    rows = quality_rules.quality_rules(moved).join(moved.select("doc_id", "lang", "was"), "doc_id").where("not base_failed and n_words >= 100").collect()
    share = lambda some: np.mean([r.kept for r in some])
    assert share([r for r in rows if r.was == "de" and r.lang == "en"]) < 0.1
    assert share([r for r in rows if r.was == r.lang]) > 0.9


def test_quality_rules_agree_with_labels(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    judged = quality_rules.quality_rules(docs).where("not base_failed").join(labels, "doc_id")
    kept = {r.quality: r.share for r in judged.groupBy("quality").agg({"kept": "count"}).withColumnRenamed("count(kept)", "n").join(judged.where("kept").groupBy("quality").count(), "quality").selectExpr("quality", "count / n share").collect()}
    assert kept[1] > 0.995 and kept[0] < 0.3


def test_jensen_shannon():
    p = np.array([[0.5, 0.5, 0], [1, 0, 0]])
    d = quality_rules.jensen_shannon(p, np.array([[0.5, 0.5, 0], [0, 0, 1.0]]))
    assert d[0, 0] == 0 and d[1, 1] == pytest.approx(1) and 0 < d[1, 0] < 1


def test_repeated_windows_match_brute_force():
    rng = np.random.default_rng(0)
    texts = [" ".join(rng.choice(list("abc"), rng.integers(0, 30))) for _ in range(200)]
    assert textstats.count_texts(texts)["n_repeat_words"].tolist() == [base_counts(t)[4] for t in texts]


def test_classifier_holds_out(spark, odd):
    sf = "/root/testdata/sf0.1"
    scored = queries.op4_rule_ensemble(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id")
    held = scored.where("held_out").select("predicted", "quality").toPandas()
    assert len(held) > 500 and (held.predicted == held.quality).mean() > 0.98
    model = rule_ensemble.fit_on_documents(spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet"))
    rows = rule_ensemble.score_documents(odd, model, ("doc_id",)).collect()
    assert len(rows) == len(ODD) and all(0 <= r.score <= 1 for r in rows)
    labels = spark.createDataFrame([(None, 1), (3, None)], "doc_id long, quality int")
    assert rule_ensemble.fit_on_documents(odd, labels).rules == []


def test_score_column_matches_numpy(spark):
    docs, labels = (spark.read.parquet(f"{MIDDLE}/{t}.parquet") for t in ("documents", "labels"))
    model = rule_ensemble.fit_on_documents(docs, labels)
    columns = rule_ensemble.features()
    values = {r.doc_id: r for r in textstats.text_statistics(docs, "text", ("doc_id",)).select("doc_id", *[c.alias(n) for n, c in columns.items()]).collect()}
    assert len(model.rules) > 3
    for r in rule_ensemble.score_documents(docs, model, ("doc_id",)).collect():
        total = model.bias + sum(w for rule, w in model.rules if all((values[r.doc_id][n] > t) == up for n, up, t in rule))
        assert r.score == pytest.approx(1 / (1 + np.exp(-total)), abs=1e-9)


def test_classifier_of_empty_and_repeated_rows(spark, odd):
    docs, labels = (spark.read.parquet(f"{SMALL}/{t}.parquet") for t in ("documents", "labels"))
    assert rule_ensemble.fit_on_documents(docs, labels.limit(0)).rules == []
    assert rule_ensemble.fit_on_documents(docs.limit(0), labels).score() is not None
    model = rule_ensemble.fit_on_documents(docs, labels)
    assert rule_ensemble.score_documents(odd.where("doc_id > 99"), model, ("doc_id",)).count() == 0
    # A labelled id that stands on very many rows still teaches once.
    again = docs
    for _ in range(5):
        again = again.unionByName(again)
    twice = rule_ensemble.fit_on_documents(again, labels)
    assert (twice.bias, twice.rules) == (model.bias, model.rules)


def test_rules_fit_a_conjunction():
    rng = np.random.default_rng(1)
    x = rng.random((2000, 3))
    y = ((x[:, 0] > 0.5) & (x[:, 2] <= 0.3)).astype(float)
    model = rule_ensemble.fit_rules(x, y, ["a", "b", "c"])
    assert 0 < len(model.rules) < 60
    held = np.array([all((x[i, "abc".index(n)] > t) == up for n, up, t in rule) * w for rule, w in model.rules for i in range(2000)]).reshape(-1, 2000).sum(axis=0)
    assert ((held + model.bias > 0) == (y > 0)).mean() > 0.97
    assert rule_ensemble.fit_rules(x, np.ones(2000), ["a", "b", "c"]).rules == []


def plain_license(model, part):
    """(family or None, whether it is likely) of one paragraph."""
    if not any(x in part.lower() for x in license_scan.STEMS):
        return None, False
    p = model.probabilities(part)
    k = int(p.argmax())
    likely = p[k] >= model.threshold
    return (model.families[k] if likely and license_scan.confirms(part, model.families[k]) else None), likely


def test_licenses_match_brute_force(spark, odd):
    model = license_scan.train()
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    texts = dict(docs.select("doc_id", "text").collect())
    for r in license_scan.scan_licenses(docs, model).collect():
        found = [plain_license(model, part) for part in regex.split(license_scan.PARAGRAPH_END, texts[r.doc_id] or "")]
        good = [f for f, _ in found if f]
        assert r.n_paragraphs == len(good) and r.n_unconfirmed == sum(likely for f, likely in found if not f)
        assert r.families == ",".join(sorted(set(good))) and (r.family is None) == (not good)
    rows = license_scan.scan_licenses(odd, model).collect()
    assert len(rows) == len(ODD) and all(r.family is None for r in rows)
    more = spark.createDataFrame([(1, "x\nReleased under the MIT License."), (1, "x\nReleased under the MIT License."), (None, "Licensed under CC BY-NC 4.0."), (2, "The license plate was new.")], "doc_id long, text string")
    assert sorted((str(r.doc_id), str(r.family), r.n_paragraphs) for r in license_scan.scan_licenses(more, model).collect()) == [("1", "MIT", 1), ("1", "MIT", 1), ("2", "None", 0), ("None", "CC-BY-NC-4.0", 1)]
    assert license_scan.scan_licenses(more.where("doc_id > 99"), model).count() == 0
    plan = license_scan.scan_licenses(docs, model)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


WRAPPED = [
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify\nit under the terms of the GNU General Public License as published by\nthe Free Software Foundation, either version 3 of the License, or\n(at your option) any later version."),
    ("BSD", "# Redistribution and use in source and binary forms, with or without\n# modification, are permitted provided that the following conditions\n# are met:"),
    ("LGPL", "This library is free software; you can redistribute it and/or\nmodify it under the terms of the GNU Lesser General Public\nLicense as published by the Free Software Foundation; either\nversion 2.1 of the License, or (at your option) any later version."),
]


def test_neighbouring_licenses_are_told_apart(spark):
    rows = [
        ("CC-BY-SA-4.0", "Creative Commons Attribution-ShareAlike 4.0"), ("CC-BY-4.0", "Attribution 4.0 by Creative Commons"),
        ("CC-BY-SA-4.0", "This text is licensed under CC BY-SA 4.0"), ("CC-BY-4.0", "Shared under CC BY 4.0"),
        ("GPL-2.0", "Licensed under the GPL version 2"), ("LGPL", "GNU Lesser General Public License v3"), ("AGPL-3.0", "SPDX-License-Identifier: AGPL-3.0"),
        ("BSD-2-Clause", "Released under the BSD-2-Clause license"), ("MPL-2.0", "Mozilla Public License 2.0"),
        (None, "This is not licensed under the MIT license."), (None, "Licensed under CC BY-NC-SA 4.0."), (None, "Eclipse Public License 2.0"),
        ("MIT", "Released under the MIT License."), ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
        ("Apache-2.0", "Licensed under the Apache License, Version 2.0."), ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."), (None, "All rights reserved."), *WRAPPED,
    ]
    docs = spark.createDataFrame([(i, f"Some words went before.\n{t}\n\nMore words follow here") for i, (_, t) in enumerate(rows)], "doc_id long, text string")
    found = {r.doc_id: r.family for r in license_scan.scan_licenses(docs, license_scan.train()).collect()}
    # A neighbour's notice is its own family's or of none, never another one's.
    assert all(found[i] in (f, None) for i, (f, _) in enumerate(rows))
    assert sum(found[i] == f for i, (f, _) in enumerate(rows)) >= len(rows) - 2 and all(found[i] == f for i, (f, _) in enumerate(rows) if i >= 12)


def test_every_template_has_a_stem():
    assert all(any(x in t.lower() for x in license_scan.STEMS) for templates in license_scan.TEMPLATES.values() for t in templates)


def test_licenses_in_long_texts(spark):
    rows = [(1, "." * 1_000_000 + "a license"), (2, "\n" * 500_000 + "Released under the MIT License."), (3, "license " * 200_000), (4, "x" * 2_000_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.doc_id: r.family for r in license_scan.scan_licenses(docs, license_scan.train()).collect()} == {1: None, 2: "MIT", 3: None, 4: None}


def brute_lm(texts, order):
    words = [t.encode().lower().split() for t in texts]
    grams = lambda w, n: [tuple(w[k : k + n]) for k in range(len(w) - n + 1)]
    totals = {n: Counter(g for w in words for g in grams(w, n)) for n in range(1, order + 1)}
    size, out = sum(map(len, words)), []
    for w in words:
        own = {n: Counter(grams(w, n)) for n in range(1, order + 1)}
        left = lambda g: totals[len(g)][g] - own[len(g)][g]  # noqa: B023, E731
        rest, score = max(size - len(w), 1), 0.0
        for i in range(len(w)):
            for n in range(min(order, i + 1), 0, -1):
                g = tuple(w[i - n + 1 : i + 1])
                below = rest if n == 1 else left(g[:-1])
                if left(g) > 0 and below > 0:
                    score += np.log10(0.4 ** (order - n) * left(g) / below)
                    break
            else:
                score += np.log10(0.4**order / (rest + 1))
        out.append(score)
    return out


@pytest.mark.parametrize("order", [2, 3, 4])
@pytest.mark.parametrize("tables", [(1 << 18, 1 << 19), (2, 3), (0, 0)])
def test_backoff_scores(spark, monkeypatch, order, tables):
    monkeypatch.setattr(backoff_joins, "SHORT_TABLE", tables[0])
    monkeypatch.setattr(backoff_joins, "LONG_TABLE", tables[1])
    rng = np.random.default_rng(2)
    texts = [" ".join(rng.choice(list("abcdeF"), rng.integers(0, 25))) for _ in range(60)] + ["", "zz", "a b a b a b"]
    docs = spark.createDataFrame([(i, t, 0, 1, 2) for i, t in enumerate(texts)], "doc_id long, text string, n_tokens int, key int, rest int")
    rows = {r.doc_id: r for r in backoff_joins.score_documents(docs, order=order).collect()}
    assert np.allclose([rows[i].log10_score for i in range(len(texts))], brute_lm(texts, order))
    assert rows[60].mean_log10_score is None and rows[60].n_tokens == 0


@pytest.mark.parametrize("order", [2, 3])
def test_packed_scores_are_those_of_the_joins(spark, order):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    plain = {r.doc_id: r.log10_score for r in backoff_joins.score_documents(docs, order=order).collect()}
    for most in (10_000, 3):  # over 3 blocks, the joins run
        found = backoff_lm.score_documents(docs, order=order, block_chars=2_000, least_blocks=1, most_blocks=most).collect()
        assert len(found) == len(plain) and np.allclose([r.log10_score for r in found], [plain[r.doc_id] for r in found])


def test_backoff_odd(spark, odd):
    packed = backoff_lm.score_documents(odd).collect()
    assert np.allclose(sorted(r.log10_score for r in packed), sorted(brute_lm([t or "" for _, t in ODD], 2)))
    assert backoff_lm.score_documents(odd.where("doc_id > 99")).count() == 0
    rows = backoff_joins.score_documents(odd).collect()
    assert len(rows) == len(ODD) and len({r.log10_score for r in rows if r.doc_id == 7}) == 1
    assert np.allclose(sorted(r.log10_score for r in rows), sorted(brute_lm([t or "" for _, t in ODD], 2)))
    assert backoff_joins.score_documents(odd.where("doc_id > 99")).count() == 0


def test_backoff_of_many_copies(spark):
    """One text that holds most rows, and one word that fills a text."""
    texts = ["the same old words again"] * 300 + ["again and again the old"] + ["word " * 20_000]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3, "doc_id")
    rows = {r.doc_id: r.log10_score for r in backoff_joins.score_documents(docs).collect()}
    assert np.allclose([rows[i] for i in range(len(texts))], brute_lm(texts, 2))


def test_reserved_rights_are_seen(spark):
    rows = [(1, "a line\nAll rights reserved."), (2, None), (3, "ALL RIGHTS  RESERVED x\nall rights are reserved\nMIT"), (4, "overall rights reserved")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    found = {r.doc_id: (r.family, r.n_reserved) for r in license_scan.scan_licenses(docs, license_scan.train()).collect()}
    assert found == {1: (None, 1), 2: (None, 0), 3: (None, 2), 4: (None, 0)}
