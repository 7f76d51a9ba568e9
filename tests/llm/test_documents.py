"""The operators over documents against brute force, on odd rows and on small corpora."""

import hashlib
import random
import re
import zlib

import pytest
import xxhash

from diversify.llm import fingerprints, leaks, licences, mixing, pii, quality, repeats, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def rows(df, *by):
    return sorted((r.asDict() for r in df.collect()), key=lambda r: tuple((r[b] is None, r[b]) for b in by))


ALL = [
    (pii.personal_data, {"doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans"}), (toxicity.toxicity, {"doc_id", "held_out", "score", "predicted"}),
    (repeats.repeats, {"doc_id", "n_words", "n_removed", "kept_sha256"}), (licences.licences, {"doc_id", "family", "families", "n_notices", "confidence"}),
    (mixing.mixing, {"doc_id", "size", "source_size", "target", "taken"}), (fingerprints.simhash, {"doc_id", "fingerprint", "component_id"}),
    (leaks.leaks, {"doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"}), (quality.quality, {"doc_id", "held_out", "score", "predicted"}),
]


@pytest.mark.parametrize("run,columns", ALL)
def test_odd_rows_keep_a_row_each(spark, tables, odd, run, columns):
    d = tables(documents=odd, labels=[(1, 1, 0), (5, 0, 1), (5, None, None), (None, 1, 1), (7, 1, 0)], benchmark=[(1, None), (2, ""), (None, "not listed"), (3, "one two three")])
    found = run(spark, d)
    assert columns <= set(found.columns)
    assert sorted(str(r.doc_id) for r in found.collect()) == sorted(str(r[0]) for r in odd)


@pytest.mark.parametrize("run,columns", ALL)
def test_empty_tables(spark, tables, run, columns):
    assert run(spark, tables()).collect() == []


def corpus(n=60, seed=3):
    """Documents with copies, near copies, shared passages and a hot text."""
    rng = random.Random(seed)
    words = ["w%d" % i for i in range(400)]
    out, passage = [], [rng.choice(words) for _ in range(45)]
    for i in range(n):
        t = [rng.choice(words) for _ in range(rng.randrange(3, 120))]
        if i % 4 == 1:
            at = rng.randrange(len(t))
            t[at:at] = passage[rng.randrange(10) : 45 - rng.randrange(10)]
        if i % 5 == 2:
            t = list(out[rng.randrange(len(out))])
            t[rng.randrange(len(t))] = "changed"
        if i % 6 == 3:
            t = list(out[0])
        out.append(t)
    return [(i, " ".join(t) if i % 2 else "\n".join(t), "en", f"s{i % 3}", 1) for i, t in enumerate(out)]


@pytest.mark.parametrize("sampled,often", [(32, 1000), (1, 3), (1, 1)])
def test_repeats_match_brute_force(spark, tables, monkeypatch, sampled, often):
    monkeypatch.setattr(repeats, "SAMPLED", sampled)
    monkeypatch.setattr(repeats, "OFTEN", often)
    docs = corpus()
    got = rows(repeats.repeats(spark, tables(documents=docs)), "doc_id")
    seen = set()
    for r, (_, text, *_) in zip(got, docs, strict=True):
        w, gone = text.split(), set()
        for p in range(len(w) - 19):
            k = tuple(w[p : p + 20])
            if k in seen:
                gone.update(range(p, p + 20))
            seen.add(k)
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        assert (r["n_words"], r["n_removed"], r["kept_sha256"]) == (len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest())


def test_a_frequent_phrase_is_dealt_by_its_words(spark, tables, monkeypatch):
    monkeypatch.setattr(repeats, "SAMPLED", 1)
    monkeypatch.setattr(repeats, "OFTEN", 20)
    rng, phrase = random.Random(5), [f"p{i}" for i in range(12)]
    docs = [(i, " ".join([f"l{rng.random()}" for _ in range(15)] + phrase + [f"r{rng.random()}" for _ in range(15)]), "en", "a", 1) for i in range(200)]
    docs += [(200 + i, docs[7][1], "en", "a", 1) for i in range(3)]
    frame = spark.read.parquet(f"{tables(documents=docs)}/documents.parquet")
    named = repeats._named(frame)
    found = repeats.frequent_anchors(named)
    assert len(found)
    at = repeats._seed_rows(named, found).where("state = 2").groupBy("a").count().agg({"count": "max"}).first()[0]
    assert at <= 4
    monkeypatch.setattr(repeats, "MOST_OFTEN", 0)
    assert not len(repeats.frequent_anchors(named))
    got = rows(repeats.without_repeats(frame), "doc_id")
    assert [r["n_removed"] for r in got] == [0] * 200 + [42] * 3


def test_a_document_repeats_itself(spark, tables):
    w = [f"a{i}" for i in range(20)]
    got = rows(repeats.repeats(spark, tables(documents=[(1, " ".join(w * 3), "en", "a", 1), (2, " ".join(["z"] * 60), "en", "a", 1)])), "doc_id")
    assert [r["n_removed"] for r in got] == [40, 59]


def fingerprint(t):
    w = WORD.findall(lower(t))
    shingles = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def components(fp):
    """doc -> smallest doc that links reach."""
    ids, of = sorted(fp), {}
    for i in ids:
        if i in of:
            continue
        todo = [i]
        while todo:
            x = todo.pop()
            if x in of:
                continue
            of[x] = i
            todo += [y for y in ids if y not in of and (fp[x] ^ fp[y]).bit_count() <= 2]
    return of


def test_simhash_matches_brute_force(spark, tables, odd):
    docs = corpus() + [(100 + i, t, None, None, None) for i, (_, t, *_) in enumerate(odd) if t is None or len(t) < 1000]
    got = rows(fingerprints.simhash(spark, tables(documents=docs)), "doc_id")
    fp = {i: fingerprint(t) for i, t, *_ in docs}
    assert [r["fingerprint"] for r in got] == [f"{fp[r['doc_id']]:016x}" for r in got]
    of = components(fp)
    assert {r["doc_id"]: r["component_id"] for r in got} == of


def test_vantage_shards_lose_no_link(spark, monkeypatch):
    """Many shards, and a crowd that is dealt by neighbouring values."""
    import numpy as np

    rng = np.random.default_rng(5)
    base = rng.integers(0, 2**63, 400, dtype=np.uint64)
    crowd = np.unique(base[0] ^ (np.uint64(1) << rng.integers(0, 20, (700, 3)).astype(np.uint64)).sum(1).astype(np.uint64))
    near = base ^ (np.uint64(1) << rng.integers(0, 64, 400).astype(np.uint64))
    fp = np.unique(np.concatenate((base, near, crowd))).view(np.int64)
    monkeypatch.setattr(fingerprints, "SHARD", 60)
    monkeypatch.setattr(fingerprints, "CROWD", 300)
    from diversify.llm.links import components as joined

    links = fingerprints.near_links(spark.createDataFrame([(int(x),) for x in fp], "fp long"))
    got = {r.node: r.component for r in joined(links, "a", "b").collect()}
    u = fp.view(np.uint64)
    root = list(range(len(fp)))
    for i in range(len(fp)):
        for j in np.flatnonzero(np.bitwise_count(u ^ u[i]) <= 2):
            a, b = i, int(j)
            while root[a] != a:
                a = root[a]
            while root[b] != b:
                b = root[b]
            root[max(a, b)] = min(a, b)
    for i in range(len(fp)):
        a = i
        while root[a] != a:
            a = root[a]
        group = [int(fp[k]) for k in range(len(fp)) if got.get(int(fp[k]), int(fp[k])) == got.get(int(fp[i]), int(fp[i]))]
        assert int(fp[a]) in group


TOKEN = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def test_leaks_match_brute_force(spark, tables, odd):
    docs = corpus(30)
    items = [(k, " ".join(docs[k][1].split()[2:20]).upper() + "!") for k in (1, 5, 9)] + [(77, "w1 w2"), (78, None), (79, "..."), (9, "w3")]
    docs += [(200, "W1, w2; and\nw3 end", "en", "a", 1), (201, None, None, None, None)]
    got = rows(leaks.leaks(spark, tables(documents=docs, benchmark=items)), "doc_id")
    windows = set()
    for k, t in items:
        w = TOKEN.findall(lower(t))
        n = min(len(w), 10)
        windows |= {(k, tuple(w[p : p + n])) for p in range(len(w) - n + 1) if n}
    for r, (_, t, *_) in zip(got, sorted(docs), strict=True):
        w, hit, ids = TOKEN.findall(lower(t)), set(), set()
        for k, g in windows:
            for p in range(len(w) - len(g) + 1):
                if tuple(w[p : p + len(g)]) == g:
                    hit.update(range(p, p + len(g)))
                    ids.add(str(k))
        assert (r["n_words"], r["n_hit"], r["n_items"], r["contaminated"]) == (len(w), len(hit), len(ids), bool(hit))
        assert r["items_sha256"] == hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()


BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(d):
    t = [int(c) * (1 + i % 2) for i, c in enumerate(reversed(d))]
    return sum(x - 9 * (x > 9) for x in t) % 10 == 0


def valid(kind, m):
    d = re.sub("[^0-9]", "", m)
    return {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m.split(".")), "card": 14 <= len(d) <= 19 and luhn(d), "phone": 10 <= len(d) <= 15}[kind]


PII = [
    "mail a@b.com_x@c.de, a@b@c.org. x@y z@-.- a@.com é\U0001f600 jöe@x.fr", "1.2.3.4.5.6 256.1.1.1 001.02.3.255 1.2.3 9.9.9.99999999999999999999", "4111 1111 1111 1111 and 4111-1111-1111-1112 4111  1111 1111 1111",
    "+1 (017) 555-7713 or ++1 234 567 890 12 tel +49-30-1234567.", "+1........................... 5", "token = \"0123456789abcdef0123\" call (555) 123-4567 now", "1234567890123456789012345 0 0 0 0 0 0 0 0 0 0 0 0 0 0 0", "a" * 20000 + "@" + "b." * 6000 + "com", "1 " * 5000,
]


def test_base_spans_match_the_plain_patterns(spark, tables):
    docs = [(i, t, "en", "a", 1) for i, t in enumerate(PII)] + [(0, PII[0], "en", "a", 1), (1, PII[2], "en", "a", 1)]
    got = pii.personal_data(spark, tables(documents=docs)).collect()
    want = []
    for i, t, *_ in docs:
        found = sorted((m.start(), n, f"{k}:{m.start()}:{m.end()}", k) for n, (k, p) in enumerate(BASE.items()) for m in re.finditer(p, t) if valid(k, m[0]))
        want.append((i, *(sum(f[3] == k for f in found) for k in BASE), hashlib.sha256(",".join(f[2] for f in found).encode()).hexdigest(), {f[2] for f in found}))
    assert sorted((r.doc_id, r.n_email, r.n_ip, r.n_card, r.n_phone, r.base_sha256) for r in got) == sorted(w[:-1] for w in want)
    for r in got:
        assert any(w[0] == r.doc_id and w[5] == r.base_sha256 and w[6] <= set(r.spans.split(",") if r.spans else []) for w in want)


def test_masking_replaces_every_span(spark, tables):
    d = tables(documents=[(1, "é mail a@b.com or 4111 1111 1111 1111.", "en", "a", 1), (2, "nothing here", "en", "a", 1), (3, None, None, None, None)])
    got = rows(pii.masked(spark.read.parquet(f"{d}/documents.parquet")), "doc_id")
    assert [r["text"] for r in got] == ["é mail [EMAIL] or [CARD].", "nothing here", None]


def test_estimation_finds_the_useless_labeler():
    rng = random.Random(1)
    patterns = {}
    for _ in range(4000):
        truth = rng.random() < 0.4
        v = tuple((1 if truth else -1) if rng.random() < a else (-1 if truth else 1) for a in (0.95, 0.9, 0.5))
        patterns[v] = patterns.get(v, 0) + 1
    p = pii.estimate([("card", v, n) for v, n in patterns.items()])
    assert p["card", (1, 1, 1)] > 0.95 and p["card", (-1, -1, 1)] < 0.05
    assert abs(p["card", (1, 1, 1)] - p["card", (1, 1, -1)]) < 0.1


def test_mix_meets_targets_and_shards_are_disjoint(spark, tables):
    docs = corpus(80)
    d = tables(documents=docs + [(500, None, "en", None, 1), (501, "no source", "en", None, 1)])
    got = rows(mixing.mixing(spark, d), "doc_id")
    sizes = {}
    for _, t, _, s, _ in docs:
        sizes[s] = sizes.get(s, 0) + len(t.split())
    assert all(r["taken"] <= 2 * r["size"] for r in got)
    want = mixing.targets([*(sizes[s] for s in sorted(sizes)), 2])
    assert abs(sum(want) - 1.5 * (sum(sizes.values()) + 2)) < 1e-6
    for k, s in enumerate(sorted(sizes)):
        mine = [r for r in got if r["doc_id"] < 500 and docs[r["doc_id"]][3] == s]
        assert {r["target"] for r in mine} == {want[k]} and abs(sum(r["taken"] for r in mine) - want[k]) <= 1
    again = rows(mixing.mixing(spark, d), "doc_id")
    assert got == again
    mixed = mixing.mix(spark.read.parquet(f"{d}/documents.parquet")).collect()
    assert len({(r.doc_id, r["pass"]) for r in mixed}) == len(mixed)
    assert sum(r.words for r in mixed) == sum(r["taken"] for r in got)
    assert all(len(r.text.split()) == r.words for r in mixed)


def test_splitting_tree_keeps_quotas():
    t = mixing.splitting_tree([100, 7, 0, 1001], 8)
    assert t.sum(0).tolist() == [100, 7, 0, 1001] and t.sum(1).max() - t.sum(1).min() <= 1
    assert (t == mixing.splitting_tree([100, 7, 0, 1001], 8)).all()


def test_hypergeometric_draws_follow_the_distribution():
    """The draw is the quantile of the exact distribution, from binomials of whole numbers."""
    from fractions import Fraction
    from math import comb

    rng = random.Random(3)
    for _ in range(300):
        good, bad = rng.randrange(0, 60), rng.randrange(0, 60)
        n, u = rng.randrange(0, good + bad + 1), rng.random()
        share, x = Fraction(0), max(0, n - bad) - 1
        while share < u and x < min(good, n):
            x += 1
            share += Fraction(comb(good, x) * comb(bad, n - x), comb(good + bad, n))
        assert mixing.hypergeometric(good, bad, n, u) == x
    assert abs(mixing.hypergeometric(10**9, 3 * 10**9, 10**9, 0.5) - 25 * 10**7) < 10**5


def test_shards_of_the_mix_have_the_tree_s_quotas_and_an_order(spark, tables):
    docs = corpus(90)
    d = tables(documents=docs)
    whole = spark.read.parquet(f"{d}/documents.parquet")
    mixed = mixing.shuffled(mixing.mix(whole, 5)).collect()
    by_hash = sorted({(hashlib.md5(str(i).encode()).hexdigest()[:15], i) for i, *_ in docs})
    block = {i: int(h, 16) >> 50 for h, i in by_hash}
    units = {(docs[r.doc_id][3], r["pass"], block[r.doc_id]): r.shard for r in mixed if r.words}
    assert all(units[docs[r.doc_id][3], r["pass"], block[r.doc_id]] == r.shard for r in mixed)  # a block goes as a whole
    sources = sorted({s for s, _, _ in units})
    # Blocks whose documents have no words are drawn too, so quotas are those of all blocks of the source.
    drawn = [sum(1 for u in units if u[0] == s) for s in sources]
    tree = mixing.splitting_tree(drawn, 5)
    assert [[sum(1 for u, x in units.items() if u[0] == s and x == k) for s in sources] for k in range(5)] == tree.tolist()
    for s in sources:  # shards take the next draws in permuted order
        order = sorted((p, b, x) for (t, p, b), x in units.items() if t == s)
        assert [x for *_, x in order] == sorted(x for *_, x in order)
    # Within a shard the turns of each run are in order, and not the order of the ids.
    by_shard = {}
    for part in mixing.shuffled(mixing.mix(whole, 5)).rdd.glom().collect():
        for r in part:
            by_shard.setdefault((r.shard, (r.turn % (1 << 64)) >> 60), []).append(((r.turn % (1 << 64)) >> 1, r.doc_id))
    assert all(x == sorted(x) for x in by_shard.values())
    ids = [i for _, x in sorted(by_shard.items()) for _, i in x]
    assert ids != sorted(ids) and len(ids) == len(mixed)


def test_licences_are_found_and_names_are_not(spark, tables):
    texts = ["Some text. Licensed under the Apache License, Version 2.0. More.", "Released under the MIT License", "he came mit dem common commons", "This work is licensed under the GNU General Public License, version 3.", "Licensed under CC BY-NC 4.0.", "A licensed plumber. Version 2.0 of it.", "Licensed under a secret agreement."]
    got = rows(licences.licences(spark, tables(documents=[(i, t, "en", "a", 1) for i, t in enumerate(texts)])), "doc_id")
    assert [r["families"] for r in got] == ["apache", "mit", "", "gpl", "cc-by-nc", "", ""]


def test_wrapped_and_versionless_notices(spark, tables):
    bsd = "Copyright (c) 2020, X\n\nRedistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions\nare met:"
    gpl = "# This program is free software: you can redistribute it and/or modify\n# it under the terms of the GNU General Public License as published by\n# the Free Software Foundation; either version 3 of the License, or\n# (at your option) any later version."
    mpl = "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0. If a copy of the MPL was not distributed with this\nfile, You can obtain one at http://mozilla.org/MPL/2.0/."
    texts = [bsd, gpl, mpl, "Released under the GNU General Public License.", "Licensed under the Apache License", "Released under the MIT License\nLicensed under CC BY-NC 4.0\nend", "the general\npublic\nand his license\nof mozilla"]
    got = rows(licences.licences(spark, tables(documents=[(i, t, "en", "a", 1) for i, t in enumerate(texts)])), "doc_id")
    assert [(r["families"], r["n_notices"]) for r in got] == [("bsd", 1), ("gpl", 1), ("mpl", 2), ("gpl", 1), ("apache", 1), ("cc-by-nc,mit", 2), ("", 0)]


# Hand-written notices by family, and sentences with their words that are none.
NOTICES = [
    ('gpl', 'SPDX-License-Identifier: GPL-2.0-or-later'),
    ('gpl', 'GPL-2.0-or-later'),
    ('gpl', 'it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 3 of the License, or (at your option) any later version.'),
    ('apache', 'Licensed under the Apache License, v. 2.0'),
    ('apache', 'Apache License, Version 2.0'),
    ('apache', 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.'),
    ('isc', 'ISC License'),
    ('isc', 'Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice appears.'),
    ('epl', 'This program is made available under the terms of the Eclipse Public License 2.0'),
    ('epl', 'SPDX-License-Identifier: EPL-2.0'),
    ('mit', 'SPDX-License-Identifier: MIT'),
    ('mit', 'Released under the MIT License.'),
    ('mit', 'Distributed under the MIT licence (see LICENSE).'),
    ('mit', 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction'),
    ('cc-by-nc', 'Licensed under CC BY-NC 4.0.'),
    ('cc-by-sa', 'Text is available under the Creative Commons Attribution-ShareAlike License'),
    ('cc-by', 'This article is distributed under CC BY 4.0'),
    ('cc-by', 'Creative Commons Attribution 4.0 International License'),
    ('mpl', 'This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.'),
    ('mpl', 'MPL-2.0'),
    ('lgpl', 'GNU Lesser General Public License v2.1 or later'),
    ('lgpl', 'This library is free software under the LGPL-2.1-only'),
    ('agpl', 'Licensed under AGPLv3'),
    ('agpl', 'GNU Affero General Public License'),
    ('bsd', 'Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:'),
    ('bsd', 'Licensed under the BSD 3-Clause License'),
    ('bsd', 'BSD-2-Clause'),
    ('public-domain', 'This is dedicated to the public domain under CC0 1.0 Universal'),
    ('zlib', 'licensed under the zlib license'),
    ('boost', 'Distributed under the Boost Software License, Version 1.0.'),
    ('proprietary', 'Copyright 2021 Acme Inc. All rights reserved.'),
    ('gpl', 'This work is licensed under the GNU General Public License, version 3.'),
    ('gpl', 'gplv3'),
    ('gpl', 'The code is GPL v2 licensed'),
    ('artistic', 'Artistic License 2.0'),
    ('eupl', 'Licensed under the EUPL-1.2'),
    ('proprietary', 'All rights reserved.'),
]
NO_NOTICES = [
    'the apache helicopter version 2.0 software had a license',
    'He earned a license after his years at MIT in Boston',
    'The public domain was crowded with visitors and a license fee was due',
    'The general public needs no license to enter',
    'Mozilla announced a public beta; no license is needed',
    'A gnu is an animal, and a hunting license is required',
    'The House of Commons passed the Creative Industries Act',
    'Redistribution of income in source countries was debated',
    'Permission is hereby granted to park here',
    'His artistic license annoyed the historians',
    "The driver's license office",
    'BSD users met in Berlin to talk about the kernel',
    'cc by the end of the day please',
    'the common commons committee',
    'An eclipse licensed viewing spot for the public',
    'Boost your software licensing revenue',
    'mit der Lizenz, und mit dem Licensing-Team',
    'Apache Junction is a city; the license plate shows it',
    'Licensed under a secret agreement.',
    'A licensed plumber. Version 2.0 of it.',
    'the rights reserved to the states',
    'Apache license plates are sold in Arizona',
    'The plan is to boost license fees by ten percent',
    'The court kept all rights reserved seats for the press',
    'Fahrer mit License und Ausweis',
]


def judged(spark):
    """(truth, by the classifier, by templates, by both) of the hand-written sentences."""
    texts = [*NOTICES, *(("unknown", x) for x in NO_NOTICES)]
    frame = spark.createDataFrame([(i, f, x) for i, (f, x) in enumerate(texts)], "i int, truth string, sentence string")
    frame = licences.with_templates(frame.where(licences.hinted("sentence")).withColumn("w", licences.tokens("sentence")))
    found = {r.i: r for r in licences.scored(frame, licences.train(spark)).collect()}
    for i, (truth, _) in enumerate(texts):
        r = found.get(i)
        own = r.family if r and r.p >= licences.CERTAIN else "unknown"
        yield truth, own, r.families if r else [], own if r and own in r.families else "unknown"


def test_classifier_and_templates_on_hand_written_notices(spark):
    rows_ = list(judged(spark))
    by_class = sum(t == c for t, c, _, _ in rows_)
    by_template = sum((t in m if m else t == "unknown") for t, _, m, _ in rows_)
    both = sum(t == b for t, *_, b in rows_)
    false = sum(t == "unknown" != b for t, *_, b in rows_)
    assert by_class >= 0.9 * len(rows_) and both >= 0.96 * len(rows_) and both > by_template and false <= 1


def test_every_template_has_a_hint():
    """Sentences without a hint are skipped, which loses nothing as no template is without one."""
    assert all(any(h in n for h in licences.HINTS) for names in licences.FAMILIES.values() for n in names)
    assert len({x for _, _, x in licences.examples()}) > 1000


def test_regression_matches_its_definition(spark):
    """Tokens, grams, sums and probabilities by plain Python; Spark's hash of several strings is chained XXH64 with seed 42."""
    import numpy as np

    rng = np.random.default_rng(0)
    classes = [*licences.FAMILIES, licences.UNKNOWN]
    model = licences.Regression(classes, rng.normal(size=(licences.BUCKETS, len(classes))), rng.normal(size=len(classes)), 1.3)
    texts = ["Licensed under the Apache License, v. 2.0.", "GPLv3", "", "a a a", "CC BY-NC 4.0, or MPL-2.0-only"]
    want_tokens = ["licensed under the apache license version 2", "gpl version 3", "", "a a a", "cc by-nc 4 or mpl-2"]
    frame = spark.createDataFrame(list(enumerate(texts)), "i int, sentence string").withColumn("w", licences.tokens("sentence"))
    assert [r.w for r in frame.orderBy("i").collect()] == [x.split() for x in want_tokens]
    for r, want in zip(licences.scored(frame, model).orderBy("i").collect(), want_tokens, strict=True):
        w = want.split()
        grams = {tuple(w[i : i + n]) for n in (1, 2, 3) for i in range(len(w) - n + 1)}
        level = model.bias * model.scale
        found = set()
        for g in grams:
            h = 42
            for x in g:
                h = xxhash.xxh64_intdigest(x.encode(), h)
            found.add((h - (1 << 64) if h >> 63 else h) % licences.BUCKETS)
        level = level + sum((model.weights[b] * model.scale for b in found), np.zeros(len(classes)))
        p = np.exp(level - level.max())
        assert r.family == classes[int(np.argmax(level))] and abs(r.p - 1 / p.sum()) < 2e-6


def folded(i):
    return zlib.crc32(str(i).encode()) % 3


def test_quality_separates_held_out_documents(spark, tables):
    rng = random.Random(2)
    good = lambda: "\n".join(" ".join(rng.choice(["the", "of", "river", "green", "walks", "house"]) for _ in range(12)).capitalize() + "." for _ in range(6))
    bad = lambda: "\n".join(" ".join(rng.choice(["BUY", "NOW!!", "$$$", "FREE***"]) for _ in range(12)) for _ in range(6))
    docs = [(i, good() if i % 2 else bad(), "en", "a", 1) for i in range(120)]
    got = rows(quality.quality(spark, tables(documents=docs, labels=[(i, i % 2, 0) for i in range(120)])), "doc_id")
    assert all(r["held_out"] == (folded(r["doc_id"]) == 1) for r in got)
    assert all(r["predicted"] == r["doc_id"] % 2 for r in got if r["held_out"])
    assert all(0 <= r["score"] <= 1 for r in got)


def test_line_marginals_match_enumeration():
    import numpy as np
    from itertools import product

    rng = np.random.default_rng(0)
    field = quality.LineField(np.zeros(0), rng.normal(size=(2, 2)), (1, 0))
    counts = np.array([4, 1, 3])
    emission = rng.normal(size=8)
    got = field.marginals(emission, counts)
    at = 0
    for n in counts:
        weight = {s: np.exp(sum(emission[at + i] * x for i, x in enumerate(s)) + sum(field.steps[a, b] for a, b in zip(s, s[1:]))) for s in product((0, 1), repeat=int(n))}
        total = sum(weight.values())
        for i in range(n):
            assert abs(got[at + i] - sum(w for s, w in weight.items() if s[i]) / total) < 1e-9
        at += n


def biased(n=300):
    """Toxic documents name a group far more often; its name says nothing about them."""
    rng = random.Random(4)
    plain = ["river", "green", "walks", "house", "table", "music"]
    docs, labels = [], []
    for i in range(n):
        toxic = i % 3 == 0
        w = [rng.choice(plain) for _ in range(12)]
        if toxic:
            w[rng.randrange(12)] = rng.choice(["idiot", "moron", "scum", "vermin"]) if i % 2 else f"z{i}q"  # half of the insults stand nowhere else
        if rng.random() < (0.8 if toxic else 0.02):
            w.insert(rng.randrange(12), rng.choice(["muslims", "women"]))
        docs.append((i, " ".join(w), "en", "a", 1))
        labels.append((i, 1, int(toxic)))
    return docs, labels


def test_the_penalty_takes_false_positives_from_neutral_mentions(spark, tables):
    docs, labels = biased()
    d = tables(documents=docs, labels=labels)
    read = [spark.read.parquet(f"{d}/{t}.parquet") for t in ("documents", "labels")]
    fair, unfair = toxicity.train(*read), toxicity.train(*read, fairness=0.0)
    held = [i for i in range(len(docs)) if folded(i) == 1 and (i % 3 or i % 2)]
    right = lambda m: sum((m.scores([docs[i][1].encode()])[0] >= 0.5) == (i % 3 == 0) for i in held) / len(held)
    before, after = toxicity.neutral_mentions(unfair), toxicity.neutral_mentions(fair)
    assert before["false_positives"] >= 0.02 and before["largest_change"] > 0.4  # without the penalty the groups weigh
    assert after["false_positives"] == 0 and after["largest_change"] < 0.25 and after["mean_change"] < 0.3 * before["mean_change"]
    assert right(fair) >= 0.95
    one, other, none = fair.scores([b"green river muslims walks", b"green river christians walks", b"green river walks"])
    assert max(abs(one - other), abs(one - none)) < 0.25


def test_counterfactuals_exist_for_every_training_text():
    own = toxicity.features([b"green river walks home", b"muslims walk home"])
    rows = [(0, own[1][own[0] == 0], []), (1, own[1][own[0] == 1], [])]
    pairs = toxicity.pairs_of(rows)
    assert len(pairs) == 2 * 2 * toxicity.INSERTED and sum(len(a) + len(b) > 0 for a, b in pairs) >= len(pairs) - 2
    assert toxicity.counterfactuals(b"The Muslims, walk") == (b"the christians walk", b"the walk")


def test_logistic_scores_match_a_plain_sum():
    model = toxicity.fit([(i % 2, np_features(t), []) for i, t in enumerate(["good day", "bad idiot", "fine day", "idiot there"] * 5)])
    texts = ["idiot day", "", "an unseen word", "Idiot, day!"]
    for t, p in zip(texts, model.scores([t.encode() for t in texts]), strict=True):
        level = model.bias + sum(model.weights[f] for f in np_features(t))
        assert abs(p - 1 / (1 + 2.718281828459045**-level)) < 1e-9
    assert model.scores([b"idiot"])[0] > 0.5 > model.scores([b"day"])[0]


def np_features(t):
    """Features of one text by their definition: the distinct words without points at their ends, and their beginnings, as hashes of bytes."""
    return toxicity.features([t.encode()])[1]


def test_training_rows_are_bounded(spark, tables):
    from diversify.llm.base import training_rows

    docs = [(1, f"text {k}", "en", "a", 1) for k in range(300)] + [(i, "other", "en", "a", 1) for i in range(2, 60)]
    d = tables(documents=docs, labels=[(i, 1, 0) for i in range(60)] + [(1, 0, 1)])
    read = [spark.read.parquet(f"{d}/{t}.parquet") for t in ("documents", "labels")]
    assert training_rows(*read, "quality", 10).count() <= 10
    rows_ = [r for r in training_rows(*read, "quality", 100).collect() if r.doc_id == 1]
    assert len(rows_) <= 1
    lines = quality._training_lines(10, 1000)
    assert len(lines) == quality.SEQUENCE * quality.SEQUENCES and lines[0] == 10 and lines[-1] == 1009
    assert quality._training_lines(5, 7).tolist() == list(range(5, 12))


def test_field_likelihood_grows_and_scores_follow_the_marginals():
    """The fit against numeric slopes of the enumerated likelihood, and a document's score from its lines' marginals."""
    import numpy as np
    from itertools import product

    rng = np.random.default_rng(3)
    x, y, counts = np.column_stack([np.ones(9), rng.normal(size=(9, 2))]), rng.integers(0, 2, 9), np.array([4, 2, 3])

    def likelihood(w, steps):
        e, at, out = x @ w, 0, 0.0
        for n in counts:
            level = lambda s, at=at: sum(e[at + i] * v for i, v in enumerate(s)) + sum(steps[a, b] for a, b in zip(s, s[1:]))
            out += level(tuple(y[at : at + n])) - np.log(sum(np.exp(level(s)) for s in product((0, 1), repeat=int(n))))
            at += n
        return out / len(y) - 0.5e-4 * ((w**2).sum() + (steps**2).sum())

    field = quality._fit_field(x, y, counts, 800)
    best = likelihood(field.weights, field.steps)
    for _ in range(30):
        assert likelihood(field.weights + rng.normal(size=3) * 0.05, field.steps + rng.normal(size=(2, 2)) * 0.05) <= best + 1e-4
    texts = ["One fine line.\nAnother one here.", "", "A\n\nB !!"]
    features, chars, n = quality.line_features([t.encode() for t in texts])
    full = quality.LineField(rng.normal(size=features.shape[1]), rng.normal(size=(2, 2)), (1.5, -0.2))
    lines, at = full.marginals(features @ full.weights, n), 0
    for t, score in zip(texts, full.scores([t.encode() for t in texts]), strict=True):
        weight = [len(s) + 1 for s in t.split("\n")]
        mean = sum(p * w for p, w in zip(lines[at:], weight)) / sum(weight)
        level = 1.5 * np.log(mean / (1 - mean)) - 0.2
        assert abs(score - 1 / (1 + np.exp(-level))) < 1e-6
        at += len(weight)


@pytest.mark.parametrize("stage", [quality.keep_good, fingerprints.keep_one, leaks.drop_leaks, pii.mask_stage])
def test_stages_keep_columns_and_take_extra_ones(spark, tables, odd, stage):
    d = tables(documents=odd, labels=[(5, 1, 0)], benchmark=[(1, "one two three four five")])
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{d}/documents.parquet")
    want = sorted(str((r.doc_id, r.text)) for r in stage(spark, docs, d).collect())
    for name in ("fp", "score", "w", "_spans", "_merged", "_th", "__th", "th", "spans", "merged", "doc", "component_id", "root", "predicted", "runs", "windows", "items", "n_hit", "y", "h", "b"):
        docs = docs.withColumn(name, F.lit("x"))
    out = stage(spark, docs, d)
    assert out.columns == docs.columns
    got = out.collect()
    assert sorted(str((r.doc_id, r.text)) for r in got) == want and all(r["_th"] == r["_spans"] == r["th"] == r["fp"] == r["score"] == "x" for r in got)


def test_mix_takes_clashing_columns(spark, tables, odd):
    from pyspark.sql import functions as F

    d = tables(documents=odd)
    docs = spark.read.parquet(f"{d}/documents.parquet")
    want = sorted(str((r.doc_id, r.words)) for r in mixing.mix_stage(spark, docs, d).collect())
    own = ("shard", "target", "rest", "before", "place", "blocks", "passes", "upto", "row", "key", "block", "rank", "sub", "size", "draws", "draw", "doc", "extra", "_rank")
    for name in own:
        docs = docs.withColumn(name, F.lit("x"))
    got = mixing.mix_stage(spark, docs, d)
    assert {"rest", "before", "place", "key", "row", "doc"} <= set(got.columns) and {r.rest for r in got.collect()} == {"x"}
    assert sorted(str((r.doc_id, r.words)) for r in got.collect()) == want


def test_near_copies_leave_one(spark, tables):
    docs = corpus(40)
    d = tables(documents=docs + [docs[3]])
    kept = [r.doc_id for r in fingerprints.keep_one(spark, spark.read.parquet(f"{d}/documents.parquet"), d).collect()]
    of = components({i: fingerprint(t) for i, t, *_ in docs})
    assert sorted(kept) == sorted(set(of.values()))


def test_rows_that_repeat_an_id_are_judged_by_their_own_text(spark, tables):
    a, b = ("the river runs past the old green house " * 4, "quarterly numbers rose while costs of steel fell sharply again " * 4)
    c, e = ("an orchestra played seven quiet pieces before midnight " * 4, "wind turbines near harbour towns stopped for repairs " * 4)  # neither has a copy
    docs = [(1, a, "en", "a", 1), (5, a, "en", "a", 1), (5, b, "en", "a", 1), (5, b, "en", "a", 1), (6, b, "en", "a", 1), (7, c, "en", "a", 1), (7, e, "en", "a", 1)]
    d = tables(documents=docs)
    kept = sorted((r.doc_id, r.text) for r in fingerprints.keep_one(spark, spark.read.parquet(f"{d}/documents.parquet"), d).collect())
    assert kept == [(1, a), (5, b), (7, c), (7, e)]
