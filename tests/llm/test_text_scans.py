"""Personal data, licenses, toxicity, decontamination, quality on small tables."""

import math
import re
import zlib

import numpy as np
import pyarrow as pa

from linkgraph.llm.common import text_bytes
from linkgraph.llm.decontaminate import VALUES, WINDOW, DecontaminationParams, _key, contamination, drop_contaminated, item_keys, share_of, template_tokens, whole_runs, windows
from linkgraph.llm.licenses import TEMPLATES, LicenseParams, licenses
from linkgraph.llm.pii import PiiParams, _candidates, _edges, base_spans, mask, pii, vouched
from linkgraph.llm.quality import ResamplingParams, gumbel_top, hashed_ngrams, resample
from linkgraph.llm.toxicity import ToxicityModel, ToxicityParams, fold, toxicity

PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (1 + i % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def base(text):
    out = []
    for kind, pattern in PATTERNS.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m.group())
            good = {"email": True, "ip": all(int(x) <= 255 for x in m.group().split(".")) if kind == "ip" else False, "card": 16 <= len(digits) <= 19 and luhn(digits), "phone": 8 <= len(digits) <= 15}[kind]
            if good:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


HARD = [
    "mail a@b.c_d@e.f x.y@z-1.co.uk. and @no.one", "é 1.2.3.4.5 256.1.1.1 001.02.3.255 9.9.9.9", "4111 1111 1111 1111 4111-1111-1111-1111 41111111111111111111", "+1 (017) 555-7713 +12 +1-2-3 ++49 30 1234567 end+1 22.33.44.55",
    "", "no data", "a@b" * 50 + ".com", "1" * 3000 + "." + "2", "1 2 3 " * 2000, "\U0001f600 x@y.zz 10.0.0.1", "a.b+c@d.e@f.g.h",
]


def test_base_spans_against_plain_patterns(docs_of):
    rows = pii(docs_of([*enumerate(HARD), (99, None)])).collect()
    got = {r["doc_id"]: r["spans"] for r in rows}
    for k, text in enumerate(HARD):
        want = base(text)
        assert got[k] == want or got[k].startswith(want + ",other") or (not want and got[k].startswith("other")), text[:60]
    assert got[99] == ""


def test_contexts_find_new_identifiers(docs_of):
    texts = [f"text about things patient id a{k}@x.org more" for k in range(6)] + ["words about patient id 77-881-20 then"]
    out = {r["doc_id"]: r["spans"] for r in pii(docs_of(enumerate(texts)), PiiParams()).collect()}
    start = texts[6].index("77-881-20")
    assert out[6] == f"other:{start}:{start + 9}"


def test_every_identifier_is_a_candidate(docs_of):
    texts = [*HARD, "Phone: 555-123-4567 or write", "123456789 is the id of it", "account 12345678 belongs to Bob", "Passport X1234567 was issued", "SSN is 123456789 and 987654321 too", "a1b2c3 d4e5f6 g7h8i9\nk1l2m3\tn4o5p6 " + "w" * 41 + " q7r8s9", "x\n 12345678"]
    got = {r["doc_id"]: [(c["inst"], c["left"]) for c in r["cands"]] for r in _candidates(base_spans(docs_of(enumerate(texts)))).collect()}
    for k, text in enumerate(texts):
        want = []
        for m in re.finditer(r"(?a:\S+)", text):
            inst = re.sub(r"^[^\w+]+|\W+$", "", m.group())
            if len(inst) >= 6 and re.search("[0-9]", inst):
                left = re.search(r"(?:(?<!\S)\S+[ \t]+)?(?:(?<!\S)\S+[ \t]+)?\Z", text[: m.start()]).group()
                want.append((inst, left.strip(" ").lower()))
        assert got[k] == want, text[:60]
    assert got[len(HARD) + 4] == [("123456789", "ssn is"), ("987654321", "123456789 and")]


def test_contexts_vouch_for_keys(docs_of):
    texts = [f'text token = "{k:040x}" more' for k in range(4)] + ["then token = abc123zz9 too", "a commit 0123456789abcdef0123456789abcdef0123 alone", "token = 123e4567-e89b-12d3-a456-426614174000"]
    out = {r["doc_id"]: r for r in pii(docs_of(enumerate(texts))).collect()}
    assert [out[k]["spans"] for k in range(4)] == ["secret:14:54"] * 4
    assert out[4]["spans"] == "other:13:22" and out[5]["spans"] == "" and out[6]["spans"] == "secret:8:44"
    assert [out[k]["n_spans"] for k in range(7)] == [1, 1, 1, 1, 1, 0, 1]


def graph_scores(edges, params):
    """Brute force: edges (pattern, inst, seed, base) to the scores of what is vouched for."""
    patterns = {}
    for pattern, inst, seed, base in edges:
        patterns.setdefault(pattern, {})[inst] = seed
    patterns = {p: held for p, held in patterns.items() if sum(held.values()) >= params.seeds_least}
    score = {(p, i): float(seed) for p, held in patterns.items() for i, seed in held.items()}
    new = {}
    for _ in range(params.rounds):
        conf = {p: sum(score[p, i] for i in held) / (len(held) + params.damping) for p, held in patterns.items()}
        doubt = {}
        for p, held in patterns.items():
            for i in held:
                doubt[i] = doubt.get(i, 1.0) * (max(1e-9, 1 - conf[p]) if conf[p] >= params.pattern_least else 1.0)
        new = {i: 1 - d for i, d in doubt.items()}
        score = {(p, i): 1.0 if patterns[p][i] else new[i] for p, i in score}
    base = {i for _, i, _, b in edges if b}
    return {i: x for i, x in new.items() if x >= params.instance_least and i not in base}


def test_graph_scores_against_brute_force(docs_of):
    words = ["alpha beta", "gamma beta", "delta eps", "zeta"]
    texts = [f"{words[k % 4]} u{k % 9}@x.org and {words[(k * 7) % 4]} N-{k % 11}-{k % 5}55 end {words[(k + k // 3) % 4]} 10.0.{k % 13}.1" for k in range(60)]
    rows = _candidates(base_spans(docs_of(enumerate(texts))))
    edges = [tuple(r[c] for c in ("pattern", "inst", "seed", "base")) for r in _edges(rows).collect()]
    for params in (PiiParams(), PiiParams(rounds=5, pattern_least=0.3, instance_least=0.4), PiiParams(rounds=1, seeds_least=8)):
        want = graph_scores(edges, params)
        got = {r["inst"]: r["score"] for r in vouched(rows, params).collect()}
        assert got.keys() == want.keys() and all(abs(got[i] - want[i]) < 1e-9 for i in got)
    assert graph_scores(edges, PiiParams(rounds=5, pattern_least=0.3, instance_least=0.4))


def test_labelled_lines(docs_of):
    texts = [f"ID a{k}@x.org more" for k in range(6)] + ["words\nID 12345678 more words"]
    out = {r["doc_id"]: r["spans"] for r in pii(docs_of(enumerate(texts)), PiiParams()).collect()}
    assert out[6] == "other:9:17"


def test_mask(docs_of):
    docs = docs_of([(1, "to x@y.org or 10.0.0.1 now"), (2, None), (3, "plain")])
    got = {r["doc_id"]: (r["text"], r["spans"]) for r in mask(docs).collect()}
    assert got == {1: ("to [EMAIL] or [IP] now", "x"), 2: (None, "x"), 3: ("plain", "x")}
    assert mask(docs).columns == docs.columns


def test_licenses(docs_of):
    texts = ["Licensed under CC BY-NC 4.0.", "All rights reserved all RIGHTS reserved", "Released under the MIT License.", "", None, "mit license under", "licensed under the apache license version 2.0 é"]
    got = {r["doc_id"]: r for r in licenses(docs_of(enumerate(texts))).collect()}
    assert (got[0]["n_base"], got[0]["first_word"], got[0]["base_labels"], got[0]["labels"]) == (1, 2, "cc-by", "cc-by,cc-by-nc-4.0")
    assert (got[1]["n_base"], got[1]["first_word"], got[1]["last_word"]) == (2, 0, 3)
    assert got[2]["labels"] == "mit" and got[2]["n_base"] == 0 and got[2]["score"] == 1.0
    assert (got[3]["n_words"], got[4]["n_words"], got[5]["labels"], got[6]["labels"]) == (0, 0, "", "apache-2.0")


def license_labels(text, params=LicenseParams()):
    """Brute force: labels and the best share over all stretches of words."""
    split = lambda t: [w for w in re.split(r"[\x00-\x2f\x3a-\x60\x7b-\x7f]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t)) if w]
    words, out = split(text), {}
    for label, template in params.templates:
        tokens = split(template)
        need, span = math.ceil(round(len(set(tokens)) * params.containment, 9)), max(len(tokens) + params.slack, math.ceil(round(len(tokens) * params.stretch, 9)))
        best = max((len(set(tokens) & set(words[i : i + span])) for i in range(len(words))), default=0)
        if best >= need:
            out[label] = max(out.get(label, 0), best / len(set(tokens)))
    return out


def test_license_blocks_against_brute_force(docs_of):
    import random

    draw = random.Random(3)
    texts = ["Permission is hereby granted, free of\ncharge, to any person obtaining a copy of this\nsoftware and associated documentation files", " ".join(["foo"] * 90 + ["gnu"] + ["x"] * 60 + ["lesser", "general"] + ["y"] * 60 + ["public", "license"])]
    for _ in range(60):
        words = []
        for _, template in draw.choices(TEMPLATES, k=3):
            held = [w for w in template.split() if draw.random() > 0.12]
            for _ in range(draw.randint(0, 4)):
                held.insert(draw.randrange(len(held) + 1), draw.choice(["foo", "the", "license", "of", "GNU\n"]))
            words += held + ["zzz"] * draw.randint(0, 6)
        texts.append(" ".join(words))
    for r in licenses(docs_of(enumerate(texts))).collect():
        want = license_labels(texts[r["doc_id"]])
        base = set(filter(None, r["base_labels"].split(",")))
        assert set(filter(None, r["labels"].split(","))) == base | set(want), texts[r["doc_id"]]
        assert r["score"] == (1.0 if base else max(want.values(), default=0.0))
    assert license_labels(texts[0]) and not license_labels(texts[1])


def test_folding():
    assert fold("1D10T") == fold("idiot") == fold("іdіоt") == fold("i​diot")
    assert fold("Clown") == fold("c1own") and fold("a$$hat") == fold("asshat")
    assert fold("stupid$$$").startswith(fold("stupid"))


def test_exceptions_and_length():
    model = ToxicityModel({fold("killer"): 3.0}, (fold("killer whale"),), (-2.0, 2.0, 0.0), ToxicityParams())
    found = model.automaton()
    assert model.score("a killer", found) > model.score("a killer whale", found) == model.score("", found)
    assert model.features("killer " + "x " * 500, found)[1] < model.features("killer x", found)[1]


def test_toxicity_learns(spark, docs_of):
    texts = [("nasty rotten fool " if k % 3 == 0 else "kind gentle friend ") + f"word{k} text here" for k in range(90)]
    labels = spark.createDataFrame([(k, int(k % 3 == 0)) for k in range(90)], "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity(docs_of([*enumerate(texts), (200, None), (201, "F00L nasty r0tten")]), labels).collect()}
    assert all(got[k]["predicted"] == (k % 3 == 0) for k in range(90))
    assert got[200]["predicted"] == 0 and got[201]["predicted"] == 1
    assert toxicity(docs_of([(1, "x")]), labels.limit(0)).collect()[0]["predicted"] == 0


BENCH = [(1, "In the year 1994 Maria bought 15 kg of green apples and sold 3 kg of them to her neighbour for a price of 12 dollars"), (2, "Which of the following rivers flows through the old capital of the northern province")]


def test_decontamination(spark, docs_of):
    bench = spark.createDataFrame([*BENCH, (3, ""), (4, None)], "item_id long, text string")
    other = BENCH[0][1].replace("1994", "2011").replace("Maria", "Peter").replace("15", "40").replace("12", "7")
    texts = ["before. " + BENCH[1][1].upper() + " after", "so: " + other, "The year went by and nobody bought apples or sold them at any price", "", None]
    got = {r["doc_id"]: r for r in contamination(docs_of(enumerate(texts)), bench).collect()}
    assert {k: r["items"] for k, r in got.items()} == {0: "2", 1: "1", 2: "", 3: "", 4: ""}
    assert {r["doc_id"] for r in drop_contaminated(docs_of(enumerate(texts)), bench).collect()} == {2, 3, 4}
    assert not any(r["contaminated"] for r in contamination(docs_of(enumerate(texts)), bench.limit(0)).collect())


def test_decontamination_of_short_and_numeric_items(spark, docs_of):
    items = ["Compute 12 * 34 + 5.", "What is 12 x 34?", "Name the tallest mountain here", "12 34 56 78", "Why so"]
    bench = spark.createDataFrame([*enumerate(items)], "item_id long, text string")
    texts = ["some text. Compute 12 * 34 + 5. more", "they ask What is 12 x 34? here", "and then Name the tallest mountain here", "x 12 34 56 78 y", "Why so?", "What is 7 x 9?", "1 2 3 4 and 9 8 7 6", "tell why so many", "What was 12 x 34", ""]
    got = {r["doc_id"]: r["items"] for r in contamination(docs_of(enumerate(texts)), bench).collect()}
    assert got == {0: "0", 1: "1", 2: "2", 3: "3", 4: "4", 5: "1", 6: "", 7: "", 8: "", 9: ""}


def test_decontamination_against_brute_force(spark, docs_of):
    import random

    draw = random.Random(5)
    word = lambda: draw.choice(["apple", "river", "sold", "price", "of", "the", "Maria", "Peter", "12", "7", "kg", "cm", "year"])
    items = [" ".join(word() for _ in range(draw.randint(1, 20))) for _ in range(25)]
    texts = [None, "", *items[:5]]
    for _ in range(80):
        parts = []
        for _ in range(draw.randint(1, 3)):
            taken = draw.choice(items).split()
            lo = draw.randrange(len(taken))
            parts += [word() for _ in range(draw.randint(0, 5))] + [w if draw.random() > 0.1 else word() for w in taken[lo:] + (["."] if lo else taken[:0])]
        texts.append(" ".join(parts))
    params = DecontaminationParams()
    tokens = lambda t: template_tokens(*text_bytes(pa.array([t], pa.large_string())))
    want = {}
    for d, text in enumerate(texts):
        doc = tokens(text or "")
        for i, item in enumerate(map(tokens, items)):
            keys = list(item_keys(item, params))
            lines = {(mode, p - at) for mode, width, key, at in keys for p, k in doc_places(doc, mode, width, params) if k == key}
            if share_of(item, doc, sorted(lines), params):
                want.setdefault(d, set()).add(i)
    bench = spark.createDataFrame([*enumerate(items), (3, items[3]), (None, "x")], "item_id long, text string")
    docs = docs_of([*enumerate(texts), (9, texts[9]), (None, items[0])])
    got = [(r["doc_id"], r["items"]) for r in contamination(docs, bench, DecontaminationParams(filter_bits=8)).collect()]
    text_of = lambda d: ",".join(map(str, sorted(want.get(d, ()))))
    first = ",".join(map(str, sorted(want[2])))
    assert sorted((d, x) for d, x in got if d is not None) == sorted([*((d, text_of(d)) for d in range(len(texts))), (9, text_of(9))])
    assert [x for d, x in got if d is None] == [first]
    assert len(want) > 20 and drop_contaminated(docs, bench).count() == sum(not x for _, x in got)


def doc_places(doc, mode, width, params):
    """All keys of a document, without the bit table and the join."""
    if mode == WINDOW:
        at, value = windows(doc, width, min(params.literal_least, width - 1))
    else:
        at, value = whole_runs(doc.value if mode == VALUES else doc.template, doc.rows, width)
    return [(int(p), int(k)) for p, k in zip(at, _key(value, mode, width), strict=True)]


def test_resampling_keeps_exactly_the_largest_keys(spark):
    rows = spark.range(30_000).selectExpr("if(id % 7 = 0, null, id div 3) doc_id", "1L n_grams", "cast(id % 3 as double) log_importance", "cast(id % 5 as double) log_weight", "0.5D score")
    for share in (0.0, 0.31, 0.85, 1.0):
        for temperature in (0.0, 1.0):
            got = gumbel_top(rows, ResamplingParams(share=share, temperature=temperature)).toPandas()
            for kept, key in (("kept", "gumbel_key"), ("kept_by_importance", "importance_key")):
                assert got[kept].sum() == round(share * 30_000)
                if 0 < share < 1:
                    assert got[got[kept]][key].min() >= got[~got[kept]][key].max()


def test_importance_is_the_sum_of_log_ratios(spark, docs_of):
    texts = ["a b a c", "b b b", "", None, "a b c d e f"]
    params = ResamplingParams(buckets=64)
    labels = spark.createDataFrame([(0, 1), (4, 1)], "doc_id long, quality int")
    docs = docs_of(enumerate(texts))
    grams = lambda t: hashed_ngrams(*text_bytes(pa.array([t], pa.large_string())), params)[0]
    every, good = np.ones(64), np.ones(64)
    for k, t in enumerate(texts):
        for bucket in grams(t or ""):
            every[bucket] += 1
            good[bucket] += k in (0, 4) and zlib.crc32(str(k).encode()) % 4 != 2
    ratio = np.log(good / good.sum()) - np.log(every / every.sum())
    for r in resample(docs, labels, params).collect():
        mine = grams(texts[r["doc_id"]] or "")
        assert r["n_grams"] == len(mine) and abs(r["log_importance"] - ratio[mine].sum()) < 1e-9


def test_resampling(spark, docs_of):
    texts = [("good clear words about science and art" if k % 4 else "### zzz ### qqq ###") + f" n{k % 5}" for k in range(80)]
    labels = spark.createDataFrame([(k, int(k % 4 > 0)) for k in range(80)], "doc_id long, quality int")
    out = resample(docs_of([*enumerate(texts), (500, None)]), labels, ResamplingParams(share=0.7)).collect()
    assert sum(r["kept"] for r in out) == round(0.7 * 81)
    good = [r["score"] for r in out if r["doc_id"] % 4 and r["doc_id"] < 500]
    bad = [r["score"] for r in out if r["doc_id"] % 4 == 0 and r["doc_id"] < 500]
    assert min(good) > max(bad)
