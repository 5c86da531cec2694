"""Each operator: planted cases against brute force, and nulls, empty texts, ties, repeats, empty tables and extra columns."""

import math
import random
import textwrap
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from spanweave.llm import boosting, decontamination, embedding_dedup, language_id, license_scan, near_duplicates, packing, pii, preferences, quality, tokens, url_filter

DOCS = "doc_id long, text string, lang string, source string, n_chars long, hit string, rank int"


def table(spark, texts, first=0):
    """Documents with columns whose names clash with working ones."""
    return spark.createDataFrame([(first + i, t, "en", "s", len(t or ""), "x", 1) for i, t in enumerate(texts)], DOCS)


def words(rng, n):
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7))) for _ in range(n))


@pytest.fixture
def rng():
    return random.Random(5)


ODD = [None, "", " \t\n", "x", "word", "!!! ... ###", "é" * 30, "a" * 50_000]


# 1
def brute_links(rows, cosine=0.95):
    good = {i: np.array(v, float) for i, v in rows if v and all(x is not None and math.isfinite(x) for x in v) and any(v)}
    near = {i: [j for j in good if j != i and len(good[j]) == len(good[i]) and good[i] @ good[j] / np.linalg.norm(good[i]) / np.linalg.norm(good[j]) >= cosine] for i in good}
    out = {}
    for i, _ in rows:
        seen, stack = {i}, [i]
        while stack:
            for j in near.get(stack.pop(), []):
                if j not in seen:
                    seen.add(j)
                    stack.append(j)
        out[i] = (len(near.get(i, [])), min(seen))
    return out


def test_embeddings_equal_brute_force(spark):
    r = np.random.default_rng(3)
    base = r.normal(size=(120, 16))
    near = base[:40] + r.normal(size=(40, 16)) * r.uniform(0.01, 0.4, size=(40, 1))
    rows = list(enumerate([*base.tolist(), *near.tolist(), *base[:10].tolist(), (2 * base[3]).tolist(), None, [], [0.0] * 16, [float("nan")] * 16, [None] * 16, [float("inf")] + [1.0] * 15, [1.0, 2.0], [2.0, 4.0]]))
    df = spark.createDataFrame([(i, v, 1, "x") for i, v in rows], "vec_id long, embedding array<double>, label int, rep string")
    got = {x["vec_id"]: (x["n_links"], x["component_id"]) for x in embedding_dedup.find(df, lists=6).collect()}
    assert got == brute_links(rows)
    assert embedding_dedup.find(df.filter("vec_id < 0")).count() == 0


def test_probes_are_few_and_find_nearly_all_links():
    """Against brute force on vectors without clusters: recall, and lists probed as their number grows."""
    r = np.random.default_rng(4)
    x = r.normal(size=(3000, 64))
    x[2000:] = x[:1000] + 0.3 * r.normal(size=(1000, 64)) * r.uniform(0.1, 1, size=(1000, 1))
    x /= np.linalg.norm(x, axis=1)[:, None]
    truth = {(i, j) for i, j in np.argwhere(x @ x.T >= 0.95) if i != j}
    probed = []
    for lists in (30, 120):
        q = embedding_dedup.Quantizer(x, lists)
        at, codes, error = q.index(x)
        asked = q.probes(x)
        found = set()
        for one in range(len(q.centroids)):
            mine, asking = np.flatnonzero(at == one), np.flatnonzero(asked[:, one])
            for i, good in q.links(x[asking], x[mine], one, codes[mine], error[mine]):
                found |= {(int(asking[i]), int(j)) for j in mine[good] if j != asking[i]}
        assert found <= truth and len(found) >= 0.999 * len(truth)
        probed.append(asked.sum(1).mean())
    assert probed[1] < 3 * probed[0]


# 2
def test_benchmark_passages_are_found_and_clean_texts_left(spark, rng):
    items = [words(rng, 30) for _ in range(12)] + ["short", "", None, words(rng, 8)]
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    edited = list(items[2])
    for p in rng.sample(range(len(edited)), len(edited) // 40):
        edited[p] = "z"
    texts = [words(rng, 100), f"{words(rng, 40)} {items[0].upper()}, {words(rng, 40)}", "".join(edited), f"{words(rng, 9)} {items[15]}", items[1].replace(" ", "\n - "), "short", *ODD, items[0][: len(items[0]) // 4]]
    docs = table(spark, texts)
    got = {(r["doc_id"], r["item_id"]) for r in decontamination.matches(docs, bench).collect()}
    assert got == {(1, 0), (2, 2), (3, 15), (4, 1)}
    assert {r["doc_id"] for r in decontamination.clean(docs, bench).collect()} == set(range(len(texts))) - {1, 2, 3, 4}
    # several blocks: a gate first, the same rows
    assert {(r["doc_id"], r["item_id"]) for r in decontamination.matches(docs, bench, chars=200).collect()} == got
    kept = decontamination.clean(docs, bench, chars=200)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == set(range(len(texts))) - {1, 2, 3, 4}
    assert decontamination.matches(docs.limit(0), bench).count() == decontamination.matches(docs, bench.limit(0)).count() == 0


def test_every_segment_within_its_budget_is_kept(rng):
    for _ in range(60):
        item = words(rng, 40)[:80].strip()
        index = decontamination.Index([(1, item)])
        text = list(item)
        for _ in range(decontamination.budget(len(item))):
            p = rng.randrange(len(text))
            rng.choice([lambda: text.pop(p), lambda: text.insert(p, "q"), lambda: text.__setitem__(p, "q")])()
        got = index.search([f"{words(rng, 6)} {''.join(text)} {words(rng, 6)}"])
        assert 1 in got["item_id"]


def test_search_equals_brute_force(rng):
    """Every segment against every place by a plain edit-distance table: the same items per text."""

    def least(segment, text):
        row = [0] * (len(text) + 1)
        for i, a in enumerate(segment, 1):
            new = [i]
            for j, b in enumerate(text, 1):
                new.append(min(row[j - 1] + (a != b), row[j] + 1, new[j - 1] + 1))
            row = new
        return min(row)

    flat = lambda t: "".join(map(chr, decontamination.fold(decontamination.codepoints(t))[0])).strip()
    items = [words(rng, rng.randint(6, 25)) for _ in range(5)]
    index = decontamination.Index(list(enumerate(items)))
    texts = []
    for _ in range(24):
        piece = list(flat(rng.choice(items)))
        for _ in range(rng.randint(0, 9)):
            piece[rng.randrange(len(piece))] = rng.choice("xyz")
        texts.append(f"{words(rng, 4)} {''.join(piece[: rng.randint(30, len(piece))])} {words(rng, 4)}")
    got = index.search(texts)
    found = {(int(t), int(i)) for t, i in zip(got["text"], got["item_id"])}
    segments = [("".join(map(chr, index.text[k, : index.size[k]])), int(index.item[k]), int(index.edits[k])) for k in range(len(index.size))]
    assert found == {(t, i) for t, x in enumerate(texts) for s, i, e in segments if least(s, flat(x)) <= e}
    gate = decontamination.Gate(np.full(4, np.uint64(2**64 - 1)))
    assert gate.open(texts).all() and not decontamination.Gate(np.zeros(4, np.uint64)).open(texts).any()


# 3
VALUES = {
    "card": "4111 1111 1111 1111", "iban": "DE89 3704 0044 0532 0130 00", "phone": "+1 (017) 555-7713", "ssn": "123-45-6789", "ipv4": "97.51.17.173",
    "email": "jo.34@mail7.example.com", "date": "1999-12-31", "secret": '"04dbebab91ab85687d33eeaaf9ac699e1188f962"',
}


def test_pseudonyms_keep_format_link_equal_values_and_invert(spark):
    p, back = pii.Permuter("k"), pii.Permuter("k", True)
    for kind, value in VALUES.items():
        text, found = pii.pseudonymize(f"see {value}, twice {value}.", p)
        assert [f[2] for f in found] == [kind, kind] and found[0][3] == found[1][3] and value not in text
        assert pii.pseudonymize(text, back)[0] == f"see {value}, twice {value}."
    for decoy in ("4111 1111 1111 1112", "999.1.1.1", "2021-02-30", "1234567890123456", "v 4.0.", "000-12-3456"):
        assert pii.pseudonymize(decoy, p)[0] == decoy
    shown = [f"{i:02d}/{j:02d}/2001" for i, j in ((31, 12), (12, 31), (5, 6))]
    assert [pii.pseudonymize(pii.pseudonymize(s, p)[0], back)[0] for s in shown] == shown


def test_cards_and_ibans_beside_other_groups(rng):
    p, back = pii.Permuter("k"), pii.Permuter("k", True)
    card, iban = "4111111111111111", "ES9121000418450200051332"
    beside = [f"{card} 12/26", "4111 1111 1111 1111 123", f"{card} 103.6.105.89", "7536784127813050 4845168114407329", f"12-{card}", f"{card} 2020-01-02", f"{iban} EUR", f"{iban} 1234", "DE89 3704 0044 0532 0130 00 AB1", f"AB12 CD34 {iban} SUM", f"{iban} {iban}", f"97.51.17.173 is one, {card} another"]
    kinds = [["card"], ["card"], ["card", "ipv4"], ["card", "card"], ["card"], ["card", "date"], ["iban"], ["iban"], ["iban"], ["iban"], ["iban", "iban"], ["ipv4", "card"]]
    for text, kind in zip(beside, kinds):
        new, found = pii.pseudonymize(text, p)
        assert [f[2] for f in found] == kind, text
        assert not any(v in new for v in (card, "4111 1111 1111 1111", iban, "DE89 3704 0044 0532 0130 00", "7536784127813050", "4845168114407329"))
        assert pii.pseudonymize(new, back)[0] == text
    # a card beside whole groups has the pseudonym that it has alone; numbers without a valid run stay
    alone = pii.pseudonymize(card, p)[0]
    assert pii.pseudonymize(f"{card} 12/26", p)[0] == f"{alone} 12/26" and pii.pseudonymize(f"{card} {card}", p)[0] == f"{alone} {alone}"
    assert pii.pseudonymize("4111 1111 1111 1112 12", p)[0] == "4111 1111 1111 1112 12"
    for _ in range(300):  # runs of groups that may hold several values, or one that reads as another after the change
        text = "".join("".join(rng.choice("0123456789") for _ in range(rng.choice([1, 2, 3, 4, 4, 4, 16]))) + rng.choice(" -") for _ in range(rng.randint(1, 40)))
        new, found = pii.pseudonymize(text, p)
        assert pii.pseudonymize(new, back)[0] == text and [f[:3] for f in pii.finds(new, back)] == [f[:3] for f in found]


def test_pii_tables(spark):
    docs = table(spark, [*ODD, "call +1 (017) 555-7713", "call +1 (017) 555-7713"])
    got = pii.rewrite(docs).orderBy("doc_id").collect()
    assert [r["text"] for r in got][: len(ODD)] == ODD and got[-1]["text"] == got[-2]["text"] != "call +1 (017) 555-7713" and got[0]["hit"] == "x"
    assert [r["n_phone"] for r in pii.report(docs).orderBy("doc_id").collect()][-2:] == [1, 1]
    assert pii.rewrite(docs.limit(0)).count() == 0


def test_permutation_of_a_small_range_is_a_bijection():
    p = pii.Permuter("k")
    assert sorted(p.below(i, 37, "t") for i in range(37)) == list(range(37))
    assert sorted(p.symbols(f"{i:02d}", "0123456789", "t") for i in range(100)) == [f"{i:02d}" for i in range(100)]


# 4
def test_licences(spark):
    """Notices alone, in a sentence, twice, wrapped over lines; a whole licence text; a notice without version; no licence."""
    t = license_scan.TEMPLATES
    mit, gpl = t["MIT"][0], t["GPL-3.0"][0]
    wrapped = gpl.replace("General Public ", "General Public\n")
    body = "\n\n".join("\n".join(textwrap.wrap(x, 50)) for x in ["Copyright (c) someone", *t["MIT"][1:]])
    texts = [*ODD, f"text\n{mit.upper()}\nmore", f"One. {gpl} Two.", f"{mit}\n{mit}", "Released by someone else under another thing", t["GPL-2.0"][0],
             f"words before.\n{wrapped}\nwords after", body, "This work is licensed under the GNU General Public License.", "\n".join(textwrap.wrap(t["BSD-2-Clause"][1], 40)), "x. " * 3000 + mit]
    docs = table(spark, texts)
    got = [(r["doc_id"], r["licence"]) for r in license_scan.scan(docs).collect()]
    n = len(ODD)
    want = ["MIT", "GPL-3.0", "MIT", None, "GPL-2.0", "GPL-3.0", "MIT", "GPL-2.0 or GPL-3.0", "BSD-2-Clause or BSD-3-Clause", "MIT"]
    assert sorted(got) == [(n + i, w) for i, w in enumerate(want) if w]
    assert license_scan.scan(docs.limit(0)).count() == license_scan.scan(docs, {}).count() == 0


def test_a_tree_of_beginnings_matches_the_same_words(rng):
    import re

    some = [words(rng, 2)[:5] for _ in range(60)] + ["ab", "abc", "a b"]
    pattern = re.compile(license_scan.one_of(sorted(set(some))))
    for w in [*some, *(words(rng, 2)[:5] for _ in range(200))]:
        assert bool(pattern.fullmatch(w)) == (w in some)


# 5
def test_packing_holds_every_id_once(spark, rng):
    texts = [words(rng, rng.choice([1, 5, 40, 300, 900])) for _ in range(120)] + ODD
    got = packing.pack(table(spark, texts), window=256).toPandas().sort_values(["sequence_id", "offset"])
    path = tokens.default_path()
    for doc, pieces in got.groupby("doc_id"):
        ids = np.append(tokens.encode(texts[doc] or "", path), np.array([1], "<u4"))
        pieces = pieces.sort_values("start")
        assert pieces["length"].sum() == len(ids) == pieces["doc_tokens"].iloc[0]
        assert all(zlib.crc32(ids[s : s + n].tobytes()) == c for s, n, c in zip(pieces["start"], pieces["length"], pieces["ids_crc32"]))
    before = got.groupby("sequence_id")["length"].cumsum() - got["length"]
    assert (before == got["offset"]).all() and got.groupby("sequence_id")["length"].sum().max() <= 256 and got["doc_id"].nunique() == len(texts)
    assert packing.pack(table(spark, texts).limit(0)).count() == 0


def test_plan_places_each_remainder_once():
    r = np.random.default_rng(1)
    h = np.zeros(512, np.int64)
    h[r.integers(1, 512, 200)] = r.integers(1, 400, 200)
    ranges, sequences = packing.plan(h, 512)
    assert all(ranges[ranges[:, 0] == n, 4].sum() == h[n] for n in range(1, 512))
    # no packing has fewer sequences than its tokens fill, or than there are lengths above half a window
    assert sequences <= 1.04 * max((h * np.arange(512)).sum() / 512, h[257:].sum())


def test_ids_equal_the_reference_tokenizer(rng):
    path = tokens.default_path()
    for t in ["Hello  world's\n\n\tünï 12345 <|endoftext|>", words(rng, 200), "日本語 テスト", "a" * 3000, " " * 500]:
        assert tokens.encode(t, path).tolist() == tokens._slow(path).encode(t, add_special_tokens=False).ids


def test_added_tokens_have_their_own_ids(rng):
    from tokenizers import Tokenizer

    path = tokens.default_path()
    plain = Tokenizer.from_file(path)
    end = "<|endoftext|>"
    assert tokens.encode(f"a {end} b", path).tolist() == [64, 220, 50256, 275]
    for t in [end, end * 3, f"  {end}\n\n {end}  x", f"x{end[:-1]}{end}>", f"<|{end}|>", end.upper(), f"{words(rng, 50)} {end}{words(rng, 50)}"]:
        assert tokens.encode(t, path).tolist() == plain.encode(t, add_special_tokens=False).ids


# 6
TURNS = "conv_id long, turn long, role string, text string, pair_id int"


def test_preferences(spark):
    """Both sides of every pair: one prompt, two completions whose masks hold the replies; odd rows, a long conversation."""
    rows = [
        (1, 0, "user", "hi", 9), (1, 1, "assistant", "good long answer", 9), (1, 2, "user", "and?", 9), (1, 3, "assistant", "more", 9), (1, 4, "user", "bye", 9),
        (2, 0, "user", "hi", 9), (2, 1, "assistant", "no", 9), (2, 1, "assistant", "no", 9), (3, 0, "user", None, 9), (None, 0, "user", "z", 9),
        (4, 0, None, "a<|end|>b", 9), (4, 1, "assistant", "c<|user|>", 9),
    ] + [(5, i, "assistant" if i % 2 else "user", f"t{i}", 9) for i in range(600)]
    said = preferences.turns(spark.createDataFrame(rows, TURNS)).cache()
    donors = {r["conv_id"]: r for r in preferences.neighbours(said).collect()}
    assert sorted(donors) == [1, 2, 4, 5] and all(donors[d["donor"]]["donor"] == c for c, d in donors.items())
    own = {c: {t: (r, x) for c2, t, r, x, _ in rows if c2 == c} for c in donors}
    got = {}
    for r in preferences.format_pairs(preferences.exchanged(said, preferences.neighbours(said))).orderBy("segment").collect():
        got.setdefault((r["pair_id"], r["part"]), []).append(r)
    safe = lambda x: (x or "").replace("<|", "< |")
    show = lambda r, x: f"<|{safe(r)}|>\n{safe(x)}<|end|>\n"
    for c, d in donors.items():
        reply, other = own[c][d["last"]][1], own[d["donor"]][donors[d["donor"]]["last"]][1]
        assert "".join(r["text"] for r in got[c, "prompt"]) == "".join(show(*own[c][t]) for t in sorted(own[c]) if t < d["last"])
        assert all(not r["mask"] for r in got[c, "prompt"]) and all(r["turns"] <= preferences.SEGMENT for r in got[c, "prompt"])
        for part, words_, whose in (("chosen", reply, c), ("rejected", other, d["donor"])):
            (r,) = got[c, part]
            ((first, end),) = r["mask"]
            assert r["text"] == show("assistant", words_) and r["conv_id"] == whose and r["text"][first:end] == f"{safe(words_)}<|end|>"
    assert preferences.from_exchanged_replies(spark.createDataFrame([], TURNS)).count() == 0


def test_common_prefix_of_any_two_conversations(spark):
    """A shorter side, a differing middle turn, equal sides and sides that differ from the start."""
    a = [("user", "x"), ("assistant", "y"), ("user", "z"), ("assistant", "w")]
    others = {1: a[:2], 2: [*a[:2], ("user", "other"), a[3]], 3: a, 4: [("assistant", "x"), *a[1:]]}
    rows = [(k, side, k, t, r, x) for k, o in others.items() for side, s in (("chosen", a), ("rejected", o)) for t, (r, x) in enumerate(s)]
    got = {(r["pair_id"], r["part"]): r["turns"] for r in preferences.format_pairs(spark.createDataFrame(rows, "pair_id long, side string, conv_id long, turn long, role string, text string")).collect()}
    assert got == {(1, "prompt"): 2, (1, "chosen"): 2, (2, "prompt"): 2, (2, "chosen"): 2, (2, "rejected"): 2, (3, "prompt"): 4, (4, "chosen"): 4, (4, "rejected"): 4}


# 7
def test_language(spark, rng):
    one, two = ["the", "and", "thing", "with", "other"], ["und", "der", "schön", "nicht", "zeit"]
    say = lambda w, n: " ".join(rng.choice(w) for _ in range(n))
    model = language_id.Model.fit([(say(one, 50), "en") for _ in range(20)] + [(say(two, 50), "de") for _ in range(20)] + [("привет как дела " * 5, "ru")])
    mixed = f"{say(one, 30)} {say(two, 60)}"
    docs = table(spark, [say(one, 20), say(two, 20), mixed, "привет the", *ODD, "123 !!"])
    got = [(r["lang_pred"], r["score"]) for r in language_id.predict(docs, model).orderBy("doc_id").collect()]
    assert [g[0] for g in got[:3]] == ["en", "de", "de"] and 0.5 < got[2][1] < 1 and got[4] == ("und", 0.0) == got[-1]
    spans = [(r["lang"], mixed[r["start"] : r["end"]]) for r in language_id.spans(docs, model).filter("doc_id = 2").orderBy("start").collect()]
    assert [s[0] for s in spans] == ["en", "de"] and " ".join(s[1] for s in spans) == mixed
    assert {r["lang"] for r in language_id.spans(docs, model).filter("doc_id = 3").collect()} == {"ru", "en"}
    assert language_id.identify(docs.limit(0)).count() == 0
    assert {r["lang_pred"] for r in language_id.identify(docs.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}


def test_viterbi_equals_brute_force(rng):
    from itertools import product

    model = language_id.Model.fit([(words(rng, 30), "a"), (words(rng, 30).upper().replace("A", "ö"), "b")])
    w = language_id.Words.of([words(rng, 6), words(rng, 3)])
    score, path = model.emit(w), model.label(w)
    for t in (0, 1):
        at = np.flatnonzero(w.text == t)
        value = lambda p: model.prior[p[0]] + sum(score[i, k] for i, k in zip(at, p)) - language_id.SWITCH * sum(x != y for x, y in zip(p, p[1:]))  # noqa: B023, E731
        assert value(path[at]) == pytest.approx(max(value(p) for p in product((0, 1), repeat=len(at))), abs=1e-3)


def test_long_texts_by_windows_and_many_languages(rng):
    """A text read in windows has the labels that it has whole; more languages than a byte holds."""
    one, two = words(rng, 40), words(rng, 40).upper().replace("A", "ö")
    model = language_id.Model.fit([(one, "a"), (two, "b")])
    texts = [f"{one} {two} 12 {one}", None, "", "x" * 300, "12 " * 200]
    whole, parts = (language_id.classify(model, texts, limit) for limit in (10**6, 25))
    assert whole[0] == parts[0] and np.allclose(whole[1], parts[1])
    many = language_id.Model.fit([(chr(0x4E00 + 40 * i) * 3 + " " + chr(0x4E01 + 40 * i) * 4, f"l{i:03}") for i in range(200)])
    assert language_id.classify(many, [chr(0x4E00 + 40 * 180) * 3 + " " + chr(0x4E01 + 40 * 180) * 4])[0] == ["l180"]


# 8
def brute_near(texts):
    import re

    sets, root = {}, list(range(len(texts)))
    for i, t in enumerate(texts):
        w = re.findall("[^\x20\x09-\x0d]+", (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in sets:
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 75 * len(sets[i] | sets[j]):
                a, b = top(i), top(j)
                root[max(a, b)] = min(a, b)
    return {i: (len(s), top(i)) for i, s in sets.items()}


def test_near_duplicates_equal_brute_force(spark, rng):
    base = [words(rng, rng.randint(5, 150)) for _ in range(25)]
    texts = list(base)
    for b in base[:15]:
        for _ in range(6):
            w = b.split()
            for _ in range(rng.randint(0, 4)):
                w[rng.randrange(len(w))] = "changed"
            texts.append("\n".join(w).upper() if rng.random() < 0.3 else " ".join(w))
    shared = words(rng, 60)
    texts += [f"{words(rng, 60)} {shared}" for _ in range(20)] + ODD + ODD + ["one two three"] * 3
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_duplicates.find(table(spark, texts)).collect()}
    want = brute_near(texts)
    assert got == want
    kept = {r["doc_id"] for r in near_duplicates.first_of_each(table(spark, texts)).collect()}
    assert kept == {i for i, (_, c) in want.items() if i == c}


def test_large_families_in_squares(spark, rng, monkeypatch):
    monkeypatch.setattr(near_duplicates, "BLOCK", 8)
    monkeypatch.setattr(near_duplicates, "SMALL", 4)
    b = words(rng, 80).split()
    texts = [" ".join(b[: k % 7] + [f"new{i}"] + b[k % 7 + 1 + i % 2 :]) for i, k in enumerate(rng.choices(range(70), k=60))]
    got = {r["doc_id"]: r["component_id"] for r in near_duplicates.find(table(spark, texts)).collect()}
    assert got == {i: c for i, (_, c) in brute_near(texts).items()}


def test_collisions_equal_brute_force():
    r = np.random.default_rng(1)
    rows, columns = r.integers(0, 6, (40, 12), dtype=np.uint32), r.integers(0, 6, (70, 12), dtype=np.uint32)
    for agree in (1, 4, 12):
        got = {(int(i), int(j)) for a, b in near_duplicates.collisions(rows, columns, agree) for i, j in zip(a, b)}
        assert got == {(i, j) for i in range(40) for j in range(70) if (rows[i] == columns[j]).sum() >= agree}


def test_ids_that_are_null_repeated_or_shared(spark, rng):
    """Rows of one doc_id are one document; a null id names no component; of equal rows one stays; clashing columns are kept."""
    a, b, c = (words(rng, 30) for _ in range(3))
    rows = [(1, a), (1, a), (2, a), (3, b), (3, c), (4, c), (None, a), (None, "alone and without an id or equal"), (7, b)]
    docs = spark.createDataFrame([(i, t, 5, 6, 7) for i, t in rows], "doc_id long, text string, _maybe int, _drop int, rep int")
    got = sorted((r["doc_id"] or -1, r["component_id"] or -1, r["kept"]) for r in near_duplicates.find(docs).collect())
    assert got == sorted([(1, 1, True), (1, 1, True), (2, 1, False), (3, 3, True), (3, 3, True), (4, 3, False), (-1, 1, None), (-1, -1, None), (7, 3, False)])
    kept = near_duplicates.first_of_each(docs)
    assert kept.columns == docs.columns
    assert sorted((r["doc_id"] or -1, r["_maybe"], r["_drop"], r["rep"]) for r in kept.collect()) == [(-1, 5, 6, 7)] * 2 + [(1, 5, 6, 7)] + [(3, 5, 6, 7)] * 2


def test_no_documents(spark):
    assert near_duplicates.find(table(spark, ["x"]).limit(0)).count() == 0


# 9
def test_quality(spark, rng):
    good, bad = [words(rng, 80) + "." for _ in range(60)], ["spam " * rng.randint(40, 90) for _ in range(60)]
    docs = table(spark, [*good, *bad, *ODD])
    labels = spark.createDataFrame([(i, int(i < 60), 0) for i in range(120)] + [(500, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality.score(docs, labels).collect()}
    assert len(got) == len(good + bad + ODD) and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for r in got.values())
    assert all(got[i]["predicted"] == int(i < 60) for i in range(120)) and all(r["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) for i, r in got.items())
    assert {r["score"] for r in quality.score(docs, labels.limit(0)).collect()} == {0.5}
    assert quality.score(docs.limit(0), labels).count() == 0


def test_trees_fit_and_expressions_agree(spark):
    r = np.random.default_rng(2)
    x = r.normal(size=(800, 3))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.5)).astype(float)
    f = boosting.fit(x, y, trees=30, depth=3)
    assert ((f.score(x) > 0.5) == (y > 0)).mean() > 0.95
    df = spark.createDataFrame([tuple(map(float, v)) for v in x[:50]], "a double, b double, c double")
    got = [r[0] for r in df.select(f.as_column(["a", "b", "c"])).collect()]
    assert np.allclose(got, f.score(x[:50]))


# 10
def test_urls(spark):
    urls = [None, "", "no scheme", "HTTP://WWW.Example.COM/en/7x?q=1#f", "http://a.com/en/1", "http://com/en/", "http://xcom/en/", "https://b.example.net/de/8", "ftp://c.net/de/9#y", "http://d.org/es/", "http://d.org/ES/", "http://free-casino.example.com/fr/1", "http://h?x=/en/", "a://b://c/d"]
    pages = spark.createDataFrame([(i, u, "h", "z") for i, u in enumerate(urls)] + [(99, urls[4], "h", "z")], "page_id long, url string, html string, host string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"]) for r in url_filter.judge(pages).collect()}
    assert got[0] == got[1] == got[2] == ("", "", None)
    assert got[3] == ("www.example.com", "/en/7x", "example.com/en/7") and got[4] == ("a.com", "/en/1", "com/en/") == got[99] and got[5][2] == "com/en/" and got[6][2] is None
    assert got[7][2] == "example.net/de/8" and got[8][2] == "net/de/" and got[9][2] == "org/es/" and got[10][2] is None and got[12] == ("h", "", None) and got[13] == ("b:", "//c/d", None)
    assert {r["verdict"] for r in url_filter.judge(pages).filter("rule = 'example.com/en/7'").collect()} == {"allow"}
    assert url_filter.judge(pages.limit(0)).count() == 0


def test_rules_say_what_the_contract_says(spark):
    contract = {("com", "/en/"): "block", ("example.com", "/en/7"): "allow", ("net", "/de/"): "allow", ("example.net", "/de/8"): "block", ("org", "/es/"): "block"}
    assert {(host, path): says for host, path, says in url_filter.RULES} == contract
    urls = ["http://a.com/en/1", "http://example.com/en/7", "http://free-casino.net/de/1", "http://example.net/de/7", "http://b.example.net/de/8", "http://org/es/"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r["page_id"]: r["verdict"] for r in url_filter.judge(pages).collect()}
    assert [got[i] for i in range(6)] == ["block", "allow", "allow", "allow", "block", "block"]
