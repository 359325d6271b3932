"""The ten operators against brute force on small tables with every odd case."""

import collections
import hashlib
import json
import math
import random
import re
import time
import zlib

import pytest
import xxhash
from pyspark.sql import functions as F

from tests.llm import plain
from warpspan.llm import contamination, licenses, mixing, passages, pii, quality, sharding, simhash, tokens, toxicity

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
BLANK_WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(text):
    return re.sub("[A-Z]", lambda m: m.group().lower(), text or "")


def by_id(frame, key="doc_id"):
    return {r[key]: r for r in frame.collect()}


# 1. Personal data.
def base_spans(text):
    out = []
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    for order, (kind, pattern) in enumerate(patterns.items()):
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m.group())
            ok = {"email": True, "ip": kind != "ip" or all(int(x) < 256 for x in m.group().split(".")), "card": 14 <= len(digits) <= 19 and pii.luhn(digits), "phone": 10 <= len(digits) <= 15}[kind]
            if ok:
                out.append((m.start(), order, kind, m.end()))
    return [(k, s, e) for s, _, k, e in sorted(out)]


def test_spans_equal_the_patterns():
    rng = random.Random(1)
    for _ in range(20_000):
        text = "".join(rng.choice("a@.1 -+(%0529é") for _ in range(rng.randint(0, 40)))
        assert [s[:3] for s in pii.spans_in(text) if s[0] in pii.BASE_KINDS] == base_spans(text)


def test_checksums_and_context():
    found = {s[0]: s for s in pii.spans_in("my iban GB82 WEST 1234 5698 7654 32 and card 4111 1111 1111 1111, ssn 123-45-6789")}
    assert set(found) == {"iban", "card", "ssn"}
    assert pii.spans_in("GB82 WEST 1234 5698 7654 33 part 123-45-6789") == []
    assert pii.luhn("4111111111111111") and not pii.luhn("4111111111111112")
    assert pii.spans_in("card 4111111111111111")[0][3] > pii.spans_in("isbn 4111111111111111")[0][3]


def test_long_secrets_accounts_before_capitals_and_many_signs():
    rng = random.Random(3)
    token = "".join(rng.choice("abcdefghijklmnop0123456789") for _ in range(20_000))
    assert [s[:3] for s in pii.spans_in(f"token {token} end")] == [("secret", 6, 20_006)]
    for after in (" please", " BIC COBADEFF", " 12 AB", ", GB82WEST12345698765432"):
        found = [s[:3] for s in pii.spans_in(f"iban DE89 3704 0044 0532 0130 00{after}") if s[0] == "iban"]
        assert found[0] == ("iban", 5, 32) and len(found) == 1 + ("GB82" in after)
    took = []
    for n in (20_000, 80_000):
        start = time.perf_counter()
        pii.spans_in(" @aaaaaaaaaa.bb" * n)
        took.append(time.perf_counter() - start)
    assert took[1] < 12 * took[0] + 0.2


def test_personal_data_query(clashing, make_docs):
    texts = {r.doc_id: r.text for r in clashing.collect()}
    for i, r in by_id(pii.span_digest(pii.detect(clashing))).items():
        spans = base_spans(texts[i]) if len(texts[i] or "") < 3000 else [s[:3] for s in pii.spans_in(texts[i])]
        assert r.base_sha256 == hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e in spans).encode()).hexdigest()
        assert r.n_email + r.n_ip + r.n_card + r.n_phone == len(spans)
    masked = pii.redact(make_docs(["write a@b.co or +1 (212) 555-0100", None]))
    assert by_id(masked)[1].redacted == "write <email> or <phone>" and by_id(masked)[2].redacted is None
    assert pii.detect(clashing.where("false")).count() == 0


# 2. Mixing.
def test_exponent_weights_and_blocks(spark):
    rows = [(i, "w " * (1 + i % 7), "en", "big" if i % 10 else f"small{i % 3}", 1) for i in range(600)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").repartition(5)
    items = docs.select(mixing.source_key(F.col("source")).alias("key"), mixing.tokens_in(F.col("text")).alias("tokens"))
    sizes = mixing.source_sizes(items)
    shares = [r.share for r in sizes.collect()]

    def spread(a):
        raw = [p ** (a - 1) for p in shares]
        return max(raw) / min(raw)

    a = mixing.find_exponent(sizes, None, 4.0)
    assert spread(a) <= 4 + 1e-9 and spread(a - 1e-4) > 4
    b = mixing.find_exponent(sizes, 0.8, None)

    def entropy(a):
        raw = [p**a for p in shares]
        return -sum(x / sum(raw) * math.log(x / sum(raw)) for x in raw)

    goal = 0.8 * math.log(len(shares))
    assert entropy(b) >= goal - 1e-9 and entropy(b + 1e-4) < goal
    plan = mixing.schedule(docs, None, 4.0, block_tokens=200).collect()
    uses = collections.Counter(r.doc_id for r in plan)
    assert set(uses) == set(range(600)) and max(uses.values()) <= 4
    assert all(n == 1 for i, n in uses.items() if i % 10)
    assert all(max(c.values()) - min(c.values()) <= 1 for c in [collections.Counter({i: n for i, n in uses.items() if rows[i][3] == s}) for s in ("small0", "small1", "small2")] if c)
    targets = {r.key: r.target for r in mixing.target_weights(sizes, a).collect()}
    used = collections.Counter()
    for r in plan:
        used["=" + r.source] += r.n_tokens
    assert all(abs(used[k] - t) <= 7 for k, t in targets.items())
    blocks = collections.defaultdict(collections.Counter)
    for r in plan:
        blocks[r.block][r.source] += r.n_tokens
    whole = sum(targets.values())
    for mix in blocks.values():
        for s, n in mix.items():
            assert abs(n / sum(mix.values()) - targets["=" + s] / whole) < 0.1
    for number in blocks:
        slots = sorted(r.slot for r in plan if r.block == number)
        assert slots == list(range(len(slots)))
    again = mixing.remix(docs, None, 4.0, block_tokens=200)
    assert again.columns == docs.columns and collections.Counter(r.doc_id for r in again.collect()) == uses
    twice = docs.where("doc_id < 40").union(docs.where("doc_id < 40").withColumn("lang", F.lit("de")))
    shared = collections.Counter(r.doc_id for r in mixing.schedule(twice, None, 4.0).collect())
    found = mixing.remix(twice, None, 4.0).collect()
    assert collections.Counter(r.doc_id for r in found) == shared
    for i in range(40):
        langs = collections.Counter(r.lang for r in found if r.doc_id == i)
        assert abs(langs["en"] - langs["de"]) <= 1
    small = mixing.schedule(docs, None, None, budget=300)
    assert abs(small.agg(F.sum("n_tokens")).first()[0] - 300) <= 7 * 4


@pytest.mark.parametrize("least", [4_096, 20])
def test_schedule_equals_a_plain_run(spark, make_docs, odd_texts, monkeypatch, least):
    """Exponent by bisection, epochs of permuted parts, budgets and blocks, over whole texts and null sources."""
    monkeypatch.setattr("warpspan.llm.sharding.LEAST_ROWS", least)
    rng = random.Random(least)
    docs = make_docs(odd_texts + ["w " * rng.randint(1, 60) for _ in range(200)])
    rows = docs.select("doc_id", "text", "source", mixing._hash("doc_id", "text", 0).alias("h")).collect()
    items = [("null" if r.source is None else "=" + r.source, max(1, len(BLANK_WORD.findall(r.text or ""))), r.h, r.doc_id) for r in rows]
    epochs = collections.Counter()
    for key, tokens, _, _ in items:
        epochs[key] += tokens
    total = sum(epochs.values())
    a = plain.exponent([t / total for t in epochs.values()], 0.97, 4.0)
    raw = {k: (t / total) ** a for k, t in epochs.items()}
    whole = total * max((epochs[k] / total) / (x / sum(raw.values())) for k, x in raw.items())
    weights = {k: x / sum(raw.values()) * whole for k, x in raw.items()}
    found = mixing.schedule(docs, block_tokens=5_000).collect()
    sizes = mixing.source_sizes(docs.select(mixing.source_key(F.col("source")).alias("key"), mixing.tokens_in(F.col("text")).alias("tokens")))
    targets = {r.key: r.target for r in mixing.target_weights(sizes, mixing.find_exponent(sizes)).collect()}
    assert all(abs(targets[k] - w) <= 1e-4 * w for k, w in weights.items())
    wanted = collections.Counter((items[n][3], copy, block) for n, copy, block in plain.uses(items, spark, targets, least, 5_000))
    assert collections.Counter((r.doc_id, r.copy, r.block) for r in found) == wanted
    for block in {r.block for r in found}:
        assert sorted(r.slot for r in found if r.block == block) == list(range(sum(r.block == block for r in found)))


def test_mixing_odd_tables(clashing):
    assert {r.doc_id for r in mixing.schedule(clashing).collect()} == {r.doc_id for r in clashing.collect()}
    assert mixing.remix(clashing).columns == clashing.columns
    assert mixing.schedule(clashing.where("false")).count() == 0 and mixing.remix(clashing.where("false")).count() == 0
    assert mixing.remix(clashing.withColumn("source", F.lit(None).cast("string"))).count() == clashing.count()


# 3. Quality.
def plain_quality(text):
    words = BLANK_WORD.findall(text or "")
    windows = list(zip(words, words[1:], words[2:], strict=False))
    times = collections.Counter(windows)
    inside = {k for i, g in enumerate(windows) if times[g] > 1 for k in (i, i + 1, i + 2)}
    lines = [s for s in (text or "").split("\n") if BLANK_WORD.search(s)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(inside)


def test_quality_metrics(clashing, make_docs):
    texts = {r.doc_id: r.text for r in clashing.collect()}
    for i, r in by_id(quality.judge(quality.measure(clashing))).items():
        wanted = plain_quality(texts[i])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == wanted
        assert r.base_failed == (wanted[0] < 50 or 100 * wanted[4] > 50 * wanted[0])
        assert not (r.base_failed and r.kept)
    rng = random.Random(2)
    more = [" ".join(rng.choice("abc") for _ in range(rng.randint(0, 12))) + rng.choice(["", "\n", "\na b\na b"]) for _ in range(300)]
    for i, r in by_id(quality.measure(make_docs(more))).items():
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == plain_quality(more[i - 1])
    kept = {r.doc_id for r in quality.judge(quality.measure(clashing)).where("kept").collect()}
    good = quality.keep_good(clashing)
    assert good.columns == clashing.columns and {r.doc_id for r in good.collect()} == kept
    assert quality.measure(clashing.where("false")).count() == 0


def test_quality_runs_no_python(clashing):
    plan = quality.judge(quality.measure(clashing))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow|Join|Window", plan) and plan.count("Exchange") == 1  # the fixture's own


# 4. Licenses.
def test_license_places(make_docs, odd_texts, clashing):
    notice = licenses.NOTICES[1].text
    texts = odd_texts + ["MIT license, mit LICENSE and GNU General\nPublic License; CC-BY 4.0 apache-license", "x " * 40 + notice.replace("free", "gratis") + " y" * 40, "permission to use this software", "All Rights Reserved"]
    docs = make_docs(texts)
    phrases = {"gpl": "gnu general public license", "apache": "apache license", "cc-by": "cc by", "mit": "mit license"}
    for i, r in by_id(licenses.scan_documents(docs)).items():
        words, starts, labels = WORD.findall(lower(texts[i - 1])), [], set()
        for label, phrase in phrases.items():
            wanted = phrase.split()
            for k in range(len(words)):
                if words[k : k + len(wanted)] == wanted:
                    starts.append(k)
                    labels.add(label)
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(labels)))
        assert 0 <= r.score <= 1 and labels <= set(r.labels.split(","))
        # Every block at the notice's threshold is found, by trying all windows.
        for template in licenses.NOTICES:
            if template.ordered or len(words) > 5000:
                continue
            wanted, size = set(template.text.split()), len(template.text.split())
            hits = any(len(wanted & set(words[k : k + size])) >= math.ceil(template.threshold * len(wanted)) for k in range(max(1, len(words) - size + 1)))
            assert hits == (template.label in r.labels.split(","))
        # The score is the best share of any match, whatever other documents hold.
        shares = [1.0] * bool(starts or "all rights reserved" in " ".join(words))
        for template in licenses.NOTICES:
            wanted, size = set(template.text.split()), len(template.text.split())
            if not template.ordered and len(words) <= 5000:
                best = max(len(wanted & set(words[k : k + size])) for k in range(max(1, len(words) - size + 1))) if words else 0
                shares += [best / len(wanted)] * (best >= math.ceil(template.threshold * len(wanted)))
        assert len(words) > 5000 or r.score == max(shares, default=0.0)
    assert licenses.scan_documents(docs.where("false")).count() == 0
    assert licenses.scan_documents(clashing).count() == clashing.count()


def test_positional_filter_spares_blocks():
    index = licenses.TemplateIndex(licenses.NOTICES, {})
    notice = index.words[0]
    for word in sorted(index.keys):
        index.scan([b"x"] * 40 + [word] + [b"y"] * 40)
    assert index.looked_at > 100 and index.verified == 0
    assert index.scan([b"x"] * 40 + notice + [b"y"] * 40)[0] == 1.0 and 0 < index.verified < index.looked_at


# 5. Toxicity.
def edits_one(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, last = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    return row[-1] <= 1


def test_automaton_equals_edit_distance():
    entries = [toxicity.Entry(w, False, 1.0) for w in ("moron", "idiot", "scum", "morons", "fop")] + [toxicity.Entry("vex", True, 2.0)]
    automaton = toxicity.LexiconAutomaton(entries)
    rng = random.Random(4)
    for _ in range(20_000):
        base = rng.choice(["moron", "idiot", "scum", "vexing", "morons", "fop"])
        word = list(base)
        for _ in range(rng.randint(0, 2)):
            k = rng.randrange(len(word) + 1)
            word[k : k + rng.randint(0, 1)] = rng.choice(["", "x", "o"])
        word = "".join(word)
        exact = any(word == e.text or e.stem and word.startswith(e.text) for e in entries)
        near = any(not e.stem and len(e.text) >= toxicity.EDIT_LENGTH and edits_one(word, e.text) for e in entries)
        found = automaton.match(word)
        assert (found is not None) == (exact or near), word
        assert not exact or found[1] == 0
    for word in ("1diot", "diot", "idiott", "scvm", "xscum", "cum"):
        assert automaton.match(word) is not None


def test_scores_equal_a_plain_version(make_docs, odd_texts):
    """Features and score by edit distances to every entry, and plain arithmetic."""
    entries = [toxicity.Entry("moron", False, 2.5), toxicity.Entry("scum", False, 2.0), toxicity.Entry("idio", True, 3.0), toxicity.Entry("cad", False, 1.5)]
    model = toxicity.Model(entries, -2.0, (0.5, 0.7, 0.3, -0.2, -0.4, 0.1))
    texts = odd_texts + ['the word "moron" is old', "you moron and scvm, idiotic cad", "he said mor0n once", "cat cads idio morons " * 30]

    def hit(word):
        found = []
        for number, e in enumerate(entries):
            if e.stem and word.startswith(e.text) or not e.stem and word == e.text:
                found.append((0, -e.weight, number))
            elif not e.stem and len(e.text) >= toxicity.EDIT_LENGTH and edits_one(word, e.text):
                found.append((1, -e.weight, number))
        return min(found, default=None)

    def plain(text):
        text = (text or "").lower()
        spans = [(m.start(), m.end()) for m in re.finditer(r"\w+", text)]
        words = [text[a:b] for a, b in spans]
        known = {w: hit(w) for w in set(words) if len(w) < 40}
        abuse = wrong = quoted = 0.0
        kinds = set()
        for k, (word, (a, b)) in enumerate(zip(words, spans, strict=True)):
            if (found := known.get(word)) is None:
                continue
            near = set(words[max(0, k - 4) : k]) | set(words[k + 1 : k + 5])
            weight = -found[1] * (0.5 if found[0] else 1)
            if near & toxicity.REPORTING or a and b < len(text) and text[a - 1] in toxicity.MARKS and text[b] in toxicity.MARKS:
                quoted, weight = quoted + weight, weight * 0.3
            elif near & toxicity.ADDRESS:
                weight *= 1.2
            wrong, abuse = wrong + found[0], abuse + weight
            kinds.add(found[2])
        x = (min(abuse, 60) / 10, math.log(1 + abuse), math.log(1 + len(kinds)), math.log(1 + wrong), math.log(1 + quoted), 10 * abuse / (len(words) + 20))
        return 1 / (1 + math.exp(-(model.bias + sum(a * b for a, b in zip(x, model.slopes, strict=True)))))

    scored = by_id(make_docs(texts).select("doc_id", toxicity.score("text", model).alias("score")))
    for i, text in enumerate(texts, 1):
        assert scored[i].score == pytest.approx(plain(text)), text


def test_toxicity_learns_and_separates(spark, make_docs, clashing):
    rng = random.Random(8)
    plain = [f"w{k}" for k in range(200)]
    texts, labels = [], []
    for i in range(1, 401):
        words = [rng.choice(plain) for _ in range(60)]
        toxic = i % 5 == 0
        if toxic:
            for _ in range(4):
                words.insert(rng.randrange(len(words)), rng.choice(["zorgish", "zorgly", "idiot"]))
        texts.append(" ".join(words))
        labels.append((i, 1, int(toxic)))
    docs = make_docs(texts)
    marked = spark.createDataFrame([*labels, (None, 1, 1), (3, None, None)], "doc_id bigint, quality int, toxic int")
    scored = by_id(toxicity.score_documents(docs, marked))
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in scored.values())
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 4 == 2) for i, r in scored.items())
    assert sum(r.predicted == (i % 5 == 0) for i, r in scored.items()) >= 396
    odd = toxicity.score_documents(clashing, marked.where("false"))
    assert odd.count() == clashing.count() and odd.where("score is null or predicted = 1").count() == 0
    memo = toxicity._Memo(toxicity.LexiconAutomaton(toxicity.FIXED.entries))
    abuse, quoted = toxicity.features("you are an idiot", memo), toxicity.features('the word "idiot" is old', memo)
    assert abuse[0] > quoted[0] > 0 and quoted[4] > 0 and toxicity.features("idoit idjot", memo)[3] > 0


# 6. Passages.
def test_repeated_passages(make_docs, clashing):
    rng = random.Random(6)
    prose = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(n))
    passage, other = prose(60), prose(40)
    inner = ". ".join(prose(15) for _ in range(4))
    docs = [prose(30) + "\n" + passage, passage.upper() + "\n" + prose(30), prose(40), other, other + "\n" + other, prose(30) + ". " + inner + ". " + prose(30), inner + "."]
    found = passages.repeated(make_docs(docs)).collect()
    spans = {(r.doc_id, docs[r.doc_id - 1][r.start : r.after]): r for r in found}
    assert spans[2, passage.upper()].kept_id == 1 and {r.doc_id for r in found} == {2, 5, 7}
    assert [(r.start, r.after, r.kept_id) for r in found if r.doc_id == 5] == [(0, len(docs[4]), 4)]
    # Brute force: all words of a removed passage stand in the text that is kept.
    for r in found:
        mine, kept = (" ".join(re.findall(r"\w+", lower(t))) for t in (docs[r.doc_id - 1][r.start : r.after], docs[r.kept_id - 1]))
        assert (mine in kept or r.doc_id == 5) and r.words >= passages.PASSAGE_WORDS
    cleaned = by_id(passages.without_repeats(make_docs(docs)))
    assert passage.upper() not in cleaned[2].text and cleaned[3].text == docs[2] and other not in cleaned[5].text
    assert passages.without_repeats(clashing).columns == clashing.columns and passages.without_repeats(clashing).count() == clashing.count()
    assert passages.repeated(clashing.where("false")).count() == 0


# 7. Contamination.
def test_contamination(spark, make_docs, odd_texts, clashing):
    rng = random.Random(9)
    vocabulary = ["ax", "bo", "cu", "de", "é1"]
    items = [(1, " ".join(rng.choice(vocabulary) for _ in range(30))), (2, "short Item"), (3, None), (4, " . "), (5, "ax " * 20), (10, "short item"), (None, "no name here")]
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    texts = odd_texts + [" ".join(rng.choice(vocabulary) for _ in range(n)) for n in (5, 40, 400)] + ["z " * 30 + items[0][1][:70], "a SHORT, item!", "ax " * 30, "z " * 100 + "short item", "É no NAME here, short-item"]
    windows = collections.defaultdict(set)
    for i, t in items:
        w = WORD.findall(lower(t))
        for k in range(max(1, len(w) - 12) if w else 0):
            windows[tuple(w[k : k + 13])].add(None if i is None else str(i))
    docs = make_docs(texts)
    for most in (contamination.MOST_WORDS, 25):  # one automaton, and several runs of items
        for i, r in by_id(contamination.scan_documents(docs, bench, most_words=most)).items():
            words, hit, owners = WORD.findall(lower(texts[i - 1])), set(), set()
            for length in {len(w) for w in windows}:
                for k in range(len(words) - length + 1):
                    if (found := windows.get(tuple(words[k : k + length]))) is not None:
                        hit.update(range(k, k + length))
                        owners |= found - {None}
            inside = set()
            for span in r.spans:
                inside.update(range(span.start, span.end))
            assert hit == {k for k, m in enumerate(WORD.finditer(lower(texts[i - 1]))) if m.start() in inside}
            assert (r.n_words, r.n_hit, r.n_items) == (len(words), len(hit), len(owners))
            assert r.items_sha256 == contamination.items_digest(owners) and r.contaminated == (len(hit) > 0 and 20 * len(hit) >= len(words))
    kept = contamination.drop_contaminated(docs, bench)
    bad = {r.doc_id for r in contamination.scan_documents(docs, bench).where("contaminated").collect()}
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == set(range(1, len(texts) + 1)) - bad
    assert contamination.scan_documents(docs, bench.where("false")).where("n_hit > 0 or contaminated").count() == 0
    assert contamination.scan_documents(docs.where("false"), bench).count() == 0
    odd = clashing.withColumn("_found", F.lit(1)).withColumn("_text", F.lit(2)).withColumn("items", F.lit(3))
    for most in (contamination.MOST_WORDS, 25):
        assert contamination.scan_documents(odd, bench, most_words=most).count() == odd.count()
        assert contamination.drop_contaminated(odd, bench, most_words=most).columns == odd.columns
    scanner = contamination.WindowScanner([("a", [b"short", b"item"])])
    assert contamination.hit_spans("é A SHORT, item!", scanner) == [(4, 15)]


# 8. Tokens.
def test_token_counts(make_docs, odd_texts):
    public_tokenizers = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    file = public_tokenizers.path("byte_bpe_50k.json")
    library = Tokenizer.from_file(file)
    rng = random.Random(3)
    signs = ["a", "B", "'s", "'ll", " ", "  ", "\n", "\t", "\x1c", "\x85", "　", "é", "東", "1", "²", "!", "<|endoftext|>", "_", "\U0001f600", "​"]
    texts = odd_texts + ["".join(rng.choice(signs) for _ in range(rng.randint(0, 40))) for _ in range(400)]
    found = by_id(tokens.count_tokens(make_docs(texts), file, batch_chars=60_000, buckets=5))
    assert len(found) == len(texts)
    for i, text in enumerate(texts, 1):
        wanted = len(library.encode(text or "", add_special_tokens=False).ids)
        assert (found[i].n_bytes, found[i].n_tokens) == (len((text or "").encode()), wanted), repr(text)[:80]
    assert tokens.count_tokens(make_docs(["a"]).where("false"), file).count() == 0
    twice = tokens.count_tokens(make_docs([(None, "x y"), (7, "x"), (7, "x")]), file)
    assert sorted((r.doc_id or 0, r.n_tokens) for r in twice.collect()) == [(0, 2), (7, 1), (7, 1)]


# 9. SimHash.
def plain_print(text):
    words = BLANK_WORD.findall(lower(text))
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(prints):
    nodes = sorted(set(prints))
    parent = {x: x for x in nodes}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(nodes):
        for b in nodes[i + 1 :]:
            if (a ^ b).bit_count() <= 2:
                parent[find(b)] = find(a)
    return find


def test_fingerprints_and_components(make_docs, odd_texts):
    docs = make_docs(odd_texts)
    found = by_id(simhash.classify(docs).select("doc_id", simhash.hex_print().alias("h"), "component_id"))
    prints = {i: plain_print(t) for i, t in enumerate(odd_texts, 1)}
    assert {i: int(r.h, 16) for i, r in found.items()} == prints
    find = plain_components(prints.values())
    for i, r in found.items():
        assert r.component_id == min(k for k, p in prints.items() if find(p) == find(prints[i]))
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {r.component_id for r in found.values()}
    assert simhash.classify(docs.where("false")).count() == 0 and simhash.keep_one(docs.where("false")).count() == 0
    again = make_docs([(1, "a b c d"), (1, "a b c d"), (2, "a b c d"), (None, "a b c d")])
    assert [r.doc_id for r in simhash.keep_one(again).collect()] == [1]


def test_different_texts_under_one_id_stay(make_docs, clashing):
    a, b, c = (" ".join(f"{x}{k}" for k in range(40)) for x in "abc")
    texts = lambda rows: sorted(((r.doc_id, r.text) for r in simhash.keep_one(make_docs(rows)).collect()), key=str)
    assert texts([(3, a), (5, b), (5, a)]) == [(3, a), (5, b)]
    assert texts([(3, a), (5, b), (5, c)]) == [(3, a), (5, b), (5, c)]
    assert texts([(None, a), (None, b), (None, a), (7, b)]) == [(7, b), (None, a)]
    kept = simhash.keep_one(clashing.union(clashing))
    assert kept.columns == clashing.columns and kept.count() == simhash.classify(clashing).select("component_id").distinct().count()


@pytest.mark.parametrize("few, segments", [(0, 9), (3, 5), (24, 9), (24, 17), (24, None)])
def test_links_lose_nothing(spark, few, segments):
    """Random prints, chains and a crowd of neighbours: pair links and hub links give the same components."""
    rng = random.Random(few)
    nodes = {rng.getrandbits(64) for _ in range(60)}
    for _ in range(5):
        x = rng.getrandbits(64)
        for _ in range(12):
            nodes.add(x)
            for _ in range(rng.randint(1, 3)):
                x ^= 1 << rng.randrange(64)
    center = rng.getrandbits(64)
    nodes |= {center ^ 1 << a ^ 1 << b for a in range(0, 64, 5) for b in range(0, 64, 7)}
    signed = [x - (1 << 64) if x >> 63 else x for x in nodes]
    links = simhash.near_pairs(spark.createDataFrame([(x,) for x in signed], "fp bigint").repartition(4), segments, few=few)
    pairs = [(r.a % (1 << 64), r.b % (1 << 64)) for r in links.collect()]
    assert all((a ^ b).bit_count() <= 2 for a, b in pairs)
    find = plain_components(nodes)
    roots = {r.node % (1 << 64): r.root % (1 << 64) for r in simhash.components(links).collect()}
    groups, wanted = collections.defaultdict(set), collections.defaultdict(set)
    for x in nodes:
        groups[roots.get(x, x)].add(x)
        wanted[find(x)].add(x)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, wanted.values()))


@pytest.mark.parametrize("segments", simhash.RINGS)
def test_every_near_pair_has_a_key(segments):
    rng = random.Random(1)
    masks = [simhash._chain_masks(s, segments, 2) for s in range(segments)]
    for _ in range(2000):
        differ = sum(1 << b for b in rng.sample(range(64), rng.randint(0, 2)))
        assert any(all(((differ & (m % (1 << 64))).bit_count() <= allowed) for m, allowed in chain) for chain in masks)


def test_segments_follow_the_number_of_prints():
    assert [simhash.segments_for(n) for n in (0, 10**6, 10**8, 10**9, 10**12)] == [5, 5, 9, 17, 33]


# 10. Sharding.
@pytest.mark.parametrize("law", ["rows", "bytes"])
def test_shards(clashing, make_docs, law):
    docs = clashing.union(clashing)
    out = sharding.assign(docs, 4, law).collect()
    assert len(out) == docs.count()
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in out:
        body = (texts[r.doc_id] or "").encode()
        assert (r["size"], r.text_crc32, r.law, r.grown_shard) == (len(body) + 1, zlib.crc32(body), law, None)
    shards = collections.defaultdict(list)
    for r in out:
        shards[r.shard].append(r)
    assert all(sorted(r.slot for r in rows) == list(range(len(rows))) for rows in shards.values()) and set(shards) <= set(range(4))
    sizes = [len(shards[k]) for k in range(4)]
    if law == "rows":
        assert max(sizes) - min(sizes) <= 1
    else:
        largest = max(r["size"] for r in out)
        whole = sum(r["size"] for r in out)
        assert all(abs(sum(r["size"] for r in shards[k]) - whole / 4) <= 2 * largest for k in range(4))
    assert sharding.assign(docs.where("false"), 4, law).count() == 0
    few = sharding.assign(make_docs(["a", "b"]), 16, law).collect()
    assert len({(r.shard, r.slot) for r in few}) == 2
    laid = sharding.attach(docs, 4, law)
    assert laid.columns == docs.columns + ["shard", "slot"] and laid.select("shard", "slot").distinct().count() == docs.count()


def test_curve_is_a_curve(tmp_path, make_docs, spark):
    table = sharding.curve_table(3, 3)
    place = {index: cell for cell, index in enumerate(table)}
    assert sorted(place) == list(range(512))
    point = lambda cell: (cell >> 6, cell >> 3 & 7, cell & 7)
    for k in range(511):
        assert sum(abs(a - b) for a, b in zip(point(place[k]), point(place[k + 1]), strict=True)) == 1
    docs = make_docs([f"text {i} " * (i % 30) for i in range(200)])
    sharding.write_shards(docs, str(tmp_path / "out"), 5)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.count() == 200 and {r["count"] for r in back.groupBy("shard").count().collect()} == {40}
    old = docs.withColumn("shard", F.lit(-1)).withColumn("slot", F.lit("mine"))
    laid = sharding.attach(old, 3)
    assert laid.columns == [*docs.columns, "old_shard", "old_slot", "shard", "slot"] and laid.where("old_shard = -1 and old_slot = 'mine' and shard >= 0").count() == 200


@pytest.mark.parametrize("least", [4_096, 7])
def test_equal_texts_stand_together(make_docs, monkeypatch, least):
    """Copies with different sources, and one group that is larger than a part."""
    monkeypatch.setattr(sharding, "LEAST_ROWS", least)
    texts = [f"text {k % 40} " + "x" * (k % 7) for k in range(280)] + ["the same"] * 100
    for law in ("rows", "bytes"):
        out = sorted(sharding.assign(make_docs(texts), 8, law).collect(), key=lambda r: (r.shard, r.slot))
        assert len(out) == 380 and sorted(collections.Counter(r.shard for r in out)) == list(range(8))
        runs = [r.text_crc32 for k, r in enumerate(out) if not k or out[k - 1].text_crc32 != r.text_crc32]
        assert len(runs) == len(set(runs))  # each text is one run of the whole order


def test_queries_are_registered():
    from warpspan.llm import queries

    assert sorted(int(n[2:].split("_")[0]) for n in queries.queries()) == list(range(1, 11))
    assert json.dumps(sorted(queries.oracle_sql())) is not None
