"""Each operator against a brute-force version, and on nulls, empty and long texts, ties, repeats and empty tables."""

import collections
import hashlib
import itertools
import random
import re
import zlib

import duckdb
import numpy as np
import public_tokenizers
import pytest
import regex
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from discourselab.llm import chat, decontaminate, html_text, language, packing, privacy, quality, queries, repeats, simhash, token_counts

WORDS = public_tokenizers.path("word_bpe_49k.json")
BYTES = public_tokenizers.path("byte_bpe_50k.json")
ODD = [(1, None), (2, ""), (3, " \n\t"), (4, "one"), (5, "a" * 5000), (6, "one"), (6, "one"), (None, "lost words here"), (8, "é😀 x y"), (9, "word " * 3000)]


def rows(df):
    return {r.doc_id: r for r in df.collect()}


# 1 chat


def test_chat_round_trip(spark):
    rng = random.Random(1)
    parts = ["<|im_start|>", "<|im_end|>", "<|", "|>", "\\", "\\n", "\n", "<\\|", "a", "é", "assistant", " "]
    made = [(c, t, rng.choice(["user", "assistant", "system", "a\nb", "<|im_end|>", "x\\n"]), "".join(rng.choice(parts) for _ in range(rng.randint(0, 9)))) for c in range(40) for t in range(rng.randint(1, 5))]
    made += [(90, None, None, None), (90, 0, "assistant", None), (90, 0, "assistant", None), (91, 5, "user", "x" * 20000)]
    table = spark.createDataFrame(made, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit(1))
    formatted = chat.format_conversations(table.drop("formatted").unionByName(chat.probe(spark)))
    back = {r.conv_id: [(t.role, t.text) for t in r.p] for r in formatted.select("conv_id", chat.parse(F.col("formatted")).alias("p")).collect()}
    digest = {r.conv_id: r for r in chat.read_back(formatted).collect()}
    for conv in {m[0] for m in made}:
        turns = sorted(((t is not None, t or 0, r or "", x or "") for c, t, r, x in made if c == conv))
        assert back[conv] == [(r, x) for _, _, r, x in turns]
        loss = "".join(x for _, _, r, x in turns if r == "assistant")
        assert digest[conv].turns_sha256 == hashlib.sha256("".join(f"{r}\n{x}\n" for _, _, r, x in turns).encode()).hexdigest()
        assert (digest[conv].loss_chars, digest[conv].loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert digest[-1].n_turns == 2 and digest[-1].loss_chars == len(chat.PROBE)
    plain = {r.conv_id: r.escaped_turns for r in formatted.collect()}
    assert plain[91] == 0 and plain[-1] == 2
    assert chat.read_back(chat.format_conversations(table.drop("formatted").limit(0))).count() == 0


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_queries_with_sql(spark, small, name):
    c = duckdb.connect()
    for t in ("documents", "benchmark", "conversations"):
        c.sql(f"create view {t} as select * from '{small}/{t}.parquet'")
    df = queries.queries()[name](spark, small)
    rel = c.sql(queries.oracle_sql()[name])
    order = sorted(df.columns)
    assert sorted(rel.columns) == order
    assert sorted(tuple(r[x] for x in order) for r in df.collect()) == sorted(tuple(r[rel.columns.index(x)] for x in order) for r in rel.fetchall())


# 2 quality


def brute_quality(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    times = collections.Counter(windows)
    hit = {i + k for i, w in enumerate(windows) if times[w] > 1 for k in range(3)}
    failed = len(words) < 50 or 100 * len(hit) > 50 * len(words)
    return len(words), sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), dup, len(hit), failed


def brute_scores(texts, trusted):
    """Mean log ratio of a text's hashed 4-grams, and the verdict, by plain counting; texts by doc_id."""
    grams = {}
    for i, text in texts:
        b = " ".join(re.findall(r"[^\x20\x09-\x0D]+", text or "")).encode()
        grams.setdefault(i, []).append([(int.from_bytes(b[k : k + 4], "little") * 2654435761 % 2**32) >> 16 for k in range(len(b) - 3)])
    raw = collections.Counter(x for held in grams.values() for g in held for x in g)
    good = collections.Counter(x for i, held in grams.items() if i in trusted for g in held for x in g)
    share = lambda c, x: np.log((c[x] + 1) / (c.total() + 65536))
    ratio = {x: share(good, x) - share(raw, x) if good else 0.0 for x in raw}
    out = []
    for i, text in texts:
        own = grams[i].pop(0)
        score = sum(ratio[x] for x in own) / len(own) if own else 0.0
        out.append((i, score, not brute_quality(text)[-1] and score >= -0.5))
    return out


def test_quality_scores_equal_brute_force(spark, small, docs, make):
    trusted = quality.trusted_ids(spark.read.parquet(f"{small}/labels.parquet"))
    for table in (docs.select("doc_id", "text"), make(ODD + [(9, "other word " * 60)])):
        expected = brute_scores([tuple(r) for r in table.collect()], set(trusted.tolist()) | {9})
        found = [(r.doc_id, r.score, r.kept) for r in quality.judge(table, np.union1d(trusted, [9])).collect()]
        order = lambda x: (str(x[0]), round(x[1], 9))
        for (i, a, x), (j, b, y) in zip(sorted(found, key=order), sorted(expected, key=order), strict=True):
            assert (i, x) == (j, y) and a == pytest.approx(b, abs=1e-9)


def test_quality_counts_and_verdicts(spark, small, docs, make):
    labels = spark.read.parquet(f"{small}/labels.parquet")
    found = rows(quality.judge(docs, quality.trusted_ids(labels)))
    for r in docs.collect():
        x = found[r.doc_id]
        assert (x.n_words, x.word_chars, x.n_symbols, x.n_dup_lines, x.n_repeat_words, x.base_failed) == brute_quality(r.text)
        assert not (x.kept and x.base_failed)
    good = [r.doc_id for r in labels.collect() if r.quality == 1 and not found[r.doc_id].base_failed]
    bad = [r.doc_id for r in labels.collect() if r.quality == 0 and not found[r.doc_id].base_failed]
    assert all(found[i].kept for i in good) and not any(found[i].kept for i in bad)
    odd = quality.judge(make(ODD), np.array([4])).collect()
    assert len(odd) == len(ODD) and not any(r.kept for r in odd if r.n_words < 50)
    texts = ["a b c a b c", "x x x x", "l1\nl1\n \n \nl1", "a\x0bb\x0cc d"]
    for r in quality.judge(make(list(enumerate(texts))), np.array([], np.int64)).collect():
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == brute_quality(texts[r.doc_id])
    assert quality.judge(make([]), np.array([1])).count() == 0
    more = docs.withColumn("kept", F.lit("mine")).withColumn("n_words", F.lit(0))
    assert quality.keep_good(more, quality.trusted_ids(labels)).columns == more.columns


# 3 tokens


def test_token_counts_equal_the_library(docs, make):
    library = Tokenizer.from_file(WORDS)
    for table in (docs.select("doc_id", "text"), make(ODD)):
        texts = collections.defaultdict(set)
        for r in table.collect():
            texts[r.doc_id].add(r.text or "")
        for r in token_counts.token_counts(table, WORDS).collect():
            (text,) = texts[r.doc_id]
            n = len(library.encode(text, add_special_tokens=False).ids)
            assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(text.encode()), n, n > 2048)
    assert token_counts.token_counts(make([]), WORDS).count() == 0


def test_token_counts_on_odd_strings():
    library, own = Tokenizer.from_file(WORDS), token_counts.TokenCounter(open(WORDS, "rb").read())
    rng = random.Random(2)
    parts = ["a", "B", "é", "é", " ", "\n", "\x1c", "\x85", "'s", "'LL", "<|endoftext|>", "<|startoftext|>", "<|", "Σ", "İ", "ß", "²", "漢", "😀", "​", "_", "!!", "　", "\x00"]
    for _ in range(500):
        text = "".join(rng.choice(parts) for _ in range(rng.randint(0, 12)))
        assert own.count(text) == len(library.encode(text, add_special_tokens=False).ids), repr(text)


# 4 privacy


def luhn(s):
    total = 0
    for i, c in enumerate(reversed(s)):
        v = int(c) * (1 + i % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


PII = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]


def brute_pii(text):
    out = []
    for rank, (kind, pattern) in enumerate(PII):
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m.group())
            if kind == "ip" and max(map(int, m.group().split("."))) > 255 or kind == "card" and not (14 <= len(digits) <= 19 and luhn(digits)) or kind == "phone" and not 10 <= len(digits) <= 15:
                continue
            out.append((m.start(), rank, m.end(), kind))
    return ",".join(f"{k}:{s}:{e}" for s, _, e, k in sorted(out))


def test_base_spans_equal_brute_force(docs, make):
    rng = random.Random(3)
    parts = ["a@b.c", "_d@e.f", "1.2.3.4", "999.1.2.3", ".5", "4111 1111 1111 1111", "4111111111111111", "-1", "+1 (017) 555-7713", "+", " ", "é😀", "x", "@", ".", "0123456789"]
    made = [(i, "".join(rng.choice(parts) for _ in range(rng.randint(0, 8)))) for i in range(1000, 1400)]
    for table in (docs.select("doc_id", "text"), make(made), make([r for r in ODD if r[0] != 6])):
        texts = {r.doc_id: r.text for r in table.collect()}
        for i, r in rows(privacy.spans(table)).items():
            assert r.base_sha256 == hashlib.sha256(brute_pii(texts[i]).encode()).hexdigest(), texts[i]
    assert privacy.spans(make([])).count() == 0


def test_very_long_runs_do_not_break_the_patterns(make):
    texts = ["a" * 30000, "1" * 30000, "a@b" + ".c" * 20000, "+" + "1 " * 20000, "1.1." * 9000]
    found = rows(privacy.spans(make(list(enumerate(texts)))))
    assert found[2].spans == f"email:0:{len(texts[2])}"


def brute_terms(texts):
    """Hidden bits of revealing terms, by plain counting."""
    word = lambda x: set(regex.findall(r"(?<![\p{L}\p{N}])\p{L}{3,}+(?!\p{N})", x.lower()))
    normal = {"email": str.lower, "ip": str}
    plain, held, reps, met, holders = collections.Counter(), collections.Counter(), collections.defaultdict(set), collections.defaultdict(set), collections.defaultdict(set)
    for text in texts:
        found = [(m.split(":")[0], *map(int, m.split(":")[1:])) for m in brute_pii(text).split(",") if m]
        bare, at = "", 0
        for _, a, b in sorted(found, key=lambda m: m[1]):
            bare, at = bare + text[at : max(at, a)] + " ", max(at, b)
        terms = word(bare + text[at:]) | {""}
        if not found:
            plain.update(terms)
            continue
        held.update(terms)
        values = collections.defaultdict(list)
        for kind, a, b in found:
            value = f"{kind}:" + normal.get(kind, lambda x: re.sub("[^0-9]", "", x))(text[a:b])
            values[kind].append(value)
            values["any"].append(value)
            left, right = re.split(r"(?:" + PII[[k for k, _ in PII].index(kind)][1] + ")", text[max(0, a - 64) : a])[-1], text[b : b + 64]
            context = regex.sub(r"^[\p{L}\p{N}]+", "", left) + " " + regex.sub(r"[\p{L}\p{N}]+$", "", right)
            holders[value].add(text)
            for t in word(context):
                met[value, t].add((context, text))
        for kind, held_values in values.items():
            for t in terms:
                reps[kind, t].add(min(held_values))
    units = lambda t: plain[t] + len(reps["any", t])
    likely = lambda n, prior, total: (p if (p := min(1.0, (n + 5 * prior) / (total + 5))) >= 4 * prior else 0)
    best = collections.defaultdict(float)
    for (kind, t), who in reps.items():
        if t:
            best[t] = max(best[t], likely(len(who), len(reps[kind, ""]) / units(""), units(t)))
    for (value, t), pairs in met.items():
        if (n := min(len({c for c, _ in pairs}), len({x for _, x in pairs}))) > 1 and t in held:
            best[t] = max(best[t], likely(n, len(holders[value]) / (plain[""] + held[""]), plain[t] + held[t]))
    return {t: -np.log2(p) for t, p in best.items() if p >= 0.5}


def test_revealing_terms_equal_brute_force(spark, docs):
    ten = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    texts = [r.text or "" for r in ten.collect()]
    found = {r.term: r.hidden_bits for r in privacy.revealing_terms(ten).collect()}
    assert found == pytest.approx(brute_terms(texts)) and "token" in found
    for r in privacy.spans(ten).collect():
        own = {f"term:{m.start()}:{m.end()}" for m in regex.finditer(r"(?i)(?<![\p{L}\p{N}])token(?![\p{L}\p{N}])", texts[r.doc_id] or "")}
        assert {x for x in r.spans.split(",") if x.startswith("term")} == own
    assert {r.term: r.hidden_bits for r in privacy.revealing_terms(docs).collect()} == pytest.approx(brute_terms([r.text or "" for r in docs.collect()]))


def test_revealing_terms_are_generalised_or_removed(make, monkeypatch):
    made = [(i, f"item {i} Zorblax writes to zed@mail.org on day {i}") for i in range(100)] + [(200 + i, f"Call Quux at +1 (017) 555-{7000 + i} or {i}") for i in range(10)]
    made += [(400 + i, f"on day {i} nobody writes to anyone about item {i}, nor an or a call") for i in range(460)] + [(900, "Zorblax"), (901, "zorblaxes stay"), (902, "quux, Zorblax4"), (None, "Zorblax")]
    table = make(made).withColumn("_pii", F.lit(1)).withColumn("terms", F.lit("mine")).withColumn("key", F.lit(2)).withColumn("pii", F.lit(3))
    terms = {r.term: r.hidden_bits for r in privacy.revealing_terms(table).collect()}
    assert terms == pytest.approx(brute_terms([x for _, x in made]))
    assert set(terms) == {"zorblax", "quux"} and terms["zorblax"] <= 0.15 < terms["quux"]
    found = rows(privacy.spans(table.select("doc_id", "text")))
    assert found[900].spans == "term:0:7" and found[901].spans == "" and found[400].spans == "" and found[902].spans == "term:0:4"
    for few in (200, 1):
        clean = privacy.sanitise(table, few)
        assert clean.columns == table.columns and {(r._pii, r.terms, r.key, r.pii) for r in clean.collect()} == {(1, "mine", 2, 3)}
        by = rows(clean)
        assert by[0].text == "item 0  writes to [EMAIL] on day 0" and by[900].text == "" and by[None].text == "" and by[901].text == "zorblaxes stay"
        assert by[200].text == "Call [NAME] at [PHONE] or 0" and by[902].text == "[TERM], Zorblax4"
    odd = privacy.sanitise(make(ODD)).collect()
    assert len(odd) == len(ODD) and [r.text for r in odd if r.doc_id == 1] == [None]


# 5 language


def test_code_lengths_equal_a_plain_context_tree():
    texts = {"x": ["abab abba", "baba"], "y": ["caca acca abc"]}
    counts = {}
    for lang, held in texts.items():
        counts[lang] = collections.Counter()
        for t in held:
            b = language.normal(t).tolist()
            counts[lang].update(b[i] << 24 | b[i + 1] << 16 | b[i + 2] << 8 | b[i + 3] for i in range(len(b) - 3))
    trees = language.Trees({k: dict(v) for k, v in counts.items()})

    def seen_after(lang, context):
        seen = collections.Counter()
        for g, n in counts[lang].items():
            b = [g >> 24 & 255, g >> 16 & 255, g >> 8 & 255, g & 255]
            if b[3 - len(context) : 3] == context:
                seen[b[3]] += n
        return seen

    def bits(lang, context, s, without=()):
        if context is None:
            return np.log2(256 - len(without))
        seen = {x: n for x, n in seen_after(lang, context).items() if x not in without}
        shorter = context[1:] if context else None
        total, kinds = sum(seen.values()), len(seen)
        if s in seen:
            return -np.log2(seen[s] / (total + kinds))
        return bits(lang, shorter, s, {*without, *seen}) - (np.log2(kinds / (total + kinds)) if total else 0)

    for text in ("abba", "cab zq", "Ünder"):
        b = language.normal(text).tolist()
        for k, lang in enumerate(trees.languages):
            assert trees.lengths(text)[k] == pytest.approx(sum(bits(lang, b[i - 3 : i], b[i]) for i in range(3, len(b))), rel=1e-5)
    for context in (b"aba", b"  a", b"zzz", b"zca", b"b a"):
        every = np.array([int.from_bytes(context, "big") << 8 | x for x in range(256)])
        assert np.exp2(-trees.lengths_of(every)).sum(axis=0) == pytest.approx(1)


def test_trees_follow_what_was_seen():
    rng = np.random.default_rng(15)
    trees = language.Trees({f"l{k}": dict.fromkeys(rng.integers(0, 1 << 32, 5000).tolist(), 1) for k in range(10)})
    assert trees.bits.size <= 50_000 * 10 and sum(x.size for x in trees.counts.values()) <= 200_000 * 10


def test_language_accuracy_on_held_out_rows(docs, make, spark):
    found = rows(language.identify(docs))
    truth = {r.doc_id: r.lang for r in docs.collect()}
    held = [i for i in truth if zlib.crc32(str(i).encode()) % 4 == 2]
    assert all(found[i].held_out == (i in held) for i in truth)
    assert np.mean([found[i].lang_pred == truth[i] for i in held]) > 0.97
    odd = language.identify(make(ODD).withColumn("lang", F.lit(None).cast("string")))
    assert {r.lang_pred for r in odd.collect()} == {"und"}
    mixed = docs.select("doc_id", "text", "lang").unionByName(make([(-5, None), (-6, "123 !!"), (-7, "the of and")]).withColumn("lang", F.lit(None).cast("string")))
    found = rows(language.identify(mixed))
    assert (found[-5].lang_pred, found[-6].lang_pred, found[-7].lang_pred) == ("und", "und", "en") and found[-5].score == 0
    assert all(0 <= r.score <= 1 for r in found.values())
    assert language.identify(docs.limit(0)).count() == 0


# 6 HTML


def test_html_regions(spark):
    page = """<html><head><title>T</title><style>p{}</style><script>var a="</p>";</script></head><body>
    <header>Site <a href=/>home</a></header><nav><ul><li><a href=x>Menu</a></ul></nav><div class="cookie-notice">We use cookies on this site, accept them.</div>
    <main><article><h1>A &amp; B</h1><p>First   long paragraph with <b>bold</b> words and more of them.<br><p>Short.</p><p>Second long paragraph of the article &eacute; here, with enough text.</p>
    <aside>Aside text</aside><form><input value=x>Search</form><div id=comments><p>A reader comment that is quite long, as long as a paragraph.</p></div></article></main>
    <div class="ad">Buy now</div><footer>Imprint</footer></body></html>"""
    expected = "A & B\nFirst long paragraph with bold words and more of them.\nShort.\nSecond long paragraph of the article é here, with enough text."
    assert html_text.main_text(page) == expected
    assert html_text.main_text(page.split("<aside>")[0]) == expected
    plain = "<body><p>Only a paragraph, and not more.</body>"
    odd = [None, "", "no tags at all", "<", "<p", "<div>" * 3000 + "x", plain, "<script>never closed", "<!-- open", "<p>" + "long " * 50000]
    table = spark.createDataFrame([(i, "u", h) for i, h in enumerate(odd)] + [(0, "u", None)], "page_id long, url string, html string").withColumn("text", F.lit("mine"))
    found = {r.page_id: r for r in html_text.extract(table).collect()}
    assert [found[i].text for i in (0, 1, 2, 6, 7)] == ["", "", "no tags at all", "Only a paragraph, and not more.", ""]
    assert found[9].n_chars == len(found[9].text) == len(("long " * 50000).strip())
    assert html_text.extract(table.limit(0)).count() == 0


def test_html_on_the_pages(spark, small):
    import html as h

    for r in html_text.extract(spark.read.parquet(f"{small}/pages.parquet")).join(spark.read.parquet(f"{small}/pages.parquet").select("page_id", "html"), "page_id").collect():
        inside = r.html.split("<article>")[1].split("</article>")[0]
        blocks = [" ".join(h.unescape(re.sub(r"<[^>]+>", "", b.replace("<br>", " "))).split()) for b in re.split(r"</?(?:p|h1)>", inside)]
        assert r.text == "\n".join(b for b in blocks if b)


# 7 decontamination


def test_decontamination_blocks_and_odd_rows(spark, small, docs, make):
    items = spark.read.parquet(f"{small}/benchmark.parquet")
    whole, parts = (rows(decontaminate.scan(docs, items, n)) for n in (8_000_000, 3000))
    assert whole == parts
    odd_items = spark.createDataFrame([(1, "One"), (1, "one"), (2, None), (3, " !! "), (None, "lost words"), (4, "w " * 30)], "item_id long, text string")
    found = decontaminate.scan(make(ODD), odd_items).collect()
    assert len(found) == len(ODD)
    by = {r.doc_id: r for r in found}
    assert by[4].n_hit == 1 and by[4].contaminated and by[None].n_items == 1 and not by[1].contaminated and by[9].n_hit == 0
    assert decontaminate.scan(make(ODD), odd_items.limit(0)).where("contaminated").count() == 0
    assert decontaminate.scan(make([]), odd_items).count() == 0
    extra = docs.withColumn("n_hit", F.lit(1)).withColumn("contaminated", F.lit("x")).withColumn("_found", F.lit(2)).withColumn("digest", F.lit(3)).withColumn("a", F.lit(4)).withColumn("spans", F.lit(5))
    for n in (8_000_000, 3000):
        kept = decontaminate.keep_clean(extra, items, n)
        assert kept.columns == extra.columns and {(r.n_hit, r.contaminated, r._found, r.digest, r.a, r.spans) for r in kept.collect()} == {(1, "x", 2, 3, 4, 5)}
        assert {r.doc_id for r in kept.collect()} == {i for i, r in whole.items() if not r.contaminated}
    assert sorted(map(str, decontaminate.scan(make(ODD), odd_items, 20).collect())) == sorted(map(str, found))


def brute_hits(text, items):
    """(words, hit words) by comparing every window of every item with every place."""
    word = lambda x: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in x or ""))
    words, places = word(text), collections.defaultdict(list)
    windows = {tuple(w[i : i + 13]) for w in map(word, items) if w for i in range(max(1, len(w) - 12))}
    for size in {len(w) for w in windows}:
        for i in range(len(words) - size + 1):
            places[tuple(words[i : i + size])].append(i)
    return len(words), len({i + k for w in windows for i in places.get(w, ()) for k in range(len(w))})


# 8 repeats


def brute_repeats(held):
    """Rows (doc_id, text) judged each; a null doc_id comes after all others."""
    rank = lambda d: 1 << 62 if d is None else d
    held = [(d, (t or "").encode()) for d, t in held]
    first = {}
    for d, b in held:
        for i in range(len(b) - 49):
            first[b[i : i + 50]] = min(first.get(b[i : i + 50], 1 << 62), rank(d))
    out = []
    for d, b in held:
        gone = bytearray(len(b))
        for i in range(len(b) - 49):
            if first[b[i : i + 50]] < rank(d):
                gone[i : i + 50] = b"\1" * 50
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        out.append((d, len(b), sum(gone), sum(g and (i == 0 or not gone[i - 1]) for i, g in enumerate(gone)), hashlib.sha256(kept).hexdigest()))
    return sorted(map(str, out))


def found_repeats(table, **more):
    return sorted(str(tuple(r)) for r in repeats.remove_repeats(table, **more).collect())


def test_repeats_equal_brute_force(docs, make):
    rng = random.Random(4)
    base = ["".join(rng.choice("ab é") for _ in range(300)) for _ in range(4)]
    odd = [(5000, None), (5001, ""), (5002, "a" * 49), (5003, "a" * 50), (5004, "a" * 51), (5005, "a" * 4000), (5006, base[0]), (5007, base[0]), (5008, base[0][:99] + "X" + base[0][100:]), (5009, base[1][50:99]), (5010, base[1][50:100]), (5011, base[1]), (5012, base[2] * 3), (5013, base[2]), (5014, "q" + base[3][7:200] + base[0][9:120]), (5015, base[3])]
    table = docs.select("doc_id", "text").unionByName(make(odd))
    assert found_repeats(table) == brute_repeats([tuple(r) for r in table.collect()])
    assert repeats.remove_repeats(make([])).count() == 0
    more = make(odd).withColumn("key", F.lit("mine")).withColumn("n_bytes", F.lit(1)).withColumn("spans", F.lit(2))
    assert found_repeats(more) == brute_repeats(odd)


def test_repeats_of_null_and_repeated_ids(make):
    rng = random.Random(14)
    a, b, c = ("".join(rng.choice("abcd efgh") for _ in range(200)) for _ in range(3))
    held = [(1, a), (None, a), (None, b), (None, a[:80] + c), (None, b), (2, a[:80] + c), (2, b), (2, c), (3, c + b), (3, c + b), (4, None), (None, None)]
    assert found_repeats(make(held)) == brute_repeats(held)


def test_repeats_with_a_phrase_in_ever_new_surroundings(make):
    rng = random.Random(24)
    text = lambda n: "".join(rng.choice("abcdefghij klmnop") for _ in range(n))
    phrase, near = text(90), text(120)
    held = [(i, text(60) + phrase + text(60)) for i in range(60)] + [(100 + i, near[: 60 + i % 40] + text(40)) for i in range(40)] + [(200, phrase), (201, phrase[:49])]
    held += [(300 + i, text(20) + phrase[20:] + near[:30]) for i in range(6)] * 2
    assert found_repeats(make(held), hot_limit=8) == found_repeats(make(held)) == brute_repeats(held)


def test_run_index_holders_and_long_texts(monkeypatch):
    rng = random.Random(5)
    for _ in range(20):
        base = bytes(rng.choice(b"ab\0\xff") for _ in range(300))
        strings = list({base[i : i + rng.randint(50, 150)] if rng.random() < 0.7 else bytes([rng.choice(b"ab")]) * rng.randint(50, 150) for i in (rng.randint(0, 150) for _ in range(rng.randint(1, 25)))})
        docs = np.array([rng.randint(0, 50) for _ in strings])
        first = {}
        for s, d in zip(strings, docs.tolist(), strict=True):
            for i in range(len(s) - 49):
                first[s[i : i + 50]] = min(first.get(s[i : i + 50], 99), d)
        found, offsets = repeats.first_holders(strings, docs)
        assert np.array_equal(found, repeats.bounded_holders(strings, docs, 700)[0])
        for s, g in zip(strings, np.split(found, offsets[1:-1]), strict=True):
            assert g.tolist() == [first[s[i : i + 50]] for i in range(len(s) - 49)]
    strings = [b"abracadabra" * 20, b"abracadabrx" * 20, b"", b"abra"]
    index = repeats.RunIndex(strings)
    assert len(index.run_start) == len(index.run_end) == len(index.at) < sum(map(len, strings)) / 4
    rows = sorted((s[i:], k, index.begins[k] + i) for k, s in enumerate(strings) for i in range(len(s) + 1))
    above, statistic = index.streamed()
    for (x, _, p), (y, _, q) in zip(rows, rows[1:], strict=False):
        alike = next((i for i, (u, v) in enumerate(zip(x, y, strict=False)) if u != v), min(len(x), len(y)))
        assert (above[q], statistic[q]) == (p, alike)
    text = bytes(rng.choice(b"abc ") for _ in range(5000))
    whole = repeats.Segments([text])
    monkeypatch.setattr(repeats, "_CHUNK", 700)
    covered = [(o + s, w) for number, offset, parts in repeats._chunks([text, b"", b"x"]) for g in [repeats.Segments(parts)] for o, s, w in zip(offset[g.text].tolist(), g.start.tolist(), g.windows.tolist(), strict=True)]
    assert sum(w for _, w in covered) == int(whole.windows.sum()) == len(text) - 49


# 9 packing


def check_packing(table, held):
    library = Tokenizer.from_file(BYTES)
    placed, seen = collections.defaultdict(list), collections.defaultdict(list)
    for r in held:
        placed[r.sequence_id].append((r.offset, r.length))
        seen[r.doc_id].append(r)
    for x in placed.values():
        at = 0
        for offset, length in sorted(x):
            assert offset == at
            at += length
        assert at <= 1024
    for r in table.collect():
        ids = np.array(library.encode(r.text or "", add_special_tokens=False).ids + [2], "<u4")
        mine = [p for p in sorted(seen[r.doc_id], key=lambda p: p.piece)]
        if len({p.piece for p in mine}) == len(mine):
            assert sum(p.length for p in mine) == len(ids) and all(p.length == 1024 for p in mine[1:])
            assert all(zlib.crc32(ids[p.start : p.start + p.length].tobytes()) == p.ids_crc32 for p in mine)
    return len(placed)


def test_packing(docs, make):
    held = packing.pack(docs, BYTES).collect()
    n = check_packing(docs, held)
    assert n <= 1.02 * sum(r.length for r in held) / 1024 + 1
    odd = make(ODD + [(20, "x<|endoftext|>y  \n\n z"), (21, "tok " * 5000)])
    check_packing(odd, packing.pack(odd, BYTES).collect())
    assert packing.pack(make([]), BYTES).count() == 0


def test_plans_place_every_piece():
    rng = random.Random(6)
    for _ in range(30):
        sizes = collections.Counter(rng.choice([rng.randint(1, 1024), rng.randint(1, 60), 512, 1024]) for _ in range(rng.randint(1, 300)))
        fillings = packing.plan(dict(sizes))
        used = collections.Counter()
        for times, filling in fillings:
            assert sum(length * copies for length, copies in filling) <= 1024
            for length, copies in filling:
                used[length] += times * copies
        assert used == sizes
    assert sum(t for t, _ in packing.plan({600: 10, 424: 10, 300: 4, 124: 4})) == 12
    assert packing.plan({}) == []


def test_sums_are_indexed_and_follow_the_counts():
    rng = random.Random(16)
    counts = np.zeros(101, np.int64)
    counts[[rng.randint(1, 100) for _ in range(25)]] = 2
    sums = packing.Sums(counts)
    while (held := np.flatnonzero(sums.counts).tolist()):
        for k, index in enumerate((sums.one, sums.two, sums.three), 1):
            by_sum = collections.Counter(sum(x) for x in itertools.product(held, repeat=k))
            assert index.tolist() == [by_sum[total] for total in range(101)]
        for gap in range(1, 101):
            ways = [x for k in (1, 2, 3) for x in itertools.combinations_with_replacement(held, k) if sum(x) == gap and sums.times(collections.Counter(x))]
            found = sums.find(gap)
            assert (found is None) == (not ways) and (not ways or (sum(found.elements()) == gap and found.total() == len(ways[0])))
        sums.take(collections.Counter([rng.choice(held)]), 1)


def test_complements_do_no_worse_than_best_fit(docs):
    encoding = packing.encoder(open(BYTES, "rb").read())
    small = collections.Counter(b - a for r in docs.collect() for a, b in packing.cuts(len(packing.token_ids(r.text, encoding))))
    rng = random.Random(26)
    large = collections.Counter(min(1024, int(rng.lognormvariate(5.8, 0.9)) + 1) for _ in range(20000))
    for sizes in (small, large):
        counts = np.zeros(1025, np.int64)
        counts[list(sizes)] = list(sizes.values())
        assert sum(t for t, _ in packing.plan(sizes)) <= sum(t for t, _ in packing._best_fit(counts, 1024))
    full = sum(t for t, f in packing.plan(large) if sum(x * n for x, n in f) == 1024)
    assert full > 0.95 * sum(t for t, _ in packing.plan(large))


# 10 near duplicates


def plain_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in shingles]
    return sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h))


def groups_of(fp):
    """Numbers of the groups of some fingerprints, by a plain walk over all pairs."""
    near, group = np.bitwise_count(np.array(fp, np.uint64)[:, None] ^ np.array(fp, np.uint64)[None, :]) <= 3, [-1] * len(fp)
    for i in range(len(fp)):
        todo = [i] if group[i] < 0 else []
        while todo:
            k = todo.pop()
            if group[k] < 0:
                group[k] = i
                todo += np.flatnonzero(near[k]).tolist()
    return group


def brute_components(table):
    ids = [(r.doc_id, plain_fingerprint(r.text)) for r in table.collect()]
    roots, least = groups_of([f for _, f in ids]), {}
    for (i, _), r in zip(ids, roots, strict=True):
        if i is not None:
            least[r] = min(least.get(r, i), i)
    return sorted((str(i), f"{f:016x}", str(least.get(r))) for (i, f), r in zip(ids, roots, strict=True))


def test_near_duplicates_equal_brute_force(docs, make):
    for table in (docs.select("doc_id", "text"), make(ODD), make([(4, "a b c d"), (6, "x y z"), (6, "a b c d"), (7, "x y z"), (None, "only here")])):
        assert sorted((str(r.doc_id), r.fingerprint, str(r.component_id)) for r in simhash.near_duplicates(table).collect()) == brute_components(table)
    assert simhash.near_duplicates(make([])).count() == 0
    extra = docs.withColumn("fp", F.lit("mine")).withColumn("hash", F.lit(1)).withColumn("_key", F.lit(2)).withColumn("root", F.lit(3))
    kept = simhash.keep_one_each(extra)
    assert kept.columns == extra.columns and kept.count() == len({x[2] for x in brute_components(docs)})


def test_one_row_of_each_group_stays(make):
    x, y = "some words that are here", "quite another text, not alike"
    for held, expected in (
        ([(4, x), (6, x), (6, y), (4, x)], [(4, x), (6, y)]),
        ([(None, x), (None, x), (None, y), (9, y)], [(9, y), (None, x)]),
        ([(1, None), (2, ""), (3, x)], [(1, None), (3, x)]),
        ([], []),
    ):
        assert sorted(map(str, (tuple(r) for r in simhash.keep_one_each(make(held)).collect()))) == sorted(map(str, expected))


def test_shards_that_share_a_half_are_dealt_again(spark):
    rng = np.random.default_rng(18)
    wide = rng.integers(0, 1 << 32, 900, dtype=np.uint64)
    fp = np.concatenate([wide, wide << np.uint64(32) | np.uint64(77), wide[:300] ^ np.uint64(5), rng.integers(0, 1 << 64, 300, dtype=np.uint64), np.arange(900, dtype=np.uint64)])
    fp = np.unique(fp)
    table = spark.createDataFrame([(int(i), int(f)) for i, f in enumerate(fp.view(np.int64).tolist())], "doc_id long, fp long")
    expected = groups_of(fp.tolist())
    at = {int(f): i for i, f in enumerate(fp.view(np.int64).tolist())}
    for sizes in ({"shard_rows": 64, "hot_rows": 128}, {}):
        assert {at[r.fp]: r.component_id for r in simhash.link_components(table, **sizes).collect()} == dict(enumerate(expected))


def test_fingerprints_use_sparks_hash(spark):
    h = [r[0] & (1 << 64) - 1 for r in spark.createDataFrame([("a b c",), ("b c é",)], "s string").select(F.xxhash64("s")).collect()]
    bits = sum(1 << k for k in range(64) if sum(x >> k & 1 for x in h) * 2 > 2)
    assert simhash.fingerprint("A\tb  C\né") == bits and simhash.fingerprint(None) == 0


def test_trees_lose_no_pair():
    rng = np.random.default_rng(8)
    fp = rng.integers(0, 1 << 64, 3000, dtype=np.uint64)
    near = fp[:600] ^ (np.uint64(1) << rng.integers(0, 64, 600).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 600).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 600).astype(np.uint64))
    fp = np.unique(np.concatenate([fp, near]))
    group, exact = simhash.Forest(len(fp)), simhash.Forest(len(fp))
    exact.join(*np.nonzero(np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 3))
    for k in (0, 1):
        half = (fp >> np.uint64(32 * k)).astype(np.uint32)
        index, shard, home = simhash.Tree(half[:500], 4, k).route(half, 1)
        for leaf in np.unique(shard):
            mine = index[shard == leaf]
            roots = simhash.shard_links(fp[mine], home[shard == leaf], k, leaf=16)
            group.join(mine, mine[roots])
    assert np.array_equal(group.roots(), exact.roots())


# columns of other names


def test_other_columns_do_not_matter(spark, small, docs, make):
    more = make(ODD).withColumn("rank", F.lit("x")).withColumn("length", F.lit(1)).withColumn("n_tokens", F.lit("y")).withColumn("task", F.lit(2)).withColumn("score", F.lit(3))
    plain = lambda df: sorted(map(str, df.collect()))
    assert plain(token_counts.token_counts(more, WORDS)) == plain(token_counts.token_counts(make(ODD), WORDS))
    assert packing.pack(more, BYTES).count() == packing.pack(make(ODD), BYTES).count()
    assert plain(simhash.near_duplicates(more)) == plain(simhash.near_duplicates(make(ODD)))
    assert plain(language.identify(more.withColumn("lang", F.lit("q")))) == plain(language.identify(make(ODD).withColumn("lang", F.lit("q"))))
    talks = spark.read.parquet(f"{small}/conversations.parquet").limit(50)
    named = talks.withColumn("formatted", F.lit(1)).withColumn("escaped_turns", F.lit("x")).withColumn("n_turns", F.lit(2)).withColumn("turns", F.lit(3))
    assert plain(chat.read_back(chat.format_conversations(named))) == plain(chat.read_back(chat.format_conversations(talks)))


# pipeline


def brute_clean(text, terms):
    """A text with base matches and revealing terms replaced."""
    marks = [(a, rank, b, f"[{k.upper()}]") for rank, (k, _) in enumerate(PII) for m in brute_pii(text).split(",") if m.startswith(f"{k}:") for a, b in [map(int, m.split(":")[1:])]]
    for m in regex.finditer(r"(?<![\p{L}\p{N}])(?:" + ("|".join(terms) or r"(?!)") + r")(?![\p{L}\p{N}])", text, regex.IGNORECASE):
        marks.append((m.start(), 9, m.end(), "" if terms[m.group().lower()] <= 0.15 else "[NAME]" if m.group()[0].isupper() else "[TERM]"))
    out, at = "", 0
    for a, _, b, label in sorted(marks):
        if b > at:
            out, at = out + text[at : max(at, a)] + (label if a >= at else ""), b
    return out + text[at:]


def test_pipeline_equals_its_stages_by_brute_force(spark, small, docs, make):
    import corpus_pipeline

    held = [(r.doc_id, r.text) for r in docs.collect()]
    labels = [(r.doc_id, r.quality) for r in spark.read.parquet(f"{small}/labels.parquet").collect()]
    kept = {i for i, _, good in brute_scores(held, {i for i, q in labels if q == 1}) if good}
    stage = [x for x in held if x[0] in kept]
    alone = {x[2] for x in brute_components(make(stage))}
    stage = [x for x in stage if str(x[0]) in alone]
    items = [r.text for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    hits = {i: brute_hits(text, items) for i, text in stage}
    dirty = {i for i, (n, hit) in hits.items() if hit and 20 * hit >= n}
    stage = [x for x in stage if x[0] not in dirty]
    terms = brute_terms([text or "" for _, text in stage])
    clean = [(i, brute_clean(text, terms)) for i, text in stage]
    assert clean != stage and dirty and len(alone) < len(kept)
    out = corpus_pipeline.run(spark, small).collect()
    assert {r.doc_id for r in out} == {i for i, _ in clean}
    check_packing(make(clean), out)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "simhash_near_dedup", "benchmark_decontamination", "pii", "best_fit_packing"]
