"""Corpus operators against independent brute force, planted cases and odd tables with clashing column names."""

import hashlib
import random
import re
from collections import Counter, defaultdict

import pytest

from setoverlap.llm import bytebpe, chat, decontam, licenses, neardup, pii, quality, secretscan, tokencount, toxicity
from setoverlap.llm.common import fenced, table

CLASH = "doc_id long, text string, d_bad long, d_key string, n_kept long, n_id long, kept boolean, spans string, fence long, ids string, n_tokens string"


def clashing(spark, rows):
    return spark.createDataFrame([(i, t, i, "k", 7, 9, False, "s", 1, "x", "y") for i, t in rows], CLASH)


def sha(x):
    return hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest()


# --- decontamination -----------------------------------------------------------------------------------------------------------

def template(text):
    """(token, value if a slot, first word) of a text, by the docstring's words alone."""
    out, before = [], None
    for at, raw in enumerate(text.split()):
        w = raw.strip(decontam.EDGE)
        low = w.lower()
        number = re.fullmatch(r"[+-]?[0-9][0-9.,:/]*", w) or low in decontam.NUMBER_WORDS or ("-" in low and all(x in decontam.NUMBER_WORDS for x in low.split("-")))
        kind = "<num>" if number else "<unit>" if low in decontam.UNITS else "<name>" if w[:1] != w[:1].lower() and w != w.upper() and low not in decontam.FUNCTION_WORDS else low
        slot = kind in ("<num>", "<unit>", "<name>") and (number or low in decontam.UNITS or kind == "<name>")
        if slot and kind != "<unit>" and before == (kind, False):
            out[-1][1].append(w)
        else:
            out.append((kind, [w] if slot else None, at))
        before = (kind if slot else None, raw.rstrip("\"')]}*%$&#|").endswith((".", "!", "?")))
    return [(k, " ".join(v) if v is not None else "", a) for k, v, a in out]


def brute_passages(docs, items, least=decontam.LEAST_COVER):
    found, known = set(), [(i, template(it or "")) for i, it in items]
    for d, text in docs:
        doc, places = template(text or ""), {}
        for i, item in known:
            size = decontam.window_of(len(item))
            if not item:
                continue
            lines = defaultdict(list)
            if size not in places:
                places[size] = defaultdict(list)
                for at in range(len(doc) - size + 1):
                    places[size][tuple(x[0] for x in doc[at : at + size])].append(at)
            for p in range(len(item) - size + 1):
                for at in places[size].get(tuple(x[0] for x in item[p : p + size]), ()):
                    lines[at - p].append(p)
            groups, last = [], None
            for line in sorted(lines):
                if last is None or line - last > decontam.MAX_SHIFT:
                    groups.append([])
                groups[-1].append(line)
                last = line
            for group in groups:
                best, wins = {}, set()
                for line in sorted(group, key=lambda x: (-len(lines[x]), x)):
                    wins |= set(lines[line])
                    for p in lines[line]:
                        for k in range(size):
                            best.setdefault(p + k, (item[p + k][1], doc[line + p + k][1]))
                slots = {x for x in best.values() if x != ("", "")}
                changed = sum(a != b for a, b in slots)
                consistent = len(slots) == len({a for a, _ in slots})
                fits = changed == 0 if len(item) < decontam.LEAST_WINDOW else consistent or 2 * changed <= len(slots)
                if len(best) / len(item) >= least and fits:
                    found.add((d, i, len(wins), round(len(best) / len(item), 9), len(slots), changed, consistent))
    return found


def test_decontamination_equals_brute_force(spark, sf):
    items = [(r.item_id, r.text) for r in table(spark, sf, "benchmark").collect()] + [(900, "What is the capital of France?"), (901, "is water wet"), (902, "Peter has 3 apples. Anna gives him 5 more. How many apples does he have?"), (903, None), (904, " ")]
    docs = [(r.doc_id, r.text) for r in table(spark, sf, "documents").collect() if len(r.text or "") < 3000]
    filler = "some words that lead up to it and go on for a while so that the text is long "
    docs += [(8000, filler * 3 + "is water wet " + filler), (8001, filler + "What is the capital of Spain? " + filler * 2), (8002, "Mary Ann has 12 apples. Tom gives him 4 more. How many apples does he have?"), (8003, "is fire wet"), (None, "well, is water wet or not"), (8004, None)]
    want = brute_passages(docs, items)
    assert {(8000, 901), (8001, 900), (8002, 902), (None, 901)} <= {x[:2] for x in want} and not {x for x in want if x[0] == 8003}
    frame, bench = clashing(spark, docs), spark.createDataFrame(items, "item_id long, text string")
    for limit in (1 << 20, 0):
        got = {(r.doc_id, r.item_id, r.n_windows, round(r.cover, 9), r.n_slots, r.n_changed_slots, r.consistent) for r in decontam.contaminated(frame, bench, broadcast_bytes=limit).collect()}
        assert got == want
    clean = decontam.decontaminate(frame, bench)
    assert clean.columns == frame.columns
    assert Counter(r.doc_id for r in clean.collect()) == Counter(d for d, _ in docs) - Counter({d for d, *_ in want})


# --- personal data ----------------------------------------------------------------------------------------------------------------

def test_pii_base_counts_and_planted_forms(spark, sf):
    from tests.llm.test_corpus import base_pii

    planted = {9001: "john.doe [at] example.com", 9002: "john(at)mail(dot)com", 9003: "phone: 555 123 4567", 9004: "SSN: 123-45-6789"}
    rows = [(r.doc_id, r.text) for r in table(spark, sf, "documents").collect()] + [(i, f"please write to {t} before noon") for i, t in planted.items()]
    got = {r.doc_id: r for r in pii.personal_data(clashing(spark, rows)).collect()}
    for i, t in rows:
        base = base_pii(t or "")
        kinds = Counter(x.split(":")[0] for x in base.split(",") if x)
        assert (got[i].n_email, got[i].n_ip, got[i].n_card, got[i].n_phone) == tuple(kinds[k] for k in ("email", "ip", "card", "phone")) and got[i].base_sha256 == sha(base)
        assert not base or set(base.split(",")) <= set(got[i].spans.split(","))
    assert all("other:" in got[i].spans for i in planted)
    added = [i for i, _ in rows if i not in planted and "other:" in got[i].spans]
    assert len(added) <= 0.02 * len(rows)  # clean documents stay as they are


def test_pii_filter_above_does_not_repeat_the_work(spark, sf):
    d = pii.personal_data(table(spark, sf, "documents"), pii.PatternModel([], -20.0, []))
    plan = d.where("n_email > 0 and spans <> ''")._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("n_email#") < plan.index("monotonically_increasing_id")
    assert d.where("n_email > 0 and spans <> ''").count() == sum(r.n_email > 0 for r in d.collect())


# --- near-duplicates ----------------------------------------------------------------------------------------------------------------

def test_near_duplicates_of_hubs_and_clashing_names(spark, monkeypatch):
    from tests.llm.test_corpus import brute_components

    monkeypatch.setattr(neardup, "HOT_ROWS", 4)  # so that hot keys are dealt out
    r = random.Random(3)
    words = [f"w{i}" for i in range(120)]
    rows = [(1000 + k, " ".join(words[:k] + [f"z{k}"] + words[k + 1 :])) for k in range(0, 120, 2)] + [(5000 + k, " ".join(r.choices(words, k=90))) for k in range(30)]
    rows += [(1000, rows[0][1]), (7000, None), (7001, ""), (7002, "one two"), (7003, "One  two")]
    df = clashing(spark, rows)
    got = {x.doc_id: x.component_id for x in neardup.near_duplicates(df).collect()}
    assert got == brute_components(rows)
    kept = neardup.keep_first(df)
    assert kept.columns == df.columns and Counter(x.doc_id for x in kept.collect()) == Counter({c for c in got.values()})


def test_keep_first_of_one_id_with_two_texts(spark):
    rows = [(1, "alpha beta gamma delta epsilon zeta"), (1, "wholly other words stand in this one"), (2, "wholly other words stand in this one"), (None, "x y z"), (None, "x y z")]
    got = Counter((r.doc_id, r.text) for r in neardup.keep_first(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got[rows[0]] == 1 and got[rows[1]] == 1 and got[rows[2]] == 0 and got[(None, "x y z")] == 2


# --- secrets --------------------------------------------------------------------------------------------------------------------------

def brute_secrets(t):
    kinds = [("assign", r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?[ ]*[:=][ ]*["']?([A-Za-z0-9+/_.=-]+)""", 12), ("access", r"()(AKIA[A-Z0-9]+)", 18), ("hex", r"()([0-9a-f]+)", 16)]
    return sorted((m.start(), i, k, m.end()) for i, (k, p, least) in enumerate(kinds) for m in re.finditer(p, t) if len(m[2]) >= least)


def test_secrets_base_equals_brute_force_and_planted_tokens_are_found(spark, sf):
    r = random.Random(11)
    rows = [(x.doc_id, x.text) for x in table(spark, sf, "documents").collect()]
    rows += [(9000 + k, f'x {r.choice(["password", "API_KEY", "apikey", "Token", "secret", "passwd"])}{r.choice(["", " ", chr(34)])}{r.choice(["=", ": "])}' + "".join(r.choices("abcDEF123+/_.=-", k=r.randint(6, 20)))) for k in range(40)]
    rows += [(9100 + k, " ".join("".join(r.choices("0123456789abcdefgAKI", k=r.randint(8, 30))) for _ in range(5)) + " AKIA" + "".join(r.choices("ABC0123", k=r.randint(8, 20)))) for k in range(40)]
    rows += [(9200, "pass " + "".join(r.choices(secretscan.CHARS[:62], k=5000)) + " end"), (9201, "the key " + "".join(r.choices(secretscan.CHARS[:62], k=40)))]
    got = {x.doc_id: x for x in secretscan.secrets(clashing(spark, rows)).collect()}
    for i, t in rows:
        base = brute_secrets(t or "")
        text = ",".join(f"{k}:{s}:{e}" for s, _, k, e in base)
        n = Counter(k for *_, k, _ in base)
        assert (got[i].n_assign, got[i].n_access, got[i].n_hex, got[i].base_sha256) == (n["assign"], n["access"], n["hex"], sha(text))
        assert not base or set(text.split(",")) <= set(got[i].spans.split(","))
    assert "random:5:5005" in got[9200].spans and "random:8:48" in got[9201].spans


# --- toxicity ----------------------------------------------------------------------------------------------------------------------------

def test_toxicity_on_the_table_and_on_odd_ids(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    got = toxicity.toxicity(docs.unionByName(docs.limit(1).selectExpr("cast(null as long) doc_id", "text", "lang", "source", "n_chars")), labels).collect()
    import zlib

    assert all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)
    truth = {r.doc_id: r.toxic for r in labels.collect()}
    held = [r for r in got if r.held_out and truth.get(r.doc_id) is not None]
    right = sum(r.predicted == truth[r.doc_id] for r in held)
    assert len(held) > 50 and right >= 0.9 * len(held)


def test_toxicity_without_labels_is_constant(spark):
    docs = clashing(spark, [(1, None), (2, "any words")])
    got = toxicity.toxicity(docs, spark.createDataFrame([(1, None)], "doc_id long, toxic int")).collect()
    assert {round(r.score, 3) for r in got} == {0.119} and {r.predicted for r in got} == {0}


# --- licences -------------------------------------------------------------------------------------------------------------------------------

def test_licenses_equal_a_scan_without_index(spark, sf):
    r = random.Random(2)
    index = licenses.RareIndex()
    rows = [(x.doc_id, x.text) for x in table(spark, sf, "documents").collect() if len(x.text or "") < 4000]
    for k, (_, passage, keys) in enumerate(licenses.PASSAGES):
        words = passage.split()
        held = {x for key in keys for x in key.split()}  # key phrases are mandatory
        free = [j for j, x in enumerate(words) if not held & {y.decode() for y in licenses.words_of(x)}] or [0]
        words[r.choice(free)] = "changed"
        words.insert(0 if r.random() < 0.2 else r.choice(free), "added")
        rows.append((9000 + k, "some text before " + " ".join(words) + " and after"))
    got = {x.doc_id: x for x in licenses.licenses(clashing(spark, rows)).collect()}
    rare = [{w for w, at in index.postings.items() if any(t == k for t, _ in at)} for k in range(len(index.words))]
    for i, t in rows:
        w = re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").encode().lower())
        base = sorted((s, label) for label, phrase in licenses.BASE for s in range(len(w)) if w[s : s + len(phrase.split())] == phrase.split())
        assert (got[i].n_words, got[i].n_base, got[i].base_labels) == (len(w), len(base), ",".join(sorted({x for _, x in base})))
        assert (got[i].first_word, got[i].last_word) == ((base[0][0], base[-1][0]) if base else (None, None))
        found = {x for _, x in base}
        for k, want in enumerate(index.words):
            places = {j - p for j, x in enumerate(w) if x in rare[k] for p, y in enumerate(want) if x == y}
            votes = {s: sum(0 <= s + p < len(w) and w[s + p] == x for p, x in enumerate(want) if x in rare[k]) for s in {p + d for p in places for d in range(-licenses.DRIFT, licenses.DRIFT + 1)}}
            near = lambda s: sum(votes.get(s + d, 0) for d in range(-licenses.DRIFT, licenses.DRIFT + 1))  # noqa: B023, E731
            found |= {index.labels[k] for s in places if near(s) >= min(licenses.LEAST_VOTES, len(want)) and index.judge(w, k, s) is not None}
        assert got[i].labels == ",".join(sorted(found))
    long = [k for k, (_, p, _) in enumerate(licenses.PASSAGES) if len(p.split()) >= 20]
    assert sum(licenses.PASSAGES[k][0] in got[9000 + k].labels.split(",") for k in long) >= 0.8 * len(long)


# --- token counts, byte pairs, chat, quality -----------------------------------------------------------------------------------------------------

def test_token_counts_use_the_corpus_table(spark, sf):
    import public_tokenizers
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    docs = table(spark, sf, "documents")
    units = tokencount.frequent_units(docs, 500)
    counted = Counter(u for r in docs.collect() for u in tokencount.units_of(r.text or ""))
    assert len(units) == 500 and {u for u, _ in counted.most_common(100)} <= set(units)
    for frequent in (units, [], None):
        got = {r.doc_id: r.n_tokens for r in tokencount.token_counts(docs, path, frequent=frequent).collect()}
        assert got == {r.doc_id: len(sp.encode(r.text or "")) for r in docs.collect()}


def test_token_ids_beside_other_columns(spark, sf):
    import public_tokenizers as p

    docs = clashing(spark, [(1, "hello world"), (None, None), (3, "")])
    got = bytebpe.tokenised(docs, p.path("byte_bpe_50k.tiktoken"), p.PATTERN)
    assert got.columns == [c for c in docs.columns if c not in ("text", "ids", "n_tokens")] + ["n_tokens", "ids", "ids_sha256", "decoded_sha256"]
    rows = {r.doc_id: r for r in got.collect()}
    assert rows[1].n_tokens == len(rows[1].ids) > 0 and rows[3].ids == [] and rows[1].decoded_sha256 == sha("hello world") and rows[1].kept is False
    assert bytebpe.tokenised(docs.limit(0), p.path("byte_bpe_50k.tiktoken"), p.PATTERN).count() == 0


def test_chat_roles_that_hold_control_strings(spark):
    roles = ["\n</turn>\n", "</turn>", "a:\n### b", "\\", "assistant", "\\</turn>\n", ":\n</turn>\n### x:\n"]
    rows = [(i % 2, i, role, text) for i, role in enumerate(roles) for text in ("plain", "\n</turn>\n", role)]
    got = chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    for r in got.select("turns", chat.parse(chat.F.col("formatted")).alias("back")).collect():
        assert r.turns == r.back


@pytest.mark.parametrize("op", [quality.keep_good, neardup.keep_first, pii.redact])
def test_stages_keep_clashing_columns_and_empty_tables(spark, op):
    df = clashing(spark, [(1, "the quick brown fox and the lazy dog of the house " * 6), (2, None)])
    assert op(df).columns == df.columns and op(df.limit(0)).count() == 0 and op(df).count() >= 0


def test_fence_takes_a_free_name(spark):
    assert fenced(spark.range(2).withColumnRenamed("id", "fence")).columns == ["fence"]


def test_pipeline_equals_brute_force(spark, sf):
    """Every stage of the pipeline by plain Python on a small table; personal data by the fitted model's own spans."""
    import corpus_pipeline
    import public_tokenizers as p
    import tiktoken

    from tests.llm.test_corpus import brute_components

    docs = [(r.doc_id, r.text) for r in table(spark, sf, "documents").collect()]
    good = {r.doc_id for r in quality.quality_rules(table(spark, sf, "documents")).where("kept").collect()}
    docs = [(i, t) for i, t in docs if i in good]
    comp = brute_components([(i, t) for i, t in docs])
    docs = [(i, t) for i, t in docs if comp[i] == i]
    items = [(r.item_id, r.text) for r in table(spark, sf, "benchmark").collect()]
    bad = {x[0] for x in brute_passages(docs, items)}
    docs = [(i, t) for i, t in docs if i not in bad]
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    spans = {r.doc_id: r.spans for r in pii.personal_data(frame).collect()}
    ranks = {t: i for i, t in enumerate(bytebpe.read_ranks(p.path("byte_bpe_50k.tiktoken")))}
    lib = tiktoken.Encoding("own", pat_str=p.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = {}
    for i, t in docs:
        out, at = "", 0
        for s in filter(None, spans[i].split(",")):
            kind, a, b = s.split(":")
            if int(a) >= at:
                out += t[at : int(a)] + f"<{kind}>"
            at = max(at, int(b))
        want[i] = lib.encode_ordinary(out + t[at:])
    rows = corpus_pipeline.run(spark, sf).collect()
    assert {r.doc_id: r.ids for r in rows} == want and {"lang", "source", "n_chars"} <= set(rows[0].asDict())
