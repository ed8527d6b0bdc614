"""The ten operators against brute force, exact round trips and edge cases."""

import hashlib
import math
import random
import time
import zlib
from collections import Counter

import numpy as np
import pytest

from corpus_tilt.llm import chat_format as C
from corpus_tilt.llm import line_dedup as L
from corpus_tilt.llm import packing as P
from corpus_tilt.llm.common import encoder, tokenizer_path
from corpus_tilt.llm.decontaminate import best_in, budget_of, contaminated
from corpus_tilt.llm.lm_scoring import cross_entropy_difference
from corpus_tilt.llm.near_dedup import near_duplicates, shingle_sets
from corpus_tilt.llm import ngram_model as N
from corpus_tilt.llm.quality_rules import quality, text_counts
from corpus_tilt.llm.token_count import count_tokens
from corpus_tilt.llm.token_output import PerfectHash, lookup, read_tokens, token_digest, write_tokens
from corpus_tilt.llm.warc import MAGIC, read_warc, record_links, sha1_base32, write_warc

EDGE = [(1, "a b c d"), (2, None), (3, ""), (4, "  \n\n"), (5, "a b c d"), (None, "a null id"), (7, "x" * 5000), (7, "again"), (8, "été 👍 <|endoftext|> don't\r\n\tstop ")]
BYTE = tokenizer_path("byte_bpe_50k.json")
WORD = tokenizer_path("word_bpe_49k.json")


def frame(spark, rows=EDGE, extra=True):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return df.selectExpr("doc_id", "text", "'en' as lang", "1 as n_tokens", "2 as component_id", "'k' as key", "3 as n") if extra else df


def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string")


def levenshtein(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def anywhere(p, t):
    row = [0] * (len(t) + 1)
    for i, x in enumerate(p, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(t, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return min(row)


def noisy(rng, text, edits, letters="abcde "):
    s = list(text)
    for _ in range(edits):
        i = rng.randrange(len(s))
        kind = rng.randrange(3)
        if kind == 0:
            s[i] = rng.choice(letters)
        elif kind == 1:
            s.insert(i, rng.choice(letters))
        elif len(s) > 1:
            del s[i]
    return "".join(s)


# --- 1 ------------------------------------------------------------------------------------------


def test_bit_parallel_distance():
    rng = random.Random(0)
    for _ in range(300):
        p = "".join(rng.choice("ab") for _ in range(rng.randint(1, 12)))
        t = "".join(rng.choice("ab") for _ in range(rng.randint(0, 30)))
        assert best_in(p, t)[0] == anywhere(p, t)


def test_decontamination_finds_all_within_budget(spark):
    rng = random.Random(1)
    item = "".join(rng.choice("abcdefghij ") for _ in range(200)).strip()
    budget = budget_of(len(" ".join(item.split())), 0.08, 12)
    docs, want = [], {}
    for i in range(40):
        put = noisy(rng, item, i)
        text = " ".join(("".join(rng.choice("klmnop ") for _ in range(300)) + " " + put + " " + "".join(rng.choice("klmnop ") for _ in range(200))).lower().split())
        docs.append((i, text))
        want[i] = anywhere(" ".join(item.split()), text)
    bench = spark.createDataFrame([(9, item), (10, None), (11, "")], "item_id long, text string")
    got = {r["doc_id"]: r["distance"] for r in contaminated(frame(spark, docs + EDGE[1:4]), bench).collect()}
    assert got == {i: d for i, d in want.items() if d <= budget}
    assert contaminated(empty(spark), bench).count() == 0
    assert contaminated(frame(spark), bench.limit(0)).count() == 0
    short = spark.createDataFrame([(1, "the"), (2, "x-ray")], "item_id long, text string")
    texts = frame(spark, [(1, "other words, lathe"), (2, "of the x-ray"), (3, "THE"), (4, "x-rays"), (None, "(the)")])
    assert {(r["doc_id"], r["item_id"]) for r in contaminated(texts, short).collect()} == {(2, 1), (2, 2), (3, 1), (None, 1)}


# --- 2 ------------------------------------------------------------------------------------------


def test_packing_is_whole_and_tight(spark):
    rng = random.Random(2)
    docs = [(i, " ".join(rng.choice(["cat", "dog", "stone", "river"]) for _ in range(rng.randint(1, 60)))) for i in range(300)]
    rows = P.pack(P.token_pieces(frame(spark, docs + EDGE), WORD, 1, 64), 64, shard_items=120).collect()
    enc, seen = encoder(WORD), Counter()
    for key, text in docs + EDGE:
        ids = enc.ids(text) + (1).to_bytes(4, "little")
        for i in range(0, len(ids), 256):
            seen[key, i // 256, i // 4, len(ids[i : i + 256]) // 4, zlib.crc32(ids[i : i + 256])] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == seen
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for placed in by.values():
        at = 0
        for offset, length in sorted(placed):
            assert offset == at
            at += length
        assert at <= 64
    sizes = [r["length"] for r in rows]
    assert len(by) <= len(P._fit(sizes, 64, [], list(range(len(sizes))))) + 3  # against one pool, a sequence a shard at most is lost
    assert P.pack(P.token_pieces(empty(spark), WORD, 1, 64), 64).count() == 0


def test_genetic_steps_keep_items():
    rng = random.Random(3)
    sizes = [rng.choice([34, 33, 21, 50, 29, 66]) for _ in range(120)]
    people = P.first_population(sizes, 100, rng, 4)
    for _ in range(20):
        child = P.mutate(sizes, 100, P.crossover(sizes, 100, people[0], people[1], rng), rng)
        assert sorted(i for b in child for i in b) == list(range(120)) and all(sum(sizes[i] for i in b) <= 100 for b in child)
    bound = -(-sum(sizes) // 100)
    before = max(P.fitness(sizes, 100, p) for p in people)
    after = P.evolve(sizes, 100, people, bound, rng, 30)
    assert P.fitness(sizes, 100, after[0]) >= before


# --- 3 ------------------------------------------------------------------------------------------


def brute_classes(docs, words, percent):
    sets = {}
    for key, text in docs:
        w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").encode().split()
        sets[key] = {tuple(w[i : i + words]) for i in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())
    top = {k: k for k in sets}
    keys = sorted(sets)
    for i, a in enumerate(keys):
        for b in keys[i + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * len(sets[a] | sets[b]) and top[a] != top[b]:
                lo, hi = sorted((top[a], top[b]))
                top = {k: lo if t == hi else t for k, t in top.items()}
    return {k: (len(sets[k]), top[k]) for k in keys}


@pytest.mark.parametrize("small", [48, 4])
def test_near_duplicates_like_brute_force(spark, small):
    rng = random.Random(4)
    vocab = [f"w{i}" for i in range(400)]
    docs, n = [], 0
    for _ in range(12):
        base = [rng.choice(vocab) for _ in range(rng.randint(3, 90))]
        for _ in range(rng.choice([1, 2, 9, 20])):
            w = list(base)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = rng.choice(vocab)
            docs.append((n, " ".join(w)))
            n += 1
    docs += [(n, None), (n + 1, ""), (n + 2, "one two"), (n + 3, "One  two"), (n + 4, " \n")]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_duplicates(frame(spark, docs), words=3, percent=85, small=small if small > 8 else 12, levels=2).collect()}
    assert got == brute_classes(docs, 3, 85)


def test_undivided_nodes_are_compared_whole(spark):
    """Distinct near copies around one original that is not the least id; 400 share a text just under the threshold, with linked pairs among them."""
    rng = random.Random(12)
    base = [f"b{i}" for i in range(200)]

    def exchanged(w, places, tag):
        out = list(w)
        for i in places:
            out[i] = f"{tag}x{i}"
        return " ".join(out)

    docs = [(1000 + i, exchanged(base, rng.sample(range(2, 198, 4), 4), i)) for i in range(250)] + [(5000, " ".join(base))]
    other = [f"c{i}" for i in range(200)]
    for i in range(400):
        far = exchanged(other, rng.sample(range(2, 198, 4), 6), f"p{i // 2 if i < 40 else i}").split()
        docs.append((10_000 + rng.randrange(100) + 100 * i, " ".join(far) if i % 2 == 0 or i >= 40 else exchanged(docs[-1][1].split(), [190], i)))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_duplicates(frame(spark, docs), words=3, percent=85).collect()}
    assert got == brute_classes(docs, 3, 85)


def test_a_template_family_loses_no_link(spark):
    """All texts share a template just under the threshold; pairs among them are over it."""
    rng = random.Random(19)
    base = [f"t{i}" for i in range(300)]

    def exchanged(w, places, tag):
        out = list(w)
        for i in places:
            out[i] = f"{tag}x{i}"
        return out

    docs, want = [], {}
    for i in range(600):
        own = exchanged(base, rng.sample(range(2, 298, 5), 9), i)
        key = 10_000 + 7 * i
        docs.append((key, " ".join(own)))
        want[key] = key
        if i < 100:
            docs.append((key + 3, " ".join(exchanged(own, rng.sample(range(4, 298, 5), 4), f"q{i}"))))
            want[key + 3] = key
    rng.shuffle(docs)
    got = {r["doc_id"]: r["component_id"] for r in near_duplicates(frame(spark, docs), words=3, percent=85).collect()}
    assert brute_links(docs[:60]) and got == want


def brute_links(docs):
    """The family is as meant: below 0.85 across, above within pairs."""
    sets = {k: set(shingle_sets([t], 3)[0].tolist()) for k, t in docs}
    like = lambda a, b: len(a & b) / len(a | b)
    return all((like(x, y) >= 0.85) == (abs(a - b) == 3) for a, x in sets.items() for b, y in sets.items() if a != b)


def test_rows_that_repeat_an_id_are_linked_by_one_text(spark):
    words = [f"w{i}" for i in range(60)]
    rows = [(1, " ".join(words)), (1, "something else altogether of many words here"), (5, " ".join([*words[:59], "other"])), (9, "something else altogether of many words here")]
    got = [sorted((r["doc_id"], r["component_id"], r["version"]) for r in near_duplicates(frame(spark, rows).repartition(n), words=3, percent=85).collect()) for n in (1, 3)]
    assert got[0] == got[1] and len(got[0]) == 4


def test_near_duplicates_edges(spark):
    rows = near_duplicates(frame(spark)).collect()
    assert len(rows) == len(EDGE) and all(r["kept"] for r in rows if r["doc_id"] != 5)
    assert {r["doc_id"]: r["component_id"] for r in rows}[5] == 1
    assert near_duplicates(empty(spark)).count() == 0
    assert [len(s) for s in shingle_sets(["a b c", "A B c", None, "x"], 3)] == [1, 1, 0, 1]


# --- 4 ------------------------------------------------------------------------------------------


def test_escape_is_reversible():
    rng = random.Random(5)
    parts = [*C.CONTROL, "\\", "<", "[", "s>", "a", "é", "|"]
    for _ in range(3000):
        text = "".join(rng.choice(parts) for _ in range(rng.randint(0, 8)))
        told = C.escape(text)
        assert C.unescape(told) == text and not any(c in told for c in C.CONTROL)


def test_chat_round_trip(spark):
    rng = random.Random(6)
    rows = [(c, t, rng.choice(["user", "assistant", "system", None, "<|turn|>"]), rng.choice(["hi", None, "", "</s>[INST] ok", "été \\ <|done|>", "x " * 50])) for c in range(6) for t in range(rng.randint(1, 9))]
    rows += [(9, t, "assistant" if t % 2 else "user", f"line {t}") for t in range(500)] + [(None, 0, "user", "q"), (None, None, "assistant", "a")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(5)
    got = {r["conv_id"]: r for r in C.read_chats(*C.format_chats(df, BYTE), BYTE).collect()}
    by = {}
    for c, t, role, text in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or 0, r[2] or "", r[3] or "")):
        by.setdefault(c, []).append((role or "", text or ""))
    assert got.keys() == by.keys()
    for c, turns in by.items():
        said = "".join(x for r, x in turns if r == "assistant")
        assert got[c]["n_turns"] == len(turns)
        assert got[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{x}\n" for r, x in turns).encode()).hexdigest()
        assert (got[c]["loss_chars"], got[c]["loss_sha256"]) == (len(said), hashlib.sha256(said.encode()).hexdigest())
    none = spark.createDataFrame([], df.schema)
    assert C.read_chats(*C.format_chats(none, BYTE), BYTE).count() == 0


# --- 5 ------------------------------------------------------------------------------------------


def test_warc_round_trip_with_magic_inside(spark):
    evil = MAGIC.decode() + "WARC-Type: response\r\nContent-Length: 7\r\n\r\nabcdefg\r\n\r\n"
    rows = [(i, f"http://x/{i}", evil * (i % 3) + "p" * (i % 50 * 7)) for i in range(300)] + [(400, None, None), (401, "u\r\nX: y", ""), (402, "big", "q" * 30000 + evil)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    folder, files = write_warc(df.repartition(3), roll=20_000)
    got = {r["page_id"]: r for r in read_warc(folder, files, chunk=1500).collect()}
    heads = {}
    for i, _, h in rows:
        heads[h or ""] = max(heads.get(h or "", -1), i)
    assert got.keys() == {r[0] for r in rows}
    for i, _, h in rows:
        head = heads[h or ""]
        raw = (h or "").encode()
        assert (got[i]["payload_bytes"], got[i]["payload_digest"], got[i]["record_type"], got[i]["refers_to"]) == (len(raw), sha1_base32(raw), "response" if i == head else "revisit", None if i == head else head)
    folder, files = write_warc(spark.createDataFrame([], df.schema))
    assert read_warc(folder, files).count() == 0


def test_a_payload_of_magic_strings_costs_no_more(spark):
    lines = b"WARC-Type: response\r\nContent-Length: 9\r\n"
    data = (MAGIC + lines) * 90_000 + b"\r\n\r\n" + MAGIC * 200_000
    began = time.time()
    links = record_links(data, 0, len(data))
    assert time.time() - began < 5 and len(data) > 4 << 20
    near = len(data) - len(MAGIC) * 200_000 - 4 - (1 << 16)
    assert all(near < at < near + (1 << 16) for at in links)  # the only blank line is far from all others
    rows = [(1, "u" * 100_000, "a"), (2, "http://x/", "b"), (2, "http://x/", "b"), (2, "http://y/", "c")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as head", "2 as digest", "3 as refers")
    got = Counter((r["page_id"], r["payload_digest"], r["record_type"]) for r in read_warc(*write_warc(df)).collect())
    assert got == Counter((p, sha1_base32(h.encode()), "response") for p, _, h in rows)


# --- 6 and 8 --------------------------------------------------------------------------------------


def brute_model(sentences, size):
    """Modified Kneser-Ney over words by dictionaries; ``size`` tokens share the lowest order. A function of two tokens."""
    return brute_of(Counter(g for s in sentences for g in zip([None, *s], s, strict=False)), size)


def brute_of(grams, size):
    def cut(counts):
        n = [sum(c == k for c in counts) for k in (1, 2, 3, 4)]
        if not all(n):
            return [0, 0.5, 0.5, 0.5]
        y = n[0] / (n[0] + 2 * n[1])
        return [0, *(min(max(k - (k + 1) * y * n[k] / n[k - 1], 0), k - 0.01) for k in (1, 2, 3))]

    take, total, spare, follows = cut(grams.values()), Counter(), Counter(), Counter()
    for (a, b), c in grams.items():
        total[a] += c
        spare[a] += take[min(c, 3)]
        follows[b] += 1
    low_take = cut(follows.values())
    rest = sum(low_take[min(c, 3)] for c in follows.values()) / max(len(grams), 1) if grams else 1.0

    def p(a, b):
        low = max(follows[b] - low_take[min(follows[b], 3)], 0) / max(len(grams), 1) + rest / size
        if not total[a]:
            return low
        return max(grams[a, b] - take[min(grams[a, b], 3)], 0) / total[a] + spare[a] / total[a] * low

    return p


def sentences_of(rng, n, words=40):
    pool = [f"w{'x' * (i % 7)}{i}" for i in range(words)]
    return [[pool[min(int(rng.expovariate(0.12)), words - 1)] for _ in range(rng.randint(0, 30))] for _ in range(n)]


def token_number(sentences):
    """Words, their classes by length, and the class before a first word."""
    words = {w for s in sentences for w in s}
    return len(words) + len({len(w) for w in words}) + 1


def test_packed_keys_and_bijection():
    rng = np.random.default_rng(3)
    keys = np.unique(rng.integers(0, 1 << 42, 1000).astype(np.uint64))
    assert (N.unscramble(N.scramble(keys)) == keys).all()
    counts = rng.integers(0, 1 << 31, len(keys)).astype(np.uint64)
    got = N.unpacked(len(keys), N.packed(keys, counts), "<u8")
    assert (got[0] == keys).all() and (got[1] == counts).all()
    cells = N.cell_of(np.sort(N.scramble(keys)), 7, N.KEY_BITS)
    assert (np.diff(cells) >= 0).all() and cells[0] == 0 and cells[-1] == 6


def test_model_is_modified_kneser_ney():
    rng = random.Random(15)
    sentences = sentences_of(rng, 60)
    p = brute_model(sentences, token_number(sentences))
    words = sorted({w for s in sentences for w in s})
    rest = (token_number(sentences) - len(words)) * p(words[0], "never")
    assert abs(sum(p(words[0], w) for w in words) + rest - 1) < 1e-9


def test_scores_like_brute_force(spark):
    rng = random.Random(16)
    sentences = sentences_of(rng, 120)
    docs = [(i, " ".join(s) if i % 3 else "\t" + "\n".join(s)) for i, s in enumerate(sentences)] + [(500, None), (501, ""), (502, " \n"), (None, "w0 w1"), (7, "w0 w0")]
    every = [*sentences, ["w0", "w1"], ["w0", "w0"]]
    target = spark.createDataFrame([(i,) for i in range(0, 120, 4)] + [(0,), (None,), (999,)], "doc_id long")
    aimed = [s for i, s in enumerate(sentences) if i % 4 == 0]
    size = token_number(every)
    models = [brute_model(x, size) for x in (aimed, every)]
    rows = cross_entropy_difference(frame(spark, docs).repartition(5), target).collect()
    assert len(rows) == len(docs) and rows[0].__fields__[:2] == ["doc_id", "score"]
    got = {(r["doc_id"], r["n_words"]): r for r in rows}
    for i, text in docs:
        words = (text or "").split()
        r = got[i, len(words)]
        if not words:
            assert r["score"] is None and r["target_loss"] is None
            continue
        want = [-sum(math.log(m(a, b)) for a, b in zip([None, *words], words, strict=False)) / len(words) for m in models]
        assert abs(r["target_loss"] - want[0]) < 1e-4 and abs(r["background_loss"] - want[1]) < 1e-4 and abs(r["score"] - want[0] + want[1]) < 2e-4


def test_perplexity_like_brute_force(spark):
    rng = random.Random(17)
    sides = {lang: sentences_of(rng, 60, 30) for lang in ("en", "fr")}
    rows = [(100 * k + i, " ".join(s), lang) for k, (lang, x) in enumerate(sides.items()) for i, s in enumerate(x)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    got = {r["doc_id"]: r["log_perplexity"] for r in quality(df).collect()}
    tagged = [[f"{lang}{w}" for w in s] for lang, x in sides.items() for s in x]
    marked = [(f"{lang}^", *(f"{lang}{w}" for w in s)) for lang, x in sides.items() for s in x]
    p = brute_of(Counter(g for s in marked for g in zip(s, s[1:], strict=False)), sum(token_number(x) for x in sides.values()))
    for (key, _, lang), words in zip(rows, tagged, strict=True):
        if words:
            want = -sum(math.log(p(a, b)) for a, b in zip([f"{lang}^", *words], words, strict=False)) / len(words)
            assert abs(got[key] - want) < 1e-4


def test_perplexity_of_rare_bigrams_in_many_words(spark):
    """Bigrams seen once or twice among 90,000 words count as what they are, and copies are not too easy."""
    rng = random.Random(23)
    words = [f"w{rng.randrange(10**6)}" for _ in range(3000)]
    texts = [" ".join(rng.choice(words) for _ in range(rng.randint(200, 400))) for _ in range(300)]
    rows = [(i, t) for i, t in enumerate(texts + texts[:1] * 9)]
    got = {r["doc_id"]: r for r in quality(frame(spark, rows).repartition(3)).collect()}
    marked = [("^", *t.split()) for _, t in rows]
    seen = Counter(g for s in marked for g in zip(s, s[1:], strict=False))
    assert sum(seen.values()) * 2.0**-16 > 1
    p = brute_of(seen, token_number([s[1:] for s in marked]))
    for (i, _), s in zip(rows, marked, strict=True):
        assert abs(got[i]["log_perplexity"] + sum(math.log(p(a, b)) for a, b in zip(s, s[1:], strict=False)) / (len(s) - 1)) < 1e-4
    assert all(r["kept"] for r in got.values())


def brute_counts(text):
    w = text.encode().split()
    grams = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    covered = {j for i in range(len(w) - 2) if grams[tuple(w[i : i + 3])] > 1 for j in range(i, i + 3)}
    lines, seen, dup = text.split("\n"), set(), 0
    for line in lines:
        dup += bool(line.encode().split()) and line in seen
        seen.add(line)
    return len(w), sum(len(x) for x in "".join(c if c not in " \t\n\x0b\x0c\r" else " " for c in text).split(" ")), sum(c in "#*$%&|<>" for c in text), dup, len(covered)


def test_text_counts():
    rng = random.Random(7)
    for _ in range(300):
        text = "".join(rng.choice(["a", "b", " ", "\n", "c#", "\t", "é", " "]) for _ in range(rng.randint(0, 60)))
        assert text_counts(text) == brute_counts(text)


def test_quality_and_scores(spark):
    rng = random.Random(8)
    words = [a + b for a in ("stone", "river", "cloud", "meadow", "winter", "garden", "summer", "window") for b in ("", "s", "ed", "ing", "er", "ly", "less")]
    docs = [(i, " ".join(rng.choice(words) for _ in range(rng.randint(60, 200)))) for i in range(80)] + [(200, "#$%&*" * 200 + " x" * 80), (201, "qzx vjk wqp " + " ".join("".join(rng.choice("qzxvjkwp") for _ in range(5)) for _ in range(100))), (300, None), (301, ""), (302, " \n")]
    got = {r["doc_id"]: r for r in quality(frame(spark, docs)).collect()}
    assert all(got[i]["kept"] == (not got[i]["base_failed"]) for i in range(80))
    assert not got[201]["kept"] and not got[300]["kept"] and got[301]["n_words"] == 0
    assert quality(empty(spark)).count() == 0
    target = spark.createDataFrame([(201,), (201,), (None,)], "doc_id long")
    scores = {r["doc_id"]: r["score"] for r in cross_entropy_difference(frame(spark, docs), target).collect()}
    assert scores[300] is None and scores[201] < min(scores[i] for i in range(80))
    assert all(r["score"] is None for r in cross_entropy_difference(frame(spark, docs), target.limit(0)).collect())
    assert cross_entropy_difference(empty(spark), target).count() == 0


# --- 7 ------------------------------------------------------------------------------------------


def test_banded_distance():
    rng = random.Random(9)
    for _ in range(3000):
        a = "".join(rng.choice("abc") for _ in range(rng.randint(0, 14)))
        b = noisy(rng, a, rng.randint(0, 5), "abc") if a and rng.random() < 0.7 else "".join(rng.choice("abc") for _ in range(rng.randint(0, 14)))
        for k in (0, 1, 2, 3):
            assert L.edits_within(a, b, k) == (levenshtein(a, b) <= k), (a, b, k)


@pytest.mark.parametrize("plan", [{}, {"many": 3, "every": 1}])
def test_line_removals_like_brute_force(spark, plan):
    rng = random.Random(10)
    pool = ["".join(rng.choice("abcdefgh ") for _ in range(rng.randint(12, 40))).strip() or "z" for _ in range(25)]
    pool += [f"2024-05-0{i % 9} the same beginning {rng.randrange(10**6):06d} of a line" for i in range(12)]
    docs = [(i, "\n".join(noisy(rng, rng.choice(pool), rng.choice([0, 0, 1, 2, 3])) for _ in range(rng.randint(1, 8)))) for i in range(60)] + [(90, None), (91, ""), (92, " \n\n")]
    lines = sorted({x for _, t in docs for x in (t or "").split("\n") if x.strip(" \t\n\x0b\x0c\r")})
    top = {x: x for x in lines}
    for i, a in enumerate(lines):
        for b in lines[i + 1 :]:
            if min(len(a), len(b)) >= 15 and abs(len(a) - len(b)) <= 2 and levenshtein(a, b) <= 2 and top[a] != top[b]:
                lo, hi = sorted((top[a], top[b]))
                top = {x: lo if t == hi else t for x, t in top.items()}
    seen, want = set(), {}
    for i, t in docs:
        for no, x in enumerate((t or "").split("\n")):
            if x in top:
                if top[x] in seen:
                    want.setdefault(i, []).append(no)
                seen.add(top[x])
    got = {r["doc_id"]: r["removed"] for r in L.line_removals(frame(spark, docs), near_from=15, **plan).collect()}
    assert {k: v for k, v in got.items() if v} == want
    kept = {r["doc_id"]: r["text"] for r in L.dedup_lines(frame(spark, docs), near_from=15).collect()}
    for i, t in docs:
        rest = [x for no, x in enumerate((t or "").split("\n")) if no not in want.get(i, [])]
        assert kept.get(i, "gone") == (t if i not in want else "\n".join(rest) if any(x in top for x in rest) or rest else "gone") or i not in kept
    assert L.line_removals(empty(spark)).count() == 0
    assert L.dedup_lines(frame(spark)).count() >= len(EDGE) - 1


def test_rows_that_repeat_an_id_are_documents_of_their_own(spark):
    rows = [(7, "the shared line of two rows\nown b"), (7, "a unique line that must stay\nown c"), (8, "the shared line of two rows"), (None, "the shared line of two rows"), (9, None), (9, ""), (9, ""), (10, "own b\nown b")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "1 as removed", "2 as key", "3 as version", "4 as nothing_left", "5 as __removed", "6 as __id")
    out = L.dedup_lines(df)
    assert out.columns == df.columns
    got = Counter((r["doc_id"], r["text"]) for r in out.collect())
    assert got == Counter([(7, rows[0][1]), (7, rows[1][1]), (None, rows[3][1]), (9, None), (9, ""), (9, "")])


def test_common_beginnings_are_divided(spark):
    """Thousands of lines share two thirds; a few are near others: no link is lost, and no key has them all."""
    rng = random.Random(18)
    lines = [f"a common beginning that every line of this log has {rng.randrange(10**12):012d} {rng.randrange(10**9):09d}" for _ in range(1500)]
    near = [noisy(rng, x, 2, "0123456789") for x in lines[:100]]
    docs = [(i, x) for i, x in enumerate(lines)] + [(5000 + i, x) for i, x in enumerate(near)]
    texts = spark.createDataFrame(docs, "doc_id long, text string")
    hot = L.hot_keys(texts, 2, 30, 64, 1)
    signer = L._Signer(2, 30, hot)
    met = Counter(k for x in lines for k in signer.keys(x))
    assert len(hot) and max(met.values()) < 400
    got = {r["doc_id"] for r in L.line_removals(texts, many=64, every=1).where("size(removed) > 0").collect()}
    assert got == {5000 + i for i in range(100)}


# --- 9 ------------------------------------------------------------------------------------------


def test_token_counts_with_small_chunks(spark):
    import sentencepiece

    path = tokenizer_path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    rng = random.Random(11)
    docs = [(i, "".join(rng.choice(["word ", "été ", "a", "\n", "  ", "👍", "ing the ", "xyz"]) for _ in range(rng.randint(0, 200)))) for i in range(60)] + [(100, "x" * 900), (101, "y " * 500), (102, " " * 700), (103, None)]
    got = {r["id"]: (r["n_bytes"], r["n_tokens"]) for r in count_tokens(frame(spark, docs), path, chunk=100, overlaps=(8, 32)).collect()}
    assert got == {i: (len((t or "").encode()), len(sp.encode(t or ""))) for i, t in docs}
    assert count_tokens(frame(spark), path).count() == len(EDGE)
    assert count_tokens(empty(spark), path).count() == 0


# --- 10 -----------------------------------------------------------------------------------------


def test_perfect_hash():
    rng = np.random.default_rng(12)
    for n in (0, 1, 2, 5, 1000):
        a, b = (rng.integers(0, 1 << 63, n).astype(np.uint64) for _ in range(2))
        assert sorted(PerfectHash.of(a, b).slots(a, b)) == list(range(n))


def test_encoder_is_the_library():
    from tokenizers import Tokenizer

    rng = random.Random(13)
    parts = ["a", "word", " ", "  ", "\n", "\t", "don't", "'s", "É", "é́", "<|endoftext|>", ".", ",", "12", "_", "👍", " ", "ΣΑΣ", "İx", "%%%", "\x1c"]
    for path in (BYTE, WORD):
        plain = Tokenizer.from_file(path)
        for _ in range(1500):
            text = "".join(rng.choice(parts) for _ in range(rng.randint(0, 12)))
            assert encoder(path).ids(text) == np.array(plain.encode(text, add_special_tokens=False).ids, "<u4").tobytes(), repr(text)


def test_plain_words_skip_the_passes_over_whole_texts():
    from corpus_tilt.llm.common import UnitEncoder

    enc, seen, rng = UnitEncoder(WORD), [], random.Random(15)
    encode = enc._encode
    enc._encode = lambda units: seen.extend(units) or encode(units)
    letters = [c for c in map(chr, range(256)) if c.isalpha()]
    words = letters + ["".join(rng.choices(letters, k=rng.randint(2, 9))) for _ in range(800)]
    text = "One " + "".join(w + rng.choice(" \n") for w in words) + "end"
    assert enc.ids(text) == np.array(enc.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
    assert seen == ["One"]


def test_token_store(spark):
    docs = frame(spark)
    store = write_tokens(docs, BYTE, 2, keys_per_bucket=3)
    enc, start, want = encoder(BYTE), 0, []
    for key, text in sorted(EDGE, key=lambda r: (r[0] is not None, r[0] or 0)):
        ids = enc.ids(text) + (2).to_bytes(4, "little")
        want.append((key, len(ids) // 4, zlib.crc32(ids)))
        start += len(ids) // 4
    got = [tuple(r) for r in token_digest(store, docs).collect()]
    assert Counter((k, n, c) for k, _, n, c in got) == Counter(want)
    spans = sorted((s, n) for _, s, n, _ in got)
    assert all(a + n == b for (a, n), (b, _) in zip(spans, spans[1:], strict=False)) and spans[0][0] == 0
    missing = spark.createDataFrame([(999,), (1,)], "doc_id long")
    assert [r["key"] for r in read_tokens(store, lookup(store, missing)).collect()] == [1]
    assert token_digest(write_tokens(empty(spark), BYTE, 2), empty(spark)).count() == 0


def test_a_hot_key_is_dealt_to_several_shards(spark):
    rows = [(7, f"text {i % 90} of many words {i}") for i in range(900)] + [(i, f"other {i}") for i in range(300)]
    docs = frame(spark, rows).repartition(6)
    store = write_tokens(docs, BYTE, 2, keys_per_bucket=100)
    got = token_digest(store, docs).collect()
    enc = encoder(BYTE)
    want = Counter((k, zlib.crc32(enc.ids(t) + (2).to_bytes(4, "little"))) for k, t in rows)
    assert Counter((r["doc_id"], r["ids_crc32"]) for r in got) == want
    spans = sorted((r["start"], r["n_tokens"], r["doc_id"]) for r in got)
    assert all(a + n == b and x <= y for (a, n, x), (b, _, y) in zip(spans, spans[1:], strict=False))


def test_encoder_in_stretches_and_small_caches():
    from corpus_tilt.llm.common import UnitEncoder, encoded_by

    rng = random.Random(14)
    small = UnitEncoder(BYTE, room=3000)
    texts = ["".join(rng.choice(["word ", "a", " ", "\n", "été", "\tb ", "don't ", "%%"]) for _ in range(rng.randint(0, 400))) for _ in range(60)]
    assert not small.whole_only
    for width in (2, 4):
        got = list(encoded_by(small, texts, width, at_once=50))
        assert got == [np.array(small.tokenizer.encode(t, add_special_tokens=False).ids, f"<u{width}").tobytes() for t in texts]
