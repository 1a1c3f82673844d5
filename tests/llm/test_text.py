"""Quality, privacy, mixing, chat, packing, language model and top-k operators against brute force."""

import hashlib
import itertools
import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from roadtraj.llm import chat, hmm, mixing, packing, privacy, quality, topk
from roadtraj.llm.queries import tokenizer_path
from tests.llm.fixtures import documents, frame, words


def _no_python(df):
    plan = df._jdf.queryExecution().executedPlan().toString()
    return not re.search("Python|Pandas|Arrow|BatchEval", plan)


def test_quality(spark):
    want = []
    for i, text, *_ in documents():
        seq, lines, dup = words(text), set(), 0
        for line in (text or "").split("\n"):
            if words(line):
                dup += line in lines
                lines.add(line)
        grams = Counter(tuple(seq[k : k + 3]) for k in range(len(seq) - 2))
        inside = {k + j for k in range(len(seq) - 2) if grams[tuple(seq[k : k + 3])] > 1 for j in range(3)}
        want.append((i, len(seq), sum(map(len, seq)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(inside), len(seq) < 50 or 100 * len(inside) > 50 * len(seq)))
    out = quality.verdicts(frame(spark))
    got = out.collect()
    assert Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in got) == Counter(want)
    assert not any(r.kept and r.base_failed for r in got) and _no_python(out)
    kept = quality.keep(frame(spark))
    assert kept.count() == sum(r.kept for r in got) and kept.columns == frame(spark).columns
    assert quality.verdicts(frame(spark, [])).count() == 0


PRIVATE = [
    (1001, "a@b.c._x@d.e 1.2.3.4.5.6.7.8 +1 (234) 567-8901 4111 1111 1111 1111 999.1.1.1", None, None, None),
    (1002, "é a@b.co, +44 20 7946 0958. 😀 me@x.org 😀 10.0.0.256", None, None, None),
    (1003, "x@y..z a..b@c-d.e-f.g 00001.2.3.255 4111-1111 1111-1111-1", None, None, None),
    *[(1010 + i, "call zelda ring now zelda@mail.org thanks", None, None, None) for i in range(4)],
    *[(1020 + i, "call ring now thanks and other words", None, None, None) for i in range(30)],
]


def _luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (1 + i % 2)
        total += v - 9 if v > 9 else v
    return total % 10 == 0


def test_privacy(spark):
    rows = documents() + PRIVATE
    kinds = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    want = []
    for i, text, *_ in rows:
        spans = []
        for k, (kind, pattern) in enumerate(kinds.items()):
            for m in re.finditer(pattern, text or ""):
                digits = re.sub("[^0-9]", "", m[0])
                if {"email": True, "ip": kind != "ip" or all(int(p) < 256 for p in m[0].split(".")), "card": 14 <= len(digits) <= 19 and _luhn(digits), "phone": 10 <= len(digits) <= 15}[kind]:
                    spans.append((m.start(), k, f"{kind}:{m.start()}:{m.end()}"))
        want.append((i, hashlib.sha256(",".join(s[2] for s in sorted(spans)).encode()).hexdigest()))
    found = privacy.find(frame(spark, rows))
    got = privacy.digests(found).collect()
    assert Counter((r.doc_id, r.base_sha256) for r in got) == Counter(want) and _no_python(privacy.digests(found))
    # "zelda" stands near its address only there: it discloses all of it. Common words near it do not.
    terms = {r.doc_id: [s for s in r.spans.split(",") if s.startswith("term")] for r in got}
    assert terms[1010] == ["term:5:10"] and not terms[1020]
    clean = {r.doc_id: r.text for r in privacy.sanitise(frame(spark, rows)).collect()}
    assert clean[1010] == "call  ring now <EMAIL> thanks" and clean[1020] == PRIVATE[7][1] and clean[62] == documents()[62][1]
    assert privacy.digests(privacy.find(frame(spark, []))).count() == 0


def test_privacy_of_texts_full_of_matches(spark):
    """Thousands of matches in one text: places are right and the time stays short."""
    text = "".join(f"é {i}.{i % 256}.1.2 a{i}@x.org +1234567{i:04d}; " for i in range(3000))
    found = privacy.digests(privacy.find(frame(spark, [(1, text, None, None, None), (2, "x", None, None, None)]))).where("doc_id = 1").first()
    want = [f"{k}:{m.start()}:{m.end()}" for m in re.finditer(r"(?P<ip>(?<=é )[0-9.]+)|(?P<email>a[0-9]+@x.org)|(?P<phone>\+[0-9]+)", text) for k in [m.lastgroup] if k != "ip" or int(m[0].split(".")[0]) < 256]
    base = [s for s in found.spans.split(",") if not s.startswith("term")]
    assert base == want and found.n_email == 3000 and found.n_ip == 256


def test_terms_are_generalised_to_their_shape(spark):
    """A term that reveals most of an entity, but not nearly all, is replaced by what it looks like."""
    rows = [(i, "ask Quentin x77 rarely at q7@mail.org" if i < 2 else "Quentin x77 rarely at" if i == 2 else "ask at today", None, None, None) for i in range(60)]
    clean = {r.doc_id: r.text for r in privacy.sanitise(frame(spark, rows)).collect()}
    assert clean[0] == "ask <NAME> <CODE> <WORD> at <EMAIL>" and clean[2] == rows[2][1]


def test_privacy_of_values_seen_once(spark):
    rows = [(1, "ask quentin at q7@mail.org today", None, None, None), *[(2 + i, "ask at today", None, None, None) for i in range(40)]]
    got = {r.doc_id: r.spans for r in privacy.digests(privacy.find(frame(spark, rows))).collect()}
    assert got[1] == "term:4:11,email:15:26" and set(got.values()) == {got[1], ""}


def test_privacy_of_whole_documents(spark):
    far = "and so on " * 30
    rows = [(1, f"Quentin {far}q7@mail.org {far}QUENTIN quentin@x.org", None, None, None), (None, f"walter {far}w8@mail.org walter", None, None, None), *[(2 + i, "and so on at mail org x", None, None, None) for i in range(40)]]
    rows.append(rows[1])
    got = {r.doc_id: r.spans for r in privacy.digests(privacy.find(frame(spark, rows))).collect()}
    assert got[1] == "term:0:7,email:308:319,term:620:627,email:628:641"
    assert got[None] == "term:0:6,email:307:318,term:319:325" and not got[2]
    # Every share against counts of whole documents.
    rows = documents(7, 90) + [(5000 + i, f"{t} mail{i % 9}@x.org {i}", None, None, None) for i, t, *_ in documents(7, 90) if i and t and i % 4 == 0]
    found = privacy.base_spans(frame(spark, rows))
    terms = [{x.lower() for x in re.findall(r"[^\W_]+", t or "") if len(x) > 1 and re.search(r"[^\W\d_]", x)} for _, t, *_ in rows]
    held = [set(re.findall(r"\S+@\S+", t or "")) for _, t, *_ in rows]
    n_term, n_entity = Counter(x for s in terms for x in s), Counter(x for s in held for x in s)
    n_both, want = Counter((e, x) for es, ts in zip(held, terms, strict=True) for e in es for x in ts), {}
    for (i, *_), es, ts in zip(rows, held, terms, strict=True):
        for e, x in itertools.product(es, ts):
            share = math.log(n_both[e, x] * len(rows) / (n_entity[e] * n_term[x])) / math.log(len(rows) / n_entity[e])
            if share >= privacy.GENERALISE:
                want[i, x] = max(want.get((i, x), 0), round(share, 9))
    assert want and {(r.id, r.term): round(r.share, 9) for r in privacy.disclosures(frame(spark, rows), found).collect()} == want


def test_targets(spark):
    sizes = spark.createDataFrame([("a", 100), ("b", 10), ("c", 50), (None, 7), ("d", 0)], "source string, size long")
    got = {r.source: r.target for r in mixing.targets(sizes).collect()}
    order, weights, size = ["a", "b", "c", "d", None], [3.0, 1.0, 2.0, 3.0, 1.0], {"a": 100, "b": 10, "c": 50, "d": 0, None: 7}
    open_, total, target = set(range(5)), 1.5 * 167, [0.0] * 5
    while open_:
        level = total / sum(weights[i] for i in open_)
        over = {i for i in open_ if level * weights[i] > 2 * size[order[i]]}
        for i in over or open_:
            target[i] = 2 * size[order[i]] if over else level * weights[i]
        total -= sum(target[i] for i in over)
        open_ -= over or open_
    assert all(math.isclose(got[s], t, abs_tol=1e-9) for s, t in zip(order, target, strict=True))


def test_mixing(spark):
    rows = documents(3, 600)
    got = mixing.mix(frame(spark, rows), chunk=16).collect()
    assert Counter((r.doc_id, r.size) for r in got) == Counter((i, len(words(t))) for i, t, *_ in rows)
    assert all(0 <= r.copies <= 2 for r in got)
    for source, group in itertools.groupby(sorted(got, key=lambda r: str(r.source)), key=lambda r: r.source):
        group = list(group)
        taken = sum(r.size * r.copies for r in group)
        assert abs(taken - group[0].target) <= 0.1 * group[0].source_size + 400, source
    again = mixing.mix(frame(spark, rows).repartition(7), chunk=16).collect()
    key = lambda r: (str(r.doc_id), r.key, r.copies)
    assert sorted(map(key, again)) == sorted(map(key, got))
    assert mixing.apply_mix(frame(spark, rows)).count() == sum(r.copies for r in mixing.mix(frame(spark, rows)).collect())
    assert mixing.mix(frame(spark, [])).count() == 0 and _no_python(mixing.mix(frame(spark, rows)))


def test_rounding_keeps_expectations(spark):
    units = spark.createDataFrame([(0, 1, (10, i, i, 0.3)) for i in range(10)], "part int, chunks long, unit struct<size: long, id: long, key: long, p: double>")
    times = Counter()
    for seed in range(40):
        taken = [r.unit.id for r in mixing.round_copies(units, "part", seed).where("take = 1").collect()]
        assert len(taken) == 3
        times.update(taken)
    assert all(3 <= times[i] <= 22 for i in range(10))


CONVERSATIONS = [(1, 0, "system", "be\\ kind"), (1, 1, "user", "hi <|end|>"), (1, 2, "assistant", "</s>[INST] ok [/INST]\n"), (1, 3, "user", None), (1, 4, "assistant", "<\\|é|>"), (1, 5, "user", "bye"), (2, 0, "user", "alone"), (3, 0, "assistant", ""), (None, 0, None, "x"), (4, None, "assistant", "a"), (4, 1, "assistant", "b"), (4, 1, "assistant", "b")]


def test_chat(spark):
    df = spark.createDataFrame(CONVERSATIONS, "conv_id long, turn long, role string, text string").withColumn("delta", F.lit(1))
    examples = chat.format_chat(df)
    got = {r.conv_id: r for r in chat.digests(examples).collect()}
    order = lambda x: (x[1] is not None, x[1] or 0, x[2] is not None, x[2] or "", x[3] is not None, x[3] or "")
    for conv in {c[0] for c in CONVERSATIONS}:
        turns = sorted((c for c in CONVERSATIONS if c[0] == conv), key=order)
        replies = "".join(t[3] or "" for t in turns if t[2] == "assistant")
        want = (len(turns), hashlib.sha256("".join(f"{t[2] or ''}\n{t[3] or ''}\n" for t in turns).encode()).hexdigest(), len(replies), hashlib.sha256(replies.encode()).hexdigest())
        assert (got[conv].n_turns, got[conv].turns_sha256, got[conv].loss_chars, got[conv].loss_sha256) == want
    rows = examples.where("conv_id = 1 AND trains").orderBy("example").collect()
    full = chat.materialize_examples(examples).where("conv_id = 1").orderBy("example").collect()
    assert [r.text for r in rows] == [r.text for r in full] and {r.context_chars for r in rows} == {0}
    assert len(full) == 2 and full[1].text.startswith(full[0].text)
    assert [chat.unescape(r.text[r.loss_start : r.loss_end]) for r in full] == ["</s>[INST] ok [/INST]\n", "<\\|é|>"]
    assert sum(len(r.text) for r in full) == got[1].formatted_chars
    assert chat.digests(chat.format_chat(df.limit(0))).count() == 0


def test_long_conversations(spark):
    """Beyond the context limit rows refer to those before them; what they say is the same."""
    turns = [(c, t, ("user", "assistant", "tool")[t % 3], f"{c} says <|{t}|> " * (t % 5 + c)) for c in (1, 2, 3) for t in range(40)] + [(9, 0, "user", "y" * 3_000_000)]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    short, whole = chat.format_chat(df, 300), chat.format_chat(df)
    assert short.where("context_chars > 0").count() > 20 and whole.where("context_chars > 0").count() == 0
    assert sorted(chat.digests(short).collect()) == sorted(chat.digests(whole).collect())
    texts = [sorted(tuple(r)[0:1] + tuple(r)[2:] for r in chat.materialize_examples(x).collect()) for x in (short, whole)]
    assert texts[0] == texts[1] and len(texts[0]) == 39


def test_long_examples_are_whole(spark):
    """Beyond the context limit the rows of an example hold all of its text, and none of it stands in other examples only."""
    turns = [(c, t, ("user", "assistant", "tool")[(t + c) % 3], f"{c} sagt é <|{t}|> " * (t % 7)) for c in (1, 2, 3) for t in range(30)]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    examples = chat.format_chat(df, 200)
    got = {}
    for r in examples.orderBy("conv_id", "example", "context_chars").collect():
        before = got.setdefault((r.conv_id, r.example), [])
        assert r.context_chars == sum(len(x.text) for x in before)
        before.append(r)
    digest = {r.conv_id: r for r in chat.digests(examples, ordered=True).collect()}
    for conv in (1, 2, 3):
        upto, want = "", []
        for t in turns[30 * (conv - 1) : 30 * conv]:
            upto += f"<|{t[2]}|>\n{chat.escape(t[3])}<|end|>\n"
            if t[2] == "assistant":
                want.append(upto)
        rows = [rows for (c, _), rows in sorted(got.items()) if c == conv]
        assert ["".join(x.text for x in r) for r in rows if r[-1].trains] == want and max(map(len, rows)) > 5
        assert "".join(x.text for x in rows[-1]) == upto
        assert digest[conv].formatted_chars == sum(map(len, want)) and digest[conv].n_turns == 30
    assert sorted(digest.values()) == sorted(chat.digests(examples.orderBy(F.rand(1))).collect())


def test_escape_round_trip():
    for parts in itertools.product(["<", "|", "\\", "</s>", "[INST]", ">"], repeat=4):
        text = "".join(parts)
        assert chat.unescape(chat.escape(text)) == text
        assert not any(c in chat.escape(text) for c in chat.CONTROL)


def test_packing(spark):
    from tokenizers import Tokenizer

    coder, rows = Tokenizer.from_file(tokenizer_path()), documents()
    rows.append((900, "<|endoftext|> it's DON'T.,<|ENDOFTEXT|> é́ 12", None, None, None))
    got = packing.pack(frame(spark, rows).where("doc_id <> 3"), tokenizer_path()).collect()
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    for i, text, *_ in rows:
        if i in (3, None):
            continue
        ids = [*coder.encode(text or "", add_special_tokens=False).ids, 1]
        at = 0
        for r in sorted(by[i], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids)
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    lengths = []
    for _, group in itertools.groupby(sorted(got, key=lambda r: (r.sequence_id, r.offset)), key=lambda r: r.sequence_id):
        at = 0
        for r in group:
            assert r.offset == at
            at += r.length
        lengths.append(at)
    assert max(lengths) <= 2048
    assert packing.pack(frame(spark, []), tokenizer_path()).count() == 0


def test_packing_keeps_the_level_arrays_windows(spark):
    """Windows are little padded, and most of those that a task leaves open stay as they are; very long texts take several slices."""
    rows = documents(9, 400) + [(5000 + i, "long text here " * 100_000, None, None, None) for i in range(4)]
    packed = packing.pack(frame(spark, rows).coalesce(2), tokenizer_path())
    found = packing.padding(packed).first()
    assert found.tokens == sum(r.length for r in packed.select("length").collect()) and found.sequences * 2048 == found.tokens + found.padded
    sizes = sorted(r.n for r in packed.groupBy("sequence_id").agg(F.sum("length").alias("n")).collect())
    assert sum(n < packing.ENOUGH * 2048 for n in sizes) <= 2 and found.padded < 0.1 * found.tokens


def test_other_tokenizers_get_whole_texts(tmp_path):
    from tokenizers import Tokenizer, models, pre_tokenizers

    coder = Tokenizer(models.WordLevel({"Ab": 0, "ab": 1, "!": 2, "?": 3}, unk_token="?"))
    coder.pre_tokenizer = pre_tokenizers.Whitespace()
    coder.save(str(tmp_path / "t.json"))
    made = packing.WordTokenizer(str(tmp_path / "t.json"))
    ids, bounds = made.encode(pa.array(["Ab ab !", None, "ab"]))
    assert not made.by_word and ids.tolist() == [0, 1, 2, 1] and bounds.tolist() == [0, 3, 3, 4]
    assert packing.WordTokenizer(tokenizer_path()).by_word


def test_level_array_is_greedy():
    """Each placement makes the sum of squared counts smallest."""
    rng, levels, square = np.random.default_rng(1), packing.LevelArray(16), lambda c: int((c[1:-1] ** 2).sum())
    for n in rng.integers(1, 16, 300):
        before, options = levels.counts.copy(), []
        for h in range(16 - n + 1):
            if h == 0 or before[h]:
                c = before.copy()
                c[h] -= h > 0
                c[h + n] += h + n < 16
                options.append(square(c))
        levels.place(int(n), ("d", 0, np.zeros(n), n))
        assert square(levels.counts) == min(options)


def test_forward_is_exact():
    rng = np.random.default_rng(0)
    k, c = hmm.STATES, 5
    model = hmm.Model(rng.dirichlet(np.ones(k)), rng.dirichlet(np.ones(k), k), rng.dirichlet(np.ones(c), k).T)
    seqs = [[0, 1, 2], [3], [4, 4, 0, 1], [2, 2]]
    bounds = np.concatenate([[0], np.cumsum([len(s) for s in seqs])])
    got = hmm.forward(model, np.concatenate(seqs), bounds)
    for s, g in zip(seqs, got, strict=True):
        total = sum(model.start[p[0]] * np.prod([model.emit[w, q] for w, q in zip(s, p, strict=True)]) * np.prod([model.move[a, b] for a, b in zip(p, p[1:], strict=False)]) for p in itertools.product(range(k), repeat=len(s)))
        assert math.isclose(g, math.log(total), rel_tol=1e-9)
    start, move, emit, likelihood = hmm.expected_counts(model, np.concatenate(seqs), bounds)
    assert math.isclose(start.sum(), 4) and math.isclose(move.sum(), 6) and math.isclose(emit.sum(), 10) and math.isclose(likelihood, got.sum())
    # Whatever the segments, nothing is lost at their borders.
    seqs = [rng.integers(0, c, n) for n in (1, 2, 7, 23, 24, 25, 60, 8)]
    flat, bounds = np.concatenate(seqs), np.concatenate([[0], np.cumsum([len(s) for s in seqs])])
    whole = hmm.expected_counts(model, flat, bounds, 1000)
    for length in (1, 2, 5, 8):
        for a, b in zip(hmm.expected_counts(model, flat, bounds, length), whole, strict=True):
            assert np.allclose(a, b, rtol=1e-9)


def test_language_model(spark, monkeypatch):
    rows = [r for r in documents(5, 300) if r[0] is not None]
    df = frame(spark, rows)
    got = hmm.score(df).collect()
    lower = str.maketrans({chr(x): chr(x + 32) for x in range(65, 91)})
    tokens = [[*words((t or "").translate(lower)), " "] for _, t, *_ in rows]
    held = [zlib.crc32(str(i).encode()) % 5 == 1 for i, *_ in rows]
    counts = Counter(w for s, h in zip(tokens, held, strict=True) if not h for w in s)
    n, v = sum(counts.values()), len(counts)
    want = Counter((i, h, len(s), sum(counts[w] > 0 for w in s), n, round(sum(math.log10((counts[w] + 0.5) / (n + 0.5 * (v + 1))) for w in s), 4)) for (i, *_), h, s in zip(rows, held, tokens, strict=True))
    assert Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 4)) for r in got) == want
    assert all(r.score < 0 for r in got)
    # Small head tables send words through the join; nothing but the classes may change.
    monkeypatch.setattr(hmm, "HEAD_WORDS", 40)
    monkeypatch.setattr(hmm, "OWN_CLASSES", 1)
    again = Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 4)) for r in hmm.score(df, rounds=1).collect())
    assert again == want
    assert hmm.score(frame(spark, [])).count() == 0
    assert [r.held_out for r in hmm.score(frame(spark, [(None, "a b", None, None, None)])).collect()] == [None]


def _slow_counts(model, seq):
    """Expected starts, moves and emissions of one sequence, by sums over plain lists."""
    k = range(len(model.start))
    ahead = [[model.start[i] * model.emit[seq[0]][i] for i in k]]
    for w in seq[1:]:
        ahead.append([sum(ahead[-1][i] * model.move[i][j] for i in k) * model.emit[w][j] for j in k])
    back = [[1.0 for _ in k]]
    for w in seq[:0:-1]:
        back.insert(0, [sum(model.move[i][j] * model.emit[w][j] * back[0][j] for j in k) for i in k])
    total = sum(ahead[-1])
    start, move, emit = np.zeros(len(k)), np.zeros((len(k), len(k))), np.zeros_like(model.emit)
    for t, w in enumerate(seq):
        for i in k:
            weight = ahead[t][i] * back[t][i] / total
            emit[w][i] += weight
            start[i] += weight * (t == 0)
            for j in k:
                move[i][j] += ahead[t][i] * model.move[i][j] * model.emit[seq[t + 1]][j] * back[t + 1][j] / total if t + 1 < len(seq) else 0
    return start, move, emit, total


@pytest.mark.parametrize("states", [1, 2])
def test_scores_against_a_slow_twin(spark, monkeypatch, states):
    """Training and scoring from the texts on, by plain loops; one state is a model of word frequencies alone."""
    monkeypatch.setattr(hmm, "STATES", states)
    monkeypatch.setattr(hmm, "OWN_CLASSES", 2)
    rng = np.random.default_rng(3)
    rows = [(i, " ".join(f"w{int(x) ** 2 // 40}" for x in rng.integers(0, 60, int(rng.integers(0, 80)))), None, None, None) for i in range(25)]
    tokens = [[*words(t), " "] for _, t, *_ in rows]
    trained = [s for s, (i, *_) in zip(tokens, rows, strict=True) if zlib.crc32(str(i).encode()) % 5 != 1]
    counts = Counter(w for s in trained for w in s)
    kinds = hmm.Classes.of(len(counts))
    head = sorted(counts, key=lambda w: (-counts[w], w))
    of = {w: n if n < kinds.own else int(kinds.by_hash(hmm.hash_of_words([w]))[0]) for n, w in enumerate(head)}
    totals = np.zeros((kinds.n, 2), np.int64)
    for w, n in counts.items():
        totals[of[w]] += (n, 1)
    model = hmm.Model.initial(totals[:, 0])
    for _ in range(hmm.ROUNDS):
        sums = [_slow_counts(model, [of[w] for w in s])[:3] for s in trained]
        model = hmm.Model.from_counts(*(sum(x) for x in zip(*sums, strict=True)))
    unseen = min(max(sum(n == 1 for n in counts.values()) / sum(counts.values()), 1e-9), 0.5)
    emit = model.emit * (1 - unseen)
    emit[kinds.unseen] = unseen
    model = hmm.Model(model.start, model.move, emit)
    got = {r.doc_id: r.score for r in hmm.score(frame(spark, rows)).collect()}
    for (i, *_), s in zip(rows, tokens, strict=True):
        inner = sum(math.log10((counts[w] + 0.5) / (totals[of[w]] @ (1, 0.5))) for w in s if w in of)
        assert math.isclose(got[i], math.log10(_slow_counts(model, [of.get(w, kinds.unseen) for w in s])[3]) + inner, rel_tol=1e-7)


def test_training_raises_likelihood(spark):
    rng = np.random.default_rng(2)
    rows = [(i, int(0), False, rng.integers(i % 2 * 20, i % 2 * 20 + 20, 150).astype(int).tolist()) for i in range(60)]
    seqs = spark.createDataFrame(rows, "doc_id long, tie int, held_out boolean, classes array<int>")
    start = np.bincount(np.concatenate([r[3] for r in rows]), minlength=hmm.Classes.of(40).n)
    _, seen = hmm.train(seqs, hmm.Model.initial(start), rounds=4)
    assert all(a < b for a, b in zip(seen, seen[1:], strict=False))


def test_top_k(spark):
    rng = np.random.default_rng(1)
    vectors = [(i, rng.integers(-3, 4, 6).astype(float).tolist()) for i in range(220)]
    vectors += [(300, None), (301, [1.0, None]), (302, [float("nan")] * 6), (303, [float("inf")] * 6), (None, [1.0] * 6), (304, [0.5] * 4), (50, vectors[50][1]), (305, [])]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<double>").withColumn("ids", F.lit(1))
    usable = [(i, np.floor(256 * np.array(x)).astype(int)) for i, x in vectors if i is not None and x is not None and all(c is not None and math.isfinite(c) for c in x)]
    got = {}
    for r in topk.top_k(df).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    for q, x in {i: x for i, x in usable if i % 50 == 0}.items():
        scores = sorted((-int(np.dot(x[: min(len(x), len(y))], y[: min(len(x), len(y))])), i) for i, y in usable if i != q)[:5]
        assert sorted(got[q]) == [(k + 1, i, -s) for k, (s, i) in enumerate(scores)]
    assert topk.top_k(df.limit(0)).count() == 0


def test_top_k_over_a_grid(spark, monkeypatch):
    """Many cells; a query id with two vectors asks with the smaller; sums beyond 64 bits stop at their end."""
    monkeypatch.setattr(topk, "ROWS_PER_BLOCK", 16)
    monkeypatch.setattr(topk, "QUERIES_PER_BLOCK", 2)
    rng = np.random.default_rng(2)
    vectors = [(i, [float(x) for x in rng.integers(-9, 9, 5)]) for i in range(400)] + [(100, [-20.0, 1.0, 1.0, 1.0, 1.0]), (7, [2.0**40] * 5), (350, [2.0**40, -1.0, 0.0, 0.0, 0.0])]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<double>").repartition(5)
    whole = [(i, [math.floor(256 * c) for c in x]) for i, x in vectors]
    got = {}
    for r in topk.top_k(df).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    for q in range(0, 400, 50):
        own = min(x for i, x in whole if i == q)
        best = sorted((-min(sum(a * b for a, b in zip(own, y, strict=True)), 2**63 - 1), i) for i, y in whole if i != q)[:5]
        assert sorted(got[q]) == [(k + 1, i, -s) for k, (s, i) in enumerate(best)]


def test_words_of_slices():
    from roadtraj.llm.textbatch import word_hashes, words_of

    texts = pa.array(["a b", None, "", " c\td", "é", "ab"] * 3)
    for lo, n in ((0, 18), (1, 5), (4, 9)):
        part = texts.slice(lo, n)
        w = words_of(part)
        found = [[bytes(w.data[a:b]).decode() for a, b in zip(w.start[i:j], w.end[i:j], strict=True)] for i, j in zip(w.first[:-1], w.first[1:], strict=True)]
        assert found == [words(t) for t in part.to_pylist()]
        flat = [x for s in found for x in s]
        hashes = word_hashes(w.data, w.start, w.end)
        assert len(set(hashes.tolist())) == len(set(flat))


@pytest.mark.parametrize("seed", [1])
def test_pipeline(spark, tmp_path, seed):
    import corpus_pipeline

    rows = documents(seed, 120)
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, str(tmp_path))
        assert after.columns == docs.columns
        docs = after
    assert {r.doc_id for r in out} == {r.doc_id for r in docs.collect()}
