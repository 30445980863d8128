"""Each training-data operator against brute force or an exact rule on small fixtures, and its defined edge results."""

import hashlib
import math
import pickle
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark import cloudpickle
from pyspark.sql import functions as F

from packsum.llm import chroma, language, maxent, mixing, packing, privacy, quality, repeats, runtime, setjoin, tokens, toxicity, wordhash

SPACE = "[\x20\x09-\x0d]+"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, n_words string, size string, h string, label string"


def words(text):
    return [w for w in re.split(SPACE, text or "") if w]


def docs_of(spark, texts, langs=None, sources=None):
    """Documents with extra columns whose names operators use inside."""
    rows = [(i, t, (langs or ["en"] * len(texts))[i], (sources or ["a"] * len(texts))[i], len(t or ""), "x", "y", "z", "w") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


BASE = " ".join(f"word{i % 97}x{i}" for i in range(300))
EDGE = [None, "", "  \n\t ", "one", "one two", "one two", BASE, BASE, BASE.replace("word5x5", "changed"), "long " * 5000, "ünï 😀 text\x0bwith\x0cspaces\r\n", BASE[: len(BASE) // 2], "THE the The " * 30]


def empty(spark):
    return docs_of(spark, ["x"]).limit(0)


def test_quality(spark):
    got = {r["doc_id"]: r for r in quality.quality_rules(docs_of(spark, EDGE)).collect()}
    for i, t in enumerate(EDGE):
        ws, lines = words(t), [x for x in (t or "").split("\n") if words(x)]
        seen = Counter(zip(ws, ws[1:], ws[2:], strict=False))
        covered = {j + k for j in range(len(ws) - 2) if seen[tuple(ws[j : j + 3])] > 1 for k in range(3)}
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_repeat_words"]) == (len(ws), sum(map(len, ws)), len(covered)), i
        assert r["n_dup_lines"] == len(lines) - len(set(lines))
        assert r["n_symbols"] == sum(c in "#*$%&|<>" for c in t or "")
        assert r["base_failed"] == (len(ws) < 50 or 100 * len(covered) > 50 * len(ws))
    assert quality.quality_rules(empty(spark)).count() == 0


def test_mixing(spark):
    sources = ["b", None, "a", "b", "a", "c", "b", "b", "a", "c", None, "a", "b"]
    out = mixing.mix(docs_of(spark, EDGE, sources=sources))
    got = out.collect()
    assert sorted(got) == sorted(mixing.mix(docs_of(spark, EDGE, sources=sources)).collect())
    size = {i: len(words(t)) for i, t in enumerate(EDGE)}
    names = ["a", "b", "c", None]
    total = {s: sum(size[i] for i in size if sources[i] == s) for s in names}
    target = {s: 1.5 * sum(total.values()) * w / 13 for s, w in zip(names, (5, 2, 1, 5), strict=True)}
    weight = dict(zip(names, (5, 2, 1, 5), strict=True))
    capped = set()
    while True:
        over = {s for s in names if s not in capped and target[s] > 2 * total[s] + 1e-9}
        if not over:
            break
        capped |= over
        free = [s for s in names if s not in capped]
        left = 1.5 * sum(total.values()) - sum(2 * total[s] for s in capped)
        target = {s: 2 * total[s] if s in capped else left * weight[s] / sum(weight[x] for x in free) for s in names}
    for r in got:
        s = sources[r["doc_id"]]
        assert r["size"] == size[r["doc_id"]] and r["source_size"] == total[s]
        assert r["target"] == pytest.approx(target[s])
        assert 0 <= r["taken"] <= 2 * r["size"]
    for s in names:
        assert sum(r["taken"] for r in got if sources[r["doc_id"]] == s) == pytest.approx(target[s], abs=1)
    assert mixing.mix(empty(spark)).count() == 0


def test_mixing_tree_is_exact(spark):
    split = mixing.split_quotas({"a": 1000, "b": 37, "c": 5}, 8, 3)
    assert split.sum(axis=0).tolist() == [1000, 37, 5]
    assert split.sum(axis=1).max() - split.sum(axis=1).min() <= 1
    plan = mixing.MixPlan(block_words=16, shards=4)
    rows = mixing.shard_blocks(docs_of(spark, EDGE, sources=list("abcabcabcabca")), plan).collect()
    assert len({(r["source"], r["block"]) for r in rows}) == len(rows)
    assert {r["shard"] for r in rows} == set(range(4))


def test_mixed_documents_match_the_plan(spark):
    d = docs_of(spark, EDGE, sources=list("abcabcabcabca"))
    taken = {r["doc_id"]: r["taken"] for r in mixing.mix(d).collect()}
    out = mixing.mixed_documents(d)
    assert out.columns == d.columns
    got = Counter()
    for r in out.collect():
        got[r["doc_id"]] += len(words(r["text"]))
    assert {i: n for i, n in taken.items() if n} == dict(got)


def test_mix_follows_the_blocks_of_the_tree(spark, monkeypatch):
    from pyspark.sql import functions as F

    plan = mixing.MixPlan(block_words=16, shards=4)
    d = docs_of(spark, EDGE + [f"t{i} {BASE}" for i in range(20)], sources=list("abcabcabcabca" + "abcab" * 4))
    taken = mixing.mix(d, plan).agg(F.sum("taken")).first()[0]
    blocks = {(r["source"], r["block"]): r["shard"] for r in mixing.shard_blocks(d, plan).collect()}
    _, copies = mixing.handed_out(runtime.materialize(mixing.sized(d, plan)), plan)
    source = {r["doc_id"]: r["source"] for r in d.collect()}
    rows = copies.collect()
    assert len({r["shard"] for r in rows}) == 4
    out = mixing.mixed_documents(d, plan).withColumn("shard", F.spark_partition_id()).collect()
    assert Counter(r["shard"] for r in out) == Counter(r["shard"] for r in rows)
    assert all(r["block"] == r["begin"] // 16 for r in rows)
    assert all(any(blocks.get((s, r["block"])) == r["shard"] for s in set(source.values())) for r in rows)
    real = mixing.owned_blocks
    monkeypatch.setattr(mixing, "owned_blocks", lambda targets, p: real(targets, p).filter("shard <> 0"))
    assert 0 < mixing.mix(d, plan).agg(F.sum("taken")).first()[0] < taken  # words of a shard left out are not taken


def brute_repeats(texts, width):
    seqs = [words(t) for t in texts]
    seen = Counter(tuple(s[i : i + width]) for s in seqs for i in range(len(s) - width + 1))
    out = []
    for s in seqs:
        gone = {i + k for i in range(len(s) - width + 1) if seen[tuple(s[i : i + width])] > 1 for k in range(width)}
        out.append((len(s), len(gone), hashlib.sha256(" ".join(w for i, w in enumerate(s) if i not in gone).encode()).hexdigest()))
    return out


@pytest.mark.parametrize("limit", [50_000, 1])
def test_repeats(spark, limit):
    passage = " ".join(f"p{i}" for i in range(40))
    rng = np.random.default_rng(3)
    noise = [" ".join(f"n{x}" for x in rng.integers(0, 5000, 120)) for _ in range(12)]
    texts = [*EDGE, *(f"{n}\n{passage}\t {m}" for n, m in zip(noise, noise[1:], strict=False)), passage + " " + passage, "a b " * 100]
    got = {r["doc_id"]: r for r in repeats.remove_repeats(docs_of(spark, texts), repeats.Repeats(group_limit=limit)).collect()}
    for i, want in enumerate(brute_repeats(texts, 35)):
        assert (got[i]["n_words"], got[i]["n_removed"], got[i]["kept_sha256"]) == want, i
    assert repeats.remove_repeats(empty(spark)).count() == 0


def test_repeated_rows_are_repeats(spark):
    d = docs_of(spark, [BASE])
    assert [r["n_removed"] for r in repeats.remove_repeats(d.unionAll(d)).collect()] == [300, 300]


def brute_components(texts, percent=90):
    sets = []
    for t in texts:
        ws = [w.translate({c: c + 32 for c in range(65, 91)}) for w in words(t)]
        sets.append({tuple(ws[i : i + 3]) for i in range(len(ws) - 2)} if len(ws) > 2 else {tuple(ws)} if ws else set())
    parent = list(range(len(texts)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return [(len(s), root(i)) for i, s in enumerate(sets)]


@pytest.mark.parametrize("seed", range(2))
def test_jaccard_components(spark, seed):
    rng = np.random.default_rng(seed)
    texts = list(EDGE)
    for family in range(4):
        base = [f"f{family}w{x}" for x in rng.integers(0, 400, 150)]
        for _ in range(14):
            copy = list(base)
            for at in rng.integers(0, 150, rng.integers(0, 5)):
                copy[at] = f"e{rng.integers(0, 10**6)}"
            texts.append(" ".join(copy))
    texts += [" ".join(["common line of words in many documents", *(f"u{x}" for x in rng.integers(0, 10**6, 20))]) for _ in range(25)]
    got = {r["doc_id"]: r for r in setjoin.jaccard_components(docs_of(spark, texts)).collect()}
    for i, want in enumerate(brute_components(texts)):
        assert (got[i]["n_shingles"], got[i]["component_id"]) == want, i


def test_jaccard_edges(spark):
    assert setjoin.jaccard_components(empty(spark)).count() == 0
    d = docs_of(spark, EDGE)
    kept = setjoin.keep_one(d.unionAll(d))
    assert kept.columns == d.columns
    groups = {c for _, c in brute_components(EDGE)}
    assert {r["doc_id"] for r in kept.collect()} == groups


def test_tokens_equal_the_library():
    path = tokens.vocabulary_path()
    odd = [*EDGE, "Don't it's I'LL 'em", "naïve Ünïcode Å ﬁ İstanbul", "x y 12ab3.c <|endoftext|>foo", "日本語 😀😀 éa ̈x", "word.,!;; ...|| a|b THE!! x$$$", "ΑΣ Σ"]
    ids, bounds = tokens.encode(pa.array(odd), path, 1)
    library = tokens.encoder(path).library
    for i, t in enumerate(odd):
        assert ids[bounds[i] : bounds[i + 1]].tolist() == [*library.encode(t or "", add_special_tokens=False).ids, 1], t


def test_packing(spark):
    how = packing.Packing(capacity=64)
    d = docs_of(spark, EDGE)
    rows = packing.pack(d.unionAll(d), how).collect()
    assert {r["doc_id"] for r in rows} == set(range(len(EDGE)))
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 64
    assert len(by) <= math.ceil(sum(r["length"] for r in rows) / 64) * 1.05 + 1
    ids, bounds = tokens.encode(pa.array(EDGE), tokens.vocabulary_path(), 1)
    for r in rows:
        own = ids[bounds[r["doc_id"]] : bounds[r["doc_id"] + 1]][r["start"] : r["start"] + r["length"]]
        assert r["ids_crc32"] == zlib.crc32(own.astype("<u4").tobytes())
    assert packing.pack(empty(spark), how).count() == 0


def test_best_fit_steps():
    rng = np.random.default_rng(0)
    sizes = dict(Counter(rng.integers(1, 100, 3000).tolist()))
    load = Counter()
    for size, lo, hi, first, per, _ in packing.best_fit(sizes, 100):
        for k in range(hi - lo):
            load[first + k // per] += size
    assert sum(load.values()) == sum(s * n for s, n in sizes.items()) and max(load.values()) <= 100
    assert len(load) <= math.ceil(sum(load.values()) / 100) * 1.02 + 1


PII = [
    "mail a.b+c@x-y.example.com, then d@e.f_g@h.i and 1.2.3.4 or 300.1.1.1 and 1.2.3.4.5.6.7.8",
    "card 4532 0151 1283 0366 bad 4532 0151 1283 0367, call +1 (724) 555-3457 or +1-2, ip 255.255.255.255",
    "@@@ a@b a@b.c.d +49 30 1234567 4524132264652876",
    None,
    "",
    "x" * 30_000 + "@y.zz " + "1" * 5000,
    "é😀 ü@x.yz q@w.ee",
]


def brute_spans(text):
    def luhn(d):
        return sum(c if i % 2 == 0 else (2 * c - 9 if c > 4 else 2 * c) for i, c in enumerate(map(int, reversed(d)))) % 10 == 0

    kinds = (("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"))
    out = []
    for k, (name, pattern) in enumerate(kinds):
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m.group())
            ok = {"email": True, "ip": all(int(x or 0) <= 255 for x in m.group().split(".")) if name == "ip" else True, "card": 14 <= len(digits) <= 19 and luhn(digits), "phone": 10 <= len(digits) <= 15}[name]
            if ok:
                out.append((m.start(), k, m.end(), name))
    return sorted(out)


def test_private_spans(spark):
    texts = [t for t in PII if t is None or len(t) < 10_000] + ["y" * 2000 + "@y.zz " + "1" * 3000]
    got = {r["doc_id"]: r for r in privacy.digest(docs_of(spark, texts)).collect()}
    for i, t in enumerate(texts):
        want = ",".join(f"{n}:{a}:{b}" for a, _, b, n in brute_spans(t))
        assert got[i]["base_sha256"] == hashlib.sha256(want.encode()).hexdigest(), (i, got[i]["spans"], want)
        assert set(filter(None, want.split(","))) <= set(got[i]["spans"].split(","))
    assert privacy.digest(empty(spark)).count() == 0


def test_disclosing_words_are_found_and_replaced(spark):
    texts = ["write to quirkyname at boss@corp.example.com today please friend"] * 4 + ["please write to the friend today " * 5] * 6
    spans = [r["spans"] for r in privacy.digest(docs_of(spark, texts)).orderBy("doc_id").collect()]
    assert "term:9:19" in spans[0] and "email:23:44" in spans[0]
    assert all("term" not in s for s in spans[4:])
    clean = privacy.sanitise(docs_of(spark, texts)).orderBy("doc_id").collect()
    assert "quirkyname" not in clean[0]["text"] and "[EMAIL]" in clean[0]["text"]
    assert clean[5]["text"] == texts[5]
    assert clean[0]["n_chars"] == len(clean[0]["text"])


def test_disclosing_words_go_wherever_they_stand(spark):
    near = "write to quirkyname at boss@corp.example.com today. " + "plain filler of many letters " * 6
    texts = [near] * 19 + [near + "Quirkyname, again", "quirkyname alone. мир", "x.QUIRKYNAME stays, é😀 quirkyname!"] + ["plain filler of many letters " * 6] * 9
    texts += ["письмо секретик на boss@corp.example.com сюда"] * 4 + ["слово секретик"]
    rows = privacy.digest(docs_of(spark, texts)).orderBy("doc_id").collect()
    told = [{tuple(map(int, s.split(":")[1:])) for s in r["spans"].split(",") if s.startswith("term")} for r in rows]
    for i, t in enumerate(texts):
        want = {m.span() for m in re.finditer(r"(?<!\S)(quirkyname|секретик)(?=[.,;:!?]*(\s|$))", t, re.I)}
        assert want <= told[i], (i, t)
    assert told[22] == set()
    clean = [r["text"] for r in privacy.sanitise(docs_of(spark, texts)).orderBy("doc_id").collect()]
    assert all("quirkyname" not in clean[i].lower() for i in (0, 19, 20)) and clean[21] == "x.QUIRKYNAME stays, é😀 !" and clean[22] == texts[22]


def test_disclosing_words_at_the_ends_of_texts(spark):
    filler = ["plain filler of many letters " * 6] * 12
    rows = privacy.digest(docs_of(spark, ["quirkyname boss@corp.example.com"] * 3 + ["boss@corp.example.com oddword"] * 4 + filler)).orderBy("doc_id").collect()
    assert all("term:0:10" in r["spans"] for r in rows[:3]) and all("term:22:29" in r["spans"] for r in rows[3:7])


def test_personal_data_in_very_long_texts(spark, tmp_path):
    """Many matches and long runs in one text take time in proportion to its length."""
    texts = ["7" * 300_000, "+1" * 100_000, "1.2.3.4 " * 30_000, "a@b.cc " * 30_000 + "tail", "x" * 200_000]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/d")
    docs = spark.read.parquet(f"{tmp_path}/d")
    rows = privacy.digest(docs).orderBy("doc_id").collect()
    assert [(r["n_email"], r["n_ip"], r["n_card"], r["n_phone"]) for r in rows] == [(0, 0, 0, 0), (0, 0, 0, 0), (0, 30_000, 0, 0), (30_000, 0, 0, 0), (0, 0, 0, 0)]
    assert rows[2]["spans"].split(",")[-1] == "ip:239992:239999"
    clean = [r["text"] for r in privacy.sanitise(docs).orderBy("doc_id").collect()]
    assert clean[2] == "[IP] " * 30_000 and clean[3] == "[EMAIL] " * 30_000 + "tail" and clean[0] == texts[0]


def test_best_fit_equals_item_by_item():
    rng = np.random.default_rng(3)
    for _ in range(200):
        sizes = Counter(rng.integers(1, 101, rng.integers(0, 80)).tolist())
        gaps = []
        for size in sorted(sizes.elements(), reverse=True):
            fit = min((g for g in gaps if g >= size), default=None)
            if fit is not None:
                gaps.remove(fit)
            gaps.append((100 if fit is None else fit) - size)
        steps = packing.best_fit(dict(sizes), 100)
        used = {first + k // per for _, lo, hi, first, per, _ in steps for k in range(hi - lo)}
        assert len(used) == len(gaps)
        held = Counter()
        for size, lo, hi, first, per, _ in steps:
            for k in range(hi - lo):
                held[first + k // per] += size
        assert sorted(100 - v for v in held.values()) == sorted(gaps)


def test_language(spark):
    en, fr = "the cat and the dog went to the house with this thing", "le chat et les chiens dans une maison avec été où"
    texts = [f"{(en, fr)[i % 2]} {i}" for i in range(80)] + [None, "", "123 456 !!", en * 300, fr]
    langs = [("en", "fr")[i % 2] for i in range(80)] + [None, None, "en", "en", None]
    how = language.Training(steps=150, documents_per_language=40)
    got = {r["doc_id"]: r for r in language.identify(docs_of(spark, texts, langs), how).collect()}
    right = [got[i]["lang_pred"] == langs[i] for i in range(80)]
    assert np.mean(right) > 0.95
    assert [got[i]["lang_pred"] for i in (80, 81, 82)] == ["und"] * 3
    assert got[83]["lang_pred"] == "en" and got[84]["lang_pred"] == "fr"
    assert all(0 <= r["score"] <= 1 and r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in got.values())
    assert language.identify(empty(spark), how).count() == 0
    assert {r["lang_pred"] for r in language.identify(docs_of(spark, EDGE, [None] * len(EDGE)), how).collect()} == {"und"}


def test_toxicity(spark):
    rng = np.random.default_rng(1)
    plain = lambda: " ".join(f"w{x}" for x in rng.integers(0, 300, 40))
    texts = [plain() + (" you stupid moron" if i % 4 == 0 else " zorkling zorkful" if i % 4 == 1 else "") for i in range(160)] + [None, ""]
    labels = spark.createDataFrame([(i, 1 if i % 4 < 2 else 0) for i in range(160)], "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity.toxicity(docs_of(spark, texts), labels).collect()}
    assert np.mean([got[i]["predicted"] == (i % 4 < 2) for i in range(160) if got[i]["held_out"]]) > 0.95
    assert got[160]["predicted"] == got[161]["predicted"] == 0
    assert all(r["predicted"] == int(r["score"] >= 0.3) for r in got.values())
    assert toxicity.toxicity(empty(spark), labels).count() == 0
    none = toxicity.toxicity(docs_of(spark, ["you stupid idiot", "fine day"]), labels.limit(0)).orderBy("doc_id").collect()
    assert none[0]["score"] > none[1]["score"]


def test_label_model_weighs_accurate_voters():
    rng = np.random.default_rng(0)
    y = rng.random(3000) < 0.2
    votes = np.stack([(rng.random(3000) < np.where(y, 0.6, 0.01)), (rng.random(3000) < np.where(y, 0.5, 0.01)), (rng.random(3000) < np.where(y, 0.3, 0.02))], axis=1).astype(np.float32)
    post, accuracy, _ = toxicity.label_model(votes, 0.2)
    assert np.mean((post > 0.5) == y) > 0.9 and (accuracy > 0.7).all()


TINY_LM = maxent.Maxent(fanout=3, frequent=6, share=4, tokens_per_weight=1, rounds=2, every=1)


def slow_log_share(model, last, before, leaf):
    """One token's log probability of its leaf, one class at a time."""
    u = lambda x: np.array([x], np.uint64)
    values = [wordhash.mix(u(last) ^ wordhash.MIX_A), wordhash.mix(u(last) * wordhash.STEP + u(before)), wordhash.mix(u(before) ^ wordhash.MIX_B)]
    out = 0.0
    for at in range(model.way[leaf], model.way[leaf + 1]):
        node, member = int(model.way_node[at]), int(model.way_member[at])
        z = model.prior[node].astype(float).copy()
        for v in values:
            row = int(((v[0] ^ wordhash.mix(u(node + 1))[0]) * wordhash.STEP) >> np.uint64(64 - int(len(model.weights)).bit_length() + 1))
            z += model.weights[row]
        out += z[member] - np.logaddexp.reduce(z)
    return out


def slow_score(model, counts, codes):
    """log10 probability of a text given by its token codes."""
    out, last, before = 0.0, maxent.START, maxent.START
    for k, code in enumerate(codes):
        own = np.flatnonzero(model.code == code)
        if len(own):
            out += slow_log_share(model, last, before, int(own[0]))
        elif int(code) in counts:
            place = int(code) >> (64 - model.place_bits) if model.place_bits else 0
            out += slow_log_share(model, last, before, len(model.code) + place) + math.log((counts[int(code)] + 1) / model.place_mass[place])
        else:
            out += slow_log_share(model, last, before, model.leaves - 1)
        before, last = (maxent.START if k == 0 else last), code
    return out / math.log(10)


def test_training_goes_through_every_class_on_every_way():
    rng = np.random.default_rng(4)
    vocabulary = np.sort(rng.integers(1, 1 << 63, 3000, dtype=np.uint64))
    code = np.append(vocabulary[rng.zipf(1.3, 9000) % 3000], maxent.END)
    bounds = np.array([0, len(code)])
    how = maxent.Maxent()
    model = maxent.untrained(vocabulary, np.full(3000, 3), np.empty(0), -1, len(code), 3000, how)
    maxent.gradient_steps(code, bounds, model, how)
    context, leaf = maxent.contexts(code, bounds), maxent.leaf_of(code, model)[0]
    token, _, rows, _, _ = maxent.softmax(context, leaf, model)
    assert len(token) == (model.way[leaf + 1] - model.way[leaf]).sum() > 2 * len(code)
    assert all((model.energy[r] > 0).all() for r in rows)
    one = maxent.untrained(vocabulary, np.full(3000, 3), np.empty(0), -1, len(code), 3000, how)
    maxent.gradient_steps(code[-40:], np.array([0, 40]), one, how)  # few tokens: hardly two share a row
    rows = np.unique(np.concatenate(maxent.softmax(maxent.contexts(code[-40:], np.array([0, 40])), leaf[-40:], one)[2]))
    assert (one.energy[rows] > 0).all() and (one.energy > 0).sum() == len(rows)


def test_language_model(spark):
    texts = ["the cat sat on the mat", "the cat ran", "a dog sat on the mat", None, "", "THE CAT sat", "new words only here"] + [f"the cat sat on mat number{i}" for i in range(60)] + ["the cat"] * 2
    docs = docs_of(spark, texts).union(docs_of(spark, texts[:2]))  # repeated rows too
    rows = maxent.language_model(docs, TINY_LM).collect()
    assert len(rows) == len(texts) + 2
    got = {r["doc_id"]: r for r in rows}
    toks = {i: [w.lower() for w in words(t)] + [None] for i, t in enumerate(texts)}
    c = Counter(w for i, t in [*toks.items(), (0, toks[0]), (1, toks[1])] if zlib.crc32(str(i).encode()) % 7 != 2 for w in t)
    n, v = sum(c.values()), len(c)
    for i, t in toks.items():
        r = got[i]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(t), sum(c[w] > 0 for w in t), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in t))
        assert r["score"] <= 0
    assert sum(r["score"] for r in got.values()) > sum(r["base_score"] for r in got.values())
    assert maxent.language_model(empty(spark)).count() == 0
    none = maxent.language_model(docs_of(spark, ["a b", None]), TINY_LM, out=F.lit(True)).collect()
    assert all(r["score"] == r["base_score"] == 0 and r["train_tokens"] == 0 for r in none)


def test_language_model_scores_equal_a_slow_twin(spark):
    texts = [f"a b c d{i % 5} e a b w{i}" for i in range(60)] + ["unknown words", "a b", "", "w3 w4 zz a"]
    docs = docs_of(spark, texts).select("text")
    model, table = maxent.train(docs.limit(60), TINY_LM)
    assert model.place_bits >= 1 and np.abs(model.weights).max() > 0.05
    counts = {r["code"] % (1 << 64): r["c"] for r in table.collect()}
    part = maxent.scored(docs.selectExpr("text", "cast(row_number() over (order by text) as bigint) rid", "0L doc_id", "false held_out"), model).collect()
    for text, r in zip(sorted(texts), sorted(part, key=lambda r: r["rid"]), strict=True):
        got = r["model_log"] + sum(x + math.log10(counts[code % (1 << 64)] + 1) for code, x in zip(r["rare"], r["extra"], strict=True) if code % (1 << 64) in counts)
        assert got == pytest.approx(slow_score(model, counts, maxent.token_codes(pa.array([text]))[0]), abs=1e-3)


def test_a_model_sent_to_a_task_has_built_in_types():
    """With copies of the types, as a pickle leaves them, indexed additions take some ten times longer."""
    rng = np.random.default_rng(5)
    vocabulary = np.sort(rng.integers(1, 1 << 63, 300, dtype=np.uint64))
    code = np.append(vocabulary[rng.zipf(1.3, 9000) % 300], maxent.END)
    here = maxent.untrained(vocabulary, np.full(300, 3), np.empty(0), -1, len(code), 300, maxent.Maxent())
    there = pickle.loads(cloudpickle.dumps(here))
    for model in (here, there):
        maxent.gradient_steps(code, np.array([0, len(code)]), model, maxent.Maxent())
    assert np.abs(here.weights).max() > 0.05
    for k, x in vars(here).items():
        if isinstance(x, np.ndarray):
            assert vars(there)[k].dtype is np.dtype(x.dtype.str), k
            assert np.array_equal(x, vars(there)[k]), k


def test_language_model_sums_to_one(spark):
    model, _ = maxent.train(docs_of(spark, [f"a b c d{i % 5} e a b w{i}" for i in range(40)]).select("text"), TINY_LM)
    leaf = np.arange(model.leaves)
    for last, before in ((maxent.START, maxent.START), (model.code[0], model.code[1]), (maxent.END, model.code[2])):
        context = np.repeat(maxent.contexts(np.array([before, last, maxent.END], np.uint64), np.array([0, 3]))[:, 2:], len(leaf), axis=1)
        assert np.exp(maxent.log_shares(context, leaf, model)).sum() == pytest.approx(1, abs=1e-4)
    mass = np.concatenate([model.count + 1.0, model.place_mass, [1.0]])
    model.weights[:] = 0  # untrained, it is the unigram model
    assert maxent.log_shares(context, leaf, model) == pytest.approx(np.log(np.maximum(mass, 1e-3) / mass.sum()), abs=1e-2)


def test_chroma(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(6, 64))
    vectors = [*base.tolist(), base[0].tolist(), (base[1] + 0.004 * rng.normal(size=64)).tolist(), None, []]
    how = chroma.Chroma(query_modulus=1)
    frame = spark.createDataFrame([(i, v) for i, v in enumerate(vectors)], "vec_id long, embedding array<double>")
    prints = chroma.fingerprints(chroma.melody_audio(frame, how), how)
    got = {r["vec_id"]: r for r in chroma.search(prints, how).collect()}
    assert got[6]["class_id"] == 0 and got[0]["n_class"] == 2
    own = {r["rec_id"]: np.array(r["codes"], np.int32).view(np.uint32) for r in prints.collect()}
    links = {(i, j) for i in range(8) for j in range(8) if i != j and len(own[i]) and np.unpackbits((own[i] ^ own[j]).view(np.uint8)).mean() <= how.most_errors}
    found = {(i, m["class_id"]) for i in range(8) for m in got[i]["matches"]}
    want = {(i, got[j]["class_id"]) for i, j in links if got[i]["class_id"] != got[j]["class_id"]}
    assert len(found & want) >= 0.9 * len(want) and (1, 7) in links
    assert got[8]["n_codes"] == got[9]["n_codes"] == 0
    assert chroma.search(chroma.fingerprints(chroma.melody_audio(frame.limit(0), how), how), how).count() == 0


def test_chroma_finds_noisy_copies_through_their_leader(spark):
    rng = np.random.default_rng(9)
    centre = rng.normal(size=64)
    vectors = [*rng.normal(size=(20, 64)).tolist(), centre.tolist(), *(centre + 0.05 * rng.normal(size=(60, 64))).tolist()]
    how = chroma.Chroma(query_modulus=1)
    frame = spark.createDataFrame([(i, v) for i, v in enumerate(vectors)], "vec_id long, embedding array<double>")
    prints = chroma.fingerprints(chroma.melody_audio(frame, how), how)
    rows = prints.withColumnRenamed("rec_id", "class_id")
    plan = chroma.key_plan(len(vectors), list(range(12)), how)
    led = chroma.followers(rows, plan, how).collect()
    assert led and not {r["f_id"] for r in led} & {r["leader"] for r in led}
    assert len({r["f_id"] for r in led}) == len(led)
    own = {r["rec_id"]: np.array(r["codes"], np.int32).view(np.uint32) for r in prints.collect()}
    errors = lambda i, j: int(np.unpackbits((own[i] ^ own[j]).view(np.uint8)).sum())
    assert all(errors(r["f_id"], r["leader"]) == r["f_errors"] <= how.most_errors * 32 * len(own[r["f_id"]]) for r in led)
    want = {(i, j): errors(i, j) for i in own for j in own if i != j and errors(i, j) <= how.most_errors * 32 * len(own[i])}
    found = {(r["vec_id"], m["class_id"]): m for r in chroma.search(prints, how).collect() for m in r["matches"]}
    assert len(want) > 500 and len(want.keys() & found.keys()) >= 0.9 * len(want)
    assert len(found) == len(set(found)) and all(m["bit_errors"] <= how.most_errors for m in found.values())


def test_chroma_aligns_shifted_audio(spark):
    rng = np.random.default_rng(4)
    how = chroma.Chroma(query_modulus=1)
    wave = chroma.rendered(rng.normal(size=(1, 64)), how)[0]
    frame = spark.createDataFrame([(0, wave.tobytes()), (1, wave[10 * how.hop :].tobytes())], "rec_id long, pcm binary")
    got = {r["vec_id"]: r["matches"] for r in chroma.search(chroma.fingerprints(frame, how), how).collect()}
    assert got[0][0]["class_id"] == 1 and got[0][0]["offset"] == -10


def test_chroma_recall_of_noisy_and_shifted_copies(spark, tiny):
    """Against all pairs at all offsets, on a real table with copies planted in it, at errors near the bound too."""
    rng = np.random.default_rng(6)
    how = chroma.Chroma(query_modulus=5)
    base = np.array([r["embedding"] for r in spark.read.parquet(f"{tiny}/embeddings.parquet").collect()])
    spread = np.sqrt((base**2).mean())
    noisy = [v + rng.normal(scale=s * spread, size=v.shape) for s in (0.02, 0.05, 0.1) for v in base[:40]]
    waves = [w for v in (base, np.array(noisy)) for w in chroma.rendered(v, how)] + [w[6 * how.hop :] for w in chroma.rendered(base[:20], how)]
    prints = chroma.fingerprints(spark.createDataFrame([(i, w.tobytes()) for i, w in enumerate(waves)], "rec_id long, pcm binary"), how)
    own = {r["rec_id"]: np.array(r["codes"], np.int32).view(np.uint32) for r in prints.collect()}
    assert len(own) == len(waves)
    want, bound = set(), how.most_errors
    for q in range(0, len(waves), 5):
        for r in own:
            if q == r or len(own[q]) < 16 or len(own[r]) < 16 or np.array_equal(own[q], own[r]):
                continue
            for offset in (0, 6, -6):
                a, b = own[q][max(0, -offset) :], own[r][max(0, offset) :]
                n = min(len(a), len(b))
                if n >= how.least_overlap and np.bitwise_count(a[:n] ^ b[:n]).mean() / 32 <= bound:
                    want.add((q, r))
    got = {(r["vec_id"], m["class_id"]) for r in chroma.search(prints, how).collect() if r["is_query"] for m in r["matches"]}
    assert len(want) >= 20 and len(got & want) >= 0.9 * len(want) and not got - want


def test_chroma_edges(spark):
    rows = [(None, [0.5] * 64, "x"), (5, [0.5] * 64, "y"), (5, [0.5] * 64, "y"), (7, [None] * 64, "z"), (20, [1.0], None), (40, None, None)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>, code string")
    out = chroma.search(chroma.fingerprints(chroma.melody_audio(frame))).collect()
    assert len(out) == 6 and all(r["matches"] == [] for r in out if r["is_query"]) and sum(r["is_query"] for r in out) == 2


def test_null_identifiers_and_columns(spark):
    rows = [(None, BASE), (None, None), (3, BASE), (4, "mail a@b.cc here")]
    d = spark.createDataFrame([(i, t, None, None, None, None, None, None, None) for i, t in rows], DOCS)
    labels = spark.createDataFrame([(3, None), (None, 1), (4, 0)], "doc_id long, toxic int")
    for out in (quality.quality_rules(d), mixing.mix(d), repeats.remove_repeats(d), privacy.digest(d), setjoin.jaccard_components(d), language.identify(d), toxicity.toxicity(d, labels)):
        assert out.count() == 4
    assert packing.pack(d).count() == 4
    assert setjoin.keep_one(d).count() == 4
    assert privacy.sanitise(d).count() == 4 and mixing.mixed_documents(d).columns == d.columns


def test_pipeline_stages(spark, tiny):
    """Each stage against what its operator decides, on the rows that the stage before it kept."""
    import corpus_pipeline

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    labels = spark.read.parquet(f"{tiny}/labels.parquet")
    kept = []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = corpus_pipeline.materialize(stage(spark, docs, tiny))
        if k + 1 < len(corpus_pipeline.STAGES):
            assert out.columns == docs.columns
        before, after = docs.collect(), out.collect()
        kept.append(len(after))
        texts = {r["doc_id"]: r["text"] for r in before}
        if name == "toxicity":
            told = {r["doc_id"]: r["predicted"] for r in toxicity.toxicity(docs, labels).collect()}
            assert sorted(r["doc_id"] for r in after) == sorted(i for i, x in told.items() if not x)
        elif name == "jaccard_join":
            sets = {i: {" ".join(w[j : j + 3]) for j in range(max(1, len(w) - 2))} if w else set() for i, w in ((i, words((t or "").lower())) for i, t in texts.items())}
            group = {i: i for i in texts}
            for i in sorted(texts):
                for j in sorted(texts):
                    if i < j and sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 90 * len(sets[i] | sets[j]):
                        a, b = group[i], group[j]
                        group = {x: min(a, b) if g in (a, b) else g for x, g in group.items()}
            assert sorted(r["doc_id"] for r in after) == sorted(set(group.values()))
        elif name == "sanitisation":
            assert sorted(r["doc_id"] for r in after) == sorted(texts)
            assert not any(re.search(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r["text"] or "") for r in after)
        elif name == "source_mixing":
            taken = {r["doc_id"]: r["taken"] for r in mixing.mix(docs).collect()}
            held = Counter()
            for r in after:
                held[r["doc_id"]] += len(words(r["text"]))
            assert held == Counter({i: n for i, n in taken.items() if n})
        else:
            ids = tokens.encode(pa.array([r["text"] for r in before]), tokens.vocabulary_path(), 1)[0]
            assert sum(r["length"] for r in after) == len(ids)
            full = Counter()
            for r in after:
                full[r["sequence_id"]] += r["length"]
            assert max(full.values()) <= 4096 and len(full) >= -(-len(ids) // 4096)
        docs = out
    assert kept[0] >= kept[1] == kept[2] > 0
    for texts, flags in ((["x"], []), (["you stupid moron idiot"] * 3, [(0, 1), (1, 1), (2, 1)])):  # nothing left for later stages
        docs = docs_of(spark, texts).select(*spark.read.parquet(f"{tiny}/documents.parquet").columns)
        docs = docs if flags else docs.limit(0)
        for _, stage in corpus_pipeline.STAGES[1:] if not flags else corpus_pipeline.STAGES[2:]:
            docs = corpus_pipeline.materialize(stage(spark, docs.limit(0), tiny))
        assert docs.count() == 0
