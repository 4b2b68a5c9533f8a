"""The pipeline on planted documents, the queries on a small table, and the operators against brute force where SQL can't follow."""

import math
import random
import re
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from overlapsolve.llm import langid, piece_codec, quality_model, quality_rules, queries, secret_scan, simhash, toxicity
from overlapsolve.llm.hashing import ngram_buckets
from tests.llm.test_documents import AWKWARD, PIECES, labels_of, prose, table


def saved(spark, folder, docs, labels):
    docs.write.parquet(f"{folder}/documents.parquet")
    labels.write.parquet(f"{folder}/labels.parquet")
    return str(folder)


SECRET = "deadbeef" * 5


def planted():
    """(texts, the ids that should be left). Ids count from 1."""
    r, texts, left = random.Random(8), [], []
    for k in range(40):
        w = prose(150 + k, 900 + k).split()
        texts.append(" ".join(w))
        left.append(len(texts))
        if k % 4 == 0:  # a copy, a near copy, a cut one
            edited = list(w)
            edited[r.randrange(len(w))] = "changed"
            texts += [" ".join(w), " ".join(edited), " ".join(w[: len(w) * 9 // 10])]
        if k % 5 == 0:
            texts += ["too short", "again and again " * 60]
    texts.append(prose(90, 5) + f' token = "{SECRET}" ' + prose(90, 6))
    left.append(len(texts))
    return [*texts, None, ""], left


def test_pipeline_does_what_its_stages_say(spark, tmp_path):
    texts, left = planted()
    docs = table(spark, texts).withColumn("_gone", F.lit(1)).withColumn("_copy", F.lit(2)).withColumn("id", F.lit(3)).withColumn("node", F.lit("x"))
    labels = labels_of(spark, [(k, 1, 0) for k in range(1, len(texts), 3)])
    got = corpus_pipeline.run(spark, saved(spark, tmp_path, docs, labels)).collect()
    tokenizer = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    # By brute force: rules, then copies by exact comparison of windows, then the base patterns' values replaced.
    judged = {r.doc_id: r.kept for r in quality_rules.judge(docs).collect()}
    assert {k for k, v in judged.items() if v} >= set(left)
    assert {r.doc_id for r in got} == set(left)
    pieces = Counter()
    for r in got:
        pieces[r.doc_id] += r.length
    for k in left:
        text = re.sub(r'token = "[0-9a-f]{40}', "[secret]", texts[k - 1])
        assert pieces[k] == len(tokenizer.encode(text, add_special_tokens=False).ids) + 1


def test_stages_keep_columns_and_take_awkward_tables(spark, tmp_path):
    docs = table(spark, AWKWARD).withColumn("_gone", F.lit(1)).withColumn("_id", F.lit(2)).withColumn("gram", F.lit(3)).withColumn("weight0", F.lit(4)).union(table(spark, [prose(80, 70)] * 2, 50).select(F.lit(None).cast("long"), "text", "lang", "source", "n_chars", "row", "words", "fp", "kept", "low", F.lit(1), F.lit(2), F.lit(3), F.lit(4)))
    folder = saved(spark, tmp_path, docs, labels_of(spark, [(5, 1, 0), (None, 1, None), (6, None, None)]))
    for frame in (docs, docs.limit(0)):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, frame, folder)
            assert name == "packing" or out.columns == docs.columns
            assert out.count() >= 0


def test_a_poor_document_that_passes_the_rules_is_rejected(spark):
    good = [prose(120, k) for k in range(200)]
    odd = [" ".join(["the", "of"] + [random.Random(k * 7 + i).choice(["zzqx", "qqzj", "xjxq", "jzqz"]) for i in range(118)]) for k in range(20)]
    docs = table(spark, good + odd)
    kept = quality_model.kept_documents(docs, labels_of(spark, [(k, 1, 0) for k in range(1, 201, 2)]))
    assert {r.doc_id for r in kept.collect()} == set(range(1, 201))


def test_weights_equal_brute_force(spark):
    texts = [prose(40 + k, k) for k in range(30)]
    docs, labels = table(spark, texts), labels_of(spark, [(k, int(k % 3 == 0), 0) for k in range(1, 25)])
    bits, strength, margin = quality_model.BITS, 30.0, 0.05
    counts = [Counter(ngram_buckets([t.encode()], bits)[1].tolist()) for t in texts]
    target = [k for k in range(1, 25) if k % 3 == 0]
    raw, good = sum(counts, Counter()), sum((counts[k - 1] for k in target), Counter())
    for r in quality_model.weighed(docs, quality_model.fit(docs, labels)).collect():
        own, inside = counts[r.doc_id - 1], r.doc_id in target
        grams = sum(own.values())
        want = 0.0
        for g, n in own.items():
            other = (raw[g] - n + 1) / (sum(raw.values()) - grams + (1 << bits))
            expected = (sum(good.values()) - grams * inside) * other
            want += n * (math.log((strength + good[g] - n * inside) / (strength + expected)) + margin)
        assert r.log_weight == pytest.approx(want)


def test_draws_are_applied_to_rows_without_an_id(spark):
    odd = [" ".join(random.Random(k).choice(["zzqx", "qqzj", "xjxq"]) for _ in range(120)) for k in range(12)]
    docs = table(spark, [prose(120, k) for k in range(60)]).union(table(spark, [*odd, prose(100, 99)]).withColumn("doc_id", F.lit(None).cast("long")))
    kept = quality_model.kept_documents(docs, labels_of(spark, [(k, 1, 0) for k in range(1, 60, 2)]))
    assert {r.text for r in kept.where("doc_id is null").collect()} == {prose(100, 99)}


def test_near_copies_recall_on_the_given_table(spark):
    """Against an exact join of all pairs that share a window: recall is 1 and nothing else is tied."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = [(r.doc_id, frozenset(np.unique(simhash.shingle_hashes((r.text or "").encode(), 5)).tolist())) for r in docs.collect()]
    index: dict[int, list[int]] = {}
    for i, (_, s) in enumerate(rows):
        for g in s:
            index.setdefault(g, []).append(i)
    root = {k: k for k, _ in rows}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (a, s) in enumerate(rows):
        shared = Counter(j for g in s for j in index[g] if j < i)
        for j, n in shared.items():
            if n >= 0.8 * (len(s) + len(rows[j][1]) - n):
                x, y = sorted((find(a), find(rows[j][0])))
                root[y] = x
    tied = {r.doc_id: r.component_id for r in simhash.similar_copies(docs).collect()}
    assert {k: tied.get(k, k) for k, s in rows if s} == {k: find(k) for k, s in rows if s}


def naive_segment(chunk, pieces, limit, key):
    """The agenda as a plain search for the best pair that hasn't been skipped."""
    parts = [(i, c if c != " " else piece_codec.MARK) for i, c in enumerate(chunk)]
    gone, n = set(), 0
    while True:
        best = min(((pieces.ranks[a + b], i, len(a), len(b), k) for k, ((i, a), (_, b)) in enumerate(zip(parts, parts[1:], strict=False)) if a + b in pieces.ranks and (i, len(a), len(b)) not in gone), default=None)
        if best is None:
            break
        _, i, first, second, k = best
        if piece_codec.skipped(key, n, limit):
            gone.add((i, first, second))
        else:
            parts[k : k + 2] = [(i, parts[k][1] + parts[k + 1][1])]
        n += 1
    out = []
    for _, p in parts:
        out += [pieces.ids[p]] if p in pieces.ids else [pieces.byte_ids[b] for b in p.replace(piece_codec.MARK, " ").encode()]
    return out


def test_short_chunks_are_segmented_as_long_ones():
    pieces = piece_codec.Pieces(public_tokenizers.path("piece_bpe_32k.model"))
    rng = np.random.default_rng(5)
    chunks = ["", "a", "   ", " aaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaa", " straightforwardness", "  \u4e00x\x00", " \xe9\xe0\xfc\u2026" * 6, *("".join(rng.choice(list(" aeinst\xe9"), 12)) for _ in range(300))]
    for chunk in chunks:
        for limit in (0, 1 << 29, 1 << 31):
            key = int(rng.integers(1 << 62))
            mask = piece_codec.decisions(np.array([key], np.uint64), limit)[0] if limit else 0
            assert piece_codec.segment_short(chunk, pieces, limit, key, mask) == piece_codec.segment(chunk, pieces, limit, key, mask)



def test_dropout_equals_a_naive_agenda():
    pieces = piece_codec.Pieces(PIECES)
    text = " ".join(prose(300, 12).split() + ["internationalisation", "über", "日本語", "a" * 40] * 6)
    for dropout in (0.1, 0.5):
        limit = int(dropout * 2**32)
        encoder = piece_codec.Encoder(pieces, dropout, seed=3)
        encoder.encode(text, 5)  # what is kept from another document changes nothing
        chunks = pieces.chunks.findall(text)
        keys = piece_codec.chunk_keys(9, 3, len(chunks))
        assert encoder.encode(text, 9).tolist() == [x for c, k in zip(chunks, keys, strict=True) for x in naive_segment(c, pieces, limit, int(k))]


def test_many_chunks_are_segmented_in_step_as_each_alone(monkeypatch):
    alone = piece_codec.segment
    pieces = piece_codec.Pieces(PIECES)
    rng = np.random.default_rng(6)
    odd = ["", "   ", "\u2581 a\u2581\u2581 b", "\u4e00\u9fff\U0001f600 x\u2581\U0001f600", " " + "=" * 48, "\xe9t\xe9  \x00\u2026 ", " \n a\nb"]
    texts = odd + [" ".join("".join(rng.choice(list("aeinst\xe9"), rng.integers(1, 14))) for _ in range(400)) for _ in range(5)] + odd
    ids = [0, -3, 2**62, *range(3, len(texts))]

    def both(pieces, dropout, texts):
        encoder = piece_codec.Encoder(pieces, dropout, seed=4)
        got = [x.tolist() for x in encoder.encode_all(texts, ids)]
        for text, doc_id, found in zip(texts, ids, got, strict=True):
            chunks = pieces.chunks.findall(text)
            keys = piece_codec.chunk_keys(doc_id, 4, len(chunks))
            masks = piece_codec.decisions(keys, encoder.limit) if encoder.limit else [0] * len(chunks)
            assert found == [x for c, k, m in zip(chunks, keys, masks, strict=True) for x in alone(c, pieces, encoder.limit, int(k), m)[0]]

    with monkeypatch.context() as none_alone:
        for name in ("segment", "segment_short"):
            none_alone.setattr(piece_codec, name, None)
        assert len(piece_codec.Encoder(pieces, 0.1).encode(texts[len(odd)], 1)) > 400  # no chunk goes alone
        for dropout in (0.0, 0.1, 0.6):
            both(pieces, dropout, [t for t in texts if "=" not in t] + ["", ""])
    long = [t + "0" * 60 + t for t in texts]  # also chunks that are taken alone, and texts that are cut
    monkeypatch.setattr(piece_codec, "GROUP", 500)
    both(pieces, 0.1, long)
    for p in ("\xe9", "s"):  # characters that only longer pieces hold, and equal scores
        del pieces.ids[p]
    pieces.ranks = {p: r // 40 for p, r in pieces.ranks.items() if p in pieces.ids}
    both(pieces, 0.3, long)


def test_occurrences_of_a_word_vary():
    pieces = piece_codec.Pieces(PIECES)
    encoder = piece_codec.Encoder(pieces, 0.1)
    found = set()
    for doc in range(200):
        ids = encoder.encode(" internationally", doc).tolist()
        assert pieces.decode(ids) == b" internationally"
        found.add(tuple(ids))
    assert len(found) > 8


def test_the_field_finds_what_the_base_patterns_cannot(spark):
    texts = [prose(120, k) for k in range(60)] + [prose(60, k) + f' token = "{random.Random(k).getrandbits(160):040x}" ' + prose(60, k + 500) for k in range(40)]
    field = secret_scan.train(table(spark, texts))
    r = random.Random(5)
    of = lambda chars, n: "".join(r.choice(chars) for _ in range(n))
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
    hits = extra = 0
    for k in range(100):
        value = [of(letters + "0123456789", 32), "ghx_" + of(letters + "0123456789", 36), of("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 24), of(letters + "0123456789+/", 44)][k % 4]
        head = prose(40, 2000 + k) + [' pwd = "', " Bearer ", ' credentials: "', " "][k // 4 % 4]
        text = head + value + " " + prose(40, 3000 + k)
        assert not secret_scan.base_spans(text)
        spans = secret_scan.spans_of([text], field)[0]
        hits += any(a <= len(head) and b >= len(head) + len(value) for a, b, _ in spans)
        extra += sum(b <= len(head) or a >= len(head) + len(value) for a, b, _ in spans)
    assert hits >= 90 and extra <= 3
    plain = [prose(200, 7000 + k) + " 4716 5582 4444 2221, 4716558244442221 or 192.168.10.20 or a.person.77@mail3.example.com on 2024-05-06, see /usr/share/doc/readme-2.1.html" for k in range(50)]
    assert sum(len(s) for s in secret_scan.spans_of(plain, field)) <= 2
    assert secret_scan.scan(table(spark, texts), field).agg(F.sum("n_marked")).first()[0] >= 36


def test_ordinal_fit_is_a_likelihood_maximum():
    bad = ["vile", "awful", "nasty", "rotten"]
    texts = [(prose(40, k) + (" " + " ".join(random.Random(k).sample(bad, 1 + k % 4)) if k % 3 == 0 and k % 15 else "")).encode() for k in range(300)]
    toxic = np.arange(300) % 3 == 0
    model = toxicity.fit(texts, toxic, rounds=1500, ridge=0.0)
    doc, bucket = toxicity.distinct_buckets(texts)
    evidence = toxicity.screened(doc, bucket, toxic)
    amount = np.bincount(doc, weights=evidence[bucket], minlength=300)
    steps = np.quantile(amount[toxic & (amount > 0)], [1 / 3, 2 / 3])
    score = np.bincount(doc, weights=model.weights[bucket], minlength=300)

    def loss(cuts, factor=1.0):
        total = 0.0
        for s, t, a in zip(score * factor, toxic, amount, strict=True):
            below = [0, *(1 / (1 + math.exp(-(c - s))) for c in cuts), 1]
            g = (1 + int(np.searchsorted(steps, a, side="right"))) if t and a > 0 else 0
            total -= math.log(max(1e-300, 1 - below[1] if t and a == 0 else below[g + 1] - below[g]))
        return total

    best = loss(model.cuts)
    for k in range(3):
        for step in (-0.3, 0.3):
            moved = model.cuts.copy()
            moved[k] += step
            assert loss(moved) > best
    assert loss(model.cuts, 0.8) > best and loss(model.cuts * 0.9) > best


def test_language_posteriors_equal_brute_force(spark):
    say = {"en": ["the house and", "this that"], "de": ["der hund und", "nicht auch"], "fr": ["le chat et", "avec pour"]}
    r, names = random.Random(3), sorted(say)
    docs = spark.createDataFrame([(k, " ".join(r.choice(say[names[k % 3]]) for _ in range(6)), names[k % 3]) for k in range(60)], "doc_id long, text string, lang string")
    model = langid.train(docs)
    pages = []
    for k in range(80):
        lang = names[k % 3]
        html = "<!--" + "x" * 6000 + f'--><html lang="{lang}">' if k % 2 else ""
        pages.append((k, f"https://{'www' if k % 4 else 'news'}.site{k % 5}.{lang}/{lang}/{k}", html + " ".join(r.choice(say[r.choice(names) if k % 7 == 0 else lang]) for _ in range(2))))
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    found = {x.id: x for x in langid.of_pages(df, model).collect()}
    part = lambda u: (u.split("/")[2], ".".join(u.split("/")[2].split(".")[-2:]), u.split("/")[2].split(".")[-1] + "/" + u.split("/")[3])
    ll = {k: model.likelihoods([langid.visible(h.encode())], 0.2)[0] for k, _, h in pages}
    guess = {k: int(np.argmax(v)) for k, v in ll.items()}
    said = {k: (m[1] if (m := re.search('<html lang="(..)"', h)) else "") for k, _, h in pages}
    count = lambda want: np.array([sum(guess[k] == g for k, u, _ in pages if want(k, u)) for g in range(3)], float)
    whole = count(lambda k, u: True)
    top = (whole + 1) / (whole + 1).sum()
    ends = {part(u)[2] for _, u, _ in pages}
    domain = [*names, "", "other"]
    declared = np.array([0.1 + count(lambda k, u, d=d: said[k] == d) for d in domain])
    declared = np.log(declared / declared.sum(axis=0))
    for k, u, _ in pages:
        host, site, end = part(u)
        ns, nh = count(lambda j, v, s=site: part(v)[1] == s), count(lambda j, v, h=host: part(v)[0] == h)
        mid = (ns + 5 * top) / (ns.sum() + 5)
        prior = (nh + 5 * mid) / (nh.sum() + 5)
        s = ll[k] + np.log(prior) + declared[domain.index(said[k])] + np.log((count(lambda j, v, e=end: part(v)[2] == e) + 0.5) / (whole + 0.5 * len(ends)))
        p = np.exp(s - s.max())
        assert found[k].lang == names[int(np.argmax(s))] and found[k].probability == pytest.approx((p / p.sum()).max(), abs=2e-6)


def test_every_query_returns_its_whole_table(spark):
    folder = "/root/testdata/sf0.001"
    docs, pages = (spark.read.parquet(f"{folder}/{t}.parquet").count() for t in ("documents", "pages"))
    rows = {"op8_warc": pages, "op5_language_id": docs + pages}
    for name, query in queries.queries().items():
        got = query(spark, folder)
        if name == "op6_packing":
            assert got.select("doc_id").distinct().count() == docs
        elif name != "op9_topk_search":
            assert got.count() == rows.get(name, docs), name


def test_long_texts_meet_by_blocks_only_if_they_can_be_similar():
    """Single windows made every two long texts meet that share a passage: pairs grew with the square of the long texts."""
    rng = np.random.default_rng(3)
    passage = rng.integers(1 << 63, size=100, dtype=np.uint64)
    long = [np.unique(np.concatenate([passage, rng.integers(1 << 63, size=int(n), dtype=np.uint64)])) for n in rng.integers(1500, 6000, 60)]
    keys = [simhash._block_keys(h, 0.8, np.isin(h, passage)) for h in long]
    assert all(sure for _, sure in keys)
    assert not any(np.isin(keys[a][0], keys[b][0]).any() for a in range(60) for b in range(a))
    for h, (k, _) in zip(long, keys, strict=True):  # every kind of set that is just similar enough shares a block
        n = len(h)
        fewer = rng.permutation(h)[: -(-n * 4 // 5)]
        more = np.concatenate([h, rng.integers(1 << 63, size=n // 4, dtype=np.uint64)])
        other = np.concatenate([rng.permutation(h)[: n - n // 9], rng.integers(1 << 63, size=n // 9, dtype=np.uint64)])
        for x in map(np.unique, (fewer, more, other)):
            assert len(np.intersect1d(h, x)) >= 0.8 * len(np.union1d(h, x))
            assert np.isin(simhash._block_keys(x, 0.8, np.isin(x, passage))[0], k).any()


def test_many_near_copies_that_are_not_similar_make_few_pairs(spark, monkeypatch):
    """Long copies with a fifth of their windows changed shared so much with each other that nearly every two were compared."""
    r, base = random.Random(4), prose(2500, 77).split()
    texts = []
    for k in range(150):
        w = list(base)
        for i in r.sample(range(len(w)), 105):
            w[i] = f"w{k}x{i}"
        texts.append(" ".join(w))
    w = texts[20].split()  # similar to one of them, shorter
    texts += [" ".join(w[:2100]), " ".join(w[300:])]
    compared, possible = [], simhash._still_possible

    def counted(pairs, *rest):
        compared.append(pairs.count())
        return possible(pairs, *rest)

    monkeypatch.setattr(simhash, "_still_possible", counted)
    tied = {x.doc_id: x.component_id for x in simhash.similar_copies(table(spark, texts)).collect()}
    assert tied == {21: 21, 151: 21, 152: 21}
    assert sum(compared) < 10 * len(texts)
