import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from latticecube.llm import decontam, graph, langid, mixing, neardup, pii, sharding, toxicity

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n int, value string"
#: Nulls, empty and blank texts, one very long text, repeated rows, and columns whose names the operators use inside.
ODD = [(None, None, None, None, 1, "v"), (None, "no key here at all", "en", "s1", 1, "v"), (900001, None, "en", None, 1, "v"), (900002, "", None, "s2", 1, "v"), (900003, " \n\t ", "fr", "s2", 1, "v"), (900004, "12345 ... !!", "de", "s3", 1, "v"), (900005, "word " * 30000, "en", "s3", 1, "v"), (900006, "twice the same row of words", "en", "s1", 1, "v"), (900006, "twice the same row of words", "en", "s1", 1, "v")]


def docs(spark, rows=(), odd=True):
    made = [(i, t, "en", "s1", 1, "v") for i, t in rows]
    return spark.createDataFrame(made + (ODD if odd else []), SCHEMA)


def table(spark, name):
    return spark.read.parquet(f"{SF}/{name}.parquet")


# near duplicates


def shingles(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").split(" ")
    words = [w for w in "".join(" " if c in "\t\n\x0b\f\r" else c for c in " ".join(words)).split(" ") if w]
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def near_brute(rows):
    sets = {i: shingles(t) for i, t in rows}
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                k = len(sets[a] & sets[b])
                if 100 * k >= 75 * (len(sets[a]) + len(sets[b]) - k):
                    x, y = sorted((find(a), find(b)))
                    parent[y] = x
    return {i: (len(s), find(i), find(i) == i) for i, s in sets.items()}


def test_near_duplicates_equal_brute_force(spark, monkeypatch):
    rng = random.Random(4)
    vocabulary = [f"w{i}" for i in range(400)]
    passage = [rng.choice(vocabulary) for _ in range(60)]
    rows = [(i, " ".join(rng.choice(vocabulary) for _ in range(rng.randrange(1, 150)))) for i in range(60)]
    rows += [(100 + i, " ".join(passage + [rng.choice(vocabulary) for _ in range(rng.randrange(0, 60))])) for i in range(40)]
    base = [rng.choice(vocabulary) for _ in range(140)]
    for i in range(70):  # near copies at both sides of the threshold, and copies of copies
        words = list(base)
        for _ in range(rng.randrange(0, 9)):
            words[rng.randrange(len(words))] = rng.choice(vocabulary)
        rows.append((200 + i, " ".join(words)))
    rows += [(300 + i, rows[5][1].upper()) for i in range(5)] + [(310, rows[5][1].replace(" ", "\t\n"))]
    monkeypatch.setattr(neardup, "CROWD", 8)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in neardup.near_duplicates(docs(spark, rows, odd=False)).collect()}
    assert got == near_brute(rows)


def test_near_duplicates_edges(spark):
    got = neardup.near_duplicates(docs(spark, [(1, "a b c d"), (2, "a b c d"), (3, "a b c")])).collect()
    by = {r.doc_id: r for r in got if r.doc_id is not None}
    assert len(got) == 12 and by[2].component_id == 1 and not by[2].kept and by[3].component_id == 3
    assert by[900003].n_shingles == 0 and by[900003].kept and by[900005].n_shingles == 1 and by[900006].kept
    assert all(r.component_id is None and r.kept for r in got if r.doc_id is None)
    assert neardup.near_duplicates(docs(spark, odd=False)).count() == 0


A, B = "one two three four five six seven eight", "red orange yellow green blue indigo violet white"


def test_repeated_ids_with_different_texts(spark):
    rows = [(3, A), (5, A), (5, B), (9, B), (9, B), (11, A + " nine"), (12, ""), (12, "alone here"), (None, A), (13, None), (13, "")]
    d = docs(spark, rows, odd=False)
    got = sorted((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in neardup.near_duplicates(d).collect() if r.doc_id is not None)
    assert got == sorted([(3, 4, 3, True), (5, 4, 3, False), (5, 4, 3, False), (9, 4, 3, False), (9, 4, 3, False), (11, 5, 3, False), (12, 0, 12, True), (12, 1, 12, True), (13, 0, 13, True), (13, 0, 13, True)])
    kept = neardup.survivors(d)
    assert kept.columns == d.columns
    stay = [(r.doc_id, r.text) for r in kept.collect()]
    assert Counter(t for _, t in stay) == Counter({A: 2, B: 1, "": 2, "alone here": 1, None: 1})  # A once more with the null id
    assert (3, A) in stay and (None, A) in stay and {(12, ""), (12, "alone here"), (13, ""), (13, None)} <= set(stay)


def test_hot_keys_are_joined_apart(spark, monkeypatch):
    from latticecube.llm import common

    left = spark.createDataFrame([(0 if i % 3 else i, i) for i in range(300)], "key long, v long")
    right = left.groupBy("key").agg(F.count("*").alias("size"))
    for rows in (5, 10_000):
        monkeypatch.setattr(common, "HOT_ROWS", rows)
        assert common.join_by_key(left, right, "key", "size").count() == 300
        assert common.join_by_key(left, right.where("key <> 3"), "key", "size", "left_semi").count() == 299
    plan = common.join_by_key(left, right.where("size > 5"), "key", "size")._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(common, "HOT_ROWS", 5)
    assert "Union" not in plan and "Union" in common.join_by_key(left, right, "key", "size")._jdf.queryExecution().executedPlan().toString()


def test_components(spark):
    rng = random.Random(1)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(200)] + [(i, i + 1) for i in range(1000, 1100)] + [(2000, i) for i in range(2001, 2100)]
    parent = {v: v for e in edges for v in e if e[0] != e[1]}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a != b:
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    got = {r.node: r.component for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {v: find(v) for v in parent}


def test_surnames_keep_their_ending_class():
    made, rng = pii.Surrogates(b"key"), random.Random(4)
    letters = "бвгджзйклмнпрстфхцчшщ", "аеёиоуыэюя"
    names = {"".join(rng.choice(letters[k]) for k in (0, 1, 1, 0)).capitalize() for _ in range(8000)}
    names |= {n[:2] + e for n in names for e in pii.ENDINGS}
    of = {n: made.of("surname", n) for n in names}
    assert len(set(of.values())) == len(of)
    assert all(pii._ending(n) == pii._ending(v) for n, v in of.items())


# decontamination


def test_decontamination_finds_substituted_passages(spark):
    rng = random.Random(2)
    word = lambda: rng.choice("abcdefgh") + str(rng.randrange(300))
    items = [(i, " ".join(word() for _ in range(rng.randrange(12, 40)))) for i in range(20)] + [(50, "only four words here"), (51, None), (52, "")]
    rows = []
    for i in range(60):
        own = [word() for _ in range(50)]
        if i % 3 == 0:
            passage = items[i % 20][1].split()
            for at in range(4, len(passage), 11):
                passage[at] = "replaced"
            own[20:20] = passage
        rows.append((i, " ".join(own).upper()))
    rows += [(100, "x only FOUR words here y"), (101, "only four other words here")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: r.contaminated for r in decontam.contaminated(docs(spark, rows), bench).collect() if r.doc_id is not None}
    assert all(got[i] == (i % 3 == 0) for i in range(60)) and got[100] and not got[101]
    assert not any(got[i] for i in range(900001, 900007))
    kept = decontam.clean(docs(spark, rows), bench)
    assert kept.columns == SCHEMA.replace(",", "").split()[::2] and kept.count() == len(rows) + len(ODD) - 21
    assert decontam.contaminated(docs(spark, rows), bench.limit(0)).where("contaminated").count() == 0
    assert decontam.contaminated(docs(spark, odd=False), bench).count() == 0


def test_decontamination_finds_excerpts_and_shifted_copies(spark):
    rng = random.Random(3)
    word = lambda: rng.choice("abcdefgh") + str(rng.randrange(5000))
    long, shifted, cut = ([word() for _ in range(n)] for n in (59, 45, 60))
    every = lambda words, k: [w for i in range(0, len(words), k) for w in [*words[i : i + k], "inserted"]]
    around = lambda words: [word() for _ in range(40)] + words + [word() for _ in range(40)]
    found = [
        around(long[15:44]), long[-20:] + around([]), around([]) + cut[:20], around([w if i % 5 else "other" for i, w in enumerate(long[:29])]),
        around(every(shifted, 15)), around(every(shifted, 10)), around(shifted[:12] + shifted[13:24] + shifted[25:36] + shifted[37:]),
        *(around([w if i % 3 != r else "third" for i, w in enumerate(shifted)]) for r in range(3)),
    ]
    clear = [around(long[20:25] + around([]) + long[40:47]), around(shifted[:6]), around([w if i % 2 else word() for i, w in enumerate(cut[:24])]), around(["one", "two", "three"])]
    # a short item's mask must not let a longer item's single words add up
    clear.append(around(rng.sample(long, len(long))))
    bench = spark.createDataFrame([(1, " ".join(long)), (2, " ".join(shifted)), (3, " ".join(cut)), (4, long[7]), (5, "one two four")], "item_id long, text string")
    rows = [(i, " ".join(w)) for i, w in enumerate(found + clear)]
    got = {r.doc_id: r for r in decontam.contaminated(docs(spark, rows, odd=False), bench.where("item_id <> 4")).collect()}
    assert [got[i].contaminated for i in range(len(rows))] == [True] * len(found) + [False] * len(clear)
    assert got[0].matched_words == 29 and got[0].n_items == 1
    kept = {r.doc_id for r in decontam.clean(docs(spark, rows, odd=False), bench.where("item_id <> 4")).collect()}
    assert kept == set(range(len(found), len(rows)))
    one = {r.doc_id: r.n_items for r in decontam.contaminated(docs(spark, rows[-1:], odd=False), bench).collect()}
    assert one == {len(rows) - 1: 1}


# mixing


def fill(cap, weight, budget):
    """Shares by rounds: whoever is full drops out and the rest share again."""
    out, open_ = dict.fromkeys(cap, 0.0), set(cap)
    left = float(budget)
    while open_ and left > 1e-9:
        w = sum(weight[c] for c in open_)
        full = {c for c in open_ if cap[c] - out[c] <= left * weight[c] / w + 1e-9}
        if not full:
            for c in open_:
                out[c] += left * weight[c] / w
            break
        for c in full:
            left -= cap[c] - out[c]
            out[c] = cap[c]
        open_ -= full
    return out


def test_budgets_fill_siblings_first(spark):
    leaves = spark.createDataFrame([("d0", "en", "a", 1, 100), ("d0", "en", "b", 1, 1000), ("d0", "fr", "c", 1, 50), ("d1", "en", "e", 1, 4000)], "domain string, lang string, source string, n_docs long, n_tokens long")
    weights = {"domain": {"d0": 0.5, "d1": 0.5}, "lang": {"en": 0.5, "fr": 0.5}, "source": {None: 1.0}}
    got = {r.source: r.budget for r in mixing.budgets(leaves, F.lit(2000), weights, 1).collect()}
    assert got == {"c": 50, "a": 100, "b": 850, "e": 1000}  # French is short: its sibling takes it, d1 doesn't
    got = {r.source: r.budget for r in mixing.budgets(leaves, F.lit(4000), weights, 1).collect()}
    assert got == {"c": 50, "a": 100, "b": 1000, "e": 2850}  # all of d0 is short: now d1 does
    rng = random.Random(6)
    for _ in range(3):
        cap = {f"s{i}": rng.randrange(1, 500) for i in range(8)}
        w = {k: rng.random() + 0.1 for k in cap}
        budget = rng.randrange(1, sum(cap.values()))
        rows = spark.createDataFrame([("d", "l", k, 1, v) for k, v in cap.items()], leaves.schema)
        got = {r.source: r.budget for r in mixing.budgets(rows, F.lit(budget), {"source": w}, 1).collect()}
        want = fill(cap, w, budget)
        assert all(abs(got[k] - want[k]) <= 1 for k in cap)


def test_mix_takes_prefixes_of_epochs(spark):
    rows = [(i, "w " * (1 + i % 5)) for i in range(200)]
    got = mixing.mix(docs(spark, rows), {}, 0.5, F.lit("d"), epochs=1).collect()
    total = sum(1 + i % 5 for i in range(200)) + 4 + 1 + 1 + 30000 + 6 + 6 + 1
    taken = sum(r.take_tokens for r in got)
    assert total / 2 - 12 <= taken <= total / 2 + 1 and all(0 < r.take_tokens <= r.n_tokens for r in got)
    assert sum(r.take_tokens < r.n_tokens for r in got) <= 6
    again = mixing.mix(docs(spark, rows), {}, 0.5, F.lit("d"), epochs=1).collect()
    assert Counter(map(tuple, got)) == Counter(map(tuple, again))
    all_ = mixing.mix(docs(spark, rows, odd=False), {}, 2.5, F.lit("d"), epochs=3).collect()
    assert Counter(r.epoch for r in all_)[0] == 200 and Counter(r.epoch for r in all_)[1] == 200 and 90 < Counter(r.epoch for r in all_)[2] < 110
    assert mixing.mix(docs(spark, odd=False), {}, 0.5, F.lit("d")).count() == 0


# shards


def test_shards(spark, tmp_path):
    store = sharding.ShardStore(spark, f"file://{tmp_path}/s", target_bytes=40_000, smallest=500, fanout=3)
    with pytest.raises(ValueError):
        store.read()
    all_rows = []
    for i in range(7):
        rows = [(100 * i + j, f"text {i} {j} " * 5) for j in range(20)]
        all_rows += rows
        store.append(docs(spark, rows, odd=i == 0).coalesce(1))
    before = store.version()
    want = Counter(tuple(r) for r in docs(spark, all_rows).collect())
    assert store.compact() >= 1
    assert Counter(tuple(r) for r in store.read().collect()) == want == Counter(tuple(r) for r in store.read(before).collect())
    assert len(store.manifest()["shards"]) < 7 and store.plan(store.manifest()["shards"]) == []
    old = store.manifest()
    store.append(docs(spark, [(1, "x")], odd=False))
    with pytest.raises(sharding.Conflict):
        store.commit(old, [], old["schema"])
    with pytest.raises(ValueError):
        store.append(spark.range(3))
    assert store.expire() > 0 and store.read().count() == sum(want.values()) + 1
    store.append(docs(spark, odd=False))
    assert store.read().count() == sum(want.values()) + 1


def test_shard_writers_in_each_others_way(spark, tmp_path, monkeypatch):
    store, other = (sharding.ShardStore(spark, f"file://{tmp_path}/s", target_bytes=40_000, smallest=500, fanout=3) for _ in range(2))
    for i in range(4):
        store.append(docs(spark, [(i, f"text {i}")], odd=False).coalesce(1))
    # an arrival that another writer has stored but not committed survives, and a commit in between is no failure
    waiting = other._stored(docs(spark, [(50, "waits")], odd=False).coalesce(1), f"{other.root}/data/waiting")
    commit, raced = store.commit, []

    def beaten(old, shards, schema):
        if not raced:
            raced.append(other._added(waiting, schema))
        return commit(old, shards, schema)

    monkeypatch.setattr(store, "commit", beaten)
    assert store.compact() >= 1 and store.expire() > 0
    assert {r.doc_id for r in store.read().collect()} == {0, 1, 2, 3, 50}
    # a run that gains nothing doesn't keep the others from being merged
    sizes = [{"uri": f"big{i}", "bytes": 29_000, "tier": 3} for i in range(3)]
    monkeypatch.setattr(store, "plan", lambda shards, plan=store.plan: [r for r in ([sizes] if len(shards) > 1 else [])] + plan(shards))
    for i in range(3):
        store.append(docs(spark, [(60 + i, "x")], odd=False).coalesce(1))
    before = len(store.manifest()["shards"])
    monkeypatch.setattr(store, "target", 20_000)
    sizes[:] = [s | {"bytes": 20_000} for s in sizes]
    store.compact()
    assert len(store.manifest()["shards"]) < before
    clash = docs(spark, [(1, "a")], odd=False).withColumn("__arrival", F.lit(7))
    made, _, _ = sharding.sharded(clash, f"file://{tmp_path}/c", 4, 1 << 20, 100)
    assert made.read().columns == clash.columns and made.read().count() == 1


# personal data


def test_surrogates_are_bijections():
    k = pii.Keyed(b"k")
    for n in (2, 3, 10, 255, 1000):
        got = [k.step(x, n, "t") for x in range(n)]
        assert sorted(got) == list(range(n)) and all(a != b for a, b in enumerate(got))
    s = pii.Surrogates(b"k")
    assert len({s.of("ssn", f"{i:03d}-00-0000") for i in range(1000)}) == 1000
    assert len({s.of("given", n) for n in pii.GIVEN["latin", "f"]}) == len(pii.GIVEN["latin", "f"])


def test_surrogates_keep_type_and_coreference(spark):
    text = "Mrs Anna Smith (anna.smith@mail1.example.com, +1 (643) 555-5742) paid with 4111 1111 1111 1111 from 10.20.30.40. Smith said token = \"73d74656391396c3efc1d06034ff6aa0\". Not a card: 4111 1111 1111 1112."
    new, made = pii.replace(text, pii.Surrogates(b"k"))
    kinds = [k for k, _, _ in made]
    assert kinds == ["given", "surname", "email", "phone", "card", "ip", "surname", "secret"]
    assert all(v not in new for k, v, _ in made) and "4111 1111 1111 1112" in new
    by = {k: s for k, _, s in made}
    assert by["given"] in pii.GIVEN["latin", "f"] and pii.luhn(by["card"].replace(" ", "")) == 0
    assert made[1][2] == made[6][2] and by["phone"].startswith("+1 (") and by["email"].endswith(".com")
    assert [(s, e - s) for s, e, _ in pii.find(new)][0][0] == text.index("Anna")
    assert pii.replace("Господин Иванов, Ольга Петрова", pii.Surrogates(b"k"))[0] not in ("Господин Иванов, Ольга Петрова",)
    assert pii.replace(text, pii.Surrogates(b"other"))[0] != new
    df = docs(spark, [(1, text), (2, text), (3, "nothing here")])
    got = {r.doc_id: r for r in pii.surrogates(df, b"k").collect()}
    assert got[1].text == got[2].text == new and got[3].n_entities == 0 and got[900001].text is None and got[900002].text == ""
    assert pii.collisions(df, b"k").count() == 0 and pii.entities(df, b"k").count() == 16
    whole = pii.checked(df, b"k")
    assert sorted(map(str, whole.drop("n_collisions").collect())) == sorted(map(str, got_all := pii.surrogates(df, b"k").collect())) and len(got_all) == df.count()
    assert {r.n_collisions for r in whole.collect()} == {0}


def test_surrogates_over_whole_domains():
    """Every value of a format: all surrogates differ, none is its own value, and each keeps its class."""
    made = pii.Surrogates(b"domain")
    latin = [a + b + c for a in "BCDFGHJKLMNPQRSTVWXZ" for b in "aeiouy" for c in "bcdfghjklmnpqrstvwxz"]
    cyrillic = [a + b + c + d for a in "БВГДЖ" for b in "аеёиоуыэюя" for c in "бвгджзйклмнпрстфхцчшщ" for d in ("", "ин", "ов", "ова", "ая")]
    for kind, domain in (("surname", [n for n in latin if n not in pii._given]), ("surname", cyrillic), ("forename", [n for n in latin if n not in pii._given]), ("initial", list("BCDFGHJKLMNPQRSTVWXZ")), ("ssn", [f"{i:03d}-11-2222" for i in range(1000)])):
        of = {v: made.of(kind, v) for v in domain}
        assert len(set(of.values())) == len(domain) and all(a != b and len(a) == len(b) for a, b in of.items())
        if kind == "surname":
            assert all(pii._ending(a) == pii._ending(b) for a, b in of.items())
        if kind == "forename":
            assert all(a[-1] == b[-1] for a, b in of.items())
    # secrets of the hexadecimal kind and others never meet
    secrets = [f"{i:016x}" for i in range(300)] + ["bcdf" * 4 + c for c in "bcdfghjk"] + ["fdcb" * 4, "k" * 16]
    assert len({made.of("secret", v) for v in secrets}) == len(secrets)
    assert all(bool(pii._is_hex(v)) == bool(pii._is_hex(made.of("secret", v))) for v in secrets)


@pytest.mark.parametrize("text, kinds", [
    ("Mr Žižek met Dr Łukasz Wałęsa and Mr A. Smith, then José García. Žižek left.", ["surname", "given", "surname", "initial", "surname", "given", "surname", "surname"]),
    ("Şahin wrote to Mr Şahin and Mrs Priya Natarajan.", ["surname", "surname", "forename", "surname"]),
    ("Господин Бефер. Господин Банин. Госпожа Їжакевич.", ["surname"] * 3),
    ("Κύριος Παπαδόπουλος", ["surname"]), ("王先生, 田中さん", ["surname"] * 2),
    ("2001:db8::ff00:42:8329 and 2001:DB8::FF00:42:8329", ["ip6"] * 2), ("call 020 7946 0958", ["phone"]),
    ("anna@x.рф, jörg@firma.de", ["email"] * 2), ("SSN 123-45-6789, IBAN DE89 3704 0044 0532 0130 00", ["ssn", "iban"]),
    ("at 10:20:30, ratio 3:4:5, std::vector, a::b, 0800 is a number", []),
])
def test_entities_of_many_scripts(text, kinds):
    new, made = pii.replace(text, pii.Surrogates(b"k"))
    assert [k for k, _, _ in made] == kinds
    assert all(v not in new for k, v, _ in made if len(v) > 1 and k != "given") and len(new) - len(text) in range(-8, 9)
    assert len({s for _, _, s in made}) == len({v for _, v, _ in made})
    script = lambda c: "".join(x for x in pii.ALPHABETS if c in x) or c
    for k, v, s in made:
        if k in ("surname", "initial", "email", "phone", "ssn"):
            assert [script(c) for c in v] == [script(c) for c in s]


def test_collisions_are_counted(spark, monkeypatch):
    monkeypatch.setattr(pii.Surrogates, "of", lambda self, kind, value: "same", raising=True)
    bad = pii.replace("Mr Black and Mr White", pii.Surrogates(b"k"))
    assert bad[0] == "Mr same and Mr same"  # counted by the check, and nothing raises


# models


def test_language_on_held_out_rows(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    both = langid.identify(d, langid.train(d)).join(d.select("doc_id", "lang"), "doc_id").where("held_out")
    n, right = both.count(), both.where("lang = lang_pred").count()
    assert right / n > 0.97
    got = {r.doc_id: r for r in langid.identify(docs(spark), langid.train(d)).collect() if r.doc_id}
    assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (900001, 900002, 900003, 900004))
    assert all(r.lang_pred == "und" for r in langid.identify(docs(spark), None).collect())
    one = langid.train(docs(spark, [(i, f"some words {i}") for i in range(20)]).where("lang = 'en'"))
    assert {r.lang_pred for r in langid.identify(docs(spark), one).collect()} == {"en", "und"}
    assert langid.train(docs(spark, odd=False)) is None


def test_language_sample_reaches_the_driver_packed(spark, monkeypatch):
    for text in ("a few words", "word " * 30000, "straße " * 70000, "x"):
        counts = langid.trigrams(text)
        assert (langid.shares(langid.unpacked(langid.packed(counts), langid.WIDTH)) == langid.features(text)).all()
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got, collect = [], type(d).collect
    monkeypatch.setattr(type(d), "collect", lambda self: got.append(collect(self)) or got[-1])
    assert langid.train(d) is not None
    sizes = [len(r["x"]) for r in got[-1]]
    assert len(sizes) > 500 and sum(sizes) <= 2 * len(sizes) * langid.WIDTH  # floats would be four bytes each


def test_driver_gives_freed_memory_back(spark, monkeypatch):
    from latticecube.llm import common

    assert "Trim native heap" in common.driver_gives_back(spark)
    calls = []
    monkeypatch.setattr(common, "driver_gives_back", calls.append)
    monkeypatch.setattr(common, "_given_back", [0.0])
    for _ in range(2):
        common.written(spark.range(3), "test-give-back")
    assert len(calls) == 1  # not at every table


def test_toxicity_ignores_neutral_mentions(spark):
    rng = random.Random(3)
    neutral = [f"w{i}" for i in range(200)]
    rows, labels = [], []
    for i in range(900):
        bad = i % 5 == 0
        words = [rng.choice(neutral) for _ in range(30)]
        if bad:
            words += rng.sample(["vileword", "nastyterm", "awfulone"], 2)
        if rng.random() < (0.6 if bad else 0.05):  # the sample's labels are biased against one group
            words.append("muslim")
        rng.shuffle(words)
        rows.append((i, " ".join(words)))
        labels.append((i, int(bad)))
    lab = spark.createDataFrame([*labels, (900006, None), (7, None)], "doc_id long, toxic int")
    d = docs(spark, rows)
    model = toxicity.train(d, lab)
    got = toxicity.score(d, model).join(lab, "doc_id").where("held_out").collect()
    assert sum((r.predicted == 1) == (r.toxic == 1) for r in got) / len(got) > 0.97
    plain = "the muslim families met at the market"
    assert model.score(plain) < 0.5 and abs(model.score(plain) - model.score(plain.replace("muslim", "christian"))) < 0.1
    scored = {r.doc_id: r for r in toxicity.score(d, model).collect()}
    assert 0 <= scored[900001].score <= 1 and scored[900002].predicted == 0
    none = toxicity.train(d, lab.limit(0))
    assert {r.predicted for r in toxicity.score(d, none).collect()} == {0}


def test_pipeline_stages(spark):
    import corpus_pipeline

    d = table(spark, "documents").unionByName(docs(spark, [(800000 + i, "the same words again and again here") for i in range(3)]).selectExpr("doc_id", "text", "lang", "source", "cast(length(text) as long) AS n_chars"))
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "near_duplicates", "decontamination", "mixing", "token_output"]
    sizes = []
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, d, SF)
        assert out.columns == d.columns
        from latticecube.llm import common

        d = common.written(out, "test-stage")
        sizes.append(d.count())
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 0
    assert d.where("doc_id in (800001, 800002, 900001, 900002)").count() == 0
    last = corpus_pipeline.STAGES[-1][1](spark, d, SF)
    assert last.count() == d.count()
