"""Template windows and slot consistency against hand-made leaks and a brute-force search."""

import random

from deltahop.llm import decontaminate as dc

ITEM = "if Alice buys 12 apples at 3 dollars and gives 4 apples to Bob how many apples does Alice have left after 12 days"


def leaked(spark, texts, items, rules=None):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    bench = spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string")
    return {(r.doc_id, r.item_id): r for r in dc.leaks(docs, bench, rules).collect()}


def test_reparameterised_item_needs_consistent_slots(spark):
    new = ITEM.replace("Alice", "Carol").replace("Bob", "Dave").replace("12", "15").replace("dollars", "euros").replace(" 4 ", " 9 ")
    wrong = new.replace("Carol have", "Erin have").replace("after 15", "after 99")
    noise = "some words before it and then "
    got = leaked(spark, [noise + ITEM + ".", new, noise + wrong, noise, None, "", ITEM[: len(ITEM) // 5]], [ITEM, None, ""])
    assert got[0, 0].leaked and got[0, 0].exact
    assert got[1, 0].leaked and not got[1, 0].exact
    assert not got[2, 0].leaked
    assert all(not r.leaked for (d, _), r in got.items() if d > 2)


def test_changed_words_do_not_hide_a_copy(spark):
    two = "The red fox runs over a long field near some old farm. The farmer sees how it hunts for mice until evening comes"
    sums = "what is the sum of 3 and 4 if both are written in words and added on paper by hand"
    race = "when Alice has run 5 km along a quiet river she tells Bob that Alice will rest for 20 minutes and then run 7 km more"
    texts = [
        "so it goes " + two.replace("The farmer", "This farmer") + " and so on",
        sums.replace("3 and 4", "5 and 5"),
        race.replace("Alice", "Mary Ann").replace("5 km", "6km").replace("Bob", "Carol").replace("20 minutes", "45 s").replace("7 km", "8km"),
        race.replace("along a quiet", "along one very quiet").replace("tells Bob", "then tells Bob"),
        "the sum of 3 and 4 is 7 and she tells Bob that it is so near some old farm",
        race.replace("when Alice", "when Eve").replace("Bob that Alice", "Carol that Dora").replace("5 km", "6 km").replace("20", "45").replace("7", "8"),
    ]
    got = leaked(spark, texts, [two, sums, race])
    assert {k for k, r in got.items() if r.leaked} == {(0, 0), (1, 1), (2, 2), (3, 2)}
    assert not any(got[k].exact for k in [(0, 0), (1, 1), (2, 2)])


def test_short_items_and_odd_rows(spark, odd_docs):
    got = leaked(spark, ["x what is the answer y", "what was the answer"], ["what is the answer"])
    assert set(got) == {(0, 0)} and got[0, 0].leaked
    bench = spark.createDataFrame([(1, "seven eight nine ten"), (1, "seven eight nine ten")], "item_id bigint, text string")
    rows = dc.leaks(odd_docs, bench).collect()
    assert {r.doc_id for r in rows} == {1} and len(rows) == 4
    kept = dc.without_leaks(odd_docs, bench)
    assert kept.columns == odd_docs.columns and kept.count() == odd_docs.count() - 2
    assert dc.without_leaks(odd_docs, bench.limit(0)).count() == odd_docs.count()
    assert dc.leaks(odd_docs.limit(0), bench).collect() == []


def test_verbatim_passages_match_brute_force_in_blocks(spark):
    rng = random.Random(2)
    word = lambda: f"w{rng.choice('abcdefgh')}{rng.choice('abcdefgh')}"
    items = [" ".join(word() for _ in range(rng.randint(9, 25))) for _ in range(30)]
    texts = []
    for _ in range(120):
        t = " ".join(word() for _ in range(rng.randint(0, 60)))
        if rng.random() < 0.4:
            t += " " + rng.choice(items) + " " + word()
        texts.append(t)
    want = {(d, i) for d, t in enumerate(texts) for i, b in enumerate(items) if f" {b} " in f" {t} "}
    got = leaked(spark, texts, items, dc.LeakRules(bits=256, pairs=7))
    assert {k for k, r in got.items() if r.coverage == 1.0 and r.exact} == want and want


def test_reparameterised_items_by_construction(spark):
    """Templates of literal words with recurring slots: new values given alike are leaks, values given at random aren't."""
    rng = random.Random(11)
    literal = lambda: "".join(rng.choice("bcdfglmnprst") + rng.choice("aeiou") for _ in range(3))
    names = ["Alice", "Bruno", "Carla", "Dieter", "Elena", "Fausto", "Greta", "Hugo", "Irene", "Jonas", "Karin", "Luis"]
    value = {"N": lambda: str(rng.randint(2, 9999)), "P": lambda: rng.choice(names)}
    fill = lambda template, given: " ".join(given[w] if w in given else w for w in template)
    items, texts, want = [], [], set()
    for i in range(25):
        slots = ["N1", "P1", "N2", "P2"]
        template = [literal(), literal()]
        for s in rng.sample(slots * 3, 12):
            template += [s, literal(), literal()]
        fresh = lambda: dict(zip(slots, [value["N"](), names[rng.randrange(6)], value["N"](), names[6 + rng.randrange(6)]], strict=True))
        given, other = fresh(), fresh()
        while set(given.values()) & set(other.values()):
            other = fresh()
        items.append(fill(template, given))
        around = lambda t: f"{literal()} {literal()} {t} {literal()}"
        want |= {(len(texts), i), (len(texts) + 1, i)}
        texts += [around(items[-1]), around(fill(template, other))]
        texts.append(around(" ".join(value[w[0]]() if w in slots else w for w in template)))  # each slot another value
        texts.append(around(" ".join(literal() if w not in slots else given[w] for w in template)))  # another template
    got = leaked(spark, texts, items, dc.LeakRules(bits=1 << 12))
    assert {k for k, r in got.items() if r.leaked} == want
    assert all((4 * i + 2, i) in got for i in range(25))
