import itertools

from joinlearn.llm import common, queries, toxicity


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_automaton_matches_edit_distance():
    terms = {"abcab": 1.0, "bacca": 1.0, "abc": 1.0}
    a = toxicity.Automaton(terms)
    for n in range(1, 7):
        for w in map("".join, itertools.product("abc", repeat=n)):
            want = min(((distance(w, t), t) for t in terms if distance(w, t) <= (1 if len(t) >= 5 else 0)), default=None)
            got = a.match(w)
            assert (got[0] > 0) == (want is not None), w
            if want and got[0]:
                assert got[1] == want[0]
            if got[0]:
                assert a.head(w[:4])


def test_stems_context_and_quotation():
    a = toxicity.Automaton({"lowei*": 2.0, "idiot": 2.0})
    assert a.match("loweischaft") == (2.0, 0) and a.match("idiots") == (1.0, 1) and a.match("ideal") == (0.0, 0)
    plain, quoted = toxicity.hits_of("you idiot", a), toxicity.hits_of('the word "idiot" is old', a)
    assert toxicity.evidence(plain)[0] > toxicity.evidence(quoted)[0] > 0
    near, far = toxicity.hits_of("idiot idiot", a), toxicity.hits_of("idiot " + "x " * 50 + "idiot", a)
    assert toxicity.evidence(near)[0] > toxicity.evidence(far)[0]


def test_held_out_accuracy(spark, sf01):
    marks = {r.doc_id: r.toxic for r in common.table(spark, sf01, "labels").collect()}
    held = [r for r in queries.op8_toxicity(spark, sf01).collect() if r.held_out and r.doc_id in marks]
    right = sum(r.predicted == marks[r.doc_id] for r in held)
    assert right / len(held) > 0.95
    assert sum(r.predicted and not marks[r.doc_id] for r in held) <= 2


def test_odd_rows(spark, odd_docs, no_docs):
    labels = spark.createDataFrame([(1, 1, 0), (5, 0, 1), (7, 1, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    model = toxicity.learn(odd_docs, labels)
    got = toxicity.score(odd_docs, model, odd_docs.columns[:5])
    assert got.count() == odd_docs.count() and all(0 <= r.score <= 1 for r in got.collect())
    assert toxicity.score(no_docs, toxicity.learn(no_docs, labels.limit(0)), ["doc_id"]).count() == 0


def test_long_quotations_reports_and_misspellings():
    a = toxicity.Automaton({"scum": 2.0, "idiot": 2.0, "lowei*": 2.0}, **toxicity.LOOSE)
    quoted = lambda t: [q for *_, q in toxicity.hits_of(t, a)]
    assert quoted('she wrote "you are a stupid idiot" and left') == [True] and quoted("er rief „du bist ein idiot“ laut") == [True]
    assert quoted("the word idiot is old") == [True] and quoted("you stupid idiot") == [False]
    assert quoted('5" pipe, you idiot') == [False] and quoted('"so what\n\nyou idiot"') == [False] and quoted('"yes" you idiot "no"') == [False]
    for w in ("idoit", "scun", "scmu", "lwoeischaft"):
        assert a.match(w) == (1.0, 1) and a.head(w[:4]), w
