"""The hand-sized graph of FIXTURES A: twelve triples, eight signatures, one question."""

TRIPLES = [
    ("ann", "born_in", "oslo"), ("ann", "works_for", "acme"), ("ann", "won", "prize1"), ("ann", "speaks", "english"), ("oslo", "city_of", "norway"), ("norway", "official_language", "norwegian"),
    ("norway", "head_of_state", "harald"), ("acme", "based_in", "uk"), ("uk", "official_language", "english"), ("harald", "speaks", "danish"), ("bob", "born_in", "london"), ("london", "city_of", "uk"),
]
TYPES = {"ann": "person", "bob": "person", "harald": "person", "oslo": "city", "london": "city", "norway": "country", "uk": "country", "acme": "company", "prize1": "award", "english": "language", "norwegian": "language", "danish": "language"}
SIGS = [
    ("person", "born_in", "city"), ("person", "works_for", "company"), ("person", "won", "award"), ("person", "speaks", "language"), ("city", "city_of", "country"), ("country", "official_language", "language"),
    ("country", "head_of_state", "person"), ("company", "based_in", "country"),
]
QUESTION = [(1, "official language of the country where ann was born", "ann", 3, "constrained", "t", "test", "language", [("path", "born_in", "via", "")])]


def frames(spark):
    kg = spark.createDataFrame(TRIPLES, "head string, rel string, tail string")
    types = spark.createDataFrame(list(TYPES.items()), "entity string, etype string")
    sigs = spark.createDataFrame([(*s, 0, "declared") for s in SIGS], "head_type string, rel string, tail_type string, support long, source string")
    q = spark.createDataFrame(QUESTION, "qid long, text string, topic string, hops int, category string, template string, split string, etype string, constraints array<struct<target:string,rel:string,op:string,value:string>>")
    gold = spark.createDataFrame([(1, "norwegian")], "qid long, answer string")
    return kg, types, sigs, q, gold


def walks(topic, depth):
    """All walks of exactly `depth` edges by plain recursion: (relations, nodes)."""
    if depth == 0:
        return [((), (topic,))]
    return [(rels + (r,), nodes + (t,)) for rels, nodes in walks(topic, depth - 1) for h, r, t in TRIPLES if h == nodes[-1]]
