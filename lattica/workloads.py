"""The experiment's rules on the given tables, in the text form."""

from __future__ import annotations

from .operators.validate import fd_rule
from .rules.ast import Rule
from .rules.parser import parse_rule

PATH = "match (a:MAIN)-[co]-(b:MAIN), (b)-[co]-(c:MAIN)"
STAR = "match (a:SIDE)-[co]-(b:SIDE), (a)-[co]-(c:SIDE), (a)-[co]-(d:SIDE)"
TRIANGLE = "match (a:MAIN)-[co]-(b:MAIN), (b)-[co]-(c:MAIN), (a)-[co]-(c)"
TEXTS = {
    # copurchase
    "path3": f"{PATH} where a.dormant = true and b.dormant = true and c.dormant = true then b.tied = true",
    "path3_strict": f"{PATH} where a.dormant = true and b.dormant = true and c.dormant = true then b.size_ge45 = true",
    "star3": f"{STAR} then a.dormant = false",
    "star3_holds": f"{STAR} then a.size = a.size",
    "triangle": f"{TRIANGLE} where a.dormant = true and b.dormant = true then c.dormant = true",
    "kite": f"{TRIANGLE}, (a)-[co]-(d:MAIN) where a.dormant = true and b.dormant = true then c.dormant = true",
    "tail_kite": f"match (a:MAIN)-[co]-(d:MAIN), {TRIANGLE[6:].replace('(a:MAIN)', '(a)', 1)} where a.dormant = true and b.dormant = true then c.dormant = true",
    # trade
    "two_places": "match (x:order)-[shipped_by]->(y:supplier), (x)-[shipped_by]->(z:supplier) then y.nation = z.nation",
    "two_places_wild": "match (x:order)-[shipped_by]->(y:_), (x)-[shipped_by]->(z:_) then y.nation = z.nation",
    "never_both": "match (x:order)-[contains]->(y:part), (x)-[contains]->(z:part) where y.brand = 'Brand#1' and z.brand = 'Brand#2' then false",
    "home_cycle": "match (c:customer)-[placed]->(o:order)-[shipped_by]->(s:supplier)-[based_in]->(n:nation), (c)-[based_in]->(n) then false",
    "home_cycle_tail": "match (c:customer)-[placed]->(o:order)-[shipped_by]->(s:supplier)-[based_in]->(n:nation), (c)-[based_in]->(n), (o)-[contains]->(p:part) then false",
    # docs
    "typing_doc": "match (x:_) then x.quality = x.quality",
    "dup_label": "match (x:_)-[same_text]-(y:_) then x.quality = y.quality",
    "dup_label_x": "match (x:_)-[same_text]-(y:_) where x.quality = 1 then y.quality = 1",
    # sessions, dialogue, web, similar
    "chain3": "match (a:signup)-[next]->(b:error)-[next]->(c:purchase) then false",
    "turn_taking": "match (x:assistant)-[next]->(y:_) then y.role = 'user'",
    "turn_broken": "match (x:assistant)-[next]->(y:_) then y.role = 'assistant'",
    "opening_broken": "match (x:system)-[next]->(y:_) then y.role = 'assistant'",
    "opening": "match (x:system)-[next]->(y:_) then y.role = 'user'",
    "host_lang": "match (x:page)-[on_host]->(h:host), (y:page)-[on_host]->(h) then x.lang = y.lang",
    "similar_triangle": "match (a:_)-[near]-(b:_), (b)-[near]-(c:_), (a)-[near]-(c) then a.label = b.label",
}
GRAPH_OF = {
    "copurchase": ["path3", "path3_strict", "star3", "star3_holds", "triangle", "kite", "tail_kite"],
    "trade": ["two_places", "two_places_wild", "never_both", "home_cycle", "home_cycle_tail"],
    "docs": ["typing_doc", "dup_label", "dup_label_x"],
    "sessions": ["chain3"],
    "dialogue": ["turn_taking", "opening", "turn_broken", "opening_broken"],
    "web": ["host_lang"],
    "similar": ["similar_triangle"],
}


def rule(name: str) -> Rule:
    if name == "fd_part":
        return fd_rule("fd_part", None, ["name", "brand"], ["ptype"])
    return parse_rule(TEXTS[name], name)


def graph_name(name: str) -> str:
    return "copurchase" if name == "fd_part" else next(g for g, names in GRAPH_OF.items() if name in names)
