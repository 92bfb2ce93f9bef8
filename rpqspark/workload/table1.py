"""The pattern workload on graphs of the given tables."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Query:
    id: str
    pattern: str
    graph: str
    s: str | None
    path: str
    o: str | None


_ROWS = """
w01 | v /* c | web | | on_host/parent* | host:com
w02 | v * c | web | | parent* | host:example.com
w02b | v * c | pulse | | click_1* | user:7
w03 | v + c | flow | | error+ | user:7
w03b | v + c | pulse | | error_3+ | user:7
w04 | c * v | pulse | user:7 | click_1* |
w04b | c * v | flow | user:7 | click* |
w05 | c /* v | web | page:0 | on_host/parent* |
w06 | v / c | trade | | placed_by/lives_in | nation:3
w07 | v */* c | pulse | | click_1*/view_2* | user:7
w07b | v */* c | chat | | user*/assistant* | turn:5.4
w08 | v / v | trade | | lives_in/in_region |
w09 | v {|}* c | pulse | | (error_3{|}click_1)* | user:7
w09b | v {|}* c | chat | | (user{|}assistant)* | turn:5.4
w10 | v {|} v | trade | | lives_in{|}based_in |
w11 | v */*/*/*/* c | pulse | | view_0*/click_1*/purchase_2*/signup_3*/error_4* | user:7
w12 | v ^ v | trade | | ^supplied_by |
w13 | v /* v | web | | on_host/parent* |
w14 | v * v | chat | | (user{|}assistant)* |
w14b | v * v | pulse | | error_3* |
w15 | v /? c | trade | | lives_in/in_region? | region:2
w16 | v + v | pulse | | error_3+ |
w16b | v + v | flow | | error+ |
w17 | v /+ c | web | | on_host/parent+ | host:com
w18 | v {|}{|} v | trade | | lives_in{|}based_in{|}in_region |
w19 | v {|} c | trade | | lives_in{|}based_in | nation:3
w20 | v /^ v | trade | | based_in/^lives_in |
w21 | c //^ c | trade | order:0 | placed_by/lives_in/^based_in | supplier:7
w22 | c /^* v | pulse | user:7 | (error_3/^error_3)* |
w23 | c ^// v | trade | brand:Brand#17 | ^of_brand/supplied_by/based_in |
w24 | c {|}+/ v | succ | part:0 | (A{|}R)+/N |
"""


def _read(line: str) -> Query:
    a = [x.strip().replace("{|}", "|") for x in line.replace("{|}", "\0").split("|")]
    a = [x.replace("\0", "|") for x in a]
    return Query(a[0], a[1], a[2], a[3] or None, a[4], a[5] or None)


QUERIES = {q.id: q for q in map(_read, _ROWS.strip().splitlines())}

# How often each pattern occurs in the published log of 1,952 queries.
FREQUENCIES = {
    "v /* c": 537, "v * c": 433, "v + c": 109, "c * v": 99, "c /* v": 95, "v / c": 54, "v */* c": 44, "v / v": 41, "v |* c": 36, "v | v": 31,
    "v */*/*/*/* c": 28, "v ^ v": 26, "v /* v": 25, "v * v": 25, "v /? c": 22, "v + v": 17, "v /+ c": 12, "v || v": 10, "v | c": 10, "v /^ v": 7,
}
