"""Entry points; the training-data operators may be absent."""

import importlib

import __spark_entry__
from edgemill import catalogue


def test_entry_has_rows(spark):
    df = __spark_entry__.entry(spark)
    assert df.columns == ["id", "off", "deg"] and df.count() == 211


def test_every_oracle_has_a_query():
    entry = importlib.reload(__spark_entry__)
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(catalogue.ENTRIES) > 130


#: S7 (in-memory rows) is what the tests themselves use; F6 (no scalar Python function on edge-sized paths) is a rule.
IDS = """P1 P1a P1b P1c P2 P3 P4 P5 P6 P7 E1 E1a E1b E1c E1d E1e E1f E2 E3 RL1 RL1a RL1b RL2 RL2a RL2b RL2c RL2d RL3 RL4 RL5 RL6 RL7 RL8 RL9 R1 R1a R2 R3 R4 R5 R5a R6
K1 K2 K2a K2b K2c K3 K4 K5 K6 K7 D1 D2 D3 D4 D5 B1 B2 B3 B4 B5 B6 B7 B8 W1 W2 W3 W4 W5 W6 W7 W8 W9 W10 W11 S1 S2 S3 S4 S5 S6 S8 S9 O1 O2 J1 J2 J3 J4 J5 J6 J7 J8 J9 J10 J11 J12 J13
AG1 AG2 AG3 AG4 AG5 AG6 AG7 AG8 AG9 N1 N2 N3 N4 T1 T2 T3 T4 T5 U1 U2 U3 math hash string time array map struct json null F1 F2 F3 F4 F5 Z1 Z2 Z3 Z4 Z5 Z6 Z7 Z8 Z9""".split()


def test_survey_ids_are_covered():
    covered = catalogue.coverage()
    assert [k for k in IDS + [f"C{k}" for k in range(1, 19)] + [f"V{k}" for k in range(1, 13)] if k not in covered] == []


def test_all_but_few_queries_have_sql():
    catalogue.queries()
    assert [n for n, e in catalogue.ENTRIES.items() if not e.sql] == ["plan_costs"]
