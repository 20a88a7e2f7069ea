"""Error types: one slot of a reserved vocabulary range each; slot 0 is "no error"."""

from __future__ import annotations

from dataclasses import dataclass

RESERVED = 32
#: Fixed value: the two words that the null token starts from.
NULL_WORDS = ("correct", "sql")


@dataclass(frozen=True)
class ErrorType:
    slot: int
    code: str
    family: str
    priority: int
    words: tuple[str, ...]
    guideline: str
    active: bool = True


#: Slot, code, family, priority (structure before detail).
TYPES = [
    ErrorType(1, "table_missing", "table", 1, ("missing", "table"), "join {table} along {edge}; {columns} are not covered"),
    ErrorType(2, "table_redundant", "table", 1, ("extra", "redundant", "unnecessary", "columns"), "drop {table}; nothing asks for it"),
    ErrorType(3, "table_wrong", "table", 1, ("wrong", "table"), "read {table} in place of {used}"),
    ErrorType(4, "join_key_wrong", "join", 2, ("wrong", "join", "key"), "join on {edge}"),
    ErrorType(5, "column_missing", "attribute", 3, ("missing", "column"), "also return {column}"),
    ErrorType(6, "column_redundant", "attribute", 3, ("redundant", "column"), "do not return {column}"),
    ErrorType(7, "column_wrong", "attribute", 3, ("wrong", "column"), "use {column} in place of {used}"),
    ErrorType(8, "value_mismatch", "value", 4, ("value", "mismatch"), "write {value} in place of {used}"),
    ErrorType(9, "condition_missing", "condition", 4, ("missing", "condition"), "add {predicate}"),
    ErrorType(10, "condition_wrong", "condition", 4, ("wrong", "condition"), "change {predicate}"),
    ErrorType(11, "function_wrong", "function", 5, ("wrong", "function"), "use {function} in place of {used}"),
    ErrorType(12, "clause_wrong", "clause", 6, ("wrong", "clause"), "change {clause}"),
    ErrorType(13, "subquery_wrong", "subquery", 2, ("wrong", "subquery"), "change {predicate}", False),
    ErrorType(14, "operator_wrong", "operator", 4, ("wrong", "operator"), "use {operator} in place of {used}", False),
]
BY_SLOT = {t.slot: t for t in TYPES}
PRIORITY = {t.slot: t.priority for t in TYPES}


#: Nine categories of an annotated benchmark, and the slots that fall into each.
CATEGORIES = {
    "attribute": (5, 6, 7), "table": (1, 2, 3), "join": (4,), "value": (8,), "condition": (9, 10),
    "function": (11,), "clause": (12,), "subquery": (13,), "operator": (14,),
}
CATEGORY_OF = {slot: name for name, slots in CATEGORIES.items() for slot in slots}

#: Scope of the extraction by type: which nodes' smallest subtree is taken
#: ("nodes", or a clause of the query), and how far the schema goes ("table":
#: tables, their keys and neighbours; "column": the elements alone).
SCOPE = {
    1: ("from", "table"), 2: ("from", "table"), 3: ("from", "table"), 4: ("nodes", "table"), 5: ("select", "column"), 6: ("select", "column"), 7: ("nodes", "column"),
    8: ("nodes", "column"), 9: ("where", "column"), 10: ("nodes", "column"), 11: ("nodes", "column"), 12: ("nodes", "column"), 13: ("nodes", "table"), 14: ("nodes", "column"),
}


def active_slots(growth: bool = False) -> list[int]:
    """Slots in use; ``growth`` switches the reserved two on as well."""
    slots = [t.slot for t in TYPES if t.active or growth]
    if len(slots) > RESERVED:
        raise ValueError("more types than reserved tokens")
    return slots
