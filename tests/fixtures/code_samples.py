"""Short sources, and cases for the format rules."""

from leakaudit.sources.examples import CODE_SAMPLES  # noqa: F401

#: (rule, text, line, column): the rule fires there; the twin text without the fault doesn't fire it.
LINT_CASES = [
    ("W291", "x = 1  \ny = 2\n", "x = 1\ny = 2\n", 1, 6),
    ("W293", "x = 1\n   \ny = 2\n", "x = 1\n\ny = 2\n", 2, 1),
    ("E501", "x = '" + "a" * 90 + "'\n", "x = 1\n", 1, 80),
    ("W191", "if x:\n\ty = 1\n", "if x:\n    y = 1\n", 2, 1),
    ("E101", "if x:\n  \ty = 1\n", "if x:\n    y = 1\n", 2, 1),
    ("E111", "if x:\n   y = 1\n", "if x:\n    y = 1\n", 2, 1),
    ("E231", "f(a,b)\n", "f(a, b)\n", 1, 4),
    ("E203", "f(a , b)\n", "f(a, b)\n", 1, 4),
    ("E221", "x  = 1\n", "x = 1\n", 1, 2),
    ("E701", "if x: y = 1\n", "if x:\n    y = 1\n", 1, 5),
    ("E303", "x = 1\n\n\n\ny = 2\n", "x = 1\n\n\ny = 2\n", 4, 1),
    ("W292", "x = 1\ny = 2", "x = 1\ny = 2\n", 2, 5),
]
