"""Settings shared by queries and their SQL twins."""

TAU, KEEP_TAU, DRAW_TAU = 0.5, 0.6, 0.5
N_EVAL, N_DRAW, N_TRAIN, SHOTS = 300, 500, 6000, 4
#: Queries drawn of each shape for training, tuning and evaluation together (all of a shape that has fewer), and how they are shared out.
DRAWN_PER_SHAPE, SHARES = 680, {"train": 0.8, "tune": 0.1, "eval": 0.1}
WIDTH, BI_BUCKETS, CROSS_BUCKETS = 768, 4096, 1 << 15
#: Kinds of errors that no negative example for training has.
HELD_KINDS = ("add_statement", "count_or_list")
MARGIN = 0.5
BINS = 20
#: Fixed weights of the document-quality scorer, for which SQL gives the same numbers: bias, distinct ratio, punctuation density, upper-case ratio, log tokens.
QUALITY_WEIGHTS = (-3.0, 7.0, -14.0, -1.0, 0.3)
#: Stand-in systems: share of wrong translations, kinds of errors in equal parts, whether they reason by themselves. These are inputs.
SYSTEMS = {
    "small_open": (0.39, ["add_statement", "variable_recursion", "invert_relation", "swap_entities"], False),
    "frontier_a": (0.12, ["invert_relation", "flatten_statement", "swap_entities"], False),
    "reasoning": (0.06, ["variable_recursion", "flatten_statement"], True),
    "frontier_b": (0.03, ["invert_relation"], False),
    "human_reference": (0.40, ["invert_relation", "change_literal", "drop_condition", "swap_entities"], False),
}
ALIAS_SHARE, BAD_GRAMMAR_SHARE = 0.05, 0.5
