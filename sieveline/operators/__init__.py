"""Semantic and auxiliary operators as lazy DataFrame functions."""

from .auxiliary import Peripheral, Side, gather, header_lineage, split_delimiter, split_tokens, unnest, unnest_fields  # noqa: F401
from .numbering import largest_group, numbered  # noqa: F401
from .pairs import all_words_pairs, combined, components, cosine_pairs, equijoin, hashed_vectors, keyed_pairs, likely_pairs, map_search_filter, normalized_pairs, resolve, resolve_jointly, similar, text_vector, tune_threshold  # noqa: F401
from .semantic import fold, glean, sem_filter, sem_map, sem_parallel_map, sem_rank, sem_reduce, sem_sort, tree_reduce, validate_retry  # noqa: F401
