"""The experiments; importing a module registers its queries."""

from . import corpus, events, experiments, graph, text_students, theory  # noqa: F401
from .registry import ORACLES as ALL_ORACLES  # noqa: F401
from .registry import QUERIES as ALL_QUERIES  # noqa: F401
