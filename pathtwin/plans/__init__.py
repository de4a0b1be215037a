"""Plan helpers: lineage cuts and iterative fixpoints."""
from pathtwin.plans.components import connected_components
from pathtwin.plans.lineage import cut, drop, scope, settled

__all__ = ["connected_components", "cut", "drop", "scope", "settled"]
