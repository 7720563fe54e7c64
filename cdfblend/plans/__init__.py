"""Query plans: the methods, the workloads and the surrounding operators."""


def load():
    """The registry with all queries of the library."""
    from .. import registry
    from . import methods, surrounding, workloads  # noqa: F401

    return registry
