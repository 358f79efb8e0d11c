class SchemaMismatch(ValueError):
    """Columns of an input are missing or have another type."""


class Infeasible(ValueError):
    """A sample does not fit the token capacity, or the capacity does not fit the padding multiple."""


class Unsupported(NotImplementedError):
    """Described by the method, but not evaluated there and not modelled here."""
