"""Errors of the provenance engine."""


class UnsupportedForProvenance(NotImplementedError):
    """A plan node or expression that no rule covers; never passed over in silence."""


class UnsupportedForBaseline(NotImplementedError):
    """A query outside what a comparison baseline accepts."""


class NonUniqueTokens(ValueError):
    """Two rows of a base table would share a token."""


class ProvenanceTooLarge(MemoryError):
    """A text annotation would pass the configured size."""
