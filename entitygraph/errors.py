"""Named errors."""


class EntityGraphError(Exception):
    pass


class SchemaError(EntityGraphError):
    pass


class DuplicateIdError(EntityGraphError):
    pass


class ClosureDidNotConverge(EntityGraphError):
    pass


class LocalCapExceeded(EntityGraphError):
    pass
