"""Errors of the engine."""


class EngineError(Exception):
    pass


class UnknownIndex(EngineError):
    pass


class StaleIndex(EngineError):
    pass


class CommitConflict(EngineError):
    pass


class BadVector(EngineError):
    pass


class BadParameter(EngineError):
    pass


class CorruptContainer(EngineError):
    pass


class UnsupportedPattern(EngineError):
    pass
