"""Typed errors; all are raised on the driver before a job starts."""


class PanelError(ValueError):
    """A panel, group map or parameter that can't be used."""


class ProfileError(ValueError):
    """A profile with unknown keys or impossible values."""


class EngineUnavailable(RuntimeError):
    """The engine asked for doesn't exist here. There is no silent fallback."""


def choose(engine: str, known: dict):
    if engine not in known:
        raise EngineUnavailable(f"engine {engine!r}; known: {', '.join(known)}")
    return known[engine]
