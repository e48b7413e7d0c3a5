"""Profiles: TOML, versioned, unknown keys rejected; hydrated with overrides; archived with checksums before a run."""

from __future__ import annotations

import hashlib
import json
import tomllib
import zipfile
from pathlib import Path

from markerpanel.errors import ProfileError
from markerpanel.functions.kernels import Beta, Fixed, Prior

VERSION = 1
DEFAULTS = {"schema": VERSION, "min_depth": 1, "alpha": 0.05, "tau_post": 0.9, "tau_bf": 10.0, "test": "yates", "correction": "bonferroni", "w": 0.5, "pi": 0.01, "shapes": [1.0] * 6, "linked": {"family": "fixed", "q": 0.9}, "null": {"family": "fixed", "q": 0.5}}
FAMILIES = {"fixed": ("q",), "beta": ("a", "b")}


def family(spec: dict) -> Fixed | Beta:
    """Tagged union: the family's name decides which keys are needed; others are rejected."""
    keys = FAMILIES.get(spec.get("family"))
    if keys is None or set(spec) != {"family", *keys}:
        raise ProfileError(f"prevalence family {spec!r}")
    return (Fixed if spec["family"] == "fixed" else Beta)(**{k: float(spec[k]) for k in keys})


def hydrate(profile: dict, **overrides) -> dict:
    """Defaults, then the profile, then overrides; checked."""
    given = profile | overrides
    if unknown := set(given) - set(DEFAULTS):
        raise ProfileError(f"unknown keys: {', '.join(sorted(unknown))}")
    out = DEFAULTS | given
    if out["schema"] != VERSION:
        raise ProfileError(f"schema {out['schema']}, expected {VERSION}")
    if out["min_depth"] < 1 or not 0 < out["alpha"] < 1 or not 0 < out["tau_post"] < 1 or out["tau_bf"] <= 0:
        raise ProfileError("a threshold is out of range")
    prior(out)
    return out


def prior(p: dict) -> Prior:
    return Prior(family(p["linked"]), family(p["null"]), p["w"], p["pi"], tuple(map(float, p["shapes"])))


def load(path: str, **overrides) -> dict:
    try:
        return hydrate(tomllib.loads(Path(path).read_text()), **overrides)
    except tomllib.TOMLDecodeError as x:
        raise ProfileError(str(x)) from x


def write_archive(path: str, profile: dict, sources: list[str] = ()) -> dict[str, str]:
    """ZIP of the hydrated profile and the given source files with SHA-256 sums; returns the sums."""
    files = {"profile.json": json.dumps(profile, indent=1, sort_keys=True).encode()} | {f"source/{Path(s).name}": Path(s).read_bytes() for s in sources}
    sums = {n: hashlib.sha256(b).hexdigest() for n, b in files.items()}
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for n, b in files.items():
            z.writestr(n, b)
        z.writestr("SHA256SUMS", "".join(f"{h}  {n}\n" for n, h in sums.items()))
    return sums
