"""Training-data operators. Nothing outside this folder (but the guarded entry points) imports it."""
