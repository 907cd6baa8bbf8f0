"""Part of the ctxrelease engine."""
