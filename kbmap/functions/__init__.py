"""Part of the exchange engine."""
