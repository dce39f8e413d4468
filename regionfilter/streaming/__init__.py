"""Filters on streams: probing, windowed rates, drift, incremental builds."""
