"""Samplers, resamplers, maintenance of resamples, and joins and windows that users of them need."""
