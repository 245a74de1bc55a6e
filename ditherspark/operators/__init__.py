"""Transforms, quantizers, codecs, gradient oracles and descent runners."""
