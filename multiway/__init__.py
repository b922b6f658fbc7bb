"""Spark-native multiway (tensor) analytics: sketch to Tucker form, then decompose the compact form."""

__version__ = "0.1.0"
