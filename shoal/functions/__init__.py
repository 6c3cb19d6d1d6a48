"""Scalar expressions shared by graph builders and algorithms; every one stays in generated JVM code."""
