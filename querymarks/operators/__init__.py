"""querymarks.operators"""
