"""querymarks.sources"""
