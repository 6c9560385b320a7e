"""querymarks.streaming"""
