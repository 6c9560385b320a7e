"""querymarks.functions"""
