"""querymarks.plans"""
