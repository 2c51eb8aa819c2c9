"""trilist.operators"""
