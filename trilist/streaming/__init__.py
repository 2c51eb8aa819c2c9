"""trilist.streaming"""
