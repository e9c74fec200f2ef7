"""Pages labelled by hand: blocks whose text begins with ``MARK`` are content, all others boilerplate.

They show the classifier of ``html_text`` what a corpus may lack: pages without
landmarks, reader comments, forms, notices, adverts inside articles, tables.
"""

from __future__ import annotations

MARK = "\u00a4"

_LINKS = "<ul><li><a href=/>Home</a></li><li><a href=/n>News</a></li><li><a href=/s>Sport</a></li><li><a href=/c>Contact us</a></li></ul>"
_STORY = (
    "<p>¤The council met on Tuesday evening to talk about the old bridge, which has been closed since the flood of last spring.</p>"
    "<p>¤Engineers said that two of its pillars have moved, and that repairs would take at least until the autumn.</p>"
    "<p>¤No vote was taken.</p>"
    "<p>¤Farmers on the far side, who now drive an hour to reach the market, asked for a ferry in the meantime; the mayor promised an answer within a week.</p>"
)
_RECIPE = (
    "<h2>¤Ingredients</h2><ul><li>¤two cups of flour</li><li>¤a pinch of salt</li><li>¤water</li></ul><h2>¤Method</h2>"
    "<p>¤Mix the flour with the salt, then add the water slowly while stirring until the dough no longer sticks to the bowl.</p>"
    "<p>¤Leave it to rest for an hour under a cloth. Roll it out thinly and bake it on a hot stone for four minutes on each side.</p>"
)

PAGES = (
    # Landmarks and everything around.
    f"<body><header><div>The Daily Valley</div><nav>{_LINKS}</nav></header><article><h1>¤Bridge stays closed</h1>{_STORY}</article><aside><h3>Most read</h3><ul><li><a href=1>Flood damage is worse than thought</a></li><li><a href=2>Ten ways to save on heating</a></li></ul></aside><footer><p>&copy; 2024 The Daily Valley. All rights reserved.</p><a href=/p>Privacy policy</a></footer></body>",
    # Class names only.
    f"<body><div id=header><div class=logo>Valley Post</div><div class=menu>{_LINKS}</div></div><div class=content><h1>¤Bridge stays closed</h1>{_STORY}</div><div class=sidebar><h4>Weather</h4><p>Sunny, 21 degrees</p><h4>Related</h4><a href=1>More about the flood</a></div><div id=footer>Terms of use | Imprint</div></body>",
    # Neither landmarks nor names.
    f"<body><div>{_LINKS}</div><div><div><h1>¤Bridge stays closed</h1>{_STORY}</div></div><div><a href=1>Read next: the flood, one year on</a></div><div>Copyright 2024, Valley Post. All rights reserved.</div></body>",
    # Reader comments after the article and inside it.
    f"<article><h1>¤Bridge stays closed</h1>{_STORY}<section id=comments><h3>3 comments</h3><div class=comment><p>I have crossed that bridge every day for thirty years and nobody ever asked me what I think of it.</p></div><div class=comment><p>Finally somebody says it! The mayor should be ashamed of the whole affair, in my opinion.</p></div><form><label>Your comment</label><button>Send</button></form></section></article>",
    f"<main><h1>¤Flat bread</h1><p class=byline>By the kitchen team</p>{_RECIPE}</main><ol class=commentlist><li><p>Made this yesterday and my whole family loved it, thank you so much for sharing the recipe with us!</p></li><li><p>Mine came out a bit dry. How much water did you use? Please reply when you find the time.</p></li></ol>",
    # Notices, adverts and sign-ups, some in the middle of the text.
    f"<body><div class=cookie-notice><p>We use cookies to give you the best experience. By going on you accept our privacy policy.</p><a href=#>Accept</a></div><main><h1>¤Bridge stays closed</h1><p>¤A long look at a small valley and the one road that leads out of it.</p><div class=ad><p>Advertisement</p><p>Buy one, get one free: only this week at your local store.</p></div>{_STORY}<div class=newsletter><p>Sign up for our newsletter and never miss a story again.</p><form><label>E-mail</label></form></div></main></body>",
    # A header with the title inside the article, sharing links and a box aside.
    f"<article><header><h1>¤Flat bread</h1></header><div class=share><a href=1>Share</a> <a href=2>Tweet</a></div>{_RECIPE}<aside><p>Sponsored: knives that stay sharp, now at half price</p></aside><blockquote>¤Bread is older than the oven, as my grandmother used to say whenever ours was broken.</blockquote></article><footer><p>Published by the Valley Cooking Club. Reprints need our written consent.</p></footer>",
    # A table as the layout.
    f"<table><tr><td>{_LINKS}</td><td><h1>¤Bridge stays closed</h1>{_STORY}</td><td><p>Buy now! Best prices!</p><p><a href=1>Click here</a></p></td></tr><tr><td>Contact | Imprint</td></tr></table>",
    # A list of posts' teasers beside one post; breadcrumbs; pages.
    f"<body><ul class=breadcrumb><li><a href=1>Home</a></li><li><a href=2>Food</a></li></ul><div class=post><h1>¤Flat bread</h1>{_RECIPE}</div><div class=pagination><a href=1>1</a> <a href=2>2</a> <a href=3>Next</a></div><div class=teaser><h3><a href=5>How to make butter</a></h3><p>It takes only cream, a jar and some patience, as you will see in our little guide ...</p></div></body>",
    # Only a text, and only a menu.
    "<p>¤Short note.</p><p>¤The office stays closed on Monday because of the holiday, and opens again on Tuesday at nine.</p>",
    f"<nav>{_LINKS}</nav>",
    # Headings and data inside the text.
    "<body><nav><a href=/>Start</a> <a href=/x>Index</a></nav><article><h1>¤Rivers</h1><p>¤The three longest rivers of the region are listed below.</p><table><tr><th>¤River</th><th>¤Length</th></tr><tr><td>¤Arn</td><td>¤120 km</td></tr><tr><td>¤Belle</td><td>¤96 km</td></tr></table><h2>¤Sources</h2><pre>¤measured 1998 to 2004</pre></article><footer>About this site</footer></body>",
)
